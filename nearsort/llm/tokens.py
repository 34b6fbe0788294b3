"""Byte-level BPE token counts: lengths only, from batches balanced by bytes.

A text is split at safe boundaries, encoded by the ``tokenizers`` library in batches, and each
distinct piece's result is remembered in the worker up to a fixed number of pieces.
"""

from __future__ import annotations

import os
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .lean import lean
from .textscan import text_buffers

#: A single space between two characters that are no white space always begins a new pre-token.
_BOUNDARY = re.compile(r"(?<=\S) (?=\S)")
_UNSAFE = re.compile(r"[ \n]\s|\s[ \n]")
#: Distinct pieces remembered by one worker; beyond it the memory is cleared.
MEMO_PIECES = 500_000
#: Characters given to the library at once.
BATCH_CHARS = 1 << 20
_tokenizers: dict[str, object] = {}


def load(path: str):
    """The tokenizer of a .json file, once per worker, with truncation and padding off."""
    if path not in _tokenizers:
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        t = Tokenizer.from_file(path)
        t.no_truncation()
        t.no_padding()
        _tokenizers[path] = t
    return _tokenizers[path]


def safe_split(path: str) -> bool:
    """Whether texts may be split before single spaces: a byte-level pre-tokenizer that adds none, no normaliser, no added token with a space."""
    import json

    raw = load(path).to_str()
    spec = json.loads(raw)
    pre = spec.get("pre_tokenizer") or {}
    plain = pre.get("type") == "ByteLevel" and not pre.get("add_prefix_space") and pre.get("use_regex", True)
    tokens = spec.get("added_tokens") or []
    return bool(plain and spec.get("normalizer") is None and not any(t["lstrip"] or t["rstrip"] or t["single_word"] or re.search(r"\s", t["content"]) for t in tokens))


def split(text: str) -> list[list[str]]:
    """Lines, each as parts: the line's encoding is its first part's and, after a space each, the others'; between lines stands one newline token.

    Only used where a break sits between two characters that are no white space; otherwise
    the text is one line, split before its safe single spaces.
    """
    if _UNSAFE.search(text):
        return [_BOUNDARY.split(text)]
    return [x.split(" ") for x in text.split("\n")]


class Encoder:
    """Encodings of many texts through a bounded memory of pieces.

    ``of`` turns ids into what is kept; kept values are joined by ``+`` (numbers or bytes).
    """

    def __init__(self, path: str, of):
        self.tokenizer, self.of, self.safe = load(path), of, safe_split(path)
        self.memo: dict[str, object] = {}
        self.older: dict[str, object] = {}
        self.heads: dict[str, object] = {}
        self.special = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.newline = self._encode(["\n"])[0]

    def _encode(self, texts: list[str]) -> list:
        out: list = []
        for some in by_bytes(texts):
            out += [self.of(e.ids) for e in self.tokenizer.encode_batch_fast(some, add_special_tokens=False)]
        return out

    def _learn(self, memo: dict, parts: set[str], lead: str) -> None:
        """After a letter or digit, a closing full stop or comma is a pre-token of its own."""
        new = parts.difference(memo)
        if not self.safe:
            new_list = list(new)
            memo.update(zip(new_list, self._encode(new_list)))
            return
        if lead and self.older:
            for p in [p for p in new if p in self.older]:
                memo[p] = self.older[p]
                new.discard(p)
        ends = [p for p in new if p[-1:] in (".", ",") and p[-2:-1].isascii() and p[-2:-1].isalnum()]
        base = new.difference(ends)
        base.update(p[:-1] for p in ends if p[:-1] not in memo)
        base_list = list(base)
        memo.update(zip(base_list, self._encode([lead + p for p in base_list])))
        if ends:
            mark = dict(zip(".,", self._encode([".", ","])))
            for p in ends:
                memo[p] = memo[p[:-1]] + mark[p[-1]]

    def batch(self, texts: list[str]) -> Iterator[list]:
        """Per text, what its consecutive pieces give."""
        if len(self.memo) > MEMO_PIECES:
            self.older, self.memo = self.memo, {}
        if len(self.heads) > MEMO_PIECES:
            self.heads = {}
        lines = [split(t) if self.safe and not any(s in t for s in self.special) else [[t]] for t in texts]
        heads: set[str] = set()
        rest: set[str] = set()
        for text in lines:
            for line in text:
                heads.add(line[0])
                rest.update(line[1:])
        self._learn(self.heads, heads, "")
        self._learn(self.memo, rest, " ")
        get = self.memo.__getitem__
        for text in lines:
            out: list = []
            for k, line in enumerate(text):
                if k:
                    out.append(self.newline)
                out.append(self.heads[line[0]])
                out += map(get, line[1:])
            yield out


def by_bytes(texts: list[str], limit: int = BATCH_CHARS) -> Iterator[list[str]]:
    """Consecutive texts, about ``limit`` characters at a time."""
    some, size = [], 0
    for t in texts:
        some.append(t)
        size += len(t)
        if size >= limit:
            yield some
            some, size = [], 0
    if some:
        yield some


def slices(column: pa.Array, limit: int = BATCH_CHARS) -> Iterator[list[str]]:
    """The texts of a column (null: empty), about ``limit`` bytes at a time, so that only these are Python objects."""
    _, offsets = text_buffers(column)
    row, n = 0, len(offsets) - 1
    while row < n:
        to = min(n, max(row + 1, int(np.searchsorted(offsets, offsets[row] + limit, side="right")) - 1))
        yield [x or "" for x in column.slice(row, to - row).to_pylist()]
        row = to


def token_counts(docs: DataFrame, path: str, limit: int = 1024, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """n_bytes, n_tokens and over_limit of every text.

    A null text counts as empty (0 bytes, 0 tokens); repeated rows each give a row; ids may be
    null; further columns are ignored. An empty table gives an empty result.
    """
    kind = docs.schema[id_col].dataType

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = Encoder(path, len)
        for b in batches:
            column = b.column("t")
            n_tokens: list[int] = []
            n_bytes: list[int] = []
            for some in slices(column):
                n_tokens += [sum(x) for x in encoder.batch(some)]
                n_bytes += [len(t.encode()) for t in some]
            yield pa.RecordBatch.from_arrays(
                [b.column("i"), pa.array(n_bytes, pa.int64()), pa.array(n_tokens, pa.int64()), pa.array([n > limit for n in n_tokens], pa.bool_())], names=[id_col, "n_bytes", "n_tokens", "over_limit"]
            )

    schema = f"`{id_col}` {kind.simpleString()}, n_bytes long, n_tokens long, over_limit boolean"
    return docs.select(F.col(id_col).alias("i"), F.col(text_col).alias("t")).mapInArrow(lean(run), schema)
