"""SentencePiece models run by the ``tokenizers`` library.

The model's protobuf is read field by field; normaliser, metaspace marker, BPE merges or unigram
scores and byte fallback are rebuilt as a ``tokenizers`` pipeline. Every distinct piece that the
rebuilt pipeline encodes is also encoded by the ``sentencepiece`` library; where the two differ
the latter's ids stand and the row says so.
"""

from __future__ import annotations

import hashlib
import os
import re
import struct
import sys
from array import array
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from . import tokens
from .lean import lean, trim

MARK = "▁"
#: Fixed values of the model format: piece types and model types.
NORMAL, UNKNOWN, CONTROL, USER_DEFINED, UNUSED, BYTE = 1, 2, 3, 4, 5, 6
UNIGRAM, BPE = 1, 2
#: Distinct words remembered by one worker, in each of two generations.
MEMO_PIECES = 300_000
#: Threads of the library in one worker; the machine's cores are shared by many workers, and each thread keeps memory of its own.
THREADS = 2
#: Bytes of text that are Python objects at once.
SLICE_BYTES = 1 << 18
#: Words encoded at once; the library's result objects take some kilobytes a word.
ENCODE_WORDS = 4096


def _fields(raw: bytes) -> Iterator[tuple[int, object]]:
    """(field number, value) of one protobuf message; length-delimited values as bytes."""

    def varint(at: int) -> tuple[int, int]:
        value = shift = 0
        while True:
            byte = raw[at]
            value |= (byte & 127) << shift
            at, shift = at + 1, shift + 7
            if byte < 128:
                return value, at

    at = 0
    while at < len(raw):
        key, at = varint(at)
        number, wire = key >> 3, key & 7
        if wire == 0:
            value, at = varint(at)
        elif wire == 2:
            n, at = varint(at)
            value, at = raw[at : at + n], at + n
        elif wire == 5:
            value, at = raw[at : at + 4], at + 4
        elif wire == 1:
            value, at = raw[at : at + 8], at + 8
        else:
            raise ValueError(f"wire type {wire} in a model file")
        yield number, value


@dataclass
class Model:
    pieces: list[tuple[str, float, int]] = field(default_factory=list)
    kind: int = UNIGRAM
    byte_fallback: bool = False
    charsmap: bytes = b""
    dummy_prefix: bool = True
    squeeze: bool = True
    escape: bool = True

    @property
    def unk(self) -> int:
        return next(i for i, p in enumerate(self.pieces) if p[2] == UNKNOWN)


def parse(raw: bytes) -> Model:
    m = Model()
    for number, value in _fields(raw):
        if number == 1:
            text, score, kind = "", 0.0, NORMAL
            for n, v in _fields(value):
                if n == 1:
                    text = v.decode()
                elif n == 2:
                    (score,) = struct.unpack("<f", v)
                elif n == 3:
                    kind = v
            m.pieces.append((text, score, kind))
        elif number == 2:
            for n, v in _fields(value):
                if n == 3:
                    m.kind = v
                elif n == 35:
                    m.byte_fallback = bool(v)
        elif number == 3:
            for n, v in _fields(value):
                if n == 2:
                    m.charsmap = v
                elif n == 3:
                    m.dummy_prefix = bool(v)
                elif n == 4:
                    m.squeeze = bool(v)
                elif n == 5:
                    m.escape = bool(v)
    return m


def rebuild(m: Model):
    """A ``tokenizers`` pipeline of the model; white space is escaped by the normaliser."""
    from tokenizers import Regex, Tokenizer, decoders, models, normalizers

    vocab = {p[0]: i for i, p in enumerate(m.pieces)}
    if m.kind == BPE:
        merges = []
        for text, score, kind in m.pieces:
            if kind in (NORMAL, USER_DEFINED):
                cuts = [(text[:k], text[k:]) for k in range(1, len(text)) if text[:k] in vocab and text[k:] in vocab]
                merges += [(-score, vocab[text], vocab[a], vocab[b], a, b) for a, b in cuts]
        merges.sort()
        model = models.BPE(vocab=vocab, merges=[x[-2:] for x in merges], unk_token=m.pieces[m.unk][0], fuse_unk=True, byte_fallback=m.byte_fallback)
    else:
        model = models.Unigram([(p[0], p[1]) for p in m.pieces], unk_id=m.unk, byte_fallback=m.byte_fallback)
    t = Tokenizer(model)
    steps = []
    if m.charsmap:
        steps.append(normalizers.Precompiled(m.charsmap))
    if m.squeeze:
        steps += [normalizers.Replace(Regex("^ +| +$"), ""), normalizers.Replace(Regex(" {2,}"), " ")]
    if m.dummy_prefix:
        steps.append(normalizers.Prepend(" "))
    if m.escape:
        steps.append(normalizers.Replace(" ", MARK))
    if steps:
        t.normalizer = normalizers.Sequence(steps)
    t.decoder = decoders.Sequence([decoders.Replace(MARK, " "), decoders.ByteFallback(), decoders.Fuse()])
    return t


def splittable(m: Model) -> bool:
    """Words may be encoded one by one if no piece holds the marker after another character and nothing else rewrites or joins text."""
    return not (m.charsmap or m.squeeze) and m.dummy_prefix and m.escape and not any(re.search(f"[^{MARK}]{MARK}", p[0]) for p in m.pieces) and not any(p[2] == USER_DEFINED for p in m.pieces)


class Coder:
    """Encodes and decodes texts; remembers the pieces of words in two generations of bounded size."""

    def __init__(self, path: str, memo_pieces: int = MEMO_PIECES):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "true")
        os.environ.setdefault("RAYON_NUM_THREADS", str(THREADS))
        import sentencepiece

        self.memo_pieces = memo_pieces

        with open(path, "rb") as f:
            self.model = parse(f.read())
        self.pipeline = rebuild(self.model)
        self.library = sentencepiece.SentencePieceProcessor(model_file=path)
        self.split = splittable(self.model)
        self.width = np.dtype("<u2" if len(self.model.pieces) <= 1 << 16 else "<u4")
        self.pack = (lambda ids, kind="H" if self.width.itemsize == 2 else "I": array(kind, ids).tobytes()) if sys.byteorder == "little" else (lambda ids: np.asarray(ids, dtype=self.width).tobytes())
        self.memo: dict[str, bytes] = {}
        self.older: dict[str, bytes] = {}
        self.unlike: set[str] = set()
        self.plain = [self._surface(p) for p in self.model.pieces]
        self.bare: dict[str, bytes] = {}
        self.joined = {p[0][k : k + 2] for p in self.model.pieces if p[2] != BYTE for k in range(len(p[0]) - 1)}
        self.newline: bytes | None = None
        byte = next((i for i, p in enumerate(self.model.pieces) if p[2] == BYTE and p[0] == "<0x0A>"), None)
        if self.split and byte is not None and self.model.byte_fallback and not any("\n" in p[0] for p in self.model.pieces):
            self.newline = self.pack([byte])

    def _surface(self, piece: tuple[str, float, int]) -> bytes:
        text, _, kind = piece
        if kind == BYTE:
            return bytes([int(text[3:5], 16)])
        if kind == CONTROL:
            return b""
        if kind == UNKNOWN:
            return " ⁇ ".encode()
        return text.replace(MARK, " ").encode()

    def _encode(self, texts: list[str]) -> list[tuple[bytes, bool]]:
        """Ids of whole texts by the rebuilt pipeline, held against the library's."""
        own = [e.ids for e in self.pipeline.encode_batch_fast(texts, add_special_tokens=False)]
        theirs = self.library.encode(texts, num_threads=1)
        if own != theirs:
            return [(self.pack(b), a == b) for a, b in zip(own, theirs)]
        return [(self.pack(b), True) for b in theirs]

    def _keep(self, memo: dict[str, bytes], words: list[str], skip: int = 0, lead: str = "") -> None:
        for at in range(0, len(words), ENCODE_WORDS):
            some = words[at : at + ENCODE_WORDS]
            for w, (ids, same) in zip(some, self._encode([lead + w for w in some])):
                memo[w] = ids[skip:]
                if not same:
                    self.unlike.add(w)

    def batch(self, texts: list[str]) -> Iterator[tuple[bytes, bool]]:
        """(ids as little-endian bytes, whether both libraries agreed) per text."""
        if not self.split:
            yield from self._encode(texts)
            return
        if len(self.memo) > self.memo_pieces:
            self.older, self.memo = self.memo, {}
        if len(self.bare) > self.memo_pieces:
            self.bare = {}
        lines = [self._parts(t) for t in texts]
        new: set[str] = set()
        heads: set[str] = set()
        for text in lines:
            for k, line in enumerate(text):
                new.update(line[1:] if k else line)
                if k:
                    heads.add(line[0])
        self._learn(new, heads)
        get = self.memo.__getitem__
        for t, text in zip(texts, lines):
            if not t:
                yield b"", True
                continue
            got: list[bytes] = []
            for k, line in enumerate(text):
                if k:
                    got.append(self.newline)
                    got.append(self.bare[line[0]])
                    got += map(get, line[1:])
                else:
                    got += map(get, line)
            yield b"".join(got), not self.unlike or not any(w in self.unlike for line in text for w in line)

    def _parts(self, text: str) -> list[list[str]]:
        """Lines of words; a newline is its own byte piece, which no other piece crosses."""
        if MARK in text:
            return [[text]]
        lines = text.split("\n") if self.newline else [text]
        return [re.split("(?<=[^ ]) ", x) if "  " in x or x[:1] == " " else x.split(" ") for x in lines]

    def _learn(self, words: set[str], heads: set[str]) -> None:
        """Words carry the marker in front, heads (after a newline) do not. A last character that no piece joins to the one before it is encoded by itself."""
        words.difference_update(self.memo)
        for p in [p for p in words if p in self.older]:
            self.memo[p] = self.older[p]
            words.discard(p)
        if "" in words:  # what stands after a closing space: the marker alone
            self.memo[""] = self.pack([self.library.piece_to_id(MARK)])
            words.discard("")
        ends = [p for p in words if self.newline and p[-1:] in ".,;:!?" and len(p) > 1 and p[-2:].replace(" ", MARK) not in self.joined]
        base = words.difference(ends)
        base.update(p[:-1] for p in ends if p[:-1] not in self.memo)
        base_list = list(base)
        self._keep(self.memo, base_list)
        if self.newline:
            heads.update(p[-1] for p in ends)
            head_list = [p for p in heads if p not in self.bare]
            self._keep(self.bare, head_list, 2 * self.width.itemsize, "\n")
            for p in ends:
                self.memo[p] = self.memo[p[:-1]] + self.bare[p[-1]]
                if self.unlike and (p[:-1] in self.unlike or p[-1] in self.unlike):
                    self.unlike.add(p)

    def decode(self, ids: bytes) -> str:
        """The text of ids: byte pieces joined as UTF-8, the leading marker dropped."""
        table = self.plain
        raw = b"".join([table[i] for i in np.frombuffer(ids, dtype=self.width).tolist()])
        text = raw.decode("utf-8", "replace")
        return text[1:] if self.model.dummy_prefix and text[:1] == " " else text


def encode(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", keep: bool = False, memo_pieces: int = MEMO_PIECES) -> DataFrame:
    """n_tokens, token_ids (little-endian uint16, uint32 for larger vocabularies), ids_sha256, parity (both libraries gave the same ids) and round_trip (decoding gives the text back).

    A null text encodes like the empty text, to no tokens. Repeated rows each give a row, null ids
    stay; further columns are dropped unless ``keep``. An empty table gives an empty result.
    ``memo_pieces`` trades a worker's memory for time; results don't depend on it.
    """
    own = ["n_tokens", "token_ids", "ids_sha256", "parity", "round_trip"]
    others = [c for c in docs.columns if keep and c not in {id_col, *own}]
    source = docs.select(id_col, *others, F.col(text_col).alias("__text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = Coder(path, memo_pieces)
        for b in batches:
            trim()
            row = 0
            column = b.column(b.schema.get_field_index("__text"))
            for some in tokens.slices(column, SLICE_BYTES):
                out = list(coder.batch(some))
                ids = [x[0] for x in out]
                at = slice(row, row + len(some))
                yield pa.RecordBatch.from_arrays(
                    [b.column(k).slice(row, len(some)) for k in range(b.num_columns - 1)]
                    + [
                        pa.array([len(x) // coder.width.itemsize for x in ids], pa.int64()), pa.array(ids, pa.binary()), pa.array([hashlib.sha256(x).hexdigest() for x in ids]),
                        pa.array([x[1] for x in out], pa.bool_()), pa.array([coder.decode(i) == t for i, t in zip(ids, some)], pa.bool_()),
                    ],
                    names=[id_col, *others, *own],
                )
                row = at.stop

    kept = "".join(f"`{c}` {docs.schema[c].dataType.simpleString()}, " for c in [id_col, *others])
    return source.mapInArrow(lean(run), kept + "n_tokens long, token_ids binary, ids_sha256 string, parity boolean, round_trip boolean")


def decode(rows: DataFrame, path: str, id_col: str = "doc_id", ids_col: str = "token_ids") -> DataFrame:
    """Texts of encoded rows; null ids decode to the empty text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = Coder(path)
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([coder.decode(x or b"") for x in b.column(1).to_pylist()], pa.string())], names=[id_col, "text"])

    return rows.select(id_col, ids_col).mapInArrow(lean(run), f"`{id_col}` {rows.schema[id_col].dataType.simpleString()}, text string")
