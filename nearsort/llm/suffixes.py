"""Substring removal by suffix arrays built in shards with external induced sorting.

Candidate regions come keyed by anchor. A shard lays them end to end in a file, an anchor's shared gram
being one symbol of its own, sorts the suffixes with their common-prefix lengths on disk, and marks each
window that agrees with a neighbour in suffix order over its whole length. One key may hold any number of regions:
they go to the file as they arrive.
"""

from __future__ import annotations

import hashlib
import os
import tempfile
from array import array
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from . import recurrence as rec, textscan as ts
from .induced import disk_array, sort_suffixes
from .lean import lean

#: Bytes of a removed string, of its anchor, of a probe. With these lengths every string of 240 bytes holds a probe; 51 words are longer in 99 of 100 cases.
SPAN, GRAM, PROBE = 400, 288, 128
#: Words of a repeated passage ("over 50"), of its anchor.
PASSAGE, PASSAGE_GRAM = 51, 36
#: Symbols sorted at once unless one key has more.
SHARD_SYMBOLS = 1 << 19
_BLOCK = 1 << 16


class Shard:
    """Regions laid end to end in a file as 32-bit symbols: 0 ends a region, bytes are 1 to 256, grams follow.

    kind "bytes": a region's windows start at its first symbols and have ``window`` symbols.
    kind "words": a window starts with a blank, so never inside a word, and has ``window`` words, the anchor being one; its length in bytes is its own.
    """

    def __init__(self, kind: str, window: int):
        self.kind, self.window = kind, window
        self.folder = tempfile.TemporaryDirectory()
        self.file = open(os.path.join(self.folder.name, "text"), "wb")
        self.size, self.names = 0, {}
        self.bounds, self.windows = array("q", [0]), array("q")
        self.starts, self.lengths = array("q"), array("q")

    def add(self, left: bytes, gram: bytes, right: bytes, n: int) -> None:
        if self.kind == "words":
            left, right = b" " + left + b" " if left else b" ", right + b" " if right else b""
            start = np.flatnonzero(np.frombuffer(left, np.uint8) == 32)
            end = len(left) + 1 + np.concatenate(([0], np.flatnonzero(np.frombuffer(right, np.uint8) == 32) + 1))
            after = self.window - len(start)  # words behind the anchor in the region's first window
            n = len(end) - after
            self.starts.frombytes(start[:n].astype(np.int64).tobytes())
            self.lengths.frombytes((end[after : after + n] - start[:n]).astype(np.int64).tobytes())
        size = len(left) + len(right) + 2
        symbols = np.zeros(size, np.int32)
        symbols[: len(left)] = np.frombuffer(left, np.uint8)
        symbols[len(left)] = self.names.setdefault(gram, 256 + len(self.names))
        symbols[len(left) + 1 : -1] = np.frombuffer(right, np.uint8)
        symbols += 1
        symbols[-1] = 0
        symbols.tofile(self.file)
        self.size += size
        self.bounds.append(self.size)
        self.windows.append(n)

    def repeated(self) -> Iterator[np.ndarray]:
        """Per region, the numbers of windows that occur at another place of the shard too."""
        self.file.close()
        if not self.size:
            return
        text = np.asarray(np.memmap(self.file.name, dtype=np.int32, mode="r"))
        starts, lengths = (np.frombuffer(x, np.int64) for x in (self.starts, self.lengths))
        order, lcp = sort_suffixes(text, self.window if self.kind == "bytes" else int(lengths.max()), self.folder.name)
        shared = disk_array(self.folder.name, len(text), np.int32)
        for a in range(0, len(text), _BLOCK):
            here, after = lcp[a : a + _BLOCK], lcp[a + 1 : a + _BLOCK + 1]
            most = np.array(here)
            np.maximum(most[: len(after)], after, out=most[: len(after)])
            shared[order[a : a + _BLOCK]] = most
        used = 0
        for a, n in zip(self.bounds, self.windows):
            if self.kind == "words":
                yield np.flatnonzero(shared[a + starts[used : used + n]] >= lengths[used : used + n])
                used += n
            else:
                yield np.flatnonzero(shared[a : a + n] >= self.window)

    def close(self) -> None:
        self.file.close()
        self.folder.cleanup()


def _search(batches: Iterator[pa.RecordBatch], units: rec.Units, shard: int) -> Iterator[pa.RecordBatch]:
    """(id, th, at, a, b) of intervals of windows that recur."""
    names = [*rec.PLACE, "a", "b"]
    now, places, key = None, array("q"), None

    def flush() -> Iterator[pa.RecordBatch]:
        out: list[list[int]] = [[] for _ in names]
        for k, some in enumerate(now.repeated()):
            if not len(some):
                continue
            i, th, at, shift = places[4 * k : 4 * k + 4]
            for interval in zip(*rec.merged(some + shift, units.span)):
                for o, v in zip(out, (i, th, at, *interval)):
                    o.append(v)
            if len(out[0]) > 50_000:
                yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in out], names=names)
                out = [[] for _ in names]
        yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in out], names=names)
        now.close()

    for b in batches:
        for k, i, th, at, shift, left, g, right, n in zip(*(c.to_pylist() for c in b.columns)):
            if now is not None and k != key and now.size >= shard:
                yield from flush()
                now = None
            if now is None:
                now, places = Shard(units.kind, units.span - units.gram + 1), array("q")
            key = k
            now.add(left, g, right, n)
            places.extend((i, th, at, shift))
    if now is not None:
        yield from flush()


def intervals(prepared: DataFrame, span: int = SPAN, gram: int = GRAM, together: int = rec.TOGETHER, shard: int = SHARD_SYMBOLS, kind: str = "bytes", piece: int = rec.PIECE_BYTES, probe: int = 0) -> tuple[DataFrame, DataFrame]:
    """(id, th, a, b): intervals of bytes (or words) covered by runs of ``span`` that start anywhere else too; they may overlap. And the probes of recurrence.find()."""
    units = rec.Units(kind, span, gram, piece)
    members, groups, regions, probes = rec.find(prepared, units, together, probe)
    found = regions.mapInArrow(lean(lambda x: _search(x, units, shard)), "id long, th long, at long, a long, b long")
    return rec.whole_marks(members, groups, span, keep_first=False).unionByName(rec.part_marks(found)), probes


def _kept(text: bytes, a: np.ndarray, b: np.ndarray) -> tuple[bytes, int, int]:
    if not len(a):
        return text, 0, 0
    gone = ts.cover(len(text), a, b)
    spans = int(gone[0]) + int((gone[1:] & ~gone[:-1]).sum())
    return np.frombuffer(text, np.uint8)[~gone].tobytes(), int(gone.sum()), spans


def removed(text: bytes, a: np.ndarray, b: np.ndarray, n: int) -> tuple[int, int, int, str, int]:
    kept, gone, spans = _kept(text, a, b)
    return len(text), gone, spans, hashlib.sha256(kept).hexdigest(), n


def remove_substrings(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", span: int = SPAN, gram: int = GRAM, together: int = rec.TOGETHER, shard: int = SHARD_SYMBOLS, probe: int = PROBE, piece: int = rec.PIECE_BYTES) -> DataFrame:
    """n_bytes, n_removed, n_spans, kept_sha256 and n_repeated_probes of every document.

    A byte goes if a string of ``span`` bytes over it also starts anywhere else, in any document or its
    own; shorter texts lose nothing. n_repeated_probes counts the document's probes that are anywhere else too: strings of ``probe`` bytes
    at the anchors that windows of ``span - gram + probe`` bytes choose, so any repeated string of that length shows. It reports passages
    that are too short to go, and takes no part in what goes. A null text is empty. Null ids are documents like any other.
    Rows that repeat an id with the same text count as one document and each get its result. An empty
    table gives an empty result; further columns are ignored.
    """
    marks, probes = intervals(rec.prepare(docs, id_col, text_col), span, gram, together, shard, piece=piece, probe=probe)
    none = F.lit(None).cast("long")
    both = marks.withColumn("n", F.lit(0).cast("long")).unionByName(probes.select("id", "th", none.alias("a"), none.alias("b"), F.col("probes").alias("n")))
    return rec.apply(rec.named(docs, id_col, text_col), both, id_col, removed, "n_bytes long, n_removed long, n_spans long, kept_sha256 string, n_repeated_probes long")


def _without_words(text: bytes, a: np.ndarray, b: np.ndarray) -> bytes:
    """The text without the words of the intervals and the blanks that follow each."""
    if not len(a):
        return text
    data = np.frombuffer(text, np.uint8)
    start, _, _ = ts.words(data, np.asarray([0, len(data)]), ~ts.SPACE)
    gone, edge = ts.cover(len(start), a, b), np.append(start, len(text))
    return data[~ts.cover(len(text), edge[:-1][gone], edge[1:][gone])].tobytes()


def _cut(docs: DataFrame, id_col: str, text_col: str, marks: DataFrame, kept: Callable[[bytes, np.ndarray, np.ndarray], bytes]) -> DataFrame:
    others = [c for c in docs.columns if c != text_col]
    whole = F.struct(*(F.col(c).alias(f"c{k}") for k, c in enumerate(others)), F.col(text_col).isNull().alias("blank"))
    out = rec.apply(rec.named(docs, id_col, text_col, whole), marks, "original", lambda t, a, b, _: (kept(t, a, b).decode("utf-8", "ignore"),), "kept string")
    values = {c: F.col("original")[f"c{k}"] for k, c in enumerate(others)} | {text_col: F.when(~F.col("original.blank"), F.col("kept"))}
    return out.select(*(values[c].alias(c) for c in docs.columns))


def cut_texts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", span: int = SPAN, gram: int = GRAM) -> DataFrame:
    """``docs`` with repeated substrings cut out of the text; other columns stay. Of a character cut in two nothing is left. A null text stays null."""
    return _cut(docs, id_col, text_col, intervals(rec.prepare(docs, id_col, text_col), span, gram)[0], lambda t, a, b: _kept(t, a, b)[0])


def cut_passages(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", span: int = PASSAGE, gram: int = PASSAGE_GRAM, together: int = rec.TOGETHER, shard: int = SHARD_SYMBOLS) -> DataFrame:
    """``docs`` with passages of ``span`` words or more that start anywhere else too cut out of the text, at all their places.

    Words are what blanks separate; blanks themselves are not compared. Other columns stay. A null text stays null.
    """
    return _cut(docs, id_col, text_col, intervals(rec.prepare(docs, id_col, text_col), span, gram, together, shard, "words")[0], _without_words)
