"""Token-id rows of fixed length by best-fit-decreasing packing.

Texts become byte-pair ids, by tiktoken, where they are read; a text longer than a row is cut into segments without loss.
Segments are dealt to shards of a bounded expected size, in documents and in bytes, by a hash, and every shard is packed by
itself: longest segment first, each into the open row with the least room that still fits, which a
segment tree over the remaining capacities finds in O(log row length).
"""

from __future__ import annotations

import base64
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .lean import lean

#: Characters encoded at once; a longer text is cut before a single space between two others.
CHUNK_CHARS = 200_000
_BOUNDARY = re.compile(r"(?<=\S) (?=\S)")
_encodings: dict[tuple[str, str], object] = {}
#: Documents and bytes of text that a shard holds on average; segments are no more than both allow.
SHARD_DOCS, SHARD_BYTES = 8192, 24 << 20


def load(path: str, pattern: str):
    """The encoding of a ranks file, once per worker, without special tokens: their strings are ordinary text."""
    if (path, pattern) not in _encodings:
        import tiktoken

        with open(path, "rb") as f:
            ranks = {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, f)}
        _encodings[path, pattern] = tiktoken.Encoding("ranks", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
    return _encodings[path, pattern]


def chunks(text: str, size: int = CHUNK_CHARS) -> Iterator[str]:
    """Parts of about ``size`` characters whose ids, joined, are the text's."""
    at = 0
    while len(text) - at > size and (cut := _BOUNDARY.search(text, at + size)):
        yield text[at : cut.start()]
        at = cut.start()
    yield text[at:]


class CapacityTree:
    """Open rows by remaining capacity; ``best(n)`` is the least capacity >= n that has a row."""

    def __init__(self, capacity: int):
        self.size = 1 << capacity.bit_length()
        self.count = [0] * (2 * self.size)
        self.rows: list[list[int]] = [[] for _ in range(capacity + 1)]

    def add(self, capacity: int, row: int) -> None:
        self.rows[capacity].append(row)
        self._step(capacity, 1)

    def take(self, capacity: int) -> int:
        self._step(capacity, -1)
        return self.rows[capacity].pop()

    def _step(self, capacity: int, by: int) -> None:
        at = capacity + self.size
        while at:
            self.count[at] += by
            at >>= 1

    def best(self, n: int) -> int | None:
        at = n + self.size
        if self.count[at]:
            return n
        while at > 1:
            if not at & 1 and self.count[at + 1]:
                at += 1
                while at < self.size:
                    at = 2 * at if self.count[2 * at] else 2 * at + 1
                return at - self.size
            at >>= 1
        return None


def best_fit_decreasing(lengths: np.ndarray, capacity: int) -> list[list[int]]:
    """Rows of indices into ``lengths`` (each 1..capacity); ties keep the given order."""
    tree, rows = CapacityTree(capacity), []
    for i in np.argsort(-lengths, kind="stable").tolist():
        n = int(lengths[i])
        room = tree.best(n)
        if room is None:
            rows.append([i])
            row, room = len(rows) - 1, capacity
        else:
            row = tree.take(room)
            rows[row].append(i)
        if room > n:
            tree.add(room - n, row)
    return rows


def pack(docs: DataFrame, path: str, pattern: str, row_tokens: int = 2048, eos_id: int = 50256, pad_id: int = 50256, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Packed rows: shard, row_no, n_tokens, token_ids (row_tokens little-endian uint16/uint32, padded), doc_ids, segment_starts (each segment's first place in its document's ids), cu_seqlens, position_resets (places where positions start at 0 again).

    Every text ends in ``eos_id``; a null or empty text gives that id alone. Repeated rows are
    packed as often as they occur, null ids are kept, further columns ignored. Positions inside
    a row start again at every segment. An empty table gives no rows.
    """
    tokens_width = np.dtype("<u2" if max(eos_id, pad_id, load(path, pattern).max_token_value) < 1 << 16 else "<u4")
    width = tokens_width.itemsize
    kind = docs.schema[id_col].dataType
    eos = np.asarray([eos_id], dtype=tokens_width).tobytes()

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoding = load(path, pattern)
        for b in batches:
            ids, texts, n = b.column("i"), b.column("t"), b.num_rows
            out, size = ([], [], []), 0
            for row in range(n):
                text = texts[row].as_py() or ""
                data = b"".join([encoding.encode_to_numpy(part, disallowed_special=()).astype(tokens_width).tobytes() for part in chunks(text)]) + eos
                for at in range(0, len(data), row_tokens * width):
                    out[0].append(row)
                    out[1].append(at // width)
                    out[2].append(data[at : at + row_tokens * width])
                size += len(data)
                if size > 8 << 20 or row == n - 1:
                    yield pa.RecordBatch.from_arrays([ids.take(pa.array(out[0], pa.int64())), pa.array(out[1], pa.int64()), pa.array(out[2], pa.binary())], names=["id", "start", "ids"])
                    out, size = ([], [], []), 0

    segments = docs.select(F.col(id_col).alias("i"), F.col(text_col).alias("t")).mapInArrow(lean(encode), f"id {kind.simpleString()}, start long, ids binary")
    size = docs.agg(F.count("*").alias("n"), F.coalesce(F.sum(F.octet_length(text_col)), F.lit(0)).alias("b")).first()
    shards = max(1, -(-size.n // SHARD_DOCS), -(-size.b // SHARD_BYTES))
    segments = segments.withColumn("shard", F.pmod(F.xxhash64("id", "start", F.length("ids")), F.lit(shards)))

    def packed(shard: int, ids: list, start: list, data: list) -> pa.RecordBatch:
        lengths = np.asarray([len(x) // width for x in data], dtype=np.int64)
        rows = best_fit_decreasing(lengths, row_tokens)
        pad = np.asarray([pad_id], dtype=tokens_width).tobytes()
        cu = [[0, *np.cumsum(lengths[r]).tolist()] for r in rows]
        return pa.RecordBatch.from_arrays(
            [
                pa.array([shard] * len(rows), pa.int64()), pa.array(range(len(rows)), pa.int64()), pa.array([c[-1] for c in cu], pa.int64()),
                pa.array([b"".join(data[i] for i in r) + pad * (row_tokens - c[-1]) for r, c in zip(rows, cu)], pa.binary()),
                pa.array([[ids[i] for i in r] for r in rows]), pa.array([[start[i] for i in r] for r in rows], pa.list_(pa.int64())), pa.array(cu, pa.list_(pa.int64())), pa.array([c[:-1] for c in cu], pa.list_(pa.int64())),
            ],
            names=["shard", "row_no", "n_tokens", "token_ids", "doc_ids", "segment_starts", "cu_seqlens", "position_resets"],
        )

    def fill(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, ids, start, data = None, [], [], []
        for b in batches:
            for s, i, a, d in zip(*(b.column(c).to_pylist() for c in ("shard", "id", "start", "ids"))):
                if s != now and data:
                    yield packed(now, ids, start, data)
                    ids, start, data = [], [], []
                now = s
                ids.append(i)
                start.append(a)
                data.append(d)
        if data:
            yield packed(now, ids, start, data)

    schema = f"shard long, row_no long, n_tokens long, token_ids binary, doc_ids array<{kind.simpleString()}>, segment_starts array<long>, cu_seqlens array<long>, position_resets array<long>"
    dealt = segments.repartition(max(min(shards, 20_000), 1), "shard").sortWithinPartitions("shard", F.length("ids").desc(), "id", "start")
    return dealt.mapInArrow(lean(fill), schema)
