"""Benchmark decontamination as a prefix-filtered set join with exact verification.

An item's window is a set of positioned word shingles; as all of them must occur, the window's
prefix is its single rarest shingle, rarity being the count over all documents. Documents meet
windows only through that shingle; position and length bounds then fix where the window would
start, and the words are compared there.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from . import textscan as ts
from .durable import cut
from .lean import lean

#: Words in a window, in a shingle; benchmark bytes that one broadcast block may hold.
WINDOW = 13
SHINGLE = 5
BLOCK_BYTES = 1 << 19


def item_words(text: str | None) -> list[bytes]:
    data = np.frombuffer((text or "").encode(), dtype=np.uint8)
    start, end, _ = ts.words(ts.LOWER[data], np.asarray([0, len(data)]), ts.ALNUM)
    raw = ts.LOWER[data].tobytes()
    return [raw[a:b] for a, b in zip(start, end)]


class Block:
    """Windows of some benchmark items: per distinct window its words, items and shingle hashes."""

    def __init__(self, items: list[tuple[str, str | None]], window: int, shingle: int):
        self.window, self.shingle = window, shingle
        found: dict[tuple[bytes, ...], set[str]] = {}
        for item, text in items:
            w = item_words(text)
            for k in range(max(1, len(w) - window + 1) if w else 0):
                found.setdefault(tuple(w[k : k + window]), set()).add(item)
        self.windows = list(found)
        self.items = [sorted(found[w]) for w in self.windows]
        self.key: dict[int, list[tuple[int, int]]] = {}
        # shingle hashes by their length: windows shorter than a shingle are one shingle
        self.grams: list[list[tuple[int, int]]] = []
        for w in self.windows:
            raw = b" ".join(w)
            data = np.frombuffer(raw, dtype=np.uint8)
            s, e, _ = ts.words(data, np.asarray([0, len(data)]), ts.ALNUM)
            k = min(shingle, len(w))
            self.grams.append([(k, int(h)) for h in ts.word_rolling(ts.word_hash(data, s, e)).grams(k)])

    def distinct(self) -> dict[int, np.ndarray]:
        """Sorted shingle hashes by shingle length."""
        out: dict[int, set[int]] = {}
        for g in self.grams:
            for k, h in g:
                out.setdefault(k, set()).add(h)
        return {k: np.sort(np.asarray(list(v), dtype=np.uint64)) for k, v in out.items()}

    def choose(self, rarity: dict[tuple[int, int], int]) -> None:
        """Keep of each window the rarest shingle (ties: the first) and its place in the window."""
        key: dict[tuple[int, int], list[tuple[int, int]]] = {}
        for n, g in enumerate(self.grams):
            place = min(range(len(g)), key=lambda j: (rarity.get(g[j], 0), j))
            if rarity.get(g[place], 0):
                key.setdefault(g[place], []).append((n, place))
        self.lengths = sorted({k for k, _ in key})
        self.sorted = {k: np.sort(np.asarray([h for n, h in key if n == k], dtype=np.uint64)) for k in self.lengths}
        self.key = key
        self.grams = []


def _scan(column: pa.Array, lengths: list[int], tables: dict[int, np.ndarray]):
    """Per group of rows: rows, lower-cased bytes, words, and per shingle length the places whose hash is in its table."""
    for row, data, offsets in ts.groups(column):
        data = ts.LOWER[data]
        start, end, first = ts.words(data, offsets, ts.ALNUM)
        rolling = ts.word_rolling(ts.word_hash(data, start, end))
        hits = []
        for k in lengths:
            g, table = rolling.grams(k), tables[k]
            at = np.searchsorted(table, g)
            at[at == len(table)] = 0
            hits.append((k, np.flatnonzero(table[at] == g), g) if len(g) else (k, np.zeros(0, np.int64), g))
        yield row, data, start, end, first, hits


def _rarity(docs: DataFrame, text_col: str, block: Block) -> dict[tuple[int, int], int]:
    """Occurrences in all documents of the block's shingles; as many rows as the block has, at most."""
    tables = block.distinct()
    shared = docs.sparkSession.sparkContext.broadcast(tables)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tables = shared.value
        sums = {k: np.zeros(len(v), np.int64) for k, v in tables.items()}
        for b in batches:
            for _, _, _, _, _, hits in _scan(b.column("t"), list(tables), tables):
                for k, at, g in hits:
                    sums[k] += np.bincount(np.searchsorted(tables[k], g[at]), minlength=len(tables[k]))
        for k, n in sums.items():
            at = np.flatnonzero(n)
            yield pa.RecordBatch.from_arrays([pa.array([k] * len(at), pa.int32()), pa.array(ts.signed(tables[k][at]), pa.int64()), pa.array(n[at], pa.int64())], names=["k", "h", "n"])

    got = docs.select(F.col(text_col).alias("t")).mapInArrow(lean(count), "k int, h long, n long").groupBy("k", "h").agg(F.sum("n").alias("n")).toArrow()
    return {(k, h & (1 << 64) - 1): n for k, h, n in zip(*(got.column(c).to_pylist() for c in ("k", "h", "n")))}


def find(block: Block, column: pa.Array) -> Iterator[tuple[int, int, np.ndarray, set[str]]]:
    """(row, words, hit word places, items) of every row."""
    for row, data, start, end, first, hits in _scan(column, block.lengths, block.sorted):
        raw = data.tobytes()
        covered: dict[int, list[tuple[int, int]]] = {}
        items: dict[int, set[str]] = {}
        for k, places, g in hits:
            for p in places.tolist():
                doc = int(np.searchsorted(first, p, side="right")) - 1
                for n, place in block.key[(k, int(g[p]))]:
                    words = block.windows[n]
                    a = p - place
                    b = a + len(words)
                    if a >= first[doc] and b <= first[doc + 1] and all(raw[x:y] == w for x, y, w in zip(start[a:b].tolist(), end[a:b].tolist(), words)):
                        covered.setdefault(doc, []).append((a - int(first[doc]), b - int(first[doc])))
                        items.setdefault(doc, set()).update(block.items[n])
        for doc in range(len(first) - 1):
            n_words = int(first[doc + 1] - first[doc])
            at = np.asarray(covered.get(doc, ()), dtype=np.int64).reshape(-1, 2)
            yield row + doc, n_words, np.flatnonzero(ts.cover(n_words, at[:, 0], at[:, 1])) if len(at) else np.zeros(0, np.int64), items.get(doc, set())


def blocks_of(benchmark: DataFrame, item_col: str, text_col: str, window: int, shingle: int, block_bytes: int) -> Iterator[Block]:
    """The benchmark in blocks of bounded size, one held at a time. Items without a word are left out."""
    sizes = benchmark.select(F.coalesce(F.octet_length(text_col), F.lit(0)).alias("n")).agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    parts = max(1, -(-int(sizes) // block_bytes))
    rows = benchmark.select(F.col(item_col).cast("string").alias("item"), F.col(text_col).alias("text"), F.pmod(F.xxhash64(F.col(item_col).cast("string"), F.col(text_col)), F.lit(parts)).alias("part"))
    for part in range(parts):
        got = [(r.item if r.item is not None else "", r.text) for r in rows.where(F.col("part") == part).toLocalIterator()]
        block = Block(got, window, shingle)
        if block.windows:
            yield block


def _text_key(text_col: str) -> list:
    """Two hashes by which texts are told apart."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    return [F.xxhash64(text).alias("__k1"), F.xxhash64(F.lit(1), text).alias("__k2")]


def _hits_by_block(docs: DataFrame, blocks: Iterator[Block], text_col: str) -> DataFrame | None:
    """(__k1, __k2, places, items) of texts with a hit, one row a text: each block's hits are written before the next block is taken up."""
    sc, parts = docs.sparkSession.sparkContext, []
    source = docs.select(*_text_key(text_col), F.col(text_col).alias("t"))
    for block in blocks:
        block.choose(_rarity(docs, text_col, block))
        shared = sc.broadcast(block)

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            for b in batches:
                got = [(row, at, sorted(names)) for row, _, at, names in find(shared.value, b.column(2)) if len(at)]
                rows = pa.array([r for r, _, _ in got], pa.int64())
                yield pa.RecordBatch.from_arrays([b.column(0).take(rows), b.column(1).take(rows), pa.array([x.tolist() for _, x, _ in got], pa.list_(pa.int64())), pa.array([x for _, _, x in got], pa.list_(pa.string()))], names=["__k1", "__k2", "places", "items"])

        hits = source.mapInArrow(lean(run), "__k1 long, __k2 long, places array<long>, items array<string>")
        parts.append(cut(hits.dropDuplicates(["__k1", "__k2"])))
        shared.destroy()
    if not parts:
        return None
    every = parts[0]
    for x in parts[1:]:
        every = every.unionByName(x)
    united = lambda c: F.array_distinct(F.flatten(F.collect_list(c))).alias(c)
    return every.groupBy("__k1", "__k2").agg(united("places"), united("items"))


def contamination(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", window: int = WINDOW, shingle: int = SHINGLE, block_bytes: int = BLOCK_BYTES, keep: bool = False) -> DataFrame:
    """n_words, n_hit, n_items, items_sha256, contaminated of every document.

    A word inside any occurrence of an item's window is hit; contaminated: a word is hit and the hit
    words are at least a twentieth of all. A null text has no words; an item without words has no
    window; null item ids count as the empty id. Rows are judged one by one, so repeated rows
    get equal verdicts. Further columns are dropped unless ``keep``; a clashing name is replaced.
    A benchmark larger than one block is worked through block by block; the hits of each are written
    to shared storage, and united per text at the end, so no worker holds more than one block.
    """
    own = ["n_words", "n_hit", "n_items", "items_sha256", "contaminated"]
    others = [c for c in docs.columns if keep and c not in {id_col, *own}]
    kept = "".join(f"`{c}` {docs.schema[c].dataType.simpleString()}, " for c in [id_col, *others])
    blocks = blocks_of(benchmark, item_col, item_text_col, window, shingle, block_bytes)
    first, second = next(blocks, None), next(blocks, None)
    if second is not None:
        return _judged_by_hits(docs, _hits_by_block(docs, chain((first, second), blocks), text_col), id_col, text_col, others)
    source = docs.select(id_col, *others, F.col(text_col).alias("__text"))
    only = first or Block([], window, shingle)
    only.choose(_rarity(docs, text_col, only) if first else {})
    shared = docs.sparkSession.sparkContext.broadcast(only)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            column = b.column(b.num_columns - 1)
            rows = [(n, len(at), len(names), hashlib.sha256(",".join(sorted(names)).encode()).hexdigest(), len(at) > 0 and 20 * len(at) >= n) for _, n, at, names in find(shared.value, column)]
            values = list(zip(*rows)) or [()] * len(own)
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], *(pa.array(v, k) for v, k in zip(values, (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.bool_())))], names=[id_col, *others, *own])

    return source.mapInArrow(lean(run), kept + "n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean")


def _judged_by_hits(docs: DataFrame, hits: DataFrame, id_col: str, text_col: str, others: list[str]) -> DataFrame:
    """The verdicts of contamination() from the united hits of all blocks."""
    names = [id_col, *others, "__k1", "__k2"]

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            n = [np.diff(first) for _, _, _, _, first, _ in _scan(b.column(b.num_columns - 1), [], {})]
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array(np.concatenate(n) if n else [], pa.int64())], names=[*names, "__n"])

    source = docs.select(id_col, *others, *_text_key(text_col), F.col(text_col).alias("__text"))
    kept = "".join(f"`{c}` {source.schema[c].dataType.simpleString()}, " for c in names)
    rows = source.mapInArrow(lean(count), kept + "__n long").join(hits, ["__k1", "__k2"], "left")
    n_hit = F.when(F.col("places").isNull(), F.lit(0)).otherwise(F.size("places")).cast("long")
    items = F.coalesce(F.array_join(F.array_sort("items"), ","), F.lit(""))
    return rows.select(
        id_col, *others, F.col("__n").alias("n_words"), n_hit.alias("n_hit"), F.when(F.col("items").isNull(), F.lit(0)).otherwise(F.size("items")).cast("long").alias("n_items"),
        F.sha2(items.cast("binary"), 256).alias("items_sha256"), ((n_hit > 0) & (20 * n_hit >= F.col("__n"))).alias("contaminated"),
    )
