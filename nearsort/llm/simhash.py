"""SimHash near-duplicates with covering locality-sensitive hashing.

Every bit position gets a random nonzero vector of r + 1 bits. For each of the 2**(r+1) - 1 nonzero
vectors v, a table keeps the positions whose vector has an odd product with v. Any r positions miss
one v entirely, so two fingerprints that differ in at most r bits have equal keys in some table.
Tables hold distinct fingerprints only, however many documents share one.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, functions as F

from . import textscan as ts
from .components import components
from .durable import cut
from .heavy import attach
from .lean import lean

BITS, RADIUS = 64, 3
#: Members up to which a bucket is compared in one task, block by block; larger ones are linked through shared neighbours.
BUCKET = 16_384
#: Shingles hashed at once.
SHINGLES = 65_536


def masks(bits: int = BITS, radius: int = RADIUS, seed: int = 20) -> list[int]:
    """The covering family for ``radius``; positions are dealt evenly over the nonzero vectors, then shuffled."""
    size = (1 << radius + 1) - 1
    vectors = np.random.default_rng(seed).permutation(np.arange(bits) % size) + 1
    return [sum(1 << i for i in range(bits) if bin(int(vectors[i]) & v).count("1") & 1) for v in range(1, size + 1)]


def simhash(text: str | None) -> int:
    """Majority bits of the XXH64 (seed 42) of all 3-word shingles."""
    return next(column_fingerprints(pa.array([text], pa.string())))


def column_fingerprints(column: pa.Array, size: int = 3) -> Iterator[int]:
    """Of each text, from shingles of ``size`` words."""
    hasher, form = xxhash.xxh64_intdigest, b" ".join([b"%b"] * size)
    for _, data, offsets in ts.groups(column):
        data = ts.LOWER[data]
        start, end, first = ts.words(data, offsets, ~ts.SPACE)
        raw = data.tobytes()
        words = [raw[a:b] for a, b in zip(start.tolist(), end.tolist())]
        bounds = first.tolist()
        for a, b in zip(bounds, bounds[1:]):
            if b == a:
                yield 0
                continue
            bits = np.zeros(64, dtype=np.int64)
            for k in range(a, max(a + 1, b - size + 1), SHINGLES):  # shingles that start in [k, k + SHINGLES)
                w = words[k : min(b, k + SHINGLES + size - 1)]
                if b - a < size:
                    h = [hasher(b" ".join(w), 42)]
                else:
                    h = [hasher(x, 42) for x in map(form.__mod__, zip(*(w[n:] for n in range(size))))]
                some = np.asarray(h, dtype=">u8")
                bits += np.unpackbits(some.view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
            yield int.from_bytes(np.packbits(2 * bits > max(1, b - a - size + 1)).tobytes(), "big")


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, fp): the fingerprint as a signed long. Null and wordless texts have fingerprint zero."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fp = np.fromiter(column_fingerprints(b.column(1)), dtype=np.uint64, count=b.num_rows)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(ts.signed(fp), pa.int64())], names=[id_col, "fp"])

    return docs.select(id_col, F.col(text_col).alias("t")).mapInArrow(lean(run), f"`{id_col}` {docs.schema[id_col].dataType.simpleString()}, fp long")


def _forest(fp: np.ndarray, radius: int) -> list[tuple[int, int]]:
    """Edges that join all members linked within the radius: at most one fewer than members.

    Each member is taken up once and held against those not yet reached, in one array operation.
    """
    edges, left = [], np.arange(len(fp))
    while len(left):
        todo, left = [int(left[0])], left[1:]
        while todo and len(left):
            x = todo.pop()
            near = np.bitwise_count(fp[left] ^ fp[x]) <= radius
            found = left[near].tolist()
            edges += [(x, y) for y in found]
            todo += found
            left = left[~near]
    return edges


def links(distinct: DataFrame, radius: int = RADIUS, bucket: int = BUCKET) -> DataFrame:
    """Edges (a, b) between distinct fingerprints (column fp) whose components are those of all links within ``radius``."""
    table = masks(BITS, radius)
    as_long = lambda m: F.lit(m - (1 << 64) if m >> 63 else m)
    keyed = distinct.select("fp", F.posexplode(F.array(*(F.col("fp").bitwiseAND(as_long(m)) for m in table))).alias("t", "key"))
    sizes = keyed.groupBy("t", "key").agg(F.count("*").alias("n")).where("n > 1")
    small = keyed.join(sizes.where(F.col("n") <= bucket).select("t", "key"), ["t", "key"]).groupBy("t", "key").agg(F.collect_list("fp").alias("fps"))

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            lists = b.column("fps")
            for k in range(len(lists)):
                fp = np.sort(lists[k].values.to_numpy(zero_copy_only=False).view(np.uint64))
                got = np.asarray(_forest(fp, radius), dtype=np.int64).reshape(-1, 2)
                if len(got):
                    yield pa.RecordBatch.from_arrays([pa.array(ts.signed(fp[got[:, 0]])), pa.array(ts.signed(fp[got[:, 1]]))], names=["a", "b"])

    found = small.select("fps").mapInArrow(lean(compare), "a long, b long")
    large = sizes.where(F.col("n") > bucket).select("t", "key")
    if large.isEmpty():
        return found
    # A word z within floor(r/2) of x and within r - floor(r/2) of y shows that x and y are linked; any link has one.
    # All fingerprints around a z that has such an x are linked to x, so each z gives a star.
    near, far = radius // 2, radius - radius // 2
    hot = cut(keyed.join(large, ["t", "key"]).select("t", "fp"))
    edges = []
    for t in sorted(r.t for r in hot.select("t").distinct().collect()):  # at most as many as tables
        free = [1 << i for i in range(BITS) if not table[t] >> i & 1]
        flips = [(d, sum(c)) for d in range(far + 1) for c in combinations(free, d)]
        members = hot.where(F.col("t") == t).select("fp")
        around = members.select("fp", F.explode(F.array(*(F.struct(F.lit(d).alias("d"), F.col("fp").bitwiseXOR(as_long(m)).alias("z")) for d, m in flips))).alias("x")).select("fp", "x.d", "x.z")
        centre = around.where(F.col("d") <= near).groupBy("z").agg(F.min("fp").alias("a"))
        edges.append(around.join(centre, "z").where("fp != a").select("a", F.col("fp").alias("b")).distinct())
    for e in edges:
        found = found.unionByName(e)
    return found


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", radius: int = RADIUS, bucket: int = BUCKET) -> DataFrame:
    """fingerprint (16 hex digits) and component_id (least id reachable over links) of every row.

    Texts without words have fingerprint zero and are linked like any other. A null id takes part,
    but is a component's id only where no other is there. Repeated rows each give a row. An
    empty table gives an empty result; further columns are ignored.
    """
    fps = cut(fingerprints(docs, id_col, text_col))
    distinct = cut(fps.groupBy("fp").agg(F.min(id_col).alias("least"), F.count("*").alias("n")))
    roots = components(links(distinct.select("fp"), radius, bucket), "a", "b").select(F.col("node").alias("fp"), "root")
    rooted = distinct.join(roots, "fp", "left").select("fp", "least", "n", F.coalesce("root", "fp").alias("root"))
    named = cut(rooted.join(rooted.groupBy("root").agg(F.min("least").alias("component_id")), "root").select("fp", "component_id", "n"))
    return attach(fps, named, "fp", "n").select(id_col, F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", radius: int = RADIUS) -> DataFrame:
    """One document of each component, the one of the least id, with all its columns; of rows that repeat that id, one. Rows without an id can't be told apart and all stay."""
    ided = docs.where(F.col(id_col).isNotNull())
    chosen = near_duplicates(ided, id_col, text_col, radius).where(F.col(id_col) == F.col("component_id")).select(F.col(id_col).alias("__id"))
    kept = ided.join(chosen, F.col(id_col) == F.col("__id"), "left_semi").dropDuplicates([id_col])
    return kept.unionByName(docs.where(F.col(id_col).isNull()))
