"""Near-duplicates by the similarity of their five-word shingles.

Candidates come from two sources. Covering SimHash over the same shingles (``simhash.links``) joins texts whose fingerprints differ in at
most three of 64 bits. At a similarity of 0.8 fingerprints differ in about ten bits, and covering that radius takes thousands of tables; so
pairs further apart come from a sketch of 100 minima per text, cut into 20 bands of five: a pair of similarity s shares no band with
probability (1 - s**5)**20, at 0.8 about 0.0004. The components of all candidates are then looked at one by one, and within them the whole
shingle sets decide which texts are linked, whichever source joined them; a component that is too large for one task is looked at in chunks
(``_split``).
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import Column, DataFrame, functions as F

from . import simhash, textscan as ts
from .components import components
from .durable import cut
from .lean import lean

#: Words of a shingle; least similarity of a link, as a fraction.
WORDS, LEAST = 5, (4, 5)
BANDS, ROWS = 20, 5
#: Share of equal minima below which a pair isn't compared: four standard deviations under 0.8.
SCREEN = 0.64
#: Texts, and bytes of them, up to which a component is looked at in one task, and about as many as a chunk of a larger one has.
GROUP_TEXTS, GROUP_BYTES = 16_384, 32 << 20
#: Texts of a split component that are in all of its chunks, on average.
CENTRES = 16
_FACTORS = np.random.default_rng(5).integers(0, 1 << 63, BANDS * ROWS, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_TERMS = np.random.default_rng(6).integers(0, 1 << 63, BANDS * ROWS, dtype=np.uint64)


def _sketches(column: pa.Array) -> Iterator[tuple[bytes, bytes]]:
    """(digest of the lower-cased words, minima as 32-bit numbers) of each text."""
    for _, data, offsets in ts.groups(column):
        data = ts.LOWER[data]
        start, end, first = ts.words(data, offsets, ~ts.SPACE)
        rolling = ts.word_rolling(ts.word_hash(data, start, end))
        n = np.diff(first)
        owner = np.repeat(np.arange(len(n)), n)
        whole = np.flatnonzero(owner[: -WORDS + 1] == owner[WORDS - 1 :]) if len(owner) >= WORDS else np.zeros(0, np.int64)
        short = np.flatnonzero((n > 0) & (n < WORDS))
        hashes = np.concatenate((rolling.grams(WORDS)[whole], rolling.runs(first[short], first[short + 1])))
        of = np.concatenate((owner[whole], short))
        order = np.argsort(of, kind="stable")
        hashes, of = hashes[order], of[order]
        minima = np.full((len(n), BANDS * ROWS), np.iinfo(np.uint32).max, np.uint32)
        if len(of):
            at = np.flatnonzero(np.concatenate(([True], of[1:] != of[:-1])))
            for k, (f, t) in enumerate(zip(_FACTORS, _TERMS)):
                minima[of[at], k] = np.minimum.reduceat(hashes * f + t, at) >> np.uint64(32)
        inside = ~ts.SPACE[data]
        keep = inside.copy()
        keep[1:] |= inside[:-1]
        plain = np.where(inside, data, np.uint8(32))[keep].tobytes()
        place = np.concatenate(([0], np.cumsum(keep)))[offsets].tolist()
        for d, (a, b) in enumerate(zip(place, place[1:])):
            yield hashlib.blake2b(plain[a:b].strip(b" "), digest_size=16).digest(), minima[d].tobytes()


def shingles(text: bytes) -> np.ndarray:
    """Sorted 64-bit hashes of all runs of five words; fewer words are one run, none an empty set."""
    data = ts.LOWER[np.frombuffer(text, np.uint8)]
    start, end, _ = ts.words(data, np.asarray([0, len(data)]), ~ts.SPACE)
    raw = data.tobytes()
    words = [raw[a:b] for a, b in zip(start.tolist(), end.tolist())]
    if not words:
        return np.zeros(0, np.uint64)
    runs = zip(*(words[k:] for k in range(WORDS))) if len(words) >= WORDS else [words]
    return np.unique(np.fromiter((xxhash.xxh64_intdigest(b" ".join(x), 7) for x in runs), np.uint64))


def alike(a: np.ndarray, b: np.ndarray) -> bool:
    part, whole = LEAST
    if whole * min(len(a), len(b)) < part * max(len(a), len(b)):
        return False
    both = len(np.intersect1d(a, b, assume_unique=True))
    return whole * both >= part * (len(a) + len(b) - both)


def linked(sketches: np.ndarray, sets: list[np.ndarray]) -> list[int]:
    """For each text the first one that it is linked to, directly or over others."""
    head, left = [-1] * len(sets), np.arange(len(sets))
    while len(left):
        seed, left = int(left[0]), left[1:]
        head[seed], todo = seed, [seed]
        while todo and len(left):
            x = todo.pop()
            near = (sketches[left] == sketches[x]).mean(axis=1) >= SCREEN
            for k in np.flatnonzero(near).tolist():
                if alike(sets[x], sets[left[k]]):
                    head[left[k]] = seed
                    todo.append(int(left[k]))
            left = left[[head[k] < 0 for k in left.tolist()]]
    return head


def _verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    press = zstandard.ZstdDecompressor()
    group, rows = None, []

    def flush() -> pa.RecordBatch:
        sketches = np.stack([np.frombuffer(s, np.uint32) for _, s, _ in rows])
        head = linked(sketches, [x for _, _, x in rows])
        return pa.RecordBatch.from_arrays([pa.array([d for d, _, _ in rows], pa.binary()), pa.array([rows[k][0] for k in head], pa.binary())], names=["dig", "head"])

    for b in batches:
        for g, d, s, z in zip(*(c.to_pylist() for c in b.columns)):
            if g != group and rows:
                yield flush()
                rows = []
            group = g
            rows.append((d, s, shingles(press.decompress(z))))
    if rows:
        yield flush()


def _compare(rows: DataFrame, *place: str) -> DataFrame:
    """(dig, head) of the texts of each component and place, compared in one task."""
    group = F.concat("root", F.concat_ws("/", *(F.col(c).cast("string") for c in place)).cast("binary")) if place else F.col("root")
    some = rows.select(group.alias("group"), "dig", "sketch", "z")
    return some.repartition("group").sortWithinPartitions("group", "dig").mapInArrow(lean(_verify), "dig binary, head binary")


def _parts(rows: DataFrame, texts: int, size: int) -> DataFrame:
    """(root, n, parts): texts of each component, and the chunks that they need."""
    sums = rows.groupBy("root").agg(F.count("*").alias("n"), F.sum("size").alias("b"))
    return sums.select("root", "n", F.greatest(F.ceil(F.col("n") / texts), F.ceil(F.col("b") / size), F.lit(1)).cast("int").alias("parts"))


def _split(rows: DataFrame, texts: int, size: int) -> DataFrame:
    """(dig, head) of components (root, dig, sketch, size, z, n, parts) that no task holds whole; no link is lost.

    Their texts are dealt to chunks, and a few of them go to all chunks; what is linked within the chunks makes classes. Two texts
    of one class need no comparison, so what is outside a component's largest class is then held, a block at a time, against every chunk.
    """
    own = F.pmod(F.xxhash64("dig"), F.col("parts")).cast("int")
    every = F.sequence(F.lit(0), F.col("parts") - 1)
    centre = (F.col("dig") == F.col("root")) | (F.pmod(F.xxhash64("dig", F.lit(1)), F.ceil(F.col("n") / CENTRES)) == 0)
    edges = cut(_compare(rows.withColumn("chunk", F.explode(F.when(centre, every).otherwise(F.array(own)))), "chunk").where("dig != head"))
    classes = components(edges, "dig", "head").select(F.col("node").alias("dig"), F.col("root").alias("class"))
    classes = cut(rows.select("root", "dig", "size").join(classes, "dig", "left").withColumn("class", F.coalesce("class", "dig")))
    largest = classes.groupBy("root", "class").agg(F.count("*").alias("n")).groupBy("root").agg(F.max_by("class", F.struct("n", "class")).alias("largest"))
    rest = cut(classes.join(largest, "root").where("class != largest").select("root", "dig", "size"))
    if not rest.isEmpty():
        left = rows.join(_parts(rest, texts, size).select("root", F.col("parts").alias("blocks")), "root")
        whole = left.withColumns({"chunk": own, "block": F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))})
        block = F.pmod(F.xxhash64("dig", F.lit(2)), F.col("blocks")).cast("int")
        some = left.join(rest.select("dig"), "dig", "left_semi").withColumns({"chunk": F.explode(every), "block": block})
        edges = edges.unionByName(cut(_compare(whole.unionByName(some), "block", "chunk").where("dig != head")))
    return components(edges, "dig", "head").select(F.col("node").alias("dig"), F.col("root").alias("head"))


def _texts(docs: DataFrame, text_col: str) -> Column:
    return F.coalesce(F.col(text_col), F.lit(""))


def _by_bands(distinct: DataFrame) -> DataFrame:
    """(a, b) that join digests which agree in a band of their minima."""
    bands = F.array(*(F.xxhash64(F.substring("sketch", 1 + 4 * ROWS * k, 4 * ROWS)) for k in range(BANDS)))
    keyed = distinct.select("dig", F.posexplode(bands).alias("band", "key"))
    heads = keyed.groupBy("band", "key").agg(F.min("dig").alias("a"), F.count("*").alias("n")).where("n > 1").drop("n")
    return keyed.join(heads, ["band", "key"]).select("a", F.col("dig").alias("b"))


def _by_fingerprints(distinct: DataFrame) -> DataFrame:
    """(a, b) that join digests whose fingerprints are linked by covering SimHash."""
    first = cut(distinct.groupBy("fp").agg(F.min("dig").alias("a")))
    same = distinct.join(first, "fp").where("a != dig").select("a", F.col("dig").alias("b"))
    ends = [first.select(F.col("fp").alias(x), F.col("a").alias(y)) for x, y in (("a", "x"), ("b", "y"))]
    near = cut(simhash.links(first.select("fp"))).join(ends[0], "a").join(ends[1], "b")
    return same.unionByName(near.select(F.col("x").alias("a"), F.col("y").alias("b")))


def clusters(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", texts: int = GROUP_TEXTS, size: int = GROUP_BYTES) -> DataFrame:
    """(id, th, head): every row's id, the hash of its text and a digest that linked texts share; equal words are linked whatever their blanks and case.

    ``texts`` and ``size`` bound what is compared in one task; results don't depend on them.
    """
    text = _texts(docs, text_col)
    kind = docs.schema[id_col].dataType.simpleString()

    def sketch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            got = list(_sketches(b.column(2)))
            prints = ts.signed(np.fromiter(simhash.column_fingerprints(b.column(2), WORDS), np.uint64, b.num_rows))
            bytes_ = np.diff(ts.text_buffers(b.column(2))[1])
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), *(pa.array([x[k] for x in got], pa.binary()) for k in (0, 1)), pa.array(bytes_, pa.int64()), pa.array(prints, pa.int64())], names=["id", "th", "dig", "sketch", "size", "fp"])

    plain = docs.select(F.col(id_col).alias("id"), F.xxhash64(text).alias("th"), text.alias("t"))
    rows = cut(plain.mapInArrow(lean(sketch), f"id {kind}, th long, dig binary, sketch binary, size long, fp long"))
    distinct = cut(rows.groupBy("dig").agg(F.min(F.struct("id", "th")).alias("least"), F.first("sketch").alias("sketch"), F.max("size").alias("size"), F.first("fp").alias("fp")))
    roots = components(_by_fingerprints(distinct).unionByName(_by_bands(distinct)), "a", "b")
    members = roots.unionByName(roots.select(F.col("root").alias("node"), "root").distinct()).withColumnRenamed("node", "dig")
    wanted = members.join(distinct, "dig").select("least.id", "least.th", "root", "dig", "sketch", "size")
    large = cut(_parts(wanted, texts, size).where("parts > 1"))

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        press = zstandard.ZstdCompressor(level=1)
        for b in batches:
            raw, off = ts.text_buffers(b.column(2))
            whole, at = raw.data, off.tolist()
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([press.compress(whole[x:y]) for x, y in zip(at, at[1:])], pa.binary())], names=["id", "th", "z"])

    pressed = plain.mapInArrow(lean(pack), f"id {kind}, th long, z binary")
    whole = pressed.join(wanted, ["id", "th"]).dropDuplicates(["id", "th"]).select("root", "dig", "sketch", "size", "z")
    if large.isEmpty():
        checked = _compare(whole)
    else:
        whole = cut(whole)
        checked = _compare(whole.join(large, "root", "left_anti")).unionByName(_split(whole.join(large, "root"), texts, size))
    return rows.select("id", "th", "dig").join(checked, "dig", "left").select("id", "th", F.coalesce("head", "dig").alias("head"))


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Of texts that are linked, directly or over others, by a similarity of 0.8 or more the one of the least id, with all its columns; of repeated rows one.

    Rows without an id can't be told apart and all stay. Texts without words are alike.
    """
    ided = docs.where(F.col(id_col).isNotNull())
    chosen = clusters(ided, id_col, text_col).groupBy("head").agg(F.min(F.struct("id", "th")).alias("x")).select(F.col("x.id").alias("__id"), F.col("x.th").alias("__th"))
    kept = ided.withColumn("__t", F.xxhash64(_texts(ided, text_col))).join(chosen, (F.col(id_col) == F.col("__id")) & (F.col("__t") == F.col("__th")), "left_semi")
    return kept.dropDuplicates([id_col, "__t"]).drop("__t").unionByName(docs.where(F.col(id_col).isNull()))
