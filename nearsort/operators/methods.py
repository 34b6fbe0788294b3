"""Blocking methods: rows with id and k in, pairs (left_id, right_id, distance) out."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, functions as F

from . import layout, pairs
from .partitioners import Partitioner

def _bucket(rows: DataFrame, w: int, cols: tuple[str, ...] = ("id",)) -> DataFrame:
    """Rank buckets inside each partition."""
    rank = F.row_number().over(Window.partitionBy("p").orderBy("k", "id"))
    return pairs.bucket(rows if "g" in rows.columns else rows.withColumn("g", rank), w, cols, group="p")


_ENGINES = {"frame": pairs.frame, "lag": pairs.lag, "bucket": _bucket}


def _engine(name: str):
    return _ENGINES[name]


def sequential_pairs(entities: DataFrame, w: int, cols: tuple[str, ...] = ("id",)) -> DataFrame:
    """One ordered pass in a single task, sorted on disk if need be: the meaning that all other window methods must reproduce."""
    return pairs.frame(entities.withColumn("one", F.lit(0)), w, group="one", cols=cols)


def local_pairs(entities: DataFrame, w: int, partitioner: Partitioner, cols: tuple[str, ...] = ("id",), engine: str = "frame") -> DataFrame:
    """Windows inside each ordered partition only: pairs across seams are missing."""
    placed = layout.place(layout.tag(entities, partitioner), partitioner.parts)
    if engine in ("ring", "grouped"):
        return getattr(pairs, engine)(placed, w, cols=cols)
    return _engine(engine)(placed, w, cols=cols)


def seams(offsets: DataFrame) -> DataFrame:
    """(seam, at): partition to the right of a seam, and the rows before it."""
    return offsets.where("off > 0").select(F.col("p").alias("seam"), F.col("off").alias("at"))


def _near_seams(rows: DataFrame, offsets: DataFrame, w: int, after: int) -> DataFrame:
    """Rows whose global rank lies in (at - (w - 1), at + after] of a seam, by an equi-join of rank buckets."""
    size = w - 1
    q = F.floor(F.col("at") / size)
    table = seams(offsets).select("seam", "at", F.explode(F.array(q - 1, q, q + 1)).alias("b"))
    d = F.col("g") - F.col("at")
    return rows.withColumn("b", F.floor(F.col("g") / size)).join(F.broadcast(table), "b").where((d > -size) & (d <= after)).drop("b", "at")


def boundary_rows(ordered: DataFrame, offsets: DataFrame, w: int, completeness: str = "exact") -> DataFrame:
    """Input of the second job: for each seam the rows within w - 1 of it. "adjacent" takes the neighbouring partitions' tails and heads only."""
    offsets = layout.known(offsets)
    edge = ordered.where((F.col("rn") <= w - 1) | (F.col("rn_desc") <= w - 1))
    near = _near_seams(edge, offsets, w, w - 1)
    if completeness == "adjacent":
        near = near.where((F.col("p") == F.col("seam")) | (F.col("p") == F.col("seam") - 1))
    return near


def seam_pairs(boundary: DataFrame, w: int, cols: tuple[str, ...] = ("id",), parallelism: int | None = None, engine: str = "frame") -> DataFrame:
    """Windows over each seam's rows; pairs of one partition are known already, others belong to the seam before their right row."""
    rows = boundary.coalesce(parallelism) if parallelism else boundary
    some = (*dict.fromkeys((*cols, "p", "seam")),)
    got = pairs.bucket(rows, w, some, group="seam") if engine == "bucket" else pairs.frame(rows, w, group="seam", order=("g",), cols=some)
    return got.where((F.col("left_p") < F.col("right_p")) & (F.col("right_p") == F.col("right_seam"))).drop("left_p", "right_p", "left_seam", "right_seam")


def stitch_pairs(entities: DataFrame, w: int, partitioner: Partitioner, completeness: str = "exact", cols: tuple[str, ...] = ("id",), parallelism: int | None = None, engine: str = "frame") -> DataFrame:
    """Windows in partitions, and a second small pass over the rows around seams. Both read the one wide exchange."""
    rows = entities.select(*dict.fromkeys(("id", "k", *cols)))
    offsets = layout.offsets_of(entities, partitioner)
    ordered = layout.ordered(rows, partitioner, offsets)
    inside = _engine(engine)(layout.place(layout.tag(rows, partitioner), partitioner.parts), w, cols=cols)
    return union_sorted(inside, seam_pairs(boundary_rows(ordered, offsets, w, completeness), w, cols, parallelism, engine))


def union_sorted(*found: DataFrame, order: tuple[str, ...] = ()) -> DataFrame:
    """Several results as one, in the order of ``order`` if any is asked for."""
    out = found[0]
    for x in found[1:]:
        out = out.unionByName(x)
    return out.orderBy(*order) if order else out


def replica_rows(entities: DataFrame, w: int, partitioner: Partitioner, scope: str = "partition", mapper: str | Column = "mapper_id") -> DataFrame:
    """Copies of each partition's greatest w - 1 rows (one set a map task with scope "map"), addressed to the next partition."""
    tagged = layout.tag(entities, partitioner).where(F.col("p") < partitioner.parts - 1)
    group = ["p"] if scope == "partition" else [F.col(mapper) if isinstance(mapper, str) else mapper, F.col("p")]
    top = F.row_number().over(Window.partitionBy(*group).orderBy(F.col("k").desc(), F.col("id").desc()))
    return tagged.withColumn("n", top).where(F.col("n") <= w - 1).drop("n").withColumn("target", F.col("p") + 1)


def replica_pairs(entities: DataFrame, w: int, partitioner: Partitioner, completeness: str = "exact", scope: str = "partition", mapper: str = "mapper_id", cols: tuple[str, ...] = ("id",), engine: str = "frame") -> DataFrame:
    """One wide pass: the last w - 1 rows before a partition are copied in front of it; a pair counts where its right row is no copy.

    Exact completeness takes each partition's last w - 1 rows (a partial limit before the shuffle) and ranks them from the offsets, so
    the rows as a whole are moved and sorted once.
    """
    extra = [mapper] if completeness != "exact" and scope == "map" else []
    tagged = layout.tag(entities.select(*dict.fromkeys(("id", "k", *cols, *extra))), partitioner)
    if completeness == "exact":
        offsets = layout.offsets_of(entities, partitioner)
        top = F.row_number().over(Window.partitionBy("p").orderBy(F.col("k").desc(), F.col("id").desc()))
        tails = tagged.withColumn("rn_desc", top).where(F.col("rn_desc") <= w - 1).join(F.broadcast(offsets), "p")
        tails = tails.withColumn("g", F.col("off") + F.col("rows") - F.col("rn_desc") + 1)
        copies = _near_seams(tails, offsets, w, 0).select(*tagged.columns, F.col("seam").alias("target"))
    else:
        copies = replica_rows(entities, w, partitioner, scope, mapper).select(*tagged.columns, "target")
        if scope == "map":  # of what the map tasks sent, the greatest w - 1
            top = F.row_number().over(Window.partitionBy("target").orderBy(F.col("k").desc(), F.col("id").desc()))
            copies = copies.withColumn("n", top).where(F.col("n") <= w - 1).drop("n")
    both = tagged.withColumn("target", F.col("p")).withColumn("is_copy", F.lit(False)).unionByName(copies.withColumn("is_copy", F.lit(True)))
    placed = both.repartitionById(partitioner.parts, F.col("target"))
    some = (*dict.fromkeys((*cols, "is_copy")),)
    if engine == "bucket":
        rank = F.row_number().over(Window.partitionBy("target").orderBy("k", "id"))
        got = pairs.bucket(placed.withColumn("g", rank), w, some, group="target")
    else:
        got = pairs.frame(placed, w, group="target", order=("k", "id"), cols=some)
    return got.where("not right_is_copy").drop("left_is_copy", "right_is_copy")


def rank_bucket_pairs(entities: DataFrame, w: int, parts: int = 10, cols: tuple[str, ...] = ("id",)) -> DataFrame:
    """Ranges cut inside heavy keys, global ranks, and the bucket join: even work whatever the keys."""
    return pairs.bucket(layout.ordered_by_range(entities, parts), w, cols)


def multipass_pairs(entities: DataFrame, keys: list[Column], w: int, parts: int = 10) -> DataFrame:
    """The window method once per key; a pair found several times counts once. Pairs are (least id, greatest id)."""
    from .partitioners import balanced_partitioner

    found = None
    for key in keys:
        one = entities.withColumn("k", key)
        got = stitch_pairs(one, w, balanced_partitioner(one, parts)).select("left_id", "right_id")
        found = got if found is None else found.unionByName(got)
    return unordered_distinct(found)


def unordered_distinct(found: DataFrame) -> DataFrame:
    return found.select(F.least("left_id", "right_id").alias("left_id"), F.greatest("left_id", "right_id").alias("right_id")).dropDuplicates()


def link_pairs(one: DataFrame, other: DataFrame, w: int, parts: int = 10) -> DataFrame:
    """Windows over two sources together; only pairs across the sources count. Output: id of the first, id of the second."""
    from .partitioners import balanced_partitioner

    both = one.select("id", "k", F.lit(0).alias("src")).unionByName(other.select("id", "k", F.lit(1).alias("src")))
    # ids of two sources may clash: order by (k, id) with the source folded into the id
    both = both.withColumn("id", F.struct("id", "src"))
    got = stitch_pairs(both, w, balanced_partitioner(both, parts)).where("left_id.src <> right_id.src")
    first = F.when(F.col("left_id.src") == 0, F.col("left_id.id")).otherwise(F.col("right_id.id"))
    second = F.when(F.col("left_id.src") == 1, F.col("left_id.id")).otherwise(F.col("right_id.id"))
    return got.select(first.alias("left_id"), second.alias("right_id"), "distance")


def cross_pairs(entities: DataFrame, tile: int | None = None) -> DataFrame:
    """All pairs: the baseline without blocking, by lists of ``tile`` ids that meet the ids, so that no task holds or sends all rows."""
    return pairs.all_of(entities, tile)


def block_pairs(entities: DataFrame, tile: int | None = None) -> DataFrame:
    """Standard blocking: all pairs of equal key, a big block's by pairs of its tiles. With ``tile``, tiles are runs of so many ids."""
    if tile is None:
        return pairs.unordered(pairs.spread(known := entities.where("k is not null").select("k", "id"), known, "k", same=True))
    t = F.floor((F.row_number().over(Window.partitionBy("k").orderBy("id")) - 1) / tile)
    tiled = entities.withColumn("t", t)
    last = tiled.groupBy("k").agg(F.max("t").alias("last"))
    left = tiled.join(last, "k").select("k", F.col("id").alias("left_id"), F.col("t").alias("a"), F.explode(F.sequence("t", "last")).alias("b"))
    right = tiled.join(last, "k").select("k", F.col("id").alias("right_id"), F.col("t").alias("b"), F.explode(F.sequence(F.lit(0).cast("long"), "t")).alias("a"))
    return left.join(right, ["k", "a", "b"]).where("left_id < right_id").select("left_id", "right_id")


def exploded_rows(entities: DataFrame, w: int) -> DataFrame:
    """Every row once per window it lies in, with the window's first rank (the design that was turned down)."""
    ranked = layout.ordered_by_range(entities, 8)
    n = F.lit(ranked.count())
    first, last = F.greatest(F.lit(1).cast("long"), F.col("g") - (w - 1)), F.least(F.col("g"), F.greatest(F.lit(1).cast("long"), n - w + 1))
    return ranked.select("id", "g", F.explode(F.sequence(first, last)).alias("window"))


def exploded_raw_pairs(rows: DataFrame) -> DataFrame:
    a = rows.select("window", F.col("id").alias("left_id"), F.col("g").alias("lg"))
    b = rows.select("window", F.col("id").alias("right_id"), F.col("g").alias("rg"))
    return a.join(b, "window").where("lg < rg").select("left_id", "right_id", (F.col("rg") - F.col("lg")).alias("distance"))


def exploded_window_pairs(entities: DataFrame, w: int) -> DataFrame:
    return exploded_raw_pairs(exploded_rows(entities, w)).dropDuplicates()


def term_counts(texts: DataFrame, text_col: str = "text") -> DataFrame:
    """(term, n) of white-space separated terms, summed before and after the shuffle."""
    return texts.select(F.explode(F.split(F.coalesce(F.col(text_col), F.lit("")), " ")).alias("term")).where("term <> ''").groupBy("term").agg(F.count("*").alias("n"))
