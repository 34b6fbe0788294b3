"""Cost and accuracy measures."""

from __future__ import annotations

import time
from collections.abc import Callable

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window, functions as F

from ..functions import matching
from . import layout, methods
from .partitioners import Partitioner


def pair_count(n: int, w: int, closed: bool = False) -> float:
    """Comparisons of a window run; the closed form holds for n >= w - 1 only."""
    return (n - w / 2) * (w - 1) if closed else sum(max(0, n - d) for d in range(1, w))


def count_pairs(found: DataFrame) -> DataFrame:
    return found.agg(F.count("*").alias("pairs"))


def missed_pairs(sizes: list[int], w: int, closed: bool = False) -> float:
    """Pairs that local windows miss; the closed form needs partitions of w - 1 rows at least."""
    if closed:
        return (len(sizes) - 1) * w * (w - 1) / 2
    return pair_count(sum(sizes), w) - sum(pair_count(n, w) for n in sizes)


def boundary_volume(entities: DataFrame, w: int, partitioner: Partitioner) -> DataFrame:
    """(rows, bound): what the second job reads, and 2 (r - 1) (w - 1)."""
    rows = methods.boundary_rows(*layout.persist_layout(entities, partitioner), w)
    return rows.agg(F.count("*").alias("rows")).withColumn("bound", F.lit(2 * (partitioner.parts - 1) * (w - 1)).cast("long"))


def replica_bound(m: int, r: int, w: int) -> int:
    return m * (r - 1) * (w - 1)


def replica_volume(entities: DataFrame, w: int, partitioner: Partitioner, m: int) -> DataFrame:
    """(copies, bound) of the one-pass method with copies chosen in m map tasks."""
    copies = methods.replica_rows(entities, w, partitioner, "map")
    return copies.agg(F.count("*").alias("copies")).withColumn("bound", F.lit(replica_bound(m, partitioner.parts, w)).cast("long"))


def gini(sizes: DataFrame, parts: int) -> DataFrame:
    """Gini coefficient of (p, rows); partitions of 0..parts-1 without rows count as zero. At most (parts - 1) / parts."""
    every = sizes.sparkSession.range(parts).select(F.col("id").cast("int").alias("p"))
    full = every.join(F.broadcast(sizes), "p", "left").select(F.coalesce("rows", F.lit(0)).alias("y"), "p")
    ranked = full.withColumn("i", F.row_number().over(Window.partitionBy(F.lit(0)).orderBy("y", "p")))
    total = ranked.agg(F.sum(F.col("i") * F.col("y")).cast("double").alias("a"), F.sum("y").cast("double").alias("b"))
    return total.select(F.round(F.try_divide(2 * F.col("a"), parts * F.col("b")) - (parts + 1) / F.lit(parts), 6).alias("gini"))


def gini_by_udaf(sizes: DataFrame, parts: int) -> DataFrame:
    """The same by a pandas aggregate function; all sizes meet in one task, so it is for comparison only."""

    @F.pandas_udf("double")
    def coefficient(y: pd.Series) -> float:
        y = y.sort_values().to_numpy("float64")
        return float(2 * (range(1, len(y) + 1) * y).sum() / (len(y) * y.sum()) - (len(y) + 1) / len(y)) if y.sum() else None

    every = sizes.sparkSession.range(parts).select(F.col("id").cast("int").alias("p"))
    return every.join(F.broadcast(sizes), "p", "left").agg(F.round(coefficient(F.coalesce("rows", F.lit(0)).cast("double")), 6).alias("gini"))


def partition_profile(sizes: DataFrame) -> DataFrame:
    last = F.max_by("rows", "p")
    return sizes.agg(F.count("*").alias("partitions"), F.sum("rows").alias("rows"), F.max("rows").alias("largest"), F.round(F.max("rows") / F.sum("rows"), 6).alias("largest_share"), F.round(last / F.sum("rows"), 6).alias("last_share"))


def sizes_of(entities: DataFrame, partitioner: Partitioner) -> DataFrame:
    return layout.tag(entities, partitioner).groupBy("p").agg(F.count("*").alias("rows"))


def matcher_savings(found: DataFrame, w1: float = 0.5, w2: float = 0.5, least: float = 0.75) -> DataFrame:
    """Pairs, those that need the second matcher, and those spared it."""
    s1 = matching.edit_similarity(F.col("left_title_ascii"), F.col("right_title_ascii"))
    need = s1 * w1 + w2 >= least
    return found.agg(F.count("*").alias("pairs"), F.count_if(need).alias("second_runs"), F.count_if(~need).alias("skipped"))


def selectivity(matches: DataFrame, candidates: DataFrame) -> DataFrame:
    a, b = matches.agg(F.count("*").alias("matches")), candidates.agg(F.count("*").alias("candidates"))
    return a.crossJoin(b).withColumn("ratio", F.round(F.try_divide(F.col("matches"), F.col("candidates")), 6))


def explosion_report(entities: DataFrame, w: int) -> DataFrame:
    """Rows, raw pairs and distinct pairs of the exploded design."""
    rows = methods.exploded_rows(entities, w)
    raw = methods.exploded_raw_pairs(rows)
    a = rows.agg(F.count("*").alias("rows"))
    b = raw.groupBy("left_id", "right_id").agg(F.count("*").alias("n")).agg(F.sum("n").alias("raw_pairs"), F.count("*").alias("distinct_pairs"))
    return a.crossJoin(b)


def buffer_need(entities: DataFrame, w: int) -> DataFrame:
    """Rows that a task must hold: the largest block, against w - 1."""
    return entities.groupBy("k").agg(F.count("*").alias("n")).agg(F.max("n").alias("block_rows")).withColumn("window_rows", F.lit(w - 1).cast("long"))


def same_pairs(one: DataFrame, other: DataFrame) -> DataFrame:
    """(only_left, only_right, both), counted as multisets of (left_id, right_id)."""
    tag = lambda d, a, b: d.select("left_id", "right_id", F.lit(a).alias("a"), F.lit(b).alias("b"))
    each = tag(one, 1, 0).unionByName(tag(other, 0, 1)).groupBy("left_id", "right_id").agg(F.sum("a").alias("a"), F.sum("b").alias("b"))
    zero = F.lit(0).cast("long")
    return each.agg(F.coalesce(F.sum(F.greatest(zero, F.col("a") - F.col("b"))), zero).alias("only_left"), F.coalesce(F.sum(F.greatest(zero, F.col("b") - F.col("a"))), zero).alias("only_right"), F.coalesce(F.sum(F.least("a", "b")), zero).alias("both"))


def exact_copies(entities: DataFrame, col: str = "text") -> DataFrame:
    """Pairs of rows with equal values: the truth of pair completeness."""
    key = F.sha2(F.coalesce(F.col(col), F.lit("")).cast("binary"), 256)
    return methods.block_pairs(entities.select(key.alias("k"), "id"))


def pair_completeness(found: DataFrame, truth: DataFrame) -> DataFrame:
    """(found, existing) true pairs."""
    hit = truth.join(methods.unordered_distinct(found), ["left_id", "right_id"], "left_semi")
    return hit.agg(F.count("*").alias("found")).crossJoin(truth.agg(F.count("*").alias("existing")))


def reduction_ratio(n: int) -> Column:
    """An aggregate over pairs of n rows: the share of all pairs that needn't be compared."""
    return F.lit(1.0) - F.count("*") / F.lit(max(1.0, n * (n - 1) / 2))


def time_method(run: Callable[[], DataFrame]) -> float:
    """Seconds to make all rows of a method's result, without a sink's cost."""
    began = time.perf_counter()
    run().write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


def speedup(seconds: dict[int, float]) -> dict[int, float]:
    """By cores: time on the fewest cores over time."""
    base = seconds[min(seconds)]
    return {c: base / s for c, s in sorted(seconds.items())}


def shuffle_report(spark: SparkSession, event_log: str, since: float | None = None, until: float | None = None) -> DataFrame:
    """Shuffled and spilled bytes of all tasks in an event log, or of those that ended between two times (seconds)."""
    task = "Event string, `Task Info` struct<`Finish Time`: long>, `Task Metrics` struct<`Shuffle Write Metrics`: struct<`Shuffle Bytes Written`: long>, `Disk Bytes Spilled`: long>"
    events = spark.read.schema(task).json(event_log).where("Event = 'SparkListenerTaskEnd'")
    at, m = F.col("Task Info")["Finish Time"], F.col("Task Metrics")
    if since is not None:
        events = events.where(at >= F.lit(int(since * 1000)))
    if until is not None:
        events = events.where(at <= F.lit(int(until * 1000)))
    return events.agg(F.sum(m["Shuffle Write Metrics"]["Shuffle Bytes Written"]).alias("shuffle_bytes"), F.sum(m["Disk Bytes Spilled"]).alias("spill_bytes"))
