"""Non-decreasing functions from blocking key to partition number (from 0)."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window, functions as F

from ..plans.durable import cut

#: Different keys up to which the driver sums the histogram; beyond it, key ranges are summed where they lie.
MAX_HISTOGRAM = 100_000
#: Cuts up to which a partition number is a sum of comparisons, which compiles better than a function over an array.
FEW_CUTS = 100


@dataclass(frozen=True)
class Partitioner:
    """``column`` maps the key column to a partition; ``parts`` is the number of partitions."""

    parts: int
    column: Callable[[Column], Column]


def cut_partitioner(cuts: list, side: str = "right") -> Partitioner:
    """Number of cuts below the key; side "left" counts a cut equal to the key too."""
    reached = (lambda c, k: c < k) if side == "right" else (lambda c, k: c <= k)

    def column(k: Column) -> Column:
        if len(cuts) > FEW_CUTS:
            return F.size(F.filter(F.array(*map(F.lit, cuts)), lambda c: reached(c, k)))
        total = F.lit(0)
        for c in cuts:
            total = total + F.when(reached(F.lit(c), k), 1).otherwise(0)
        return total

    return Partitioner(len(cuts) + 1, column)


def key_histogram(entities: DataFrame) -> DataFrame:
    return entities.groupBy("k").agg(F.count("*").alias("rows"))


def balanced_partitioner(entities: DataFrame, r: int = 10, near: int = MAX_HISTOGRAM) -> Partitioner:
    """Near-equal blocks of whole keys: a key goes where the middle of its rows lies. A key stays whole however heavy it is (see layout.composite_range)."""
    hist = key_histogram(entities)
    some = hist.limit(near + 1).agg(F.collect_list(F.struct("k", "rows")).alias("all")).first()["all"]
    if len(some) <= near:
        some = sorted(some, key=lambda x: (x.k is not None, x.k))
        n, below, firsts = sum(x.rows for x in some), 0, {}
        for x in some:
            firsts.setdefault((2 * below + x.rows) * r // (2 * n), x.k)
            below += x.rows
    else:
        firsts = _far_firsts(hist, r)
    cuts = []
    for i in range(1, r):
        later = [k for p, k in sorted(firsts.items()) if p >= i]
        if later:
            cuts.append(later[0])
    own = cut_partitioner(cuts, side="left")
    return Partitioner(r, own.column)


def _far_firsts(hist: DataFrame, r: int) -> dict:
    """First key of each block, from prefix sums inside key ranges and one sum a range on the driver."""
    ranged = cut(hist.repartitionByRange("k").withColumn("part", F.spark_partition_id()))
    sums = sorted(ranged.groupBy("part").agg(F.sum("rows").alias("rows")).collect())
    offsets, n = [], 0
    for x in sums:
        offsets.append((x.part, n))
        n += x.rows
    before = Window.partitionBy("part").orderBy("k").rowsBetween(Window.unboundedPreceding, -1)
    table = hist.sparkSession.createDataFrame(offsets, "part int, off long")
    placed = ranged.join(F.broadcast(table), "part").select("k", "rows", (F.col("off") + F.coalesce(F.sum("rows").over(before), F.lit(0))).alias("below"))
    p = F.floor((2 * F.col("below") + F.col("rows")) * r / F.lit(2 * n))
    return {x.p: x.k for x in placed.select("k", p.alias("p")).groupBy("p").agg(F.min("k").alias("k")).collect()}


def key_ordinal(k: Column) -> Column:
    """Place of the first two characters in a key space of 28 x 28, letters being 1..26; beyond letters the second does not count."""
    clamp = lambda c: F.greatest(F.lit(0), F.least(F.lit(27), F.ascii(c) - 96))
    first, second = clamp(F.substring(k, 1, 1)), clamp(F.substring(k, 2, 1))
    return first * 28 + F.when(first.between(1, 26), second).otherwise(0)


def even_partitioner(parts: int) -> Partitioner:
    """Equal intervals of the key space from 'a' to 'z'."""
    return Partitioner(parts, lambda k: F.greatest(F.lit(0), F.least(F.lit(parts - 1), F.floor((key_ordinal(k) - 28) * parts / F.lit(728)).cast("int"))))


def skew_last(entities: DataFrame, partitioner: Partitioner, share: float) -> DataFrame:
    """Keys of a hashed subset moved to 'zz', so that about ``share`` of the rows fall in the last partition."""
    p = partitioner.column(F.col("k"))
    last, n = entities.agg(F.count_if(p == partitioner.parts - 1), F.count("*")).first()
    natural = last / n if n else 0.0
    limit = max(0, int(10_000 * (share - natural) / (1 - natural))) if natural < 1 else 0
    moved = (p < partitioner.parts - 1) & (F.pmod(F.pmod(F.col("id"), F.lit(1_000_000_007)) * 7919, F.lit(10_000)) < limit)
    return entities.withColumn("k", F.when(moved, F.lit("zz")).otherwise(F.col("k")))


def halves() -> Partitioner:
    """Words up to m, and the others."""
    return cut_partitioner(["n"], side="left")


def monotone(entities: DataFrame) -> DataFrame:
    """(p, low, high, ok): does every partition end at or before the next one's first key?"""
    each = entities.groupBy("p").agg(F.min("k").alias("low"), F.max("k").alias("high"))
    before = F.lag("high").over(Window.partitionBy(F.lit(0)).orderBy("p"))
    return each.withColumn("ok", F.coalesce(before <= F.col("low"), F.lit(True)))


def assert_monotone(entities: DataFrame) -> None:
    if not monotone(entities).where("not ok").isEmpty():
        raise AssertionError("partition numbers do not follow the key order")
