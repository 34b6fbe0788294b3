"""The ordered layout that all window methods share: p, rank in p, partition offsets, global rank.

The order is always (k, id): with ties broken, heads, tails and copies agree in every method.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F

from ..plans.durable import cut
from .partitioners import Partitioner


def tag(entities: DataFrame, partitioner: Partitioner) -> DataFrame:
    return entities.withColumn("p", partitioner.column(F.col("k")).cast("int"))


def place(tagged: DataFrame, parts: int) -> DataFrame:
    """One shuffle straight by partition number; windows over p need no other."""
    return tagged.repartitionById(parts, F.col("p"))


def rank_local(placed: DataFrame) -> DataFrame:
    return placed.withColumn("rn", F.row_number().over(Window.partitionBy("p").orderBy("k", "id")).cast("long"))


def partition_offsets(tagged: DataFrame) -> DataFrame:
    """(p, rows, off) of partitions with rows: as many rows as partitions, so one task sums them."""
    w = Window.partitionBy(F.lit(0)).orderBy("p").rowsBetween(Window.unboundedPreceding, -1)
    return tagged.groupBy("p").agg(F.count("*").alias("rows")).select("p", "rows", F.coalesce(F.sum("rows").over(w), F.lit(0)).alias("off"))


def rank_global(ranked: DataFrame, offsets: DataFrame) -> DataFrame:
    """g from 1, and the rank from the end of p."""
    return ranked.join(F.broadcast(offsets), "p").withColumns({"g": F.col("off") + F.col("rn"), "rn_desc": F.col("rows") - F.col("rn") + 1})


def known(offsets: DataFrame) -> DataFrame:
    """The offsets, one row a partition, held by the plan itself, so that nothing behind them is run again."""
    return offsets.sparkSession.createDataFrame(offsets.collect(), offsets.schema)


def offsets_of(entities: DataFrame, partitioner: Partitioner) -> DataFrame:
    """known() offsets from a scan of the keys alone."""
    return known(partition_offsets(tag(entities.select("k"), partitioner)))


def ordered(entities: DataFrame, partitioner: Partitioner, offsets: DataFrame | None = None) -> DataFrame:
    """Everything above: p, rn, rows, off, g, rn_desc. Plans that use it more than once share its one wide exchange."""
    placed = place(tag(entities, partitioner), partitioner.parts)
    return rank_global(rank_local(placed), offsets_of(entities, partitioner) if offsets is None else offsets)


def persist_layout(entities: DataFrame, partitioner: Partitioner) -> tuple[DataFrame, DataFrame]:
    """(ordered rows, offsets) with the ranked rows written to shared storage, for work that goes on over several jobs."""
    ranked = cut(rank_local(place(tag(entities, partitioner), partitioner.parts)))
    offsets = known(partition_offsets(ranked))
    return rank_global(ranked, offsets), offsets


def composite_range(entities: DataFrame, parts: int) -> DataFrame:
    """p from sampled ranges of (k, id), which may cut inside a heavy key; written once, as a sample taken again may cut elsewhere."""
    return cut(entities.repartitionByRange(parts, "k", "id").withColumn("p", F.spark_partition_id()))


def ordered_by_range(entities: DataFrame, parts: int) -> DataFrame:
    tagged = composite_range(entities, parts)
    return rank_global(rank_local(tagged), known(partition_offsets(tagged)))
