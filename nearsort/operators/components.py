"""Clusters of matches: connected components by alternating stars."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from ..plans.durable import cut


def clusters(matches: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(id, cluster) of every entity in a match; cluster is the least id. Every round is cut from its lineage."""
    pairs = matches.select(F.greatest("left_id", "right_id").alias("u"), F.least("left_id", "right_id").alias("v")).where("u != v").distinct()
    pairs, before = cut(pairs), None
    for _ in range(max_rounds):
        if pairs.isEmpty():
            break
        both = pairs.unionByName(pairs.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
        outer = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u != v").distinct()
        low = outer.groupBy("u").agg(F.min("v").alias("m"))
        inner = outer.join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        pairs = cut(inner.unionByName(low.select("u", F.col("m").alias("v"))).where("u != v").distinct())
        state = pairs.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if state == before:
            break
        before = state
    else:
        raise RuntimeError("clusters did not settle")
    return pairs.select(F.col("u").alias("id"), F.col("v").alias("cluster")).unionByName(pairs.select(F.col("v").alias("id"), F.col("v").alias("cluster"))).distinct()
