"""SQL users' way in: views, and a table function that slides over sorted partitions."""

from __future__ import annotations

from collections import deque

from pyspark.sql import SparkSession, functions as F

from ..sources import tables


@F.udtf(returnType="left_id bigint, right_id bigint, distance bigint")
class SlidingPairs:
    """sliding_pairs(TABLE(t) PARTITION BY (p) ORDER BY (k, id), w): rows need a column id."""

    def __init__(self) -> None:
        self.last: deque | None = None

    def eval(self, row, w: int):  # noqa: ANN001
        if self.last is None:
            self.last = deque(maxlen=w - 1)
        n = len(self.last)
        for k, old in enumerate(self.last):
            yield old, row["id"], n - k
        self.last.append(row["id"])


def register(spark: SparkSession, folder: str | None = None) -> None:
    """Register the table function, and the given tables as views."""
    spark.udtf.register("sliding_pairs", SlidingPairs)
    for name in tables.SCHEMAS if folder else ():
        spark.read.parquet(f"{folder}/{name}.parquet").createOrReplaceTempView(name)
