"""Where pairs and layouts go."""

from __future__ import annotations

from pyspark.sql import DataFrame


def write_pairs(found: DataFrame, path: str, by: str | None = None) -> None:
    """Parquet, one folder per value of ``by`` if given; parts can be read together as one set."""
    writer = found.write.mode("overwrite").option("compression", "zstd")
    (writer.partitionBy(by) if by else writer).parquet(path)


def save_layout(ordered: DataFrame, table: str, buckets: int) -> None:
    """The ordered layout as a bucketed table, so that later jobs over p need no shuffle."""
    ordered.write.mode("overwrite").bucketBy(buckets, "p").sortBy("k", "id").saveAsTable(table)
