"""Joins that keep a heavy key's rows where they are."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

#: A key is heavy if it has more than one in so many of all rows; so at most this many keys are.
SLOTS = 1000


def attach(rows: DataFrame, table: DataFrame, key: str | list[str], count: str, slots: int = SLOTS) -> DataFrame:
    """``rows`` joined with ``table``, which has one row for each key that is wanted and in ``count`` the rows that have it.

    Heavy keys, at most ``slots``, are broadcast, so that their rows are not brought together; all others are joined by a shuffle.
    ``table`` and ``rows`` should be cheap to read twice. Null keys match nothing.
    """
    total = table.agg(F.coalesce(F.sum(count), F.lit(0))).first()[0]
    heavy = table.where(F.col(count) * slots > F.lit(total)).drop(count)
    light = table.where(F.col(count) * slots <= F.lit(total)).drop(count)
    many = rows.join(F.broadcast(heavy), key)
    few = rows.join(F.broadcast(heavy.select(key)), key, "left_anti").join(light, key)
    return many.unionByName(few)
