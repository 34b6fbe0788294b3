"""Workloads of the timings: methods over cores, and partitioners of growing skew, with matching."""

from __future__ import annotations

import os
import time

from pyspark.sql import DataFrame, SparkSession, functions as F

from ..functions.matching import TitleAbstract
from ..operators import measures, partitioners as parts
from ..sources import tables
from .resolve import SnConfig, resolve

EARLY, LATE = ("title_ascii",), ("abstract",)
#: Shares of rows in the last of eight even partitions.
SHARES = (40, 55, 70, 85)


def matches(entities: DataFrame, config: SnConfig) -> DataFrame:
    return resolve(entities, config, TitleAbstract(), EARLY, LATE)


def timed(entities: DataFrame, config: SnConfig) -> float:
    return round(measures.time_method(lambda: matches(entities, config)), 3)


def rows_of(spark: SparkSession, folder: str, sliced: bool) -> DataFrame:
    """Publications of all documents, or one of each slice of their texts: more rows where windows are small. Abstracts have at most 500 characters."""
    if sliced:
        return tables.slices(spark, folder)
    return tables.publications(spark, folder, features=True).select("id", "k", "title_ascii", F.substring("abstract", 1, 500).alias("abstract"))


def over_cores(spark: SparkSession, folder: str, event_log: str | None = None, full: bool = True) -> dict[str, dict]:
    """Seconds of both completion methods at w = 10 (slices) and w = 1000 (documents), ten hand-balanced blocks; and what each shuffled.

    Without ``full`` only replication runs at w = 1000.
    """
    out: dict[str, dict] = {"seconds": {}, "rows": {}, "shuffle_mb": {}}
    for w, sliced in ((10, True), (1000, False)):
        e = rows_of(spark, folder, sliced)
        n = e.count()
        block = parts.balanced_partitioner(e, 10)
        for method in ("stitch", "replica") if full or w == 10 else ("replica",):
            since = time.time()
            out["seconds"][f"{method}_w{w}"] = timed(e, SnConfig(w=w, method=method, partitioner=block))
            out["rows"][f"{method}_w{w}"] = n
            if event_log:
                time.sleep(1)
                report = measures.shuffle_report(spark, os.path.join(event_log, "*"), since, time.time()).first()
                out["shuffle_mb"][f"{method}_w{w}"] = round((report.shuffle_bytes or 0) / 1e6, 1)
    return out


def skewed(entities: DataFrame, share: int) -> tuple[DataFrame, parts.Partitioner]:
    even = parts.even_partitioner(8)
    return (parts.skew_last(entities, even, share / 100) if share else entities), even


def over_skew(spark: SparkSession, folder: str) -> dict[str, dict]:
    """Gini and seconds of replication, w = 100, for seven partitioners; rank buckets on the most skewed keys; even8 against even8_85 at three windows."""
    e = rows_of(spark, folder, False).cache()
    e.count()
    cases = {"balanced": (e, parts.balanced_partitioner(e, 10)), "even10": (e, parts.even_partitioner(10)), "even8": skewed(e, 0)} | {f"even8_{s}": skewed(e, s) for s in SHARES}
    gini = {n: round(measures.gini(measures.sizes_of(x, p), p.parts).first()[0], 3) for n, (x, p) in cases.items()}
    run = lambda n, w, method="replica": timed(cases[n][0], SnConfig(w=w, method=method, r=8, partitioner=cases[n][1]))
    seconds = {n: run(n, 100) for n in cases}
    seconds["rank_bucket_on_even8_85"] = run("even8_85", 100, "rank_bucket")
    windows = {f"w{w}": {n: seconds[n] if w == 100 else run(n, w) for n in ("even8", "even8_85")} for w in (10, 100, 1000)}
    e.unpersist()
    return {"gini": gini, "seconds_w100": seconds, "windows": windows, "penalty_w100": round(seconds["even8_85"] / seconds["balanced"], 2)}
