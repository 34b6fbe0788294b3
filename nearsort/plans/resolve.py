"""Configuration, engine choice, and block-then-match plans."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame

from ..functions.matching import Matcher
from ..operators import methods
from ..operators.partitioners import Partitioner, balanced_partitioner
from ..operators.relational import enrich_pairs


@dataclass(frozen=True)
class SnConfig:
    """Defaults of a window run. method: sequential, local, stitch, replica, rank_bucket, blocks, cross or exploded. partitioner: balanced over r blocks if none."""

    w: int = 10
    r: int = 10
    method: str = "stitch"
    engine: str = "auto"
    completeness: str = "exact"
    partitioner: Partitioner | None = None

    def __post_init__(self) -> None:
        if self.w < 2 or self.r < 1:
            raise ValueError("w must be 2 or more, r 1 or more")
        if self.method not in METHODS:
            raise ValueError(f"no method {self.method}")


def choose_engine(config: SnConfig) -> str:
    """Lists per row for small windows, rank buckets beyond: a list copies each row w - 1 times, a bucket twice. The pairs are the same."""
    if config.engine != "auto":
        return config.engine
    return "frame" if config.w <= 20 else "bucket"


METHODS: dict[str, Callable[[DataFrame, SnConfig, tuple[str, ...]], DataFrame]] = {
    "sequential": lambda e, c, cols: methods.sequential_pairs(e, c.w, cols),
    "local": lambda e, c, cols: methods.local_pairs(e, c.w, c.partitioner or balanced_partitioner(e, c.r), cols, choose_engine(c)),
    "stitch": lambda e, c, cols: methods.stitch_pairs(e, c.w, c.partitioner or balanced_partitioner(e, c.r), c.completeness, cols, engine=choose_engine(c)),
    "replica": lambda e, c, cols: methods.replica_pairs(e, c.w, c.partitioner or balanced_partitioner(e, c.r), c.completeness, cols=cols, engine=choose_engine(c)),
    "rank_bucket": lambda e, c, cols: methods.rank_bucket_pairs(e, c.w, c.r, cols),
    "blocks": lambda e, c, cols: methods.block_pairs(e),
    "cross": lambda e, c, cols: methods.cross_pairs(e),
    "exploded": lambda e, c, cols: methods.exploded_window_pairs(e, c.w),
}
#: Methods whose pairs can carry attributes along.
CARRYING = ("sequential", "local", "stitch", "replica", "rank_bucket")


def candidates(entities: DataFrame, config: SnConfig, cols: tuple[str, ...] = ("id",)) -> DataFrame:
    return METHODS[config.method](entities, config, cols)


def resolve(entities: DataFrame, config: SnConfig, matcher: Matcher, early: tuple[str, ...], late: tuple[str, ...] = ()) -> DataFrame:
    """(left_id, right_id, score) of matching pairs.

    Early features ride along with the pairs, so they should be short; late ones are joined to the pairs that ``matcher.narrow`` leaves.
    """
    if config.method in CARRYING:
        found = candidates(entities.select("id", "k", *early), config, ("id", *early))
    else:
        found = enrich_pairs(candidates(entities.select("id", "k"), config).select("left_id", "right_id"), entities, list(early))
    if late:
        found = enrich_pairs(matcher.narrow(found), entities, list(late))
    return matcher(found).select("left_id", "right_id", "score")
