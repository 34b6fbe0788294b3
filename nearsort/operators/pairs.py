"""Engines that turn ordered rows into pairs at distance 1..w-1. Left is the earlier row."""

from __future__ import annotations

import math
from collections import deque
from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window, functions as F, types as T

from ..plans.durable import cut

#: Rows of a key's tile; pairs that a task is to make on average; most tasks, beyond which tasks grow.
TILE, TASK_PAIRS, MOST_TASKS = 4096, 25_000_000, 20_000
#: Rows of a list that is written once for each partner: so short that its repeats lie in one page of a file, where they compress.
LIST = 256


def _flat(rows: DataFrame, cols: list[str]) -> DataFrame:
    return rows.select(*(F.col(f"left.{c}").alias(f"left_{c}") for c in cols), *(F.col(f"right.{c}").alias(f"right_{c}") for c in cols), F.col("distance").cast("long").alias("distance"))


def _order(order: list[str]) -> list[Column]:
    return [F.col(c) for c in order]


def frame(rows: DataFrame, w: int, group: str = "p", order: tuple[str, ...] = ("k", "id"), cols: tuple[str, ...] = ("id",)) -> DataFrame:
    """The next w - 1 rows gathered by a window frame, then exploded."""
    whole = F.struct(*cols)
    ahead = F.collect_list(whole).over(Window.partitionBy(group).orderBy(*_order(list(order))).rowsBetween(1, w - 1))
    got = rows.select(whole.alias("left"), ahead.alias("ahead")).select("left", F.posexplode("ahead").alias("d", "right"))
    return _flat(got.withColumn("distance", F.col("d") + 1), list(cols))


def lag(rows: DataFrame, w: int, group: str = "p", order: tuple[str, ...] = ("k", "id"), cols: tuple[str, ...] = ("id",)) -> DataFrame:
    """One lead per distance; for small windows."""
    whole = F.struct(*cols)
    spec = Window.partitionBy(group).orderBy(*_order(list(order)))
    got = rows.select(whole.alias("left"), F.array(*(F.lead(whole, d).over(spec) for d in range(1, w))).alias("ahead")).select("left", F.posexplode("ahead").alias("d", "right"))
    return _flat(got.where("right is not null").withColumn("distance", F.col("d") + 1), list(cols))


def bucket(ranked: DataFrame, w: int, cols: tuple[str, ...] = ("id",), group: str | None = None) -> DataFrame:
    """Equi-join of rank buckets of w - 1 rows: a row meets its own and the next bucket, whatever the keys' skew."""
    size = w - 1
    b = F.floor((F.col("g") - 1) / size)
    extra = [group] if group else []
    left = ranked.select(F.struct(*cols).alias("left"), F.col("g").alias("lg"), *extra, F.explode(F.array(b, b + 1)).alias("b"))
    right = ranked.select(F.struct(*cols).alias("right"), F.col("g").alias("rg"), *extra, b.alias("b"))
    d = F.col("rg") - F.col("lg")
    return _flat(left.join(right, ["b", *extra]).where(d.between(1, size)).withColumn("distance", d), list(cols))


def _pair_schema(rows: DataFrame, cols: list[str]) -> T.StructType:
    fields = [T.StructField(f"{side}_{c}", rows.schema[c].dataType) for side in ("left", "right") for c in cols]
    return T.StructType([*fields, T.StructField("distance", T.LongType())])


def ring(rows: DataFrame, w: int, group: str = "p", order: tuple[str, ...] = ("k", "id"), cols: tuple[str, ...] = ("id",)) -> DataFrame:
    """A ring of the last w - 1 rows over sorted Arrow batches; rows must already lie by ``group``."""
    cols = list(cols)
    schema = _pair_schema(rows, cols)
    names = schema.names

    def slide(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, now = deque(maxlen=w - 1), None
        for b in batches:
            out: list[list] = [[] for _ in names]
            data = [b.column(k).to_pylist() for k in range(b.num_columns)]
            for values in zip(*data):
                if values[0] != now:
                    last.clear()
                    now = values[0]
                row = values[1:]
                for k, old in enumerate(last):
                    for o, v in zip(out, (*old, *row, len(last) - k)):
                        o.append(v)
                last.append(row)
                if len(out[0]) > 50_000:
                    yield pa.RecordBatch.from_arrays([pa.array(o, t.type) for o, t in zip(out, arrow)], names=names)
                    out = [[] for _ in names]
            yield pa.RecordBatch.from_arrays([pa.array(o, t.type) for o, t in zip(out, arrow)], names=names)

    from pyspark.sql.pandas.types import to_arrow_schema

    arrow = to_arrow_schema(schema)
    return rows.sortWithinPartitions(group, *order).select(group, *cols).mapInArrow(slide, schema)


def grouped(rows: DataFrame, w: int, group: str = "p", order: tuple[str, ...] = ("k", "id"), cols: tuple[str, ...] = ("id",)) -> DataFrame:
    """A whole partition in memory at once: for comparison only."""
    cols = list(cols)

    def all_in_group(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(list(order), kind="stable").reset_index(drop=True)
        parts = []
        for d in range(1, w):
            a, b = pdf[cols].iloc[: max(0, len(pdf) - d)].reset_index(drop=True), pdf[cols].iloc[d:].reset_index(drop=True)
            parts.append(pd.concat([a.add_prefix("left_"), b.add_prefix("right_")], axis=1).assign(distance=d))
        return pd.concat(parts)

    return rows.select(*dict.fromkeys([group, *order, *cols])).groupBy(group).applyInPandas(all_in_group, _pair_schema(rows, cols))


def spread(left: DataFrame, right: DataFrame, key: str, same: bool = False, tile: int | None = None, hint: str = "merge") -> DataFrame:
    """All pairs of rows (key, id, ...) of equal key, as columns left_ and right_; no key's pairs are the work of one task.

    Ids of a key that has more than ``tile`` rows are dealt to tiles by their hash, and pairs of tiles are joined: what is moved is the
    rows times half the tiles of their key, and no more. With ``same`` both sides are one table, and of a pair of its rows either of the two
    orders comes, but one only. A null key equals a null key.
    """
    tile = tile or TILE
    left = cut(left)
    right = left if same else cut(right)
    sizes = left.groupBy(key).agg(F.count("*").alias("m"))
    n = F.col("m") if same else F.col("n")
    if not same:
        other = right.groupBy(F.col(key).alias("__k")).agg(F.count("*").alias("n"))
        sizes = sizes.join(other, F.col(key).eqNullSafe(F.col("__k"))).drop("__k")
    sizes = cut(sizes)
    work = sizes.agg(F.sum(F.col("m").cast("double") * n)).first()[0] or 0.0
    tasks = max(left.sparkSession.sparkContext.defaultParallelism, min(MOST_TASKS, int(work / (1 + same) / TASK_PAIRS) + 1))
    tiles = lambda c: F.ceil(c / tile).cast("int")
    large = F.broadcast(sizes.where(F.greatest("m", n) > tile).select(F.col(key).alias("__k"), tiles(F.col("m")).alias("__m"), tiles(n).alias("__n")))
    one = F.lit(1)

    def side(rows: DataFrame, name: str, own: str, far: str, upward: bool) -> DataFrame:
        mine, most = F.coalesce(F.col(own), one), F.coalesce(F.col(far), one) - 1
        t = F.pmod(F.xxhash64("id"), mine).cast("int")
        rows = rows.join(large, F.col(key).eqNullSafe(F.col("__k")), "left").withColumn(f"{name}__t", t)
        t = F.col(f"{name}__t")
        met = F.sequence(t, most) if same and upward else F.sequence(F.lit(0), t) if same else F.sequence(F.lit(0), most)
        a, b = (t, F.col("__o")) if upward else (F.col("__o"), t)
        cols = [F.col(c).alias(f"{name}_{c}") for c in rows.columns if c not in (key, "__k", "__m", "__n", f"{name}__t")]
        rows = rows.withColumn("__o", F.explode(met)).select(F.struct(key).alias(f"{name}__h"), F.col(key).alias(f"{name}_{key}"), a.alias(f"{name}__a"), b.alias(f"{name}__b"), *cols)
        return rows.repartition(tasks, f"{name}__h", f"{name}__a", f"{name}__b")

    x, y = side(left, "left", "__m", "__n", True), side(right, "right", "__n", "__m", False)
    place = ["right__h", "right__a", "right__b"]
    others = [c for c in y.columns if c not in (*place, f"right_{key}")]
    tiled = y.groupBy(*place).agg(F.collect_list(F.struct(*others)).alias("__right"))  # a list is gone through faster than the rows of a join
    met = (F.col("left__h") == F.col("right__h")) & (F.col("left__a") == F.col("right__a")) & (F.col("left__b") == F.col("right__b"))  # structs of nulls are equal
    mine = [c for c in x.columns if c not in ("left__h", f"left_{key}")]
    got = x.join(tiled.hint(hint), met).select(F.col(f"left_{key}").alias(key), *mine, "right__b", F.explode("__right").alias("__x")).select(key, *mine, "right__b", "__x.*")
    got = got.where((F.col("left__a") < F.col("right__b")) | (F.col("left_id") < F.col("right_id"))) if same else got
    return got.drop("left__a", "left__b", "right__b")


def all_of(rows: DataFrame, size: int | None = None) -> DataFrame:
    """(left_id, right_id), the least first, of all pairs of different ids. Each task takes some lists of near ids and some ids, and reads both
    where they are kept: ids are moved in proportion to their number, no copies of them are.
    """
    ids = cut(rows.where("id is not null").select("id").repartitionByRange("id").sortWithinPartitions("id"))
    least, most = (math.sqrt(n) for n in (ids.sparkSession.sparkContext.defaultParallelism, MOST_TASKS))
    parts = math.ceil(max(least, min(most, ids.count() / math.sqrt(2 * TASK_PAIRS))))
    lists = ids.withColumn("n", F.expr(f"monotonically_increasing_id() div {size or LIST}")).groupBy("n").agg(F.sort_array(F.collect_list("id")).alias("ids"))
    lists = cut(lists.select("ids", F.element_at("ids", -1).alias("last")).repartition(parts))
    ids = cut(ids.select(F.col("id").alias("left_id")).repartition(parts))
    met = lists.hint("shuffle_replicate_nl").join(ids, F.col("left_id") < F.col("last"))
    return met.select("left_id", F.explode("ids").alias("right_id")).where("left_id < right_id")


def band(left: DataFrame, right: DataFrame, width: float) -> DataFrame:
    """(left_id, right_id) of rows (id, v) with |left v - right v| <= width, by pairs of tiles of near values; null, NaN and infinite values have no pair.

    A tile lies in one bucket of the width and is moved as a row of arrays, to those tiles only that its values reach.
    """
    bucket = lambda x: F.floor(x / F.lit(width))
    slack = width * (1 + 1e-9)  # a difference may be rounded down to the width

    def tiles(rows: DataFrame) -> DataFrame:
        rows = rows.where(F.col("v") - F.col("v") <= width).select("id", "v").repartitionByRange("v", "id").sortWithinPartitions("v", "id")
        rows = rows.withColumn("t", F.expr(f"monotonically_increasing_id() div {TILE}")).groupBy(bucket(F.col("v")).alias("b"), "t").agg(F.sort_array(F.collect_list(F.struct("v", "id"))).alias("x"))
        return cut(rows.select("b", "t", F.col("x.id").alias("ids"), F.col("x.v").alias("vs")))

    def side(tiled: DataFrame, name: str, arrays: bool) -> DataFrame:
        cols = ("b", "t", "ids", "vs") if arrays else ("b", "t", "lo", "hi", "n")
        if not arrays:
            tiled = tiled.withColumns({"lo": F.get("vs", F.lit(0)), "hi": F.element_at("vs", -1), "n": F.size("vs").cast("double")})
        return tiled.select(*(F.col(c).alias(f"{name}_{c}") for c in cols))

    x = tiles(left)
    y = x if right is left else tiles(right)
    a, b = side(x, "left", False), side(y, "right", False)
    a = a.withColumn("right_b", F.explode(F.sequence(bucket(F.col("left_lo") - slack), bucket(F.col("left_hi") + slack))))
    met = a.join(b, "right_b").where((F.col("right_lo") <= F.col("left_hi") + slack) & (F.col("right_hi") >= F.col("left_lo") - slack))
    place = ["left_b", "left_t", "right_b", "right_t"]
    met = cut(met.select(*place, (F.col("left_n") * F.col("right_n")).alias("n"), F.floor((F.col("right_n") - 1) / LIST).alias("last")))
    work = met.agg(F.sum("n")).first()[0] or 0.0
    tasks = max(met.sparkSession.sparkContext.defaultParallelism, min(MOST_TASKS, int(work / TASK_PAIRS) + 1))
    first = F.lit(0).cast("long")
    x, y = (met.drop("n").join(side(rows, name, True), [f"{name}_b", f"{name}_t"]).repartition(tasks, *place).withColumn("at", F.explode(F.sequence(first, "last"))) for rows, name in ((x, "left"), (y, "right")))
    # a tile's rows come once for each list of the other tile, list by list, so that a row of the join makes one list's pairs only
    x = x.select(*place, "at", "left_vs", F.posexplode("left_ids").alias("i", "left_id")).select(*place, "at", "left_id", F.get("left_vs", F.col("i")).alias("left_v"))
    start = (F.col("at") * LIST + 1).cast("int")
    y = y.select(*(F.col(c).alias(f"_{c}") for c in (*place, "at")), *(F.slice(c, start, F.lit(LIST)).alias(c) for c in ("right_ids", "right_vs")))
    same = F.col("at") - F.col("_at") == 0  # no key of the join, which would be dealt anew by it
    near = (F.get("right_vs", F.lit(0)) <= F.col("left_v") + slack) & (F.element_at("right_vs", -1) >= F.col("left_v") - slack)
    got = x.hint("merge").join(y, [*(F.col(c) == F.col(f"_{c}") for c in place), same, near])
    got = got.select("left_id", "left_v", "right_vs", F.posexplode("right_ids").alias("i", "right_id"))
    return got.where(F.abs(F.col("left_v") - F.get("right_vs", F.col("i"))) <= width).select("left_id", "right_id")


def unordered(found: DataFrame) -> DataFrame:
    """(least id, greatest id) of pairs of different ids."""
    return found.where("left_id <> right_id").select(F.least("left_id", "right_id").alias("left_id"), F.greatest("left_id", "right_id").alias("right_id"))
