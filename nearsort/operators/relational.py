"""Operators that users of the methods need around them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, functions as F

from . import pairs


def with_key(entities: DataFrame, key: Column) -> DataFrame:
    return entities.withColumn("k", key)


def in_languages(docs: DataFrame, langs: list[str]) -> DataFrame:
    return docs.where(F.col("lang").isin(langs))


def min_length(docs: DataFrame, chars: int) -> DataFrame:
    return docs.where(F.col("n_chars") >= chars)


def same_key_join(entities: DataFrame, hint: str = "merge") -> DataFrame:
    """Pairs of equal key, null keys among them, by the kind of join that ``hint`` names; a heavy key's by pairs of its tiles."""
    rows = entities.select("k", "id")
    return pairs.unordered(pairs.spread(rows, rows, "k", same=True, hint=hint))


def attach_nation(rows: DataFrame, nation: DataFrame, key: str) -> DataFrame:
    """Nations are a fixed list of 25."""
    return rows.join(F.broadcast(nation.select(F.col("n_nationkey").alias(key), "n_name")), key)


def band_join(left: DataFrame, right: DataFrame, col: str, width: float) -> DataFrame:
    """left_id, right_id with |left - right| <= width, by pairs of tiles of near values, whatever bucket is heavy."""
    x = left.select("id", F.col(col).alias("v"))
    return pairs.band(x, x if right is left else right.select("id", F.col(col).alias("v")), width)


def events_within(a: DataFrame, b: DataFrame, interval: str = "10 minutes") -> DataFrame:
    """(left_id, right_id): events of b at most ``interval`` after one of a, of the same user."""
    x = a.select("user_id", F.col("event_id").alias("left_id"), F.col("ts").alias("t1"))
    y = b.select("user_id", F.col("event_id").alias("right_id"), F.col("ts").alias("t2"))
    return x.join(y, "user_id").where(f"t2 > t1 and t2 <= t1 + interval {interval}").select("left_id", "right_id")


def previous_event(a: DataFrame, b: DataFrame) -> DataFrame:
    """As-of join: for each event of a the last event of b of the same user at or before it (ties: greatest id)."""
    both = a.select("user_id", "ts", "event_id", F.lit(1).alias("side")).unionByName(b.select("user_id", "ts", "event_id", F.lit(0).alias("side")))
    w = Window.partitionBy("user_id").orderBy("ts", "side", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    last = F.last(F.when(F.col("side") == 0, F.col("event_id")), ignorenulls=True).over(w)
    return both.withColumn("previous_id", last).where("side = 1").select("event_id", "previous_id")


def has_partner(entities: DataFrame, found: DataFrame) -> DataFrame:
    ids = found.select(F.explode(F.array("left_id", "right_id")).alias("id"))
    return entities.join(ids, "id", "left_semi")


def singletons(entities: DataFrame, found: DataFrame) -> DataFrame:
    ids = found.select(F.explode(F.array("left_id", "right_id")).alias("id"))
    return entities.join(ids, "id", "left_anti")


def pair_diff(one: DataFrame, other: DataFrame) -> DataFrame:
    a = one.select("left_id", "right_id", F.lit(True).alias("a"))
    b = other.select("left_id", "right_id", F.lit(True).alias("b"))
    both = a.join(b, ["left_id", "right_id"], "full_outer")
    return both.where("a is null or b is null").select("left_id", "right_id", F.when(F.col("a").isNull(), "right").otherwise("left").alias("only_in"))


def enrich_pairs(found: DataFrame, entities: DataFrame, cols: list[str]) -> DataFrame:
    for side in ("left", "right"):
        found = found.join(entities.select(F.col("id").alias(f"{side}_id"), *(F.col(c).alias(f"{side}_{c}") for c in cols)), f"{side}_id")
    return found


def block_members(entities: DataFrame) -> DataFrame:
    """Blocks as sorted id lists; a block is in one row, so for small blocks only."""
    return entities.groupBy("k").agg(F.sort_array(F.collect_list("id")).alias("ids"))


def distinct_keys(entities: DataFrame) -> DataFrame:
    return entities.agg(F.count_distinct("k").alias("keys"))


def approx_distinct_keys(entities: DataFrame, rsd: float = 0.05) -> DataFrame:
    return entities.agg(F.approx_count_distinct("k", rsd).alias("keys"))


def block_cube(docs: DataFrame) -> DataFrame:
    return docs.cube("lang", "source").agg(F.count("*").alias("n"))


def partition_rollup(docs: DataFrame) -> DataFrame:
    return docs.rollup("lang", "source").agg(F.count("*").alias("n"))


def matches_by_language(matches: DataFrame, docs: DataFrame, langs: list[str]) -> DataFrame:
    left = docs.select(F.col("doc_id").alias("left_id"), F.col("lang").alias("left_lang"))
    right = docs.select(F.col("doc_id").alias("right_id"), F.col("lang").alias("right_lang"))
    return matches.join(left, "left_id").join(right, "right_id").groupBy("left_lang").pivot("right_lang", langs).agg(F.count(F.lit(1))).na.fill(0)


def block_size_quantiles(entities: DataFrame) -> DataFrame:
    sizes = entities.groupBy("k").agg(F.count("*").alias("n"))
    return sizes.agg(F.percentile("n", F.array(F.lit(0.5), F.lit(0.9), F.lit(0.99))).alias("q")).select(*(F.col("q")[i].alias(f"q{n}") for i, n in enumerate((50, 90, 99))))


def cut_points(entities: DataFrame, col: str, r: int) -> DataFrame:
    return entities.agg(F.percentile_approx(col, [i / r for i in range(1, r)], 10_000).alias("cuts"))


def best_matches(matches: DataFrame, k: int) -> DataFrame:
    w = Window.partitionBy("left_id").orderBy(F.col("score").desc(), "right_id")
    return matches.withColumn("n", F.row_number().over(w)).where(F.col("n") <= k).drop("n")


def heaviest_blocks(entities: DataFrame, k: int) -> DataFrame:
    return entities.groupBy("k").agg(F.count("*").alias("n")).orderBy(F.col("n").desc(), "k").limit(k)


def ordered_pairs(matches: DataFrame) -> DataFrame:
    return matches.orderBy(F.col("score").desc(), "left_id", "right_id")


def pairs_union(one: DataFrame, other: DataFrame, all: bool = False) -> DataFrame:
    both = one.union(other)
    return both if all else both.distinct()


def pairs_intersect(one: DataFrame, other: DataFrame, all: bool = False) -> DataFrame:
    return one.intersectAll(other) if all else one.intersect(other)


def pairs_except(one: DataFrame, other: DataFrame, all: bool = False) -> DataFrame:
    return one.exceptAll(other) if all else one.subtract(other)


def neighbours(events: DataFrame) -> DataFrame:
    """Each event with the ones before and after it, and its user's first and last."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return events.select("event_id", F.lag("event_id").over(w).alias("before_id"), F.lead("event_id").over(w).alias("after_id"), F.first("event_id").over(whole).alias("first_id"), F.last("event_id").over(whole).alias("last_id"), F.nth_value("event_id", 2).over(whole).alias("second_id"))


def rankings(entities: DataFrame) -> DataFrame:
    w = Window.partitionBy("k").orderBy("v")
    total = Window.partitionBy("k").orderBy("v", "id")
    cols = {"rn": F.row_number().over(total), "rnk": F.rank().over(w), "dense": F.dense_rank().over(w), "quarter": F.ntile(4).over(total)}
    near = F.count("*").over(w.rangeBetween(-5, 5))
    return entities.select("id", "k", *(c.cast("long").alias(n) for n, c in cols.items()), F.round(F.percent_rank().over(w), 6).alias("share"), near.alias("near"))


def props_of(events: DataFrame) -> DataFrame:
    """One row per entry of the JSON properties."""
    return events.select("event_id", F.explode(F.from_json("props", "map<string,int>")).alias("name", "value"))


def term_map(docs: DataFrame) -> DataFrame:
    """Terms of at least two occurrences in each document, as a map."""
    terms = docs.select(F.col("doc_id"), F.explode(F.split("text", " ")).alias("term")).where("term <> ''").groupBy("doc_id", "term").agg(F.count("*").alias("n"))
    each = terms.groupBy("doc_id").agg(F.map_from_entries(F.collect_list(F.struct("term", "n"))).alias("terms"))
    return each.select("doc_id", F.map_filter("terms", lambda _, n: n > 1).alias("terms"))


def sample_keys(entities: DataFrame, fraction: float, seed: int = 7) -> DataFrame:
    return entities.select("k").sample(fraction=fraction, seed=seed)


def random_split(entities: DataFrame, weights: list[float], seed: int = 7) -> list[DataFrame]:
    return entities.randomSplit(weights, seed)
