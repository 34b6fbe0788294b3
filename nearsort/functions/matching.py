"""Matchers: similarity columns over pair rows with left_ and right_ attributes."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass
from typing import Protocol

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, functions as F, types as T


def ascii_fold(c: Column) -> Column:
    return F.regexp_replace(c, r"[^\x00-\x7F]", "?")


def edit_similarity(a: Column, b: Column) -> Column:
    """1 - distance / longer length; two empty strings: 1; a null: 0."""
    n = F.greatest(F.char_length(a), F.char_length(b))
    return F.coalesce(F.when(n == 0, F.lit(1.0)).otherwise(F.lit(1.0) - F.levenshtein(a, b) / n), F.lit(0.0))


def bounded_edit(a: Column, b: Column, least: float) -> Column:
    """edit_similarity where it reaches ``least``, else 0; stops early at the distance that ``least`` allows."""
    n = F.greatest(F.char_length(a), F.char_length(b))
    bound = F.floor((1.0 - least) * n + 1e-9).cast("int")
    near = F.abs(F.char_length(a) - F.char_length(b)) <= bound
    d = F.call_function("levenshtein", a, b, bound)
    return F.coalesce(F.when(n == 0, F.lit(1.0)).when(near & (d >= 0), F.lit(1.0) - d / n).otherwise(F.lit(0.0)), F.lit(0.0))


#: Characters that one machine word has bits for.
_WORD = 64


def edit_distances(left: list[str], right: list[str]) -> np.ndarray:
    """Edit distances of pairs of texts, a column of the usual table at a time for all pairs: its steps up and down are the bits of two words.

    Texts of more than 64 characters are worked out one by one, with long numbers for words.
    """
    m, n = (np.fromiter(map(len, x), np.int64, len(x)) for x in (left, right))
    out = np.zeros(len(left), np.int64)
    for k in np.flatnonzero(np.maximum(m, n) > _WORD).tolist():
        out[k] = _long_distance(left[k], right[k])
    short = np.flatnonzero(np.maximum(m, n) <= _WORD)
    if not len(short):
        return out
    a, b = (np.array([x[k] for k in short.tolist()], dtype=f"<U{_WORD}").view(np.uint32).reshape(len(short), _WORD) for x in (left, right))
    m, n = m[short], n[short]
    one = np.uint64(1)
    last = np.left_shift(one, np.maximum(m - 1, 0).astype(np.uint64))
    up, down, score = np.full(len(short), ~np.uint64(0)), np.zeros(len(short), np.uint64), m.copy()
    for j in range(int(n.max())):
        equal = np.packbits(a == b[:, j : j + 1], axis=1, bitorder="little").view("<u8").ravel()
        straight = equal | down
        level = (((equal & up) + up) ^ up) | equal
        more, less = down | ~(level | up), up & level
        score += (j < n) * (((more & last) != 0).astype(np.int64) - ((less & last) != 0))
        more, less = more << one | one, less << one
        up, down = less | ~(straight | more), more & straight
    out[short] = np.where(m == 0, n, score)
    return out


def _long_distance(x: str, y: str) -> int:
    if not x:
        return len(y)
    places: dict[str, int] = {}
    for k, c in enumerate(x):
        places[c] = places.get(c, 0) | 1 << k
    whole, last = (1 << len(x)) - 1, 1 << len(x) - 1
    up, down, score = whole, 0, len(x)
    for c in y:
        equal = places.get(c, 0)
        straight = equal | down
        level = (((equal & up) + up) ^ up) | equal
        more, less = (down | ~(level | up)) & whole, up & level
        score += bool(more & last) - bool(less & last)
        more, less = (more << 1 | 1) & whole, less << 1 & whole
        up, down = (less | ~(straight | more)) & whole, more & straight
    return score


def text_edit_similarity(a: Column, b: Column, least: float) -> Column:
    """bounded_edit() in Arrow batches: some ten times as fast for titles, as all pairs of a batch are worked out together."""

    @F.pandas_udf("double")
    def similarity(left: pd.Series, right: pd.Series) -> pd.Series:
        some = (left.notna() & right.notna()).to_numpy()
        x, y = left[some].tolist(), right[some].tolist()
        n = np.maximum(np.fromiter(map(len, x), np.int64, len(x)), np.fromiter(map(len, y), np.int64, len(y)))
        d = edit_distances(x, y)
        near = d <= np.floor((1.0 - least) * n + 1e-9)
        out = np.zeros(len(left))
        out[some] = np.where(n == 0, 1.0, np.where(near, 1.0 - d / np.maximum(n, 1), 0.0))
        return pd.Series(out)

    return similarity.asNondeterministic()(a, b)


def trigrams(c: Column, padded: bool = False) -> Column:
    """Distinct 3-grams; none for fewer than three characters."""
    c = F.concat(F.lit("  "), c, F.lit("  ")) if padded else c
    return _grams(c, F.split(c, ""), lambda x, y: F.concat(x, y), "string")


def gram_codes(c: Column, padded: bool = False) -> Column:
    """Distinct 3-grams as numbers, 21 bits a character: equal codes are equal grams, and sets of numbers meet faster than sets of strings."""
    c = F.concat(F.lit("  "), c, F.lit("  ")) if padded else c
    points = F.transform(F.split(c, ""), lambda x: F.ascii(x).cast("long"))
    return _grams(c, points, lambda x, y: F.shiftleft(x, 21) + y, "long")


def _grams(c: Column, chars: Column, join: Callable[[Column, Column], Column], kind: str) -> Column:
    """Characters are zipped with those behind them: a substring at each place would count from the start again."""
    n = F.char_length(c)
    behind = lambda k: F.slice(chars, F.lit(k + 1), F.greatest(n - k, F.lit(0)))
    three = F.zip_with(F.zip_with(chars, behind(1), join), behind(2), join)
    return F.when(n < 3, F.array().cast(f"array<{kind}>")).otherwise(F.array_distinct(F.slice(three, F.lit(1), F.greatest(n - 2, F.lit(0)))))


def gram_similarity(a: Column, b: Column, a_text: Column, b_text: Column, kind: str = "dice") -> Column:
    """Overlap of two gram arrays; texts too short for a gram are compared for equality; a null: 0."""
    common = F.size(F.array_intersect(a, b))
    total = F.size(a) + F.size(b)
    value = 2.0 * common / F.nullif(total, F.lit(0)) if kind == "dice" else common / F.nullif(total - common, F.lit(0)).cast("double")
    short = (F.char_length(a_text) < 3) | (F.char_length(b_text) < 3)
    return F.coalesce(F.when(short, F.when(a_text == b_text, 1.0).otherwise(0.0)).otherwise(value), F.lit(0.0))


def trigram_similarity(a: Column, b: Column, kind: str = "dice", padded: bool = False) -> Column:
    return gram_similarity(gram_codes(a, padded), gram_codes(b, padded), a, b, kind)


def text_gram_similarity(a: Column, b: Column) -> Column:
    """Dice overlap of the 3-grams of two whole texts, as trigram_similarity gives it. A null: 0.

    Arrow batches and sorted numbers: the same by array functions, which Spark interprets element by element, takes some ten times as long on texts of
    thousands of characters. A text that is in several pairs of a batch is taken apart once.
    """

    @F.pandas_udf("double")
    def overlap(left: pd.Series, right: pd.Series) -> pd.Series:
        known: dict[str, np.ndarray] = {}

        def codes(text: str) -> np.ndarray:
            if text not in known:
                c = np.frombuffer(text.encode("utf-32-le"), np.uint32).astype(np.uint64)
                known[text] = np.unique(c[:-2] << np.uint64(42) | c[1:-1] << np.uint64(21) | c[2:])
            return known[text]

        def one(x: str | None, y: str | None) -> float:
            if x is None or y is None:
                return 0.0
            if x == y or len(x) < 3 or len(y) < 3:
                return float(x == y)
            p, q = codes(x), codes(y)
            return 2.0 * len(np.intersect1d(p, q, assume_unique=True)) / (len(p) + len(q))

        return pd.Series([one(x, y) for x, y in zip(left, right)], dtype="float64")

    return overlap.asNondeterministic()(a, b)  # so that a filter on the score doesn't run it a second time


def combine(parts: list[tuple[Column, float]]) -> Column:
    total = sum(w for _, w in parts)
    value = F.lit(0.0)
    for c, w in parts:
        value = value + c * F.lit(w / total)
    return value


def threshold(score: Column, least: float = 0.75) -> Column:
    return score >= least


def short_circuit(first: Column, second: Column, w1: float = 0.5, w2: float = 0.5, least: float = 0.75) -> Column:
    """The weighted mean; the second matcher runs only where the first leaves the threshold in reach, else 0 stands for it."""
    return F.when(first * w1 + w2 >= least, first * w1 + second * w2).otherwise(first * w1)


def exact(left: list[Column], right: list[Column]) -> Column:
    """Equality of all attributes, by hash first."""
    same = F.xxhash64(*left) == F.xxhash64(*right)
    for a, b in zip(left, right):
        same = same & a.eqNullSafe(b)
    return same


def rules(*predicates: Column) -> Column:
    """Domain rules that all have to hold; unknown counts as no."""
    out = F.lit(True)
    for p in predicates:
        out = out & F.coalesce(p, F.lit(False))
    return out


def cosine(a: Column, b: Column) -> Column:
    zero = F.lit(0.0)
    dot = F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y), zero, lambda s, x: s + x)
    norm = lambda v: F.sqrt(F.aggregate(v, zero, lambda s, x: s + x.cast("double") * x))
    return F.coalesce(F.try_divide(dot, norm(a) * norm(b)), F.lit(0.0))


def prepare(entities: DataFrame, title: str = "title") -> DataFrame:
    """Per-row features, once before pairing: the folded title."""
    return entities.withColumn("title_ascii", ascii_fold(F.coalesce(F.col(title), F.lit(""))))


class Matcher(Protocol):
    """Anything that keeps the matching rows of a pair table and adds ``score``. Matchers of two stages have ``narrow`` too, which keeps the pairs that may match."""

    def __call__(self, pairs: DataFrame) -> DataFrame: ...


@dataclass(frozen=True)
class TitleAbstract:
    """Edit similarity of titles and gram overlap of abstracts, weighted, with a threshold."""

    w1: float = 0.5
    w2: float = 0.5
    least: float = 0.75
    skip: bool = True

    def narrow(self, pairs: DataFrame) -> DataFrame:
        """The titles' similarity as s1; with ``skip`` only pairs that the abstracts can still lift over the threshold."""
        a, b = F.col("left_title_ascii"), F.col("right_title_ascii")
        if not self.skip:
            return pairs.withColumn("s1", edit_similarity(a, b))
        need = max(0.0, (self.least - self.w2) / self.w1)
        return pairs.withColumn("s1", text_edit_similarity(a, b, need)).where(F.col("s1") * self.w1 + self.w2 >= self.least)

    def __call__(self, pairs: DataFrame) -> DataFrame:
        if "s1" not in pairs.columns:
            pairs = self.narrow(pairs)
        pairs = pairs.withColumn("s2", text_gram_similarity(F.coalesce(F.col("left_abstract"), F.lit("")), F.coalesce(F.col("right_abstract"), F.lit(""))))
        return pairs.withColumn("score", F.col("s1") * self.w1 + F.col("s2") * self.w2).where(threshold(F.col("score"), self.least)).drop("s1", "s2")


def pandas_matcher(function: Callable[[pd.DataFrame], pd.Series], least: float) -> Matcher:
    """A matcher from a vectorised function over batches of pair rows."""

    def run(pairs: DataFrame) -> DataFrame:
        def score(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for pdf in batches:
                yield pdf.assign(score=function(pdf).astype("float64"))

        schema = T.StructType([*pairs.schema.fields, T.StructField("score", T.DoubleType())])
        return pairs.mapInPandas(score, schema).where(F.col("score") >= least)

    return run


def learned(training: DataFrame, features: list[str], label: str = "label"):
    """A logistic classifier of pair features; its ``transform`` adds ``prediction`` and ``probability``. Matches are rare among candidates, so both classes weigh alike."""
    from pyspark.ml import Pipeline
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import VectorAssembler

    share = training.agg(F.avg(label)).first()[0] or 0.0
    weight = F.when(F.col(label) == 1, F.lit(0.5 / max(share, 1e-9))).otherwise(F.lit(0.5 / max(1 - share, 1e-9)))
    stages = [VectorAssembler(inputCols=features, outputCol="features"), LogisticRegression(labelCol=label, weightCol="weight", maxIter=50, regParam=0.001)]
    return Pipeline(stages=stages).fit(training.withColumn("weight", weight))
