"""Homomorphic multiset fingerprints of texts. DataFrame functions only.

A text is the multiset of its paragraphs: its lines, long lines cut after sentences. Each
paragraph's hash gives a wide vector of bits; the fingerprint is the sum of the vectors and the
number of paragraphs, lane by lane modulo 2**16. Order does not matter, and the fingerprint of a text
after inserting or deleting paragraphs is the old one plus or minus theirs. Read as +1/-1
vectors, the sums also estimate how much two multisets share.
"""

from __future__ import annotations

from collections import Counter

from pyspark.sql import Column, DataFrame, Window, functions as F

#: 60-bit hash words per paragraph; each gives 60 lanes.
WORDS = 3
MODULUS = 1 << 16
_PAIR = (1 << 30) | 1
#: Rows of an id range on average, and ranges at most (their bounds are held by the driver, a few MB); beyond 200 million rows ranges grow, and sort on disk.
RANGE_ROWS = 4096
MAX_RANGES = 50_000


def paragraphs(text: Column) -> Column:
    """Lines, cut after a full stop, question or exclamation mark and a space; none for the empty text."""
    return F.when(text == "", F.array().cast("array<string>")).otherwise(F.split(text, r"\n|(?<=[.!?]) "))


def _sums(unit: Column) -> list[Column]:
    """Aggregates over paragraph rows (a null is no paragraph): the count ``n``, then bit counts, two lanes (30 bits apart) in each number."""
    hashes = [F.xxhash64(F.lit(k), unit) for k in range(WORDS)]
    return [F.count(unit).alias("n"), *(F.coalesce(F.sum(F.when(unit.isNotNull(), F.shiftright(h, b).bitwiseAND(F.lit(_PAIR)))), F.lit(0)).alias(f"s{w * 30 + b}") for w, h in enumerate(hashes) for b in range(30))]


def _lanes(modulus: int = MODULUS) -> list[Column]:
    """``n`` and ``lanes`` (array<bigint>), modulo a power of two up to 2**30, from the columns of _sums()."""
    high = F.lit(modulus - 1)
    each = [F.col(f"s{k}") for k in range(WORDS * 30)]
    return [F.col("n").bitwiseAND(high).alias("n"), F.array(*(c.bitwiseAND(high) for c in each), *(F.shiftright(c, 30).bitwiseAND(high) for c in each)).alias("lanes")]


def fingerprints(docs: DataFrame, keys: list[str], text_col: str = "text") -> DataFrame:
    """(keys, n, lanes): the fingerprint of all texts of each key together. Null and empty texts add nothing; no rows, no fingerprints."""
    units = docs.select(*keys, F.explode_outer(paragraphs(F.coalesce(F.col(text_col), F.lit("")))).alias("__u"))
    return units.groupBy(*keys).agg(*_sums(F.col("__u"))).select(*keys, *_lanes())


def combine(n: Column, lanes: Column, other_n: Column, other_lanes: Column, sign: int = 1) -> tuple[Column, Column]:
    """(n, lanes) after inserting (sign 1) or deleting (sign -1) the paragraphs of another fingerprint."""
    return F.pmod(n + sign * other_n, F.lit(MODULUS)), F.zip_with(lanes, other_lanes, lambda x, y: F.pmod(x + sign * y, F.lit(MODULUS)))


def text_of(n: Column, lanes: Column) -> Column:
    """Hexadecimal of all modulo 2**16, four digits each."""
    digits = lambda c: F.lpad(F.hex(c.bitwiseAND(F.lit(MODULUS - 1))), 4, "0")
    return F.lower(F.concat(digits(n), F.array_join(F.transform(lanes, digits), "")))


def _signed(x: Column) -> Column:
    return F.pmod(x + F.lit(MODULUS // 2), F.lit(MODULUS)) - F.lit(MODULUS // 2)


def likeness(n: Column, lanes: Column, other_n: Column, other_lanes: Column, wrapped: bool = True) -> Column:
    """1 for equal fingerprints, else about the shared part of both multisets, in 0..1; two empty texts: 1.

    ``n`` and ``other_n`` should be plain columns: they are used inside lambdas. ``wrapped`` sums are known modulo 2**16 only: with 32,768
    paragraphs or more their sign is lost and the estimate means nothing. Sums before reduction have no such bound.
    """
    zero = F.lit(0.0)
    of = _signed if wrapped else (lambda x: x)

    def square(values: Column, count: Column) -> Column:
        return F.aggregate(values, zero, lambda s, c: s + F.pow(of(2 * c - count).cast("double"), F.lit(2)))

    apart = F.aggregate(F.zip_with(lanes, other_lanes, lambda p, q: of(2 * (p - q) - (n - other_n))), zero, lambda s, d: s + F.pow(d.cast("double"), F.lit(2)))
    both = square(lanes, n) + square(other_lanes, other_n)
    return F.when(apart == 0, F.lit(1.0)).otherwise(F.greatest(F.lit(0.0), F.lit(1.0) - apart / F.nullif(both, F.lit(0.0))))


def _range_of(key: Column, th: Column, cuts: list[tuple[int, int]]) -> Column:
    """Number of cuts below (key, th), by binary search in two literals."""
    if not cuts:
        return F.lit(0)
    keys, ths = (_literal([c[k] for c in cuts], "bigint") for k in (0, 1))
    steps = F.array(*(F.lit(1 << k) for k in reversed(range(len(cuts).bit_length()))))

    def below(at: Column) -> Column:
        k = F.try_element_at(keys, at)
        return (at <= len(cuts)) & ((k < key) | ((k == key) & (F.try_element_at(ths, at) < th)))

    return F.aggregate(steps, F.lit(0), lambda at, s: F.when(below(at + s), at + s).otherwise(at))


def _literal(values: list, kind: str) -> Column:
    """An array literal: one call whatever its length, folded into a constant by the optimizer."""
    return F.split(F.lit(",".join(map(str, values))), ",").cast(f"array<{kind}>")


def _shares(parts: int) -> Column:
    return _literal([k / parts for k in range(1, parts)], "double")


def _cuts(keyed: DataFrame, range_rows: int) -> list[tuple[int, int]]:
    """Bounds of ranges of about ``range_rows`` rows of (key, th). A key that fills several ranges is cut by th."""
    n = keyed.count()
    parts = max(1, min(MAX_RANGES, -(-n // range_rows)))
    if parts == 1:
        return []
    got = Counter(keyed.agg(F.percentile_approx("key", _shares(parts), max(10_000, 4 * parts))).first()[0])
    top = (1 << 63) - 1
    cuts = {(k, top) for k in got}
    wide = {k: n + 1 for k, n in got.items() if n > 1}
    if wide:
        most = max(wide.values())
        some = keyed.join(F.broadcast(keyed.sparkSession.createDataFrame([(k,) for k in wide], "key long")), "key")
        for r in some.groupBy("key").agg(F.percentile_approx("th", _shares(most), max(10_000, 4 * most)).alias("at")).collect():
            step = max(1, most // wide[r.key])
            cuts |= {(r.key, t) for t in r.at[step - 1 :: step]}
            cuts.add((r.key - 1, top) if r.key > -(1 << 63) else (r.key, -(1 << 63)))
    return sorted(cuts)


def edited(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", range_rows: int = RANGE_ROWS) -> DataFrame:
    """Fingerprints of every text and of its edited text, and their likeness.

    The edited text has its last floor(n/2) code points replaced by the first as many (or all) of the
    next document, in descending order of ids; the last document's next is the first. Null ids come
    last, equal ids go by the text's hash, repeated rows follow one another. A null text
    is empty. Likeness is taken from whole sums, fingerprints hold them modulo 2**16. One row alone is its own next. An empty table gives an empty result.
    """
    base = docs.select(F.col(id_col).alias("id"), F.coalesce(F.col(text_col), F.lit("")).alias("text")).withColumn("th", F.xxhash64("text"))
    low = F.lit(-(1 << 63))
    key = F.coalesce(F.col("id").cast("long"), low)
    cuts = _cuts(docs.select(F.coalesce(F.col(id_col).cast("long"), low).alias("key"), F.xxhash64(F.coalesce(F.col(text_col), F.lit(""))).alias("th")), range_rows)
    base = base.withColumn("range", _range_of(key, F.col("th"), cuts))
    # the first row of each range that has rows, for the range above it; a number of rows that MAX_RANGES bounds
    tops = sorted((r.range, r.top) for r in base.groupBy("range").agg(F.max(F.struct(key.alias("key"), "th")).alias("top")).collect())
    target = {}
    for k, (_, top) in enumerate(tops):
        above = tops[(k + 1) % len(tops)][0]
        target.setdefault((top.key, top.th), []).append(above)
    seams = docs.sparkSession.createDataFrame([(k, t, r) for (k, t), rs in target.items() for r in rs], "key long, t long, to int")
    copies = base.join(F.broadcast(seams), (F.col("key") == key) & (F.col("t") == F.col("th")))
    copies = copies.select("id", "text", "th", F.col("to").alias("range"), F.lit(1).alias("copy")).dropDuplicates(["range", "id", "th"])
    both = base.withColumn("copy", F.lit(0)).unionByName(copies)
    order = Window.partitionBy("range").orderBy("copy", F.col("id").desc_nulls_last(), F.col("th").desc())
    rows = both.withColumns({"row": F.row_number().over(order), "next_text": F.lead("text").over(order), "n_chars": F.char_length("text")})
    half = F.floor(F.col("n_chars") / 2).cast("int")
    rows = rows.withColumn("changed", F.when(F.col("copy") == 0, F.concat(F.expr("left(text, n_chars - cast(floor(n_chars / 2) as int))"), F.substring(F.coalesce("next_text", F.lit("")), F.lit(1), half))))
    whole = F.struct("id", "copy", F.col("n_chars").cast("long").alias("n_chars"), F.sha2(F.col("changed").cast("binary"), 256).alias("sha")).alias("doc")
    rows = rows.select("range", "row", whole, "text", "changed")
    # both texts' paragraphs; ranges stay where they are, so neither aggregation nor the second window moves rows
    of = lambda c, k: F.transform(paragraphs(F.col(c)), lambda u: F.struct(F.lit(k).alias("k"), u.alias("u")))
    units = rows.select("range", "row", "doc", F.explode_outer(F.concat(of("text", 0), F.coalesce(of("changed", 1), F.array().cast("array<struct<k:int,u:string>>")))).alias("x"))
    sums = units.select("range", "row", F.coalesce("x.k", F.lit(0)).alias("k"), "doc", F.col("x.u").alias("u")).groupBy("range", "row", "k").agg(F.first("doc").alias("doc"), *_sums(F.col("u"))).select("range", "row", "k", "doc", *_lanes(1 << 30))
    print_of = F.struct("n", "lanes")
    pair = sums.groupBy("range", "row").agg(F.first("doc").alias("doc"), F.max(F.when(F.col("k") == 0, print_of)).alias("a"), F.max(F.when(F.col("k") == 1, print_of)).alias("b"))
    after = Window.partitionBy("range").orderBy("row")
    pair = pair.withColumn("c", F.lead("a").over(after)).where("doc.copy = 0")
    none = F.struct(F.lit(0).cast("long").alias("n"), F.array_repeat(F.lit(0).cast("long"), WORDS * 60).alias("lanes"))
    flat = pair.select("doc.id", "doc.n_chars", "doc.sha", *(F.coalesce(c, none)[x].alias(f"{c}_{x}") for c in "abc" for x in ("n", "lanes")))
    of = lambda c: (F.col(f"{c}_n"), F.col(f"{c}_lanes"))
    return flat.select(F.col("id").alias(id_col), "n_chars", F.col("sha").alias("edited_sha256"), text_of(*of("a")).alias("fingerprint"), text_of(*of("b")).alias("edited_fingerprint"), likeness(*of("a"), *of("b"), wrapped=False).alias("near_edited"), likeness(*of("a"), *of("c"), wrapped=False).alias("near_next"))
