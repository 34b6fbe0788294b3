"""Registered queries: (Spark form, SQL form or none) by name."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, functions as F

from .functions import keys, matching
from .operators import components, layout, measures, methods, pairs, partitioners as parts, relational as rel
from .plans import sqlsurface
from .plans.durable import cut
from .plans.resolve import SnConfig, resolve
from .sources import tables
from .streaming import events as streams

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}

# ---- SQL that the oracles share -------------------------------------------------------------

E = "e AS (SELECT doc_id AS id, lower(substring(coalesce(text, ''), 1, 2)) AS k FROM documents)"
R = "r AS (SELECT id, k, row_number() OVER (ORDER BY k, id) AS g FROM e)"
PK = """hist AS (SELECT k, count(*) AS n FROM e GROUP BY k),
cum AS (SELECT k, n, sum(n) OVER (ORDER BY k) - n AS below, sum(n) OVER () AS total FROM hist),
pk AS (SELECT k, CAST(((2 * below + n) * 10) // (2 * total) AS INTEGER) AS p FROM cum)"""
Q = "q0 AS (SELECT r.id, r.k, r.g, pk.p FROM r JOIN pk ON r.k = pk.k), sz AS (SELECT p, count(*) AS n, min(g) - 1 AS off FROM q0 GROUP BY p), q AS (SELECT q0.*, g - off AS rn, n - (g - off) + 1 AS rn_desc FROM q0 JOIN sz ON q0.p = sz.p)"
WITH_R, WITH_Q = f"WITH {E}, {R}", f"WITH {E}, {R}, {PK}, {Q}"
PAIR = "a.id AS left_id, b.id AS right_id, CAST(b.g - a.g AS BIGINT) AS distance"


def _full(w: int, source: str = WITH_R, where: str = "true", table: str = "r") -> str:
    return f"{source} SELECT {PAIR} FROM {table} a JOIN {table} b ON b.g BETWEEN a.g + 1 AND a.g + {w - 1} WHERE {where}"


def _add(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def put(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return put


def _e(spark: SparkSession, sf: str) -> DataFrame:
    return tables.keyed(spark, sf)


def _part(e: DataFrame) -> parts.Partitioner:
    return parts.balanced_partitioner(e, 10)


# ---- window methods -------------------------------------------------------------------------

for _w in (3, 10, 100):
    QUERIES[f"sn_sequential_w{_w}"] = lambda s, d, w=_w: methods.sequential_pairs(_e(s, d), w)
    ORACLES[f"sn_sequential_w{_w}"] = _full(_w)
for _w in (10, 100):
    QUERIES[f"sn_stitch_w{_w}"] = lambda s, d, w=_w: methods.stitch_pairs(e := _e(s, d), w, _part(e))
    QUERIES[f"sn_replica_w{_w}"] = lambda s, d, w=_w: methods.replica_pairs(e := _e(s, d), w, _part(e))
    ORACLES[f"sn_stitch_w{_w}"] = ORACLES[f"sn_replica_w{_w}"] = _full(_w)
for _w in (10, 1000):
    QUERIES[f"sn_rank_bucket_w{_w}"] = lambda s, d, w=_w: methods.rank_bucket_pairs(_e(s, d), w)
    ORACLES[f"sn_rank_bucket_w{_w}"] = _full(_w)
for _n in ("frame", "lag", "ring", "grouped"):
    QUERIES[f"sn_local_{_n}_w10"] = lambda s, d, n=_n: methods.local_pairs(e := _e(s, d), 10, _part(e), engine=n)
    ORACLES[f"sn_local_{_n}_w10"] = _full(10, WITH_Q, "a.p = b.p", "q")
QUERIES["sn_local_w10"], ORACLES["sn_local_w10"] = QUERIES["sn_local_frame_w10"], ORACLES["sn_local_frame_w10"]


@_add("sn_local_missed_w10", _full(10, WITH_Q, "a.p <> b.p", "q").replace(PAIR, "a.id AS left_id, b.id AS right_id"))
def _missed(s: SparkSession, d: str) -> DataFrame:
    e = _e(s, d)
    return rel.pairs_except(methods.stitch_pairs(e, 10, _part(e)).select("left_id", "right_id"), methods.local_pairs(e, 10, _part(e)).select("left_id", "right_id"))


_ADJACENT = _full(100, WITH_Q, "a.p = b.p OR (b.p = a.p + 1 AND a.rn_desc <= 99 AND b.rn <= 99)", "q")


@_add("sn_stitch_adjacent_w100", _ADJACENT)
def _adjacent(s: SparkSession, d: str) -> DataFrame:
    return methods.stitch_pairs(e := _e(s, d), 100, _part(e), "adjacent")


@_add("sn_stitch_one_reducer_w10", _full(10))
def _one_reducer(s: SparkSession, d: str) -> DataFrame:
    return methods.stitch_pairs(e := _e(s, d), 10, _part(e), parallelism=1)


for _scope in ("map", "partition"):
    QUERIES[f"sn_replica_{_scope}_w100"] = lambda s, d, c=_scope: methods.replica_pairs(e := _e(s, d), 100, _part(e), "adjacent", c)
    ORACLES[f"sn_replica_{_scope}_w100"] = _ADJACENT


@_add("sn_stitch_boundary_rows_w10", f"{WITH_Q} SELECT q.id, q.k, q.p, sz.p AS seam FROM q JOIN sz ON sz.off > 0 AND q.g > sz.off - 9 AND q.g <= sz.off + 9")
def _boundary(s: SparkSession, d: str) -> DataFrame:
    e = _e(s, d)
    part = _part(e)
    return methods.boundary_rows(*layout.persist_layout(e, part), 10).select("id", "k", "p", "seam")


@_add("sn_stitch_seam_pairs_w10", _full(10, WITH_Q, "a.p <> b.p", "q"))
def _seams(s: SparkSession, d: str) -> DataFrame:
    e = _e(s, d)
    part = _part(e)
    return methods.seam_pairs(methods.boundary_rows(*layout.persist_layout(e, part), 10), 10)


_COPIES = f"{WITH_Q}, c AS (SELECT id, k, p, row_number() OVER (PARTITION BY id % 4, p ORDER BY k DESC, id DESC) AS n FROM q WHERE p < 9)"


@_add("sn_replica_rows_map_w10", f"{_COPIES} SELECT id, k, p, p + 1 AS target FROM c WHERE n <= 9")
def _copies(s: SparkSession, d: str) -> DataFrame:
    return methods.replica_rows(e := _e(s, d), 10, _part(e), "map").select("id", "k", "p", "target")


@_add("sn_replica_volume", f"{_COPIES} SELECT count(*) AS copies, CAST(4 * 9 * 9 AS BIGINT) AS bound FROM c WHERE n <= 9")
def _volume(s: SparkSession, d: str) -> DataFrame:
    return measures.replica_volume(e := _e(s, d), 10, _part(e), 4)


@_add("sn_boundary_volume", f"{WITH_Q} SELECT count(*) AS rows, CAST(2 * 9 * 9 AS BIGINT) AS bound FROM q JOIN sz ON sz.off > 0 AND q.g > sz.off - 9 AND q.g <= sz.off + 9")
def _boundary_volume(s: SparkSession, d: str) -> DataFrame:
    return measures.boundary_volume(e := _e(s, d), 10, _part(e))


_TWO = """WITH x AS (SELECT doc_id AS id, lower(substring(coalesce(text, ''), 1, 2)) AS k1, coalesce(lang, '') || '/' || coalesce(source, '') AS k2 FROM documents),
r AS (SELECT id, row_number() OVER (ORDER BY k1, id) AS g1, row_number() OVER (ORDER BY k2, id) AS g2 FROM x),
u AS (SELECT least(a.id, b.id) AS left_id, greatest(a.id, b.id) AS right_id FROM r a JOIN r b ON b.g1 BETWEEN a.g1 + 1 AND a.g1 + 4
UNION SELECT least(a.id, b.id), greatest(a.id, b.id) FROM r a JOIN r b ON b.g2 BETWEEN a.g2 + 1 AND a.g2 + 4)"""


def _twice(s: SparkSession, d: str) -> DataFrame:
    e = tables.publications(s, d)
    return methods.multipass_pairs(e.select("id", "title", "lang", "source"), list(keys.KeySet((keys.prefix_key("title"), keys.composite_key("lang", "source"))).keys), 5)


QUERIES["sn_multipass_w5"], ORACLES["sn_multipass_w5"] = _twice, f"{_TWO} SELECT left_id, right_id FROM u"


@_add("sn_udtf_w10", _full(10, WITH_Q, "a.p = b.p", "q"))
def _udtf(s: SparkSession, d: str) -> DataFrame:
    sqlsurface.register(s)
    layout.tag(e := _e(s, d), _part(e)).select("id", "k", "p").createOrReplaceTempView("tagged_entities")
    return s.sql("SELECT * FROM sliding_pairs(TABLE(SELECT p, k, id FROM tagged_entities) PARTITION BY (p) ORDER BY (k, id), 10)")


@_add("sn_sql_w10", _full(10))
def _sql(s: SparkSession, d: str) -> DataFrame:
    _e(s, d).createOrReplaceTempView("keyed_entities")
    return s.sql(
        "SELECT id AS left_id, n.id AS right_id, CAST(d + 1 AS BIGINT) AS distance FROM (SELECT id, collect_list(struct(id)) OVER (ORDER BY k, id ROWS BETWEEN 1 FOLLOWING AND 9 FOLLOWING) AS ahead FROM keyed_entities) LATERAL VIEW posexplode(ahead) x AS d, n"
    )


@_add(
    "sn_link_w10",
    """WITH u AS (SELECT doc_id AS id, 0 AS src, lower(substring(coalesce(text, ''), 1, 2)) AS k FROM documents UNION ALL SELECT item_id, 1, lower(substring(coalesce(text, ''), 1, 2)) FROM benchmark),
r AS (SELECT *, row_number() OVER (ORDER BY k, id, src) AS g FROM u)
SELECT CASE WHEN a.src = 0 THEN a.id ELSE b.id END AS left_id, CASE WHEN a.src = 1 THEN a.id ELSE b.id END AS right_id, CAST(b.g - a.g AS BIGINT) AS distance FROM r a JOIN r b ON b.g BETWEEN a.g + 1 AND a.g + 9 WHERE a.src <> b.src""",
)
def _link(s: SparkSession, d: str) -> DataFrame:
    b = tables.load(s, d, "benchmark").select(F.col("item_id").alias("id"), keys.prefix_key("text").alias("k"))
    return methods.link_pairs(_e(s, d).select("id", "k"), b, 10)


# ---- baselines ------------------------------------------------------------------------------


@_add("er_cross", "SELECT a.doc_id AS left_id, b.doc_id AS right_id FROM documents a JOIN documents b ON a.doc_id < b.doc_id")
def _cross(s: SparkSession, d: str) -> DataFrame:
    return methods.cross_pairs(_e(s, d))


_BLOCKS = f"WITH {E} SELECT a.id AS left_id, b.id AS right_id FROM e a JOIN e b ON a.k = b.k AND a.id < b.id"
QUERIES["er_blocks"], ORACLES["er_blocks"] = lambda s, d: methods.block_pairs(_e(s, d)), _BLOCKS
QUERIES["er_blocks_tiled"], ORACLES["er_blocks_tiled"] = lambda s, d: methods.block_pairs(_e(s, d), tile=50), _BLOCKS
QUERIES["er_blocks_hash_join"], ORACLES["er_blocks_hash_join"] = lambda s, d: rel.same_key_join(_e(s, d), "shuffle_hash"), _BLOCKS
QUERIES["er_exploded_w10"], ORACLES["er_exploded_w10"] = lambda s, d: methods.exploded_window_pairs(_e(s, d), 10), _full(10)
QUERIES["er_exploded_report"] = lambda s, d: measures.explosion_report(_e(s, d), 10)
ORACLES["er_exploded_report"] = f"""{WITH_R}, n AS (SELECT count(*) AS n FROM r), x AS (SELECT id, g, unnest(range(greatest(1, g - 9), least(g, greatest(1, n - 9)) + 1)) AS win FROM r, n),
raw AS (SELECT a.id AS l, b.id AS r FROM x a JOIN x b ON a.win = b.win AND a.g < b.g)
SELECT (SELECT count(*) FROM x) AS rows, count(*) AS raw_pairs, count(DISTINCT (l, r)) AS distinct_pairs FROM raw"""

# ---- matching -------------------------------------------------------------------------------

EARLY, LATE = ("title_ascii",), ("abstract",)
_MATCH = f"""WITH e AS (SELECT doc_id AS id, lower(substring(coalesce(text, ''), 1, 2)) AS k, regexp_replace(substring(coalesce(text, ''), 1, 60), '[^\\x00-\\x7F]', '?', 'g') AS t, substring(coalesce(text, ''), 61) AS ab FROM documents),
r AS (SELECT id, t, row_number() OVER (ORDER BY k, id) AS g FROM e),
c1 AS (SELECT a.id AS left_id, b.id AS right_id, CASE WHEN greatest(length(a.t), length(b.t)) = 0 THEN 1.0::DOUBLE ELSE 1.0::DOUBLE - levenshtein(a.t, b.t)::DOUBLE / greatest(length(a.t), length(b.t)) END AS s1 FROM r a JOIN r b ON b.g BETWEEN a.g + 1 AND a.g + 9),
need AS (SELECT left_id, right_id FROM c1 WHERE s1 >= 0.5),
ch AS (SELECT id, string_split(ab, '') AS l FROM e WHERE id IN (SELECT left_id FROM need UNION SELECT right_id FROM need)),
gr AS (SELECT DISTINCT id, l[i] || l[i + 1] || l[i + 2] AS gram FROM (SELECT id, l, unnest(range(1, len(l) - 1)) AS i FROM ch)),
gn AS (SELECT id, count(*) AS n FROM gr GROUP BY id),
cm AS (SELECT left_id, right_id, count(*) AS common FROM need JOIN gr a ON a.id = left_id JOIN gr b ON b.id = right_id AND b.gram = a.gram GROUP BY left_id, right_id),
c AS (SELECT c1.left_id, c1.right_id, s1, CASE WHEN s1 < 0.5 THEN 0.0::DOUBLE WHEN length(x.ab) < 3 OR length(y.ab) < 3 THEN CASE WHEN x.ab = y.ab THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END ELSE 2.0::DOUBLE * coalesce(common, 0) / (m.n + n.n) END AS s2
FROM c1 JOIN e x ON x.id = c1.left_id JOIN e y ON y.id = c1.right_id LEFT JOIN cm ON cm.left_id = c1.left_id AND cm.right_id = c1.right_id LEFT JOIN gn m ON m.id = c1.left_id LEFT JOIN gn n ON n.id = c1.right_id)"""


def _match(s: SparkSession, d: str) -> DataFrame:
    return resolve(tables.publications(s, d, features=True), SnConfig(), matching.TitleAbstract(), EARLY, LATE)


QUERIES["er_match_w10"] = lambda s, d: _match(s, d).withColumn("score", F.round("score", 6))
ORACLES["er_match_w10"] = f"{_MATCH} SELECT left_id, right_id, round(s1 * 0.5::DOUBLE + s2 * 0.5::DOUBLE, 6) AS score FROM c WHERE s1 * 0.5::DOUBLE + s2 * 0.5::DOUBLE >= 0.75"
QUERIES["er_match_full_w10"] = lambda s, d: resolve(tables.publications(s, d, features=True), SnConfig(method="replica"), matching.TitleAbstract(skip=False), EARLY, LATE).withColumn("score", F.round("score", 6))
ORACLES["er_match_full_w10"] = ORACLES["er_match_w10"]


@_add("er_short_circuit", f"{_MATCH} SELECT count(*) AS pairs, count_if(s1 >= 0.5) AS second_runs, count_if(s1 < 0.5) AS skipped FROM c")
def _savings(s: SparkSession, d: str) -> DataFrame:
    e = tables.publications(s, d, features=True)
    return measures.matcher_savings(methods.stitch_pairs(e, 10, _part(e), cols=("id", "title_ascii")))


@_add("er_match_pandas", f"{_MATCH} SELECT left_id, right_id FROM c WHERE s1 >= 0.75")
def _pandas(s: SparkSession, d: str) -> DataFrame:
    e = tables.publications(s, d, features=True).select("id", "k", "title_ascii")
    found = methods.stitch_pairs(e, 10, _part(e), cols=("id", "title_ascii")).withColumn("s1", matching.edit_similarity(F.col("left_title_ascii"), F.col("right_title_ascii")))
    return matching.pandas_matcher(lambda pdf: pdf["s1"], 0.75)(found).select("left_id", "right_id")


def _titles(name: str, view: Callable[[SparkSession, str], DataFrame], sql: str, least: float = 0.75) -> None:
    """Window of ten over another table, matched by title."""

    def run(s: SparkSession, d: str) -> DataFrame:
        e = view(s, d)
        found = methods.stitch_pairs(e, 10, _part(e), cols=("id", "title"))
        return found.where(matching.edit_similarity(F.col("left_title"), F.col("right_title")) >= least).select("left_id", "right_id", "distance")

    QUERIES[name] = run
    ORACLES[name] = f"WITH e AS ({sql}), r AS (SELECT *, row_number() OVER (ORDER BY k, id) AS g FROM e) SELECT {PAIR} FROM r a JOIN r b ON b.g BETWEEN a.g + 1 AND a.g + 9 WHERE CASE WHEN greatest(length(a.t), length(b.t)) = 0 THEN 1.0::DOUBLE ELSE 1.0::DOUBLE - levenshtein(a.t, b.t)::DOUBLE / greatest(length(a.t), length(b.t)) END >= {least}"


_titles("er_match_customer", tables.customers, "SELECT c_custkey AS id, c_mktsegment || '/' || c_nationkey AS k, c_name AS t FROM customer", 0.9)
_titles("er_match_part", lambda s, d: tables.parts(s, d), "SELECT p_partkey AS id, p_brand AS k, p_name AS t FROM part")
_titles("er_match_part_type", lambda s, d: tables.parts(s, d, True), "SELECT p_partkey AS id, p_brand || '/' || p_type AS k, p_name AS t FROM part")
_titles("er_match_pages", tables.page_titles, "SELECT page_id AS id, coalesce(lower(regexp_extract(url, '://([^/?#]*)', 1)), '') AS k, regexp_replace(regexp_extract(html, '<title>([^<]*)</title>', 1), '[^\\x00-\\x7F]', '?', 'g') AS t FROM pages", 0.6)
_titles("er_match_orders", tables.order_entities, "SELECT o_orderkey AS id, year(o_orderdate) || '/' || o_orderpriority AS k, CAST(o_custkey AS VARCHAR) AS t FROM orders", 0.9)


@_add("er_match_rules", f"WITH {E}, r AS (SELECT e.id, e.k, d.lang, d.text, row_number() OVER (ORDER BY e.k, e.id) AS g FROM e JOIN documents d ON d.doc_id = e.id) SELECT a.id AS left_id, b.id AS right_id FROM r a JOIN r b ON b.g BETWEEN a.g + 1 AND a.g + 9 WHERE a.lang = b.lang AND a.text = b.text")
def _rules(s: SparkSession, d: str) -> DataFrame:
    e = tables.publications(s, d).select("id", "k", "text", "lang")
    found = methods.replica_pairs(e, 10, _part(e), cols=("id", "text", "lang"))
    return found.where(matching.rules(F.col("left_lang") == F.col("right_lang"), matching.exact([F.col("left_text")], [F.col("right_text")]))).select("left_id", "right_id")


@_add("er_match_conversations", "WITH e AS (SELECT conv_id * 1000 + turn AS id, lower(substring(coalesce(text, ''), 1, 2)) AS k FROM conversations), r AS (SELECT id, k, row_number() OVER (ORDER BY k, id) AS g FROM e) SELECT " + PAIR + " FROM r a JOIN r b ON b.g BETWEEN a.g + 1 AND a.g + 4")
def _conversations(s: SparkSession, d: str) -> DataFrame:
    e = tables.load(s, d, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("id"), keys.prefix_key("text").alias("k"))
    return methods.stitch_pairs(e, 5, _part(e))


@_add("er_cosine", "WITH r AS (SELECT vec_id AS id, embedding, label, row_number() OVER (ORDER BY label, vec_id) AS g FROM embeddings) SELECT a.id AS left_id, b.id AS right_id FROM r a JOIN r b ON b.g BETWEEN a.g + 1 AND a.g + 9 WHERE list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])) >= 0.2")
def _cosine(s: SparkSession, d: str) -> DataFrame:
    e = tables.load(s, d, "embeddings").select(F.col("vec_id").alias("id"), F.lpad(F.col("label").cast("string"), 6, "0").alias("k"), "embedding")
    found = methods.stitch_pairs(e, 10, _part(e), cols=("id", "embedding"))
    return found.where(matching.cosine(F.col("left_embedding"), F.col("right_embedding")) >= 0.2).select("left_id", "right_id")


QUERIES["er_clusters"] = lambda s, d: components.clusters(_match(s, d))
ORACLES["er_clusters"] = f"""{_MATCH.replace('WITH e AS', 'WITH RECURSIVE e AS', 1)}, m AS (SELECT left_id AS a, right_id AS b FROM c WHERE s1 * 0.5::DOUBLE + s2 * 0.5::DOUBLE >= 0.75), ed AS (SELECT a, b FROM m UNION SELECT b, a FROM m),
reach(id, other) AS (SELECT a, a FROM ed UNION SELECT reach.id, ed.b FROM reach JOIN ed ON reach.other = ed.a)
SELECT id, min(other) AS cluster FROM reach GROUP BY id"""


@_add("er_learned")
def _learned(s: SparkSession, d: str) -> DataFrame:
    """Pairs of a held-out fold (two of ten by the hash of the pair) with label and prediction; the classifier learns from the others."""
    e = tables.publications(s, d, features=True)
    found = rel.enrich_pairs(methods.stitch_pairs(e, 10, _part(e), cols=("id", *EARLY)), e, ["abstract", "text"])
    s1 = matching.edit_similarity(F.col("left_title_ascii"), F.col("right_title_ascii"))
    s2 = matching.text_gram_similarity(F.col("left_abstract"), F.col("right_abstract"))
    rows = found.select("left_id", "right_id", s1.alias("s1"), s2.alias("s2"), F.col("left_text").eqNullSafe(F.col("right_text")).cast("double").alias("label"))
    rows = cut(rows.withColumn("held_out", F.pmod(F.xxhash64("left_id", "right_id"), F.lit(10)) < 2))
    model = matching.learned(rows.where("not held_out"), ["s1", "s2"])
    return model.transform(rows.where("held_out")).select("left_id", "right_id", "label", "prediction")


# ---- partitioners and measures --------------------------------------------------------------

_ORD = "CASE WHEN length(k) = 0 THEN 0 ELSE least(27, greatest(0, unicode(substring(k, 1, 1)) - 96)) END AS c1, CASE WHEN length(k) < 2 THEN 0 ELSE least(27, greatest(0, unicode(substring(k, 2, 1)) - 96)) END AS c2"


def _even_sql(b: int) -> str:
    return f"o AS (SELECT id, k, {_ORD} FROM e), t AS (SELECT id, k, CAST(greatest(0, least({b - 1}, floor((c1 * 28 + CASE WHEN c1 BETWEEN 1 AND 26 THEN c2 ELSE 0 END - 28) * {b} / 728.0::DOUBLE))) AS INTEGER) AS p FROM o)"


def _gini_sql(head: str, b: int, table: str = "t") -> str:
    return f"{head}, sizes AS (SELECT s.p, count({table}.p) AS y FROM (SELECT unnest(range({b})) AS p) s LEFT JOIN {table} ON s.p = {table}.p GROUP BY s.p), ranked AS (SELECT y, row_number() OVER (ORDER BY y, p) AS i FROM sizes) SELECT round(2 * sum(i * y)::DOUBLE / ({b} * sum(y)::DOUBLE) - {b + 1}::DOUBLE / {b}, 6) AS gini FROM ranked"


def _gini(e: DataFrame, p: parts.Partitioner) -> DataFrame:
    return measures.gini(measures.sizes_of(e, p), p.parts)


QUERIES["part_gini_balanced"], ORACLES["part_gini_balanced"] = lambda s, d: _gini(e := _e(s, d), _part(e)), _gini_sql(WITH_Q, 10, "q")
for _b in (8, 10, 32):
    QUERIES[f"part_gini_even{_b}"] = lambda s, d, b=_b: _gini(_e(s, d), parts.even_partitioner(b))
    ORACLES[f"part_gini_even{_b}"] = _gini_sql(f"WITH {E}, {_even_sql(_b)}", _b)
for _s in (40, 55, 70, 85):
    QUERIES[f"part_gini_even8_{_s}"] = lambda s, d, q=_s: _gini(parts.skew_last(_e(s, d), parts.even_partitioner(8), q / 100), parts.even_partitioner(8))
    ORACLES[f"part_gini_even8_{_s}"] = _gini_sql(f"WITH {E}, {_even_sql(8)}, f AS (SELECT count_if(p = 7)::DOUBLE / count(*) AS f FROM t), t2 AS (SELECT CASE WHEN p < 7 AND (id * 7919) % 10000 < floor(10000 * ({_s / 100}::DOUBLE - f) / (1 - f)) THEN 7 ELSE p END AS p FROM t, f)", 8, "t2")
QUERIES["part_gini_composite"] = lambda s, d: measures.gini(layout.composite_range(_e(s, d), 10).groupBy("p").agg(F.count("*").alias("rows")), 10)


QUERIES["part_gini_udaf"] = lambda s, d: measures.gini_by_udaf(measures.sizes_of(_e(s, d), parts.even_partitioner(8)), 8)
ORACLES["part_gini_udaf"] = ORACLES["part_gini_even8"]


@_add("part_monotone", f"WITH {E}, {_even_sql(10)} SELECT p, min(k) AS low, max(k) AS high, true AS ok FROM t GROUP BY p")
def _monotone(s: SparkSession, d: str) -> DataFrame:
    return parts.monotone(layout.tag(_e(s, d), parts.even_partitioner(10)))


@_add("part_profile", f"WITH {E}, {_even_sql(8)}, z AS (SELECT p, count(*) AS n FROM t GROUP BY p) SELECT count(*) AS partitions, CAST(sum(n) AS BIGINT) AS rows, max(n) AS largest, round(max(n) / sum(n), 6) AS largest_share, round(arg_max(n, p) / sum(n), 6) AS last_share FROM z")
def _profile(s: SparkSession, d: str) -> DataFrame:
    return measures.partition_profile(measures.sizes_of(_e(s, d), parts.even_partitioner(8)))


@_add("part_halves", "SELECT CAST(CASE WHEN term >= 'n' THEN 1 ELSE 0 END AS INTEGER) AS p, count(*) AS n FROM (SELECT DISTINCT unnest(string_split(text, ' ')) AS term FROM documents) WHERE term <> '' GROUP BY 1")
def _halves(s: SparkSession, d: str) -> DataFrame:
    return methods.term_counts(tables.load(s, d, "documents")).groupBy(parts.halves().column(F.col("term")).alias("p")).agg(F.count("*").alias("n"))


@_add("measure_pair_count", "WITH n AS (SELECT count(*) AS n FROM documents) SELECT w, CAST(sum(greatest(0, n - x)) AS BIGINT) AS pairs FROM n, (SELECT unnest([10, 100, 1000]) AS w), unnest(range(1, w)) AS t(x) GROUP BY w")
def _counts(s: SparkSession, d: str) -> DataFrame:
    n = _e(s, d).count()
    return s.createDataFrame([(w, measures.pair_count(n, w)) for w in (10, 100, 1000)], "w int, pairs long")


@_add("measure_missed_w100", f"{_full(100, WITH_Q, 'a.p <> b.p', 'q').replace(PAIR, 'count(*) AS missed, CAST(44550 AS BIGINT) AS closed_form')}")
def _missed_count(s: SparkSession, d: str) -> DataFrame:
    e = _e(s, d)
    sizes = {r.p: r.rows for r in measures.sizes_of(e, _part(e)).collect()}
    n = [sizes.get(p, 0) for p in range(10)]
    return s.createDataFrame([(measures.missed_pairs(n, 100), int(measures.missed_pairs(n, 100, True)))], "missed long, closed_form long")


_TRUTH = "tr AS (SELECT a.doc_id AS a, b.doc_id AS b FROM documents a JOIN documents b ON coalesce(a.text, '') = coalesce(b.text, '') AND a.doc_id < b.doc_id)"


@_add("measure_pair_completeness", f"{WITH_R}, {_TRUTH}, f AS (SELECT least(a.id, b.id) AS a, greatest(a.id, b.id) AS b FROM r a JOIN r b ON b.g BETWEEN a.g + 1 AND a.g + 9) SELECT count(f.a) AS found, count(*) AS existing FROM tr LEFT JOIN f ON tr.a = f.a AND tr.b = f.b")
def _completeness(s: SparkSession, d: str) -> DataFrame:
    e = tables.publications(s, d)
    return measures.pair_completeness(methods.stitch_pairs(e.select("id", "k"), 10, _part(e)), measures.exact_copies(e))


@_add("measure_selectivity", f"{_MATCH}, z AS (SELECT count_if(s1 * 0.5::DOUBLE + s2 * 0.5::DOUBLE >= 0.75) AS matches, count(*) AS candidates FROM c) SELECT matches, candidates, round(matches / candidates, 6) AS ratio FROM z")
def _selectivity(s: SparkSession, d: str) -> DataFrame:
    e = _e(s, d)
    return measures.selectivity(_match(s, d), methods.stitch_pairs(e, 10, _part(e)))


@_add("measure_reduction_ratio", f"{WITH_R}, n AS (SELECT count(*) AS n FROM r) SELECT round(1.0::DOUBLE - count(*)::DOUBLE / greatest(1.0::DOUBLE, any_value(n.n) * (any_value(n.n) - 1) / 2.0::DOUBLE), 6) AS ratio FROM r a JOIN r b ON b.g BETWEEN a.g + 1 AND a.g + 9, n")
def _reduction(s: SparkSession, d: str) -> DataFrame:
    e = _e(s, d)
    return methods.stitch_pairs(e, 10, _part(e)).agg(F.round(measures.reduction_ratio(e.count()), 6).alias("ratio"))


@_add("measure_multipass_gain", f"{_TWO}, {_TRUTH}, one AS (SELECT least(a.id, b.id) AS left_id, greatest(a.id, b.id) AS right_id FROM r a JOIN r b ON b.g1 BETWEEN a.g1 + 1 AND a.g1 + 4) SELECT count(DISTINCT CASE WHEN one.left_id IS NOT NULL THEN (tr.a, tr.b) END) AS one_pass, count(DISTINCT CASE WHEN u.left_id IS NOT NULL THEN (tr.a, tr.b) END) AS two_passes FROM tr LEFT JOIN one ON tr.a = one.left_id AND tr.b = one.right_id LEFT JOIN u ON tr.a = u.left_id AND tr.b = u.right_id")
def _gain(s: SparkSession, d: str) -> DataFrame:
    e = tables.publications(s, d)
    truth = measures.exact_copies(e)
    one = measures.pair_completeness(methods.stitch_pairs(e.select("id", "k"), 5, _part(e)), truth).select(F.col("found").alias("one_pass"))
    return one.crossJoin(measures.pair_completeness(_twice(s, d), truth).select(F.col("found").alias("two_passes")))


@_add("measure_same_pairs", f"{WITH_R} SELECT CAST(0 AS BIGINT) AS only_left, CAST(0 AS BIGINT) AS only_right, count(*) AS \"both\" FROM r a JOIN r b ON b.g BETWEEN a.g + 1 AND a.g + 9")
def _same(s: SparkSession, d: str) -> DataFrame:
    e = _e(s, d)
    return measures.same_pairs(methods.stitch_pairs(e, 10, _part(e)), methods.replica_pairs(e, 10, _part(e)))


@_add("measure_buffer_need", f"WITH {E} SELECT max(n) AS block_rows, CAST(9 AS BIGINT) AS window_rows FROM (SELECT count(*) AS n FROM e GROUP BY k)")
def _buffer(s: SparkSession, d: str) -> DataFrame:
    return measures.buffer_need(_e(s, d), 10)


# ---- keys and counts ------------------------------------------------------------------------

QUERIES["word_count"] = lambda s, d: methods.term_counts(tables.load(s, d, "documents"))
ORACLES["word_count"] = "SELECT term, count(*) AS n FROM (SELECT unnest(string_split(text, ' ')) AS term FROM documents) WHERE term <> '' GROUP BY term"
QUERIES["word_count_conversations"] = lambda s, d: methods.term_counts(tables.load(s, d, "conversations"))
ORACLES["word_count_conversations"] = ORACLES["word_count"].replace("documents", "conversations")


def _key(name: str, table: str, id_col: str, key: Callable, sql: str) -> None:
    QUERIES[f"key_{name}"] = lambda s, d: tables.load(s, d, table).select(F.col(id_col).alias("id"), key().alias("k"))
    ORACLES[f"key_{name}"] = f"SELECT {id_col} AS id, {sql} AS k FROM {table}"


_key("prefix", "documents", "doc_id", lambda: keys.prefix_key("text"), "lower(substring(text, 1, 2))")
_key("concat_prefix", "documents", "doc_id", lambda: keys.concat_prefix_key([("lang", 2), ("text", 3)]), "lower(substring(lang, 1, 2)) || lower(substring(text, 1, 3))")
_key("attribute", "part", "p_partkey", lambda: keys.attribute_key("p_brand"), "p_brand")
_key("composite", "part", "p_partkey", lambda: keys.composite_key("p_brand", "p_type"), "p_brand || '/' || p_type")
_key("initials_year", "orders", "o_orderkey", lambda: keys.initials_year_key(F.split("o_orderpriority", "-"), F.year("o_orderdate")), "list_aggregate(list_transform(string_split(o_orderpriority, '-'), lambda x: upper(substring(x, 1, 1))), 'string_agg', '') || year(o_orderdate)")
_key("ordinal", "orders", "o_orderkey", lambda: keys.ordinal_key("o_custkey"), "o_custkey")
_key("date", "orders", "o_orderkey", lambda: keys.date_key("o_orderdate"), "CAST(date_diff('day', DATE '1970-01-01', CAST(o_orderdate AS DATE)) AS BIGINT)")
_key("suffix", "customer", "c_custkey", lambda: keys.suffix_key("c_name"), "lower(right(c_name, 3))")
_key("host", "pages", "page_id", lambda: keys.host_key("url"), "coalesce(lower(regexp_extract(url, '://([^/?#]*)', 1)), '')")
_CODES = "translate(regexp_replace(upper(p_name), '[^A-Z]', 'A', 'g'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', '01230127022455012623017202')"
_RUNS = f"substring({_CODES}, 1, 1) || replace(substring({_CODES}, 2), '7', '')"
for _digit in "0123456":
    _RUNS = f"regexp_replace({_RUNS}, '{_digit}+', '{_digit}', 'g')"
_key("soundex", "part", "p_partkey", lambda: keys.soundex_key("p_name"), f"upper(substring(p_name, 1, 1)) || rpad(substring(replace(substring({_RUNS}, 2), '0', ''), 1, 3), 3, '0')")

# ---- relational surface ---------------------------------------------------------------------


_IDS = f"{_MATCH}, i AS (SELECT unnest([left_id, right_id]) AS id FROM c WHERE s1 * 0.5::DOUBLE + s2 * 0.5::DOUBLE >= 0.75)"
QUERIES["rel_semi"], ORACLES["rel_semi"] = lambda s, d: rel.has_partner(_e(s, d).select("id", "k"), _match(s, d)), f"{_IDS} SELECT id, k FROM e WHERE id IN (SELECT id FROM i)"
QUERIES["rel_anti"], ORACLES["rel_anti"] = lambda s, d: rel.singletons(_e(s, d).select("id", "k"), _match(s, d)), f"{_IDS} SELECT id, k FROM e WHERE id NOT IN (SELECT id FROM i)"
QUERIES["rel_band"] = lambda s, d: rel.band_join(*[tables.load(s, d, "part").select(F.col("p_partkey").alias("id"), F.col("p_retailprice").alias("v"))] * 2, "v", 1.0)
ORACLES["rel_band"] = "SELECT a.p_partkey AS left_id, b.p_partkey AS right_id FROM part a JOIN part b ON abs(a.p_retailprice - b.p_retailprice) <= 1.0"
QUERIES["rel_projection"], ORACLES["rel_projection"] = lambda s, d: rel.with_key(tables.load(s, d, "documents"), keys.prefix_key("text")).select("doc_id", "k"), "SELECT doc_id, coalesce(lower(substring(text, 1, 2)), '') AS k FROM documents"
QUERIES["rel_filter"], ORACLES["rel_filter"] = lambda s, d: rel.min_length(rel.in_languages(tables.load(s, d, "documents"), ["de", "en"]), 500).select("doc_id"), "SELECT doc_id FROM documents WHERE lang IN ('de', 'en') AND n_chars >= 500"
QUERIES["rel_lookup"] = lambda s, d: rel.enrich_pairs(methods.stitch_pairs(e := tables.publications(s, d), 3, _part(e)).select("left_id", "right_id"), e, ["lang", "source"])
ORACLES["rel_lookup"] = f"{WITH_R} SELECT a.id AS left_id, b.id AS right_id, x.lang AS left_lang, x.source AS left_source, y.lang AS right_lang, y.source AS right_source FROM r a JOIN r b ON b.g BETWEEN a.g + 1 AND a.g + 2 JOIN documents x ON x.doc_id = a.id JOIN documents y ON y.doc_id = b.id"
QUERIES["rel_block_members"] = lambda s, d: rel.block_members(_e(s, d)).select("k", F.array_join(F.transform("ids", lambda i: i.cast("string")), ",").alias("ids"))
ORACLES["rel_block_members"] = f"WITH {E} SELECT k, string_agg(CAST(id AS VARCHAR), ',' ORDER BY id) AS ids FROM e GROUP BY k"
QUERIES["rel_term_map"] = lambda s, d: rel.term_map(tables.load(s, d, "conversations").select(F.col("conv_id").alias("doc_id"), "text")).select("doc_id", F.explode("terms").alias("term", "n"))
ORACLES["rel_term_map"] = "SELECT conv_id AS doc_id, term, count(*) AS n FROM (SELECT conv_id, unnest(string_split(text, ' ')) AS term FROM conversations) WHERE term <> '' GROUP BY conv_id, term HAVING count(*) > 1"
QUERIES["rel_interval"] = lambda s, d: rel.events_within(*[tables.load(s, d, "events")] * 2, "10 minutes")
ORACLES["rel_interval"] = "SELECT a.event_id AS left_id, b.event_id AS right_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE"


def _sides(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    e = tables.load(s, d, "events")
    return e.where("event_id % 2 = 0"), e.where("event_id % 2 = 1")


QUERIES["rel_asof"] = lambda s, d: rel.previous_event(*_sides(s, d))
ORACLES["rel_asof"] = "SELECT a.event_id, arg_max(b.event_id, (b.ts, b.event_id)) AS previous_id FROM events a LEFT JOIN events b ON a.user_id = b.user_id AND b.event_id % 2 = 1 AND b.ts <= a.ts WHERE a.event_id % 2 = 0 GROUP BY a.event_id"
for _n, _f in (("cube", rel.block_cube), ("rollup", rel.partition_rollup)):
    QUERIES[f"rel_{_n}"] = lambda s, d, f=_f: f(tables.load(s, d, "documents"))
    ORACLES[f"rel_{_n}"] = f"SELECT lang, source, count(*) AS n FROM documents GROUP BY {_n} (lang, source)"


@_add("rel_grouping_sets", "SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())")
def _sets(s: SparkSession, d: str) -> DataFrame:
    tables.load(s, d, "documents").createOrReplaceTempView("docs_for_sets")
    return s.sql("SELECT lang, source, count(*) AS n FROM docs_for_sets GROUP BY GROUPING SETS ((lang), (source), ())")


@_add("rel_setops", f"{WITH_R}, a AS (SELECT x.id AS left_id, y.id AS right_id FROM r x JOIN r y ON y.g BETWEEN x.g + 1 AND x.g + 4), b AS (SELECT left_id, right_id FROM a WHERE left_id < right_id) SELECT 'except' AS op, count(*) AS n FROM (SELECT * FROM a EXCEPT SELECT * FROM b) UNION ALL SELECT 'intersect', count(*) FROM (SELECT * FROM a INTERSECT SELECT * FROM b) UNION ALL SELECT 'union', count(*) FROM (SELECT * FROM a UNION SELECT * FROM b) UNION ALL SELECT 'diff', count(*) FROM a WHERE left_id >= right_id")
def _setops(s: SparkSession, d: str) -> DataFrame:
    e = _e(s, d)
    a = methods.stitch_pairs(e, 5, _part(e)).select("left_id", "right_id")
    b = a.where("left_id < right_id")
    each = {"except": rel.pairs_except(a, b), "intersect": rel.pairs_intersect(a, b), "union": rel.pairs_union(a, b), "diff": rel.pair_diff(a, b)}
    out = None
    for name, df in each.items():
        one = df.agg(F.lit(name).alias("op"), F.count("*").alias("n"))
        out = one if out is None else out.unionByName(one)
    return out


QUERIES["rel_topk"], ORACLES["rel_topk"] = lambda s, d: rel.heaviest_blocks(_e(s, d), 10), f"WITH {E} SELECT k, count(*) AS n FROM e GROUP BY k ORDER BY n DESC, k LIMIT 10"
QUERIES["rel_best_match"] = lambda s, d: rel.best_matches(_match(s, d), 1).select("left_id", "right_id")
ORACLES["rel_best_match"] = f"{_MATCH}, m AS (SELECT left_id, right_id, row_number() OVER (PARTITION BY left_id ORDER BY s1 * 0.5::DOUBLE + s2 * 0.5::DOUBLE DESC, right_id) AS n FROM c WHERE s1 * 0.5::DOUBLE + s2 * 0.5::DOUBLE >= 0.75) SELECT left_id, right_id FROM m WHERE n = 1"
QUERIES["rel_windows"] = lambda s, d: rel.rankings(tables.load(s, d, "part").select(F.col("p_partkey").alias("id"), F.col("p_brand").alias("k"), F.col("p_size").alias("v")))
ORACLES["rel_windows"] = "SELECT p_partkey AS id, p_brand AS k, CAST(row_number() OVER t AS BIGINT) AS rn, CAST(rank() OVER w AS BIGINT) AS rnk, CAST(dense_rank() OVER w AS BIGINT) AS dense, CAST(ntile(4) OVER t AS BIGINT) AS quarter, round(percent_rank() OVER w, 6) AS share, count(*) OVER (PARTITION BY p_brand ORDER BY p_size RANGE BETWEEN 5 PRECEDING AND 5 FOLLOWING) AS near FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size), t AS (PARTITION BY p_brand ORDER BY p_size, p_partkey)"
QUERIES["rel_neighbours"] = lambda s, d: rel.neighbours(tables.load(s, d, "events"))
ORACLES["rel_neighbours"] = "SELECT event_id, lag(event_id) OVER w AS before_id, lead(event_id) OVER w AS after_id, first_value(event_id) OVER f AS first_id, last_value(event_id) OVER f AS last_id, nth_value(event_id, 2) OVER f AS second_id FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id), f AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)"
QUERIES["rel_json"] = lambda s, d: rel.props_of(tables.load(s, d, "events"))
ORACLES["rel_json"] = "SELECT event_id, unnest(map_keys(m)) AS name, unnest(map_values(m)) AS value FROM (SELECT event_id, CAST(props::JSON AS MAP(VARCHAR, INTEGER)) AS m FROM events)"
QUERIES["rel_nation"] = lambda s, d: rel.attach_nation(tables.load(s, d, "customer"), tables.load(s, d, "nation"), "c_nationkey").groupBy("n_name").agg(F.count("*").alias("n"))
ORACLES["rel_nation"] = "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name"
QUERIES["rel_distinct_keys"], ORACLES["rel_distinct_keys"] = lambda s, d: rel.distinct_keys(_e(s, d)), f"WITH {E} SELECT count(DISTINCT k) AS keys FROM e"
QUERIES["rel_block_quantiles"] = lambda s, d: rel.block_size_quantiles(_e(s, d)).select(*(F.round(c, 6).alias(c) for c in ("q50", "q90", "q99")))
ORACLES["rel_block_quantiles"] = f"WITH {E}, z AS (SELECT count(*) AS n FROM e GROUP BY k) SELECT round(quantile_cont(n, 0.5), 6) AS q50, round(quantile_cont(n, 0.9), 6) AS q90, round(quantile_cont(n, 0.99), 6) AS q99 FROM z"
QUERIES["rel_pivot"] = lambda s, d: rel.matches_by_language(_match(s, d), tables.load(s, d, "documents"), ["de", "en", "es", "fr"])
ORACLES["rel_pivot"] = f"{_MATCH} SELECT x.lang AS left_lang, count_if(y.lang = 'de') AS de, count_if(y.lang = 'en') AS en, count_if(y.lang = 'es') AS es, count_if(y.lang = 'fr') AS fr FROM c JOIN documents x ON x.doc_id = left_id JOIN documents y ON y.doc_id = right_id WHERE s1 * 0.5::DOUBLE + s2 * 0.5::DOUBLE >= 0.75 GROUP BY x.lang"
QUERIES["rel_ordered_matches"] = lambda s, d: rel.ordered_pairs(_match(s, d)).select("left_id", "right_id")
ORACLES["rel_ordered_matches"] = f"{_MATCH} SELECT left_id, right_id FROM c WHERE s1 * 0.5::DOUBLE + s2 * 0.5::DOUBLE >= 0.75"


@_add("volume_lineitem_w3", "SELECT CAST(2 * count(*) - 3 AS BIGINT) AS pairs FROM lineitem")
def _lineitem(s: SparkSession, d: str) -> DataFrame:
    li = tables.load(s, d, "lineitem")
    e = li.select(F.col("l_shipdate").alias("k"), F.struct(*li.columns).alias("id"))
    return measures.count_pairs(methods.rank_bucket_pairs(e, 3).select("distance"))


@_add("volume_events_w10", "WITH r AS (SELECT event_id AS id, row_number() OVER (ORDER BY user_id, event_id) AS g FROM events) SELECT " + PAIR + " FROM r a JOIN r b ON b.g BETWEEN a.g + 1 AND a.g + 9")
def _events(s: SparkSession, d: str) -> DataFrame:
    return methods.rank_bucket_pairs(tables.load(s, d, "events").select(F.col("event_id").alias("id"), keys.ordinal_key("user_id").alias("k")), 10)


# ---- streams --------------------------------------------------------------------------------

_CLOSED = "(SELECT max(ts) - INTERVAL 10 MINUTE FROM events)"


@_add("stream_tumbling", f"SELECT date_trunc('hour', ts) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2 HAVING date_trunc('hour', ts) + INTERVAL 1 HOUR <= {_CLOSED}")
def _tumbling(s: SparkSession, d: str) -> DataFrame:
    return streams.run_once(streams.tumbling_counts(streams.read_events(s, f"{d}/events.parquet")), "tumbling")


@_add("stream_sliding", f"WITH w AS (SELECT event_type, unnest([time_bucket(INTERVAL 30 MINUTE, ts), time_bucket(INTERVAL 30 MINUTE, ts) - INTERVAL 30 MINUTE]) AS start FROM events) SELECT start, event_type, count(*) AS n FROM w GROUP BY start, event_type HAVING start + INTERVAL 1 HOUR <= {_CLOSED}")
def _sliding(s: SparkSession, d: str) -> DataFrame:
    return streams.run_once(streams.tumbling_counts(streams.read_events(s, f"{d}/events.parquet"), slide="30 minutes"), "sliding")


@_add("stream_session", f"WITH x AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events), y AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS ses FROM x) SELECT min(ts) AS start, user_id, count(*) AS n FROM y GROUP BY user_id, ses HAVING max(ts) + INTERVAL 30 MINUTE <= {_CLOSED}")
def _session(s: SparkSession, d: str) -> DataFrame:
    return streams.run_once(streams.session_counts(streams.read_events(s, f"{d}/events.parquet")), "session")


@_add("stream_dedupe", "SELECT event_id FROM events")
def _dedupe(s: SparkSession, d: str) -> DataFrame:
    twice = streams.read_events(s, f"{d}/events.parquet").withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2))))
    return streams.run_once(streams.first_of_duplicates(twice, ["event_id"]), "dedupe").select("event_id")


@_add("stream_interval", ORACLES["rel_interval"])
def _stream_interval(s: SparkSession, d: str) -> DataFrame:
    a, b = (streams.read_events(s, f"{d}/events.parquet") for _ in range(2))
    return streams.run_once(streams.within(a, b), "interval").select("left_id", "right_id")


@_add("stream_incremental_pairs", _full(10))
def _incremental(s: SparkSession, d: str) -> DataFrame:
    e = _e(s, d)
    docs = streams.read_stream(s, f"{d}/documents.parquet")
    keyed = docs.select(F.col("doc_id").alias("id"), keys.prefix_key("text").alias("k"))
    return streams.IncrementalPairs(s, _part(e), 10).run(keyed)


def entry(spark: SparkSession, folder: str) -> DataFrame:
    """Flagship: stitched windows of ten over publications, matched by title and abstract."""
    return _match(spark, folder)
