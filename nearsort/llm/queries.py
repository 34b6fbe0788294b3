"""Registered queries of this subpackage: each operator over its whole table, and their SQL where there is one."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession, functions as F

from . import decontaminate, fingerprint, language, packing, phrases, pieces, simhash, suffixes, tokens, urls

#: Fixed names of the vocabulary files.
BYTE_BPE = "byte_bpe_50k.json"
BYTE_RANKS = "byte_bpe_50k.tiktoken"
PIECE_BPE = "piece_bpe_32k.model"


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1(spark: SparkSession, sf_dir: str) -> DataFrame:
    return phrases.remove_repeats(_table(spark, sf_dir, "documents"))


def op2(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pieces.encode(_table(spark, sf_dir, "documents"), public_tokenizers.path(PIECE_BPE))


def op3(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprint.edited(_table(spark, sf_dir, "documents"))


def op4(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(_table(spark, sf_dir, "documents"))


def op5(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urls.judge(_table(spark, sf_dir, "pages"))


def op6(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(_table(spark, sf_dir, "documents"), public_tokenizers.path(BYTE_RANKS), public_tokenizers.PATTERN)


def op7(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokens.token_counts(_table(spark, sf_dir, "documents"), public_tokenizers.path(BYTE_BPE))


def op8(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffixes.remove_substrings(_table(spark, sf_dir, "documents"))


def op9(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents")
    model = language.fit(docs.where(~language.held_out()))
    return language.identify(docs.select("doc_id", "text"), model).select("doc_id", language.held_out().alias("held_out"), "lang_pred", "score")


def op10(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.contamination(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark"))


QUERIES = {
    "op1_repeated_phrases": op1,
    "op2_sentencepiece": op2,
    "op3_fingerprints": op3,
    "op4_simhash": op4,
    "op5_url_rules": op5,
    "op6_packing": op6,
    "op7_token_counts": op7,
    "op8_suffix_arrays": op8,
    "op9_language": op9,
    "op10_decontamination": op10,
}

ORACLES = {
    "op1_repeated_phrases": r"""
WITH d AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
wins AS (SELECT doc_id, s, array_to_string(w[s:s+19], ' ') AS win FROM d, unnest(range(1, len(w) - 18)) AS t(s)),
firsts AS (SELECT win, min((doc_id, s)) AS f FROM wins GROUP BY win HAVING count(*) > 1),
later AS (SELECT x.doc_id, x.s FROM wins x JOIN firsts f ON x.win = f.win WHERE (x.doc_id, x.s) <> f.f),
gone AS (SELECT DISTINCT doc_id, p FROM later, unnest(range(s, s + 20)) AS t(p)),
per AS (SELECT doc_id, list(p) AS ps FROM gone GROUP BY doc_id),
kept AS (SELECT d.doc_id, w, CASE WHEN ps IS NULL THEN w ELSE list_filter(w, lambda x, i: NOT list_contains(ps, i)) END AS k FROM d LEFT JOIN per ON d.doc_id = per.doc_id)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(len(w) - len(k) AS BIGINT) AS n_removed, sha256(array_to_string(k, ' ')) AS kept_sha256 FROM kept""",
    "op5_url_rules": r"""
WITH p AS (SELECT page_id, coalesce(regexp_extract(url, '^(?:.|\n)*?://([^/?#]*)', 1), '') AS h, coalesce(regexp_extract(url, '^(?:.|\n)*?://[^/?#]*([^?#]*)', 1), '') AS path FROM pages),
q AS (SELECT page_id, translate(h, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, path FROM p),
r(verdict, h, pre) AS (VALUES ('block', 'com', '/en/'), ('allow', 'example.com', '/en/7'), ('allow', 'net', '/de/'), ('block', 'example.net', '/de/8'), ('block', 'org', '/es/')),
m AS (SELECT page_id, arg_max(r.h || r.pre, length(r.h || r.pre)) AS rule, arg_max(r.verdict, length(r.h || r.pre)) AS v
      FROM q JOIN r ON (host = r.h OR ends_with(host, '.' || r.h)) AND starts_with(path, r.pre) GROUP BY page_id)
SELECT q.page_id, q.host, q.path, m.rule, coalesce(m.v, 'allow') AS verdict FROM q LEFT JOIN m ON q.page_id = m.page_id""",
    "op10_decontamination": r"""
WITH d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
b AS (SELECT CAST(item_id AS VARCHAR) AS item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
items AS (SELECT DISTINCT item_id, least(13, len(w)) AS n, array_to_string(w[s:s+12], ' ') AS win FROM b, unnest(range(1, greatest(2, len(w) - 11))) AS t(s) WHERE len(w) > 0),
sizes AS (SELECT DISTINCT n FROM items),
hits AS (SELECT doc_id, i.item_id, s, x.n FROM (SELECT doc_id, s, n, array_to_string(w[s:s+n-1], ' ') AS win FROM d, sizes, unnest(range(1, len(w) - n + 2)) AS t(s)) x JOIN items i ON x.win = i.win AND x.n = i.n),
words AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(s, s + n)) AS p FROM hits) GROUP BY doc_id),
names AS (SELECT doc_id, count(DISTINCT item_id) AS n_items, string_agg(DISTINCT item_id, ',' ORDER BY item_id) AS ids FROM hits GROUP BY doc_id)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items, sha256(coalesce(ids, '')) AS items_sha256,
       coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated
FROM d LEFT JOIN words ON d.doc_id = words.doc_id LEFT JOIN names ON d.doc_id = names.doc_id""",
}
