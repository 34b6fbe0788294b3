"""Given tables, with fixed schemas, and entity views of them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, functions as F

from ..functions import keys, matching

#: Columns that each table must have.
SCHEMAS = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey long, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey long, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey long, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp, o_orderpriority string",
    "lineitem": "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp",
    "events": "event_id long, ts timestamp, user_id long, event_type string, value double, props string",
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "embeddings": "vec_id long, embedding array<float>, label int",
    "pages": "page_id long, url string, html string",
    "benchmark": "item_id long, text string",
    "labels": "doc_id long, quality int, toxic int",
    "conversations": "conv_id long, turn long, role string, text string",
}


def load(spark: SparkSession, folder: str, name: str) -> DataFrame:
    """A table with its declared columns; a missing one fails here and not in a later plan."""
    df = spark.read.parquet(f"{folder}/{name}.parquet")
    wanted = [part.split(" ")[0] for part in SCHEMAS[name].split(", ")]
    missing = set(wanted) - set(df.columns)
    if missing:
        raise ValueError(f"{name} lacks {sorted(missing)}")
    return df.select(*wanted)


def load_entities(spark: SparkSession, path: str, fmt: str, schema: str, id_col: str, key: Column) -> DataFrame:
    """Rows of a csv, json, orc, parquet or text source as entities."""
    df = spark.read.format(fmt).schema(schema).load(path)
    return df.select(F.col(id_col).alias("id"), key.alias("k"), *(c for c in df.columns if c not in (id_col, "id", "k")))


def publications(spark: SparkSession, folder: str, features: bool = False) -> DataFrame:
    """Documents as publications: title of 60 characters, the rest of the text as abstract, two-letter key."""
    docs = load(spark, folder, "documents")
    title = F.substring(F.coalesce("text", F.lit("")), 1, 60)
    view = docs.select(F.col("doc_id").alias("id"), keys.prefix_key(title).alias("k"), title.alias("title"), F.substring(F.coalesce("text", F.lit("")), 61, (1 << 31) - 1).alias("abstract"), "text", "lang", "source")
    return matching.prepare(view) if features else view


def slices(spark: SparkSession, folder: str, chars: int = 560) -> DataFrame:
    """Every ``chars`` characters of every document as a publication of its own: more rows than documents, and all of their text. For timings."""
    docs = load(spark, folder, "documents").select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    last = F.floor(F.greatest(F.char_length("text") - 1, F.lit(0)) / chars).cast("int")
    some = F.transform(F.sequence(F.lit(0), last), lambda n: F.substring(F.col("text"), n * chars + 1, F.lit(chars)))
    cut = docs.select("doc_id", F.posexplode(some).alias("n", "part"))
    part = cut.select((F.col("doc_id") * 100_000 + F.col("n")).alias("id"), "part")
    title = F.substring("part", 1, 60)
    return matching.prepare(part.select("id", keys.prefix_key(title).alias("k"), title.alias("title"), F.substring("part", 61, chars).alias("abstract")))


def keyed(spark: SparkSession, folder: str) -> DataFrame:
    """(id, k, mapper_id) only: what window methods have to move. mapper_id stands in for the input split."""
    return publications(spark, folder).select("id", "k").withColumn("mapper_id", F.pmod("id", F.lit(4)))


def customers(spark: SparkSession, folder: str) -> DataFrame:
    c = load(spark, folder, "customer")
    return c.select(F.col("c_custkey").alias("id"), keys.composite_key("c_mktsegment", "c_nationkey").alias("k"), F.col("c_name").alias("title"))


def parts(spark: SparkSession, folder: str, with_type: bool = False) -> DataFrame:
    p = load(spark, folder, "part")
    key = keys.composite_key("p_brand", "p_type") if with_type else keys.attribute_key("p_brand")
    return p.select(F.col("p_partkey").alias("id"), key.alias("k"), F.col("p_name").alias("title"))


def page_titles(spark: SparkSession, folder: str) -> DataFrame:
    p = load(spark, folder, "pages")
    title = F.regexp_extract("html", r"<title>([^<]*)</title>", 1)
    return p.select(F.col("page_id").alias("id"), keys.host_key("url").alias("k"), matching.ascii_fold(title).alias("title"))


def order_entities(spark: SparkSession, folder: str) -> DataFrame:
    o = load(spark, folder, "orders")
    return o.select(F.col("o_orderkey").alias("id"), keys.composite_key(F.year("o_orderdate"), "o_orderpriority").alias("k"), F.col("o_custkey").cast("string").alias("title"))
