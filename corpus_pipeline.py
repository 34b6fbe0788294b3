"""Cleaning a corpus in five stages, each written as Parquet and read again as the next one's documents."""

from __future__ import annotations

import uuid

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession, functions as F

from nearsort.llm import decontaminate, durable, language, pieces, shingles, suffixes

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]
#: Languages that the corpus is to hold; probability from which a prediction counts.
WANTED, LEAST_SCORE = ("de", "en", "es", "fr"), 0.5


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep documents that are predicted to be in a language of WANTED with a probability of LEAST_SCORE or more.

    Null texts and texts without a letter are in no language. Where no row outside the held-out fold has a label there is nothing to
    learn from, and all texts with a letter stay. The label column is left as it is.
    """
    model = language.fit(docs.where(~language.held_out()))
    if not model.langs:
        return docs.where(F.col("text").rlike(r"\p{L}")).select(*COLUMNS)
    judged = language.identify(docs, model, lang_out="__lang", score_out="__score")
    return judged.where(F.col("__lang").isin(*WANTED) & (F.col("__score") >= LEAST_SCORE)).select(*COLUMNS)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep of documents linked by a similarity of 0.8 or more of their five-word shingles the one of the least id.

    Covering SimHash, and bands of minima for pairs beyond its three bits, find what is compared.
    """
    return shingles.keep_one(docs).select(*COLUMNS)


def cut_repeated_substrings(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Cut out passages of over 50 words that occur elsewhere too; documents stay, n_chars follows the text."""
    return suffixes.cut_passages(docs).withColumn("n_chars", F.char_length("text").cast("long")).select(*COLUMNS)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop documents of which a twentieth or more is benchmark passages."""
    judged = decontaminate.contamination(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"), keep=True)
    return judged.where(~F.col("contaminated")).select(*COLUMNS)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every text."""
    return pieces.encode(docs, public_tokenizers.path("piece_bpe_32k.model"), memo_pieces=150_000)


STAGES = [
    ("language", identify_language),
    ("near_duplicates", drop_near_duplicates),
    ("substrings", cut_repeated_substrings),
    ("decontamination", drop_contaminated),
    ("sentencepiece", encode),
]

#: Naive Bayes, near-duplicates and SentencePiece have no SQL form.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; the tables between stages lie in the shared checkpoint folder."""
    folder = durable.shared_folder(spark)
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    name = uuid.uuid4().hex
    for k, (stage, function) in enumerate(STAGES):
        docs = function(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs.write.parquet(f"{folder}/corpus-{name}/{k}-{stage}")
            docs = spark.read.parquet(f"{folder}/corpus-{name}/{k}-{stage}")
    return docs
