"""A training-data pipeline over ``documents``: rules, line dedup, near-dedup, mixing, encoding.

Every stage works on all rows that the one before it wrote, and takes any row: nulls in every column, empty and very long texts,
repeated rows and ids, further columns (which go) and empty tables.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from curator.llm import line_dedup, mixing, piece_bpe, quality, simhash
from curator.llm.entries import CAP, SHARE, WEIGHTS, vocabulary
from curator.llm.scratch import fresh_path
from curator.llm.text import n_words

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the rules keep; null and empty texts fail them, repeated rows are judged one by one."""
    return quality.judge_quality(docs.select(*COLUMNS)).filter("kept").select(*COLUMNS)


def deduplicated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One line of every component stays; documents that lose every line go, those without a line stay as they are.

    Rows that repeat id and text keep the same lines; null ids come last.
    """
    out = line_dedup.dedup_lines(docs.select(*COLUMNS)).filter((F.col("n_lines") == 0) | (F.col("n_dropped") < F.col("n_lines")))
    return out.withColumn("n_chars", F.coalesce(F.length("text"), "n_chars").cast("long")).select(*COLUMNS)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document of the smallest id of every component, one row if it is repeated, a null id last; texts without a word are one component."""
    return simhash.one_per_component(docs.select(*COLUMNS))


def mixed_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes them; those without a word are never taken, and of identical rows any may be."""
    sized = docs.select(*COLUMNS, n_words(F.col("text")).alias("size"), F.xxhash64("text").alias("tie"))
    out = mixing.materialize(mixing.mix_sources(sized, WEIGHTS, SHARE, CAP, tie_col="tie"))
    return out.withColumn("n_chars", F.length("text").cast("long")).select(*COLUMNS)


def encoded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Counts and digests of the token ids of every document of the mix, row by row; null text counts as empty."""
    return piece_bpe.encode_documents(docs.select("doc_id", "lang", "source", "text"), vocabulary("piece_bpe_32k.model"))


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("quality_rules", quality_rules),
    ("line_dedup", deduplicated_lines),
    ("simhash_near_dedup", near_duplicates),
    ("mixing", mixed_sources),
    ("sentencepiece", encoded),
]

#: SQL cannot express MinHash components, SimHash links or sentencepiece merges; the stages are tested against brute force.
ORACLE_SQL: str | None = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for at, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if at < len(STAGES) - 1:
            path = fresh_path(spark, name)
            docs.write.parquet(path)
            docs = spark.read.parquet(path)
    return docs
