"""Readers with declared schemas."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SCHEMAS = {
    "conversations": "conv_id long, turn long, role string, text string",
    "samples": "sample_id long, instruction string, response string",
    "token_logprobs": "sample_id long, pos int, lp_with double, lp_without double",
}


def require(df: DataFrame, *columns: str) -> DataFrame:
    """``df`` unless a column is missing, which is named in the error."""
    if missing := [c for c in columns if c not in df.columns]:
        raise ValueError(f"missing columns {missing}; there are {df.columns}")
    return df


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_samples(spark: SparkSession, path: str, fmt: str = "json", kind: str = "samples") -> DataFrame:
    """Chat logs or samples from json lines, csv, orc or parquet, by a declared schema."""
    reader = spark.read.schema(SCHEMAS[kind])
    return (reader.option("header", True) if fmt == "csv" else reader).format(fmt).load(path)


def page_text(pages: DataFrame, html_col: str = "html") -> DataFrame:
    """``page_id, text``: visible text of an HTML page (tags, scripts and the common entities resolved)."""
    text = F.regexp_replace(F.col(html_col), r"(?is)<(script|style)\b.*?</\1>", " ")
    text = F.regexp_replace(text, r"(?s)<[^>]*>", " ")
    for entity, char in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&nbsp;", " "), ("&amp;", "&")):
        text = F.replace(text, F.lit(entity), F.lit(char))
    return pages.select("page_id", F.trim(F.regexp_replace(text, r"[ \t\r\n]+", " ")).alias("text"))
