"""Instruction vectors: hashed tokens, given tables or a function."""

from __future__ import annotations

from collections.abc import Callable
from typing import Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from curator.functions.expr import norm
from curator.sources.checkpoints import stage


def hashed_vectors(pairs: DataFrame, dim: int = 64, seed: int = 42, weight: str = "count", column: str = "instr") -> DataFrame:
    """``sample_id, v``: signed hashed bag of tokens of unit length; an empty instruction has the zero vector.

    ``weight``: ``count``, or ``tfidf`` with smoothed document frequencies over the samples.  ``column``: ``instr``, ``resp``, or ``both`` one after the other.
    """
    if column == "both":
        pairs = pairs.withColumn("both", F.concat("instr", "resp"))
    pairs = stage(pairs.select("sample_id", column), "instructions")  # read twice, cut into tokens once
    toks = pairs.select("sample_id", F.explode(column).alias("tok"))
    if weight == "tfidf":
        df = toks.distinct().groupBy("tok").agg(F.count(F.lit(1)).alias("df"))
        n = pairs.count()
        toks = toks.join(df, "tok").withColumn("w", F.log((1 + F.lit(n)) / (1 + F.col("df"))) + 1)
    else:
        toks = toks.withColumn("w", F.lit(1.0))
    h = F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), F.col("tok"))), 1, 8), 16, 10).cast("long")
    sign = F.when(F.pmod((h / dim).cast("long"), F.lit(2)) == 0, 1.0).otherwise(-1.0)
    cells = toks.groupBy("sample_id", F.pmod(h, F.lit(dim)).cast("int").alias("b")).agg(F.sum(sign * F.col("w")).alias("x"))
    filled = cells.groupBy("sample_id").agg(F.map_from_entries(F.collect_list(F.struct("b", "x"))).alias("m"))
    raw = F.transform(F.sequence(F.lit(0), F.lit(dim - 1)), lambda b: F.coalesce(F.element_at("m", b), F.lit(0.0)))
    dense = pairs.select("sample_id").join(filled, "sample_id", "left").select("sample_id", F.coalesce(raw, F.array_repeat(F.lit(0.0), dim)).alias("v"))
    return dense.withColumn("len", norm(F.col("v"))).select("sample_id", F.when(F.col("len") > 0, F.transform("v", lambda x: x / F.col("len"))).otherwise(F.col("v")).alias("v"))


def table_vectors(vectors: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    return vectors.select(F.col(id_col).alias("sample_id"), F.col(vec_col).cast("array<double>").alias("v"))


def function_vectors(pairs: DataFrame, fn: Callable, column: str = "instruction") -> DataFrame:
    """``fn``: iterator of pandas series of texts to iterator of series of lists."""
    import pandas as pd

    def run(batches):
        return fn(batches)

    run.__annotations__ = {"batches": Iterator[pd.Series], "return": Iterator[pd.Series]}
    return pairs.select("sample_id", F.pandas_udf(run, "array<double>")(F.col(column)).alias("v"))
