"""Writers of selected and packed data."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def write_selection(selected: DataFrame, path: str, by: tuple[str, ...] = ("strategy", "rate_pct")) -> None:
    selected.write.mode("overwrite").partitionBy(*by).parquet(path)


def write_packed(packed: DataFrame, path: str, rows_per_file: int = 100_000) -> None:
    """Packed rows in (batch, row) order within each file."""
    packed.repartition("batch_id").sortWithinPartitions("batch_id", "row_id").write.mode("overwrite").option("maxRecordsPerFile", rows_per_file).parquet(path)


def write_jsonl(samples: DataFrame, path: str) -> None:
    samples.write.mode("overwrite").json(path)


def write_manifest(spark: SparkSession, path: str, name: str, rows: int, **parameters) -> None:
    """One row that tells what was written with which parameters."""
    one = spark.range(1).select(F.lit(name).alias("name"), F.lit(rows).cast("long").alias("n_rows"), F.to_json(F.create_map(*(F.lit(str(x)) for kv in sorted(parameters.items()) for x in kv)) if parameters else F.expr("map()")).alias("parameters"))
    one.write.mode("append").json(path)


def register_views(spark: SparkSession, **frames: DataFrame) -> None:
    for name, df in frames.items():
        df.createOrReplaceTempView(name)
