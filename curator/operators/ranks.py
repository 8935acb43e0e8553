"""Ranks without a window over all rows of a group."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from curator.sources.checkpoints import stage


def ranked_in_ranges(rows: DataFrame, by: list[str], order: list[Column]) -> DataFrame:
    """``rows`` plus ``rank`` (long, from 1) in the order of ``order`` within each group of ``by``.

    Rows are dealt to ranges of the whole sort key, which Spark balances on a sample of it, so neither a large group nor an outlying or frequent value puts
    more rows in a task; ``order`` should end with a unique column.  The sorted rows are stored with their place in their range, and the
    ranks come from prefix sums over one row per group and range.
    """
    sorted_ = rows.repartitionByRange(*by, *order).sortWithinPartitions(*by, *order)
    # The number holds the range in its upper bits and the place in the range below; it is stored, so it is made once.
    placed = stage(sorted_.withColumn("_at", F.monotonically_increasing_id()), "ranges")
    placed = placed.withColumn("_range", F.shiftright("_at", 33))
    parts = placed.groupBy("_range", *by).agg(F.count(F.lit(1)).alias("_n"), F.min("_at").alias("_first"))
    before = Window.partitionBy(*by).orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)
    parts = parts.select("_range", *by, "_first", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_ahead"))
    same = [F.col("a._range") == F.col("b._range"), *(F.col(f"a.{c}").eqNullSafe(F.col(f"b.{c}")) for c in by)]
    joined = placed.alias("a").join(parts.alias("b"), same)
    return joined.select(*(f"a.{c}" for c in rows.columns), (F.col("_ahead") + F.col("_at") - F.col("_first") + 1).cast("long").alias("rank"))
