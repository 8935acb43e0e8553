"""SQL functions: expressions that Catalyst inlines, and a table function that packs a partition."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

DEFINITIONS = {
    "ifd": "(lp_with ARRAY<DOUBLE>, lp_without ARRAY<DOUBLE>) RETURNS DOUBLE RETURN exp((aggregate(lp_without, 0D, (s, x) -> s + x) - aggregate(lp_with, 0D, (s, x) -> s + x)) / size(lp_with))",
    "l2": "(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN sqrt(aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x))",
    "padding": "(used BIGINT, cells BIGINT) RETURNS DOUBLE RETURN CASE WHEN cells > 0 THEN 1 - used / cells ELSE 0D END",
}


def register(spark: SparkSession) -> None:
    """Temporary functions ``ifd``, ``l2``, ``padding`` and the table function ``pack_rows``."""
    for name, body in DEFINITIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")
    spark.udtf.register("pack_rows", udtf(PackRows, returnType="row_id int, sample_id long, offset int, length int"))


class PackRows:
    """``pack_rows(TABLE t PARTITION BY batch_id ORDER BY (n_tokens DESC, sample_id))``: first fit into rows of CONTEXT tokens."""

    CONTEXT = 4096

    def __init__(self) -> None:
        self.used: list[int] = []

    def eval(self, row):
        size = row["n_tokens"]
        spot = next((i for i, u in enumerate(self.used) if u + size <= self.CONTEXT), len(self.used))
        if spot == len(self.used):
            self.used.append(0)
        yield spot, row["sample_id"], self.used[spot], size
        self.used[spot] += size
