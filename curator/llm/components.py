"""Connected components of an edge table by alternating star contraction (distributed union-find).

Each round hangs every node's neighbours on the smallest node of its neighbourhood, first the larger, then the
smaller ones.  Stars on the smallest node of each component remain after a number of
rounds logarithmic in the node count.  Only counts and checksums reach the driver.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .scratch import discard, stored


def _state(edges: DataFrame) -> tuple[int, int]:
    got = edges.agg(F.count(F.lit(1)).alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("x")).first()
    return got.n, int(got.x or 0)


def connected_components(edges: DataFrame, src: str = "src", dst: str = "dst") -> DataFrame:
    """``node, component``: the smallest node that each node of ``edges`` reaches.

    Edges are undirected; null ends, loops and repeats are ignored.  Nodes without an edge are not returned.
    """
    pairs = edges.select(F.greatest(src, dst).alias("u"), F.least(src, dst).alias("v")).filter(F.col(src).isNotNull() & F.col(dst).isNotNull() & (F.col("u") != F.col("v")))
    now = stored(pairs.distinct(), "edges")
    state = _state(now)
    while state[0]:
        both = now.union(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        # The minima are stored, so that both sides of the join are plain exchanges and a hot node's edges can be split.
        low = stored(both.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("k"), F.least("u", "m").alias("m")), "large")
        hung = both.filter("v > u").join(low, F.col("u") == F.col("k")).select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        hung = stored(hung, "hung")
        low2 = stored(hung.groupBy("u").agg(F.min("v").alias("m")).withColumnRenamed("u", "k"), "small")
        moved = hung.join(low2, F.col("u") == F.col("k")).filter("v != m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        after = stored(moved.union(low2.select(F.col("k").alias("u"), F.col("m").alias("v"))).distinct(), "edges")
        for old in (now, low, hung, low2):
            discard(old)
        now, before, state = after, state, _state(after)
        if state == before:
            break
    return now.select(F.col("u").alias("node"), F.col("v").alias("component")).union(now.select(F.col("v"), F.col("v")).distinct())
