"""Mixing sources to target weights (operator 6), in DataFrame expressions only.

Every document gets a hash-random key.  Keys are cut into ranges; the token counts per (source, range) give distributed prefix
sums: one over the ranges of a source, one inside each range.  Each source's documents are taken in key order up to its exact
budget, whole epochs first.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .scratch import stored
from .text import SPACE_CLASS, WORD_CLASS, free_name

#: Key ranges per source, 2^RANGE_BITS: a source of 3e10 documents has 8e6 in a range.
RANGE_BITS = 12
SEED = 17


def _targets(cells: DataFrame, weights: Sequence[int], share: float, cap: float) -> DataFrame:
    """One row per source: its size, and the target after the excess over ``cap`` times the size is dealt out again by weight.

    Resharing until nobody is above ends at one level ``t = least(cap, level * weight)``; the level is found from
    sums over sources in the order in which they fill up.
    """
    per = cells.groupBy("g").agg(F.sum("cell").alias("source_size"))
    turn = F.element_at(F.array(*(F.lit(float(w)) for w in weights)), (F.pmod(F.row_number().over(Window.orderBy("g")) - 1, F.lit(len(weights))) + 1).cast("int"))
    per = per.withColumn("weight", turn).withColumn("most", cap * F.col("source_size"))
    full = Window.orderBy(F.col("most") / F.col("weight"), "g")
    everyone = Window.partitionBy()
    level = (share * F.sum("source_size").over(everyone) - F.coalesce(F.sum("most").over(full.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))) / F.sum("weight").over(
        full.rowsBetween(Window.currentRow, Window.unboundedFollowing)
    )
    per = per.withColumn("level", level).withColumn("fits", F.when(F.col("level") <= F.col("most") / F.col("weight"), F.struct(F.col("most") / F.col("weight"), "g", "level")))
    found = F.min("fits").over(everyone)["level"]
    return per.select("g", "source_size", F.coalesce(F.least("most", found * F.col("weight")), F.col("most")).alias("target"))


def mix_sources(
    docs: DataFrame, weights: Sequence[int] = (3, 1, 2), share: float = 1.5, cap: float = 2.0, source_col: str = "source", size_col: str = "size", id_col: str = "doc_id", tie_col: str | None = None, seed: int = SEED
) -> DataFrame:
    """Columns of ``docs`` plus ``source_size``, ``target`` and ``taken`` (tokens that the mix takes of the row, repeats counted).

    Sources in code-point order, null last, weigh ``weights`` in turn and share ``share`` times all tokens; no target is above ``cap`` times
    its source's size.  A source's taken tokens add up to its target, rounded; its last document may be taken in part.
    Row order, partitioning and reruns do not matter: keys are hashes of the id and of ``tie_col``, ties go by id, size and ``tie_col``, so only identical rows
    can change places.  Null sizes count as zero, null ids are one more id, an empty table gives an empty one.
    Columns that bear an added column's name are replaced.
    """
    names = [c for c in docs.columns if c.lower() not in ("source_size", "target", "taken")]
    g, key, cell, size = (free_name(n, names) for n in ("mix_source", "mix_key", "mix_cell", "mix_size"))
    base = docs.select(*names).withColumns(
        {
            g: F.when(F.col(source_col).isNull(), "1").otherwise(F.concat(F.lit("0"), F.col(source_col))),
            # The tie column is part of the key, so rows that share an id, or have none, are dealt to all ranges.
            key: F.xxhash64(F.lit(seed), F.col(id_col), F.col(id_col).isNull(), *([F.col(tie_col)] if tie_col else [])),
            size: F.coalesce(F.col(size_col).cast("long"), F.lit(0)),
        }
    )
    base = base.withColumn(cell, F.shiftrightunsigned(F.col(key), 64 - RANGE_BITS))
    cells = stored(base.groupBy(F.col(g).alias("g"), F.col(cell).alias("c")).agg(F.sum(size).alias("cell")), "cells")
    before = Window.partitionBy("g").orderBy("c").rowsBetween(Window.unboundedPreceding, -1)
    plan = cells.withColumn("before", F.coalesce(F.sum("cell").over(before), F.lit(0))).join(_targets(cells, weights, share, cap), "g")
    plan = plan.withColumn("budget", F.least(F.round("target").cast("long"), F.floor(cap * F.col("source_size"))))
    plan = plan.withColumn("epochs", F.when(F.col("source_size") > 0, F.expr("budget div source_size")).otherwise(0))
    plan = stored(plan.select(F.col("g").alias("_g"), F.col("c").alias("_c"), "before", "epochs", (F.col("budget") - F.col("epochs") * F.col("source_size")).alias("rest"), F.col("source_size").alias("_s"), F.col("target").alias("_t")), "plan")
    ties = [F.col(key), F.col(id_col), F.col(size), *([F.col(tie_col)] if tie_col else [])]
    ahead = Window.partitionBy("_g", "_c").orderBy(*ties).rowsBetween(Window.unboundedPreceding, -1)
    joined = base.join(plan, (F.col(g) == F.col("_g")) & (F.col(cell) == F.col("_c")))
    ahead_sum = F.col("before") + F.coalesce(F.sum(size).over(ahead), F.lit(0))
    extra = F.greatest(F.lit(0), F.least(F.col(size), F.col("rest") - ahead_sum))
    return joined.select(*names, F.col("_s").alias("source_size"), F.col("_t").alias("target"), (F.col("epochs") * F.col(size) + extra).cast("long").alias("taken"))


def materialize(mixed: DataFrame, text_col: str = "text", size_col: str = "size") -> DataFrame:
    """The rows of a mix: each document once per whole take, and a last copy cut to the words of a partial take.

    Rows that the mix takes nothing of go, those of null or empty text among them.  Repeated rows are taken row by row, an empty table gives an empty one, and
    a cut text of any length keeps its white space up to the last word taken.
    """
    copies = F.expr(f"CAST(ceil(taken / `{size_col}`) AS INT)")
    turn = free_name("mix_turn", mixed.columns)
    rows = mixed.filter("taken > 0").withColumn(turn, F.explode(F.sequence(F.lit(1), copies)))
    left = F.col("taken") - (F.col(turn) - 1) * F.col(size_col)
    # The text up to the end of word number ``left`` stays as it is.
    word_ends = F.array_join(F.slice(F.regexp_extract_all(F.col(text_col), F.lit(f"{SPACE_CLASS}*{WORD_CLASS}"), F.lit(0)), F.lit(1), left.cast("int")), "")
    return rows.withColumn(text_col, F.when(left >= F.col(size_col), F.col(text_col)).otherwise(word_ends)).drop(turn)
