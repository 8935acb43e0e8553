"""Selection strategies: the hardest share of every cluster, and the baselines."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from curator.operators.ranks import ranked_in_ranges

#: Scores are ranked at this many places, so that equal scores computed in another order stay equal.
PLACES = 9
#: Cuts that the approximate plan can choose from, and the accuracy of its sketch.
STEPS, ACCURACY = 1000, 10_000


def quotas(sizes: DataFrame, rate_pct: int | None = None, budget: int | None = None, rounding: str = "ceil", count: int | None = None) -> DataFrame:
    """``sizes`` (cluster_id, n: a row per cluster) plus ``quota``.

    Of a rate: ``ceil``, ``floor``, ``round`` (half up) or ``largest_remainder``; a ``budget`` of samples is shared by largest remainder; ``count`` is per cluster.
    """
    if count is not None:
        return sizes.withColumn("quota", F.least(F.col("n"), F.lit(count)).cast("long"))
    whole = Window.partitionBy()
    total = F.sum("n").over(whole)
    if budget is not None or rounding == "largest_remainder":
        goal = F.least(F.lit(budget), total) if budget is not None else F.expr(f"(sum(n) over () * {rate_pct} + 99) div 100")
        share = sizes.withColumn("goal", goal).withColumn("total", total)
        # Products of two counts leave the range of a long from some 10^9 samples on.
        product = F.col("n").cast("decimal(19,0)") * F.col("goal").cast("decimal(19,0)")
        share = share.withColumn("_p", product).withColumn("low", F.expr("_p div total")).withColumn("rest", F.expr("_p % total"))
        spare = F.col("goal") - F.sum("low").over(whole)
        turn = F.row_number().over(Window.orderBy(F.desc("rest"), "cluster_id"))
        return share.select("cluster_id", "n", (F.col("low") + F.when(turn <= spare, 1).otherwise(0)).cast("long").alias("quota"))
    add = {"ceil": 99, "floor": 0, "round": 50}[rounding]
    return sizes.withColumn("quota", F.expr(f"(n * {rate_pct} + {add}) div 100"))


def _order(column: Column, descending: bool = True) -> list[Column]:
    key = F.round(column, PLACES)
    return [key.desc() if descending else key.asc(), F.col("sample_id").asc()]


def top_of_cluster(rows: DataFrame, order: list[Column], **quota) -> DataFrame:
    """``rows`` (with cluster_id) up to each cluster's quota, plus ``rank``, by one window per cluster."""
    sizes = rows.groupBy("cluster_id").agg(F.count(F.lit(1)).alias("n"))
    ranked = rows.withColumn("rank", F.row_number().over(Window.partitionBy("cluster_id").orderBy(*order)).cast("long"))
    # A row per cluster; the optimizer broadcasts it when it is small, as it is for any sensible k.
    return ranked.join(quotas(sizes, **quota).select("cluster_id", "quota"), "cluster_id").filter(F.col("rank") <= F.col("quota")).drop("quota")


def top_by_threshold(rows: DataFrame, value: str = "ifd", descending: bool = True, **quota) -> DataFrame:
    """The same rows as ``top_of_cluster``, with ranks from balanced ranges in place of a sort of each cluster in one task."""
    sizes = rows.groupBy("cluster_id").agg(F.count(F.lit(1)).alias("n"))
    ranked = ranked_in_ranges(rows, ["cluster_id"], _order(F.col(value), descending))
    return ranked.join(quotas(sizes, **quota).select("cluster_id", "quota"), "cluster_id").filter(F.col("rank") <= F.col("quota")).select(*rows.columns, "rank")


def top_approximately(rows: DataFrame, value: str = "ifd", descending: bool = True, **quota) -> DataFrame:
    """About each cluster's quota, by a cut from a mergeable sketch of its scores, without any sort; ``rank`` is null.

    A cluster of n rows keeps its quota to within n / STEPS + 2 n / ACCURACY rows, and those more that have the cut's score.
    """
    keyed = rows.withColumn("_x", F.round(F.col(value), PLACES) * (1 if descending else -1))
    fractions = [i / STEPS for i in range(STEPS + 1)]
    sketch = keyed.groupBy("cluster_id").agg(F.count(F.lit(1)).alias("n"), F.percentile_approx("_x", fractions, ACCURACY).alias("_q"))
    wanted = quotas(sketch.select("cluster_id", "n"), **quota).join(sketch.select("cluster_id", "_q", F.col("n").alias("_n")), "cluster_id")
    place = F.greatest(F.lit(1), F.least(F.lit(STEPS + 1), F.round((1 - F.col("quota") / F.col("_n")) * STEPS).cast("int") + 1))
    cut = wanted.filter("quota > 0").select("cluster_id", F.when(F.col("quota") < F.col("_n"), F.element_at("_q", place)).alias("_cut"))
    kept = keyed.join(cut, "cluster_id").filter(F.col("_cut").isNull() | (F.col("_x") >= F.col("_cut")))
    return kept.select(*rows.columns, F.lit(None).cast("long").alias("rank"))


def select_stratified(scored: DataFrame, rate_pct: int | None = 40, plan: str = "window", order: str = "desc", eligible: DataFrame | None = None, max_ifd: float | None = None, **quota) -> DataFrame:
    """``sample_id, cluster_id, ifd, rank`` of the hardest share of every cluster of ``scored``.

    ``plan``: ``window`` sorts each cluster, ``threshold`` sorts balanced ranges of all rows, ``approx`` cuts at approximate percentiles (and may keep a few more or
    less).  ``eligible`` holds the ids that may be chosen; ``max_ifd`` leaves out scores from there on.
    """
    rows = scored.select("sample_id", "cluster_id", "ifd")
    if eligible is not None:
        rows = rows.join(eligible.select("sample_id"), "sample_id", "left_semi")
    if max_ifd is not None:
        rows = rows.filter(F.col("ifd") < max_ifd)
    if not quota.keys() & {"budget", "count"}:
        quota["rate_pct"] = rate_pct
    if plan == "threshold":
        return top_by_threshold(rows, "ifd", order == "desc", **quota)
    if plan == "approx":
        return top_approximately(rows, "ifd", order == "desc", **quota)
    return top_of_cluster(rows, _order(F.col("ifd"), order == "desc"), **quota)


def _whole(scored: DataFrame) -> DataFrame:
    return scored.select("sample_id", F.lit(0).alias("cluster_id"), "ifd")


def select_difficulty(scored: DataFrame, rate_pct: int = 40, rounding: str = "ceil") -> DataFrame:
    """The hardest share of all samples; one cluster, so by threshold."""
    return top_by_threshold(_whole(scored), "ifd", True, rate_pct=rate_pct, rounding=rounding)


def select_random(scored: DataFrame, rate_pct: int = 40, seed: int = 42, rounding: str = "ceil") -> DataFrame:
    """A reproducible random share: the smallest seeded hashes, independent of partitioning."""
    rows = _whole(scored).withColumn("h", F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), F.col("sample_id"))), 1, 12), 16, 10).cast("double"))
    return top_by_threshold(rows, "h", False, rate_pct=rate_pct, rounding=rounding).drop("h")


def select_cluster(scored: DataFrame, rate_pct: int = 40, pick: str = "random", seed: int = 42, rounding: str = "ceil") -> DataFrame:
    """A share of every cluster without regard to difficulty: ``random`` members, or those most ``central``."""
    rows = scored.select("sample_id", "cluster_id", "ifd", "dist")
    if pick == "central":
        order = _order(F.col("dist"), False)
    else:
        order = [F.md5(F.concat(F.lit(f"{seed}:"), F.col("sample_id"))), F.col("sample_id")]
    return top_of_cluster(rows, order, rate_pct=rate_pct, rounding=rounding).drop("dist")


def rank_profile(scored: DataFrame) -> DataFrame:
    """``sample_id, cluster_id, ifd, rank, n, pct_rank``: one sort that serves every rate."""
    w = Window.partitionBy("cluster_id").orderBy(*_order(F.col("ifd")))
    n = F.count(F.lit(1)).over(Window.partitionBy("cluster_id"))
    return scored.select("sample_id", "cluster_id", "ifd", F.row_number().over(w).cast("long").alias("rank"), n.alias("n"), F.percent_rank().over(w).alias("pct_rank"))


def consistency(full: DataFrame, subset: DataFrame, by: str = "cluster_id") -> DataFrame:
    """``tv, kl, chi2``: how far the shares of ``by`` in ``subset`` are from those in ``full``."""
    a = full.groupBy(by).agg(F.count(F.lit(1)).alias("n"))
    b = subset.groupBy(by).agg(F.count(F.lit(1)).alias("m"))
    every = Window.partitionBy()
    p, q = F.col("n") / F.sum("n").over(every), F.coalesce("m", F.lit(0)) / F.sum(F.coalesce("m", F.lit(0))).over(every)
    both = a.join(b, by, "left").select(p.alias("p"), q.alias("q"))
    return both.agg((F.sum(F.abs(F.col("p") - F.col("q"))) / 2).alias("tv"), F.sum(F.when(F.col("q") > 0, F.col("q") * F.log(F.col("q") / F.col("p"))).otherwise(0.0)).alias("kl"), F.sum((F.col("q") - F.col("p")) ** 2 / F.col("p")).alias("chi2"))
