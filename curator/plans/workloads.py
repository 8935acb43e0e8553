"""The experiment workloads on the given tables, in tidy form.

No language model can be trained here; an n-gram model of the chosen samples stands in for the tuned one, scored by held-out perplexity and
greedy next-token accuracy.  The numbers show that the pipeline computes, not that a selection helps a real model.
"""

from __future__ import annotations

import re
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from curator.operators import evaluate, kmeans, packing, select
from curator.operators.scoring import NGramScorer
from curator.plans import methods as m
from curator.plans import oracles as o
from curator.sources.checkpoints import stage
from curator.sources.tables import read_table

RATES = (10, 20, 30, 40, 50, 60)
PAD_CONTEXTS, PAD_SIZES = (512, 1024, 4096), (16, 64, 256)
STRATEGIES = ("random", "difficulty", "kmeans", "combined")
TIDY = ("dataset", "model", "strategy", "rate_pct", "metric", "value")


def union(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def heldout_split(pairs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Training and held-out samples; a fifth is held out by a hash of the id."""
    fold = F.pmod(F.conv(F.substring(F.md5(F.col("sample_id").cast("string")), 1, 4), 16, 10).cast("int"), F.lit(5))
    marked = pairs.withColumn("fold", fold)
    return marked.filter("fold <> 0").drop("fold"), marked.filter("fold = 0").drop("fold")


def _as_model(df: DataFrame, model: str) -> DataFrame:
    """The tokens that a model sees, ``t``, beside the other columns; for ``char`` the text, so that two characters predict the third."""
    # No token holds a blank.
    t = F.col("text") if model == "char" else F.when(F.col("text") == "", F.array().cast("array<string>")).otherwise(F.split("text", " "))
    return df.select(*(c for c in df.columns if c != "text"), t.alias("t"))


def evaluated(train: DataFrame, members: DataFrame, held: DataFrame, data: str, model: str, variants: list[str], base: DataFrame | None = None) -> DataFrame:
    """Tidy rows of the held-out measures of one model per variant, ``strategy:rate``, of ``members`` (``sample_id, variant``).

    ``base``: samples of the other data set, of which a model that was not tuned is made (``none:0``).
    """
    own = members.groupBy(F.col("sample_id").alias("id")).agg(F.collect_set("variant").alias("variants"))
    # Texts are shuffled to their models, not arrays of tokens.
    texts = train.select(F.col("sample_id").alias("id"), "text").join(own, "id").select("variants", "text")
    if base is not None:
        texts, variants = texts.unionByName(base.select(F.array(F.lit("none:0")).alias("variants"), "text")), [*variants, "none:0"]
    rows = evaluate.heldout_by_variant(_as_model(texts, model), _as_model(held.select(F.col("sample_id").alias("id"), "text"), model), variants)
    label = F.split("variant", ":")
    values = F.explode(F.array(*(F.struct(F.lit(m).alias("metric"), F.col(m).alias("value")) for m in ("heldout_ppl", "greedy_accuracy")))).alias("m")
    return rows.select(F.lit(data).alias("dataset"), F.lit(model).alias("model"), label[0].alias("strategy"), label[1].cast("int").alias("rate_pct"), values).select("dataset", "model", "strategy", "rate_pct", "m.metric", "m.value")


def _prepared(s: SparkSession, d: str, data: str, model: NGramScorer | None = None) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Training and held-out samples (``sample_id, text``: the tokens with blanks between), and the scores of the training samples."""
    train, held = heldout_split(stage(m.pairs(s, d, data).select("sample_id", F.array_join(F.concat("instr", "resp"), " ").alias("text")), "samples"))
    return train, held, m.scored(s, d, data, model=model).join(train.select("sample_id"), "sample_id", "left_semi")


def _all_prepared(s: SparkSession, d: str) -> dict[str, tuple[DataFrame, DataFrame, DataFrame]]:
    """``_prepared`` of both data sets with one model of the corpus, which goes before anything is evaluated."""
    scorer = m.corpus_model(s, d)
    ready = {data: _prepared(s, d, data, scorer) for data in ("pairs", "documents")}
    scorer.let_go(model=True)
    return ready


def _rates(rows: DataFrame, rates: tuple[int, ...]) -> DataFrame:
    """``sample_id, variant``: all samples (``full:100``) and the hardest share of every cluster at each rate, from one ranking."""
    kept = _by_rate(select.rank_profile(rows), rates).select("sample_id", F.concat(F.lit("combined:"), F.col("rate_pct")).alias("variant"))
    return stage(kept.unionByName(rows.select("sample_id", F.lit("full:100").alias("variant"))), "variants")


def _swept(s: SparkSession, d: str, rates: tuple[int, ...], untuned: bool) -> DataFrame:
    ready = _all_prepared(s, d)
    parts = []
    for data, (train, held, rows) in ready.items():
        members = _rates(rows, rates)
        other = ready["documents" if data == "pairs" else "pairs"][0]
        for model in ("word", "char"):
            # A few rows each, stored, so that the plans of the grid do not add up.
            parts.append(stage(evaluated(train, members, held, data, model, ["full:100", *(f"combined:{r}" for r in rates)], other if untuned else None), "measures"))
    return union(parts)


def _strategies(rows: DataFrame, rate: int) -> dict[str, DataFrame]:
    return {
        "random": select.select_random(rows, rate),
        "difficulty": select.select_difficulty(rows, rate),
        "kmeans": select.select_cluster(rows, rate),
        "combined": select.select_stratified(rows, rate),
    }


def main_results(s: SparkSession, d: str) -> DataFrame:
    """No tuning, full data, 40 and 30 percent, on two data sets with two models.

    Who is not tuned on a data set has seen the training samples of the other one only.
    """
    return m.six(_swept(s, d, (40, 30), True))


def _ablated(ready: tuple[DataFrame, DataFrame, DataFrame], data: str, rate: int) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Measures of the four strategies, the scores, and ``sample_id, strategy`` of what they choose."""
    train, held, rows = ready
    member = stage(union([v.select("sample_id", F.lit(k).alias("strategy")) for k, v in _strategies(rows, rate).items()]), "strategies")
    labelled = member.select("sample_id", F.concat("strategy", F.lit(f":{rate}")).alias("variant"))
    return stage(evaluated(train, labelled, held, data, "word", [f"{k}:{rate}" for k in STRATEGIES]), "measures"), rows, member


def strategy_ablation(s: SparkSession, d: str) -> DataFrame:
    """Four strategies, pairs at 40 and documents at 30 percent: held-out measures, shift of the mix, difficulty."""
    parts, ready = [], _all_prepared(s, d)
    for data, rate in (("pairs", 40), ("documents", 30)):
        measures, rows, member = _ablated(ready[data], data, rate)
        parts.append(measures)
        picked = member.join(rows, "sample_id")
        tags = [F.lit(data).alias("dataset"), F.lit("word").alias("model"), "strategy", F.lit(rate).alias("rate_pct")]
        parts.append(picked.groupBy("strategy").agg(F.avg("ifd").alias("value")).select(*tags, F.lit("mean_ifd").alias("metric"), "value"))
        for name in STRATEGIES:
            parts.append(select.consistency(rows, picked.filter(F.col("strategy") == name)).withColumn("strategy", F.lit(name)).select(*tags, F.lit("tv").alias("metric"), F.col("tv").alias("value")))
    return m.six(union(parts).select(*TIDY))


def rate_sweep(s: SparkSession, d: str) -> DataFrame:
    """Held-out measures of nested subsets of one ranking, 10 to 60 percent, against full data, on two data sets with two models."""
    return m.six(_swept(s, d, RATES, False))


def best_rates(s: SparkSession, d: str) -> DataFrame:
    """The rate of the lowest held-out perplexity for each data set and model, and that of full data."""
    rows = rate_sweep(s, d).filter("metric = 'heldout_ppl'")
    part = F.when(F.col("strategy") == "combined", F.struct("value", "rate_pct"))
    return rows.groupBy("dataset", "model").agg(F.min(part)["rate_pct"].alias("best_rate"), F.min(part)["value"].alias("at_best"), F.max(F.when(F.col("strategy") == "full", F.col("value"))).alias("at_full"))


def _by_rate(ranked: DataFrame, rates: tuple[int, ...] = RATES) -> DataFrame:
    every = F.explode(F.array(*(F.lit(r) for r in rates))).alias("rate_pct")
    return ranked.select("*", every).filter(F.expr("rank <= (n * rate_pct + 99) div 100"))


def rate_sweep_sizes(s: SparkSession, d: str) -> DataFrame:
    return m.six(_by_rate(select.rank_profile(m.scored(s, d))).groupBy("rate_pct").agg(F.count(F.lit(1)).alias("n"), F.avg("ifd").alias("mean_ifd")))


def rate_score_corr(s: SparkSession, d: str) -> DataFrame:
    """Correlation of the rate with each held-out measure, over the subsets of a sweep."""
    rows = rate_sweep(s, d).filter("strategy = 'combined'")
    return m.six(rows.groupBy("dataset", "model", "metric").agg(F.corr("rate_pct", "value").alias("r")))


def redundancy_by_rate(s: SparkSession, d: str) -> DataFrame:
    """Share of chosen documents whose response repeats another chosen one, by rate."""
    texts = m.pairs(s, d, "documents").select("sample_id", F.md5(F.array_join("resp", " ")).alias("h"))
    kept = _by_rate(select.rank_profile(m.scored(s, d, "documents"))).join(texts, "sample_id")
    per = kept.groupBy("rate_pct", "h").agg(F.count(F.lit(1)).alias("c"))
    return m.six(per.groupBy("rate_pct").agg(F.sum("c").alias("n"), (1 - F.count(F.lit(1)) / F.sum("c")).alias("duplicate_share")))


def _padding_rates(n: DataFrame, size: int) -> DataFrame:
    """``context, batch, layout, rows, cells, padding_rate, truncated`` of every layout over all samples."""
    b = packing.form_batches(n, size).persist()
    shape = ["layout", "rows", "cells", "used", "padding_rate", "attention_cells", "peak_cells", "peak_attention", "truncated"]
    report = lambda v, k, context: packing.layout_report(v, k).select(context.alias("context"), F.lit(size).alias("batch"), *shape)
    # These two do not depend on the context.
    every = F.explode(F.array(*(F.lit(c) for c in PAD_CONTEXTS)))
    parts = [report(packing.pad_layout(b), "pad_longest", every), report(packing.fixed_pack(b), "fixed_pack", every)]
    for context in PAD_CONTEXTS:
        made = {
            "pad_model_max": packing.pad_layout(b, context),
            "next_fit_asc": packing.batch_layout(packing.dynamic_pack(b, context, "next", False)),
            "next_fit_desc": packing.batch_layout(packing.dynamic_pack(b, context, "next")),
            "first_fit_desc": packing.batch_layout(packing.dynamic_pack(b, context, "first")),
            "best_fit_desc": packing.batch_layout(packing.dynamic_pack(b, context, "best")),
        }
        parts += [report(v, k, F.lit(context)) for k, v in made.items()]
    # One row per context and layout: they come to the driver, so that the plans of all batch sizes do not add up there.
    rates = union(parts)
    out = n.sparkSession.createDataFrame(rates.collect(), rates.schema)
    b.unpersist()
    return out


def padding_comparison(s: SparkSession, d: str) -> DataFrame:
    """Padding rates, costs and peaks of the layouts for two data sets, three contexts and three batch sizes, over all samples.

    Cells stand for time and the peak of a batch for memory; ``saved_cells`` and ``saved_peak`` are the shares saved against one sample a row padded to the
    longest of the batch.  ``context_use`` is the share of the context that an average row fills, ``samples_a_row`` and ``rows_a_batch`` tell how rows are shared.
    A sample longer than the context has a row of its own in packed layouts and is cut where a layout has a fixed width (``truncated`` tokens);
    ``long_samples`` and ``long_tokens`` are the shares of such samples and of their tokens.
    """
    parts = []
    for data in ("pairs", "documents"):
        n = m.lengths(s, d, data).persist()
        long = F.col("n_tokens") > F.col("context")
        shares = n.select("n_tokens", F.explode(F.array(*(F.lit(c) for c in PAD_CONTEXTS))).alias("context")).groupBy("context")
        shares = shares.agg(F.avg(long.cast("int")).alias("long_samples"), (F.sum(F.when(long, F.col("n_tokens")).otherwise(0)) / F.sum("n_tokens")).alias("long_tokens"))
        rates = union([_padding_rates(n, size) for size in PAD_SIZES])
        total = n.count()
        plain = Window.partitionBy("context", "batch")
        against = lambda c: F.max(F.when(F.col("layout") == "pad_longest", F.col(c))).over(plain)
        rates = rates.withColumns({"saved_cells": 1 - F.col("cells") / against("cells"), "saved_peak": 1 - F.col("peak_cells") / against("peak_cells")})
        rates = rates.withColumns({"context_use": F.col("used") / (F.col("rows") * F.col("context")), "samples_a_row": F.lit(total) / F.col("rows"), "rows_a_batch": F.col("rows") / F.ceil(F.lit(total) / F.col("batch"))})
        parts.append(rates.join(shares, "context").select(F.lit(data).alias("dataset"), *rates.columns, "long_samples", "long_tokens"))
    return m.six(union(parts))


def cluster_sweep(s: SparkSession, d: str) -> DataFrame:
    """Sizes, cost and shift of the mix for several numbers of clusters."""
    v = m.vectors(s, d).persist()
    scores = m.scores(s, d).select("sample_id", "ifd").persist()
    parts = []
    for k in (5, 10, 20):
        rows = scores.join(kmeans.assign(v, kmeans.fit(v, k, m.ITERS)).drop("v"), "sample_id").persist()
        report = kmeans.report(rows).agg(F.count(F.lit(1)).alias("clusters"), F.min("n").alias("smallest"), F.max("n").alias("largest"), F.sum("sse").alias("sse"))
        picked = rows.join(select.select_stratified(rows).select("sample_id"), "sample_id", "left_semi")
        parts.append(report.join(select.consistency(rows, picked).select("tv")).select(F.lit(k).alias("k"), "*"))
    return m.six(union(parts))


def dataset_diversity(s: SparkSession, d: str) -> DataFrame:
    """Type/token ratio, repeated and nearly repeated instructions, mean length, and mean distance of the vectors from their centre, of the two data sets.

    Instructions count as near copies if their vectors have the same signs throughout.
    """
    parts = []
    for data in ("pairs", "documents"):
        p = m.pairs(s, d, data)
        toks = p.select(F.explode(F.concat("instr", "resp")).alias("t")).agg((F.count_distinct("t") / F.count("t")).alias("type_token"))
        rest = p.agg((1 - F.count_distinct(F.md5(F.array_join("instr", " "))) / F.count(F.lit(1))).alias("repeated"), F.avg(F.size("resp")).alias("mean_resp"))
        v = stage(m.vectors(s, d, data), "vectors")
        signs = F.array_join(F.transform("v", lambda x: F.when(x > 0, "+").otherwise("-")), "")
        near = v.agg((1 - F.count_distinct(signs) / F.count(F.lit(1))).alias("near_copies"))
        spread = kmeans.assign(v, kmeans.fit(v, 1, 1)).agg(F.avg("dist").alias("mean_dist"))
        parts.append(toks.join(rest).join(near).join(spread).select(F.lit(data).alias("dataset"), "*"))
    return m.six(union(parts))


def consistency_mix(s: SparkSession, d: str) -> DataFrame:
    """How far the documents of each strategy at 40 percent are from all: shares by language and by source, and the mean vector."""
    rows = m.scored(s, d, "documents")
    labels = read_table(s, d, "documents").select(F.col("doc_id").alias("sample_id"), *(F.coalesce(c, F.lit("none")).alias(c) for c in ("lang", "source")))
    full = stage(rows.join(labels, "sample_id").join(m.vectors(s, d, "documents"), "sample_id"), "labelled")
    member = stage(union([x.select("sample_id", F.lit(k).alias("strategy")) for k, x in _strategies(rows, 40).items()]), "strategies")
    picked = full.join(member, "sample_id")
    parts = []
    for by in ("lang", "source"):
        for name in STRATEGIES:
            parts.append(select.consistency(full, picked.filter(F.col("strategy") == name), by).select(F.lit(name).alias("strategy"), F.lit(by).alias("by"), F.col("tv").alias("value")))
    centre = full.select(F.posexplode("v").alias("dim", "x")).groupBy("dim").agg(F.avg("x").alias("a"))
    own = picked.select("strategy", F.posexplode("v").alias("dim", "x")).groupBy("strategy", "dim").agg(F.avg("x").alias("b"))
    shift = own.join(centre, "dim").groupBy("strategy").agg(F.sqrt(F.sum((F.col("a") - F.col("b")) ** 2)).alias("value"))
    parts.append(shift.select("strategy", F.lit("mean_vector").alias("by"), "value"))
    return m.six(union(parts))


def strategy_overlap(s: SparkSession, d: str) -> DataFrame:
    """Jaccard similarity of the subsets of every two strategies at 40 percent."""
    rows = m.scored(s, d).persist()
    member = union([v.select("sample_id", F.lit(k).alias("strategy")) for k, v in _strategies(rows, 40).items()])
    sizes = member.withColumn("n", F.count(F.lit(1)).over(Window.partitionBy("strategy")))
    a, b = (sizes.select("sample_id", F.col("strategy").alias(x), F.col("n").alias(f"n_{x}")) for x in ("a", "b"))
    both = a.join(b, "sample_id").filter("a < b").groupBy("a", "b", "n_a", "n_b").agg(F.count(F.lit(1)).alias("c"))
    return m.six(both.select("a", "b", (F.col("c") / (F.col("n_a") + F.col("n_b") - F.col("c"))).alias("jaccard")))


def _heldout(s: SparkSession, d: str, metric: str) -> DataFrame:
    train, held, rows = _prepared(s, d, "pairs")
    members = select.select_stratified(rows, 40).select("sample_id", F.lit("combined:40").alias("variant"))
    return m.six(evaluated(train, members, held, "pairs", "word", ["combined:40"]).filter(F.col("metric") == metric).select("metric", "value"))


def best_strategy(s: SparkSession, d: str) -> DataFrame:
    """The strategy of the lowest held-out perplexity within 40 percent on each data set."""
    ready = _all_prepared(s, d)
    rows = union([_ablated(ready[data], data, rate)[0] for data, rate in (("pairs", 40), ("documents", 30))]).filter("metric = 'heldout_ppl'")
    best = evaluate.best_strategy(m.six(rows).withColumn("value", -F.col("value")), 40)
    return best.select("dataset", "model", "strategy", (-F.col("value")).alias("heldout_ppl"))


QUERIES = {
    "main_results": main_results,
    "strategy_ablation": strategy_ablation,
    "rate_sweep": rate_sweep,
    "best_rates": best_rates,
    "rate_sweep_sizes": rate_sweep_sizes,
    "rate_score_corr": rate_score_corr,
    "redundancy_by_rate": redundancy_by_rate,
    "padding_comparison": padding_comparison,
    "cluster_sweep": cluster_sweep,
    "dataset_diversity": dataset_diversity,
    "consistency_mix": consistency_mix,
    "strategy_overlap": strategy_overlap,
    "heldout_ppl": lambda s, d: _heldout(s, d, "heldout_ppl"),
    "greedy_accuracy": lambda s, d: _heldout(s, d, "greedy_accuracy"),
    "best_strategy": best_strategy,
}

_RATES_SQL = "(SELECT unnest([10, 20, 30, 40, 50, 60]) AS rate_pct)"
_SWEEP = f"SELECT rate_pct::INTEGER AS rate_pct, count(*) AS n, round(avg(ifd), 6) AS mean_ifd FROM ({o.ranked()}) CROSS JOIN {_RATES_SQL} WHERE rank <= (n * rate_pct + 99) // 100 GROUP BY 1"
_DOC_ALL = {"dt": o.DOC_PAIRS["dt"], "tp": o.DOC_PAIRS["dp"]} | o.NGRAM | o.EMBED | o.kmeans() | o.SCORED
_FOLD = "('0x' || substr(md5(sample_id::VARCHAR), 1, 4))::INTEGER % 5"
_TRAINED = o.SCORED["scored"] + f" WHERE {_FOLD} <> 0"
_CHARS = "(SELECT sample_id, string_split(array_to_string(list_concat(instr, resp), ' '), '') AS c FROM tp)"
_TOKENS = {
    "word": "SELECT sample_id, list_concat(instr, resp) AS t FROM tp",
    "char": f"SELECT sample_id, CASE WHEN len(c) > 1 THEN list_transform(list_zip(c[:-2], c[2:]), lambda p: p[1] || p[2]) ELSE [] END AS t FROM {_CHARS}",
}


def _prefixed(parts: dict[str, str], prefix: str) -> dict[str, str]:
    """The tables of ``parts`` under names of their own; whatever else they read keeps its name."""
    names = "|".join(sorted(parts, key=len, reverse=True))
    return {prefix + k: re.sub(rf"\b({names})\.", rf"{prefix}\1.", re.sub(rf"\b(FROM|JOIN) ({names})\b", rf"\1 {prefix}\2", body)) for k, body in parts.items()}


def _measured(model: str, base: str | None = None) -> dict[str, str]:
    """Needs ``tp`` and ``member`` (sample_id, variant); ends in ``measures`` (variant, metric, value).  ``base``: another table like ``tp`` for ``none:0``."""
    none = f" UNION ALL SELECT 'none:0', t FROM ({_TOKENS[model].replace('FROM tp', f'FROM {base}')}) WHERE {_FOLD} <> 0" if base else ""
    return {
        "tt": _TOKENS[model],
        "tv": f"SELECT variant, t FROM member JOIN tt USING (sample_id) WHERE len(t) > 0{none}",
        "hd": f"SELECT sample_id, t FROM tt WHERE {_FOLD} = 0 AND len(t) > 0",
        "vc": "SELECT variant, tok, count(*) AS n FROM (SELECT variant, unnest(t) AS tok FROM tv) GROUP BY ALL",
        "vs": "SELECT variant, sum(n) AS total, count(*) AS v FROM vc GROUP BY variant",
        "vb": "SELECT variant, prev, tok, count(*) AS n FROM (SELECT variant, unnest(list_concat(['<s>'], t[:-2])) AS prev, unnest(t) AS tok FROM tv) GROUP BY ALL",
        "vh": "SELECT variant, prev, sum(n) AS c FROM vb GROUP BY ALL",
        "hr": "SELECT sample_id, unnest(generate_series(0, len(t) - 1)) AS g, unnest(list_concat(['<s>'], t[:-2])) AS prev, unnest(t) AS tok FROM hd",
        "hk": "SELECT s.variant, sample_id, g, s.v, coalesce(q.tok, '<unk>') AS w, coalesce(q.n / s.total, 0) AS pu FROM hr r CROSS JOIN vs s LEFT JOIN vc q ON q.variant = s.variant AND q.tok = r.tok",
        "hw": "SELECT *, coalesce(lag(w) OVER (PARTITION BY variant, sample_id ORDER BY g), '<s>') AS p, row_number() OVER (PARTITION BY variant, sample_id, w ORDER BY g) - 1 AS seen FROM hk",
        "hl": """SELECT x.variant, ln(0.4 * CASE WHEN h.c IS NULL THEN pu ELSE coalesce(b.n, 0) / h.c END + 0.2 * pu + 0.1 / (v + 1) + CASE WHEN g > 0 THEN 0.3 * seen / g ELSE 0.3 * pu END) AS lp
  FROM hw x LEFT JOIN vb b ON b.variant = x.variant AND b.prev = x.p AND b.tok = x.w LEFT JOIN vh h ON h.variant = x.variant AND h.prev = x.p""",
        "gs": "SELECT variant, prev, tok AS guess FROM (SELECT b.variant, b.prev, b.tok, row_number() OVER (PARTITION BY b.variant, b.prev ORDER BY round(b.n / h.c, 9) DESC, b.tok) AS r FROM vb b JOIN vh h ON h.variant = b.variant AND h.prev = b.prev) WHERE r = 1",
        "measures": """SELECT variant, 'heldout_ppl' AS metric, exp(-avg(lp)) AS value FROM hl GROUP BY variant UNION ALL
  SELECT s.variant, 'greedy_accuracy', avg((coalesce(z.guess, '') = r.tok)::INTEGER) FROM hr r CROSS JOIN vs s LEFT JOIN gs z ON z.variant = s.variant AND z.prev = r.prev GROUP BY s.variant""",
    }


def _member_rates(rates: tuple[int, ...]) -> str:
    each = f"(SELECT unnest({list(rates)}) AS rate_pct)"
    return f"SELECT sample_id, 'combined:' || rate_pct AS variant FROM ({o.ranked()}) CROSS JOIN {each} WHERE rank <= (n * rate_pct + 99) // 100 UNION ALL SELECT sample_id, 'full:100' FROM scored"


def _tidy_sql(table: str, data: str, model: str) -> str:
    return f"SELECT '{data}' AS dataset, '{model}' AS model, split_part(variant, ':', 1) AS strategy, split_part(variant, ':', 2)::INTEGER AS rate_pct, metric, round(value, 6) AS value FROM {table}"


_SETS = {"pairs": o.ALL | {"scored": _TRAINED}, "documents": _DOC_ALL | {"scored": _TRAINED}}


def _swept_sql(rates: tuple[int, ...], untuned: bool) -> tuple[dict[str, str], str]:
    parts, rows = {}, []
    for data, tables in _SETS.items():
        parts |= _prefixed(tables | {"member": _member_rates(rates)}, f"{data}_")
    for data in _SETS:
        for model in ("word", "char"):
            own = _measured(model, f"{'documents' if data == 'pairs' else 'pairs'}_tp" if untuned else None)
            made = {k: re.sub(r"\b(FROM|JOIN) (tp|member)\b", rf"\1 {data}_\2", v) for k, v in own.items()}
            parts |= _prefixed(made, f"{data}_{model}_")
            rows.append(_tidy_sql(f"{data}_{model}_measures", data, model))
    return parts, " UNION ALL ".join(rows)


def _picks_sql(rate: int) -> str:
    kinds = {
        "combined": o.chosen(rate),
        "difficulty": o.chosen(rate, cluster="0"),
        "random": o.chosen(rate, order="substr(md5('42:' || sample_id), 1, 12), sample_id", cluster="0"),
        "kmeans": o.chosen(rate, order="md5('42:' || sample_id), sample_id"),
    }
    return " UNION ALL ".join(f"SELECT '{k}' AS strategy, sample_id FROM ({v})" for k, v in kinds.items())


def _ablated_sql() -> tuple[dict[str, str], list[str]]:
    parts, rows = {}, []
    for data, rate in (("pairs", 40), ("documents", 30)):
        own = {
            "picks": _picks_sql(rate),
            "member": f"SELECT sample_id, strategy || ':{rate}' AS variant FROM picks",
            "fullc": "SELECT cluster_id, count(*) / (SELECT count(*) FROM scored) AS p FROM scored GROUP BY cluster_id",
            "subc": "SELECT k.strategy, x.cluster_id, count(*) / sum(count(*)) OVER (PARTITION BY k.strategy) AS q FROM picks k JOIN scored x ON x.sample_id = k.sample_id GROUP BY k.strategy, x.cluster_id",
            "bothc": "SELECT n.strategy, f.p, coalesce(c.q, 0) AS q FROM (SELECT DISTINCT strategy FROM picks) n CROSS JOIN fullc f LEFT JOIN subc c ON c.strategy = n.strategy AND c.cluster_id = f.cluster_id",
            "more": f"SELECT strategy || ':{rate}' AS variant, 'tv' AS metric, sum(abs(p - q)) / 2 AS value FROM bothc GROUP BY strategy UNION ALL SELECT k.strategy || ':{rate}', 'mean_ifd', avg(x.ifd) FROM picks k JOIN scored x ON x.sample_id = k.sample_id GROUP BY k.strategy",
        }
        parts |= _prefixed(_SETS[data] | own | _measured("word"), f"{data}_")
        rows += [_tidy_sql(f"{data}_measures", data, "word"), _tidy_sql(f"{data}_more", data, "word")]
    return parts, rows


_DOC_PARTS = {"dt": o.DOC_PAIRS["dt"], "tp": o.DOC_PAIRS["dp"]}


def _clusters_sql() -> tuple[dict[str, str], str]:
    parts, rows = o.PAIRS | o.NGRAM | o.EMBED, []
    for k in (5, 10, 20):
        own = {
            "kept": o.chosen(40),
            "fullc": "SELECT cluster_id, count(*) / (SELECT count(*) FROM scored) AS p FROM scored GROUP BY cluster_id",
            "subc": "SELECT cluster_id, count(*) / (SELECT count(*) FROM kept) AS q FROM kept GROUP BY cluster_id",
            "rep": "SELECT cluster_id, count(*) AS n, sum(dist * dist) AS sse FROM scored GROUP BY cluster_id",
            "tvs": "SELECT sum(abs(f.p - coalesce(c.q, 0))) / 2 AS tv FROM fullc f LEFT JOIN subc c ON c.cluster_id = f.cluster_id",
        }
        parts |= _prefixed(o.kmeans(k) | o.SCORED | own, f"k{k}_")
        rows.append(f"SELECT {k} AS k, count(*) AS clusters, min(n) AS smallest, max(n) AS largest, round(sum(sse), 6) AS sse, round((SELECT tv FROM k{k}_tvs), 6) AS tv FROM k{k}_rep")
    return parts, " UNION ALL ".join(rows)


_ABLATION, _ABLATION_ROWS = _ablated_sql()
_SWEPT, _SWEPT_ROWS = _swept_sql(RATES, False)
_ONE = o.ALL | {"scored": _TRAINED, "member": f"SELECT sample_id, 'combined:40' AS variant FROM ({o.chosen(40)})"} | _measured("word")

ORACLES = {
    "rate_sweep_sizes": o.sql(o.ALL, _SWEEP),
    "main_results": o.sql(*_swept_sql((40, 30), True)),
    "rate_sweep": o.sql(_SWEPT, _SWEPT_ROWS),
    "best_rates": o.sql(
        _SWEPT | {"rs": _SWEPT_ROWS},
        """SELECT dataset, model, arg_min(rate_pct, (value, rate_pct)) FILTER (WHERE strategy = 'combined') AS best_rate, min(value) FILTER (WHERE strategy = 'combined') AS at_best,
  max(value) FILTER (WHERE strategy = 'full') AS at_full FROM rs WHERE metric = 'heldout_ppl' GROUP BY dataset, model""",
    ),
    "rate_score_corr": o.sql(_SWEPT | {"rs": _SWEPT_ROWS}, "SELECT dataset, model, metric, round(corr(rate_pct, value), 6) AS r FROM rs WHERE strategy = 'combined' GROUP BY ALL"),
    "strategy_ablation": o.sql(_ABLATION, " UNION ALL ".join(_ABLATION_ROWS)),
    "redundancy_by_rate": o.sql(
        _DOC_ALL | {"kp": f"SELECT rate_pct::INTEGER AS rate_pct, sample_id FROM ({o.ranked()}) CROSS JOIN {_RATES_SQL} WHERE rank <= (n * rate_pct + 99) // 100"},
        "SELECT rate_pct, count(*) AS n, round(1 - count(DISTINCT array_to_string(resp, ' ')) / count(*), 6) AS duplicate_share FROM kp JOIN tp USING (sample_id) GROUP BY rate_pct",
    ),
    "dataset_diversity": o.sql(
        _prefixed(o.PAIRS | o.EMBED | o.kmeans(1, 1), "pairs_") | _prefixed(_DOC_PARTS | o.EMBED | o.kmeans(1, 1), "documents_")
        | {"u": "SELECT 'pairs' AS dataset, instr, resp FROM pairs_tp UNION ALL SELECT 'documents', instr, resp FROM documents_tp", "x": "SELECT dataset, unnest(list_concat(instr, resp)) AS tok FROM u",
           "near": " UNION ALL ".join(f"SELECT '{k}' AS dataset, round(1 - count(DISTINCT array_to_string(list_transform(v, lambda y: CASE WHEN y > 0 THEN '+' ELSE '-' END), '')) / count(*), 6) AS near_copies FROM {k}_vec" for k in _SETS),
           "spread": " UNION ALL ".join(f"SELECT '{k}' AS dataset, round(avg(dist), 6) AS mean_dist FROM {k}_cl" for k in _SETS)},
        """SELECT dataset, type_token, repeated, mean_resp, near_copies, mean_dist FROM (SELECT dataset, round(count(DISTINCT tok) / count(*), 6) AS type_token FROM x GROUP BY 1)
  JOIN (SELECT dataset, round(1 - count(DISTINCT array_to_string(instr, ' ')) / count(*), 6) AS repeated, round(avg(len(resp)), 6) AS mean_resp FROM u GROUP BY 1) USING (dataset) JOIN near USING (dataset) JOIN spread USING (dataset)""",
    ),
    "consistency_mix": o.sql(
        _DOC_ALL | {"picks": _picks_sql(40), "lab": "SELECT sample_id, coalesce(lang, 'none') AS lang, coalesce(source, 'none') AS source FROM scored JOIN documents ON doc_id = sample_id"}
        | {f"mix_{by}": f"""SELECT strategy, '{by}' AS "by", round(sum(abs(p - q)) / 2, 6) AS value FROM (SELECT n.strategy, f.p, coalesce(c.q, 0) AS q FROM (SELECT DISTINCT strategy FROM picks) n
  CROSS JOIN (SELECT {by}, count(*) / (SELECT count(*) FROM lab) AS p FROM lab GROUP BY {by}) f
  LEFT JOIN (SELECT strategy, {by}, count(*) / sum(count(*)) OVER (PARTITION BY strategy) AS q FROM picks JOIN lab USING (sample_id) GROUP BY strategy, {by}) c ON c.strategy = n.strategy AND c.{by} = f.{by}) GROUP BY strategy""" for by in ("lang", "source")}
        | {"cells": "SELECT sample_id, unnest(generate_series(1, len(v))) AS dim, unnest(v) AS x FROM vec", "centre": "SELECT dim, avg(x) AS a FROM cells SEMI JOIN scored USING (sample_id) GROUP BY dim",
           "own": "SELECT strategy, dim, avg(x) AS b FROM picks JOIN cells USING (sample_id) GROUP BY strategy, dim"},
        """SELECT * FROM mix_lang UNION ALL SELECT * FROM mix_source UNION ALL SELECT strategy, 'mean_vector', round(sqrt(sum((a - b) * (a - b))), 6) FROM own JOIN centre USING (dim) GROUP BY strategy""",
    ),
    "cluster_sweep": o.sql(*_clusters_sql()),
    "strategy_overlap": o.sql(
        o.ALL | m._STRATEGIES,
        "SELECT a.strategy AS a, b.strategy AS b, round(count(*) / ((SELECT count(*) FROM picks WHERE strategy = a.strategy) + (SELECT count(*) FROM picks WHERE strategy = b.strategy) - count(*)), 6) AS jaccard FROM picks a JOIN picks b ON a.sample_id = b.sample_id AND a.strategy < b.strategy GROUP BY 1, 2",
    ),
    "heldout_ppl": o.sql(_ONE, "SELECT metric, round(value, 6) AS value FROM measures WHERE metric = 'heldout_ppl'"),
    "greedy_accuracy": o.sql(_ONE, "SELECT metric, round(value, 6) AS value FROM measures WHERE metric = 'greedy_accuracy'"),
    "best_strategy": o.sql(
        _ABLATION | {"rs": " UNION ALL ".join(_ABLATION_ROWS)},
        "SELECT dataset, model, strategy, value AS heldout_ppl FROM (SELECT *, row_number() OVER (PARTITION BY dataset, model ORDER BY value, strategy DESC) AS r FROM rs WHERE metric = 'heldout_ppl') WHERE r = 1",
    ),
}
