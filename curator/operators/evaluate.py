"""Scores of trained models and stand-ins for training."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from curator.operators import blocks
from curator.operators.scoring import BIGRAM, HISTORY, START, UNIFORM, UNIGRAM, NGramScorer
from curator.sources.checkpoints import stage, unstage


def pass_at_1(results: DataFrame, by: str = "suite", passed: str = "base_pass") -> DataFrame:
    return results.groupBy(by).agg(F.avg(F.col(passed).cast("int")).alias("pass_at_1"))


def pass_at_k(results: DataFrame, k: int, by: str = "suite") -> DataFrame:
    """Unbiased pass@k of rows ``item, n`` (answers), ``c`` (right ones): one minus the chance that k drawn answers are all wrong."""
    wrong = F.aggregate(F.sequence(F.lit(0), F.lit(k - 1)), F.lit(1.0), lambda p, i: p * F.greatest(F.col("n") - F.col("c") - i, F.lit(0)) / (F.col("n") - i))
    return results.filter(F.col("n") >= k).groupBy(by).agg(F.avg(1 - wrong).alias("pass_at_k"))


def macro_average(scores: DataFrame, column: str) -> DataFrame:
    return scores.agg(F.avg(column).alias("value"))


def savings(before: float, after: float) -> float:
    """Relative saving."""
    return (before - after) / before if before else 0.0


def best_strategy(results: DataFrame, budget: int | None = None) -> DataFrame:
    """Of tidy results (dataset, model, strategy, rate_pct, value) the best strategy per data set and model within a rate."""
    rows = results if budget is None else results.filter(F.col("rate_pct") <= budget)
    return rows.groupBy("dataset", "model").agg(F.max_by("strategy", F.struct("value", "strategy")).alias("strategy"), F.max("value").alias("value"))


def heldout_quality(train: DataFrame, heldout: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Held-out perplexity and greedy next-token accuracy of an n-gram model of ``train``; both tables hold token arrays ``t``."""
    model = NGramScorer.of_arrays(train)
    rows = heldout.select(F.col("id").alias("sample_id"), F.array().cast("array<string>").alias("instr"), F.col("t").alias("resp"))
    ppl = model.score(rows).agg(F.exp(-F.avg("lp_without")).alias("value"))
    guess = model.follow.groupBy("prev").agg(F.min(F.struct((-F.round("p_big", 9)).alias("p"), "tok"))["tok"].alias("guess"))
    pairs = heldout.select(F.explode(F.arrays_zip(F.concat(F.array(F.lit(START)), F.col("t")).alias("prev"), F.col("t").alias("tok"))).alias("p")).select("p.prev", "p.tok").filter("tok is not null")
    hits = pairs.join(guess, "prev", "left").agg(F.avg((F.coalesce("guess", F.lit("")) == F.col("tok")).cast("int")).alias("value"))
    return ppl, hits


#: Models are bits of a long.
MODELS = 60


def heldout_by_variant(train: DataFrame, heldout: DataFrame, variants: list[str]) -> DataFrame:
    """``variant, heldout_ppl, greedy_accuracy``: the measures of ``heldout_quality`` for one model per variant, in one plan.

    ``train``: ``variants`` (array: the models that learn from the row) or ``variant`` (one), ``t``; ``heldout``: ``id, t``.  ``t`` holds tokens, or a text whose tokens are then the
    pairs of its neighbouring characters.  All models are columns of the same rows: pairs of tokens are counted, and looked up, once for all of ``variants``, and leave a chunk of the
    texts (``blocks``) once each; what does not depend on the place of a token is computed once per different pair.
    """
    if len(variants) > MODELS:
        return reduce(DataFrame.unionByName, [heldout_by_variant(train, heldout, variants[i : i + MODELS]) for i in range(0, len(variants), MODELS)])
    spark = train.sparkSession
    if "variants" not in train.columns:
        train = train.select(F.array("variant").alias("variants"), "t")
    of = range(len(variants))
    each = lambda make: [make(i) for i in of]
    buckets = 4 * int(spark.conf.get("spark.sql.shuffle.partitions"))
    size_of = F.size if dict(train.dtypes)["t"].startswith("array") else F.length
    bits = reduce(Column.__add__, each(lambda i: F.when(F.array_contains("variants", variants[i]), F.lit(1 << i)).otherwise(F.lit(0)).cast("long")))
    marked = train.filter(size_of("t") > 0).select(F.lit(0).cast("long").alias("id"), bits.alias("aux"), "t").filter("aux <> 0")
    schema = "prev long, tok long, word string, " + ", ".join(f"b{i} long" for i in of)
    big = stage(marked.mapInArrow(blocks.count_for_models(buckets), blocks.COUNTED).groupBy("bucket").applyInArrow(blocks.add_up_models(len(variants)), schema), "bigrams")
    # A word's place in the order of all; pairs of characters are numbers in that order.
    spelled = big.filter("word is not null").groupBy("tok").agg(F.min("word").alias("word")).orderBy("word").select("tok", F.monotonically_increasing_id().alias("rank"))
    ranks = stage(spelled, "ranks")
    heads = stage(big.groupBy("prev").agg(*each(lambda i: F.sum(f"b{i}").alias(f"h{i}")), *each(lambda i: F.max(f"b{i}").alias(f"m{i}"))), "heads")
    counts = big.groupBy("tok").agg(*each(lambda i: F.sum(f"b{i}").alias(f"n{i}")))
    words = stage(counts.join(ranks, "tok", "left").withColumn("rank", F.coalesce("rank", "tok")), "words")
    size = words.agg(*each(lambda i: F.sum(f"n{i}").alias(f"t{i}")), *each(lambda i: F.count_if(F.col(f"n{i}") > 0).alias(f"v{i}"))).first()
    share = lambda c, i: F.round(F.col(f"{c}{i}") / F.col(f"h{i}"), 9)
    top = lambda i: (F.col(f"b{i}") > 0) & (share("b", i) == share("m", i))
    leaders = big.join(heads, "prev").select("prev", "tok", *each(lambda i: top(i).alias(f"top{i}"))).filter(reduce(Column.__or__, each(lambda i: F.col(f"top{i}"))))
    guess = leaders.join(words.select("tok", "rank"), "tok").groupBy("prev").agg(*each(lambda i: F.min(F.when(F.col(f"top{i}"), F.col("rank"))).alias(f"g{i}")))
    # Different held-out pairs with what the models make of them; a word that a model has not seen is unknown to it, as word and as predecessor.
    held = heldout.filter(size_of("t") > 0).select(F.col("id").cast("long"), F.lit(0).cast("long").alias("aux"), "t")
    chunks = stage(held.mapInArrow(blocks.write_chunks, blocks.CHUNKS), "chunks")
    asked = chunks.mapInArrow(blocks.pairs_in_chunks(buckets), blocks.PIECES)
    seen_pairs = asked.groupBy("bucket").applyInArrow(blocks.different, blocks.DIFFERENT)
    looked = seen_pairs.join(big.drop("word"), ["prev", "tok"], "left").join(words, "tok", "left").join(heads.join(guess, "prev"), "prev", "left")

    def fixed(i: int) -> Column:
        p_uni = F.coalesce(F.col(f"n{i}"), F.lit(0)) / F.lit(max(1, size[f"t{i}"] or 0))
        chance = F.when(F.col(f"h{i}") > 0, F.coalesce(F.col(f"b{i}"), F.lit(0)) / F.col(f"h{i}")).otherwise(p_uni)
        return BIGRAM * chance + UNIGRAM * p_uni + UNIFORM / F.lit((size[f"v{i}"] or 0) + 1) + F.when(F.col("prev") == blocks.START_ID, HISTORY * p_uni).otherwise(0.0)

    unknown = reduce(Column.__add__, each(lambda i: F.when(F.coalesce(F.col(f"n{i}"), F.lit(0)) == 0, F.lit(1 << i)).otherwise(F.lit(0)).cast("long")))
    table = stage(looked.select("bucket", "prev", "tok", "c", unknown.alias("u"), *each(lambda i: fixed(i).alias(f"x{i}")), *each(lambda i: F.coalesce(F.col(f"g{i}") == F.col("rank"), F.lit(False)).alias(f"hit{i}"))), "looked")
    hits = table.agg(*each(lambda i: (F.sum(F.when(F.col(f"hit{i}"), F.col("c")).otherwise(0)) / F.sum("c")).alias(f"a{i}")))
    answers = asked.groupBy("bucket").cogroup(table.select("bucket", "prev", "tok", "u", *(f"x{i}" for i in of)).groupBy("bucket")).applyInArrow(blocks.look_up(len(variants)), blocks.LOOKED)
    sums = chunks.groupBy("chunk").cogroup(answers.groupBy("chunk")).applyInArrow(blocks.add_logs(buckets, len(variants), HISTORY), "n long, " + ", ".join(f"s{i} double" for i in of))
    total = sums.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"), *each(lambda i: F.sum(f"s{i}").alias(f"s{i}")))
    made = [F.struct(F.lit(v).alias("variant"), F.exp(-F.col(f"s{i}") / F.col("n")).alias("heldout_ppl"), F.col(f"a{i}").alias("greedy_accuracy")) for i, v in enumerate(variants) if size[f"t{i}"]]
    one = total.join(hits)  # one row each
    if not made:
        return one.filter("false").select(F.lit("").alias("variant"), F.lit(0.0).alias("heldout_ppl"), F.lit(0.0).alias("greedy_accuracy"))
    out = stage(one.filter("n > 0").select(F.inline(F.array(*made))), "heldout")
    for stored in (chunks, table, heads, words, ranks):
        unstage(stored)
    return out
