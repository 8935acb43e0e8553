"""Token log-probabilities and the difficulty score.

The difficulty of a sample is the perplexity of its response after the instruction over that without it.  Any source of
``sample_id, pos, lp_with, lp_without`` will do: the n-gram scorer here, a table that a GPU job wrote, or a
function that runs a model on the executors.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from functools import cached_property, reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from curator.functions.expr import tokens
from curator.operators import blocks
from curator.operators.blocks import START, UNKNOWN
from curator.sources.checkpoints import stage, unstage

#: Weights of the bigram, unigram, uniform and history parts.
BIGRAM, UNIGRAM, UNIFORM, HISTORY = 0.4, 0.2, 0.1, 0.3
#: Samples are scored in so many slices at most, one after the other, of so many tokens at least; this decides about disk and time only.
SLICES, SLICE_TOKENS = 8, 12_000_000


class NGramScorer:
    """One model of a corpus: token shares, follower shares and the size of the vocabulary; its tables are stored in the shared folder."""

    def __init__(self, toks: DataFrame, min_count: int = 1):
        self.toks, self.min_count = toks.select("t").filter(F.size("t") > 0), min_count
        #: Keys are dealt to so many buckets; a bucket's keys of one corpus or slice are in a task's memory.
        self.buckets = 4 * int(toks.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        parts = self.toks.select(F.lit(0).cast("long").alias("id"), F.lit(0).cast("long").alias("aux"), "t").mapInArrow(blocks.count_keys(self.buckets), blocks.PIECES)
        #: Counts of pairs, words and predecessors, a row of arrays per bucket.
        self.counts = stage(parts.groupBy("bucket").applyInArrow(blocks.add_up(min_count), blocks.MODEL), "counts")
        size = self.counts.agg(F.sum("tokens").alias("n"), F.sum("known").alias("v"), F.sum("odd").alias("u")).first()
        self._chunks: list[DataFrame] = []
        self.total, self.size, self.odd = size.n or 0, size.v or 0, size.u or 0  # tokens of the corpus, different ones, those named like unknown words

    @classmethod
    def fit(cls, corpus: DataFrame, text_col: str = "text", min_count: int = 1, mode: str = "word") -> NGramScorer:
        toks = corpus.select(tokens(F.col(text_col), mode).alias("t"))
        return cls.of_arrays(toks, min_count)

    @classmethod
    def of_arrays(cls, toks: DataFrame, min_count: int = 1) -> NGramScorer:
        return cls(toks, min_count)

    @cached_property
    def _tables(self) -> tuple[DataFrame, DataFrame]:
        # Followers come from within the row, so no window over documents is needed.
        pairs = self.toks.select(F.explode(F.arrays_zip(F.concat(F.array(F.lit(START)), F.col("t")).alias("prev"), F.col("t").alias("tok"))).alias("p"))
        big = stage(pairs.filter("p.tok is not null").groupBy("p.prev", "p.tok").agg(F.count(F.lit(1)).alias("n")), "bigrams")
        heads = stage(big.groupBy("prev").agg(F.sum("n").alias("c")), "heads")
        follow = stage(big.join(heads, "prev").select("prev", "tok", (F.col("n") / F.col("c")).alias("p_big")), "followers")
        # Every token follows one other or the start of its text, so followers count tokens too.
        counts = stage(big.groupBy("tok").agg(F.sum("n").alias("n")), "counts")
        unstage(big)
        known = counts.filter(F.col("n") >= self.min_count).select("tok", "n", (F.col("n") / F.lit(max(1, self.total))).alias("p_uni"))
        contexts = heads.select(F.col("prev").alias("tok"), F.lit(True).alias("is_context"))
        starts = follow.filter(F.col("prev") == START).select("tok", F.col("p_big").alias("p_start"))
        vocab = known.join(contexts, "tok", "left").join(starts, "tok", "left")
        return stage(vocab.select("tok", "n", "p_uni", F.coalesce("is_context", F.lit(False)).alias("is_context"), F.coalesce("p_start", F.lit(0.0)).alias("p_start")), "vocabulary"), follow

    @property
    def vocab(self) -> DataFrame:
        """``tok, n, p_uni, is_context, p_start``."""
        return self._tables[0]

    @property
    def follow(self) -> DataFrame:
        """``prev, tok, p_big``."""
        return self._tables[1]

    def score(self, pairs: DataFrame) -> DataFrame:
        """``sample_id, pos, lp_with, lp_without`` of token pairs; ``pos`` counts response tokens from 1.

        Samples are dealt to chunks (``blocks``); what is shuffled are the different pairs and words of a chunk, as arrays, and their counts.
        """
        kind = dict(pairs.dtypes)["sample_id"]
        if self.odd or kind not in ("bigint", "int", "smallint", "tinyint"):
            return self._score_rows(pairs)
        both = pairs.select(F.col("sample_id").cast("long").alias("id"), F.size("instr").cast("long").alias("aux"), F.concat("instr", "resp").alias("t")).filter(F.size("t") > F.col("aux"))
        chunks = stage(both.mapInArrow(blocks.write_chunks, blocks.CHUNKS), "chunks")
        self._chunks.append(chunks)
        asked = chunks.mapInArrow(blocks.ask_keys(self.buckets), blocks.PIECES).unionByName(self.counts.select("bucket", "chunk", "a", "b", "c"))
        answers = asked.groupBy("bucket").applyInArrow(blocks.answer, blocks.ANSWERS)
        made = blocks.log_probabilities(self.buckets, self.total, self.size, self.min_count, (BIGRAM, UNIGRAM, UNIFORM, HISTORY))
        rows = chunks.groupBy("chunk").cogroup(answers.groupBy("chunk")).applyInArrow(made, "sample_id long, pos int, lp_with double, lp_without double")
        return rows if kind == "bigint" else rows.withColumn("sample_id", F.col("sample_id").cast(kind))

    def let_go(self, model: bool = False) -> None:
        """Remove the chunks of what was scored, and with ``model`` the counts, once nothing reads them any more."""
        while self._chunks:
            unstage(self._chunks.pop())
        if model:
            unstage(self.counts)

    def _score_rows(self, pairs: DataFrame) -> DataFrame:
        """``score`` by joins of token rows, for a corpus with a word named ``UNKNOWN``, which unknown words are taken for, or other ids than numbers."""
        # Predecessors that are unknown words, or the start of a sample, are looked up as such.
        odd = {r.tok: r for r in self.vocab.filter(F.col("tok").isin(UNKNOWN, START)).collect()}
        unknown_context, unknown_start = (odd[UNKNOWN].is_context, odd[UNKNOWN].p_start) if UNKNOWN in odd else (False, 0.0)
        both = pairs.select("sample_id", F.size("instr").alias("n_instr"), F.posexplode(F.concat("instr", "resp")).alias("g", "raw"))
        known = both.join(self.vocab, both["raw"] == self.vocab["tok"], "left").select(
            "sample_id", "g", "n_instr", F.coalesce("tok", F.lit(UNKNOWN)).alias("w"), F.coalesce("n", F.lit(0)).alias("n"), F.coalesce("is_context", F.lit(unknown_context)).alias("is_context"),
            # Only the first token of a response has another predecessor without the instruction.
            F.when(F.col("g") == F.col("n_instr"), F.coalesce("p_start", F.lit(unknown_start))).alias("p_start"),
        )
        out = F.col("g") >= F.col("n_instr")
        sample = Window.partitionBy("sample_id").orderBy("g")
        word, word_out = Window.partitionBy("sample_id", "w").orderBy("g"), Window.partitionBy("sample_id", "w", "out").orderBy("g")
        # Dealt by sample, so that no window needs a shuffle of its own.
        rows = known.repartition("sample_id").withColumn("out", out).select(
            "*",
            F.coalesce(F.lag("w").over(sample), F.lit(START)).alias("p"),
            F.coalesce(F.lag("is_context").over(sample), F.lit(self.total > 0)).alias("follows"),
            (F.row_number().over(word) - 1).alias("seen"),
            (F.row_number().over(word_out) - 1).alias("seen_out"),
        ).filter("out").drop("out", "is_context")
        big = self.follow.select(F.col("prev").alias("p"), F.col("tok").alias("w"), "p_big")
        rows = rows.join(big, ["p", "w"], "left").withColumns({"p_uni": F.col("n") / F.lit(max(1, self.total)), "k": F.col("g") - F.col("n_instr")})
        follow = F.when(F.col("follows"), F.coalesce("p_big", F.lit(0.0))).otherwise(F.col("p_uni"))

        def log_p(follows, count, length):
            share = F.when(length > 0, HISTORY * count / length).otherwise(HISTORY * F.col("p_uni"))
            return F.log(BIGRAM * follows + UNIGRAM * F.col("p_uni") + UNIFORM / (self.size + 1) + share)

        return rows.select(
            "sample_id",
            (F.col("k") + 1).cast("int").alias("pos"),
            log_p(follow, F.col("seen"), F.col("g")).alias("lp_with"),
            log_p(F.when(F.col("k") == 0, F.col("p_start")).otherwise(follow), F.col("seen_out"), F.col("k")).alias("lp_without"),
        )


@dataclass
class TableScorer:
    """Log-probabilities that another job wrote: ``sample_id, pos, lp_with, lp_without``."""

    table: DataFrame

    def score(self, pairs: DataFrame) -> DataFrame:
        return self.table.join(pairs.select("sample_id"), "sample_id", "left_semi").select("sample_id", "pos", "lp_with", "lp_without")


@dataclass
class FunctionScorer:
    """``fn(iterator of pandas frames sample_id, instr, resp) -> iterator of frames`` with the log-probability columns."""

    fn: Callable

    def score(self, pairs: DataFrame) -> DataFrame:
        return pairs.select("sample_id", "instr", "resp").mapInPandas(self.fn, "sample_id long, pos int, lp_with double, lp_without double")


def perplexity(token_lp: DataFrame, column: str) -> DataFrame:
    return token_lp.groupBy("sample_id").agg(F.count(F.lit(1)).alias("n_tokens"), F.exp(-F.avg(column)).alias("ppl"))


def difficulty(token_lp: DataFrame, max_context: int | None = None, lengths: DataFrame | None = None) -> DataFrame:
    """``sample_id, n_tokens, ppl_with, ppl_without, ifd``; with ``max_context``, of the response tokens that fit after the instruction
    (``lengths`` then gives ``sample_id, n_instr``)."""
    if max_context is not None:
        token_lp = token_lp.join(lengths.select("sample_id", "n_instr"), "sample_id").filter(F.col("n_instr") + F.col("pos") <= max_context)
    # One pass: the ratio is the exponential of the mean difference, so no perplexity can overflow on the way.
    return token_lp.groupBy("sample_id").agg(
        F.count(F.lit(1)).alias("n_tokens"), F.exp(-F.avg("lp_with")).alias("ppl_with"), F.exp(-F.avg("lp_without")).alias("ppl_without"), F.exp(F.avg(F.col("lp_without") - F.col("lp_with"))).alias("ifd")
    )


def difficulty_in_slices(scorer, pairs: DataFrame) -> DataFrame:
    """``difficulty`` of all ``pairs``, stored; only one slice of the samples has its rows of tokens on disk at a time."""
    n_tokens = pairs.agg(F.sum(F.size("instr").cast("long") + F.size("resp"))).first()[0] or 0
    n = max(1, min(SLICES, -(-n_tokens // SLICE_TOKENS)))
    # Another seed than the shuffle's, so that a slice is dealt to all partitions.
    slices = [pairs.filter(F.pmod(F.xxhash64(F.lit("slice"), F.col("sample_id")), F.lit(n)) == i) if n > 1 else pairs for i in range(n)]
    parts = []
    for x in slices:
        parts.append(stage(difficulty(scorer.score(x)), "difficulty"))
        if isinstance(scorer, NGramScorer):
            scorer.let_go()
    return reduce(DataFrame.unionByName, parts)


def difficulty_profile(scores: DataFrame, by: str = "cluster_id") -> DataFrame:
    return scores.groupBy(by).agg(F.count(F.lit(1)).alias("n"), F.avg("ifd").alias("mean_ifd"), F.coalesce(F.stddev_samp("ifd"), F.lit(0.0)).alias("sd_ifd"), F.percentile("ifd", F.lit(0.5)).alias("median_ifd"))
