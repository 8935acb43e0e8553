"""Instruction/response pairs from chat logs and from documents."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from curator.functions.expr import tokens
from curator.functions.subwords import subword_tokens


def build_pairs(conversations: DataFrame, context: str = "last_user") -> DataFrame:
    """``sample_id, instruction, response`` of every user turn directly followed by an assistant turn.

    ``context``: ``last_user`` (that turn alone), ``with_system`` (the system turn before it) or ``history`` (all turns up to it).
    A null instruction counts as empty; pairs with a blank response are left to ``rejected_pairs``.
    """
    turns = Window.partitionBy("conv_id").orderBy("turn")
    past = turns.rowsBetween(Window.unboundedPreceding, Window.currentRow)
    own = F.coalesce("text", F.lit(""))
    text = {
        "last_user": own,
        "with_system": F.concat_ws("\n", F.last(F.when(F.col("role") == "system", F.col("text")), ignorenulls=True).over(past), own),
        "history": F.concat_ws("\n", F.collect_list(own).over(past)),
    }[context]
    rows = conversations.select("conv_id", "turn", "role", text.alias("instruction"), F.lead("role").over(turns).alias("next_role"), F.lead("text").over(turns).alias("response"))
    rows = rows.filter((F.col("role") == "user") & (F.col("next_role") == "assistant"))
    return rows.filter(F.length(F.trim(F.coalesce("response", F.lit("")))) > 0).select((F.col("conv_id") * 1000 + F.col("turn")).alias("sample_id"), "instruction", "response")


def rejected_pairs(conversations: DataFrame, max_tokens: int = 4096) -> DataFrame:
    """``sample_id, reason`` of user turns that make no sample: ``no_reply``, ``blank_response`` or ``too_long``."""
    turns = Window.partitionBy("conv_id").orderBy("turn")
    rows = conversations.select("conv_id", "turn", "role", "text", F.lead("role").over(turns).alias("next_role"), F.lead("text").over(turns).alias("response")).filter("role = 'user'")
    size = F.size(tokens(F.col("text"))) + F.size(tokens(F.col("response")))
    reason = (
        F.when(F.coalesce("next_role", F.lit("")) != "assistant", "no_reply")
        .when(F.length(F.trim(F.coalesce("response", F.lit("")))) == 0, "blank_response")
        .when(size > max_tokens, "too_long")
    )
    return rows.select((F.col("conv_id") * 1000 + F.col("turn")).alias("sample_id"), reason.alias("reason")).filter("reason is not null")


def build_doc_pairs(documents: DataFrame, max_instr: int = 32, least: int = 8) -> DataFrame:
    """``sample_id, instr, resp``: the first ``min(max_instr, n div 4)`` tokens of a document against the rest."""
    rows = documents.select(F.col("doc_id").alias("sample_id"), tokens(F.col("text")).alias("toks"))
    # The token array is computed once: the generator keeps the projection below from being folded into the scan.
    rows = rows.select("sample_id", F.explode(F.array("toks")).alias("toks")).filter(F.size("toks") >= least)
    cut = F.least(F.lit(max_instr), (F.size("toks") / 4).cast("int"))
    return rows.select("sample_id", F.slice("toks", F.lit(1), cut).alias("instr"), F.slice("toks", cut + 1, F.size("toks")).alias("resp"))


def token_pairs(pairs: DataFrame, mode: str = "word", vocab: str | None = None) -> DataFrame:
    """``sample_id, instr, resp`` (token arrays) of text pairs; mode ``bpe`` takes the subwords of the vocabulary file ``vocab``."""
    if mode == "bpe":
        if vocab is None:
            raise ValueError("mode 'bpe' needs a vocabulary file")
        return pairs.select("sample_id", subword_tokens(F.col("instruction"), vocab).alias("instr"), subword_tokens(F.col("response"), vocab).alias("resp"))
    return pairs.select("sample_id", tokens(F.col("instruction"), mode).alias("instr"), tokens(F.col("response"), mode).alias("resp"))


def sample_lengths(pairs: DataFrame, overhead: int = 0) -> DataFrame:
    """``sample_id, n_instr, n_resp, n_tokens`` of token pairs."""
    n = F.size("instr") + F.size("resp") + overhead
    return pairs.select("sample_id", F.size("instr").alias("n_instr"), F.size("resp").alias("n_resp"), n.alias("n_tokens"))
