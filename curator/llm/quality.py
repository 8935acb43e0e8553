"""Quality rules as a short-circuit cascade (operator 4), in DataFrame expressions only.

A few fixed counts are taken of every text.  Further rules are tried one after another and the first that rejects ends the
row's evaluation.  Their order comes from a sample by hash: a rule's cost is the time of evaluating it many times over the sample less that of a pass
that evaluates nothing, its selectivity the rejections among the rows that no rule before it has rejected, and the next rule is always that
of most rejections per cost.  The order changes what is spent, never the verdict.
"""

from __future__ import annotations

import time
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .text import SPACES, let, words

#: Rows that costs and selectivities are estimated on, about, and how often a rule is evaluated on each to time it.
SAMPLE_ROWS, REPEATS = 2000, 12
#: Fixed values of the base counts.
SYMBOLS = "#*$%&|<>"
MIN_WORDS, MAX_REPEAT_PCT = 50, 50


@dataclass(frozen=True)
class Rule:
    """``rejects`` is a boolean column over the text and the base counts; null does not reject."""

    name: str
    rejects: Column


def _nonblank_lines(text: Column) -> Column:
    return F.filter(F.split(text, "\n"), lambda line: line.rlike(r"[^\x20\x09-\x0D]"))


def _repeat_words(w: Column) -> Column:
    """Words inside three-word windows that occur twice or more; windows are told apart by 64-bit hashes."""

    def windows(w: Column) -> Column:
        n = F.size(w) - 2
        pairs = F.zip_with(F.slice(w, 1, n), F.slice(w, 2, n), lambda a, b: F.xxhash64(a, b))
        return F.zip_with(pairs, F.slice(w, 3, n), lambda h, c: F.xxhash64(h, c))

    def covered(hashes: Column) -> Column:
        def from_sorted(s: Column) -> Column:
            n = F.size(s) - 1
            twins = F.zip_with(F.slice(s, 1, n), F.slice(s, 2, n), lambda a, b: F.when(a["h"] == b["h"], F.array(a["i"], b["i"])))
            return let(
                F.array_distinct(F.flatten(F.array_compact(twins))),
                lambda at: F.size(F.array_distinct(F.concat(at, F.transform(at, lambda i: i + 1), F.transform(at, lambda i: i + 2)))),
            )

        ordered = F.sort_array(F.transform(hashes, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
        return F.when(F.size(F.array_distinct(hashes)) == F.size(hashes), 0).otherwise(let(ordered, from_sorted))

    return F.when(F.size(w) < 4, 0).otherwise(let(windows(w), covered))


def base_counts(text: Column) -> dict[str, Column]:
    """The fixed counts; null text has none of anything."""
    text = F.coalesce(text, F.lit(""))
    counts = let(words(text), lambda w: F.struct(F.size(w).alias("n"), _repeat_words(w).alias("r")))
    dup_lines = let(_nonblank_lines(text), lambda lines: F.size(lines) - F.size(F.array_distinct(lines)))
    return {
        "_counts": counts,
        "word_chars": F.length(F.translate(text, SPACES, "")).cast("long"),
        "n_symbols": (F.length(text) - F.length(F.translate(text, SYMBOLS, ""))).cast("long"),
        "n_dup_lines": dup_lines.cast("long"),
    }


def default_rules(text_col: str = "text") -> list[Rule]:
    """Rules on top of the base ones.  Thresholds are loose enough for any running prose."""
    text, n = F.coalesce(F.col(text_col), F.lit("")), F.col("n_words")
    letters = F.length(F.regexp_replace(text, r"[^\p{L}]+", ""))
    capitals = F.length(F.regexp_replace(text, r"[^\p{Lu}]+", ""))
    lines = F.size(_nonblank_lines(text))
    shouts = F.length(text) - F.length(F.translate(text, "!?", ""))
    return [
        Rule("symbols", 4 * F.col("n_symbols") > n),
        Rule("word_length", (F.col("word_chars") < 2 * n) | (F.col("word_chars") > 15 * n)),
        Rule("repeated_lines", 2 * F.col("n_dup_lines") > lines),
        Rule("shouting", 5 * shouts > n),
        Rule("few_letters", 10 * letters < 6 * F.col("word_chars")),
        Rule("capitals", 2 * capitals > letters),
    ]


def sampled(docs: DataFrame, text_col: str, rows: int = SAMPLE_ROWS) -> DataFrame:
    """About ``rows`` rows by a hash of the text and of the row's place; all rows of a smaller table."""
    share = rows / max(rows, docs.count())
    return docs.filter(F.xxhash64(F.col(text_col), F.monotonically_increasing_id()) <= F.lit(min(2**63 - 1, int(share * 2**64) - 2**63)))


def cascade(rules: list[Rule], cost: dict[str, float], rejected: dict[frozenset[str], int]) -> list[Rule]:
    """``rules`` by falling rejections per cost, of the rows that the ones before leave; ``rejected`` counts rows by the rules that reject them.

    Of equal gains the cheaper rule goes first, then the one named first.
    """
    left, out = list(rules), []
    while left:
        gain = lambda r: sum(n for names, n in rejected.items() if r.name in names) / cost[r.name]
        out.append(max(left, key=lambda r: (gain(r), -cost[r.name])))
        left.remove(out[-1])
        rejected = {names: n for names, n in rejected.items() if out[-1].name not in names}
    return out


def rule_costs(sample: DataFrame, rules: list[Rule], repeats: int = REPEATS) -> dict[str, float]:
    """Seconds that each rule takes on ``sample``, ``repeats`` times over, beyond those of a pass without a rule."""
    # The condition stands in an aggregate above the generator, where the optimizer cannot move it to the rows below.
    many = sample.withColumn("_turn", F.explode(F.sequence(F.lit(1), F.lit(repeats))))

    def seconds(condition: Column) -> float:
        took = []
        for _ in range(2):
            began = time.perf_counter()
            many.agg(F.count_if(condition & (F.col("_turn") > 0))).collect()
            took.append(time.perf_counter() - began)
        return min(took)

    empty = seconds(F.col("base_failed").isNotNull())
    return {rule.name: max(1e-6, seconds(rule.rejects) - empty) for rule in rules}


def order_rules(counted: DataFrame, rules: list[Rule], repeats: int = REPEATS) -> list[Rule]:
    """The cascade for ``counted``, a sample with its base counts: only rows that the base leaves count, which alone the rules see."""
    sample = counted.filter(~F.col("base_failed")).persist()
    try:
        flags = [F.coalesce(rule.rejects, F.lit(False)).alias(f"_r{n}") for n, rule in enumerate(rules)]
        # At most one row per combination of rules.
        rows = sample.select(*flags).groupBy(*(f"_r{n}" for n in range(len(rules)))).count().collect()
        rejected = {frozenset(rule.name for n, rule in enumerate(rules) if row[f"_r{n}"]): row["count"] for row in rows}
        return cascade(rules, rule_costs(sample, rules, repeats), rejected)
    finally:
        sample.unpersist()


def judge_quality(docs: DataFrame, text_col: str = "text", rules: list[Rule] | None = None, sample_rows: int = SAMPLE_ROWS) -> DataFrame:
    """Columns of ``docs`` plus ``n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, kept``.

    Null and empty texts have zero counts and fail the base rules.  Rows are judged one by one: repeated rows stay, an empty table
    gives an empty one, columns that bear an added column's name are replaced.
    """
    added = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "_counts")
    names = [c for c in docs.columns if c.lower() not in added]

    def counts(rows: DataFrame) -> DataFrame:
        made = rows.withColumns(base_counts(F.col(text_col)))
        made = made.withColumns({"n_words": F.col("_counts.n").cast("long"), "n_repeat_words": F.col("_counts.r").cast("long")}).drop("_counts")
        return made.withColumn("base_failed", (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > MAX_REPEAT_PCT * F.col("n_words")))

    rules = default_rules(text_col) if rules is None else rules
    if len(rules) > 1:
        rules = order_rules(counts(sampled(docs.select(text_col), text_col, sample_rows)), rules)
    counted = counts(docs.select(*names))
    verdict = F.when(F.col("base_failed"), False)
    for rule in rules:
        verdict = verdict.when(rule.rejects, False)
    return counted.withColumn("kept", verdict.otherwise(True)).select(*names, *(a for a in added if a != "_counts"))
