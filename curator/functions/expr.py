"""Column helpers shared by the operators."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Fixed value: a token is a run of letters and digits, or one other visible character.
WORD_PATTERN = r"[\p{L}\p{N}]+|[^\s\p{L}\p{N}]"


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` over ``value`` evaluated once per row."""
    return F.transform(F.array(value), body)[0]


def tokens(text: Column, mode: str = "word") -> Column:
    """Lower-case tokens of a text: ``word``, ``space`` or ``char``; null text has none."""
    text = F.lower(F.coalesce(text, F.lit("")))
    if mode == "word":
        return F.regexp_extract_all(text, F.lit(WORD_PATTERN), F.lit(0))
    if mode == "space":
        return F.array_remove(F.split(text, r"[ \t\r\n]+"), "")
    if mode == "char":
        return F.filter(F.split(text, ""), lambda c: c != "")
    raise ValueError(f"unknown token mode {mode!r}")


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def squared_distance(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)


def cosine(a: Column, b: Column) -> Column:
    return F.when((norm(a) > 0) & (norm(b) > 0), dot(a, b) / (norm(a) * norm(b))).otherwise(0.0)
