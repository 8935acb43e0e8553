"""Expressions that several operators share."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

#: The white space that separates words, as Java/RE2 class and as characters.
SPACE_CLASS = r"[\x20\x09-\x0D]"
WORD_CLASS = r"[^\x20\x09-\x0D]+"
SPACES = " \t\n\x0b\x0c\r"


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` over ``value`` evaluated once per row, however often ``body`` names it.

    Inside a higher-order function a plain column expression would be inlined by the optimizer
    and evaluated again for every element.
    """
    return F.transform(F.array(value), body)[0]


def words(text: Column) -> Column:
    """Array of words; null text has none."""
    return F.array_remove(F.split(F.coalesce(text, F.lit("")), SPACE_CLASS + "+"), "")


def n_words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD_CLASS)), F.lit(0)).cast("long")


def free_name(wanted: str, taken: list[str]) -> str:
    """``wanted``, made longer until no column has that name (Spark compares names without case)."""
    used = {c.lower() for c in taken}
    while wanted.lower() in used:
        wanted = f"_{wanted}"
    return wanted
