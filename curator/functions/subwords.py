"""Tokens of a published subword vocabulary, which is a file named by the caller."""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F


@lru_cache(maxsize=4)
def _library(path: str):
    from tokenizers import Tokenizer

    found = Tokenizer.from_file(path)
    found.no_truncation()
    found.no_padding()
    return found


def subword_tokens(text: Column, path: str) -> Column:
    """Subwords of a text by the vocabulary file at ``path`` (present on every node), without added special tokens; null text has none."""

    @F.pandas_udf("array<string>")
    def encode(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        lib = _library(path)
        for texts in batches:
            yield pd.Series([found.tokens for found in lib.encode_batch([t or "" for t in texts], add_special_tokens=False)], dtype=object)

    return encode(text)
