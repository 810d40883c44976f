"""Counting tokens of prompts and answers."""

from __future__ import annotations

import math
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F


def estimate(text: str) -> int:
    """A quarter of the characters, rounded up."""
    return math.ceil(len(text) / 4)


def estimated(text: Column) -> Column:
    """The same, as an expression that SQL engines agree on."""
    return F.ceil(F.length(text) / 4).cast("long")


def bpe_counter(path: str):
    """count(text) -> tokens of a tokenizer file, loaded once in each task."""
    @F.pandas_udf("long")
    def count(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        from tokenizers import Tokenizer

        tokenizer = Tokenizer.from_file(path)
        for texts in batches:
            yield pd.Series([len(e.ids) for e in tokenizer.encode_batch([t or "" for t in texts], add_special_tokens=False)])

    return count
