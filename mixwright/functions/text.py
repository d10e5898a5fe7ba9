"""Words and n-grams as array columns."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def words(text: str | Column) -> Column:
    """White-space words; a null or blank text has none."""
    c = F.trim(F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit("")))
    return F.when(c == "", F.array().cast("array<string>")).otherwise(F.split(c, r"\s+"))


def n_tokens(text: str | Column) -> Column:
    return F.size(words(text)).cast("long")


def ngrams(tokens: Column, n: int) -> Column:
    """Space-joined n-grams of an array column; it must be a plain column, as it is read once per position."""
    picks = lambda i: F.concat_ws(" ", *[F.get(tokens, i + k) for k in range(n)])
    return F.when(F.size(tokens) >= n, F.transform(F.sequence(F.lit(0), F.size(tokens) - n), picks)).otherwise(F.array().cast("array<string>"))
