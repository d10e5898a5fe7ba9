"""Functions that no built-in expresses: Unicode normal form, n-gram tables, a mergeable log-sum-exp."""

from __future__ import annotations

import unicodedata
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.pandas_udf(T.StringType())
def _nfc(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
    for s in batches:
        yield s.map(lambda x: unicodedata.normalize("NFC", x), na_action="ignore")


def nfc(text: str | Column) -> Column:
    return _nfc(F.col(text) if isinstance(text, str) else text)


@F.pandas_udf(T.DoubleType())
def log_sum_exp(x: pd.Series) -> float:
    """Grouped aggregate; the native way is a maximum, then a sum of shifted exponentials."""
    if not len(x):
        return float("-inf")
    top = x.max()
    return float(top + np.log(np.exp(x - top).sum()))


@F.udtf(returnType=T.StructType([T.StructField("position", T.IntegerType()), T.StructField("gram", T.StringType())]))
class NGrams:
    """SELECT * FROM ngrams(text, n), laterally."""

    def eval(self, text: str, n: int):
        tokens = (text or "").split()
        for i in range(len(tokens) - n + 1):
            yield i, " ".join(tokens[i : i + n])
