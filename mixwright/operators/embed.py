"""Document vectors: given ones, signed hashed bags of words, or a plugged-in encoder."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mixwright.functions.hashing import CODES, coded_bag, hashed_bag
from mixwright.functions.text import words


def given(docs: DataFrame, embeddings: DataFrame) -> DataFrame:
    """Vectors by id; documents without one are dropped."""
    return docs.join(embeddings.select(F.col("vec_id").alias("doc_id"), F.col("embedding").cast("array<double>").alias("v")), "doc_id")


def hashed(docs: DataFrame, dim: int = 64, text: str = "text", id_col: str = "doc_id") -> DataFrame:
    """(doc_id, v): word counts in signed hash buckets, at unit length, made inside the row; a text without words has the zero vector.

    Stored ``codes`` of the text, if there are any, spare the hashing.
    """
    stored = "codes" in docs.columns and text == "text" and CODES % (2 * dim) == 0
    return docs.select(F.col(id_col).alias("doc_id"), (coded_bag(F.col("codes"), dim) if stored else hashed_bag(words(F.lower(F.col(text))), dim)).alias("v"))


def encoded(docs: DataFrame, encoder: Callable, text: str = "text") -> DataFrame:
    """``encoder``: a pandas function from texts to arrays of doubles."""
    return docs.select("doc_id", encoder(F.col(text)).alias("v"))
