"""Corpus statistics and preparation: filters, exact and near duplicates, decontamination, fractions."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from mixwright.functions.hashing import CODES, buckets, meets, uniform, windows
from mixwright.functions.storage import checked, kept
from mixwright.functions.text import n_tokens, ngrams, words
from mixwright.functions.udfs import nfc as nfc_of

from .near import NearSets, folded

#: Rows of a broadcast table of grams or ids.
MAX_GRAMS = 2_000_000


def stats(docs: DataFrame, by: tuple[str, ...] = ("domain",)) -> DataFrame:
    """Documents and tokens per group, and their shares of all."""
    g = docs.groupBy(*by).agg(F.count("*").alias("n_docs"), F.sum("n_tokens").cast("long").alias("n_tokens"))
    whole = g.agg(F.sum("n_docs").alias("all_docs"), F.sum("n_tokens").alias("all_tokens"))
    return g.crossJoin(F.broadcast(whole)).select(
        *by, "n_docs", "n_tokens", (F.col("n_docs") / F.col("all_docs")).alias("share_docs"), (F.col("n_tokens") / F.col("all_tokens")).alias("share_tokens")
    )


def nfc(docs: DataFrame, text: str = "text") -> DataFrame:
    """Unicode normal form C. ASCII rows need nothing, so they do not go through Python."""
    plain = F.coalesce(F.col(text).rlike(r"^[\x00-\x7F]*$"), F.lit(True))
    return docs.filter(plain).unionByName(docs.filter(~plain).withColumn(text, nfc_of(text)))


def length_filter(docs: DataFrame, min_tokens: int = 20, max_tokens: int | None = None, tokens: str = "n_tokens") -> DataFrame:
    c = F.col(tokens) >= min_tokens
    return docs.filter(c & (F.col(tokens) <= max_tokens) if max_tokens is not None else c)


def dedup_exact(docs: DataFrame, text: str = "text", id_col: str = "doc_id") -> DataFrame:
    """Ids of the first row of each text. Digests are shuffled, not texts."""
    return docs.select(id_col, F.sha2(F.coalesce(F.col(text), F.lit("")), 256).alias("digest")).groupBy("digest").agg(F.min(id_col).alias(id_col), F.count("*").alias("n_copies")).drop("digest")


def cross_domain_copies(docs: DataFrame, domain: str = "domain", text: str = "text") -> DataFrame:
    """Groups of equal texts: how many there are, and how many span domains."""
    g = docs.select(domain, F.md5(F.col(text).cast("binary")).alias("digest")).groupBy("digest").agg(F.count("*").alias("n"), F.count_distinct(domain).alias("spans"))
    return g.filter("n > 1").agg(F.count("*").alias("n_groups"), F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("n_rows"), F.count_if(F.col("spans") > 1).alias("n_cross"))


def shingles(docs: DataFrame, n: int, text: str = "text", id_col: str = "doc_id", distinct: bool = True) -> DataFrame:
    """(id, gram): lower-cased word n-grams."""
    tokens = docs.select(id_col, words(F.lower(F.col(text))).alias("tokens"))
    grams = ngrams(F.col("tokens"), n)
    return tokens.select(id_col, F.explode(F.array_distinct(grams) if distinct else grams).alias("gram"))


def decontaminate(docs: DataFrame, bench: DataFrame, n: int = 8, text: str = "text", id_col: str = "doc_id") -> DataFrame:
    """Documents that share no n-gram with the benchmark.

    The benchmark's distinct grams, 8 bytes each, are broadcast if they are counted to be at most ``MAX_GRAMS``; hashes of a
    document's grams are made in its row, and documents that hit one are checked by the grams themselves. Stored ``codes`` of the
    text, if there are any, are hashed instead of the grams.
    """
    bad = kept(shingles(bench, n, text, bench.columns[0]).select("gram").distinct().withColumn("h", F.xxhash64("gram")), "benchmark-grams")
    hashes = bad.select("h").distinct()
    few = bad.count() <= MAX_GRAMS
    if few and "codes" in docs.columns and text == "text":
        coded = bench.select(windows(buckets(words(F.lower(F.col(text))), CODES), n).alias("h"))
        asked = np.array([r[0] for r in coded.select(F.explode("h")).distinct().collect()], np.int64)
        hit = docs.filter(meets(F.col("codes"), n, asked)).select(id_col).distinct()
    else:
        hashes = F.broadcast(hashes) if few else hashes
        hit = shingles(docs, n, text, id_col, distinct=False).select(id_col, F.xxhash64("gram").alias("h")).join(hashes, "h", "left_semi").select(id_col).distinct()
    hit = kept(hit, "benchmark-hits")
    some = F.broadcast(hit) if hit.count() <= MAX_GRAMS else hit
    dirty = shingles(docs.join(some, id_col, "left_semi"), n, text, id_col).join(bad, "gram", "left_semi").select(id_col).distinct()
    return docs.join(checked(kept(dirty, "benchmark-documents"), MAX_GRAMS), id_col, "left_anti")


def near_pairs(docs: DataFrame, n: int = 5, threshold: float = 0.8, text: str = "text", id_col: str = "doc_id") -> DataFrame:
    """All pairs of distinct sets of word n-grams with Jaccard similarity of at least ``threshold``, by the smallest id of each set.

    A text of fewer than ``n`` words is one gram. ``near_members`` tells which documents each id stands for.
    """
    near = NearSets(docs, id_col, folded(text), n, threshold)
    at = lambda x: near.nodes.select(F.col("node").alias(x), F.col("least").alias(f"least_{x}"), F.col("n").alias(f"n_{x}"))
    both = near.links(every=True).join(at("a"), "a").join(at("b"), "b")
    return both.select(F.least("least_a", "least_b").alias("id_a"), F.greatest("least_a", "least_b").alias("id_b"), (F.col("shared") / (F.col("n_a") + F.col("n_b") - F.col("shared"))).alias("jaccard"))


def near_members(docs: DataFrame, n: int = 5, threshold: float = 0.8, text: str = "text", id_col: str = "doc_id") -> DataFrame:
    """(id, representative, class_id) of every document: the smallest id with its set of n-grams, and the smallest its near copies connect it to."""
    near = NearSets(docs, id_col, folded(text), n, threshold)
    classes = near.classes(near.links()).groupBy("id").agg(F.first("component").alias("class_id"))
    named = near.prints.join(near.nodes.select("key", "least"), "key").groupBy("id").agg(F.min("least").alias("representative"))
    return named.join(classes, "id").select(F.col("id").alias(id_col), "representative", "class_id")


def near_dedup(docs: DataFrame, n: int = 5, threshold: float = 0.8, text: str = "text", id_col: str = "doc_id") -> DataFrame:
    """The first document of each class of near copies; rows without an id stay."""
    near = NearSets(docs, id_col, folded(text), n, threshold)
    gone = near.classes(near.links()).filter("id <> component").select(F.col("id").alias("_gone")).distinct()
    return docs.join(gone, F.col(id_col) == F.col("_gone"), "left_anti")


def preparation(docs: DataFrame, min_tokens: int = 20, max_tokens: int | None = None, text: str = "text", id_col: str = "doc_id") -> tuple[DataFrame, DataFrame]:
    """The corpus in normal form C, within the length limits and without a second copy of any text; and (step, n_docs, n_tokens) of each step."""
    steps = [("source", docs.withColumn("n_tokens", n_tokens(text)))]
    normal = kept(nfc(docs, text).withColumn("n_tokens", n_tokens(text)), "normal-form")
    fit = length_filter(normal, min_tokens, max_tokens)
    first = kept(dedup_exact(fit, text, id_col).select(F.col(id_col).alias("_first")), "first-copies")
    out = fit.join(first, F.col(id_col) == F.col("_first"), "left_semi")
    steps += [("normal_form", normal), ("length", fit), ("dedup", out)]
    counts = None
    for k, (name, df) in enumerate(steps):
        one = df.agg(F.lit(k).alias("step"), F.lit(name).alias("name"), F.count("*").alias("n_docs"), F.coalesce(F.sum("n_tokens"), F.lit(0)).cast("long").alias("n_tokens"))
        counts = one if counts is None else counts.unionByName(one)
    return out, counts


def fraction(docs: DataFrame, share: float, seed: int = 42, id_col: str = "doc_id") -> DataFrame:
    """The rows whose draw is below ``share``; samples of growing share are nested."""
    return docs.filter(uniform(id_col, seed) < share)


def prepared(docs: DataFrame, domain: str = "source", id_col: str = "doc_id") -> DataFrame:
    return docs.select(F.col(id_col).alias("doc_id"), F.col(domain).alias("domain"), n_tokens("text").alias("n_tokens"), "text")


def first_rows(docs: DataFrame, by: str, order: list, n: int) -> DataFrame:
    return docs.withColumn("nth", F.row_number().over(Window.partitionBy(by).orderBy(*order))).filter(F.col("nth") <= n)
