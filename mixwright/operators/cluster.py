"""K-Means and its variants over (doc_id, v) tables."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.ml.clustering import KMeans
from pyspark.ml.functions import array_to_vector
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mixwright.functions.hashing import uniform
from mixwright.functions.vectors import distance, mean_vector


def default_k(n: int) -> int:
    return max(1, round((n / 2) ** 0.5))


def given(df: DataFrame, column: str = "label") -> DataFrame:
    return df.withColumn("cluster", F.col(column))


def fit_kmeans(vecs: DataFrame, k: int, seed: int = 42, iters: int = 20, engine: str = "mllib", fit_fraction: float = 1.0) -> DataFrame:
    """(cluster, centroid). The fit sees every row, or a hashed ``fit_fraction`` of the ids if one is asked; every row can still be assigned."""
    rows = vecs if fit_fraction >= 1 else vecs.filter(uniform("doc_id", seed) < fit_fraction)
    if engine == "lloyd":
        return lloyd(rows, k, iters)
    if engine != "mllib":
        raise ValueError(f"unknown engine {engine!r}")
    model = KMeans(k=k, seed=seed, maxIter=iters, featuresCol="x").fit(rows.orderBy("doc_id").select(array_to_vector("v").alias("x")))
    return vecs.sparkSession.createDataFrame([(i, [float(x) for x in c]) for i, c in enumerate(model.clusterCenters())], "cluster int, centroid array<double>")


def nearest(vecs: DataFrame, cents: DataFrame, digits: int | None = None) -> DataFrame:
    """Append cluster and dist with column functions; ties (to ``digits``, if given) go to the lowest cluster. Centroids, K rows, are broadcast as one array."""
    table = cents.agg(F.array_sort(F.collect_list(F.struct("cluster", "centroid"))).alias("_cents"))
    cut = lambda x: F.round(x, digits) if digits is not None else x
    gaps = lambda: F.transform("_cents", lambda c: F.struct(cut(distance(F.col("v"), c["centroid"])).alias("dist"), c["cluster"].alias("cluster")))
    best = vecs.crossJoin(F.broadcast(table)).withColumn("_best", F.array_min(gaps()))
    return best.withColumn("cluster", F.col("_best.cluster")).withColumn("dist", F.col("_best.dist")).drop("_best", "_cents")


def assign(vecs: DataFrame, cents: DataFrame) -> DataFrame:
    """As ``nearest``, by matrix products of blocks in Python: the faster way for many clusters or wide vectors."""
    rows = cents.orderBy("cluster").collect()  # K rows
    ids, c = np.array([r["cluster"] for r in rows]), np.array([r["centroid"] for r in rows], dtype=float)
    norms = (c * c).sum(axis=1)

    @F.pandas_udf("struct<cluster: int, dist: double>")
    def block(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        for s in batches:
            x = np.stack(s.to_numpy()).astype(float) if len(s) else np.zeros((0, c.shape[1]))
            best = (norms - 2 * x @ c.T).argmin(axis=1)
            yield pd.DataFrame({"cluster": ids[best].astype(np.int32), "dist": np.sqrt(((x - c[best]) ** 2).sum(axis=1))})

    return vecs.withColumn("_a", block("v")).withColumn("cluster", F.col("_a.cluster")).withColumn("dist", F.col("_a.dist")).drop("_a")


def lloyd(vecs: DataFrame, k: int, rounds: int = 3) -> DataFrame:
    """Lloyd's rounds with fixed starts (the k ids of least digest) and lowest-id ties: checkable in SQL."""
    starts = vecs.orderBy(F.md5(F.col("doc_id").cast("string").cast("binary")), "doc_id").limit(k)
    order = F.row_number().over(_by_digest())
    cents = starts.select((order - 1).alias("cluster"), F.col("v").alias("centroid"))
    for _ in range(rounds):
        moved = mean_vector(nearest(vecs, cents, 9).select("cluster", "v"), ["cluster"], "v", "moved")
        cents = cents.join(F.broadcast(moved), "cluster", "left").select("cluster", F.coalesce("moved", "centroid").alias("centroid"))
    return cents


def _by_digest():
    from pyspark.sql import Window

    return Window.orderBy(F.md5(F.col("doc_id").cast("string").cast("binary")), "doc_id")  # over the k starting rows only


def two_level(vecs: DataFrame, k_coarse: int, k_fine: int, seed: int = 42, iters: int = 10) -> DataFrame:
    """Append cluster = coarse * k_fine + fine: a coarse fit, then a fine one in every cell, all cells in one grouped pass.

    Fine fits run on at most ``FINE_ROWS`` hashed rows of a cell, a documented bound on the fit; every row is assigned.
    """
    coarse = assign(vecs, fit_kmeans(vecs, k_coarse, seed, iters)).drop("dist")
    per_cell = coarse.groupBy("cluster").agg(F.count("*").alias("n"))
    sample = coarse.join(F.broadcast(per_cell), "cluster").filter(uniform("doc_id", seed + 1) < FINE_ROWS / F.col("n"))

    def fit(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        x = np.stack(pdf.sort_values("doc_id")["v"].to_numpy()).astype(float)
        rng = np.random.default_rng(seed)
        c = x[rng.choice(len(x), min(k_fine, len(x)), replace=False)]
        for _ in range(iters):
            best = ((x * x).sum(1)[:, None] - 2 * x @ c.T + (c * c).sum(1)).argmin(1)
            c = np.stack([x[best == j].mean(0) if (best == j).any() else c[j] for j in range(len(c))])
        return pd.DataFrame({"coarse": key[0], "fine": np.arange(len(c)), "centroid": list(c)})

    fine = sample.groupBy("cluster").applyInPandas(fit, "coarse int, fine int, centroid array<double>")
    table = fine.groupBy("coarse").agg(F.array_sort(F.collect_list(F.struct("fine", "centroid"))).alias("cents"))
    near = coarse.withColumnRenamed("cluster", "coarse").join(F.broadcast(table), "coarse")
    best = F.array_min(F.transform("cents", lambda c: F.struct(distance(F.col("v"), c["centroid"]).alias("dist"), c["fine"].alias("fine"))))
    return near.withColumn("_b", best).withColumn("cluster", F.col("coarse") * k_fine + F.col("_b.fine")).withColumn("dist", F.col("_b.dist")).drop("_b", "cents", "coarse")


FINE_ROWS = 20_000
