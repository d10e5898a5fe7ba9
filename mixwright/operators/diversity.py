"""Cluster compactness, cluster separation and document diversity."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from mixwright.functions.storage import checked, kept
from mixwright.functions.vectors import distance, dot, mean_vector


#: Centroids that are broadcast.
MAX_CLUSTERS = 100_000


def centroids(assigned: DataFrame, vector: str = "v") -> DataFrame:
    """(cluster, centroid) as the mean of the members."""
    return mean_vector(assigned, ["cluster"], vector, "centroid")


def compactness(assigned: DataFrame, cents: DataFrame, metric: str = "euclidean", vector: str = "v", singleton: str = "literal") -> DataFrame:
    """(cluster, n, compactness): mean distance of members to their centroid; small means dense.

    A cluster of one has compactness 0 by the letter; ``singleton`` may be 'median' or 'max' of the other clusters instead.
    """
    near = assigned.join(checked(cents, MAX_CLUSTERS), "cluster")
    out = near.groupBy("cluster").agg(F.count("*").alias("n"), F.avg(distance(F.col(vector), F.col("centroid"), metric)).alias("compactness"))
    if singleton == "literal":
        return out
    if singleton not in ("median", "max"):
        raise ValueError(f"unknown singleton policy {singleton!r}")
    stand_in = out.filter("n > 1").agg((F.median("compactness") if singleton == "median" else F.max("compactness")).alias("other"))
    return out.crossJoin(F.broadcast(stand_in)).select("cluster", "n", F.when(F.col("n") == 1, F.coalesce("other", F.lit(0.0))).otherwise(F.col("compactness")).alias("compactness"))


def separation(cents: DataFrame, agg: str = "mean", metric: str = "euclidean", nearest: int = 3, alone: float | None = None) -> DataFrame:
    """(cluster, separation): distance of a centroid to the others; large means isolated.

    ``agg``: 'mean' of all others, 'min', 'knn' (mean of the ``nearest``), or 'mean_sq_fast', the mean squared distance from two
    sums over all centroids, without pairs. A lone cluster has no separation: null, or ``alone``.
    """
    if agg == "mean_sq_fast":
        total = mean_vector(cents.withColumn("one", F.lit(1)), ["one"], "centroid", "mean")
        sums = cents.agg(F.count("*").alias("k"), F.sum(dot(F.col("centroid"), F.col("centroid"))).alias("norms"))
        c, k = F.col("centroid"), F.col("k")
        value = (k * dot(c, c) + F.col("norms") - 2 * k * dot(c, F.col("mean"))) / (k - 1)
        return cents.crossJoin(F.broadcast(total)).crossJoin(F.broadcast(sums)).select("cluster", F.when(k > 1, value).otherwise(F.lit(alone)).alias("separation"))
    other = cents.select(F.col("cluster").alias("other"), F.col("centroid").alias("far"))
    # K rows against K rows: the number of clusters, not of documents. Beyond some ten thousand clusters 'mean_sq_fast' needs no pairs.
    gaps = cents.join(F.broadcast(other), F.col("cluster") != F.col("other")).select("cluster", "other", distance(F.col("centroid"), F.col("far"), metric).alias("gap"))
    if agg == "knn":
        w = Window.partitionBy("cluster").orderBy("gap", "other")
        gaps = gaps.withColumn("nth", F.row_number().over(w)).filter(F.col("nth") <= nearest)
    elif agg not in ("mean", "min"):
        raise ValueError(f"unknown separation {agg!r}")
    out = gaps.groupBy("cluster").agg((F.min("gap") if agg == "min" else F.avg("gap")).alias("separation"))
    return cents.select("cluster").join(out, "cluster", "left").select("cluster", F.coalesce("separation", F.lit(alone).cast("double")).alias("separation"))


def cluster_table(assigned: DataFrame, metric: str = "euclidean", agg: str = "mean", vector: str = "v", singleton: str = "literal", alone: float | None = None) -> DataFrame:
    """(cluster, n, compactness, separation, diversity)."""
    cents = kept(centroids(assigned, vector), "centroids")
    both = compactness(assigned, cents, metric, vector, singleton).join(separation(cents, agg, metric, alone=alone), "cluster")
    return both.withColumn("diversity", F.col("compactness") * F.col("separation"))


def score(docs: DataFrame, clusters: DataFrame) -> DataFrame:
    """Diversity of a document is that of its cluster; the cluster table has a row per cluster and is broadcast."""
    return docs.join(F.broadcast(clusters.select("cluster", "diversity")), "cluster")
