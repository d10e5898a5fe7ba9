"""Accuracy and cost measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def ordinal(df: DataFrame, y: str = "quality", yhat: str = "predicted", tolerance: int = 1) -> DataFrame:
    """One row: accuracy, mean absolute and squared error, accuracy within ``tolerance`` levels."""
    gap = F.abs(F.col(y) - F.col(yhat))
    return df.agg(
        F.count("*").alias("n"), F.avg((gap == 0).cast("double")).alias("acc"), F.avg(gap.cast("double")).alias("mae"), F.avg((gap * gap).cast("double")).alias("mse"), F.avg((gap <= tolerance).cast("double")).alias("cacc")
    )


def confusion(df: DataFrame, y: str = "quality", yhat: str = "predicted") -> DataFrame:
    return df.groupBy(F.col(y).alias("level"), F.col(yhat).alias("predicted_level")).agg(F.count("*").alias("n"))


def mix_distance(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: total variation and Kullback-Leibler divergence of two (domain, weight) tables; infinite where b lacks a domain of a."""
    both = a.select("domain", F.col("weight").alias("wa")).join(b.select("domain", F.col("weight").alias("wb")), "domain", "full").na.fill(0.0, ["wa", "wb"])
    kl = F.when(F.col("wa") == 0, 0.0).when(F.col("wb") == 0, F.lit(float("inf"))).otherwise(F.col("wa") * F.ln(F.col("wa") / F.when(F.col("wb") > 0, F.col("wb"))))
    return both.agg((F.sum(F.abs(F.col("wa") - F.col("wb"))) / 2).alias("total_variation"), F.sum(kl).alias("kl"))


def budget_error(df: DataFrame, share: float) -> DataFrame:
    """One row: tokens asked for, drawn and expected, and the relative errors; ``df`` has n_tokens, c, copies for all documents."""
    g = df.agg((F.sum("n_tokens") * F.lit(float(share))).alias("asked"), F.sum(F.col("n_tokens") * F.col("copies")).cast("long").alias("drawn"), F.sum(F.col("n_tokens") * F.col("c")).alias("expected"))
    return g.select("asked", "drawn", "expected", ((F.col("drawn") - F.col("asked")) / F.col("asked")).alias("error"), ((F.col("expected") - F.col("asked")) / F.col("asked")).alias("expected_error"))


def steps_to_target(curve: DataFrame, target: DataFrame, higher_is_better: bool = True) -> DataFrame:
    """(method, first_step): the first checkpoint at or beyond the target's single value; null if none is."""
    hit = (F.col("metric") >= F.col("target")) if higher_is_better else (F.col("metric") <= F.col("target"))
    return curve.crossJoin(F.broadcast(target)).groupBy("method").agg(F.min(F.when(hit, F.col("step"))).alias("first_step"), F.max("step").alias("last_step"), F.first("target").alias("target"))


def leaderboard(results: DataFrame) -> DataFrame:
    """Rank of each method per metric; ``higher`` tells the metric's direction."""
    w = Window.partitionBy("metric").orderBy(F.when(F.col("higher"), -F.col("value")).otherwise(F.col("value")))
    return results.withColumn("place", F.dense_rank().over(w))


def coverage(man: DataFrame) -> DataFrame:
    """One row on the redundancy of a manifest with text_hash and cluster: copies, share of repeated texts, clusters met, sum of squared cluster shares."""
    total = man.agg(F.sum("copies").alias("all_copies"))
    texts = man.agg(F.count_distinct("text_hash").alias("n_texts"), F.count_distinct("cluster").alias("n_clusters"))
    squares = man.groupBy("cluster").agg(F.sum("copies").alias("k")).agg(F.sum(F.col("k") * F.col("k")).alias("k2"))
    return total.crossJoin(texts).crossJoin(squares).select(
        F.col("all_copies").cast("long").alias("n_copies"), (1 - F.col("n_texts") / F.col("all_copies")).alias("repeated_share"), "n_clusters", (F.col("k2") / (F.col("all_copies") * F.col("all_copies"))).alias("concentration")
    )


def engine_cost(spark: SparkSession) -> dict[str, float]:
    """What the application's executors have spent so far: task seconds, GB read from files and moved through shuffles, peak GB of heap."""
    store, gb = spark.sparkContext._jsc.sc().statusStore().executorList(False), float(1 << 30)
    out = {"task_s": 0.0, "input_gb": 0.0, "shuffle_read_gb": 0.0, "shuffle_write_gb": 0.0, "peak_heap_gb": 0.0}
    for i in range(store.size()):
        e = store.apply(i)
        out["task_s"] += e.totalDuration() / 1000
        out["input_gb"] += e.totalInputBytes() / gb
        out["shuffle_read_gb"] += e.totalShuffleRead() / gb
        out["shuffle_write_gb"] += e.totalShuffleWrite() / gb
        peak = e.peakMemoryMetrics()
        out["peak_heap_gb"] = max(out["peak_heap_gb"], peak.get().getMetricValue("JVMHeapMemory") / gb if peak.isDefined() else 0.0)
    return {k: round(v, 4) for k, v in out.items()}
