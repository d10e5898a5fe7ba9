"""Uniform sampling within domains from domain weights, and simple ways to such weights."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .sampling import copies


def normalise(weights: DataFrame) -> DataFrame:
    """Weights of sum 1; (domain, weight) tables have a row per domain."""
    total = weights.agg(F.sum("weight").alias("total"))
    return weights.crossJoin(F.broadcast(total)).select("domain", (F.col("weight") / F.col("total")).alias("weight"))


def natural(stats: DataFrame) -> DataFrame:
    return stats.select("domain", F.col("share_tokens").alias("weight"))


def exclude(weights: DataFrame, names: list[str]) -> DataFrame:
    return normalise(weights.filter(~F.col("domain").isin(names)))


def manual(stats: DataFrame, factors: dict[str, float]) -> DataFrame:
    """Token shares times hand-set factors, 1 where none is set."""
    table = F.create_map(*[F.lit(x) for kv in factors.items() for x in kv]) if factors else None
    factor = F.coalesce(F.element_at(table, F.col("domain")), F.lit(1.0)) if factors else F.lit(1.0)
    return normalise(stats.select("domain", (F.col("share_tokens") * factor).alias("weight")))


def from_metric(metric: DataFrame, power: float = 1.0) -> DataFrame:
    """Weights in proportion to a power of (domain, metric), such as a small model's loss."""
    return normalise(metric.select("domain", F.pow("metric", F.lit(float(power))).alias("weight")))


def sample(docs: DataFrame, weights: DataFrame, share: float | None = None, t_tgt: float | None = None, seed: int = 42) -> DataFrame:
    """Append c and copies: each domain's rate is its part of the budget over its tokens; rates above 1 repeat documents."""
    tokens = docs.groupBy("domain").agg(F.sum("n_tokens").alias("dom_tokens"))
    w = Window.partitionBy(F.lit(1))  # a row per domain
    rate = tokens.withColumn("all_tokens", F.sum("dom_tokens").over(w)).join(weights, "domain")
    goal = F.lit(float(t_tgt)) if t_tgt is not None else F.lit(float(share)) * F.col("all_tokens")
    rate = rate.select("domain", (F.col("weight") * goal / F.col("dom_tokens")).alias("c"))
    return copies(docs.join(F.broadcast(rate), "domain"), seed)
