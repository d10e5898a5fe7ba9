"""From scores to copies: normalisation, blending, temperature softmax, stochastic rounding."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from mixwright.functions.hashing import uniform
from mixwright.functions.storage import kept

ALPHA, TAU, SEED = 0.8, 0.2, 42


def check(alpha: float = ALPHA, tau: float = TAU) -> None:
    if not 0 <= alpha <= 1:
        raise ValueError("alpha must be in [0, 1]")
    if not tau > 0:
        raise ValueError("tau must be positive")


def _scaled(c: Column, low: Column, high: Column) -> Column:
    clipped = F.greatest(low, F.least(high, c))
    return F.when(high > low, (clipped - low) / (high - low)).otherwise(F.lit(0.0))


def minmax(df: DataFrame, cols: Iterable[str] = ("quality", "diversity"), clip: tuple[float, float] | None = None, suffix: str = "_01") -> DataFrame:
    """Scale columns to [0, 1] over the whole table; a constant column becomes 0. ``clip`` takes quantiles for the ends."""
    cols = list(cols)
    if clip:
        # Exact over distinct values and their numbers: scores have a value per cell, so the last task sees few rows.
        ends = None
        for c in cols:
            values = df.groupBy(F.col(c).cast("double").alias("_v")).agg(F.count("*").alias("_n"))
            one = values.agg(*[F.percentile("_v", F.lit(q), F.col("_n")).alias(f"{c}_{end}") for q, end in zip(clip, ("low", "high"), strict=True)])
            ends = one if ends is None else ends.crossJoin(F.broadcast(one))
    else:
        ends = df.agg(*[f(c).cast("double").alias(f"{c}_{end}") for c in cols for f, end in ((F.min, "low"), (F.max, "high"))])
    scaled = {f"{c}{suffix}": _scaled(F.col(c).cast("double"), F.col(f"{c}_low"), F.col(f"{c}_high")) for c in cols}
    return df.crossJoin(F.broadcast(ends)).withColumns(scaled).drop(*ends.columns)


def weight(df: DataFrame, alpha: float = ALPHA) -> DataFrame:
    check(alpha=alpha)
    return df.withColumn("p", F.lit(float(alpha)) * F.col("diversity_01") + F.lit(1.0 - alpha) * F.col("quality_01"))


def target_docs(n_docs: float, t_src: float, t_tgt: float) -> float:
    """Documents to draw so that the token budget is met at the mean length."""
    return n_docs * t_tgt / t_src if t_src else 0.0


def frequency(df: DataFrame, tau: float = TAU, t_tgt: float | None = None, share: float | None = None, budget: str = "documents") -> DataFrame:
    """Append ``c``, the expected copies of each row; rows may stand for ``n`` documents each if there is such a column.

    The budget is ``t_tgt`` tokens, or ``share`` of the source's. 'documents' scales the document count, as the method has it;
    'tokens' rescales so that the expected tokens meet the budget.
    """
    check(tau=tau)
    if (t_tgt is None) == (share is None):
        raise ValueError("give either a token budget or a share of the source")
    times = F.col("n") if "n" in df.columns else F.lit(1)
    tokens = F.col("tokens") if "n" in df.columns else F.col("n_tokens")
    top = df.agg(F.max("p").alias("p_top"))
    shifted = F.exp((F.col("p") - F.col("p_top")) / F.lit(float(tau)))
    with_top = df.crossJoin(F.broadcast(top))
    per_doc_tokens = tokens if "n" not in df.columns else tokens
    sums = with_top.agg(
        F.sum(times * shifted).alias("z_total"),
        F.sum(times).cast("double").alias("n_total"),
        F.sum(tokens).cast("double").alias("t_total"),
        F.sum(shifted * per_doc_tokens).alias("zt_total"),
    )
    goal = F.lit(float(t_tgt)) if t_tgt is not None else F.lit(float(share)) * F.col("t_total")
    scale = {"documents": F.col("n_total") * goal / F.col("t_total") / F.col("z_total"), "tokens": goal / F.col("zt_total")}
    if budget not in scale:
        raise ValueError(f"unknown budget {budget!r}")
    return with_top.crossJoin(F.broadcast(sums)).withColumn("c", scale[budget] * shifted).drop("p_top", *sums.columns)


def copies(df: DataFrame, seed: int = SEED, id_col: str = "doc_id", rng: str = "md5", digits: int = 9) -> DataFrame:
    """Append ``copies``: the whole part of c, and one more with the chance of the rest. The draw is fixed by id, so growing
    budgets give nested samples. c is rounded to ``digits`` first, lest the last bit flips a floor between engines."""
    c = F.round("c", digits)
    return df.withColumn("copies", (F.floor(c) + (uniform(id_col, seed, rng) < c - F.floor(c)).cast("int")).cast("int"))


def score_frequencies(df: DataFrame, alpha: float = ALPHA, tau: float = TAU, t_tgt: float | None = None, share: float | None = None, budget: str = "documents", clip: tuple[float, float] | None = None) -> DataFrame:
    """minmax, weight and frequency in one go, for rows with quality, diversity and n_tokens."""
    return frequency(weight(minmax(df, clip=clip), alpha), tau, t_tgt, share, budget)


def manifest(df: DataFrame) -> DataFrame:
    """Rows of at least one copy."""
    return df.filter("copies > 0")


def materialise(man: DataFrame, docs: DataFrame) -> DataFrame:
    """One physical row per copy."""
    rows = man.select("doc_id", F.explode(F.sequence(F.lit(1), F.col("copies"))).alias("copy"))
    return rows.join(docs, "doc_id")


def order(man: DataFrame, seed: int = SEED) -> DataFrame:
    """Copies in a random training order that any partitioning reproduces; ``spot`` is the sort key."""
    rows = man.select("*", F.explode(F.sequence(F.lit(1), F.col("copies"))).alias("copy"))
    key = uniform(F.concat_ws("/", F.col("doc_id").cast("string"), F.col("copy").cast("string")), seed)
    return rows.withColumn("spot", key)


def numbered(rows: DataFrame, keys: tuple[str, ...] = ("spot", "doc_id", "copy"), out: str = "place") -> DataFrame:
    """Append the 1-based place in the order of ``keys``: ranges are sorted apart, and a row per range tells where each begins."""
    ranged = kept(rows.repartitionByRange(*keys).withColumn("_part", F.spark_partition_id()), "ranges")
    sizes = ranged.groupBy("_part").agg(F.count("*").alias("_n"))
    starts = sizes.select("_part", (F.sum("_n").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, Window.currentRow)) - F.col("_n")).alias("_start"))
    own = F.row_number().over(Window.partitionBy("_part").orderBy(*keys))
    return ranged.join(F.broadcast(starts), "_part").withColumn(out, (F.col("_start") + own).cast("long")).drop("_part", "_start")


def top_budget(df: DataFrame, share: float, id_col: str = "doc_id") -> DataFrame:
    """Best weights first until the budget is spent: the foil to sampling.

    The running sum is taken over distinct weights (few, as quality has levels and diversity is per cluster), then within the one
    weight where the budget ends, never over all documents in one task.
    """
    levels = df.groupBy("p").agg(F.sum("n_tokens").alias("level_tokens"))
    run = levels.withColumn("before", F.coalesce(F.sum("level_tokens").over(Window.orderBy(F.col("p").desc()).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    goal = levels.agg((F.sum("level_tokens") * F.lit(float(share))).alias("goal"))
    placed = df.join(F.broadcast(run.crossJoin(F.broadcast(goal))), "p").filter("before < goal")
    whole = placed.filter("before + level_tokens <= goal")
    edge = placed.filter("before + level_tokens > goal")
    w = Window.partitionBy("p").orderBy(uniform(id_col), id_col).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    edge = edge.withColumn("upto", F.col("before") + F.sum("n_tokens").over(w)).filter("upto <= goal").drop("upto")
    return whole.unionByName(edge).drop("level_tokens", "before", "goal").withColumn("copies", F.lit(1))
