"""Distributions, overlap, copy counts."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from mixwright.functions.hashing import uniform
from mixwright.functions.vectors import dot


ALL = "*"


def quality_profile(docs: DataFrame, domain: str = "domain", level: str = "quality", overall: bool = True) -> DataFrame:
    """(domain, level, n, share, mean of the domain), and the same over all domains as domain ``ALL``."""
    g = docs.groupBy(F.col(domain).alias("domain"), F.col(level).alias("level")).agg(F.count("*").alias("n"))
    if overall:
        g = g.unionByName(g.groupBy(F.lit(ALL).alias("domain"), "level").agg(F.sum("n").alias("n")))
    w = Window.partitionBy("domain")
    return g.select("domain", "level", "n", (F.col("n") / F.sum("n").over(w)).alias("share"), (F.sum(F.col("n") * F.col("level")).over(w) / F.sum("n").over(w)).alias("mean_level"))


def quality_by_length(docs: DataFrame, edges: tuple[int, ...] = (20, 50, 100, 200, 400), level: str = "quality") -> DataFrame:
    length = F.lit(0)
    for e in edges:
        length = F.when(F.col("n_tokens") >= e, F.lit(e)).otherwise(length)
    return docs.groupBy(length.alias("min_tokens")).agg(F.count("*").alias("n"), F.avg(level).alias("mean_level"))


def diversity_profile(docs: DataFrame, bins: int = 10, domain: str = "domain", value: str = "diversity_01") -> DataFrame:
    return docs.groupBy(F.col(domain).alias("domain"), F.least(F.floor(F.col(value) * bins), F.lit(bins - 1)).cast("int").alias("bin")).agg(F.count("*").alias("n"), F.avg(value).alias("mean_value"))


def diversity_spread(docs: DataFrame, domain: str = "domain", value: str = "diversity_01") -> DataFrame:
    """(domain, n, mean, spread, exact median); the last step sees a row per domain and distinct value."""
    g = docs.groupBy(F.col(domain).alias("domain"), F.col(value).alias("_v")).agg(F.count("*").alias("_n"))
    mean = F.sum(F.col("_v") * F.col("_n")) / F.sum("_n")
    out = g.groupBy("domain").agg(F.sum("_n").alias("n"), mean.alias("mean_value"), F.percentile("_v", F.lit(0.5), F.col("_n")).alias("median_value"))
    gap = F.pow(F.col("_v") - F.col("mean_value"), 2)
    spread = g.join(F.broadcast(out.select("domain", "mean_value")), "domain").groupBy("domain").agg(F.sqrt(F.sum(gap * F.col("_n")) / F.sum("_n")).alias("sd_value"))
    return out.join(spread, "domain").select("domain", "n", "mean_value", "sd_value", "median_value")


def domain_mix(drawn: DataFrame, domain: str = "domain") -> DataFrame:
    """Documents, copies and tokens per domain of source and target, and shares of tokens; ``drawn`` keeps rows without copies."""
    g = drawn.groupBy(F.col(domain).alias("domain")).agg(F.count("*").alias("n_docs"), F.sum("copies").cast("long").alias("n_copies"), F.sum("n_tokens").cast("long").alias("source_tokens"), F.sum(F.col("n_tokens") * F.col("copies")).cast("long").alias("target_tokens"))
    w = Window.partitionBy(F.lit(1))
    return g.select("*", (F.col("source_tokens") / F.sum("source_tokens").over(w)).alias("source_share"), (F.col("target_tokens") / F.sum("target_tokens").over(w)).alias("target_share"))


def rate_spread(df: DataFrame, domain: str = "domain") -> DataFrame:
    return df.groupBy(F.col(domain).alias("domain")).agg(F.min("c").alias("min_c"), F.avg("c").alias("mean_c"), F.max("c").alias("max_c"), F.stddev_pop("c").alias("sd_c"))


def overlap(assigned: DataFrame, domain: str = "domain") -> DataFrame:
    """(dom_a, dom_b, n_clusters_a, n_shared, pct): of the clusters that hold dom_a, how many also hold dom_b.

    Pairs are of domains within a cluster, after a distinct: domains squared per cluster, whatever its documents.
    """
    cells = assigned.select(F.col(domain).alias("domain"), "cluster").distinct()
    a, b = cells.select(F.col("domain").alias("dom_a"), "cluster"), cells.select(F.col("domain").alias("dom_b"), "cluster")
    shared = a.join(b, "cluster").groupBy("dom_a", "dom_b").agg(F.count("*").alias("n_shared"))
    own = cells.groupBy(F.col("domain").alias("dom_a")).agg(F.count("*").alias("n_clusters_a"))
    names = cells.select("domain").distinct()
    grid = names.select(F.col("domain").alias("dom_a")).crossJoin(F.broadcast(names.select(F.col("domain").alias("dom_b"))))  # domains squared
    full = grid.join(shared, ["dom_a", "dom_b"], "left").join(own, "dom_a").na.fill(0, ["n_shared"])
    return full.select("dom_a", "dom_b", "n_clusters_a", "n_shared", (100.0 * F.col("n_shared") / F.col("n_clusters_a")).alias("pct"))


def cluster_span(assigned: DataFrame, domain: str = "domain") -> DataFrame:
    return assigned.groupBy("cluster").agg(F.count("*").alias("n"), F.count_distinct(domain).alias("n_domains"), F.array_join(F.array_sort(F.collect_set(domain)), ",").alias("domains"))


def inspect(assigned: DataFrame, n: int = 2, domain: str = "domain", dist: str = "dist") -> DataFrame:
    """The ``n`` members of each (cluster, domain) nearest to the centroid."""
    w = Window.partitionBy("cluster", domain).orderBy(dist, "doc_id")
    return assigned.withColumn("nth", F.row_number().over(w)).filter(F.col("nth") <= n).select("cluster", F.col(domain).alias("domain"), "nth", "doc_id", dist)


def cluster_similarity(assigned: DataFrame, table: DataFrame, members: int | None = None, seed: int = 42) -> DataFrame:
    """(cluster, compactness, mean_pair_cos). The mean over all ordered pairs of distinct members follows from the sum of unit
    vectors, so nothing is paired: (|sum|^2 - n) / (n (n - 1)). ``members`` keeps about so many hashed rows a cluster.
    """
    rows = assigned
    if members is not None:
        sizes = assigned.groupBy("cluster").agg(F.count("*").alias("n_all"))
        rows = assigned.join(F.broadcast(sizes), "cluster").filter(uniform("doc_id", seed) < members / F.col("n_all")).drop("n_all")
    unit = rows.withColumn("_len", F.sqrt(dot(F.col("v"), F.col("v")))).filter("_len > 0").select("cluster", F.posexplode(F.transform("v", lambda x: x / F.col("_len"))).alias("at", "x"))
    sums = unit.groupBy("cluster", "at").agg(F.sum("x").alias("s"), F.count("*").alias("n")).groupBy("cluster").agg(F.sum(F.col("s") * F.col("s")).alias("s2"), F.max("n").alias("n"))
    mean = sums.filter("n > 1").select("cluster", ((F.col("s2") - F.col("n")) / (F.col("n") * (F.col("n") - 1))).alias("mean_pair_cos"))
    return table.select("cluster", "compactness").join(mean, "cluster")


def neighbour_similarity(cents: DataFrame) -> DataFrame:
    """(cluster, nearest, gap, cos): the closest other cluster and how alike the centroids are."""
    from mixwright.functions.vectors import distance

    other = cents.select(F.col("cluster").alias("nearest"), F.col("centroid").alias("far"))
    pairs = cents.join(F.broadcast(other), F.col("cluster") != F.col("nearest")).select(
        "cluster", F.struct(distance(F.col("centroid"), F.col("far")).alias("gap"), "nearest", (1 - distance(F.col("centroid"), F.col("far"), "cosine")).alias("cos")).alias("s")
    )
    return pairs.groupBy("cluster").agg(F.min("s").alias("s")).select("cluster", "s.nearest", "s.gap", "s.cos")


def copy_profile(drawn: DataFrame) -> DataFrame:
    """(copies, n, share, mean_p, and the distinct and copy-weighted mean weights of what is selected)."""
    g = drawn.groupBy("copies").agg(F.count("*").alias("n"), F.avg("p").alias("mean_p"), F.sum("p").alias("sum_p"))
    w = Window.partitionBy(F.lit(1))
    chosen = F.col("copies") > 0
    return g.select(
        "copies", "n", (F.col("n") / F.sum("n").over(w)).alias("share"), "mean_p",
        (F.sum(F.when(chosen, F.col("sum_p"))).over(w) / F.sum(F.when(chosen, F.col("n"))).over(w)).alias("mean_p_selected"),
        (F.sum(F.col("sum_p") * F.col("copies")).over(w) / F.sum(F.col("n") * F.col("copies")).over(w)).alias("mean_p_copies"),
    )
