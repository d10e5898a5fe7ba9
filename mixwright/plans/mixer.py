"""The per-document mixer as an estimator with a model of frozen scalars."""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass

from pyspark.ml import Estimator, Model
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from mixwright.functions.storage import kept
from mixwright.operators import cells, cluster, diversity, sampling


@dataclass
class PerDocumentMixer:
    """``fit`` takes (doc_id, domain, n_tokens, quality) and either a ``cluster`` column or a vector ``v``."""

    alpha: float = sampling.ALPHA
    tau: float = sampling.TAU
    k: int | None = None
    metric: str = "euclidean"
    separation: str = "mean"
    singleton: str = "literal"
    engine: str = "mllib"
    seed: int = sampling.SEED
    fit_fraction: float = 1.0

    def fit(self, docs: DataFrame, vectors: DataFrame | None = None) -> PerDocumentMixerModel:
        """``vectors`` may hold more documents than are scored; clusters are measured over all of it."""
        sampling.check(self.alpha, self.tau)
        vecs = vectors if vectors is not None else docs
        if "cluster" not in vecs.columns:
            k = self.k or cluster.default_k(vecs.count())
            cents = cluster.fit_kmeans(vecs.select("doc_id", "v"), k, self.seed, engine=self.engine, fit_fraction=self.fit_fraction)
            vecs = kept(cluster.assign(vecs.select("doc_id", "v"), cents).drop("dist"), "mixer-assigned")
        cents = kept(diversity.centroids(vecs), "mixer-centroids")
        table = kept(diversity.cluster_table(vecs, self.metric, self.separation, singleton=self.singleton, alone=1.0), "mixer-clusters")
        docs = docs if "cluster" in docs.columns else docs.join(vecs.select("doc_id", "cluster"), "doc_id")
        # All that the softmax needs is in the cells: a row per cluster and level.
        parts = kept(cells.build(diversity.score(docs, table), ("cluster", "quality")), "mixer-cells")
        ends = parts.agg(*[f(c).cast("double").alias(f"{n}_{c}") for c in ("quality", "diversity") for n, f in (("low", F.min), ("high", F.max))], F.coalesce(F.sum("n"), F.lit(0)).alias("n"), F.sum("tokens").cast("double").alias("tokens")).first()
        clusters = [(r["cluster"], r["diversity"], [float(x) for x in r["centroid"]]) for r in table.join(cents, "cluster").collect()]  # K rows
        model = PerDocumentMixerModel(self.alpha, self.tau, self.seed, ends["low_quality"], ends["high_quality"], ends["low_diversity"], ends["high_diversity"], ends["n"], ends["tokens"] or 0.0, 0.0, 1.0, clusters)
        weighed = model.weigh(parts)
        top = weighed.agg(F.max("p")).first()[0] or 0.0
        model.top, model.z = top, weighed.agg(F.sum(F.col("n") * F.exp((F.col("p") - F.lit(top)) / self.tau))).first()[0] or 1.0
        return model


@dataclass
class PerDocumentMixerModel:
    alpha: float
    tau: float
    seed: int
    low_quality: float
    high_quality: float
    low_diversity: float
    high_diversity: float
    n: int
    tokens: float
    top: float
    z: float
    clusters: list

    def weigh(self, df: DataFrame) -> DataFrame:
        """Append p, from frozen ranges; map only."""

        def scaled(name: str, low: float, high: float):
            return (F.col(name) - low) / (high - low) if low is not None and high > low else F.lit(0.0)

        d, q = scaled("diversity", self.low_diversity, self.high_diversity), scaled("quality", self.low_quality, self.high_quality)
        return df.withColumn("p", F.lit(self.alpha) * d + F.lit(1 - self.alpha) * q)

    def transform(self, docs: DataFrame, share: float = 1.0) -> DataFrame:
        """Append cluster (from ``v`` where missing), diversity, p, c and copies; works on batches and on streams."""
        spark = docs.sparkSession
        table = spark.createDataFrame([tuple(c) for c in self.clusters], "cluster int, diversity double, centroid array<double>")
        if "cluster" not in docs.columns:
            docs = cluster.nearest(docs, table.select("cluster", "centroid"))
        scored = docs.join(F.broadcast(table.select("cluster", "diversity")), "cluster")
        weighed = self.weigh(scored)
        c = F.lit(self.n * share / self.z) * F.exp((F.col("p") - F.lit(self.top)) / self.tau)
        return sampling.copies(weighed.withColumn("c", c), self.seed)

    def sample(self, docs: DataFrame, share: float = 1.0) -> DataFrame:
        return sampling.manifest(self.transform(docs, share))

    def save(self, spark: SparkSession, path: str) -> None:
        """One row of JSON, wherever Spark can write."""
        spark.createDataFrame([(json.dumps(asdict(self)),)], "value string").coalesce(1).write.text(path)

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> PerDocumentMixerModel:
        return cls(**json.loads(spark.read.text(path, wholetext=True).first()[0]))


class MixerEstimator(Estimator):
    """The mixer as a stage of a Pipeline: rows of doc_id, domain, n_tokens, quality and ``v`` (or cluster)."""

    def __init__(self, share: float = 1.0, **options):
        super().__init__()
        self.share, self.options = share, options

    def _fit(self, dataset: DataFrame) -> MixerTransformer:
        return MixerTransformer(PerDocumentMixer(**self.options).fit(dataset), self.share)


class MixerTransformer(Model):
    def __init__(self, model: PerDocumentMixerModel, share: float):
        super().__init__()
        self.model, self.share = model, share

    def _transform(self, dataset: DataFrame) -> DataFrame:
        return self.model.transform(dataset, self.share)


def register_sql(spark: SparkSession) -> None:
    """SQL functions for the method's formulas, usable in any query text."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION mix_weight(d DOUBLE, q DOUBLE, alpha DOUBLE) RETURNS DOUBLE RETURN alpha * d + (1 - alpha) * q")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION mix_copies(c DOUBLE, u DOUBLE) RETURNS INT RETURN int(floor(round(c, 9)) + CASE WHEN u < round(c, 9) - floor(round(c, 9)) THEN 1 ELSE 0 END)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION mix_draw(id BIGINT, seed INT) RETURNS DOUBLE RETURN double(conv(substring(md5(concat(seed, ':', id)), 1, 13), 16, 10)) / 4503599627370496D")
