"""Rubric grades, the graded split, and evaluators: ordinal, plain classifier, binary, pairwise."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.ml.classification import LogisticRegression
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from mixwright.functions.hashing import uniform
from mixwright.functions.storage import scratch
from mixwright.functions.text import words

# The rubric's dimensions and the greatest score of each.
DIMENSIONS = {"clarity": 1, "completeness": 1, "structure": 1, "credibility": 1, "significance": 1, "knowledge": 2, "depth": 2}
LEVELS = 11
SUSPECT = r"https?://|www\.|@|\d{3}[-. ]\d{3,4}|click here|buy now|free money|subscribe"


def rubric_total(df: DataFrame, dims: dict[str, int] | None = None, out: str = "quality") -> DataFrame:
    """Sum of the dimension scores; a score out of its range fails the query."""
    dims = dims or DIMENSIONS
    total = F.lit(0)
    for name, top in dims.items():
        fine = F.col(name).between(0, top)
        total = total + F.when(fine, F.col(name)).otherwise(F.raise_error(F.concat(F.lit(f"{name} out of 0..{top}: "), F.coalesce(F.col(name).cast("string"), F.lit("null")))).cast("int"))
    return df.withColumn(out, total.cast("int"))


def heuristic_rubric(docs: DataFrame, text: str = "text") -> DataFrame:
    """Append the seven dimensions from text statistics; a stand-in for a grading model."""
    t, lines = F.col("_r_text"), F.col("_r_lines")
    base = docs.withColumn("_r_text", F.coalesce(F.col(text), F.lit("")))
    base = base.withColumn("_r_lines", F.filter(F.split(t, "\n"), lambda x: x.rlike(r"\S")))
    n = F.size("codes") if "codes" in docs.columns and text == "text" else F.size(words(t))  # stored codes are one a word
    stops = F.length(t) - F.length(F.regexp_replace(t, "[.!?]", ""))
    base = base.withColumn("_r_n", n).withColumn("_r_stops", stops)
    n, stops = F.col("_r_n"), F.col("_r_stops")
    plain = F.length(F.regexp_replace(t, r"[^\p{L}\s]", ""))
    bit = lambda c: c.cast("int")
    dims = {
        "clarity": bit((F.length(t) > 0) & (plain >= 0.93 * F.length(t))),
        "completeness": bit(t.rlike(r"[.!?]\s*$") & (n >= 50)),
        "structure": bit((stops > 0) & (n >= 3 * stops) & (n <= 40 * stops)),
        "credibility": bit(~F.lower(t).rlike(SUSPECT)),
        "significance": bit(n >= 100),
        "knowledge": bit(n >= 150) + bit(n >= 400),
        "depth": bit((F.size(lines) > 0) & (10 * F.size(F.array_distinct(lines)) >= 9 * F.size(lines))) + bit(stops >= 20),
    }
    return base.withColumns(dims).drop("_r_text", "_r_lines", "_r_n", "_r_stops")


def grade(docs: DataFrame, grader: Callable[[DataFrame], DataFrame] | None = None, text: str = "text") -> DataFrame:
    """Append the dimensions and ``quality``; ``grader`` may wrap a real model as a pandas function."""
    return rubric_total(grader(docs) if grader else heuristic_rubric(docs, text))


def graded_split(docs: DataFrame, share: float = 1.0, test_fraction: float = 0.024, seed: int = 42, id_col: str = "doc_id") -> tuple[DataFrame, DataFrame]:
    """Uniform draw by hashed ids, and a test part of it: the same rows under any partitioning."""
    drawn = docs.filter(uniform(id_col, seed) < share)
    coin = uniform(id_col, seed + 1)
    return drawn.filter(coin >= test_fraction), drawn.filter(coin < test_fraction)


def encode(level: Column, levels: int = LEVELS) -> Column:
    """Is the level above k, for k = 0 .. levels - 2."""
    return F.transform(F.sequence(F.lit(0), F.lit(levels - 2)), lambda k: (level > k).cast("double"))


def monotone(exceed: Column) -> Column:
    """Running minimum, so that exceeding more is never likelier than exceeding less."""
    empty = F.array().cast("array<double>")
    return F.aggregate(exceed, empty, lambda acc, x: F.concat(acc, F.array(F.when(F.size(acc) == 0, x).otherwise(F.least(x, F.element_at(acc, -1))))))


def level_probabilities(exceed: Column) -> Column:
    """P(level k) = P(above k - 1) - P(above k)."""
    return F.zip_with(F.concat(F.array(F.lit(1.0)), exceed), F.concat(exceed, F.array(F.lit(0.0))), lambda a, b: a - b)


def decode(exceed: Column, how: str = "difference") -> Column:
    """Level from exceedances: likeliest level, count above one half, or the expectation (a real number)."""
    if how == "difference":
        p = level_probabilities(exceed)
        return (F.array_position(p, F.array_max(p)) - 1).cast("int")
    if how == "count":
        return F.size(F.filter(exceed, lambda s: s > 0.5)).cast("int")
    if how == "expected":
        return F.aggregate(exceed, F.lit(0.0), lambda a, s: a + s)
    raise ValueError(f"unknown decoder {how!r}")


def text_features(docs: DataFrame, vectors: DataFrame | None = None, text: str = "text") -> DataFrame:
    """(…, features): text statistics, and a hashed text vector where ``vectors`` (doc_id, v) has one."""
    t = F.col("_f_text")
    base = docs.withColumn("_f_text", F.coalesce(F.col(text), F.lit(""))).withColumn("_f_words", words(t)).withColumn("_f_lines", F.split(t, "\n"))
    n, chars = F.size("_f_words"), F.length(t)
    per = lambda a, b: F.when(b > 0, a / b).otherwise(F.lit(0.0))
    stats = F.array(
        F.log1p(n.cast("double")),
        per(F.length(F.regexp_replace(t, r"\s+", "")), n).cast("double"),
        per(F.size(F.array_distinct("_f_words")), n),
        per(F.length(F.regexp_replace(t, r"[\p{L}\s]", "")), chars),
        1.0 - per(F.size(F.array_distinct("_f_lines")), F.size("_f_lines")),
        F.log1p((chars - F.length(F.regexp_replace(t, "[.!?]", ""))).cast("double")),
    )
    out = base.withColumn("_f_stats", stats)
    if vectors is not None:
        out = out.join(vectors.select("doc_id", F.col("v").alias("_f_v")), "doc_id", "left").withColumn("_f_stats", F.concat("_f_stats", F.coalesce("_f_v", F.array_repeat(F.lit(0.0), 64))))
    return out.withColumn("features", array_to_vector("_f_stats")).drop("_f_text", "_f_words", "_f_lines", "_f_stats", "_f_v")


@dataclass
class OrdinalEvaluator:
    """One binary decider per threshold, or one tied decider with a bias for each threshold."""

    levels: int = LEVELS
    tied: bool = False
    how: str = "difference"
    repair: bool = False
    iterations: int = 20
    reg: float = 1e-3
    models: list = field(default_factory=list)

    def _tied(self, df: DataFrame) -> DataFrame:
        k = F.col("k")
        hot = F.transform(F.sequence(F.lit(0), F.lit(self.levels - 2)), lambda i: (i == k).cast("double"))
        return df.withColumn("k", F.explode(F.sequence(F.lit(0), F.lit(self.levels - 2)))).withColumn("x", array_to_vector(F.concat(vector_to_array("features"), hot)))

    def fit(self, train: DataFrame, level: str = "quality") -> OrdinalEvaluator:
        """Training rows need ``features`` and a level."""
        train = train.select("features", F.col(level).alias("level"))
        solver = LogisticRegression(maxIter=self.iterations, regParam=self.reg, labelCol="y")
        if self.tied:
            rows = self._tied(train).withColumn("y", (F.col("level") > F.col("k")).cast("double"))
            self.models = [solver.setFeaturesCol("x").fit(rows)]
            return self
        seen = [r[0] for r in train.select("level").distinct().orderBy("level").collect()]  # at most one row per level
        self.models = []
        for k in range(self.levels - 1):
            if not seen or min(seen) > k or max(seen) <= k:  # all training rows lie on one side
                self.models.append(float(bool(seen) and min(seen) > k))
            else:
                self.models.append(solver.fit(train.withColumn("y", (F.col("level") > k).cast("double"))))
        return self

    def score(self, docs: DataFrame, out: str = "predicted") -> DataFrame:
        """Append ``p_gt`` and the decoded level; weights are literals, so there is no shuffle and no Python."""
        if self.tied:
            w, bias, n = self.models[0].coefficients.toArray(), float(self.models[0].intercept), self.levels - 1
            base, own = F.array(*[F.lit(float(x)) for x in w[:-n]]), F.array(*[F.lit(float(x)) for x in w[-n:]])
            z = F.aggregate(F.zip_with(vector_to_array("features"), base, lambda a, b: a * b), F.lit(bias), lambda a, x: a + x)
            got = docs.withColumn("_z", z).withColumn("p_gt", F.transform(own, lambda b: 1 / (1 + F.exp(-(F.col("_z") + b))))).drop("_z")
        else:
            parts = []
            x = vector_to_array("features")
            for m in self.models:
                if isinstance(m, float):
                    parts.append(F.lit(m))
                else:
                    w = F.array(*[F.lit(float(v)) for v in m.coefficients.toArray()])
                    parts.append(1 / (1 + F.exp(-F.aggregate(F.zip_with(F.col("_x"), w, lambda a, b: a * b), F.lit(float(m.intercept)), lambda a, v: a + v))))
            got = docs.withColumn("_x", x).withColumn("p_gt", F.array(*parts)).drop("_x")
        p = monotone(F.col("p_gt")) if self.repair else F.col("p_gt")
        return got.withColumn("p_gt", p).withColumn(out, decode(F.col("p_gt"), self.how))


@dataclass
class ClassifierEvaluator:
    """Plain classification over all levels, on the same features."""

    iterations: int = 20
    reg: float = 1e-3
    model: object = None

    def fit(self, train: DataFrame, level: str = "quality") -> ClassifierEvaluator:
        self.model = LogisticRegression(maxIter=self.iterations, regParam=self.reg, family="multinomial", labelCol="y").fit(train.select("features", F.col(level).cast("double").alias("y")))
        return self

    def score(self, docs: DataFrame, out: str = "predicted") -> DataFrame:
        return self.model.transform(docs).withColumn(out, F.col("prediction").cast("int")).drop("prediction", "rawPrediction", "probability")


@dataclass
class BinaryEvaluator:
    """Learns a 0/1 label, such as an external quality or toxicity mark."""

    label: str = "quality"
    iterations: int = 20
    reg: float = 1e-3
    model: object = None

    def fit(self, train: DataFrame) -> BinaryEvaluator:
        self.model = LogisticRegression(maxIter=self.iterations, regParam=self.reg, labelCol="y").fit(train.select("features", F.col(self.label).cast("double").alias("y")))
        return self

    def score(self, docs: DataFrame, out: str = "chance") -> DataFrame:
        return self.model.transform(docs).withColumn(out, F.get(vector_to_array("probability"), F.lit(1))).drop("prediction", "rawPrediction", "probability")


def pairwise_scores(pairs: DataFrame, iterations: int = 20) -> DataFrame:
    """(criterion, item, strength) from (criterion, winner, loser): Bradley-Terry strengths by minorisation, mean 1.

    Each round is a join and an aggregate; half a virtual win and loss against strength 1 keeps strengths finite.
    """
    games = pairs.select("criterion", F.least("winner", "loser").alias("a"), F.greatest("winner", "loser").alias("b")).groupBy("criterion", "a", "b").agg(F.count("*").alias("n"))
    both = games.unionByName(games.select("criterion", F.col("b").alias("a"), F.col("a").alias("b"), "n"))
    wins = pairs.groupBy("criterion", F.col("winner").alias("item")).agg(F.count("*").alias("wins"))
    items = both.select("criterion", F.col("a").alias("item")).distinct().join(wins, ["criterion", "item"], "left").na.fill(0, ["wins"])
    strength = items.withColumn("strength", F.lit(1.0))
    for _ in range(iterations):
        own, other = strength.select("criterion", F.col("item").alias("a"), F.col("strength").alias("s_a")), strength.select("criterion", F.col("item").alias("b"), F.col("strength").alias("s_b"))
        rate = both.join(own, ["criterion", "a"]).join(other, ["criterion", "b"]).groupBy("criterion", F.col("a").alias("item")).agg(F.sum(F.col("n") / (F.col("s_a") + F.col("s_b"))).alias("rate"), F.first("s_a").alias("s_own"))
        new = items.join(rate, ["criterion", "item"]).select("criterion", "item", "wins", ((F.col("wins") + 0.5) / (F.col("rate") + 1 / (F.col("s_own") + 1))).alias("raw"))
        mean = new.groupBy("criterion").agg(F.avg("raw").alias("mean"))
        strength = new.join(F.broadcast(mean), "criterion").select("criterion", "item", "wins", (F.col("raw") / F.col("mean")).alias("strength"))
        # The strengths enter the next round twice: without a written table the plan would double each time.
        path = scratch(strength.sparkSession, "pairwise")
        strength.write.parquet(path)
        strength = strength.sparkSession.read.schema(strength.schema).parquet(path)
    return strength.select("criterion", "item", "strength")
