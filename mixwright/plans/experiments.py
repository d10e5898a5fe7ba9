"""The experiments: all mixers side by side, curves, budgets, evaluators, streams."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mixwright.functions.hashing import uniform
from mixwright.functions.storage import TEXT_ROWS, kept, scratch
from mixwright.operators import analysis, baselines, cluster, corpus, diversity, domains, embed, metrics, ngram, quality, sampling
from mixwright.sources.tables import load
from mixwright.streaming import scoring

from . import oracles as sql
from .mixer import PerDocumentMixer
from .queries import given_vectors, lang_corpus, query, scored

SHARE = 0.2
CLUSTERS = 20
START = 1_600_000_000  # seconds; a watermark begins at zero


def union(parts: list[DataFrame]) -> DataFrame:
    return reduce(lambda a, b: a.unionByName(b), parts)


def text_scored(docs: DataFrame, k: int = CLUSTERS) -> DataFrame:
    """Rubric quality and diversity of hashed text vectors, for every document, blank ones included."""
    v = kept(embed.hashed(docs), "text-vectors")
    assigned = kept(cluster.assign(v, cluster.fit_kmeans(v, k)).select("doc_id", "cluster", "v"), "text-clusters")
    graded = quality.grade(docs).select("doc_id", "domain", "n_tokens", "quality")
    return kept(diversity.score(graded.join(assigned.select("doc_id", "cluster"), "doc_id"), diversity.cluster_table(assigned)), "text-scored")


def manifests(spark, docs: DataFrame, share: float = SHARE, methods: tuple[str, ...] | None = None, seed: int = 42) -> DataFrame:
    """(method, doc_id, domain, n_tokens, copies) of every mixer on one corpus."""
    weights = baselines.all_weights(spark, docs, methods=methods)
    narrow = docs.select("doc_id", "domain", "n_tokens")
    parts = [domains.sample(narrow, w, share, seed=seed).select(F.lit(m).alias("method"), "doc_id", "domain", "n_tokens", "copies") for m, w in weights.items()]
    pdm = sampling.copies(sampling.score_frequencies(text_scored(docs), share=share), seed)
    parts.append(pdm.select(F.lit("per_document").alias("method"), "doc_id", "domain", "n_tokens", "copies"))
    return kept(union(parts).filter("copies > 0"), "manifests")


def results(docs: DataFrame, man: DataFrame, bench: DataFrame, chat: DataFrame, order: int = 2, vocab: int = ngram.VOCAB) -> DataFrame:
    """(method, metric, value, higher, place): tokens drawn, two perplexities, two accuracies and their mean, of a model of each method's manifest."""
    endings = kept(ngram.choices(bench, "item_id"), "endings")
    model = ngram.SideBySide(docs, man, {"bench": bench, "chat": chat, "endings": endings}, order, vocab)
    scored = model.scored()
    parts = [man.groupBy("method").agg(F.sum(F.col("copies") * F.col("n_tokens")).cast("double").alias("value")).select("method", F.lit("tokens").alias("metric"), "value", F.lit(True).alias("higher"))]
    for name, texts in (("validation_ppl", "bench"), ("instruction_ppl", "chat")):
        parts.append(model.perplexities(scored, texts).select("method", F.lit(name).alias("metric"), F.col("perplexity").alias("value"), F.lit(False).alias("higher")))
    accuracies = ngram.with_mean(ngram.last_word_accuracy(model.last_words(bench), bench, "item_id"), model.choice_accuracy(scored, endings, "endings"), ["method"])
    parts.append(accuracies.select("method", "metric", "value", F.lit(True).alias("higher")))
    return metrics.leaderboard(union(parts))


def lang_clean(spark, sf) -> DataFrame:
    """Decontaminated documents with the codes of their words, which are hashed once."""
    d = load(spark, sf, "documents").select("doc_id", "text", F.col("lang").alias("domain"))
    d = kept(ngram.coded(d), "coded-documents", TEXT_ROWS).withColumn("n_tokens", F.size("codes").cast("long"))
    return corpus.decontaminate(d, load(spark, sf, "benchmark"))


def chat_of(spark, sf) -> DataFrame:
    return load(spark, sf, "conversations").select("conv_id", "text")


def weight_table(name):
    def run(spark, sf):
        docs = lang_corpus(spark, sf)
        return baselines.all_weights(spark, docs, methods=(name,))[name]

    return run


for _name in ("minimax", "bivariate", "generalisation", "mixing_law"):
    query(f"w_{_name}")(weight_table(_name))


@query("weights_side_by_side")
def _(spark, sf):
    docs = lang_corpus(spark, sf)
    parts = [w.select(F.lit(m).alias("method"), "domain", "weight") for m, w in baselines.all_weights(spark, docs).items()]
    drawn = sampling.copies(sampling.score_frequencies(text_scored(docs), share=SHARE))
    return union([*parts, analysis.domain_mix(drawn).select(F.lit("per_document").alias("method"), "domain", F.col("target_share").alias("weight"))])


@query("main_table")
def _(spark, sf):
    docs = lang_clean(spark, sf)
    return results(docs, manifests(spark, docs), load(spark, sf, "benchmark"), chat_of(spark, sf))


@query("larger_model_table")
def _(spark, sf):
    docs = lang_clean(spark, sf)
    man = manifests(spark, docs, methods=("natural", "minimax", "cond_entropy"))
    return results(docs, man, load(spark, sf, "benchmark"), chat_of(spark, sf), order=3, vocab=1 << 16)


@query("small_source_table")
def _(spark, sf):
    """The source cut to a fifth, so that the budget is all of it."""
    docs = kept(corpus.fraction(lang_clean(spark, sf), 0.2, 9), "small-source")
    return results(docs, manifests(spark, docs, share=1.0), load(spark, sf, "benchmark"), chat_of(spark, sf))


def curves(spark, sf) -> DataFrame:
    """(method, step, metric) at ten checkpoints of a hash-ordered manifest; counts are additive, so a checkpoint's model sums what has come in by then."""
    docs = lang_clean(spark, sf)
    man = manifests(spark, docs)
    rows = man.select("method", "doc_id", F.explode(F.sequence(F.lit(1), F.col("copies"))).alias("copy"))
    first = F.floor(uniform(F.concat_ws("/", F.col("doc_id").cast("string"), F.col("copy").cast("string"))) * 10).cast("int") + 1
    arrivals = rows.groupBy("method", "doc_id", first.alias("step")).agg(F.count("*").alias("copies"))
    bench = load(spark, sf, "benchmark")
    model = ngram.fit_asked(docs, arrivals, bench, 10, by=("method",))
    return kept(ngram.perplexity(ngram.score(model, bench, "item_id"), ("method", "step")).select("method", "step", F.col("perplexity").alias("metric")), "curve")


@query("steps_to_target")
def _(spark, sf):
    """The first checkpoint at which each method reaches the mean of all six baselines at their last one."""
    curve = curves(spark, sf)
    target = curve.filter("method <> 'per_document' and step = 10").agg(F.avg("metric").alias("target"))
    return metrics.steps_to_target(curve, target, higher_is_better=False)


@query("speed_up")
def _(spark, sf):
    """Against each baseline: the checkpoint at which the per-document mixer reaches its final value, and how many times fewer steps that is."""
    curve = curves(spark, sf)
    own = curve.filter("method = 'per_document'").select("step", "metric")
    goals = curve.filter("method <> 'per_document' and step = 10").select(F.col("method").alias("baseline"), F.col("metric").alias("target"))
    mean = goals.agg(F.lit("mean of all").alias("baseline"), F.avg("target").alias("target"))
    met = goals.unionByName(mean).join(F.broadcast(own), F.col("metric") <= F.col("target"), "left").groupBy("baseline", "target").agg(F.min("step").alias("steps"))
    return met.select("baseline", "target", "steps", (10 / F.col("steps")).alias("times_fewer"))


@query("alpha_perplexity")
def _(spark, sf):
    """The alpha grid on rubric quality and text clusters, one model per alpha in one pass: perplexity, accuracies and their mean."""
    docs = lang_clean(spark, sf)
    s = text_scored(docs)
    man = kept(union([sampling.copies(sampling.score_frequencies(s, a, share=SHARE)).select(F.lit(a).alias("alpha"), "doc_id", "copies") for a in (0.0, 0.2, 0.4, 0.6, 0.8, 1.0)]).filter("copies > 0"), "alpha-manifests")
    model = ngram.fit(docs, man, by=("alpha",))
    bench = load(spark, sf, "benchmark")
    ppl = ngram.perplexity(ngram.score(model, bench, "item_id"), ("alpha",)).select("alpha", F.lit("validation_ppl").alias("metric"), F.col("perplexity").alias("value"))
    return ppl.unionByName(ngram.accuracies(model, bench, "item_id"))


@query("ordinal_vs_classifier")
def _(spark, sf):
    docs = load(spark, sf, "documents")
    graded = quality.grade(docs.select("doc_id", "text")).select("doc_id", "text", "quality")
    rows = kept(quality.text_features(graded, embed.hashed(docs)).select("doc_id", "features", "quality"), "features")
    train, test = quality.graded_split(rows, 1.0, 0.2)
    scored_by = {
        "ordinal": quality.OrdinalEvaluator().fit(train).score(test),
        "ordinal_tied": quality.OrdinalEvaluator(tied=True).fit(train).score(test),
        "classifier": quality.ClassifierEvaluator().fit(train).score(test),
    }
    return union([metrics.ordinal(d.select("quality", "predicted")).select(F.lit(m).alias("model"), "n", "acc", "mae", "mse", "cacc") for m, d in scored_by.items()])


@query("label_evaluator")
def _(spark, sf):
    """Held-out accuracy on external quality and toxicity labels."""
    docs = load(spark, sf, "documents").join(load(spark, sf, "labels"), "doc_id")
    rows = kept(quality.text_features(docs, embed.hashed(docs)).select("doc_id", "features", "quality", "toxic"), "features")
    train, test = quality.graded_split(rows, 1.0, 0.3)
    out = []
    for label in ("quality", "toxic"):
        got = quality.BinaryEvaluator(label).fit(train).score(test)
        out.append(got.agg(F.lit(label).alias("label"), F.count("*").alias("n"), F.avg(((F.col("chance") > 0.5).cast("int") == F.col(label)).cast("double")).alias("accuracy"), F.avg(F.col(label).cast("double")).alias("base_rate")))
    return union(out)


@query("mixer_model")
def _(spark, sf):
    """The estimator on given vectors with its own clusters."""
    docs = scored(spark, sf).select("doc_id", "domain", "n_tokens", "quality")
    vecs = given_vectors(spark, sf).drop("cluster")
    model = PerDocumentMixer(k=8).fit(docs, vecs)
    return model.transform(docs.join(vecs, "doc_id"), SHARE).select("doc_id", "cluster", "p", "c", "copies")


@query("stream_equals_batch")
def _(spark, sf):
    """Scores of a file stream against those of a batch, row by row."""
    docs = scored(spark, sf).select("doc_id", "domain", "n_tokens", "quality").join(given_vectors(spark, sf).drop("cluster"), "doc_id")
    source, sink = scratch(spark, "stream-in"), scratch(spark, "stream-out")
    docs.repartition(3).write.parquet(source)
    model = PerDocumentMixer(k=8).fit(docs)
    stream = scoring.read_files(spark, source, "doc_id long, domain string, n_tokens long, quality int, v array<double>")
    scoring.run_to(scoring.score_stream(model, stream, SHARE).select("doc_id", "copies"), sink, scratch(spark, "stream-state"))
    batch = model.transform(spark.read.parquet(source), SHARE).select("doc_id", F.col("copies").alias("batch_copies"))
    both = spark.read.parquet(sink).join(batch, "doc_id", "full")
    return both.agg(F.count("*").alias("n"), F.count_if(F.col("copies").eqNullSafe(F.col("batch_copies"))).alias("n_equal"))


@query("stream_budget")
def _(spark, sf):
    """Tokens let through per domain by the stateful budget controller."""
    source, sink = scratch(spark, "budget-in"), scratch(spark, "budget-out")
    lang_corpus(spark, sf).select("domain", "doc_id", "n_tokens").repartition(4).write.parquet(source)
    stream = scoring.read_files(spark, source, "domain string, doc_id long, n_tokens long")
    scoring.run_to(scoring.within_budget(stream, 20_000, 4), sink, scratch(spark, "budget-state"))
    return spark.read.parquet(sink).groupBy("domain").agg(F.sum("n_tokens").cast("long").alias("n_tokens"), (F.sum("n_tokens") <= 20_000).alias("within"))


@query("stream_cells")
def _(spark, sf):
    """Cells merged batch by batch against a rebuild."""
    from mixwright.operators import cells

    s = scored(spark, sf).select("doc_id", "domain", "cluster", "quality", "diversity", "n_tokens")
    source, table = scratch(spark, "cells-in"), scratch(spark, "cells-out")
    s.repartition(3).write.parquet(source)
    stream = scoring.read_files(spark, source, "doc_id long, domain string, cluster int, quality int, diversity double, n_tokens long")
    scoring.merge_cells(stream, table, scratch(spark, "cells-state")).awaitTermination()
    keys = ["domain", "cluster", "quality"]
    a = scoring.merged_cells(spark, table).select(*keys, "n", "tokens")
    b = cells.build(s).select(*keys, F.col("n").alias("n_batch"), F.col("tokens").alias("tokens_batch"))
    return a.join(b, keys, "full").agg(F.count("*").alias("n_cells"), F.count_if((F.col("n") == F.col("n_batch")) & (F.col("tokens") == F.col("tokens_batch"))).alias("n_equal"))


@query("stream_windows", "SELECT epoch(b)::BIGINT AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM (SELECT time_bucket(INTERVAL 1 HOUR, ts) AS b, event_type, value FROM events) WHERE b + INTERVAL 1 HOUR <= (SELECT max(ts) FROM events) - INTERVAL 30 MINUTE GROUP BY ALL")
def _(spark, sf):
    """Hourly windows of an event stream under a watermark: what is final when the stream's events are read."""
    e = scoring.event_time(load(spark, sf, "events")).select("ts", "event_type", "value")
    source, sink = scratch(spark, "windows-in"), scratch(spark, "windows-out")
    e.repartitionByRange(4, "ts").sortWithinPartitions("ts").write.parquet(source)
    scoring.run_to(scoring.tumbling(scoring.read_files(spark, source, "ts timestamp, event_type string, value double", 100), late="30 minutes"), sink, scratch(spark, "windows-state"))
    return spark.read.parquet(sink).select(F.unix_seconds("start").alias("start"), "event_type", "n", F.round("total", 4).alias("total"))


@query("stream_dedup", "SELECT event_type, count(*) AS n, count(DISTINCT event_id) AS n_ids FROM events GROUP BY event_type")
def _(spark, sf):
    """A stream in which every event comes twice, less its second arrivals."""
    e = scoring.event_time(load(spark, sf, "events")).select("event_id", "ts", "event_type")
    source, sink = scratch(spark, "dedup-in"), scratch(spark, "dedup-out")
    e.unionByName(e).repartition(4, "event_id").write.parquet(source)
    scoring.run_to(scoring.dedup(scoring.read_files(spark, source, "event_id long, ts timestamp, event_type string", 100), ["event_id"]), sink, scratch(spark, "dedup-state"))
    return spark.read.parquet(sink).groupBy("event_type").agg(F.count("*").alias("n"), F.count_distinct("event_id").alias("n_ids"))


@query("stream_static_join", f"{sql.mixer_cte()} SELECT domain, count(*) AS n, round(sum(c), 5) AS total FROM drawn GROUP BY domain")
def _(spark, sf):
    """A stream of documents against the static table of cell frequencies."""
    from mixwright.operators import cells

    rows = kept(scored(spark, sf).select("doc_id", "domain", "cluster", "quality", "diversity", "n_tokens"), "static-rows")
    solved = cells.solve(cells.build(rows), share=1.0).select("domain", "cluster", "quality", "c")
    source, sink = scratch(spark, "static-in"), scratch(spark, "static-out")
    rows.drop("diversity").repartition(3).write.parquet(source)
    stream = scoring.read_files(spark, source, "doc_id long, domain string, cluster int, quality int, n_tokens long")
    scoring.run_to(scoring.join_cells(stream, solved, ["domain", "cluster", "quality"]).select("doc_id", "domain", "c"), sink, scratch(spark, "static-state"))
    return spark.read.parquet(sink).groupBy("domain").agg(F.count("*").alias("n"), F.round(F.sum("c"), 5).alias("total"))


@query("stream_stream_join", f"SELECT l.doc_id, l.quality::INT AS quality FROM documents d JOIN labels l USING (doc_id) WHERE {sql.draw(seed=33)} * 7200 <= 3600")
def _(spark, sf):
    """Documents with the grades that arrive within an hour of them; later ones find no document."""
    at = F.timestamp_seconds(F.col("doc_id") + START)
    docs = load(spark, sf, "documents").select("doc_id", at.alias("ts"))
    late = (uniform("doc_id", 33) * 7_200_000_000).cast("long")
    grades = load(spark, sf, "labels").select("doc_id", F.timestamp_micros((F.col("doc_id") + START) * 1_000_000 + late).alias("graded_at"), "quality")
    left, right, sink = scratch(spark, "docs-in"), scratch(spark, "grades-in"), scratch(spark, "joined-out")
    docs.repartition(2).write.parquet(left)
    grades.repartition(2).write.parquet(right)
    d, g = scoring.read_files(spark, left, "doc_id long, ts timestamp", 100), scoring.read_files(spark, right, "doc_id long, graded_at timestamp, quality int", 100)
    scoring.run_to(scoring.join_grades(d, g).select(F.col("d.doc_id").alias("doc_id"), "quality"), sink, scratch(spark, "joined-state"))
    return spark.read.parquet(sink)
