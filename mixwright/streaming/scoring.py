"""Streams: scoring with frozen parameters, windows over arrivals, late rows, duplicates, budgets, merged cells."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout


def read_files(spark: SparkSession, path: str, schema: str, files_per_batch: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(path)


def score_stream(model, stream: DataFrame, share: float = 1.0) -> DataFrame:
    """The model's batch transform, on a stream: map only but for a broadcast of the clusters."""
    return model.transform(stream, share)


def event_time(events: DataFrame) -> DataFrame:
    """Watermarks need a timestamp with a time zone; sessions run in UTC."""
    return events.withColumn("ts", F.col("ts").cast("timestamp"))


def tumbling(events: DataFrame, width: str = "1 hour", late: str | None = None) -> DataFrame:
    e = events.withWatermark("ts", late) if late else events
    return e.groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("total")).select(F.col("w.start").alias("start"), "event_type", "n", "total")


def sliding(events: DataFrame, width: str = "2 hours", step: str = "1 hour", late: str | None = None) -> DataFrame:
    e = events.withWatermark("ts", late) if late else events
    return e.groupBy(F.window("ts", width, step).alias("w"), "event_type").agg(F.count("*").alias("n"), F.avg("value").alias("mean")).select(F.col("w.start").alias("start"), "event_type", "n", "mean")


def sessions(events: DataFrame, gap: str = "10 minutes", late: str | None = None) -> DataFrame:
    e = events.withWatermark("ts", late) if late else events
    return e.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def dedup(stream: DataFrame, keys: list[str], late: str = "1 hour") -> DataFrame:
    """First arrivals within the watermark; state is bounded by it."""
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(keys)


def join_cells(stream: DataFrame, solved: DataFrame, keys: list[str]) -> DataFrame:
    """Stream against a static table of cell frequencies."""
    return stream.join(F.broadcast(solved), keys)


def join_grades(docs: DataFrame, grades: DataFrame, late: str = "1 hour") -> DataFrame:
    """Documents with grades that arrive at most ``late`` after them."""
    d = docs.withWatermark("ts", late).alias("d")
    g = grades.withWatermark("graded_at", late).alias("g")
    return d.join(g, F.expr(f"d.doc_id = g.doc_id AND g.graded_at BETWEEN d.ts AND d.ts + INTERVAL {late}"))


def within_budget(stream: DataFrame, budget: int, parts: int = 1) -> DataFrame:
    """Rows of each domain until its tokens are spent; the state is a counter per domain and part.

    A domain's documents are dealt by hash to ``parts``, each with its part of the budget, so that a large domain is no single task.
    """
    share = [budget // parts + (k < budget % parts) for k in range(parts)]

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        spent = state.get[0] if state.exists else 0
        for pdf in batches:
            pdf = pdf.sort_values("doc_id")
            upto = spent + pdf["n_tokens"].cumsum()
            kept = pdf[upto <= share[key[1]]]
            spent += int(kept["n_tokens"].sum())
            yield kept.assign(domain=key[0])[["domain", "doc_id", "n_tokens"]]
        state.update((spent,))

    dealt = stream.select("domain", "doc_id", "n_tokens", F.pmod(F.xxhash64("doc_id"), F.lit(parts)).cast("int").alias("part"))
    return dealt.groupBy("domain", "part").applyInPandasWithState(step, "domain string, doc_id long, n_tokens long", "spent long", "append", GroupStateTimeout.NoTimeout)


def merge_cells(stream: DataFrame, path: str, checkpoint: str, keys: tuple[str, ...] = ("domain", "cluster", "quality")):
    """Cells are additive: each micro-batch adds one partial table, keyed by its number, so a replay overwrites itself."""

    def add(batch: DataFrame, number: int) -> None:
        part = batch.groupBy(*keys).agg(F.min("diversity").alias("diversity"), F.count("*").alias("n"), F.sum("n_tokens").cast("long").alias("tokens"))
        part.write.mode("overwrite").parquet(f"{path}/batch={number}")

    return stream.writeStream.foreachBatch(add).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def merged_cells(spark: SparkSession, path: str, keys: tuple[str, ...] = ("domain", "cluster", "quality")) -> DataFrame:
    return spark.read.parquet(path).groupBy(*keys).agg(F.min("diversity").alias("diversity"), F.sum("n").alias("n"), F.sum("tokens").alias("tokens"))


def run_to(stream: DataFrame, path: str, checkpoint: str, mode: str = "append") -> None:
    """Everything there is, once, to Parquet; a restart from the checkpoint writes nothing twice."""
    stream.writeStream.format("parquet").outputMode(mode).option("path", path).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
