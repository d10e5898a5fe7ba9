"""Sharding by sampled splitters: size-weighted key samples, quantile boundaries, range partitioning.

The key of a record is (hash of the text, hash of the id), so equal texts lie side by side and a hot text, being
spread over its ids, can still be cut. Ranges that come out overfull are subdivided from a denser sample. Exact
byte and row totals of the ranges then place every record at its exact byte offset in key order, and a shard is
a fortieth (say) of all bytes: shard sizes differ by less than the largest record.

Only the sample (ranges x ``oversample`` keys) and one row of totals per range reach the driver; ranges hold about
``range_rows`` records at any corpus size.

Defined results: a null text counts as empty (16 bytes, checksum 0); null and repeated ids are placed like any
others, rows alike in both id and text in one range; an empty table gives an empty result; other columns of the input are ignored; an
id column named like a result or working column is refused.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .shared import id_name, stored

OVERHEAD = 16


def locate(keys: np.ndarray, ties: np.ndarray, key: np.ndarray, tie: np.ndarray) -> np.ndarray:
    """Number of splitters at or below each (key, tie) pair."""
    low, high = np.searchsorted(keys, key, "left"), np.searchsorted(keys, key, "right")
    out = high.copy()
    for at in np.unique(low[low < high]):
        rows = np.flatnonzero((low == at) & (high > at))
        out[rows] = at + np.searchsorted(ties[at : high[rows[0]]], tie[rows], "right")
    return out


def _ranged(narrow: DataFrame, splitters: list[tuple[int, int]]) -> DataFrame:
    keys = np.array([k for k, _ in splitters], dtype=np.int64)
    ties = np.array([t for _, t in splitters], dtype=np.int64)

    @F.pandas_udf("int")
    def place(batches: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.Series]:
        for key, tie in batches:
            yield pd.Series(locate(keys, ties, key.to_numpy(), tie.to_numpy()).astype(np.int32))

    return narrow.withColumn("range", place("key", "tie"))


def _quantiles(sample: list[tuple[int, int]], parts: int) -> list[tuple[int, int]]:
    """At most ``parts - 1`` distinct boundaries that cut a sorted sample evenly."""
    return sorted({sample[len(sample) * i // parts] for i in range(1, parts)}) if sample else []


def shard(df: DataFrame, shards: int = 40, id_col: str = "doc_id", text: str = "text", range_rows: int = 250_000, oversample: int = 32, rounds: int = 3) -> DataFrame:
    """One row per record: id, size, text_crc32, law, shard, slot, grown_shard."""
    id_name(id_col, "size", "text_crc32", "key", "tie", "range", "start", "nth", "law", "shard", "slot", "grown_shard", "rows_before", "bytes_before", "first_nth")
    body = F.encode(F.coalesce(F.col(text), F.lit("")), "UTF-8")
    narrow = stored(
        df.select(F.col(id_col), (F.octet_length(body) + OVERHEAD).cast("long").alias("size"), F.crc32(body).alias("text_crc32"), F.xxhash64(body).alias("key"), F.xxhash64(F.col(id_col).cast("string")).alias("tie")),
        "shard-keys",
    )
    rows, total = narrow.agg(F.count("*"), F.coalesce(F.sum("size"), F.lit(0))).first()
    ranges = max(4 * shards, -(-rows // range_rows))

    def sample(part: DataFrame, wanted: int, mass: int) -> list[tuple[int, int]]:
        chance = F.lit(float(wanted)) * F.col("size") / F.lit(float(max(mass, 1)))
        coin = F.shiftrightunsigned(F.xxhash64("tie", F.lit("splitter")), 11) / F.lit(float(1 << 53))
        return sorted((r[0], r[1]) for r in part.filter(coin < chance).select("key", "tie").collect())

    splitters = _quantiles(sample(narrow, ranges * oversample, total), ranges)
    for _ in range(rounds):
        placed = _ranged(narrow, splitters)
        counts = {r[0]: (r[1], r[2]) for r in placed.groupBy("range").agg(F.count("*"), F.sum("size")).collect()}
        full = {k: -(-b * ranges // max(total, 1)) for k, (_, b) in counts.items() if b * ranges > 2 * total}
        if not full:
            break
        mass = sum(counts[k][1] for k in full)
        inside = sample(placed.filter(F.col("range").isin(list(full))), sum(full.values()) * oversample, mass)
        where = locate(np.array([k for k, _ in splitters], dtype=np.int64), np.array([t for _, t in splitters], dtype=np.int64), np.array([k for k, _ in inside], dtype=np.int64), np.array([t for _, t in inside], dtype=np.int64))
        more = set(splitters)
        for k, parts in full.items():
            more.update(_quantiles([s for s, w in zip(inside, where, strict=True) if w == k], parts))
        if len(more) == len(splitters):
            break
        splitters = sorted(more)
    placed = _ranged(narrow, splitters)
    counts = {r[0]: (r[1], r[2]) for r in placed.groupBy("range").agg(F.count("*"), F.sum("size")).collect()}
    bases, rows_before, bytes_before = [], 0, 0
    for k in sorted(counts):
        bases.append((k, rows_before, bytes_before))
        rows_before, bytes_before = rows_before + counts[k][0], bytes_before + counts[k][1]
    base = df.sparkSession.createDataFrame(bases, "range int, rows_before long, bytes_before long")
    order = Window.partitionBy("range").orderBy("key", "tie", id_col)
    upto = order.rowsBetween(Window.unboundedPreceding, Window.currentRow)
    start = F.col("bytes_before") + F.sum("size").over(upto) - F.col("size")
    # Twice the middle of the record over twice the total, in whole numbers.
    middle = F.expr(f"least({shards - 1}, cast((2 * start + size) * {shards} div {max(2 * total, 1)} as int))")
    cut = stored(
        placed.join(F.broadcast(base), "range")
        .withColumn("start", start)
        .withColumn("nth", F.col("rows_before") + F.row_number().over(order) - 1)
        .select(id_col, "size", "text_crc32", middle.alias("shard"), "nth"),
        "shard-cut",
    )
    first = cut.groupBy("shard").agg(F.min("nth").alias("first_nth"))
    return cut.join(F.broadcast(first), "shard").select(
        id_col, "size", "text_crc32", F.lit("bytes").alias("law"), "shard", (F.col("nth") - F.col("first_nth")).alias("slot"), F.lit(None).cast("int").alias("grown_shard")
    )
