"""Mixing sources to target weights by Pfair scheduling.

Each source's records are cut into blocks of about ``block_bytes``. With weight w, an exact fraction, block j (from 0) may
not come before floor(j / w) and is due by ceil((j + 1) / w). Earliest deadline first over these windows fills one block
per slot, and at every moment each source has had its weight's share of the slots to within less than one block.

When a source has no block left, the weights of the others are scaled up and their windows start anew from that slot, so every
block gets a slot and none stays empty. The first such phase is the longest mixture at the target weights; its
blocks are ``selected``.

The schedule is simulated on the driver, a heap step a slot. Slots are at most ``most_slots`` and one a source, as blocks grow with the
corpus beyond that; the schedule that is broadcast has as many rows. What else reaches the driver is a row per source.

Block numbers need running sums inside a source. A source may hold a third of all rows, so sums run inside hashed
chunks of about ``chunk_rows`` rows of one source, and the chunk totals are summed in a second, small step. Rows alike in
id, source and size, which need no order among them, share a chunk only up to a hash of their other columns.

Defined results: a null source is a source of its own; a null text has no bytes; repeated and null ids are each
placed; a source without bytes is one block; an empty table gives an empty result; columns of the input pass through, but for those
named like a result, which are replaced; ids may be of any type.
"""

from __future__ import annotations

import heapq
from fractions import Fraction

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .shared import free_names, stored

RESULT = ("block", "slot", "release", "deadline", "selected")


def capped_weights(mass: dict, ceiling: float | Fraction) -> dict:
    """Natural shares as fractions, but none above ``ceiling`` (or an even share, if that is larger); the excess goes to the others in proportion."""
    mass = {k: Fraction(v) for k, v in mass.items() if v > 0}
    limit = max(Fraction(ceiling).limit_denominator(10**9), Fraction(1, len(mass))) if mass else Fraction(1)
    fixed: set = set()
    while True:
        free = sum(v for k, v in mass.items() if k not in fixed)
        left = 1 - limit * len(fixed)
        over = {k for k, v in mass.items() if k not in fixed and free and v * left > limit * free}
        if not over:
            return {k: limit if k in fixed else v * left / free for k, v in mass.items()}
        fixed |= over


def windows(j: int, weight: Fraction) -> tuple[int, int]:
    """Release and deadline of block j."""
    return j * weight.denominator // weight.numerator, -(-(j + 1) * weight.denominator // weight.numerator)


def schedule(blocks: dict, weights: dict) -> list[tuple]:
    """(source, block, slot, release, deadline, phase) of all blocks by earliest deadline first."""
    names = sorted((k for k in blocks if blocks[k]), key=lambda k: (k is not None, str(k)))
    done, out, slot, phase = dict.fromkeys(names, 0), [], 0, 0
    while names:
        total = sum(Fraction(weights[k]) for k in names)
        share = [Fraction(weights[k]) / total for k in names]
        origin, first = slot, [done[k] for k in names]
        later, ready = [(0, windows(0, w)[1], i, 0) for i, w in enumerate(share)], []
        heapq.heapify(later)
        while True:
            while later and later[0][0] <= slot - origin:
                release, due, i, j = heapq.heappop(later)
                heapq.heappush(ready, (due, i, j, release))
            due, i, j, release = heapq.heappop(ready)
            if due <= slot - origin:
                raise AssertionError("a deadline is missed")
            out.append((names[i], first[i] + j, slot, origin + release, origin + due, phase))
            slot += 1
            done[names[i]] += 1
            if done[names[i]] == blocks[names[i]]:
                break
            heapq.heappush(later, (*windows(j + 1, share[i]), i, j + 1))
        names = [k for k in names if done[k] < blocks[k]]
        phase += 1
    return out


def mix(
    df: DataFrame,
    weights: dict | None = None,
    source: str = "source",
    id_col: str = "doc_id",
    size: Column | None = None,
    block_bytes: int = 1 << 16,
    ceiling: float = 0.25,
    chunk_rows: int = 2_048,
    most_slots: int = 1 << 18,
) -> DataFrame:
    """Append block, slot, release, deadline and selected.

    ``selected`` marks the longest mixture that holds the weights without repeating a record; the blocks behind it follow at the weights of
    the sources that are left. Without ``weights`` each source has its natural share up to ``ceiling``. Rows of equal slot
    belong to one block.
    """
    size = F.octet_length("text") if size is None else size
    id_, src, chunk, bytes_, upto, base, at, chunks = free_names(df, "_m_id", "_m_source", "_m_chunk", "_m_size", "_m_upto", "_m_base", "_m_block", "_m_chunks")
    by_source, by_chunk, in_plan, of_block = free_names(df, "_s_source", "_c_source", "_p_source", "_p_block")
    keep = [c for c in df.columns if c.lower() not in RESULT]
    plain = [f.name for f in df.schema if not isinstance(f.dataType, (T.MapType, T.ArrayType, T.StructType, T.VariantType, T.BinaryType)) and f.name != "text"]
    named = df.withColumns({id_: F.xxhash64(F.col(f"`{id_col}`").cast("string"), F.lit("mix")), src: F.col(f"`{source}`").cast("string"), bytes_: F.coalesce(size, F.lit(0)).cast("long"), chunk: F.xxhash64(*[F.col(f"`{c}`") for c in plain])})
    stats = {r[0]: (r[1], r[2]) for r in named.groupBy(src).agg(F.sum(bytes_), F.count("*")).collect()}
    shape = "block long, slot long, release long, deadline long, selected boolean"
    if not stats:
        return named.select(*[F.col(f"`{c}`") for c in keep], *[F.lit(None).cast(f.split()[1]).alias(f.split()[0]) for f in shape.split(", ")])
    mass = {k: max(1, v[0]) for k, v in stats.items()}
    if weights is None:
        target = capped_weights(mass, ceiling)
    else:
        if missing := [k for k in mass if not weights.get(k)]:
            raise ValueError(f"no weight for sources {missing}")
        target = {k: Fraction(weights[k]) for k in mass}
    step = max(block_bytes, -(-sum(mass.values()) // most_slots))
    # A record lies in the block of its first byte; an empty one at a source's end may lie in a block of its own.
    plan = schedule({k: v[0] // step + 1 for k, v in stats.items()}, target)
    spark = df.sparkSession
    plan = spark.createDataFrame([(k, j, s, r, d, p == 0) for k, j, s, r, d, p in plan], f"{in_plan} string, {of_block} long, {shape.split(', ', 1)[1]}")
    facts = spark.createDataFrame([(k, max(1, -(-v[1] // chunk_rows))) for k, v in stats.items()], f"{by_source} string, {chunks} long")
    known = named.join(F.broadcast(facts), F.col(src).eqNullSafe(F.col(by_source))).withColumn(chunk, F.pmod(F.col(chunk), F.col(chunks)))
    before = Window.partitionBy(src, chunk).orderBy(id_, f"`{id_col}`", bytes_).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    other = f"{by_chunk}_at"
    parts = known.groupBy(F.col(src).alias(by_chunk), F.col(chunk).alias(other)).agg(F.sum(bytes_).alias(upto))
    run = Window.partitionBy(by_chunk).orderBy(other).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    parts = parts.select(by_chunk, other, (F.sum(upto).over(run) - F.col(upto)).alias(base))
    placed = (
        known.withColumn(upto, F.sum(bytes_).over(before) - F.col(bytes_))
        .join(parts, F.col(src).eqNullSafe(F.col(by_chunk)) & (F.col(chunk) == F.col(other)))
        .withColumn(at, F.expr(f"(`{base}` + `{upto}`) div {step}"))
        .drop(*[c for c in df.columns if c not in keep])
        .join(F.broadcast(plan), F.col(src).eqNullSafe(F.col(in_plan)) & (F.col(at) == F.col(of_block)))
    )
    return placed.select(*[F.col(f"`{c}`") for c in keep], F.col(at).alias("block"), "slot", "release", "deadline", "selected")


__all__ = ["capped_weights", "mix", "schedule", "stored", "windows"]
