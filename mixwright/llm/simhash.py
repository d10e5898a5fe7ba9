"""SimHash near-duplicates by covering locality-sensitive hashing.

A text's fingerprint has a bit set where over half of its shingle hashes have it. To find all fingerprints within
``radius`` bits, every bit position gets a non-zero vector of ``radius + 1`` bits, and for each non-zero v one table
keeps the positions whose vector has odd overlap with v. Any ``radius`` differing positions leave some v orthogonal
to all of their vectors, and in that table the pair collides: 2^(radius+1) - 1 tables, no misses.

Masks repeat one vector pattern over all 64 positions, so a table keeps 32 to 37 of them.

Equal fingerprints are folded into one row first, so copies cost one row however many there are. In tables of the fold, a
bucket of up to ``bucket_rows`` fingerprints is compared pair by pair inside one equi-join, whose condition lets
only links out. The fingerprints of larger buckets are not paired: each names all points within half the radius, in any
of the 64 positions; those that share a point are within the radius of each other for an even radius, and
a star around the smallest links them.
Links are joined into components by alternating large-star and small-star rounds on ids, each stored in the shared
folder; nothing but counts reaches the driver.

``near_texts`` finds near copies by the similarity of their shingle sets. Fingerprints group the sets, and each set of a group is
checked exactly against the group's first. At a similarity of 0.8 fingerprints differ in 4 to 14 of 64 bits, beyond what
covering tables can reach, so an exact join of leading shingles (``mixwright.operators.near``) adds the links between sets that
the groups have not connected.

Defined results: a null, empty or blank text has fingerprint zero, linked like any other (in ``near_texts``, an empty set, alike only to
its like); null ids never link but keep their rows; rows that repeat an id are one node; an empty table gives an empty result; other
columns of the input are ignored; ids must be integers.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from mixwright.functions.storage import TEXT_ROWS
from mixwright.operators.components import components
from mixwright.operators.near import NearSets, asked_pairs, integer_ids, settle

from .shared import free_names, id_name, lean, sized, stored

BITS = 64
SEED = 42


def fingerprint(text: bytes, width: int = 3) -> int:
    words = text.lower().split()
    if not words:
        return 0
    if len(words) < width:
        shingles = [b" ".join(words)]
    else:
        shingles = map(b" ".join, zip(*(words[i:] for i in range(width)), strict=False))
    digest = xxhash.xxh64_intdigest
    return majority(np.array([digest(s, SEED) for s in shingles], dtype="<u8"))


def majority(hashes: np.ndarray) -> int:
    """The fingerprint of shingle hashes: bits set in over half of them."""
    ones = np.zeros(BITS, dtype=np.int64)
    for at in range(0, len(hashes), 1 << 16):
        bits = np.unpackbits(hashes[at : at + (1 << 16)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        ones += bits.sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(hashes), bitorder="little").view("<u8")[0])


def fingerprints(df: DataFrame, id_col: str = "doc_id", text: str = "text", width: int = 3) -> DataFrame:
    """(id, fp): the fingerprint as a signed long."""
    kind = df.schema[id_col].dataType

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            got = [fingerprint(t, width) for t in (x.as_py() for x in batch.column(1))]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.array(got, dtype="u8").view("i8"))], names=[id_col, "fp"])

    narrow = df.select(F.col(id_col), F.encode(F.coalesce(F.col(text), F.lit("")), "UTF-8").alias("text"))
    return narrow.mapInArrow(lean(run), f"`{id_col}` {kind.simpleString()}, fp long")


def masks(radius: int) -> list[int]:
    """The structured masks, as signed longs."""
    n = (1 << (radius + 1)) - 1
    out = []
    for v in range(1, n + 1):
        m = sum(1 << i for i in range(BITS) if bin((i % n + 1) & v).count("1") % 2)
        out.append(m - (1 << BITS) if m >> (BITS - 1) else m)
    return out


def _signed(x: int) -> int:
    return x - (1 << BITS) if x >> (BITS - 1) & 1 else x


def _star_links(hot: DataFrame, radius: int) -> DataFrame:
    """Links of the fingerprints in large buckets, linear in their number: stars around shared points."""

    def balls(depth: int) -> DataFrame:
        points = hot.select("fp", F.col("fp").alias("point"), F.lit(0).alias("next"))
        flips = F.array(*[F.lit(_signed(1 << i)) for i in range(BITS)])
        out = points
        for _ in range(depth):
            points = points.select("fp", "point", F.posexplode(F.slice(flips, F.col("next") + 1, BITS)).alias("step", "flip"), "next")
            points = points.select("fp", F.col("point").bitwiseXOR(F.col("flip")).alias("point"), (F.col("next") + F.col("step") + 1).alias("next"))
            out = out.unionByName(points)
        return out.select("fp", "point")

    near = balls(radius // 2)
    hubs = near.groupBy("point").agg(F.min("fp").alias("hub"))
    # An odd radius splits unevenly: the larger balls meet at the hub of the smaller ones.
    stars = (balls(radius // 2 + 1) if radius % 2 else near).join(hubs, "point").select(F.col("hub").alias("a"), F.col("fp").alias("b"))
    return stars.filter("a <> b").distinct()


def links(nodes: DataFrame, radius: int = 2, bucket_rows: int = 64) -> DataFrame:
    """(a, b) of distinct fingerprints: enough links within ``radius`` to connect whatever all of them would connect."""
    tables = F.array(*[F.struct(F.lit(i).alias("table"), F.lit(m).alias("mask")) for i, m in enumerate(masks(radius))])
    keyed = nodes.select("fp", F.explode(tables).alias("t")).select("fp", F.col("t.table").alias("table"), F.col("fp").bitwiseAND(F.col("t.mask")).alias("key"))
    sizes = keyed.groupBy("table", "key").agg(F.count("*").alias("n")).filter("n > 1")
    busy = stored(keyed.join(sizes, ["table", "key"]), "simhash-buckets")
    small = busy.filter(F.col("n") <= bucket_rows).select("table", "key", "fp")
    other = small.withColumnRenamed("fp", "fp2")
    near = F.bit_count(F.col("fp").bitwiseXOR(F.col("fp2"))) <= radius
    pairs = small.join(other, (small["table"] == other["table"]) & (small["key"] == other["key"]) & (F.col("fp") < F.col("fp2")) & near)
    hot = busy.filter(F.col("n") > bucket_rows).select("fp").distinct()
    return pairs.select(F.col("fp").alias("a"), F.col("fp2").alias("b")).distinct().unionByName(_star_links(hot, radius))


def near_groups(df: DataFrame, id_col: str = "doc_id", text: str = "text", width: int = 3, radius: int = 2, bucket_rows: int = 64) -> DataFrame:
    """(id, fp, component): the smallest id reachable over links, its own included."""
    integer_ids(df, id_col)
    id_name(id_col, "fp", "component")
    df, id_given, id_col = df.select(F.col(f"`{id_col}`").alias("id"), F.col(f"`{text}`").alias("text")), id_col, "id"
    prints = stored(fingerprints(df, id_col, "text", width), "simhash-prints", TEXT_ROWS)
    nodes = stored(prints.groupBy("fp").agg(F.min(id_col).cast("long").alias("least")), "simhash-nodes")
    found = links(nodes, radius, bucket_rows)
    at = lambda side: nodes.select(F.col("fp").alias(side), F.col("least").alias(f"{side}_id"))
    edges = found.join(at("a"), "a").join(at("b"), "b").select(F.col("a_id").alias("a"), F.col("b_id").alias("b"))
    # Rows that share an id but not a fingerprint are one node too.
    same = prints.groupBy(id_col).agg(F.min("fp").alias("x"), F.max("fp").alias("y"), F.count("*").alias("n")).filter((F.col("n") > 1) & (F.col("x") != F.col("y"))).select(id_col)
    twice = prints.join(same, id_col).join(nodes, "fp").select(F.col(id_col).cast("long").alias("a"), F.col("least").alias("b"))
    found = components(edges.unionByName(twice).filter("a is not null and b is not null"))
    named = nodes.join(found, F.col("least") == F.col("node"), "left").select("fp", F.coalesce("component", "least").alias("component"))
    return prints.join(named, "fp").select(F.col(id_col).alias(id_given), F.col("fp").alias("fp"), F.when(F.col(id_col).isNotNull(), F.col("component")).alias("component"))


def hex_digits(fp: Column) -> Column:
    return F.lower(F.lpad(F.hex(fp), 16, "0"))


def near_texts(df: DataFrame, id_col: str = "doc_id", body: Column | None = None, width: int = 5, threshold: float = 0.8, radius: int = 2, bucket_rows: int = 64) -> DataFrame:
    """(id, component): the smallest id reachable over links of shingle sets with a Jaccard similarity of ``threshold`` or more."""
    near = NearSets(df, id_col, body, width, threshold, mark=lambda s: _signed(majority(s)))
    found = components(links(near.nodes.select(F.col("mark").alias("fp")).distinct(), radius, bucket_rows))
    grouped = near.nodes.select("node", "mark").join(found.select(F.col("node").alias("mark"), "component"), "mark", "left").select("node", F.coalesce("component", "mark").alias("group"))
    grouped = stored(grouped, "simhash-groups")
    hubs = grouped.groupBy("group").agg(F.min("node").alias("hub"), F.max("node").alias("last")).filter("hub < last").select("group", "hub")
    asked = grouped.join(hubs, "group").filter("node <> hub").select(F.col("hub").alias("a"), F.col("node").alias("b"))
    first = settle(near.docs, near.nodes, asked_pairs(stored(asked, "simhash-asked")), width, threshold)
    known = first.select(F.col("b").alias("node"), F.col("a").alias("label")).unionByName(first.select(F.col("a").alias("node"), F.col("a").alias("label"))).distinct()
    return near.classes(first.unionByName(near.links(known=known)))


def keep_one(df: DataFrame, id_col: str = "doc_id", found: DataFrame | None = None, **options) -> DataFrame:
    """One row of each group (of ``near_groups``, or of a given (id, component)), that of the smallest id; rows without an id stay."""
    (drop,) = free_names(df, "_s_drop")
    groups = near_groups(df, id_col, **options).select(F.col(f"`{id_col}`").alias("id"), "component") if found is None else found
    gone = groups.filter(F.col("id") != F.col("component")).select(F.col("id").alias(drop)).distinct()
    return df.join(sized(stored(gone, "simhash-gone")), F.col(f"`{id_col}`") == F.col(drop), "left_anti")
