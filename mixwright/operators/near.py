"""Near-duplicates by exact Jaccard similarity of word shingles: no pair at or above the threshold is missed.

A text is the set of its distinct shingle hashes; a text of fewer words than a shingle is one shingle of all its words. Equal
sets are one node, so copies cost one row however many there are. Under one order of all shingles, two sets of similarity t
or more share a shingle among the first n - ceil(t n) + 1 of each, and the first one they share leaves room for the overlap that t
asks for. One pass over the texts ships these leading shingles as compressed arrays, a block per shard of hashes, and
a shard tells which nodes meet. Only in the bucket of the first shingle that two nodes share need they be paired: where both
have the same shingle before it, they met there.

The order puts shingles that are frequent in a sample last, so that a common passage leads no text but those made of such
passages. It changes where nodes meet, not which pairs are found. Buckets of up to ``bucket_rows`` nodes are paired at
once. Larger ones are compared set against sets, in units of two chunks of at most ``chunk_rows`` nodes, so memory is
bounded whatever a bucket holds. Nodes that are known to be connected (``known``) are not compared again.

Every node has a sketch, how many of its shingles fall into each of 128 hash classes. Two sets share at most the sum of the
smaller numbers, which rules out most candidates that have only a passage in common. The others are settled by
the sets themselves (40 bits of each hash, packed), in buckets of bounded size that hold what is near to each other: a second
pass over the asked texts alone makes their sets and sends each to the buckets that ask for it, once.

Defined results: null and blank texts are one empty set, alike only among themselves; null ids never link but keep their
rows; rows that repeat an id are one node of the classes; an empty table gives an empty result; other columns of the input are
ignored; ids must be integers.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from mixwright.functions.blocks import by_shard, changes, mix64, spread, spread_all, squeeze
from mixwright.functions.storage import TEXT_ROWS, kept, lean, lean_cogroup, lean_group, release_memory, small_batches

from .components import components

SEED = 42
ENTRY = ("u8", "u8", "u4", "u4", "u4")  # shingle, node, the shingle before it (hashed, 0: none), size of the set, place
CLASSES = 128
ASK = "unit long, a long, b long, label long, before long, side int"
#: Ids of asked texts that are broadcast, 16 bytes each; beyond it they are joined by a shuffle.
MAX_BROADCAST_ROWS = 2_000_000


def folded(text: str = "text") -> Column:
    """Lower-cased text as bytes."""
    return F.encode(F.lower(F.coalesce(F.col(text), F.lit(""))), "UTF-8")


def shingle_set(body: bytes, width: int) -> np.ndarray:
    """Sorted distinct shingle hashes."""
    words = body.split()
    if not words:
        return np.zeros(0, "u8")
    shingles = [b" ".join(words)] if len(words) < width else map(b" ".join, zip(*(words[i:] for i in range(width)), strict=False))
    digest = xxhash.xxh64_intdigest
    return np.unique(np.array([digest(s, SEED) for s in shingles], "u8"))


def _key(s: np.ndarray) -> bytes:
    return xxhash.xxh3_128_digest(s.tobytes())


def _node(key: bytes) -> int:
    return int.from_bytes(key[:8], "little", signed=True)


def _ceil(x: float) -> int:
    return math.ceil(x - 1e-9)


def _slices(batches: Iterator[pa.RecordBatch], rows: int = 512) -> Iterator[pa.RecordBatch]:
    for whole in batches:
        for i in range(0, whole.num_rows, rows):
            yield whole.slice(i, rows)


def sketch_of(s: np.ndarray) -> bytes:
    """Numbers of shingles by class; of a set too large for bytes, all 255, which rules nothing out."""
    counts = np.bincount((s >> np.uint64(57)).astype(np.int64), minlength=CLASSES)
    return (counts if counts.max() < 255 else np.full(CLASSES, 255)).astype("u1").tobytes()


def may_be_alike(x: np.ndarray, y: np.ndarray, threshold: float) -> np.ndarray:
    """Whether sets with these sketches (rows) can reach the threshold."""
    size = x.sum(axis=-1, dtype=np.int64) + y.sum(axis=-1, dtype=np.int64)
    shared = np.minimum(x, y).sum(axis=-1, dtype=np.int64)
    return (shared >= threshold / (1 + threshold) * size - 1e-9) | (x[..., 0] == 255) | (y[..., 0] == 255)


def frequent(docs: DataFrame, width: int, n: int, sample: int = 10_000, most: int = 100_000) -> tuple[np.ndarray, np.ndarray]:
    """Shingles that at least three texts of a sample have, sorted, and how many have them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for x in b.column(0):
                yield pa.RecordBatch.from_arrays([pa.array(shingle_set(x.as_py(), width).view("i8"))], names=["h"])

    drawn = docs.filter(F.pmod(F.xxhash64("body"), F.lit(max(1, n // sample))) == 0).select("body").distinct()
    with small_batches(docs.sparkSession, TEXT_ROWS):
        rows = drawn.mapInArrow(lean(run), "h long").groupBy("h").agg(F.count("*").alias("n")).filter("n > 2").orderBy(F.desc("n"), "h").limit(most).collect()
    h = np.array([r[0] for r in rows], "i8").view("u8")
    order = np.argsort(h)
    return h[order], np.array([r[1] for r in rows], "i8")[order]


def _scan(docs: DataFrame, width: int, threshold: float, shards: int, common: np.ndarray, times: np.ndarray, mark: Callable[[np.ndarray], int] | None) -> DataFrame:
    """Rows of documents (id, key, node, n, mark, sketch), and blocks of leading shingles by shard."""
    kind = docs.schema["id"].dataType

    def lead(s: np.ndarray) -> np.ndarray:
        rank = np.zeros(len(s), "i8")
        if len(common):
            at = np.minimum(np.searchsorted(common, s), len(common) - 1)
            rank = np.where(common[at] == s, times[at], 0)
        return s[np.argsort(rank, kind="stable")][: len(s) - _ceil(threshold * len(s)) + 1]

    names = ["shard", "id", "key", "node", "n", "mark", "block", "sketch"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, waiting, met = [], 0, set()

        def flush() -> pa.RecordBatch:
            rows = tuple(np.concatenate([h[k] for h in held]).astype(ENTRY[k]) for k in range(5))
            order = np.lexsort((rows[1], rows[0]))
            rows = tuple(r[order] for r in rows)
            out = [(s, squeeze(tuple(r[at] for r in rows))) for s, at in by_shard(mix64(rows[0]) % np.uint64(shards), shards)]
            none = lambda t: pa.nulls(len(out), t)
            return pa.RecordBatch.from_arrays([pa.array([o[0] for o in out], pa.int32()), none(ids.type), none(pa.binary()), none(pa.int64()), none(pa.int64()), none(pa.int64()), pa.array([o[1] for o in out], pa.binary()), none(pa.binary())], names=names)

        for b in _slices(batches):
            ids = b.column(0)
            sets = [shingle_set(x.as_py(), width) for x in b.column(1)]
            keys = [_key(s) for s in sets]
            nodes = [_node(k) for k in keys]
            marks = pa.array([mark(s) for s in sets], pa.int64()) if mark else pa.nulls(len(sets), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array([-1] * len(sets), pa.int32()), ids, pa.array(keys, pa.binary()), pa.array(nodes, pa.int64()), pa.array([len(s) for s in sets], pa.int64()), marks, pa.nulls(len(sets), pa.binary()), pa.array([sketch_of(s) for s in sets], pa.binary())], names=names)
            for s, k, node, there in zip(sets, keys, nodes, ids.is_valid().to_pylist(), strict=True):
                if not there or not len(s) or k in met:
                    continue
                if len(met) < 1_000_000:  # what is sent twice is folded later
                    met.add(k)
                first = lead(s)
                before = np.concatenate([np.zeros(1, "u8"), first[:-1] >> np.uint64(32) | np.uint64(1)]).astype("u4")
                held.append((first, np.full(len(first), node, "i8").view("u8"), before, np.full(len(first), len(s), "u4"), np.arange(len(first), dtype="u4")))
                waiting += len(first)
                if waiting > 400_000:
                    yield flush()
                    held, waiting = [], 0
                    release_memory()
        if held:
            yield flush()

    return docs.mapInArrow(lean(run), f"shard int, id {kind.simpleString()}, key binary, node long, n long, mark long, block binary, sketch binary")


def _meetings(threshold: float, bucket_rows: int):
    """Of one shard's blocks: pairs of nodes that meet in small buckets, and the rows of large ones."""

    def run(table: pa.Table) -> pa.Table:
        rows = spread_all(table.column("block").to_pylist(), ENTRY)
        order = np.lexsort((rows[1], rows[0]))
        rows = tuple(r[order] for r in rows)
        own = changes(rows[:2])
        h, node, before, n, place = (r[own] for r in rows)
        heads = np.flatnonzero(changes((h,)))
        size = np.diff(np.append(heads, len(h)))
        many = np.repeat(size, size)
        a, b = [np.zeros(0, "u8")], [np.zeros(0, "u8")]
        few = np.flatnonzero((many > 1) & (many <= bucket_rows))
        for step in range(1, bucket_rows):
            i = few[few + step < len(h)]
            i = i[h[i] == h[i + step]]
            if not len(i):
                break
            j = i + step
            na, nb = n[i].astype(float), n[j].astype(float)
            room = 1 + np.minimum(na - 1 - place[i], nb - 1 - place[j])
            good = ((before[i] != before[j]) | (before[i] == 0)) & (np.minimum(na, nb) >= threshold * np.maximum(na, nb) - 1e-9) & (room >= threshold / (1 + threshold) * (na + nb) - 1e-9)
            a.append(node[i[good]])
            b.append(node[j[good]])
        a, b = np.concatenate(a).view("i8"), np.concatenate(b).view("i8")
        pairs = np.unique(np.stack([np.minimum(a, b), np.maximum(a, b)]), axis=1) if len(a) else np.zeros((2, 0), "i8")
        # A large bucket whose nodes all come from one bucket before has been looked at there.
        low, high = (f.reduceat(before, heads) if len(heads) else before for f in (np.minimum, np.maximum))
        hot = np.repeat((size > bucket_rows) & ((low != high) | (low == 0)), size)
        k, m = pairs.shape[1], int(hot.sum())
        release_memory()
        column = lambda first, rest, t: pa.array(np.concatenate([first, rest]), t)
        return pa.table({"unit": column(np.zeros(k, "i8"), h[hot].view("i8"), pa.int64()), "a": column(pairs[0], node[hot].view("i8"), pa.int64()), "b": column(pairs[1], np.zeros(m, "i8"), pa.int64()), "before": column(np.zeros(k, "i8"), before[hot].astype("i8"), pa.int64()), "m": column(np.zeros(k, "i8"), many[hot], pa.int64())})

    return run


def compare(sets: list[np.ndarray], threshold: float, every: bool, label: np.ndarray | None = None, before: np.ndarray | None = None, side: np.ndarray | None = None) -> Iterator[tuple[int, int, int]]:
    """(i, j, shared) of all pairs at the threshold, or of enough of them to connect what all would connect.

    Sets of one label are connected; sets with the same non-zero ``before`` have met elsewhere; with sides 0 and 1 only pairs
    across them are asked for.
    """
    size = np.array([len(s) for s in sets])
    starts = np.concatenate([[0], np.cumsum(size)])
    values, codes = np.unique(np.concatenate(sets), return_inverse=True)
    mark, label = np.zeros(len(values), bool), np.arange(len(sets)) if label is None else label.copy()
    for i in range(len(sets) - 1):
        rest = np.arange(i + 1, len(sets))
        small, large = np.minimum(size[rest], size[i]), np.maximum(size[rest], size[i])
        ask = (small >= threshold * large - 1e-9) & (every | (label[rest] != label[i]))
        if before is not None and before[i]:
            ask &= before[rest] != before[i]
        if side is not None:
            ask &= side[rest] != side[i]
        rest = rest[ask]
        if not len(rest):
            continue
        mine = codes[starts[i] : starts[i + 1]]
        mark[mine] = True
        n = size[rest]
        cuts = np.concatenate([[0], np.cumsum(n)[:-1]])
        at = np.repeat(starts[rest] - cuts, n) + np.arange(n.sum())
        shared = np.add.reduceat(mark[codes[at]].astype(np.int64), cuts)
        mark[mine] = False
        good = shared >= threshold * (n + size[i] - shared) - 1e-9
        for j, s in zip(rest[good], shared[good], strict=True):
            if every or label[j] != label[i]:
                label[label == label[j]] = label[i]
                yield i, int(j), int(s)


def _settled(threshold: float, every: bool):
    """Of one bucket: the asked pairs and units that the sets confirm."""

    def run(_: tuple, asks: pa.Table, sets: pa.Table) -> pa.Table:
        held = {node: spread(x.as_py(), ("u8",), -1)[0] for node, x in zip(sets.column("node").to_pylist(), sets.column("hashes"), strict=True)}
        out, boss = [], {}

        def top(x: int) -> int:
            while boss.get(x, x) != x:
                boss[x] = x = boss.get(boss[x], boss[x])
            return x

        rows = [asks.column(c).to_pylist() for c in ("unit", "a", "b", "label", "before", "side")]
        units: dict[int, list[int]] = {}
        for i, (unit, a, b) in enumerate(zip(*rows[:3], strict=True)):
            if unit:
                units.setdefault(unit, []).append(i)
            elif a in held and b in held and (every or top(a) != top(b)):
                x, y = held[a], held[b]
                shared = len(np.intersect1d(x, y, assume_unique=True))
                if shared >= threshold * (len(x) + len(y) - shared) - 1e-9:
                    out.append((a, b, shared))
                    boss[top(a)] = top(b)
        for at in units.values():
            at = [i for i in sorted(at, key=lambda i: (rows[1][i], rows[5][i])) if rows[1][i] in held]
            if len(at) > 1:
                label, before, side = (np.array([rows[k][i] for i in at]) for k in (3, 4, 5))
                for i, j, shared in compare([held[rows[1][i]] for i in at], threshold, every, label, before, side if side.min() >= 0 else None):
                    out.append((rows[1][at[i]], rows[1][at[j]], shared))
        a, b = np.array([o[0] for o in out], "i8"), np.array([o[1] for o in out], "i8")
        release_memory()
        return pa.table([pa.array(np.minimum(a, b), pa.int64()), pa.array(np.maximum(a, b), pa.int64()), pa.array([o[2] for o in out], pa.int64())], names=["a", "b", "shared"])

    return run


def settle(docs: DataFrame, nodes: DataFrame, asks: DataFrame, width: int, threshold: float, every: bool = False) -> DataFrame:
    """(a, b, shared) of the asked pairs and units (``ASK``, with a column ``bucket``) that hold; ``docs`` has id and body."""
    asks = kept(asks, "near-asks")
    need = asks.select("bucket", F.col("a").alias("node")).unionByName(asks.filter("unit = 0").select("bucket", F.col("b").alias("node"))).distinct()
    need = kept(need.join(nodes.select("node", "least"), "node").groupBy(F.col("least").alias("asked")).agg(F.collect_list("bucket").alias("buckets")), "near-needs")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in _slices(batches):
            sets = [shingle_set(x.as_py(), width) for x in b.column(0)]
            rows = [(k, _node(_key(s)), packed) for s, to in zip(sets, b.column(1).to_pylist(), strict=True) if (packed := squeeze((np.unique(s >> np.uint64(24)),), -1)) for k in to]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate((pa.int32(), pa.int64(), pa.binary()))], names=["bucket", "node", "hashes"])

    side = F.broadcast(need) if need.count() <= MAX_BROADCAST_ROWS else need
    sets = docs.join(side, F.col("id") == F.col("asked")).select("body", "buckets").mapInArrow(lean(run), "bucket int, node long, hashes binary")
    found = asks.groupBy("bucket").cogroup(sets.groupBy("bucket")).applyInArrow(lean_cogroup(_settled(threshold, every)), "a long, b long, shared long")
    return kept(found.distinct(), "near-links", TEXT_ROWS)


def plausible_pairs(pairs: DataFrame, nodes: DataFrame, threshold: float) -> DataFrame:
    """The pairs (a, b) that their sketches do not rule out."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x, y = (np.frombuffer(b"".join(b.column(k).to_pylist()), "u1").reshape(-1, CLASSES) for k in (2, 3))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1)], names=["a", "b"]).filter(pa.array(may_be_alike(x, y, threshold)))

    at = lambda x: nodes.select(F.col("node").alias(x), F.col("sketch").alias(f"sketch_{x}"))
    return pairs.join(at("a"), "a").join(at("b"), "b").select("a", "b", "sketch_a", "sketch_b").mapInArrow(lean(run), "a long, b long")


def plausible_units(asks: DataFrame, nodes: DataFrame, threshold: float) -> DataFrame:
    """Of units, the rows that have a partner in their unit which the sketches do not rule out."""

    def run(table: pa.Table) -> pa.Table:
        units = table.column("unit").to_numpy()
        sketches = np.frombuffer(b"".join(table.column("sketch").to_pylist()), "u1").reshape(-1, CLASSES)
        label, before, side = (table.column(c).to_numpy() for c in ("label", "before", "side"))
        order = np.argsort(units, kind="stable")
        heads = np.flatnonzero(changes((units[order],)))
        good = np.zeros(len(units), bool)
        for lo, hi in zip(heads, np.append(heads[1:], len(units)), strict=True):
            at = order[lo:hi]
            for k, i in enumerate(at[:-1]):
                rest = at[k + 1 :]
                rest = rest[(label[rest] != label[i]) & ((before[rest] != before[i]) | (before[i] == 0)) & ((side[rest] != side[i]) | (side[i] < 0))]
                if len(rest):
                    found = rest[may_be_alike(sketches[i][None, :], sketches[rest], threshold)]
                    good[found] = True
                    good[i] |= len(found) > 0
        return table.select(["bucket", "unit", "a", "b", "label", "before", "side"]).filter(pa.array(good))

    with_sketch = asks.join(nodes.select(F.col("node").alias("a"), "sketch"), "a").select("bucket", "unit", "a", "b", "label", "before", "side", "sketch")
    return with_sketch.groupBy("bucket").applyInArrow(lean_group(run), f"bucket int, {ASK}")


def asked_pairs(pairs: DataFrame, bucket_pairs: int = 2_000) -> DataFrame:
    """Rows of ``ASK`` for pairs (a, b), those of one neighbourhood in one bucket, and none above about ``bucket_pairs``."""
    ends = pairs.select(F.col("a").alias("node"), F.col("b").alias("other")).unionByName(pairs.select(F.col("b").alias("node"), F.col("a").alias("other")))
    low = ends.groupBy("node").agg(F.least(F.col("node"), F.min("other")).alias("low"))
    at = lambda x: low.select(F.col("node").alias(x), F.col("low").alias(f"low_{x}"))
    keyed = kept(pairs.join(at("a"), "a").join(at("b"), "b").select("a", "b", F.least("low_a", "low_b").alias("near")), "near-keyed")
    heavy = keyed.groupBy("near").agg(F.count("*").alias("m"))
    buckets = max(1, -(-keyed.count() // bucket_pairs))
    part = F.when(F.col("m") > bucket_pairs, F.pmod(F.xxhash64("b"), F.ceil(F.col("m") / bucket_pairs))).otherwise(F.lit(0))
    zero = F.lit(0).cast("long")
    return keyed.join(heavy, "near").select(F.pmod(F.xxhash64("near", part), F.lit(buckets)).cast("int").alias("bucket"), zero.alias("unit"), "a", "b", zero.alias("label"), zero.alias("before"), F.lit(-1).alias("side"))


def asked_units(hot: DataFrame, chunk_rows: int = 1024, bucket_rows: int = 4096) -> DataFrame:
    """Rows of ``ASK`` for large buckets (unit, node, label, before, m): every two chunks of a bucket are a unit."""
    chunks = F.ceil(F.col("m") / chunk_rows)
    rows = hot.withColumn("chunk", F.pmod(F.xxhash64("node", F.lit("chunk")), chunks)).withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), chunks - 1)))
    unit = F.xxhash64("unit", F.least("chunk", "other"), F.greatest("chunk", "other"))
    side = F.when(F.col("chunk") == F.col("other"), F.lit(-1)).otherwise((F.col("chunk") > F.col("other")).cast("int"))
    rows = kept(rows.select(F.when(unit == 0, F.lit(1)).otherwise(unit).alias("unit"), F.col("node").alias("a"), F.lit(0).cast("long").alias("b"), "label", "before", side.alias("side")), "near-units")
    buckets = max(1, -(-rows.count() // bucket_rows))
    return rows.select(F.pmod(F.xxhash64("unit"), F.lit(buckets)).cast("int").alias("bucket"), *rows.columns)


def gathered_units(asks: DataFrame, bucket_rows: int = 1024) -> DataFrame:
    """The rows of units in new buckets: units that share nodes go together, so that a set is sent to few buckets, and none gets much more than ``bucket_rows``."""
    asks = kept(asks.drop("bucket"), "near-plausible")
    low = asks.groupBy("unit").agg(F.min("a").alias("low"))
    nodes = asks.select("unit", "a").join(low, "unit").groupBy("a").agg(F.min("low").alias("low"))
    near = asks.select("unit", "a").join(nodes, "a").groupBy("unit").agg(F.min("low").alias("near"), F.count("*").alias("m"))
    heavy = near.groupBy("near").agg(F.sum("m").alias("all"))
    buckets = max(1, -(-asks.count() // bucket_rows))
    part = F.when(F.col("all") > 4 * bucket_rows, F.pmod(F.xxhash64("unit"), F.ceil(F.col("all") / bucket_rows))).otherwise(F.lit(0))
    where = near.join(heavy, "near").select("unit", F.pmod(F.xxhash64("near", part), F.lit(buckets)).cast("int").alias("bucket"))
    return asks.join(where, "unit").select("bucket", *asks.columns)


def integer_ids(df: DataFrame, id_col: str) -> None:
    """A clear refusal where a cast would fail row by row."""
    if not isinstance(df.schema[id_col].dataType, T.IntegralType):
        raise TypeError(f"ids must be integers; {id_col} is {df.schema[id_col].dataType.simpleString()}")


class NearSets:
    """Nodes of a corpus and the search for their links.

    ``prints`` has a row per document (id, key, node, n, mark), ``nodes`` one per distinct set with a non-null id (key, node, least,
    n, mark, sketch), least being its smallest id. ``mark`` may compute a long from the sorted shingle hashes on the way.
    """

    def __init__(self, df: DataFrame, id_col: str = "doc_id", body: Column | None = None, width: int = 5, threshold: float = 0.8, mark: Callable[[np.ndarray], int] | None = None, shard_bytes: int = 16 << 20):
        integer_ids(df, id_col)
        self.docs, self.width, self.threshold = df.select(F.col(id_col).alias("id"), (folded() if body is None else body).alias("body")), width, threshold
        n, size = self.docs.agg(F.count("*"), F.coalesce(F.sum(F.octet_length("body")), F.lit(0))).first()
        common, times = frequent(self.docs, width, n)
        self.scanned = kept(_scan(self.docs, width, threshold, max(1, -(-int(size) // shard_bytes)), common, times, mark), "near-scan", TEXT_ROWS)
        self.prints = self.scanned.filter("shard < 0").select("id", "key", "node", "n", "mark", "sketch")
        self.nodes = kept(self.prints.filter("id is not null").groupBy("key").agg(F.first("node").alias("node"), F.min("id").alias("least"), F.first("n").alias("n"), F.first("mark").alias("mark"), F.first("sketch").alias("sketch")), "near-nodes")

    def links(self, every: bool = False, known: DataFrame | None = None, bucket_rows: int = 16, chunk_rows: int = 1024) -> DataFrame:
        """(a, b, shared) of nodes: all pairs at the threshold with ``every``, or enough of them to connect what all would connect,
        beyond the (node, label) that ``known`` has connected."""
        shape = "unit long, a long, b long, before long, m long"
        met = kept(self.scanned.filter("shard >= 0").select("shard", "block").groupBy("shard").applyInArrow(lean_group(_meetings(self.threshold, bucket_rows)), shape), "near-meetings")
        pairs, hot = met.filter("unit = 0 and m = 0").select("a", "b").distinct(), met.filter("m > 0").select("unit", F.col("a").alias("node"), "before", "m")
        if known is None:
            hot = hot.withColumn("label", F.col("node"))
        else:
            at = lambda x: known.select(F.col("node").alias(x), F.col("label").alias(f"label_{x}"))
            pairs = pairs.join(at("a"), "a", "left").join(at("b"), "b", "left").filter(F.coalesce("label_a", "a") != F.coalesce("label_b", "b")).select("a", "b")
            hot = kept(hot.join(known, "node", "left").withColumn("label", F.coalesce("label", "node")), "near-hot")
            mixed = hot.groupBy("unit").agg(F.min("label").alias("x"), F.max("label").alias("y")).filter("x <> y").select("unit")
            hot = hot.join(mixed, "unit", "left_semi")
        pairs = kept(plausible_pairs(pairs, self.nodes, self.threshold), "near-pairs")
        found = settle(self.docs, self.nodes, asked_pairs(pairs), self.width, self.threshold, every)
        if hot.isEmpty():
            return found
        units = gathered_units(plausible_units(asked_units(hot, chunk_rows), self.nodes, self.threshold))
        return found.unionByName(settle(self.docs, self.nodes, units, self.width, self.threshold, every)).distinct()

    def classes(self, links: DataFrame) -> DataFrame:
        """(id, component): for each row the smallest id that links reach, its own included; null ids have none."""
        least = lambda x: self.nodes.select(F.col("node").alias(x), F.col("least").cast("long").alias(f"{x}_id"))
        edges = links.select("a", "b").join(least("a"), "a").join(least("b"), "b").select(F.col("a_id").alias("a"), F.col("b_id").alias("b"))
        # Rows that share an id but not a set are one node too.
        same = self.prints.groupBy("id").agg(F.min("key").alias("x"), F.max("key").alias("y")).filter("x <> y").select("id")
        twice = self.prints.join(same, "id").join(self.nodes.select("key", "least"), "key").select(F.col("id").cast("long").alias("a"), F.col("least").cast("long").alias("b"))
        found = components(edges.unionByName(twice))
        named = self.nodes.select("key", "least").join(found, F.col("least") == F.col("node"), "left").select("key", F.coalesce("component", F.col("least").cast("long")).alias("component"))
        return self.prints.select("id", "key").join(named, "key", "left").select("id", F.when(F.col("id").isNotNull(), F.col("component")).alias("component"))
