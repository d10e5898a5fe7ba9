"""Interpolated modified Kneser-Ney model: counted in Spark, kept as sorted hash arrays, memory-mapped by workers.

A token is a 64-bit hash; inside n-grams it is known by 40 bits of it. Each map task counts its n-grams under dense codes and ships
them as compressed arrays, one row per shard, each with the short hashes of its own words; the whole hashes go
with the tokens' counts alone. N-grams are dealt by the token before the last, so one merge gives a shard
the counts of every order below too: of a gram, how many tokens stand before it; of a context, its total and how
many of its grams occur once, twice and more. Frequent contexts are spread: n-grams of a frequent token are dealt
by the token before it as well, and those of a frequent pair by their last token; what that leaves in parts is added up
in a second step, as is what n-grams tell of their words. N-grams and contexts that occur once, most of them, are kept as bare
hashes. Discounts come from the counts of counts, a few numbers.

Scoring tasks map the arrays (``hash_arrays``) from the shared folder and look up the distinct n-grams of a batch of texts in order.

The model of order n is p(w | c) = max(count(c w) - D, 0) / count(c) + gamma(c) p(w | c without its first token), D by count 1, 2,
3 and more; counts are occurrences at order n and numbers of distinct tokens before below; it rests on 1 / (V + 1)
for each of V known tokens and one unknown. A text has n - 1 start marks before it and one end behind it.

Sizes: shards are as many as the input's bytes ask for, so that one holds about ``shard_bytes`` of text's n-grams. Which
contexts are spread is read off a sample that grows with the number of shards, so that none holds much more than a shard's
part; it changes where n-grams are counted, not any count. Counts have 64 bits.

Defined results: a null text counts as empty and is scored by its end token; a null id is as the text of no characters
when choosing training rows; ids may be of any type; rows that repeat are counted and scored each; an empty table gives an empty
result; other columns of the input are ignored. Scores of a model without training text rest on the unknown token alone.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from mixwright.functions.blocks import by_shard, changes, mix64, rolling_sums, spread, squeeze, stretch_hash

from . import hash_arrays
from .shared import dropped, folder, lean, lean_group, release_memory, stored

END = np.uint64(0x9E3779B97F4A7C15)
START = np.uint64(0xC2B2AE3D27D4EB4F)
SPACES = np.zeros(256, bool)
SPACES[[32, 9, 10, 11, 12, 13]] = True
FLUSH_TOKENS = 1_200_000
WORD = ("u8",) * 6  # short hash; tokens before it; as a context: total, grams seen once, twice, more


def pair_hash(left: np.ndarray, right: np.ndarray) -> np.ndarray:
    return mix64(mix64(left) * np.uint64(3) + right)


def short(words: np.ndarray) -> np.ndarray:
    """40 bits of token hashes."""
    return words >> np.uint64(24)


def tokenise(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Token hashes of all texts one after another, an end token behind each, and the number of tokens of each."""
    raw = np.frombuffer(b"\n".join(texts) + b"\n", np.uint8)
    raw = np.where((raw >= 65) & (raw <= 90), raw + 32, raw).astype(np.uint8)
    gap = SPACES[raw]
    before = np.concatenate([[True], gap[:-1]])
    starts, stops = np.flatnonzero(~gap & before), np.flatnonzero(gap & ~before)
    hashes = stretch_hash(rolling_sums(raw), starts, stops)
    upto = np.searchsorted(starts, np.cumsum([len(t) + 1 for t in texts]))
    return np.insert(hashes, upto, END), np.diff(np.concatenate([[0], upto])) + 1


def _chunks(texts: list[bytes], limit: int = 2 << 20) -> Iterator[tuple[int, int]]:
    at = size = 0
    for i, t in enumerate(texts):
        if size and size + len(t) > limit:
            yield at, i
            at, size = i, 0
        size += len(t)
    if at < len(texts):
        yield at, len(texts)


def coded(tokens: np.ndarray, n: np.ndarray, order: int) -> tuple[np.ndarray, list[np.ndarray]]:
    """Distinct hashes, and columns of codes for each token's n-gram: the token before, those before that, last the token itself."""
    words, code = np.unique(np.append(tokens, START), return_inverse=True)
    start, code = code[-1], code[:-1].astype(np.uint32)
    first = np.concatenate([[0], np.cumsum(n)[:-1]]).astype(np.int64) if len(n) else np.zeros(0, np.int64)
    columns, last = [], code
    for _ in range(order - 1):
        last = np.concatenate([last[:1], last[:-1]])
        last[first] = start
        columns.append(last)
    return words, [*columns, code]


def _packed(columns: list[np.ndarray], k: int) -> tuple[np.ndarray, list[np.ndarray] | None]:
    """Rows of codes below k as single numbers of the same order, and, where 63 bits do not hold them, the distinct rows."""
    bits = max(1, int(k - 1).bit_length())
    if bits * len(columns) <= 63:
        key = columns[0].astype(np.uint64)
        for c in columns[1:]:
            key = key << np.uint64(bits) | c.astype(np.uint64)
        return key, None
    order = np.lexsort(columns[::-1])
    rows = [c[order] for c in columns]
    own = changes(tuple(rows))
    key = np.empty(len(order), np.uint64)
    key[order] = np.cumsum(own) - 1
    return key, [r[own] for r in rows]


def grouped(columns: list[np.ndarray], k: int, counts: np.ndarray | None = None) -> tuple[list[np.ndarray], np.ndarray]:
    """Distinct rows of codes in order, and how many there are of each or the sums of their counts."""
    if not len(columns[0]):
        return columns, np.zeros(0, np.uint64)
    key, rows = _packed(columns, k)
    if counts is None:
        key = np.sort(key)
    else:
        order = np.argsort(key)
        key, counts = key[order], counts[order]
    at = np.flatnonzero(changes((key,)))
    sums = np.diff(np.append(at, len(key))).astype(np.uint64) if counts is None else np.add.reduceat(counts, at).astype(np.uint64)
    if rows is None:
        bits = max(1, int(k - 1).bit_length())
        rows = [(key[at] >> np.uint64(bits * j) & np.uint64((1 << bits) - 1)).astype(np.uint32) for j in range(len(columns) - 1, -1, -1)]
    return rows, sums


def _block(words: np.ndarray, columns: list[np.ndarray], counts: np.ndarray) -> bytes:
    """A compressed block of sorted rows of codes, with the short hashes, sorted like the codes, of the words that occur in it."""
    used = np.zeros(len(words), bool)
    for c in columns:
        used[c] = True
    code = np.cumsum(used) - 1
    kind = "u2" if code[-1] < 1 << 16 else "u4"
    head = squeeze((words[used],), -1)
    body = squeeze((*(code[c].astype(kind) for c in columns), counts.astype("u8")), -1, 3)
    return bytes([int(kind[1])]) + len(head).to_bytes(4, "little") + head + body


def _words_of(blob: bytes) -> np.ndarray:
    """The words of a block."""
    return spread(blob[5 : 5 + int.from_bytes(blob[1:5], "little")], ("u8",), -1)[0]


def _unblock(blob: bytes, order: int) -> tuple[np.ndarray, list[np.ndarray], np.ndarray]:
    *columns, counts = spread(blob[5 + int.from_bytes(blob[1:5], "little") :], (f"u{blob[0]}",) * order + ("u8",), -1)
    return _words_of(blob), columns, counts


@dataclass(frozen=True)
class Model:
    """Where the arrays are, and the numbers that discounts and the lowest order need."""

    path: str
    order: int
    shards: int
    word_shards: int
    tokens: int
    vocabulary: int
    pair_types: int
    word_types: tuple[int, int, int]  # words with 1, 2, 3 and more distinct tokens before them
    discounts: tuple  # by order, from words up
    hot: np.ndarray  # tokens whose n-grams are dealt by the token before as well
    hot_pairs: np.ndarray  # pairs whose n-grams are dealt by their last token as well


def discounts(t1: int, t2: int, t3: int, t4: int) -> tuple[float, float, float]:
    """Discounts for counts 1, 2, 3+ from the counts of counts, kept within what a count can give."""
    y = t1 / (t1 + 2 * t2) if t1 + 2 * t2 else 0.5
    raw = [k - (k + 1) * y * b / a if a else k * y for k, a, b in ((1, t1, t2), (2, t2, t3), (3, t3, t4))]
    return tuple(min(max(x, 0.05), k - 0.05) for k, x in zip((1, 2, 3), raw, strict=True))


def _among(values: np.ndarray, some: np.ndarray) -> np.ndarray:
    """Which values are in a sorted array."""
    if not len(some):
        return np.zeros(len(values), bool)
    return some[np.minimum(np.searchsorted(some, values), len(some) - 1)] == values


def _in_steps(make: Callable, columns: list[np.ndarray], step: int = 1 << 17) -> tuple[np.ndarray, ...]:
    """``make`` of the columns' rows, a step after another, so that what it makes on its way stays small."""
    parts = [make([c[i : i + step] for c in columns]) for i in range(0, max(1, len(columns[0])), step)]
    return tuple(np.concatenate(column) for column in zip(*parts, strict=True))


def places(words: np.ndarray, columns: list[np.ndarray], hot: np.ndarray, hot_pairs: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Where n-grams are dealt (a hash), and which of them are of a hot token, of a hot pair."""
    return _in_steps(lambda part: _places(words, part, hot, hot_pairs), columns)


def _places(words: np.ndarray, columns: list[np.ndarray], hot: np.ndarray, hot_pairs: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    at = words[columns[0]]
    is_hot = _among(words, hot)[columns[0]]
    paired = pair_hash(at, words[columns[1]])
    if len(columns) > 2:
        is_pair = is_hot & _among(paired, hot_pairs)
        return np.where(is_pair, pair_hash(paired, words[columns[-1]]), np.where(is_hot, paired, at)), is_hot, is_pair
    return np.where(is_hot, paired, at), is_hot, np.zeros(len(at), bool)


def _hashes(words: np.ndarray, columns: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of contexts and of whole n-grams."""
    return _in_steps(lambda part: _hashed(words, part), columns)


def _whole(words: np.ndarray, columns: list[np.ndarray]) -> np.ndarray:
    """Hashes of whole n-grams."""
    return _in_steps(lambda part: _hashed(words, part)[1:], columns)[0]


def _hashed(words: np.ndarray, columns: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    context = words[columns[0]]
    for c in columns[1:-1]:
        context = pair_hash(context, words[c])
    return context, pair_hash(context, words[columns[-1]])


def _array(keys: np.ndarray, *columns: np.ndarray) -> bytes:
    if not columns:
        return hash_arrays.pack(np.sort(keys), [])
    order = np.argsort(keys)
    return hash_arrays.pack(keys[order], [c[order] for c in columns])


def _once(label: str, keys: np.ndarray, *columns: np.ndarray) -> dict[str, bytes]:
    """Two arrays: what occurs once as bare hashes, the others with their numbers."""
    one = columns[0] == 1
    return {label: _array(keys[~one], *(c[~one] for c in columns)), f"{label} once": _array(keys[one])}


def _merged(words: np.ndarray, parts: Iterable[tuple], width: int) -> tuple[list[np.ndarray], np.ndarray]:
    """Distinct n-grams of blocks, opened one after another, under codes of ``words``, and the sums of their counts."""
    k = len(words)
    bits = max(1, int(k - 1).bit_length())
    keys, counts, columns = [], [], []
    for own, codes, n in parts:
        code = np.searchsorted(words, own).astype(np.uint32)
        if bits * width <= 63:
            keys.append(_packed([code[c] for c in codes], k)[0])
        else:
            columns.append([code[c] for c in codes])
        counts.append(n.astype(np.uint32) if len(n) and n.max() < 1 << 32 else n)
    counts = [np.concatenate(counts)]
    if columns:
        return grouped([np.concatenate([c[i] for c in columns]) for i in range(width)], k, counts[0])
    keys = np.concatenate(keys)
    order = np.argsort(keys)
    counts = counts.pop()[order]
    keys = keys[order]
    del order
    at = np.flatnonzero(changes((keys,)))
    sums = np.add.reduceat(counts, at, dtype=np.uint64) if len(at) else np.zeros(0, np.uint64)
    keys = keys[at]
    return [(keys >> np.uint64(bits * j) & np.uint64((1 << bits) - 1)).astype(np.uint32) for j in range(width - 1, -1, -1)], sums


def _runs(columns: list[np.ndarray], counts: np.ndarray) -> tuple[np.ndarray, tuple[np.ndarray, ...]]:
    """Of sorted n-grams: the first row of each context, and its total and grams seen once, twice and more."""
    if not len(counts):
        return np.zeros(0, np.int64), (np.zeros(0, np.uint64),) * 4
    heads = np.flatnonzero(changes(tuple(columns[:-1])))
    return heads, tuple(np.add.reduceat(x.astype(np.uint64), heads) for x in (counts, counts == 1, counts == 2, counts > 2))


def _census(counts: np.ndarray) -> list[int]:
    return [len(counts), *(int((counts == k).sum()) for k in (1, 2, 3, 4))]


def fit(df: DataFrame, text: str = "text", shard_bytes: int = 16 << 20, hot_sample: int = 2000, hot_share: float = 0.1, order: int = 3) -> Model:
    """Count a model of order two or more over all rows of ``df``."""
    if order < 2:
        raise ValueError("the order must be two or more")
    spark = df.sparkSession
    body = F.encode(F.coalesce(F.col(text), F.lit("")), "UTF-8").alias("text")
    size = df.agg(F.coalesce(F.sum(F.octet_length(text)), F.lit(0)), F.count("*")).first()
    shards = max(1, -(-int(size[0]) // shard_bytes))
    word_shards = max(1, -(-shards // 2))
    hot, hot_pairs = _hot_contexts(df.filter(F.pmod(F.xxhash64(text), F.lit(max(1, size[1] // max(hot_sample, shards)))) == 0).select(body), hot_share / shards)
    target = folder(spark, "kneser-ney")

    def batch(rows: list) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.string()), pa.array([r[1] for r in rows], pa.int32()), pa.array([r[2] for r in rows], pa.binary())], names=["kind", "shard", "block"])

    def gather(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, sizes, waiting = [], [], 0

        def flush() -> Iterator[pa.RecordBatch]:
            words, columns = coded(np.concatenate(held), np.concatenate(sizes), order)
            held.clear()
            sizes.clear()
            times = np.bincount(columns[-1], minlength=len(words)).astype(np.uint64)
            seen = np.flatnonzero(times)
            for s, at in by_shard(mix64(words[seen]) % np.uint64(shards), shards):
                yield batch([("word", s, squeeze((words[seen[at]], times[seen[at]]), -1))])
            # Codes keep the order of hashes, and so of short ones; two words with one short hash are one in n-grams.
            words = short(words)
            columns, counts = grouped(columns, len(words))
            for s, at in by_shard(mix64(places(words, columns, hot, hot_pairs)[0]) % np.uint64(shards), shards):
                yield batch([("gram", s, _block(words, [c[at] for c in columns], counts[at]))])
            release_memory()

        for b in batches:
            for i in range(0, b.num_rows, 512):
                texts = b.column(0).slice(i, 512).to_pylist()
                for lo, hi in _chunks(texts):
                    tokens, n = tokenise(texts[lo:hi])
                    held.append(tokens)
                    sizes.append(n)
                    waiting += len(tokens)
                    if waiting > FLUSH_TOKENS:
                        yield from flush()
                        waiting = 0
        if held:
            yield from flush()

    def word_rows(words: np.ndarray, numbers: np.ndarray) -> list:
        """Blocks of word numbers, by the word's shard."""
        some = numbers.any(axis=0)
        words, numbers = words[some], numbers[:, some]
        return [("word", s, squeeze((words[at], *(x[at] for x in numbers)), -1)) for s, at in by_shard(mix64(words) % np.uint64(word_shards), word_shards)]

    def as_context(numbers: np.ndarray, columns: list[np.ndarray], counts: np.ndarray) -> None:
        """Add what pairs tell of their words."""
        numbers[0] += np.bincount(columns[1], minlength=numbers.shape[1]).astype(np.uint64)
        heads, sums = _runs(columns, counts)
        for k, x in enumerate(sums):
            numbers[1 + k][columns[0][heads]] += x

    def merge(table: pa.Table) -> pa.Table:
        shard, kinds = table.column("shard")[0].as_py(), table.column("kind").to_pylist()
        arrays, out, facts = {}, [], np.zeros((order + 1, 5), np.int64)
        parts = [spread(x.as_py(), ("u8", "u8"), -1) for k, x in zip(kinds, table.column("block"), strict=True) if k == "word"]
        if parts:
            keys, (times,) = _summed([np.concatenate([p[i] for p in parts]) for i in range(2)])
            arrays["words"] = hash_arrays.pack(keys, [times])
            facts[order, :2] = len(keys), times.sum()
        blobs = [x for k, x in zip(kinds, table.column("block"), strict=True) if k == "gram"]
        if not blobs:
            hash_arrays.write(f"{target}/grams-{shard:07d}", arrays)
            return pa.Table.from_batches([batch([("fact", -1, facts.tobytes())])])
        words = np.unique(np.concatenate([_words_of(x.as_py()) for x in blobs]))
        columns, counts = _merged(words, (_unblock(x.as_py(), order) for x in blobs), order)
        numbers = np.zeros((5, len(words)), np.uint64)
        for level in range(order, 1, -1):
            if level < order:  # drop the farthest token; what is left counts the tokens before it
                columns, counts = grouped([*columns[:-2], columns[-1]], len(words))
            if level == 2:
                part = places(words, columns, hot, hot_pairs)[1] if order > 2 else np.zeros(len(counts), bool)
                spilt = [c[part] for c in columns]
                for s, at in by_shard(mix64(_whole(words, spilt)) % np.uint64(shards), shards):
                    out.append(("pair", s, _block(words, [c[at] for c in spilt], counts[part][at])))
                columns, counts = [c[~part] for c in columns], counts[~part]
                as_context(numbers, columns, counts)
            else:
                heads, sums = _runs(columns, counts)
                opening = [c[heads] for c in columns]
                context, split = _hashes(words, opening)[0], places(words, opening, hot, hot_pairs)[2]
                arrays |= _once(f"context{level}", context[~split], *(x[~split] for x in sums))
                if split.any():
                    rows = np.sort(context[split]), np.argsort(context[split])
                    out += [(f"context{level}", s, squeeze((rows[0][at], *(x[split][rows[1]][at] for x in sums)), -1)) for s, at in by_shard(mix64(rows[0]) % np.uint64(shards), shards)]
            arrays |= _once(f"gram{level}", _whole(words, columns), counts)
            facts[level - 1] = _census(counts)
        hash_arrays.write(f"{target}/grams-{shard:07d}", arrays)
        out += word_rows(words, numbers)
        out.append(("fact", -1, facts.tobytes()))
        release_memory()
        return pa.Table.from_batches([batch(out)])

    def merge_hot(table: pa.Table) -> pa.Table:
        shard, kinds, blocks = table.column("shard")[0].as_py(), table.column("kind").to_pylist(), table.column("block").to_pylist()
        arrays, out, facts = {}, [], np.zeros((order + 1, 5), np.int64)
        for level in range(3, order + 1):
            if parts := [spread(x, ("u8",) * 5, -1) for k, x in zip(kinds, blocks, strict=True) if k == f"context{level}"]:
                keys, sums = _summed([np.concatenate([p[i] for p in parts]) for i in range(5)])
                arrays |= _once(f"context{level}", keys, *sums)
        if parts := [_unblock(x, 2) for k, x in zip(kinds, blocks, strict=True) if k == "pair"]:
            words = np.unique(np.concatenate([p[0] for p in parts]))
            columns = [np.concatenate([np.searchsorted(words, p[0]).astype(np.uint32)[p[1][k]] for p in parts]) for k in range(2)]
            columns, counts = grouped(columns, len(words), np.concatenate([p[2] for p in parts]))
            arrays |= _once("gram2", _whole(words, columns), counts)
            facts[1] = _census(counts)
            numbers = np.zeros((5, len(words)), np.uint64)
            as_context(numbers, columns, counts)
            out += word_rows(words, numbers)
        hash_arrays.write(f"{target}/hot-{shard:07d}", arrays)
        out.append(("fact", -1, facts.tobytes()))
        return pa.Table.from_batches([batch(out)])

    def merge_words(table: pa.Table) -> pa.Table:
        shard, blocks = table.column("shard")[0].as_py(), table.column("block").to_pylist()
        if shard < 0:
            facts = np.sum([np.frombuffer(x, np.int64) for x in blocks], axis=0)
            return pa.table({"kind": ["grams"], "sums": [facts.tolist()]})
        parts = [spread(x, WORD, -1) for x in blocks]
        keys, sums = _summed([np.concatenate([p[i] for p in parts]) for i in range(6)])
        hash_arrays.write(f"{target}/short-{shard:07d}", {"words": _array(mix64(keys), *sums)})
        return pa.table({"kind": ["words"], "sums": [[int((sums[0] > 0).sum()), *_census(sums[0])[1:]]]})

    shape = "kind string, shard int, block binary"
    first = stored(df.select(body).mapInArrow(lean(gather), shape).groupBy("shard").applyInArrow(lean_group(merge), shape), "kneser-ney-merged")
    second = stored(first.filter(F.col("kind").rlike("pair|context")).groupBy("shard").applyInArrow(lean_group(merge_hot), shape), "kneser-ney-hot")
    final = first.unionByName(second).filter("kind in ('word', 'fact')").groupBy("shard").applyInArrow(lean_group(merge_words), "kind string, sums array<long>")
    total = {"grams": [0] * 5 * (order + 1), "words": [0] * 5}
    for kind, at, n in final.select("kind", F.posexplode("sums").alias("at", "n")).groupBy("kind", "at").agg(F.sum("n")).collect():
        total[kind][at] = n
    dropped(first, second)
    w, g = total["words"], [total["grams"][5 * k : 5 * k + 5] for k in range(1, order + 1)]
    return Model(target, order, shards, word_shards, g[-1][1], g[-1][0], g[0][0], (w[1], w[2], w[0] - w[1] - w[2]), (discounts(*w[1:]), *(discounts(*x[1:]) for x in g[:-1])), hot, hot_pairs)


def _summed(columns: list[np.ndarray]) -> tuple[np.ndarray, list[np.ndarray]]:
    """Distinct keys (the first column) in order, and the sums of the other columns."""
    order = np.argsort(columns[0])
    keys = columns[0][order]
    at = np.flatnonzero(changes((keys,)))
    return keys[at], [np.add.reduceat(c[order], at) if len(at) else c for c in columns[1:]]


def _hot_contexts(drawn: DataFrame, share: float) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the tokens, and of the pairs of tokens, that stand before more than ``share`` of a sample's tokens.

    At most 1 / share of each reach the driver; the marks before a text always count as frequent.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(0, b.num_rows, 512):
                texts = b.column(0).slice(i, 512).to_pylist()
                for lo, hi in _chunks(texts):
                    words, (left, before, _) = coded(*tokenise(texts[lo:hi]), 3)
                    words = short(words)
                    single, pair = words[left], pair_hash(words[left], words[before])
                    for kind, values in ((0, single), (1, pair)):
                        h, n = np.unique(values, return_counts=True)
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(h), kind, "i4")), pa.array(h.view("i8")), pa.array(n)], names=["kind", "h", "n"])

    counts = stored(drawn.mapInArrow(lean(run), "kind int, h long, n long").groupBy("kind", "h").agg(F.sum("n").alias("n")), "kneser-ney-sample")
    total = counts.filter("kind = 0").agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    rows = counts.filter((F.col("n") > share * total) & (F.col("n") > 2)).collect()
    dropped(counts)
    mark = short(np.array([START]))
    found = [np.array([r["h"] for r in rows if r["kind"] == k], "i8").view("u8") for k in (0, 1)]
    return np.unique(np.append(found[0], mark)), np.unique(np.append(found[1], pair_hash(mark, mark)))


class Lookup:
    """The arrays of a model, opened when first needed."""

    def __init__(self, model: Model):
        self.model, self.files = model, hash_arrays.Files(model.path)

    def find(self, file: str, label: str, keys: np.ndarray, place: np.ndarray, shards: int, fields: int) -> list[np.ndarray]:
        """Numbers of each key, zero where it is not known; ``place`` tells the file."""
        out = [np.zeros(len(keys), np.int64) for _ in range(fields)]
        for s, rows in by_shard(mix64(place) % np.uint64(shards), shards):
            rows = rows[np.argsort(keys[rows])]
            if array := self.files.array(f"{file}-{s:07d}", label):
                hit, got = array.find(keys[rows])
                for o, v in zip(out, got, strict=True):
                    o[rows[hit]] = v
                rows = rows[~hit]
            if array := self.files.array(f"{file}-{s:07d}", f"{label} once"):
                rows = rows[array.find(keys[rows])[0]]
                for o in out[:2]:  # the count, or of a context its total and its one n-gram seen once
                    o[rows] = 1
        return out

    def words(self, tokens: np.ndarray) -> list[np.ndarray]:
        """Occurrences; tokens before; as a context total, grams seen once, twice and more."""
        known, m = short(tokens), self.model
        return [*self.find("grams", "words", tokens, tokens, m.shards, 1), *self.find("short", "words", mix64(known), known, m.word_shards, 5)]

    def grams(self, words: np.ndarray, columns: list[np.ndarray], numbers: list[np.ndarray]) -> tuple[np.ndarray, list[np.ndarray]]:
        """Counts of n-grams, and totals and grams seen once, twice and more of their contexts."""
        m, level = self.model, len(columns)
        place, is_hot, is_pair = places(words, columns, m.hot, m.hot_pairs)
        context, whole = _hashes(words, columns)

        def split(label: str, keys: np.ndarray, part: np.ndarray, fields: int) -> list[np.ndarray]:
            out = [np.zeros(len(keys), np.int64) for _ in range(fields)]
            for rows, file, at in ((np.flatnonzero(~part), "grams", place), (np.flatnonzero(part), "hot", keys)):
                if len(rows):
                    for o, v in zip(out, self.find(file, label, keys[rows], at[rows], m.shards, fields), strict=True):
                        o[rows] = v
            return out

        nothing = np.zeros(len(whole), bool)
        count = split(f"gram{level}", whole, is_hot if level == 2 < m.order else nothing, 1)[0]
        if level == 2:
            return count, [x[columns[0]] for x in numbers]
        heads = np.flatnonzero(changes(tuple(columns[:-1])))
        run = np.cumsum(changes(tuple(columns[:-1]))) - 1
        context, place, is_pair = context[heads], place[heads], is_pair[heads]
        return count, [x[run] for x in split(f"context{level}", context, is_pair, 4)]


def _discounted(count: np.ndarray, d: tuple[float, float, float]) -> np.ndarray:
    return np.where(count > 0, count - np.array([0.0, *d])[np.minimum(count, 3)], 0.0)


def log_scores(look: Lookup, texts: list[bytes]) -> tuple[np.ndarray, ...]:
    """Tokens, known tokens, base score and model score (log10) of each text."""
    m = look.model
    tokens, n = tokenise(texts)
    words, columns = coded(tokens, n, m.order)
    occ, lefts, *numbers = look.words(words)
    w, k, words = columns[-1], len(words), short(words)
    low = np.full(k, 1.0 / (m.vocabulary + 1))
    if m.pair_types:
        freed = sum(d * t for d, t in zip(m.discounts[0], m.word_types, strict=True)) / m.pair_types
        low = _discounted(lefts, m.discounts[0]) / m.pair_types + freed * low
    keys, p_low = None, low
    for level in range(2, m.order + 1):
        # The distinct n-grams of this order, and the row of each token's.
        key, rows = _packed([*columns[: level - 1], w], k)
        _, first, where = np.unique(key, return_index=True, return_inverse=True)
        some = [c[first] for c in [*columns[: level - 1], w]]
        count, (total, n1, n2, n3) = look.grams(words, some, numbers)
        d = m.discounts[level - 1]
        known = total > 0
        gamma = np.where(known, (d[0] * n1 + d[1] * n2 + d[2] * n3) / np.maximum(total, 1), 1.0)
        below = p_low[some[-1]] if keys is None else p_low[keys[first]]
        p_low, keys = np.where(known, _discounted(count, d) / np.maximum(total, 1), 0.0) + gamma * below, where
    each = p_low[keys]
    base = np.log10((occ + 1) / (m.tokens + (m.vocabulary + 1)))
    first = np.concatenate([[0], np.cumsum(n)[:-1]])
    return n, np.add.reduceat((occ[w] > 0).astype(np.int64), first), np.add.reduceat(base[w], first), np.add.reduceat(np.log10(each), first)


def score(df: DataFrame, model: Model, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """(id, n_tokens, n_known, base_score, score)."""
    kind = df.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        look = Lookup(model)
        for b in batches:
            texts = b.column(1).to_pylist()
            for lo, hi in _chunks(texts):
                n, known, base, got = log_scores(look, texts[lo:hi])
                yield pa.RecordBatch.from_arrays([b.column(0).slice(lo, hi - lo), pa.array(n, pa.int64()), pa.array(known, pa.int64()), pa.array(base), pa.array(got)], names=[id_col, "n_tokens", "n_known", "base_score", "score"])

    body = F.encode(F.coalesce(F.col(text), F.lit("")), "UTF-8")
    return df.select(F.col(f"`{id_col}`"), body.alias("text")).mapInArrow(lean(run), f"`{id_col}` {kind}, n_tokens long, n_known long, base_score double, score double")


def fold(id_col: Column, folds: int = 7) -> Column:
    """The remainder that deals rows into training and held-out ones."""
    return F.crc32(F.coalesce(id_col.cast("string"), F.lit("")).cast("binary")) % folds


def perplexity(scored: DataFrame, column: str = "score") -> DataFrame:
    """One row: 10 to the negative mean score per token."""
    return scored.agg(F.pow(F.lit(10.0), -F.sum(column) / F.sum("n_tokens")).alias("perplexity"))
