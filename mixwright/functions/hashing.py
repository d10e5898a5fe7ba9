"""Draws that depend on ids alone, not on partitions, retries or engines."""

from __future__ import annotations

import hashlib
from array import array

import numpy as np
import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F


def uniform(id_col: str | Column, seed: int = 42, rng: str = "md5") -> Column:
    """A number in [0, 1) for each id. ``md5`` agrees with other engines, ``xxhash64`` is faster."""
    c = F.col(id_col) if isinstance(id_col, str) else id_col
    if rng == "xxhash64":
        return F.shiftrightunsigned(F.xxhash64(F.lit(seed), c), 11) / F.lit(float(1 << 53))
    if rng != "md5":
        raise ValueError(f"unknown rng {rng!r}")
    digest = F.md5(F.concat(F.lit(f"{seed}:"), c.cast("string")).cast("binary"))
    return F.conv(F.substring(digest, 1, 13), 16, 10).cast("double") / F.lit(float(1 << 52))


def bucket(text: Column, buckets: int) -> Column:
    """A bucket number from the leading bits of a digest; the same in every engine."""
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("long") % buckets


def _word_codes(words: pa.Array, n: int) -> np.ndarray:
    """Buckets of a flat array of words, one digest for each distinct word."""
    coded = words.dictionary_encode()
    names = [hashlib.md5((w or "").encode()).digest() for w in coded.dictionary.to_pylist()]
    codes = np.array([int.from_bytes(d[:4], "big") % n for d in names], np.int64)
    return codes[coded.indices.to_numpy()] if len(names) else np.zeros(0, np.int64)


def _plain_lists(lists: pa.Array) -> pa.ListArray:
    """Lists of a batch with null lists emptied."""
    return lists if not lists.null_count else pa.array([x or [] for x in lists.to_pylist()], pa.list_(pa.string()))


def buckets(words: Column, n: int) -> Column:
    """``bucket`` of every word of an array column; a batch's distinct words are hashed once each."""

    @F.arrow_udf("array<int>")
    def run(lists: pa.Array) -> pa.Array:
        lists = _plain_lists(lists)
        sizes = np.diff(lists.offsets.to_numpy())
        codes = _word_codes(lists.flatten(), n).astype(np.int32)
        return pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32)), pa.array(codes))

    return run(words)


def _bags(sizes: np.ndarray, codes: np.ndarray, dim: int) -> pa.Array:
    row = np.repeat(np.arange(len(sizes)), sizes)
    at = np.bincount(row * dim + codes % dim, np.where(codes < dim, 1.0, -1.0), len(sizes) * dim).astype(float).reshape(len(sizes), dim)
    norm = np.sqrt((at * at).sum(axis=1, keepdims=True))
    flat = np.divide(at, norm, out=np.zeros_like(at), where=norm > 0).ravel()
    return pa.ListArray.from_arrays(pa.array(np.arange(len(sizes) + 1) * dim, pa.int32()), pa.array(flat))


def hashed_bag(words: Column, dim: int) -> Column:
    """Signed counts of an array column of words in ``dim`` hash buckets, at unit length; no word gives the zero vector."""

    @F.arrow_udf("array<double>")
    def run(lists: pa.Array) -> pa.Array:
        lists = _plain_lists(lists)
        return _bags(np.diff(lists.offsets.to_numpy()), _word_codes(lists.flatten(), 2 * dim), dim)

    return run(words)


#: Buckets of stored codes. As it is a multiple of all smaller powers of two, fewer buckets are their remainders.
CODES = 1 << 16
#: Bits of a code in a packed n-gram.
BITS = 17


#: Words whose codes a worker remembers.
KNOWN_WORDS = 500_000
_known: dict[bytes, int] = {}


def split_words(text: bytes) -> list[bytes]:
    """As ``words`` splits: at runs of white space, with an empty word at an end that has some other than blanks."""
    t = text.strip(b" ")
    if not t:
        return []
    out = t.split()
    if t[:1].isspace():
        out.insert(0, b"")
    if t[-1:].isspace():
        out.append(b"")
    return out


def text_codes(text: Column) -> Column:
    """``buckets(words(text), CODES)``: whole texts are split in the worker, which knows the codes of words it has met."""

    @F.arrow_udf("array<int>")
    def run(texts: pa.Array) -> pa.Array:
        sizes, out = [], array("i")
        docs = [split_words(t or b"") for t in texts.to_pylist()]
        if len(_known) > KNOWN_WORDS:
            _known.clear()
        for w in set().union(*docs).difference(_known):
            _known[w] = int.from_bytes(hashlib.md5(w).digest()[:4], "big") % CODES
        for own in docs:
            sizes.append(len(own))
            out.extend(map(_known.__getitem__, own))
        return _lists(np.array(sizes, np.int64), np.frombuffer(out, np.int32))

    return run(text.cast("binary"))


def _numbers(lists: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Sizes and flat values of lists of codes."""
    if lists.null_count:
        lists = pa.array([x or [] for x in lists.to_pylist()], pa.list_(pa.int32()))
    return np.diff(lists.offsets.to_numpy()), lists.flatten().to_numpy(zero_copy_only=False).astype(np.int64)


def _lists(sizes: np.ndarray, values: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32)), pa.array(values))


def fewer(codes: Column, n: int) -> Column:
    """``buckets`` of n, which divides ``CODES``, from stored codes."""

    @F.arrow_udf("array<int>")
    def run(lists: pa.Array) -> pa.Array:
        sizes, flat = _numbers(lists)
        return _lists(sizes, (flat % n).astype(np.int32))

    return run(codes)


def coded_bag(codes: Column, dim: int) -> Column:
    """``hashed_bag`` from stored codes; twice ``dim`` divides ``CODES``."""

    @F.arrow_udf("array<double>")
    def run(lists: pa.Array) -> pa.Array:
        sizes, flat = _numbers(lists)
        return _bags(sizes, flat % (2 * dim), dim)

    return run(codes)


def packed(codes: Column, order: int, n: int) -> Column:
    """At each position the remainder by n of its code, lowest, and of the ``order`` - 1 codes before it, ``BITS`` bits each; one up, so 0 is none."""
    if n >= 1 << BITS or order * BITS > 63:
        raise ValueError(f"{order} codes of {n} do not fit a long")

    @F.arrow_udf("array<long>")
    def run(lists: pa.Array) -> pa.Array:
        sizes, flat = _numbers(lists)
        t = flat % n + 1
        place, key = np.arange(len(t)) - np.repeat(np.cumsum(sizes) - sizes, sizes), t.copy()
        for k in range(1, order):
            key[k:] += np.where(place[k:] >= k, t[:-k] << (BITS * k), 0)
        return _lists(sizes, key)

    return run(codes)


def _windows(sizes: np.ndarray, flat: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Hash of the n codes from each position, and whether they all lie in its list."""
    left = np.repeat(np.cumsum(sizes), sizes) - np.arange(len(flat))
    h, more = np.zeros(len(flat), np.uint64), np.concatenate([flat, np.zeros(n, np.int64)]).astype(np.uint64) + np.uint64(1)
    for k in range(n):
        h = h * np.uint64(0x9E3779B97F4A7C15) + more[k : k + len(flat)]
    return ((h ^ (h >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)).view(np.int64), left >= n


def windows(codes: Column, n: int) -> Column:
    """Hashes of all n-grams of stored codes."""

    @F.arrow_udf("array<long>")
    def run(lists: pa.Array) -> pa.Array:
        sizes, flat = _numbers(lists)
        h, whole = _windows(sizes, flat, n)
        return _lists(np.maximum(sizes - n + 1, 0), h[whole])

    return run(codes)


def meets(codes: Column, n: int, hashes: np.ndarray) -> Column:
    """Whether one of ``windows`` is among ``hashes``; a table of their leading bits rules out most."""
    known = np.sort(hashes.astype(np.int64))
    table = np.zeros(1 << 22, bool)
    table[known.view(np.uint64) >> np.uint64(42)] = True
    bits = np.packbits(table)

    @F.arrow_udf("boolean")
    def run(lists: pa.Array) -> pa.Array:
        sizes, flat = _numbers(lists)
        h, whole = _windows(sizes, flat, n)
        at = np.flatnonzero(np.unpackbits(bits).view(bool)[h.view(np.uint64) >> np.uint64(42)] & whole)
        at = at[np.isin(h[at], known)]
        out = np.zeros(len(sizes), bool)
        out[np.searchsorted(np.cumsum(sizes), at, "right")] = True
        return pa.array(out)

    return run(codes)
