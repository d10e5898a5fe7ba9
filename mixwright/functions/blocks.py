"""Arrays packed into compressed binary blocks, so that a shuffle moves few rows."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import zstandard


def count_rows(keys: tuple[np.ndarray, ...], values: tuple[np.ndarray, ...]) -> tuple[tuple, tuple]:
    """Sorted distinct keys and the sums of their values."""
    order = np.lexsort(keys[::-1]) if len(keys) > 1 else np.argsort(keys[0], kind="stable")
    keys = tuple(k[order] for k in keys)
    if not len(order):
        return keys, values
    at = np.flatnonzero(changes(keys))
    return tuple(k[at] for k in keys), tuple(np.add.reduceat(v[order], at) for v in values)


def changes(keys: tuple[np.ndarray, ...]) -> np.ndarray:
    """True where a row of keys differs from the one before; the first is True."""
    return np.concatenate([[True], np.logical_or.reduce([k[1:] != k[:-1] for k in keys])]) if len(keys[0]) else np.zeros(0, bool)


def squeeze(columns: tuple[np.ndarray, ...], plain: int = 1, level: int = 1) -> bytes:
    """Columns as one compressed block; the first is sorted, unsigned and stored as differences, that at ``plain`` as it is, the others by byte planes."""
    lead = np.diff(columns[0], prepend=columns[0].dtype.type(0))
    body = b"".join(c.tobytes() if i == plain else np.ascontiguousarray(np.ascontiguousarray(c).view(np.uint8).reshape(-1, c.itemsize).T).tobytes() for i, c in enumerate((lead, *columns[1:])))
    return zstandard.ZstdCompressor(level=level).compress(body)


def spread(blob: bytes, dtypes: tuple, plain: int = 1) -> tuple[np.ndarray, ...]:
    body = zstandard.ZstdDecompressor().decompress(blob)
    n, at, out = len(body) // sum(np.dtype(d).itemsize for d in dtypes), 0, []
    for i, d in enumerate(dtypes):
        d = np.dtype(d)
        part = np.frombuffer(body, np.uint8, n * d.itemsize, at)
        out.append(part.view(d) if i == plain else np.ascontiguousarray(part.reshape(d.itemsize, n).T).view(d).ravel())
        at += n * d.itemsize
    out[0] = np.cumsum(out[0], dtype=out[0].dtype)
    return tuple(out)


def spread_all(blobs: list[bytes], dtypes: tuple) -> tuple[np.ndarray, ...]:
    parts = [spread(b, dtypes) for b in blobs]
    return tuple(np.concatenate([p[i] for p in parts]) if parts else np.zeros(0, d) for i, d in enumerate(dtypes))


def by_shard(shard: np.ndarray, shards: int) -> Iterator[tuple[int, np.ndarray]]:
    """(shard, its rows in order) for the shards that have rows."""
    if not len(shard):
        return
    order = np.argsort(shard, kind="stable")
    at = shard[order]
    heads = np.flatnonzero(changes((at,)))
    for lo, hi in zip(heads, np.append(heads[1:], len(at)), strict=True):
        yield int(at[lo]), order[lo:hi]


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit values that spreads every bit."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


BASE = 0x5851F42D4C957F2D
TABLE = np.random.default_rng(20).integers(0, 1 << 63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_powers = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """The first n powers of the rolling base and of its inverse, modulo 2^64."""
    if len(_powers[0]) < n:
        for k, base in enumerate((BASE, pow(BASE, -1, 1 << 64))):
            steps = np.full(n, base, dtype=np.uint64)
            steps[0] = 1
            _powers[k] = np.multiply.accumulate(steps)
    return _powers[0][:n], _powers[1][:n]


def rolling_sums(raw: np.ndarray) -> np.ndarray:
    """Prefix sums from which any stretch's hash follows by ``stretch_hash``."""
    return np.concatenate([np.zeros(1, np.uint64), np.cumsum(TABLE[raw] * powers(len(raw))[0])])


def stretch_hash(sums: np.ndarray, start: np.ndarray, stop: np.ndarray) -> np.ndarray:
    return mix64((sums[stop] - sums[start]) * powers(len(sums))[1][start] + (stop - start).astype(np.uint64))
