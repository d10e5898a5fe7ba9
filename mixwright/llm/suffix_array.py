"""Suffix arrays by recursive induced sorting, with priority queues that go to disk and common-prefix values carried along.

Suffixes are of type L (greater than their successor) or S; the leftmost S of each group anchor the rest. An induction from the
anchors in any order sorts the substrings of bytes between anchors; equal ones get equal names; the sequence of names, a third of
the text or less, is sorted in its turn: its own anchors' substrings are ranked, their names sorted by recursion, and
an induction orders the rest. A last induction from the sorted anchors orders all suffixes of the text. The
recursion ends where all names differ or each stands for ``depth`` bytes.

An induction takes suffixes in order and pushes each one's predecessor to a priority queue. Over bytes, the queue is one
first-in-first-out list per byte value; over names, it is one per range of names, split into a list for each name when its
turn comes. Queues are held in memory up to a limit and
written to files beyond it, in whatever file system the folder is in. The larger suffixes of a text wait for the second half of
an induction in such queues too, and the result is yielded byte value by byte value, so memory holds the text, its types and
one queue. Each entry over bytes carries its common prefix with the one before it in its queue: one more than the least value
between their successors. Over names, order alone is kept; the prefixes of the sorted anchors are read off the text.

Ranks and prefixes are exact up to ``depth`` bytes (at most 126), which is all that a search for repeats of that length needs.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow.fs as pafs

TOP = 127
MEMORY = 1 << 20
RANGE = 20_000  # suffixes of names whose keys share a queue
NONE = np.zeros(0, np.int32), np.zeros(0, np.uint8)


class Queues:
    """Lists of (position, common prefix) arrays by number, in order of pushing; beyond ``memory`` bytes they are written to ``folder``."""

    def __init__(self, buckets: int, memory: int, folder: str | None):
        self.parts: list[list] = [[] for _ in range(buckets)]
        self.sizes = np.zeros(buckets, np.int64)
        self.written: list[list] = [[] for _ in range(buckets)]  # (file, offset, entries)
        self.held, self.memory, self.files, self.spills = 0, memory, [], 0
        self.fs, self.folder = pafs.FileSystem.from_uri(folder) if folder else (None, None)

    def push(self, b: int, positions: np.ndarray, prefixes: np.ndarray) -> None:
        self.parts[b].append((positions, prefixes))
        self.sizes[b] += len(positions)
        self.held += positions.nbytes + prefixes.nbytes
        if self.fs and self.held > self.memory:
            self._spill()

    def _spill(self) -> None:
        """Write what all lists hold to one file."""
        self.fs.create_dir(self.folder, recursive=True)
        name, at = f"{self.folder}/queue-{uuid.uuid4().hex}", 0
        with self.fs.open_output_stream(name) as f:
            for b, parts in enumerate(self.parts):
                n = sum(len(p) for p, _ in parts)
                if n:
                    f.write(b"".join(p.astype("<i4").tobytes() for p, _ in parts) + b"".join(q.tobytes() for _, q in parts))
                    self.written[b].append((name, at, n))
                    at += 5 * n
                    self.parts[b] = []
        self.files.append(name)
        self.held = 0
        self.spills += 1

    def take(self, b: int) -> tuple[np.ndarray, np.ndarray]:
        """All entries of a list, in the order of pushing."""
        parts = []
        for name, at, n in self.written[b]:
            with self.fs.open_input_file(name) as f:
                raw = f.read_at(5 * n, at)
            parts.append((np.frombuffer(raw, "<i4", n), np.frombuffer(raw, np.uint8, n, 4 * n)))
        own, self.parts[b], self.written[b] = self.parts[b], [], []
        self.held -= sum(p.nbytes + q.nbytes for p, q in own)
        parts += own
        self.sizes[b] = 0
        return (np.concatenate([p for p, _ in parts]), np.concatenate([q for _, q in parts])) if parts else NONE

    def close(self) -> None:
        for f in self.files:
            self.fs.delete_file(f)
        self.files = []


def _range_minima(values: np.ndarray, low: np.ndarray, high: np.ndarray) -> np.ndarray:
    """Least of values[low..high] for each pair, low <= high."""
    out = np.empty(len(low), values.dtype)
    level = (np.frexp((high - low + 1).astype(np.float64))[1] - 1).astype(np.int8)
    table, k = values, 0
    top = int(level.max()) if len(level) else -1
    while k <= top:
        at = np.flatnonzero(level == k)
        if len(at):
            out[at] = np.minimum(table[low[at]], table[high[at] - (1 << k) + 1])
        if k < top:
            table = np.minimum(table[: len(table) - (1 << k)], table[1 << k :])
        k += 1
    return out


class _Scan:
    """One induction over bytes: takes segments of suffixes in order and pushes their predecessors of one type."""

    def __init__(self, text: np.ndarray, of_type: np.ndarray, queues: Queues, carry: bool):
        self.text, self.of_type, self.queues, self.carry = text, of_type, queues, carry
        self.least = np.full(257, TOP, np.uint8)  # since the last push to each bucket
        self.pushed = np.zeros(257, bool)

    def step(self, positions: np.ndarray, prefixes: np.ndarray) -> None:
        before = positions - 1
        at = np.flatnonzero((before >= 0) & self.of_type[before])
        b = self.text[before[at]]
        order = np.argsort(b, kind="stable")
        at, b = at[order], b[order]
        new = np.zeros(len(at), np.uint8)
        if len(at):
            first = np.concatenate([[True], b[1:] != b[:-1]])
            heads = np.flatnonzero(first)
            buckets = b[heads]
            if self.carry:
                inner = np.flatnonzero(~first)
                if len(inner):
                    new[inner] = _range_minima(prefixes, at[inner - 1] + 1, at[inner]) + 1
                upto = np.minimum.accumulate(prefixes)[at[heads]]
                new[heads] = np.where(self.pushed[buckets], np.minimum(self.least[buckets], upto) + 1, 0)
                np.minimum(new, TOP, out=new)
            cuts = np.append(heads, len(at))
            source = before[at].astype(np.int32)
            for k, bucket in enumerate(buckets):
                self.queues.push(int(bucket), source[cuts[k] : cuts[k + 1]], new[cuts[k] : cuts[k + 1]])
        if self.carry and len(prefixes):
            np.minimum(self.least, prefixes.min(), out=self.least)
            if len(at):
                behind = np.append(np.minimum.accumulate(prefixes[::-1])[::-1], TOP).astype(np.uint8)
                self.least[buckets] = behind[at[cuts[1:] - 1] + 1]
                self.pushed[buckets] = True


def _waves(queues: Queues, scan: _Scan, c: int) -> tuple[np.ndarray, np.ndarray]:
    """A queue taken whole, then what it has pushed to itself, until nothing is left."""
    waves = []
    while queues.sizes[c]:
        waves.append(queues.take(c))
        scan.step(*waves[-1])
    return (np.concatenate([w[0] for w in waves]), np.concatenate([w[1] for w in waves])) if waves else NONE


def induce(text: np.ndarray, is_s: np.ndarray, anchors: np.ndarray, prefixes: np.ndarray | None, runs: np.ndarray | None, memory: int, folder: str | None, spilt: Callable[[int], None] = lambda n: None) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """All suffixes from anchors in order: for each first byte, from the largest down, (positions in order, common prefixes with the one before)."""
    carry = prefixes is not None
    own = prefixes if carry else np.zeros(len(anchors), np.uint8)
    cuts = np.searchsorted(text[anchors], np.arange(258))
    up, larger, down = (Queues(257, memory, folder) for _ in range(3))
    try:
        scan = _Scan(text, ~is_s, up, carry)
        for c in range(257):
            p, q = _waves(up, scan, c)
            if len(p):
                larger.push(c, p, q)
            mine, mine_lcp = anchors[cuts[c] : cuts[c + 1]], own[cuts[c] : cuts[c + 1]].copy()
            if len(mine):
                mine_lcp[0] = min(runs[p[-1]], runs[mine[0]]) if carry and len(p) else 0
                scan.step(mine, mine_lcp)
        scan = _Scan(text, is_s, down, carry)
        for c in range(256, -1, -1):
            sp, sq = _waves(down, scan, c)
            p, q = larger.take(c)
            if c == 0:  # the end of the text has no successor to bring it in
                sp, sq = np.append(sp, np.int32(len(text) - 1)), np.append(sq, np.uint8(0))
            meet = np.uint8(min(runs[p[-1]], runs[sp[-1]]) if carry and len(p) and len(sp) else 0)
            if len(p):
                scan.step(p[::-1], np.concatenate([[meet], q[:0:-1]]).astype(np.uint8))
            # A queue filled downwards holds the prefix with the next one up; turned round, that is the next one's with it.
            turned = np.concatenate([[meet], sq[:0:-1]]).astype(np.uint8) if len(sp) else sq
            yield np.concatenate([p, sp[::-1]]), np.concatenate([q, turned])
    finally:
        spilt(up.spills + larger.spills + down.spills)
        for queues in (up, larger, down):
            queues.close()


def _types(text: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Which suffixes are of type S, the last place of each run of equal symbols, and the anchors."""
    n = len(text)
    place = np.arange(n - 1, dtype=np.int32)
    change = np.where(text[1:] != text[:-1], place, np.int32(n - 2))
    change = np.minimum.accumulate(change[::-1])[::-1]
    is_s = np.empty(n, bool)
    is_s[:-1] = text[1:][change] > text[change]
    is_s[-1] = True
    return is_s, change, np.flatnonzero(is_s[1:] & ~is_s[:-1]) + 1


def _drain(keys: Callable[[np.ndarray], np.ndarray], of_type: np.ndarray, given: np.ndarray, given_keys: np.ndarray, edges: np.ndarray, last: int, memory: int, folder: str | None, spilt: Callable[[int], None]) -> np.ndarray:
    """Suffixes of one type in order of key and arrival, each pushed by its successor; ``given`` ones, in order, start the chain.

    Pushed keys are even and below ``last``, given ones odd. ``edges`` cut the keys into ranges, a queue each; a range that is taken becomes a list for
    each of its keys, which grow while they are read.
    """
    queues, out = Queues(len(edges) + 1, memory, folder), []
    borders = [0, *edges.tolist(), last + 1]
    cuts = np.concatenate([[0], np.searchsorted(given_keys, edges, "left"), [len(given)]])
    # The key that each suffix pushes its predecessor with, or -1.
    sources = np.flatnonzero(of_type[:-1]) + 1
    whence = np.full(len(of_type), -1)
    whence[sources] = keys(sources - 1)
    pushes = whence.tolist()
    for r, (low, high) in enumerate(zip(borders[:-1], borders[1:], strict=True)):
        pos, fixed = queues.take(r)[0], slice(cuts[r], cuts[r + 1])
        if not len(pos) and fixed.start == fixed.stop:
            continue
        lists: list[list[int]] = [[] for _ in range(high - low)]
        for at, k in ((pos, keys(pos)), (given[fixed], given_keys[fixed])):
            for x, y in zip(at.tolist(), (k - low).tolist(), strict=True):
                lists[y].append(x)
        away: list[int] = []
        mine: list[int] = []
        for y, here in enumerate(lists, low):
            for x in here:
                k = pushes[x]
                if k >= high:
                    away.append(x - 1)
                elif k >= 0:
                    lists[k - low].append(x - 1)
            if not y & 1:
                mine += here
        out.append(np.array(mine, np.int32))
        if not away:
            continue
        new = np.array(away, np.int32)
        to = np.searchsorted(edges, whence[new + 1], "right")
        order = np.argsort(to, kind="stable")
        to, new = to[order], new[order]
        heads = np.flatnonzero(np.concatenate([[True], to[1:] != to[:-1]]))
        for lo, hi in zip(heads, np.append(heads[1:], len(to)), strict=True):
            queues.push(int(to[lo]), new[lo:hi], np.zeros(hi - lo, np.uint8))
    spilt(queues.spills)
    queues.close()
    return np.concatenate(out) if out else np.zeros(0, np.int32)


def induce_names(text: np.ndarray, is_s: np.ndarray, anchors: np.ndarray, memory: int, folder: str | None, spilt: Callable[[int], None]) -> np.ndarray:
    """All suffixes of a text of names in order, from anchors in order. The text ends with its only least name."""
    twice = text.astype(np.int64) * 2
    top, ranges = int(twice.max()) + 1, max(1, len(text) // RANGE)
    quantiles = lambda k: np.unique(np.partition(k, cut)[cut]) if len(cut := np.arange(1, ranges) * len(k) // ranges) and len(k) else k[:0]
    larger = _drain(lambda p: twice[p], ~is_s, anchors, twice[anchors] + 1, quantiles(twice[~is_s]), top, memory, folder, spilt)
    # Downwards, keys turn round: of one name, S before L.
    given = larger[::-1]
    smaller = _drain(lambda p: top - twice[p] - 1, is_s, given, top - twice[given], quantiles(top - twice[is_s] - 1), top, memory, folder, spilt)
    both, last = np.concatenate([larger, smaller[::-1]]), np.int32(len(text) - 1)
    order = np.argsort(np.concatenate([twice[larger], twice[smaller[::-1]] + 1]), kind="stable")
    both = both[order]
    return np.concatenate([[last], both[both != last]]).astype(np.int32)


def _same(padded: np.ndarray, a: np.ndarray, b: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Whether the ``size`` symbols at a and b are equal."""
    out, wide = np.ones(len(a), bool), np.arange(8)
    for lo in range(0, len(a), 1 << 16):
        part = slice(lo, lo + (1 << 16))
        x, y, n, live, at = a[part], b[part], size[part], np.arange(len(a[part])), 0
        while len(live):
            inside = at + wide < n[live][:, None]
            equal = ((padded[(x[live] + at)[:, None] + wide] == padded[(y[live] + at)[:, None] + wide]) | ~inside).all(axis=1)
            out[lo + live[~equal]] = False
            at += 8
            live = live[equal & (n[live] > at)]
    return out


def _names(text: np.ndarray, marks: np.ndarray, order: np.ndarray) -> np.ndarray:
    """Ranks of the substrings from each mark to the next, that included, whose marks ``order`` has sorted."""
    number = np.zeros(len(text), np.int32)
    number[marks] = np.arange(len(marks), dtype=np.int32)
    nth = number[order]
    size = np.append(np.diff(marks) + 1, 1)
    fresh = np.ones(len(order), bool)
    twin = np.flatnonzero(size[nth[1:]] == size[nth[:-1]]) + 1
    padded = np.concatenate([text, np.zeros(8, text.dtype)])
    fresh[twin] = ~_same(padded, order[twin].astype(np.int64), order[twin - 1].astype(np.int64), size[nth[twin]])
    names = np.empty(len(marks), np.int32)
    names[nth] = np.cumsum(fresh) - 1
    return names


def _ranked(values: np.ndarray) -> np.ndarray:
    """Dense ranks."""
    order = np.argsort(values, kind="stable")
    out = np.empty(len(values), np.int64)
    out[order] = np.cumsum(np.concatenate([[False], values[order[1:]] != values[order[:-1]]]))
    return out


def name_substrings(text: np.ndarray, is_s: np.ndarray, marks: np.ndarray) -> np.ndarray:
    """Ranks of the substrings of names from each mark to the next, that included; of equal names, one of type L is less.

    Ties are looked at again, a few symbols further on, until they are settled or at their end.
    """
    symbol = np.append(text.astype(np.int64) * 2 + is_s + 1, 0)  # 0 is behind the end of a substring
    size = np.append(np.diff(marks) + 1, 1)
    at = lambda rows, k: np.where(k < size[rows], symbol[np.minimum(marks[rows] + k, len(text))], 0)
    rank, k = _ranked(symbol[marks]), 1
    live = np.arange(len(marks))
    while len(live):
        tied = np.bincount(rank, minlength=len(marks))[rank[live]] > 1
        live = live[tied & (size[live] > k)]
        if not len(live):
            return rank
        # Within a rank, those at their end come first; new ranks leave room for all that were tied.
        more = at(live, k) << 31 | _ranked(at(live, k + 1))
        ahead = np.zeros(len(marks), np.int64)
        ahead[live] = _ranked(more) + 1
        order = np.lexsort((ahead, rank))
        r, a = rank[order], ahead[order]
        rank[order] = np.cumsum(np.concatenate([[False], (r[1:] != r[:-1]) | (a[1:] != a[:-1])]))
        k += 2
    return rank


def sort_names(text: np.ndarray, spans: np.ndarray, depth: int, memory: int, folder: str | None, spilt: Callable[[int], None]) -> np.ndarray:
    """Suffixes of a text of names, each standing for ``spans`` bytes, in order up to ``depth`` bytes."""
    if int(text.max()) == len(text) - 1 or spans.min() >= depth:
        return np.argsort(text, kind="stable").astype(np.int32)
    is_s, _, marks = _types(text)
    upto = np.concatenate([np.zeros(1, np.int64), np.cumsum(np.minimum(spans, depth), dtype=np.int64)])
    covered = np.append(upto[marks[1:]] - upto[marks[:-1]], depth)
    names = name_substrings(text, is_s, marks).astype(np.int32)
    order = marks[sort_names(names, covered, depth, memory, folder, spilt)].astype(np.int32)
    return induce_names(text, is_s, order, memory, folder, spilt)


def _common(raw: np.ndarray, a: np.ndarray, b: np.ndarray, depth: int) -> np.ndarray:
    """Common prefix of the suffixes at a and b, up to depth; ``raw`` is padded behind by as much."""
    out = np.zeros(len(a), np.uint8)
    wide = np.arange(16, dtype=np.int32)
    for lo in range(0, len(a), 1 << 15):
        left, right = a[lo : lo + (1 << 15)], b[lo : lo + (1 << 15)]
        live, part = np.arange(len(left)), np.zeros(len(left), np.int32)
        for at in range(0, depth, 16):
            same = raw[(left[live] + at)[:, None] + wide] == raw[(right[live] + at)[:, None] + wide]
            n = np.where(same.all(axis=1), 16, same.argmin(axis=1))
            part[live] += n
            live = live[n == 16]
            if not len(live):
                break
        out[lo : lo + (1 << 15)] = np.minimum(part, depth)
    return out


def sorted_suffixes(data: np.ndarray, depth: int = 100, memory: int = MEMORY, folder: str | None = None, spilt: Callable[[int], None] = lambda n: None) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """For each first byte, from the largest down to the end of the text: (suffixes in order of their first ``depth`` bytes, common
    prefixes with the one before), for bytes 0-255. The first of a byte has prefix 0.

    Prefixes are cut off at ``depth`` or a little above; where one reaches the end of the text it ends there. ``folder`` is a URI; ``spilt``
    is told how often queues were written.
    """
    if not 0 < depth < TOP:
        raise ValueError("depth must be between 1 and 126")
    n = len(data) + 1
    text = np.zeros(n, np.uint16)
    text[:-1] = data.astype(np.uint16) + 1
    if n == 1:
        yield np.zeros(1, np.int32), np.zeros(1, np.uint8)
        return
    is_s, change, marks = _types(text)
    runs = np.append(np.minimum(change - np.arange(n - 1, dtype=np.int32) + 1, TOP - 1), 1).astype(np.uint8)
    del change
    order = marks[np.argsort(text[marks], kind="stable")].astype(np.int32)
    flag = np.zeros(n, bool)
    flag[marks] = True
    parts = [p[flag[p]] for p, _ in induce(text, is_s, order, None, None, memory, folder, spilt)]
    order = np.concatenate(parts[::-1])
    del parts, flag
    order = marks[sort_names(_names(text, marks, order), np.append(np.diff(marks), depth), depth, memory, folder, spilt)].astype(np.int32)
    padded = np.concatenate([text, np.zeros(depth + 16, np.uint16)])
    lcp = np.zeros(len(marks), np.uint8)
    lcp[1:] = _common(padded, order[1:], order[:-1], depth)
    lcp[1:] = np.where(text[order[1:]] == text[order[:-1]], lcp[1:], 0)
    del padded
    yield from induce(text, is_s, order, lcp, runs, memory, folder, spilt)


def suffix_array(data: np.ndarray, depth: int = 100, memory: int = MEMORY, folder: str | None = None) -> tuple[np.ndarray, np.ndarray]:
    """``sorted_suffixes`` as two whole arrays."""
    parts = list(sorted_suffixes(data, depth, memory, folder))[::-1]
    return np.concatenate([p for p, _ in parts]), np.concatenate([q for _, q in parts])
