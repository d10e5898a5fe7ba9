"""Packing of records into fixed-capacity bins by conflict-constrained best fit.

Records are hashed into pools of about ``pool_rows`` rows, each packed by one task. In a pool, pieces go in order of
falling length. Open bins are kept by residual capacity; the search starts at the tightest bin that has room and
steps to the next residual until a bin is compatible: its bitmaps must lack the piece's duplicate cluster, and may
hold at most ``per_source`` pieces of the piece's source. A record longer than a bin is cut into full pieces and a
rest, which are placed like other pieces but never share a bin.

A pool sees its own bins alone. So bins that stay more than ``slack`` empty hand their pieces on: what all pools have left is
dealt to fewer pools and packed again, until one pool holds it, and a bin is left open for want of fitting
pieces in the whole table rather than in its pool. Each round moves what the one before could not fill.

With ``place``, a gapless number from 0 such as a record's place in a training order, pools are stretches of that order, and later ones
join neighbours: bins hold records that are scheduled together. Bins are numbered, and pieces in them laid, by their places.

Memory is one pool; a cluster or source may fill a pool entirely. Pieces that are alike in length, source and cluster
follow one another, and what refused one of them refuses the rest, so a group of copies is searched once.

``write_bins`` joins the pieces with a token store and writes the bins' ids.

Defined results: a null or empty record takes no room and is placed as a piece of length 0; a null source or cluster
conflicts with nothing; repeated rows and ids are all placed, and rows alike in id, length, source and cluster share a pool; an empty
table gives an empty result; other columns of the input are ignored; ids must be integers.
"""

from __future__ import annotations

from bisect import bisect_left, bisect_right, insort

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from mixwright.operators.near import integer_ids

from . import token_store
from .shared import folder, lean_group, stored

PLACED = "doc_id long, piece int, piece_start long, n_tokens long, source string, cluster long, pool long, bin int, bin_offset long, bin_tokens long, bin_pieces int"

SCHEMA = pa.schema(
    [("doc_id", pa.int64()), ("piece", pa.int32()), ("piece_start", pa.int64()), ("n_tokens", pa.int64()), ("source", pa.string()), ("cluster", pa.int64())]
    + [("pool", pa.int64()), ("bin", pa.int32()), ("bin_offset", pa.int64()), ("bin_tokens", pa.int64()), ("bin_pieces", pa.int32())]
)


def best_fit(pieces: list[tuple], capacity: int, per_source: int = 2) -> list[tuple[int, int]]:
    """(bin, offset) for each (length, source code or -1, cluster codes as a bitmap); pieces come sorted by falling length."""
    levels: list[int] = []  # residuals that some bin has, ascending
    rooms: dict[int, list[int]] = {}  # residual -> bins, in order of opening
    used: list[int] = []
    sources: list[list[int]] = []  # per bin, one bitmap for each count up to per_source
    clusters: list[int] = []
    out: list[tuple[int, int]] = []
    last, level, after = None, 0, -1  # the search for a repeated piece goes on where that for its twin ended
    for piece in pieces:
        length, source, cluster = piece
        bit = 1 << source if source >= 0 else 0
        found = -1
        if piece != last:
            last, level, after = piece, length, -1
        elif capacity - used[prior] >= length and not (clusters[prior] & cluster) and not (sources[prior][-1] & bit):
            found = prior  # what lies between its old and its new residual has refused already
        if found < 0:
            for k in range(bisect_left(levels, level), len(levels)):
                bins = rooms[levels[k]]
                for b in bins[bisect_right(bins, after) if levels[k] == level else 0 :]:
                    if not (clusters[b] & cluster) and not (sources[b][-1] & bit):
                        found, level, after = b, levels[k], b
                        break
                if found >= 0:
                    break
            else:
                level = capacity + 1
        if found < 0:
            found = len(used)
            used.append(0)
            sources.append([0] * per_source)
            clusters.append(0)
            left = capacity
        else:
            left = capacity - used[found]
            rooms[left].remove(found)
            if not rooms[left]:
                del rooms[left]
                levels.pop(bisect_left(levels, left))
        prior = found
        out.append((found, used[found]))
        used[found] += length
        clusters[found] |= cluster
        planes = sources[found]
        for k in range(per_source - 1, 0, -1):
            planes[k] |= planes[k - 1] & bit
        planes[0] |= bit
        left -= length
        if left not in rooms:
            rooms[left] = []
            insort(levels, left)
        insort(rooms[left], found)
    return out


def pack(df: DataFrame, tokens: Column, cluster: Column, capacity: int = 2048, per_source: int = 2, id_col: str = "doc_id", source: str = "source", pool_rows: int = 4096, slack: float = 0.02, place: Column | None = None) -> DataFrame:
    """One row per piece, with its bin and offset in it. ``cluster`` is a long that equal or near-equal records share; ``place`` is kept as a column."""
    if capacity < 1 or per_source < 1:
        raise ValueError("capacity and per_source must be positive")
    integer_ids(df, id_col)
    more = [] if place is None else ["place"]
    schema, shape = (SCHEMA, PLACED) if place is None else (SCHEMA.append(pa.field("place", pa.int64())), f"{PLACED}, place long")

    def packed(number: int, rows: list[tuple]) -> pa.Table:
        """``rows``: (document, piece, start, length, source, cluster, and the place if it is given)."""
        rows.sort(key=lambda r: tuple((v is not None, v) for v in r))
        src, clu = ({v: i for i, v in enumerate(sorted({r[k] for r in rows} - {None}))} for k in (4, 5))
        parts: dict = {}
        for d, k, _, _, s, c, *_ in rows:
            parts.setdefault((d, s, c), set()).add(k)
        several = {x: len(clu) + i for i, x in enumerate(x for x in parts if len(parts[x]) > 1)}
        pieces = []
        for at, (d, _, _, n, s, c, *_) in enumerate(rows):
            bits = (1 << clu[c] if c is not None else 0) | (1 << several[d, s, c] if (d, s, c) in several else 0)
            pieces.append((n, src.get(s, -1), bits, at))
        pieces.sort(key=lambda p: (-p[0], p[1], p[2], p[3]))
        placed = best_fit([p[:3] for p in pieces], capacity, per_source)
        if more:
            along, number_of, filled = sorted(range(len(pieces)), key=lambda i: (rows[pieces[i][3]][6], pieces[i][3])), {}, {}
            for i in along:
                b = number_of.setdefault(placed[i][0], len(number_of))
                placed[i] = b, filled.get(b, 0)
                filled[b] = placed[i][1] + pieces[i][0]
        tokens_in, pieces_in = [0] * (1 + max(b for b, _ in placed)), [0] * (1 + max(b for b, _ in placed))
        for p, (b, _) in zip(pieces, placed, strict=True):
            tokens_in[b] += p[0]
            pieces_in[b] += 1
        out = [(*rows[p[3]][:6], number, b, offset, tokens_in[b], pieces_in[b], *rows[p[3]][6:]) for p, (b, offset) in zip(pieces, placed, strict=True)]
        return pa.table([pa.array(c, type=t) for c, t in zip(zip(*out, strict=True), schema.types, strict=True)], schema=schema)

    def first(pool: pa.Table) -> pa.Table:
        rows = zip(*(pool.column(k).to_pylist() for k in ("doc_id", "n_tokens", "source", "cluster", *more)), strict=True)
        return packed(pool.column("pool")[0].as_py(), [(d, k, start, min(capacity, n - start), s, c, *p) for d, n, s, c, *p in rows for k, start in enumerate(range(0, max(n, 1), capacity))])

    def again(pool: pa.Table) -> pa.Table:
        return packed(pool.column("pool")[0].as_py(), list(zip(*(pool.column(k).to_pylist() for k in ("doc_id", "piece", "piece_start", "n_tokens", "source", "cluster", *more)), strict=True)))

    narrow = df.select(F.col(f"`{id_col}`").cast("long").alias("doc_id"), F.coalesce(tokens, F.lit(0)).cast("long").alias("n_tokens"), F.col(f"`{source}`").cast("string").alias("source"), cluster.cast("long").alias("cluster"), *([] if place is None else [place.cast("long").alias("place")]))
    n_rows = df.select(F.lit(1)).count()
    pools = max(1, -(-n_rows // pool_rows))

    def dealt(n: int) -> Column:
        if place is None:
            return F.pmod(F.xxhash64("doc_id", "n_tokens", "cluster", "source"), F.lit(n)).cast("long")
        return F.least(F.lit(n - 1), F.floor(F.col("place") * n / max(1, n_rows))).cast("long")

    done, turn, parts, low = stored(narrow.withColumn("pool", dealt(pools)).groupBy("pool").applyInArrow(lean_group(first), shape), "packed"), 0, [], F.col("bin_tokens") < (1 - slack) * capacity
    while pools > 1:
        left = done.filter(low).count()
        fewer, turn = -(-left // pool_rows), turn + 1
        if not left or fewer >= pools:
            break
        parts.append(done.filter(~low))
        pool = (F.lit(turn << 40) + dealt(fewer)).cast("long")
        done, pools = stored(done.filter(low).withColumn("pool", pool).groupBy("pool").applyInArrow(lean_group(again), shape), "packed"), fewer
    for p in parts:
        done = done.unionByName(p)
    return done


def write_bins(placed: DataFrame, index: DataFrame) -> DataFrame:
    """Write the ids of each pool's bins to a file; (pool, path, n_bins, n_tokens) of the files.

    ``index`` is of a token store whose documents were packed by their numbers of tokens. A file holds, as little-endian
    unsigned 32-bit numbers, the tokens of one bin after another, behind a table of where each bin starts.
    """
    spark, keys = placed.sparkSession, ("doc_id", "piece", "piece_start", "n_tokens", "pool", "bin", "bin_offset")
    target = folder(spark, "packed-bins")
    docs = token_store.documents(index)
    asked = placed.select(*keys).join(docs.select(F.col("doc_id").alias("held"), "path", "first"), F.col("doc_id").eqNullSafe(F.col("held")))

    def fetch(table: pa.Table) -> pa.Table:
        rows = table.sort_by([("first", "ascending"), ("piece_start", "ascending")])
        codes = token_store.read_file(rows.column("path")[0].as_py())[2]
        ids = [codes.slice(a + s, a + s + n).astype("<u4").tobytes() for a, s, n in zip(*(rows.column(c).to_pylist() for c in ("first", "piece_start", "n_tokens")), strict=True)]
        return pa.table({"pool": rows.column("pool"), "bin": rows.column("bin"), "bin_offset": rows.column("bin_offset"), "ids": pa.array(ids, pa.binary())})

    def save(table: pa.Table) -> pa.Table:
        rows = table.sort_by([("bin", "ascending"), ("bin_offset", "ascending")])
        bins, ids = rows.column("bin").to_numpy(), rows.column("ids").to_pylist()
        sizes = np.bincount(bins, [len(x) // 4 for x in ids]).astype("<u8")
        path = f"{target}/bins-{rows.column('pool')[0].as_py()}.bin"
        fs, name = pafs.FileSystem.from_uri(path)
        fs.create_dir(name.rsplit("/", 1)[0], recursive=True)
        with fs.open_output_stream(name) as f:
            f.write(np.array([len(sizes)], "<u8").tobytes() + np.concatenate([[0], np.cumsum(sizes)]).astype("<u8").tobytes() + b"".join(ids))
        return pa.table({"pool": [rows.column("pool")[0].as_py()], "path": [path], "n_bins": [len(sizes)], "n_tokens": [int(sizes.sum())]})

    read = asked.groupBy("path").applyInArrow(fetch, "pool long, bin int, bin_offset long, ids binary")
    return stored(read.groupBy("pool").applyInArrow(save, "pool long, path string, n_bins long, n_tokens long"), "bin-files")


__all__ = ["best_fit", "pack", "stored", "write_bins"]
