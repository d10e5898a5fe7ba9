"""Removal of repeated strings of ``length`` bytes by suffix arrays over content-defined shards.

A window of ``length`` bytes is known by its anchor: the ``gram`` bytes in it of least hash, the last if they recur. Equal
windows have equal anchors, so shards by anchor hold all copies of a window. Consecutive windows with one anchor form a
stretch of 2 * length - gram bytes at most.

1. Each task lists the stretches of its texts as (document, anchor, stretch hash, start, windows), folds stretches that are
   alike, and ships compressed arrays to shards by anchor: about 20 bytes for 35 of text.
2. A shard keeps the earliest of stretches that are alike and marks the others as repeats in full. Anchors that different
   stretches share may hide windows in common; their stretches are called for.
3. Documents, dealt to buckets by id and met by the calls for them, give the bytes of those stretches, again to shards by anchor.
4. A shard joins its stretches into one text, sorts its suffixes by recursive induction with common prefixes (``suffix_array``), and
   marks in every group that shares ``length`` bytes all windows but the earliest. Shards are larger than the ``memory`` of
   their queues, which go to the shared folder, and groups are marked as the sort yields them.
5. Documents, dealt as before and met by their marks, lose the marked bytes.

Skew: a passage in a third of all documents reaches a shard as one stretch a task. An anchor that many different stretches
share (a sample of documents that grows with the number of shards tells) is not sharded by itself: its stretches are dealt by
their hash in step 2 and all called for, and in step 4 they are cut where a second anchor, by another hash, changes, and
dealt by it. The sample changes the dealing and no result. Shards, buckets and queues are sized by bytes.

Windows are judged on the input, and one is earlier if its document's id is smaller, or in the same document its
start. Defined results: a null text counts as empty; a null id sorts before all ids; rows equal in id and text are one document
and get equal results; rows equal in id alone are ordered by a hash of the text; an empty table gives an empty result;
``clean`` keeps the input's columns; ids must be integers.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mixwright.functions.blocks import by_shard, changes, mix64, rolling_sums, spread_all, squeeze, stretch_hash
from mixwright.functions.storage import TEXT_ROWS
from mixwright.operators.near import integer_ids

from .shared import folder, free_names, lean, lean_cogroup, lean_group, release_memory, stored
from .suffix_array import MEMORY, sorted_suffixes

PIECE = 1 << 19
ROW = ("u8", "u8", "u8", "u8", "u4", "u1")  # document, anchor, stretch, text hash, start, windows
MARK = ("u8", "u8", "u4", "u4")  # document, text hash, first start, windows
CALL = ("u8", "u8", "u8", "u4", "u1")  # document, anchor, text hash, start, windows
FLIP = np.uint64(1 << 63)


def document_key(ids: pa.Array) -> np.ndarray:
    """Ids as unsigned numbers of the same order, nulls first."""
    return ids.fill_null(-(1 << 63)).to_numpy(zero_copy_only=False).astype(np.int64).view(np.uint64) ^ FLIP


def _pieces(texts: list[bytes], length: int) -> Iterator[tuple[np.ndarray, list[tuple[int, int, int]]]]:
    """Bytes to look at together, with (text, offset in it, bytes) of each part; parts of one text overlap by a window less one."""
    held, parts, size = [], [], 0
    for i, t in enumerate(texts):
        for at in range(0, max(1, len(t) - length + 1), PIECE):
            part = t[at : at + PIECE + length - 1]
            if len(part) < length:
                continue
            held.append(part)
            parts.append((i, at, len(part)))
            size += len(part)
            if size >= PIECE:
                yield np.frombuffer(b"".join(held), np.uint8), parts
                held, parts, size = [], [], 0
    if held:
        yield np.frombuffer(b"".join(held), np.uint8), parts


def stretches(texts: list[bytes], length: int = 100, gram: int = 32, turn: int = 0) -> Iterator[tuple[np.ndarray, ...]]:
    """Arrays (text, anchor, stretch hash, start, windows); ``turn`` chooses the hash that makes anchors."""
    low = np.uint64((1 << 24) - 1)
    for raw, parts in _pieces(texts, length):
        sums = rolling_sums(raw)
        n = len(raw)
        grams = stretch_hash(sums, np.arange(n - gram + 1), np.arange(gram, n + 1))
        grams = mix64(grams + np.uint64(turn)) if turn else grams
        best = (grams & ~low) | (low - np.arange(len(grams), dtype=np.uint64))
        width, have = length - gram + 1, 1
        first = best
        while 2 * have <= width:
            best = np.minimum(best[:-have], best[have:])
            have *= 2
        if have < width:
            best = np.minimum(best[: len(first) - width + 1], best[width - have : len(first) - width + 1 + width - have])
        where = (low - (best & low)).astype(np.int64)
        sizes = np.array([p[2] for p in parts])
        begin = np.cumsum(sizes) - sizes
        ok = np.zeros(n - length + 2, np.int32)
        np.add.at(ok, begin, 1)
        np.add.at(ok, begin + sizes - length + 1, -1)
        at = np.flatnonzero(np.cumsum(ok)[:-1] > 0)
        part = np.searchsorted(begin, at, "right") - 1
        head = np.flatnonzero(changes((where[at], part)))
        start, count = at[head], np.diff(np.append(head, len(at)))
        part = part[head]
        text, offset = np.array([p[0] for p in parts])[part], np.array([p[1] for p in parts])[part]
        yield text, grams[where[start]], stretch_hash(sums, start, start + count + length - 1), (start - begin[part] + offset).astype(np.uint32), count.astype(np.uint8)


def _earliest(rows: tuple[np.ndarray, ...]) -> tuple[tuple[np.ndarray, ...], np.ndarray, np.ndarray]:
    """Rows (document, anchor, stretch, text, start, windows) sorted by stretch and place; which open a class; which are the same place as the row before."""
    doc, anchor, stretch, text, start, count = rows
    order = np.lexsort((start, text, doc, count, stretch, anchor))
    rows = tuple(r[order] for r in rows)
    opens = changes((rows[1], rows[2], rows[5]))
    twin = ~changes((rows[0], rows[3], rows[4], rows[1], rows[2])) & ~opens
    return rows, opens, twin


def _joined_marks(doc: np.ndarray, text: np.ndarray, start: np.ndarray, count: np.ndarray) -> tuple[np.ndarray, ...]:
    """Marks in order, with those that touch or overlap made one."""
    order = np.lexsort((start, text, doc))
    doc, text, start, stop = doc[order], text[order], start[order].astype(np.int64), (start[order].astype(np.int64) + count[order])
    if not len(doc):
        return doc, text, start.astype(np.uint32), start.astype(np.uint32)
    own = changes((doc, text))
    group = np.cumsum(own) - 1
    shift = group * (np.int64(1) << 33)
    reach = np.maximum.accumulate(stop + shift) - shift
    opens = own.copy()
    opens[1:] |= start[1:] > reach[:-1]
    at = np.flatnonzero(opens)
    return doc[at], text[at], start[at].astype(np.uint32), (np.maximum.reduceat(stop, at) - start[at]).astype(np.uint32)


def _hot_anchors(drawn: DataFrame, length: int, gram: int, docs: int, shards: int) -> np.ndarray:
    """Anchors of more than a hundredth of a sample's documents, or of a quarter of a shard's part of its stretches; at most 4 a shard reach the driver."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(0, b.num_rows, 512):
                seen = [s[1] for s in stretches(b.column(0).slice(i, 512).to_pylist(), length, gram)]
                h, n = np.unique(np.concatenate(seen), return_counts=True) if seen else (np.zeros(0, "u8"), np.zeros(0, "i8"))
                yield pa.RecordBatch.from_arrays([pa.array(h.view("i8")), pa.array(n, pa.int64())], names=["h", "n"])

    counts = stored(drawn.mapInArrow(lean(run), "h long, n long").groupBy("h").agg(F.sum("n").alias("n")), "suffix-sample", TEXT_ROWS)
    total = counts.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    least = max(8, min(0.01 * docs, 0.25 * total / shards))
    return np.sort(np.array([r[0] for r in counts.filter(F.col("n") > least).select("h").collect()], "i8").view("u8"))


def repeat_marks(df: DataFrame, id_col: str = "doc_id", text: str = "text", length: int = 100, gram: int = 32, shard_bytes: int = 8 << 20, sort_bytes: int = 2 << 20, hot_sample: int = 2000, memory: int = MEMORY) -> tuple[DataFrame, int]:
    """(bucket, block) of marked windows, dealt by document to the returned number of buckets; see ``MARK``."""
    integer_ids(df, id_col)
    spark = df.sparkSession
    body = F.encode(F.coalesce(F.col(text), F.lit("")), "UTF-8")
    docs = df.select(F.col(f"`{id_col}`").cast("long").alias("id"), F.xxhash64(body).alias("hash"), body.alias("body"))
    n_docs, size = df.agg(F.count("*"), F.coalesce(F.sum(F.octet_length(text)), F.lit(0))).first()
    shards = buckets = max(1, -(-int(size) // shard_bytes))
    wanted = max(1, hot_sample, shards)
    hot = _hot_anchors(docs.filter(F.pmod("hash", F.lit(max(1, n_docs // wanted))) == 0).select("body"), length, gram, min(n_docs, wanted), shards)
    scratch = folder(spark, "suffix-queues")

    def rows_out(rows: list) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.string()), pa.array([r[1] for r in rows], pa.int32()), pa.array([r[2] for r in rows], pa.int64()), pa.array([r[3] for r in rows], pa.binary())], names=["kind", "place", "amount", "block"])

    def mark_rows(doc: np.ndarray, text_hash: np.ndarray, start: np.ndarray, count: np.ndarray) -> list:
        marks = _joined_marks(doc, text_hash, start, count)
        return [("mark", b, len(at), squeeze(tuple(m[at] for m in marks))) for b, at in by_shard(mix64(marks[0]) % np.uint64(buckets), buckets)]

    def listed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, waiting = [], 0

        def flush() -> pa.RecordBatch:
            joined = tuple(np.concatenate([h[i] for h in held]) for i in range(6))
            held.clear()
            rows, opens, twin = _earliest(joined)
            del joined
            again = ~opens & ~twin
            out = mark_rows(rows[0][again], rows[3][again], rows[4][again], rows[5][again])
            rows = tuple(r[opens] for r in rows)
            order = np.lexsort((rows[4], rows[3], rows[0]))
            rows = tuple(r[order] for r in rows)
            release_memory()
            place = mix64(np.where(np.isin(rows[1], hot), rows[2], rows[1])) % np.uint64(shards)
            out += [("list", s, len(at), squeeze(tuple(r[at] for r in rows))) for s, at in by_shard(place, shards)]
            return rows_out(out)

        for b in batches:
            for i in range(0, b.num_rows, 1024):
                piece = b.slice(i, 1024)
                doc, hashed = document_key(piece.column(0)), piece.column(1).to_numpy().view(np.uint64)
                for t, anchor, stretch, start, count in stretches(piece.column(2).to_pylist(), length, gram):
                    held.append((doc[t], anchor, stretch, hashed[t], start, count))
                    waiting += len(t)
                    if waiting > 400_000:
                        yield flush()
                        waiting = 0
        if held:
            yield flush()

    def matched(table: pa.Table) -> pa.Table:
        rows, opens, twin = _earliest(spread_all(table.column("block").to_pylist(), ROW))
        again = ~opens & ~twin
        out = mark_rows(rows[0][again], rows[3][again], rows[4][again], rows[5][again])
        rows = tuple(r[opens] for r in rows)
        heads = np.flatnonzero(changes((rows[1],)))
        alike = np.repeat(np.diff(np.append(heads, len(rows[1]))), np.diff(np.append(heads, len(rows[1]))))
        want = (alike > 1) | np.isin(rows[1], hot)
        doc, anchor, _, hashed, start, count = (r[want] for r in rows)
        order = np.lexsort((start, hashed, doc))
        call = tuple(r[order] for r in (doc, anchor, hashed, start, count))
        for b, at in by_shard(mix64(call[0]) % np.uint64(buckets), buckets):
            out.append(("call", b, int((call[4][at].astype(np.int64) + length - 1).sum()), squeeze(tuple(c[at] for c in call))))
        release_memory()
        return pa.Table.from_batches([rows_out(out)])

    shape = "kind string, place int, amount long, block binary"
    first = stored(docs.mapInArrow(lean(listed), shape), "suffix-lists", TEXT_ROWS)
    second = stored(first.filter("kind = 'list'").groupBy("place").applyInArrow(lean_group(matched), shape), "suffix-calls")
    called = second.filter("kind = 'call'")
    sorts = max(1, -(-int(called.agg(F.coalesce(F.sum("amount"), F.lit(0))).first()[0]) // sort_bytes))

    def fetched(key: tuple, texts: pa.Table, calls: pa.Table) -> pa.Table:
        doc, anchor, hashed, start, count = spread_all(calls.column("block").to_pylist(), CALL)
        out = []
        if len(doc) and texts.num_rows:
            known = {k: i for i, k in enumerate(zip(document_key(texts.column("id").combine_chunks()).tolist(), texts.column("hash").to_numpy().view(np.uint64).tolist(), strict=True))}
            bodies = texts.column("body").to_pylist()
            is_hot = np.isin(anchor, hot)
            pieces = [bodies[known[d, h]][x : x + c + length - 1] for d, h, x, c in zip(doc.tolist(), hashed.tolist(), start.tolist(), count.astype(np.int64).tolist(), strict=True)]
            whole = np.flatnonzero(~is_hot)
            rows = [[doc[whole], anchor[whole], hashed[whole], start[whole], count[whole]]]
            cut = [pieces[i] for i in whole]
            many = np.flatnonzero(is_hot)
            for t, second, _, at, n in stretches([pieces[i] for i in many], length, gram, 1):
                own = many[t]
                rows.append([doc[own], mix64(anchor[own] ^ second), hashed[own], start[own] + at, n])
                cut += [pieces[i][a : a + w + length - 1] for i, a, w in zip(own.tolist(), at.tolist(), n.astype(np.int64).tolist(), strict=True)]
            columns = [np.concatenate([r[k] for r in rows]).astype(CALL[k]) for k in range(5)]
            for p, at in by_shard(mix64(columns[1]) % np.uint64(sorts), sorts):
                at = at[np.lexsort((columns[3][at], columns[2][at], columns[0][at]))]
                out.append((p, squeeze(tuple(c[at] for c in columns)), squeeze_bytes([cut[i] for i in at.tolist()])))
        release_memory()
        return pa.table({"place": pa.array([r[0] for r in out], pa.int32()), "block": pa.array([r[1] for r in out], pa.binary()), "bytes": pa.array([r[2] for r in out], pa.binary())})

    def sorted_marks(table: pa.Table) -> pa.Table:
        doc, _, hashed, start, count = spread_all(table.column("block").to_pylist(), CALL)
        raw = b"".join(spread_bytes(x) for x in table.column("bytes").to_pylist())
        begin = np.cumsum(count.astype(np.int64) + length - 1) - (count.astype(np.int64) + length - 1)
        out = []
        # A stretch holds its windows in full, so what follows it in the joined text decides nothing.
        for place, lcp in sorted_suffixes(np.frombuffer(raw, np.uint8), length, memory, scratch):
            which = np.searchsorted(begin, place, "right") - 1
            mine = place - begin[which] < count[which]
            group, place, which = np.cumsum(lcp < length)[mine], place[mine], which[mine]
            d, h, s = doc[which], hashed[which], start[which] + (place - begin[which]).astype(np.uint32)
            order = np.lexsort((s, h, d, group))
            again = ~changes((group[order],)) & changes((d[order], h[order], s[order]))
            out.append(tuple(x[order[again]] for x in (d, h, s)))
        d, h, s = (np.concatenate([o[k] for o in out]) for k in range(3))
        found = mark_rows(d, h, s, np.ones(len(d), np.uint32))
        release_memory()
        return pa.Table.from_batches([rows_out(found)])

    dealt = F.col("id")
    bucket_of = _bucket_udf(buckets)
    texts = docs.withColumn("place", bucket_of(dealt))
    stretched = texts.groupBy("place").cogroup(called.select("place", "block").groupBy("place")).applyInArrow(lean_cogroup(fetched), "place int, block binary, bytes binary")
    third = stored(stretched.groupBy("place").applyInArrow(lean_group(sorted_marks), shape), "suffix-marks", TEXT_ROWS)
    marks = first.filter("kind = 'mark'").unionByName(second.filter("kind = 'mark'")).unionByName(third).select("place", "block")
    return marks, buckets


def squeeze_bytes(parts: list[bytes]) -> bytes:
    return zstandard.ZstdCompressor(level=1).compress(b"".join(parts))


def spread_bytes(blob: bytes) -> bytes:
    return zstandard.ZstdDecompressor().decompress(blob)


def _bucket_udf(buckets: int):
    @F.pandas_udf("int")
    def place(ids: pd.Series) -> pd.Series:
        keys = document_key(pa.Array.from_pandas(ids, type=pa.int64()))
        return pd.Series((mix64(keys) % np.uint64(buckets)).astype(np.int32))

    return place


def cut_spans(marks: list[tuple[int, int]], length: int) -> list[tuple[int, int]]:
    """Maximal removed runs (start, stop) from (first start, windows) in order."""
    out: list[tuple[int, int]] = []
    for start, count in marks:
        stop = start + count + length - 1
        if out and start <= out[-1][1]:
            out[-1] = (out[-1][0], max(stop, out[-1][1]))
        else:
            out.append((start, stop))
    return out


def removals(df: DataFrame, id_col: str = "doc_id", text: str = "text", length: int = 100, whole_chars: bool = False, **options) -> tuple[DataFrame, str, str]:
    """The input's rows with ``text`` as the kept bytes, and the names of two columns more: bytes of the text before, and
    starts and ends of what is removed. With ``whole_chars`` a character that a cut splits goes whole.
    """
    marks, buckets = repeat_marks(df, id_col, text, length, **options)
    names = [*df.columns]
    place, hashed, key, n_bytes, spans_in = free_names(df, "_x_place", "_x_hash", "_x_id", "_x_n_bytes", "_x_spans")
    body = F.encode(F.coalesce(F.col(text), F.lit("")), "UTF-8")
    docs = df.withColumn(key, F.col(f"`{id_col}`").cast("long")).withColumn(hashed, F.xxhash64(body)).withColumn(text, body).withColumn(place, _bucket_udf(buckets)(F.col(key)))
    shape = docs.drop(place, hashed, key).withColumns({n_bytes: F.lit(0).cast("long"), spans_in: F.lit(None).cast("array<bigint>")}).schema

    def cut(_: tuple, rows: pa.Table, blocks: pa.Table) -> pa.Table:
        by_doc: dict[tuple[int, int], list[tuple[int, int]]] = {}
        for d, h, s, c in zip(*(x.tolist() for x in _joined_marks(*spread_all(blocks.column("block").to_pylist(), MARK))), strict=True):
            by_doc.setdefault((d, h), []).append((s, c))
        keys = document_key(rows.column(key).combine_chunks()).tolist() if rows.num_rows else []
        hashes = rows.column(hashed).to_numpy().view(np.uint64).tolist() if rows.num_rows else []
        kept, sizes, spans = [], [], []
        for k, h, t in zip(keys, hashes, rows.column(text).to_pylist(), strict=True):
            found = cut_spans(by_doc.get((k, h), []), length)
            at, left = 0, []
            for a, b in found:
                left.append(t[at:a])
                at = b
            rest_of = b"".join([*left, t[at:]]) if found else t
            kept.append(rest_of.decode("utf-8", "ignore").encode() if whole_chars and found else rest_of)
            sizes.append(len(t))
            spans.append([x for span in found for x in span])
        release_memory()
        rest = {n: rows.column(n) for n in names}
        rest[text] = pa.array(kept, pa.binary())
        return pa.table({**rest, n_bytes: pa.array(sizes, pa.int64()), spans_in: pa.array(spans, pa.list_(pa.int64()))})

    return docs.groupBy(place).cogroup(marks.withColumnRenamed("place", place).groupBy(place)).applyInArrow(lean_cogroup(cut), shape), n_bytes, spans_in


def digests(df: DataFrame, id_col: str = "doc_id", text: str = "text", length: int = 100, **options) -> DataFrame:
    """(id, n_bytes, n_removed, n_spans, kept_sha256)."""
    out, n_bytes, spans = removals(df.select(id_col, text), id_col, text, length, **options)
    return out.select(
        id_col,
        F.col(n_bytes).alias("n_bytes"),
        (F.col(n_bytes) - F.octet_length(text)).cast("long").alias("n_removed"),
        (F.size(spans) / 2).cast("long").alias("n_spans"),
        F.sha2(text, 256).alias("kept_sha256"),
    )


def clean(df: DataFrame, id_col: str = "doc_id", text: str = "text", chars: str | None = "n_chars", length: int = 100, **options) -> DataFrame:
    """The input with repeated strings cut out of its texts, and ``chars`` counted anew. A character that a cut splits goes whole."""
    out, *own = removals(df, id_col, text, length, whole_chars=True, **options)
    out = out.withColumn(text, F.col(text).cast("string")).drop(*own)
    return out.withColumn(chars, F.length(text).cast(df.schema[chars].dataType)) if chars and chars in df.columns else out
