"""Token ids in directly addressable codes, with random access to any token.

An id is split into chunks of 8 bits, lowest first. Level 0 holds the first chunk of every id and a bitmap that tells
which ids go on; level 1 holds the second chunks of those that do, and so on. A rank directory (ones before every 512th
bit) turns a position in one level into that in the next, so token i is read with one byte and one rank a level.

Texts are encoded where they are read; only ids, compressed, are shuffled, to ranges of (id, hash of the text) of about
``file_bytes`` of text, so rows of one id may fill many files. Each range is sorted and written as one file in the shared folder,
named afresh by each attempt, so a task that runs twice leaves an unused file and nothing else. Boundaries are quantiles of a
size-weighted sample of ``oversample`` keys a file; files are at most ``most_files``, as they grow with the corpus beyond
that, and so is what reaches the driver. Single tokens are read by ranges of a file: one byte, one block of the bitmap
and one rank a level.

Encoding works on words between ASCII white space, which no tokenizer of this kind joins, and keeps a bounded dictionary of
words met before, in two halves of which the older is left behind; a test compares it with encoding whole texts. Words of Latin letters,
and what stands before their closing marks, go straight to the vocabulary model only
where the tokenizer's own rules say that its normaliser does no more to them than lower their case and compose them.

Defined results: a null text counts as empty and gives the end id alone; a null id sorts first; rows that repeat an id
are all written, next to each other, by hash of text; an empty table gives an empty result; other columns of the input are ignored; ids must
be integers.
"""

from __future__ import annotations

import json
import re
import struct
import sys
import uuid
import zlib
from array import array
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
import zstandard
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from mixwright.operators.near import integer_ids

from .shared import folder, stored
from .sharding import locate

MAGIC = b"DAC1"
BLOCK = 512
LEAST = -(1 << 63)
CACHE_WORDS = 500_000
CACHE_MARKS = 10_000
_loaded: dict = {}


LETTERS = re.compile(r"[A-Za-zÀ-ÖØ-öø-ÿ]+")
MARKS = bytes(c for c in range(33, 127) if not chr(c).isalnum())
PROBES = ("word", "Word", "WORD", "été", "ÉTÉ", "straße", "a", "é", "unbelievable", "ñandúes", "word.", "Mot,", "été.", "word'", "word$$$", "mot.%%%", "Été,&&&", "a_", "b<|", "c!?\"")


def _plain_rules(rules: dict) -> bool:
    """Whether a word of Latin letters, composed and in lower case, comes out of normaliser and splitter as one piece in visible bytes."""
    steps = lambda part, kind: [] if not part else part[kind] if part["type"] == "Sequence" else [part]
    normal, split = steps(rules["normalizer"], "normalizers"), steps(rules["pre_tokenizer"], "pretokenizers")
    space = lambda x: x["type"] == "Replace" and x["pattern"] == {"Regex": r"\s+"}
    letters = lambda x: x["type"] == "Split" and r"[\p{L}]+" in x["pattern"].get("Regex", "").split("|")
    fine = all(x["type"] in ("NFC", "Lowercase") or space(x) for x in normal) and any(x["type"] == "Lowercase" for x in normal)
    return fine and bool(split) and split[-1]["type"] == "ByteLevel" and not split[-1]["add_prefix_space"] and all(letters(x) for x in split[:-1])


class _Words(dict):
    """Ids by word; a word that is not there yet is asked from ``make``."""

    def __init__(self, make: Callable[[bytes], bytes]):
        self.make = make

    def __missing__(self, word: bytes) -> bytes:
        got = self[word] = self.make(word)
        return got


class WordEncoder:
    """Ids of a text as little-endian bytes of ``dtype``, by a dictionary of words.

    A word of Latin letters alone, or with ASCII marks behind, goes straight to the vocabulary model, past
    normaliser and splitter, if this tokenizer's rules allow it and the probe words get the same ids either way; other words take the whole way.
    """

    def __init__(self, path: str, end_id: int):
        from tokenizers import Tokenizer, pre_tokenizers

        self.tokenizer = Tokenizer.from_file(path)
        self.dtype = np.dtype("<u2" if self.tokenizer.get_vocab_size(with_added_tokens=True) <= 1 << 16 and end_id < 1 << 16 else "<u4")
        self.code = "H" if self.dtype.itemsize == 2 else "I"
        self.end = self._bytes([end_id])
        self.known, self.before = _Words(self._new), {}
        self.tokenize, n = self.tokenizer.model.tokenize, self.dtype.itemsize
        every = np.arange(1 + max(self.tokenizer.get_vocab(with_added_tokens=True).values(), default=0)).astype(self.dtype).tobytes()
        self.pieces = [every[i : i + n] for i in range(0, len(every), n)]
        visible = pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)
        self.letters = {ord(c): visible.pre_tokenize_str(c)[0][0] for c in map(chr, range(0x41, 0x100)) if LETTERS.fullmatch(c)}
        self.marks: dict[bytes, bytes] = {}
        self.direct, self.caseless = True, self._case_is_lost()
        self.direct = _plain_rules(json.loads(self.tokenizer.to_str())) and all(self._straight(w.encode()) == self._bytes(self.tokenizer.encode(w, add_special_tokens=False).ids) for w in PROBES)
        self.known.clear()

    @classmethod
    def shared(cls, path: str, end_id: int) -> WordEncoder:
        """One per worker process."""
        if (path, end_id) not in _loaded:
            _loaded[path, end_id] = cls(path, end_id)
        return _loaded[path, end_id]

    def _bytes(self, ids: list[int]) -> bytes:
        if sys.byteorder == "little":
            return array(self.code, ids).tobytes()
        return np.array(ids, dtype=self.dtype).tobytes()

    def _case_is_lost(self) -> bool:
        """Whether A-Z and a-z are one to this tokenizer, so that both may share a dictionary entry."""
        ids = lambda t: self.tokenizer.encode(t, add_special_tokens=False).ids
        upper = "".join(map(chr, range(65, 91)))
        return all(ids(w) == ids(w.lower()) for w in (*upper, upper, *PROBES))

    def _straight(self, word: bytes) -> bytes | None:
        """A word with marks behind is its letters' ids, which are remembered too, and the marks'."""
        if not self.direct:
            return None
        letters = word.rstrip(MARKS)
        if letters.isalpha():  # ASCII alone
            text = letters.lower().decode()
        elif LETTERS.fullmatch(text := letters.decode("utf-8", "replace")):
            text = text.lower().translate(self.letters)
        else:
            return None
        if len(letters) == len(word):
            return b"".join([self.pieces[t.id] for t in self.tokenize(text)])
        if (tail := self.marks.get(end := word[len(letters) :])) is None:
            if len(self.marks) > CACHE_MARKS:
                self.marks.clear()
            tail = self.marks[end] = self._whole(end)
        got = self.known.get(letters) or self.before.get(letters) or b"".join([self.pieces[t.id] for t in self.tokenize(text)])
        self.known[letters] = got
        return got + tail

    def _whole(self, word: bytes) -> bytes:
        return self._bytes(self.tokenizer.encode(word.decode("utf-8", "replace"), add_special_tokens=False).ids)

    def _new(self, word: bytes) -> bytes:
        """Ids of a word that is not among those met lately."""
        for find in (self.before.get, self._straight, self._whole):
            if (got := find(word)) is not None:
                return got

    def encode(self, texts: list[bytes]) -> Iterator[bytes]:
        for at in range(0, len(texts), 256):
            if len(self.known) > CACHE_WORDS // 2:
                self.before, self.known = self.known, _Words(self._new)  # a word that comes again is taken from the half before
            look = self.known.__getitem__
            for t in texts[at : at + 256]:
                # A text that might spell a special token keeps its case.
                yield b"".join(map(look, (t.lower() if self.caseless and b"<|" not in t else t).split())) + self.end


def pack_codes(values: np.ndarray) -> bytes:
    """The levels of an array of unsigned ids: per level its length, chunks, bitmap words and rank directory."""
    out, rest = [], values.astype(np.uint64)
    while True:
        more = rest >> np.uint64(8)
        on = more > 0
        bits = np.packbits(on, bitorder="little")
        bits = np.concatenate([bits, np.zeros(-len(bits) % (BLOCK // 8), np.uint8)])
        ones = np.bitwise_count(bits.view(np.uint64)).reshape(-1, BLOCK // 64).sum(axis=1, dtype=np.uint64)
        ranks = np.concatenate([[0], np.cumsum(ones)]).astype("<u8")
        out += [struct.pack("<QQ", len(rest), len(ranks)), (rest & np.uint64(255)).astype(np.uint8).tobytes(), bits.tobytes(), ranks.tobytes()]
        if not on.any():
            return struct.pack("<I", len(out) // 4) + b"".join(out)
        rest = more[on]


class Codes:
    """Read access to packed levels over any bytes-like object, a memory map included."""

    def __init__(self, data):
        (levels,) = struct.unpack_from("<I", data, 0)
        at, self.levels = 4, []
        for _ in range(levels):
            n, m = struct.unpack_from("<QQ", data, at)
            at += 16
            n_bits = (m - 1) * BLOCK // 8
            chunks = np.frombuffer(data, np.uint8, n, at)
            bits = np.frombuffer(data, np.uint8, n_bits, at + n)
            ranks = np.frombuffer(data, "<u8", m, at + n + n_bits)
            self.levels.append((chunks, bits, ranks))
            at += n + n_bits + 8 * m

    def __len__(self) -> int:
        return len(self.levels[0][0])

    def __getitem__(self, i: int) -> int:
        """Token i, by one rank a level."""
        if not 0 <= i < len(self):
            raise IndexError(i)
        value = shift = 0
        for chunks, bits, ranks in self.levels:
            value |= int(chunks[i]) << shift
            if not bits[i >> 3] >> (i & 7) & 1:
                return value
            block = i // BLOCK
            inside = bits[block * BLOCK // 8 : (i >> 3) + 1].copy()
            inside[-1] &= (1 << (i & 7)) - 1
            i = int(ranks[block]) + int(np.bitwise_count(inside).sum())
            shift += 8
        return value

    def slice(self, start: int, stop: int) -> np.ndarray:
        """Tokens start to stop, unpacked together."""
        out, rows, shift = np.zeros(stop - start, np.uint32), np.arange(stop - start), 0
        for chunks, bits, ranks in self.levels:
            if start == stop:
                break
            out[rows] |= chunks[start:stop].astype(np.uint32) << np.uint32(shift)
            on = np.unpackbits(bits[start >> 3 : (stop + 7) >> 3], bitorder="little")[start & 7 :][: stop - start].astype(bool)
            rows = rows[on]
            block = start // BLOCK
            inside = np.unpackbits(bits[block * BLOCK // 8 : (start + 7) >> 3], bitorder="little")[: start - block * BLOCK]
            start = int(ranks[block]) + int(inside.sum())
            stop = start + int(on.sum())
            shift += 8
        return out


def write_file(path: str, ids: list, offsets: np.ndarray, values: np.ndarray) -> None:
    """Header, record ids (with a bitmap of nulls), token offsets, levels."""
    null = np.packbits([i is None for i in ids], bitorder="little").tobytes()
    numbers = np.array([0 if i is None else i for i in ids], dtype="<i8")
    fs, name = pafs.FileSystem.from_uri(path)
    fs.create_dir(name.rsplit("/", 1)[0], recursive=True)
    with fs.open_output_stream(name) as f:
        f.write(MAGIC + struct.pack("<QQ", len(ids), len(null)) + null + numbers.tobytes() + offsets.astype("<u8").tobytes() + pack_codes(values))


def read_file(path: str) -> tuple[list, np.ndarray, Codes]:
    fs, name = pafs.FileSystem.from_uri(path)
    with fs.open_input_file(name) as f:
        data = f.read()
    if data[:4] != MAGIC:
        raise ValueError(f"{path} is not a token file")
    n, n_null = struct.unpack_from("<QQ", data, 4)
    at = 20
    null = np.unpackbits(np.frombuffer(data, np.uint8, n_null, at), bitorder="little")
    ids = np.frombuffer(data, "<i8", n, at + n_null)
    at += n_null + 8 * n
    offsets = np.frombuffer(data, "<u8", n + 1, at).astype(np.int64)
    return [None if x else int(i) for i, x in zip(ids, null, strict=False)], offsets, Codes(memoryview(data)[at + 8 * (n + 1) :])


def write_tokens(df: DataFrame, tokenizer: str, end_id: int = 1, id_col: str = "doc_id", text: str = "text", file_bytes: int = 8 << 20, oversample: int = 16, most_files: int = 1 << 16) -> DataFrame:
    """Encode and write; returns the stored index (part, path, n_docs, n_tokens, start)."""
    integer_ids(df, id_col)
    spark = df.sparkSession
    body = F.encode(F.coalesce(F.col(text), F.lit("")), "UTF-8")
    keys = df.select(F.coalesce(F.col(f"`{id_col}`").cast("long"), F.lit(LEAST)).alias("id"), F.xxhash64(body).alias("hash"), (F.octet_length(body) + 16).alias("size"))
    (total,) = df.agg(F.sum(F.coalesce(F.octet_length(text), F.lit(0)) + 16)).first()
    parts = min(most_files, max(1, -(-int(total or 0) // file_bytes)))
    coin = F.shiftrightunsigned(F.xxhash64("id", "hash", F.lit("files")), 11) / F.lit(float(1 << 53))
    drawn = sorted((r[0], r[1]) for r in keys.filter(coin * F.lit(float(total or 1)) < F.col("size") * float(parts * oversample)).select("id", "hash").collect()) if parts > 1 else []
    cuts = sorted({drawn[len(drawn) * i // parts] for i in range(1, parts)}) if drawn else []
    cut_ids, cut_hashes = np.array([c[0] for c in cuts], np.int64), np.array([c[1] for c in cuts], np.int64)
    target = folder(spark, "token-files")

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder, squeeze = WordEncoder.shared(tokenizer, end_id), zstandard.ZstdCompressor(level=1)
        for batch in batches:
            for at in range(0, batch.num_rows, 1024):
                piece = batch.slice(at, 1024)
                numbers = piece.column(0).fill_null(LEAST).to_numpy(zero_copy_only=False).astype(np.int64)
                part = locate(cut_ids, cut_hashes, numbers, piece.column(1).to_numpy(zero_copy_only=False))
                rows = [squeeze.compress(x) for x in coder.encode(piece.column(2).to_pylist())]
                yield pa.RecordBatch.from_arrays([pa.array(part.astype(np.int32)), piece.column(0), piece.column(1), pa.array(rows, pa.binary())], names=["part", "id", "hash", "ids"])

    def save(table: pa.Table) -> pa.Table:
        coder, spread = WordEncoder.shared(tokenizer, end_id), zstandard.ZstdDecompressor()
        keys, hashes, blobs = (table.column(c).to_pylist() for c in ("id", "hash", "ids"))
        order = sorted(range(len(keys)), key=lambda i: (keys[i] is not None, keys[i] or 0, hashes[i], blobs[i]))
        raw = [spread.decompress(blobs[i]) for i in order]
        offsets = np.concatenate([[0], np.cumsum([len(x) // coder.dtype.itemsize for x in raw])])
        part = table.column("part")[0].as_py()
        path = f"{target}/tokens-{part:07d}-{uuid.uuid4().hex}.dac"
        write_file(path, [keys[i] for i in order], offsets, np.frombuffer(b"".join(raw), coder.dtype))
        return pa.table({"part": pa.array([part], pa.int32()), "path": [path], "n_docs": [len(keys)], "n_tokens": [int(offsets[-1])]})

    coded = df.select(F.col(f"`{id_col}`").cast("long").alias("id"), F.xxhash64(body).alias("hash"), body.alias("text")).mapInArrow(encode, "part int, id long, hash long, ids binary")
    index = stored(coded.groupBy("part").applyInArrow(save, "part int, path string, n_docs long, n_tokens long"), "token-index")
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)  # a row per file
    return stored(index.withColumn("start", F.coalesce(F.sum("n_tokens").over(before), F.lit(0)).cast("long")), "token-index")


def _of_files(index: DataFrame, shape: str, rows) -> DataFrame:
    """``rows`` of (path, start) of each file, files spread over tasks."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for path, start in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                yield rows(path, start)

    files = index.select("path", "start")
    return files.repartition(min(1 + index.count(), 4096)).mapInArrow(read, shape)  # a number keeps a few small rows from being put into one task


def file_digests(path: str, start: int) -> pa.RecordBatch:
    """The digests of a file's documents; its levels are unpacked once."""
    ids, offsets, codes = read_file(path)
    tokens = memoryview(codes.slice(0, len(codes)).astype("<u4", copy=False)).cast("B")
    crc = [zlib.crc32(tokens[4 * a : 4 * b]) for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True)]
    return pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(offsets[:-1] + start), pa.array(np.diff(offsets)), pa.array(crc, pa.int64())], names=["doc_id", "start", "n_tokens", "ids_crc32"])


def read_digests(index: DataFrame) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) read from the files."""
    return _of_files(index, "doc_id long, start long, n_tokens long, ids_crc32 long", file_digests)


def documents(index: DataFrame) -> DataFrame:
    """(doc_id, path, first, n_tokens): each document's file and the place of its first token in it."""

    def rows(path: str, start: int) -> pa.RecordBatch:
        ids, offsets, _ = read_file(path)
        return pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array([path] * len(ids), pa.string()), pa.array(offsets[:-1]), pa.array(np.diff(offsets))], names=["doc_id", "path", "first", "n_tokens"])

    return _of_files(index, "doc_id long, path string, first long, n_tokens long", rows)


class TokenFile:
    """Single tokens of a file by ranged reads; ``taken`` counts the bytes read."""

    def __init__(self, path: str):
        fs, name = pafs.FileSystem.from_uri(path)
        self.file, self.taken = fs.open_input_file(name), 0
        if self._read(0, 4) != MAGIC:
            raise ValueError(f"{path} is not a token file")
        n, n_null = struct.unpack("<QQ", self._read(4, 16))
        at = 20 + n_null + 8 * n + 8 * (n + 1)
        (levels,) = struct.unpack("<I", self._read(at, 4))
        at, self.levels = at + 4, []
        for _ in range(levels):
            size, ranks = struct.unpack("<QQ", self._read(at, 16))
            at += 16
            bits = (ranks - 1) * BLOCK // 8
            self.levels.append((size, at, at + size, at + size + bits))
            at += size + bits + 8 * ranks

    def _read(self, at: int, n: int) -> bytes:
        self.taken += n
        return self.file.read_at(n, at)

    def __len__(self) -> int:
        return self.levels[0][0]

    def __getitem__(self, i: int) -> int:
        if not 0 <= i < len(self):
            raise IndexError(i)
        value = shift = 0
        for _, chunks, bits, ranks in self.levels:
            value |= self._read(chunks + i, 1)[0] << shift
            block = i // BLOCK
            start = block * BLOCK // 8
            inside = bytearray(self._read(bits + start, (i >> 3) + 1 - start))
            if not inside[-1] >> (i & 7) & 1:
                return value
            inside[-1] &= (1 << (i & 7)) - 1
            i = struct.unpack("<Q", self._read(ranks + 8 * block, 8))[0] + int.from_bytes(inside, "little").bit_count()
            shift += 8
        return value


def token_at(index: DataFrame, position: int) -> int:
    """The token at a global position, by its file's rank directory and a few short reads."""
    row = index.filter((F.col("start") <= position) & (F.col("start") + F.col("n_tokens") > position)).first()
    if row is None:
        raise IndexError(position)
    return TokenFile(row["path"])[position - row["start"]]
