"""Files of sorted hash arrays: written once, memory-mapped, searched without being loaded.

An array holds distinct 64-bit hashes in order, each with whole numbers. The leading bits of a hash are its place in a directory,
the 32 bits behind them are stored, so a hash costs four bytes and a bit; two hashes are told apart by about 50 bits. A
number takes one byte, and from 255 on a place in a sorted list of large values of 64 bits.
"""

from __future__ import annotations

import struct
import uuid
from collections import OrderedDict

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs

TOP = 255


def pack(keys: np.ndarray, columns: tuple[np.ndarray, ...] | list[np.ndarray]) -> bytes:
    """An array from sorted hashes and their numbers."""
    n = len(keys)
    bits = max(0, (n // 16).bit_length())
    bucket = (keys >> np.uint64(64 - bits)).astype(np.int64) if bits else np.zeros(n, np.int64)
    directory = np.searchsorted(bucket, np.arange((1 << bits) + 1)).astype("<u4")
    deepest = int(np.diff(directory).max())
    low = (keys >> np.uint64(32 - bits) & np.uint64(0xFFFFFFFF)).astype("<u4")
    out = [struct.pack("<QHHI", n, bits, len(columns), deepest), directory.tobytes(), low.tobytes()]
    for c in columns:
        large = np.flatnonzero(c >= TOP)
        out += [struct.pack("<Q", len(large)), large.astype("<u4").tobytes(), c[large].astype("<u8").tobytes(), np.minimum(c, TOP).astype("u1").tobytes()]
    return b"".join(out)


class HashArray:
    def __init__(self, raw: np.ndarray, at: int):
        take = lambda kind, n: raw[at : at + n * np.dtype(kind).itemsize].view(kind)
        n, self.bits, columns, self.deepest = struct.unpack("<QHHI", raw[at : at + 16].tobytes())
        at += 16
        self.directory = take("<u4", (1 << self.bits) + 1)
        at += self.directory.nbytes
        self.low = take("<u4", n)
        at += self.low.nbytes
        self.columns = []
        for _ in range(columns):
            (large,) = struct.unpack("<Q", raw[at : at + 8].tobytes())
            at += 8
            places = take("<u4", large)
            at += places.nbytes
            values = take("<u8", large)
            at += values.nbytes
            self.columns.append((raw[at : at + n], places, values))
            at += n

    def find(self, keys: np.ndarray) -> tuple[np.ndarray, list[np.ndarray]]:
        """(which keys are there, the numbers of those that are)."""
        bucket = (keys >> np.uint64(64 - self.bits)).astype(np.int64) if self.bits else np.zeros(len(keys), np.int64)
        want = (keys >> np.uint64(32 - self.bits) & np.uint64(0xFFFFFFFF)).astype(np.uint32)
        first, stop = self.directory[bucket].astype(np.int64), self.directory[bucket + 1].astype(np.int64)
        end, last = stop, max(0, len(self.low) - 1)
        for _ in range(int(self.deepest).bit_length()):
            middle = (first + stop) >> 1
            less = (first < stop) & (self.low[np.minimum(middle, last)] < want) if len(self.low) else np.zeros(len(keys), bool)
            first, stop = np.where(less, middle + 1, first), np.where(less, stop, middle)
        hit = first < end
        hit[hit] = self.low[first[hit]] == want[hit]
        at = first[hit]
        out = []
        for small, places, values in self.columns:
            got = small[at].astype(np.int64)
            large = np.flatnonzero(got == TOP)
            got[large] = values[np.searchsorted(places, at[large])]
            out.append(got)
        return hit, out


def write(path: str, arrays: dict[str, bytes]) -> None:
    """One file of named arrays; the name appears only when it is whole, and any attempt's file is as good."""
    fs, name = pafs.FileSystem.from_uri(path)
    fs.create_dir(name.rsplit("/", 1)[0], recursive=True)
    part = f"{name}.{uuid.uuid4().hex}"
    with fs.open_output_stream(part) as f:
        f.write(struct.pack("<I", len(arrays)))
        at = 4 + 64 * len(arrays)
        for label, body in arrays.items():
            f.write(label.encode().ljust(56, b"\0") + struct.pack("<Q", at))
            at += len(body)
        for body in arrays.values():
            f.write(body)
    try:
        fs.move(part, name)
    except OSError:  # an earlier attempt of this task has put the same arrays there
        fs.delete_file(part)


class Files:
    """Arrays by file and label. At most ``most`` files are open; where the folder is no local mount, at most ``most_bytes`` of files are held."""

    def __init__(self, folder: str, most: int = 512, most_bytes: int = 256 << 20):
        self.folder, self.most, self.most_bytes = folder, most, most_bytes
        self.open: OrderedDict[str, tuple[dict[str, HashArray], int]] = OrderedDict()

    def array(self, file: str, label: str) -> HashArray | None:
        if file not in self.open:
            self.open[file] = self._read(f"{self.folder}/{file}")
            while len(self.open) > 1 and (len(self.open) > self.most or sum(size for _, size in self.open.values()) > self.most_bytes):
                self.open.popitem(last=False)
        self.open.move_to_end(file)
        return self.open[file][0].get(label)

    def _read(self, path: str) -> tuple[dict[str, HashArray], int]:
        fs, name = pafs.FileSystem.from_uri(path)
        if fs.get_file_info(name).type == pafs.FileType.NotFound:
            return {}, 0
        mapped = isinstance(fs, pafs.LocalFileSystem)
        raw = np.frombuffer(pa.memory_map(name).read_buffer() if mapped else fs.open_input_file(name).read_buffer(), np.uint8)
        (n,) = struct.unpack("<I", raw[:4].tobytes())
        heads = [raw[4 + 64 * i : 68 + 64 * i].tobytes() for i in range(n)]
        return {h[:56].rstrip(b"\0").decode(): HashArray(raw, struct.unpack("<Q", h[56:])[0]) for h in heads}, 0 if mapped else len(raw)
