"""Wavelet matrices: bit planes with rank and select, kept in compressed shard files.

A shard file is a row of segments. A segment holds a run of whole documents: their ids and
places, and one bit plane for each bit of a token id. Planes are cut in blocks that are
compressed apart, each with the count of ones before it, so a single token, a count or an
occurrence reads a few blocks.
"""

from __future__ import annotations

import json
import struct
from functools import lru_cache

import numpy as np
import zstandard

MAGIC = b"WMX1"
BLOCK_BITS = 1 << 17
_POP = np.array([bin(i).count("1") for i in range(256)], dtype=np.uint8)


def _store(parts: list[bytes], at: int) -> list[list[int]]:
    """[place, size] of each part, for a file that has reached `at`."""
    sizes = [len(p) for p in parts]
    return [[at + sum(sizes[:i]), n] for i, n in enumerate(sizes)]


def encode_segment(ids: np.ndarray, doc_starts: np.ndarray, doc_ids: list, planes: int | None = None) -> bytes:
    """One segment: header length, JSON header, parts."""
    zstd = zstandard.ZstdCompressor(level=1)
    planes = planes or max(1, int(ids.max(initial=0)).bit_length())
    row = ids.astype(np.uint16 if planes <= 16 else np.uint32)
    parts: list[bytes] = [
        zstd.compress(np.diff(doc_starts, prepend=0).astype("<i8").tobytes()),
        zstd.compress(json.dumps(doc_ids).encode()),
    ]
    plan = {"n": len(row), "planes": planes, "docs": len(doc_starts), "levels": []}
    for plane in range(planes - 1, -1, -1):
        bits = (row >> plane) & 1 == 1
        packed = np.packbits(bits)
        ones = np.add.reduceat(_POP[packed], np.arange(0, len(packed), BLOCK_BITS // 8), dtype=np.int64) if len(packed) else np.empty(0, np.int64)
        raw = packed.tobytes()
        blocks = [zstd.compress(raw[i : i + BLOCK_BITS // 8]) for i in range(0, len(raw), BLOCK_BITS // 8)]
        plan["levels"].append({"zeros": len(row) - int(ones.sum()), "ones": (np.cumsum(ones) - ones).tolist(), "sizes": [len(b) for b in blocks]})
        parts += blocks
        row = np.concatenate([row[~bits], row[bits]])
    plan["meta"] = [len(parts[0]), len(parts[1])]
    head = json.dumps(plan).encode()
    return struct.pack("<4sQQ", MAGIC, len(head), sum(map(len, parts))) + head + b"".join(parts)


class Segment:
    """Reads one segment from a seekable file at a place; blocks are read when asked for."""

    def __init__(self, file, at: int = 0):
        self.file = file
        file.seek(at)
        magic, head, body = struct.unpack("<4sQQ", file.read(20))
        if magic != MAGIC:
            raise ValueError("not a segment of a wavelet shard")
        plan = json.loads(file.read(head))
        self.n, self.planes, self.levels = plan["n"], plan["planes"], plan["levels"]
        self.body = at + 20 + head
        self.end = self.body + body
        starts = self._part(self.body, plan["meta"][0])
        self.doc_starts = np.cumsum(np.frombuffer(starts, "<i8"))
        self.doc_ids = json.loads(self._part(self.body + plan["meta"][0], plan["meta"][1]))
        place = self.body + sum(plan["meta"])
        for level in self.levels:
            level["at"] = (np.cumsum([0, *level["sizes"]]) + place).tolist()
            place = level["at"][-1]
        self._block = lru_cache(maxsize=64)(self._read_block)

    def _part(self, at: int, size: int) -> bytes:
        self.file.seek(at)
        return zstandard.ZstdDecompressor().decompress(self.file.read(size))

    def _read_block(self, level: int, block: int) -> tuple[np.ndarray, np.ndarray]:
        x = self.levels[level]
        packed = np.frombuffer(self._part(x["at"][block], x["sizes"][block]), np.uint8)
        return packed, np.cumsum(_POP[packed], dtype=np.int64)

    def _ones(self, level: int, i: int) -> int:
        """Ones among the first i bits of a plane."""
        if i >= self.n:
            return self.n - self.levels[level]["zeros"]
        block, bit = divmod(i, BLOCK_BITS)
        packed, upto = self._block(level, block)
        byte, rest = divmod(bit, 8)
        ones = self.levels[level]["ones"][block] + (int(upto[byte - 1]) if byte else 0)
        return ones + (bin(int(packed[byte]) >> (8 - rest)).count("1") if rest else 0)

    def _bit(self, level: int, i: int) -> int:
        packed, _ = self._block(level, i // BLOCK_BITS)
        return int(packed[i % BLOCK_BITS // 8]) >> (7 - i % 8) & 1

    def token(self, i: int) -> int:
        """The id at place i."""
        if not 0 <= i < self.n:
            raise IndexError(i)
        out = 0
        for level in range(self.planes):
            bit = self._bit(level, i)
            ones = self._ones(level, i)
            i = self.levels[level]["zeros"] + ones if bit else i - ones
            out = out << 1 | bit
        return out

    def _range(self, token: int, first: int, end: int) -> tuple[int, int]:
        for level in range(self.planes):
            a, b = self._ones(level, first), self._ones(level, end)
            if token >> (self.planes - 1 - level) & 1:
                zeros = self.levels[level]["zeros"]
                first, end = zeros + a, zeros + b
            else:
                first, end = first - a, end - b
        return first, end

    def count(self, token: int, first: int = 0, end: int | None = None) -> int:
        """Occurrences of an id among the places from first to before end."""
        if token >> self.planes:
            return 0
        a, b = self._range(token, first, self.n if end is None else end)
        return b - a

    def _select(self, level: int, bit: int, k: int) -> int:
        """Place of the k-th (from 0) bit of that value in a plane."""
        low, high = 0, self.n
        while low < high:
            mid = (low + high) // 2
            ones = self._ones(level, mid + 1)
            if (ones if bit else mid + 1 - ones) > k:
                high = mid
            else:
                low = mid + 1
        return low

    def occurrence(self, token: int, k: int) -> int:
        """Place of the k-th (from 0) occurrence of an id."""
        a, b = (0, 0) if token >> self.planes else self._range(token, 0, self.n)
        if not 0 <= k < b - a:
            raise IndexError(k)
        at = a + k
        for level in range(self.planes - 1, -1, -1):
            bit = token >> (self.planes - 1 - level) & 1
            at = self._select(level, bit, at - self.levels[level]["zeros"] if bit else at)
        return at

    def tokens(self) -> np.ndarray:
        """All ids, by undoing the planes from the last to the first."""
        row = np.zeros(self.n, dtype=np.uint16 if self.planes <= 16 else np.uint32)
        zstd = zstandard.ZstdDecompressor()
        for level in range(self.planes - 1, -1, -1):
            x = self.levels[level]
            self.file.seek(x["at"][0])
            raw = self.file.read(x["at"][-1] - x["at"][0])
            cuts = np.cumsum([0, *x["sizes"]]).tolist()
            packed = b"".join(zstd.decompress(raw[a:b]) for a, b in zip(cuts, cuts[1:]))
            bits = np.unpackbits(np.frombuffer(packed, np.uint8))[: self.n].astype(bool)
            out = np.empty_like(row)
            out[~bits] = row[: x["zeros"]]
            out[bits] = row[x["zeros"] :] | row.dtype.type(1 << (self.planes - 1 - level))
            row = out
        return row.astype("<u4")


def segments(file, size: int):
    """All segments of a shard file in order."""
    at = 0
    while at < size:
        segment = Segment(file, at)
        yield segment
        at = segment.end
