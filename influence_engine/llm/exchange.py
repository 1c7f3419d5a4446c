"""Fingerprint exchange between partitions and hash-range owners.

Each sender keeps its rows where they are and sends every owner one packet: the
sorted distinct keys of that owner's range, Golomb-Rice coded. The owner merges the
packets and answers with one bit per key. A hot key occurs once per packet, however
many rows carry it, so owners stay even.
"""

from __future__ import annotations

import struct

import numpy as np

_CHUNK = 1 << 16


def rice_encode(keys: np.ndarray) -> bytes:
    """Code sorted distinct uint64 values; quotients in unary, remainders in k bits."""
    n = len(keys)
    if n == 0:
        return struct.pack("<QBQ", 0, 0, 0)
    gaps = keys.copy()
    gaps[1:] = keys[1:] - keys[:-1]
    mean = max(1, int(keys[-1]) // n)
    k = max(0, min(63, mean.bit_length() - 1))
    ends = np.cumsum((gaps >> np.uint64(k)).astype(np.int64) + 1)
    unary = np.zeros(int(ends[-1]), dtype=np.uint8)
    unary[ends - 1] = 1
    head = np.packbits(unary).tobytes()
    tail = []
    if k:
        low = gaps & np.uint64((1 << k) - 1)
        for at in range(0, n, _CHUNK):
            bits = np.unpackbits(low[at : at + _CHUNK].astype(">u8").view(np.uint8).reshape(-1, 8), axis=1)
            tail.append(np.packbits(bits[:, 64 - k :].ravel()).tobytes())
    return struct.pack("<QBQ", n, k, len(head)) + head + b"".join(tail)


def rice_decode(code: bytes) -> np.ndarray:
    n, k, size = struct.unpack_from("<QBQ", code)
    if n == 0:
        return np.empty(0, dtype=np.uint64)
    at = struct.calcsize("<QBQ")
    ends = np.flatnonzero(np.unpackbits(np.frombuffer(code, np.uint8, size, at)))[:n]
    gaps = np.diff(ends, prepend=-1).astype(np.uint64) - np.uint64(1)
    at += size
    if k:
        low = np.empty(n, dtype=np.uint64)
        for first in range(0, n, _CHUNK):
            m = min(_CHUNK, n - first)
            width = (m * k + 7) // 8
            bits = np.unpackbits(np.frombuffer(code, np.uint8, width, at))[: m * k].reshape(m, k)
            wide = np.zeros((m, 64), dtype=np.uint8)
            wide[:, 64 - k :] = bits
            low[first : first + m] = np.packbits(wide, axis=1).view(">u8").ravel()
            at += width
        gaps = (gaps << np.uint64(k)) | low
    return np.cumsum(gaps, dtype=np.uint64)


def owner_slices(keys: np.ndarray, owner_bits: int, key_bits: int):
    """Yield (owner, first, last) over sorted keys; owners are equal ranges of the key space."""
    shift = key_bits - owner_bits
    edges = np.searchsorted(keys, np.arange(1, 1 << owner_bits, dtype=np.uint64) << np.uint64(shift))
    edges = np.r_[0, edges, len(keys)]
    for owner in np.flatnonzero(edges[1:] > edges[:-1]):
        yield int(owner), int(edges[owner]), int(edges[owner + 1])


def owner_base(owner: int, owner_bits: int, key_bits: int) -> np.uint64:
    return np.uint64(owner << (key_bits - owner_bits))


def owner_bits_for(keys: int, per_owner: int = 1_000_000, least: int = 4) -> int:
    """Owners so that each holds about per_owner keys; a power of two."""
    return max(least, min(20, (max(1, keys) // per_owner).bit_length()))


def answer(codes: list[bytes], mins: list[np.ndarray] | None = None, rests: list[np.ndarray] | None = None) -> list[bytes]:
    """One bitmap for each packet: keys that another packet holds too or, with mins,
    keys for which another packet knows a smaller value. With rests, keys are equal only
    where their further 64 bits are equal too."""
    parts = [rice_decode(c) for c in codes]
    sizes = [len(p) for p in parts]
    keys = np.concatenate(parts) if parts else np.empty(0, np.uint64)
    rest = np.zeros(len(keys), np.uint64) if rests is None else np.concatenate(rests)
    order = np.argsort(keys, kind="stable") if rests is None else np.lexsort((rest, keys))
    start = np.ones(len(keys), dtype=bool)
    start[1:] = (keys[order][1:] != keys[order][:-1]) | (rest[order][1:] != rest[order][:-1])
    firsts = np.flatnonzero(start)
    run = np.cumsum(start) - 1
    hit = np.zeros(len(keys), dtype=bool)
    if len(keys):
        if mins is None:
            hit[order] = np.diff(np.r_[firsts, len(keys)])[run] > 1
        else:
            low = np.concatenate(mins)[order]
            hit[order] = np.minimum.reduceat(low, firsts)[run] < low
    out, at = [], 0
    for n in sizes:
        out.append(np.packbits(hit[at : at + n]).tobytes())
        at += n
    return out


def read_bits(bitmap: bytes, n: int) -> np.ndarray:
    return np.unpackbits(np.frombuffer(bitmap, np.uint8))[:n].astype(bool)
