"""Byte spans of many texts at once: places and 64-bit hashes, by whole arrays."""

from __future__ import annotations

import numpy as np
import xxhash

_SPACE = np.zeros(256, dtype=bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
_MASK = np.array([0] + [(1 << (8 * n)) - 1 for n in range(1, 9)], dtype=np.uint64)
_M1, _M2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)
_LONG = 4096


def mix(h: np.ndarray) -> np.ndarray:
    """A one-to-one scramble of 64-bit values."""
    h = (h ^ (h >> np.uint64(30))) * _M1
    h = (h ^ (h >> np.uint64(27))) * _M2
    return h ^ (h >> np.uint64(31))


def lanes(raw: bytes) -> np.ndarray:
    """The eight bytes from every place on as one number; what lies beyond the end is zero."""
    return np.ndarray((len(raw) + 1,), dtype="<u8", buffer=raw + bytes(9), strides=(1,))


def equal(a: np.ndarray, at_a: np.ndarray, b: np.ndarray, at_b: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Whether spans of the same size hold the same bytes; `a` and `b` are lanes."""
    out, live, at = np.ones(len(size), dtype=bool), np.flatnonzero(size > 0), 0
    while len(live):
        rest = size[live] - at
        differ = ((a[at_a[live] + at] ^ b[at_b[live] + at]) & _MASK[np.minimum(rest, 8)]) != 0
        out[live[differ]] = False
        at += 8
        live = live[(rest > 8) & ~differ]
    return out


def words(raw: bytes) -> tuple[np.ndarray, np.ndarray]:
    """First and end byte of each run of bytes other than ASCII white space."""
    space = np.ones(len(raw) + 2, dtype=bool)
    space[1:-1] = _SPACE[np.frombuffer(raw, np.uint8)]
    turns = np.flatnonzero(space[1:] != space[:-1])
    return turns[::2], turns[1::2]


def hashes(raw: bytes, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hash of each span; it depends on the span's bytes alone."""
    data = lanes(raw)
    size = ends - starts
    out = mix(size.astype(np.uint64))
    live, at = np.flatnonzero((size > 0) & (size <= _LONG)), 0
    while len(live):
        rest = size[live] - at
        lane = data[starts[live] + at] & _MASK[np.minimum(rest, 8)]
        out[live] = mix(out[live] ^ lane) + np.uint64(0x9E3779B97F4A7C15)
        at += 8
        live = live[rest > 8]
    for i in np.flatnonzero(size > _LONG):
        out[i] = xxhash.xxh64_intdigest(raw[starts[i] : ends[i]])
    return out
