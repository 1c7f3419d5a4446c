"""Words of Arrow text columns, split over all bytes at once, as `textops.tokenise` gives them."""

from __future__ import annotations

import unicodedata
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column
from pyspark.sql import functions as F

from .textops import tokenise

#: Bytes of text that a task splits at once.
HELD_BYTES = 1 << 22
#: Lower-cased letters and digits of single bytes, bytes of longer characters as they are, 0 for all others.
_LOWER = np.array([i if i > 127 else ord(chr(i).lower()) if chr(i).isalnum() else 0 for i in range(256)], dtype=np.uint8)
#: Texts of these characters alone are split by tables; the dotted capital I has a lower case of two characters.
_TABLED = r"\A[\x{0}-\x{12f}\x{131}-\x{17f}]*\z"


def _pair(i: int) -> tuple[int, int]:
    """Both bytes of a lower-cased letter or number from U+0080 on, (0, 0) for other characters."""
    low = chr(i).lower() if i != 0x130 and unicodedata.category(chr(i))[0] in "LN" else ""
    return tuple(low.encode()) if low else (0, 0)


#: The lower case of characters whose first byte is C2 to C5.
_PAIRS = np.array([_pair(i) for i in range(0x80, 0x180)], dtype=np.uint8)


def plain(text: Column) -> Column:
    """The text where tables know each of its characters, else its words joined by spaces; null gives an empty text."""
    single = F.octet_length(text) == F.char_length(text)
    known = F.is_valid_utf8(text) & (single | F.regexp_like(text, F.lit(_TABLED)))
    return F.when(known, text).otherwise(F.array_join(tokenise(text), " ")).alias("text")


def stretches(sizes: np.ndarray, most: int) -> list[slice]:
    """Runs of rows of about so large a sum of sizes."""
    part = np.cumsum(sizes, dtype=np.int64) // most
    cuts = [0, *(np.flatnonzero(part[1:] != part[:-1]) + 1).tolist(), len(sizes)]
    return [slice(a, b) for a, b in zip(cuts, cuts[1:]) if b > a]


def spelled(text: pa.Array, most: int | None = None) -> Iterator[tuple[np.ndarray, pa.Array]]:
    """Words of `plain` texts as `tokenise` gives them, some rows at a time: (words of each row, all of these words).

    Texts are split by table lookups over all bytes at once; bytes of characters beyond the tables stand in words alone.
    """
    text = text.cast(pa.large_string())
    for rows in stretches(pc.binary_length(text).to_numpy(), most or HELD_BYTES):
        here = text[rows]
        offsets = np.frombuffer(here.buffers()[1], np.int64)[here.offset : here.offset + len(here) + 1]
        data = np.frombuffer(here.buffers()[2] or b"", np.uint8)[offsets[0] : offsets[-1]]
        offsets = offsets - offsets[0]
        low = _LOWER[data]
        first = np.flatnonzero((data >= 0xC2) & (data <= 0xC5))
        pairs = _PAIRS[(data[first].astype(np.int64) - 0xC2) * 64 + data[first + 1] - 0x80]
        low[first], low[first + 1] = pairs[:, 0], pairs[:, 1]
        inside = low != 0
        # a word ends where the row does
        before, after = np.r_[False, inside[:-1]], np.r_[inside[1:], False]
        edges = offsets[(offsets > 0) & (offsets < len(data))]
        before[edges], after[edges - 1] = False, False
        starts, ends = np.flatnonzero(inside & ~before), np.flatnonzero(inside & ~after) + 1
        cuts = np.r_[0, np.cumsum(ends - starts)].astype(np.int32)
        words = pa.StringArray.from_buffers(len(starts), pa.py_buffer(cuts), pa.py_buffer(low[inside]))
        yield np.diff(np.searchsorted(starts, offsets)), words
