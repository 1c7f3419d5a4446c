"""Random numbers that depend on a key alone, so they are the same for any partitioning."""

from __future__ import annotations

import hashlib
from functools import lru_cache

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def gauss(key: str) -> float:
    """Standard normal from two 32-bit uniforms of the key's MD5."""
    d = hashlib.md5(key.encode()).hexdigest()
    u, v = (int(d[:8], 16) + 1) / 4294967297.0, int(d[8:16], 16) / 4294967296.0
    return float(np.sqrt(-2.0 * np.log(u)) * np.cos(2.0 * np.pi * v))


@lru_cache(maxsize=256)
def gauss_matrix(seed: int, tag: str, rows: int, cols: int) -> np.ndarray:
    """Entry (i, j) is gauss("seed:tag:i:j") over the root of the rows, so products keep their scale."""
    out = np.array([[gauss(f"{seed}:{tag}:{i}:{j}") for j in range(cols)] for i in range(rows)])
    return out / np.sqrt(rows)


def gauss_column(key: Column) -> Column:
    """The same normal as a Spark expression."""
    d = F.md5(key)
    u = (F.conv(F.substring(d, 1, 8), 16, 10).cast("double") + 1) / 4294967297.0
    v = F.conv(F.substring(d, 9, 8), 16, 10).cast("double") / 4294967296.0
    return F.sqrt(F.lit(-2.0) * F.ln(u)) * F.cos(F.lit(2.0 * np.pi) * v)


def fixed_order(seed: int, *cols: str) -> Column:
    """A sort key that shuffles rows in a way both engines can repeat."""
    return F.md5(F.concat_ws(":", F.lit(str(seed)), *[F.col(c).cast("string") for c in cols]))
