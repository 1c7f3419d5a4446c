"""Table functions and aggregates for SQL users."""

from __future__ import annotations

import re

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F


@F.udtf(returnType="start int, window string")
class SentenceWindows:
    """sentence_windows(text, width): every run of that many sentences; shorter texts are one."""

    def eval(self, text: str, width: int):
        cut = [s for s in (x.strip() for x in re.split(r"[.!?\n]+", text or "")) if s]
        for i in range(max(len(cut) - width, 0) + 1 if cut else 0):
            yield i, " ".join(cut[i : i + width])


@F.udtf(returnType="pos int, token string")
class TokenPositions:
    """token_positions(text): lower-cased words with their places."""

    def eval(self, text: str):
        for i, m in enumerate(re.finditer(r"[^\W_]+", (text or "").lower())):
            yield i, m.group()


@F.pandas_udf("array<double>")
def vec_sum(vectors: pd.Series) -> list:
    """Elementwise sum of a group's vectors; null ones are left out."""
    rows = [np.asarray(v, dtype=float) for v in vectors if v is not None]
    return np.sum(rows, axis=0).tolist() if rows else []


@F.pandas_udf("array<double>")
def outer_sum(vectors: pd.Series) -> list:
    """Row-major sum of outer products of a group's vectors."""
    rows = [np.asarray(v, dtype=float) for v in vectors if v is not None]
    return (np.stack(rows).T @ np.stack(rows)).ravel().tolist() if rows else []


def register(spark: SparkSession) -> None:
    spark.udtf.register("sentence_windows", SentenceWindows)
    spark.udtf.register("token_positions", TokenPositions)
    spark.udf.register("vec_sum", vec_sum)
    spark.udf.register("outer_sum", outer_sum)
