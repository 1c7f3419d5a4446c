"""Token counts by dynamic programming over prefixes."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ._runtime import documents, release_memory
from .tokens import piece_counter, public_path, runs_of

LIMIT = 4096


def _text_rows(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return docs.select(
        F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("t")
    )


def token_counts(
    docs: DataFrame, model_path: str, limit: int = LIMIT, id_col: str = "doc_id", text_col: str = "text"
) -> DataFrame:
    """Exact tokens of every whole text and the longest prefix that fits the limit.

    Null text counts as empty (0 bytes, 0 tokens). Every input row gives one row, repeated
    rows included; a null id is carried. An empty table gives no rows. Other columns are ignored.
    Returns doc_id, n_bytes, n_tokens, over_limit, fit_chars (characters of that prefix).
    """

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = piece_counter(model_path)
        for b in batches:
            texts = b.column("t").to_pylist()
            found = [x for a, z in runs_of(map(len, texts)) for x in counter.count_many(texts[a:z], limit)]
            tokens = np.array([x[0] for x in found], dtype=np.int64)
            yield pa.RecordBatch.from_arrays(
                [
                    b.column("doc_id"),
                    b.column("n_bytes"),
                    pa.array(tokens),
                    pa.array(tokens > limit),
                    pa.array([x[1] for x in found], pa.int64()),
                ],
                names=["doc_id", "n_bytes", "n_tokens", "over_limit", "fit_chars"],
            )
        release_memory()

    rows = _text_rows(docs, id_col, text_col).withColumn("n_bytes", F.octet_length("t").cast("long"))
    return rows.mapInArrow(count, "doc_id long, n_bytes long, n_tokens long, over_limit boolean, fit_chars long")


def prefix_store(docs: DataFrame, model_path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per document the token count of every prefix: prefix_tokens[i] belongs to the first i characters.

    Questions about truncation and budgets read this array; nothing is encoded again.
    Null text counts as empty and has the single entry 0.
    """

    def store(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = piece_counter(model_path)
        for b in batches:
            for i, t in zip(b.column("doc_id").to_pylist(), b.column("t").to_pylist()):
                yield pa.RecordBatch.from_arrays(
                    [pa.array([i], pa.int64()), pa.array([counter.every_prefix(t)], pa.list_(pa.int64()))],
                    names=["doc_id", "prefix_tokens"],
                )

    return _text_rows(docs, id_col, text_col).mapInArrow(store, "doc_id long, prefix_tokens array<long>")


def tokens_of_prefix(store: DataFrame, n_chars: int) -> DataFrame:
    """Tokens of each document's first n_chars characters (whole text, if shorter)."""
    at = F.least(F.lit(n_chars + 1), F.size("prefix_tokens"))
    return store.select("doc_id", F.element_at("prefix_tokens", at).alias("n_tokens"))


def longest_within(store: DataFrame, budget: int) -> DataFrame:
    """Characters of each document's longest prefix of at most budget tokens."""
    fits = F.array_position(F.transform(F.reverse("prefix_tokens"), lambda n: n <= budget), True)
    return store.select("doc_id", (F.size("prefix_tokens") - fits).cast("long").alias("fit_chars"))


def op2_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts(documents(spark, sf_dir), public_path("piece_bpe_32k.model"))
