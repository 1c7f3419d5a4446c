"""Tables with declared schemas, and prompt sets in several file formats."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

SCHEMAS = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "supplier": "s_suppkey bigint, s_name string, s_nationkey int, s_acctbal double",
    "customer": "c_custkey bigint, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "part": "p_partkey bigint, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey bigint, o_custkey bigint, o_orderstatus string, o_totalprice double, "
    "o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey bigint, l_partkey bigint, l_suppkey bigint, l_linenumber int, l_quantity double, "
    "l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, "
    "l_shipdate timestamp_ntz",
    "events": "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string",
    "documents": "doc_id bigint, text string, lang string, source string, n_chars bigint",
    "labels": "doc_id bigint, quality int, toxic int",
    "benchmark": "item_id bigint, text string",
    "embeddings": "vec_id bigint, embedding array<float>, label int",
    "conversations": "conv_id bigint, turn bigint, role string, text string",
    "pages": "page_id bigint, url string, html string",
}

PROMPT_SCHEMA = "query_id bigint, prompt string, target string"


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One table; the schema is declared, so no file is opened to infer it."""
    return spark.read.schema(SCHEMAS[name]).parquet(f"{sf_dir}/{name}.parquet")


def load_prompts(spark: SparkSession, path: str, fmt: str = "json") -> DataFrame:
    """Prompt sets: JSON lines, CSV with a header, Parquet, or text lines `prompt<TAB>target`."""
    if fmt == "text":
        parts = F.split("value", "\t", 2)
        lines = spark.read.text(path)
        return lines.select(
            F.xxhash64("value").alias("query_id"), parts[0].alias("prompt"), F.get(parts, F.lit(1)).alias("target")
        )
    reader = spark.read.schema(PROMPT_SCHEMA)
    if fmt in ("json", "csv"):
        reader = reader.option("mode", "FAILFAST").option("header", "true")
    return reader.format(fmt).load(path)


def select_candidates(
    docs: DataFrame, lang: str | None = None, source: str | None = None, min_chars: int = 0, max_chars: int | None = None
) -> DataFrame:
    """Null-safe filters that reach the Parquet scan."""
    keep: Column = F.col("n_chars") >= min_chars
    if lang is not None:
        keep &= F.col("lang").eqNullSafe(lang)
    if source is not None:
        keep &= F.col("source").eqNullSafe(source)
    if max_chars is not None:
        keep &= F.col("n_chars") <= max_chars
    return docs.filter(keep)
