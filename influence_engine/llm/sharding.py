"""Sharding by jump consistent hashing."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ._runtime import bounded_broadcast, documents, materialise

SHARDS = 8
#: Ranges of doc_id in which slots are counted at once.
RANGES = 512


def jump_shard(keys: np.ndarray, shards: int) -> np.ndarray:
    """Shard of each 64-bit key; one more shard takes keys only into itself."""
    state = keys.astype(np.int64).view(np.uint64).copy()
    at = np.zeros(len(keys), dtype=np.int64)
    jump = np.zeros(len(keys), dtype=np.int64)
    live = np.arange(len(keys))
    while len(live):
        at[live] = jump[live]
        # fixed values: the generator's multiplier and increment
        state[live] = state[live] * np.uint64(2862933555777941757) + np.uint64(1)
        reach = (at[live] + 1) * (float(1 << 31) / ((state[live] >> np.uint64(33)) + np.uint64(1)).astype(np.float64))
        jump[live] = np.minimum(reach, float(1 << 62)).astype(np.int64)
        live = live[jump[live] < shards]
    return at


def assign_shards(docs: DataFrame, shards: int = SHARDS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Put every row into a shard that its id and the shard count decide (law `key`).

    Size is the text's UTF-8 bytes plus 1; null text has no bytes. Slots count a shard's rows
    in ascending id from 0 without gaps, repeated ids included (equal ids in any order). A null
    id is treated as key -1 and comes first. Slots are counted in ranges of the id, so no task
    holds a whole shard; an id at a quantile, and the null id, has a range of its own, which is
    counted in parts by checksum. An empty table gives no rows; other columns are ignored.
    Returns doc_id, size, text_crc32, law, shard, slot, grown_shard.
    """
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    rows = docs.select(
        F.col(id_col).cast("long").alias("doc_id"),
        (F.octet_length(text) + 1).cast("long").alias("size"),
        F.crc32(text).alias("text_crc32"),
    )
    cuts = np.unique(
        docs.select(F.col(id_col).cast("double").alias("k")).approxQuantile(
            "k", [i / RANGES for i in range(1, RANGES)], 0.25 / RANGES
        )
    ).astype(np.float64)

    @F.pandas_udf("shard int, grown_shard int, range int")
    def placed(ids: pd.Series) -> pd.DataFrame:
        keys = ids.fillna(-1).astype(np.int64).to_numpy()
        spot = np.searchsorted(cuts, keys.astype(np.float64), side="left")
        # odd ranges hold a single id; whole numbers are exact as doubles below 2 ** 53
        single = np.r_[cuts, np.nan][spot] == keys if len(cuts) else np.zeros(len(keys), dtype=bool)
        spot = 2 * spot + (single & (np.abs(keys) < 1 << 53))
        spot[ids.isna().to_numpy()] = -1
        return pd.DataFrame(
            {"shard": jump_shard(keys, shards), "grown_shard": jump_shard(keys, shards + 1), "range": spot}
        )

    part = F.when(F.col("range") % 2 != 0, F.shiftright("text_crc32", 24)).otherwise(0).cast("int")
    dealt = materialise(rows.withColumn("at", placed("doc_id")).select("*", "at.*").drop("at").withColumn("part", part), "op7-dealt")
    tallies = dealt.groupBy("shard", "range", "part").agg(F.count(F.lit(1)).alias("n"))
    before = Window.partitionBy("shard").orderBy("range", "part").rowsBetween(Window.unboundedPreceding, -1)
    bases = tallies.select("shard", "range", "part", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    bases = materialise(bases, "op7-bases")
    nth = F.row_number().over(Window.partitionBy("shard", "range", "part").orderBy("doc_id", "text_crc32", "size"))
    return (
        dealt.withColumn("nth", nth)
        .join(bounded_broadcast(bases), ["shard", "range", "part"])
        .select(
            "doc_id",
            "size",
            "text_crc32",
            F.lit("key").alias("law"),
            "shard",
            (F.col("base") + F.col("nth") - 1).cast("long").alias("slot"),
            "grown_shard",
        )
    )


def op7_jump_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return assign_shards(documents(spark, sf_dir))


#: 3988292384 is the polynomial of the checksum, reversed; the state steps as in jump_shard.
ORACLE_SQL = {
    "op7_jump_sharding": r"""
        WITH RECURSIVE crc_table AS (
            SELECT list(v ORDER BY i) AS entries FROM (
                SELECT i, list_reduce(range(8), lambda c, k: CASE WHEN c & 1 = 1 THEN xor(c >> 1, 3988292384) ELSE c >> 1 END, i) AS v
                FROM range(256) AS t(i))
        ), sized AS (
            SELECT doc_id, octet_length(encode(coalesce(text, '')))::BIGINT + 1 AS size,
                   xor(list_reduce(
                       list_transform(regexp_extract_all(hex(encode(coalesce(text, ''))), '..'), lambda h: ('0x' || h)::BIGINT),
                       lambda c, b: xor(c >> 8, entries[(xor(c, b) & 255) + 1]), 4294967295), 4294967295)::BIGINT AS text_crc32
            FROM documents, crc_table
        ), hops AS (
            SELECT doc_id, doc_id::UHUGEINT AS state, 0::BIGINT AS at, 0::BIGINT AS jump FROM documents
            UNION ALL
            SELECT doc_id, state, jump, floor((jump + 1) * (2147483648.0::DOUBLE / ((state >> 33) + 1)::DOUBLE))::BIGINT
            FROM (SELECT doc_id, jump, (state * 2862933555777941757 + 1) % 18446744073709551616::UHUGEINT AS state FROM hops WHERE jump < 9)
        ), homes AS (
            SELECT doc_id, max(jump) FILTER (jump < 8)::INTEGER AS shard, max(jump) FILTER (jump < 9)::INTEGER AS grown_shard
            FROM hops GROUP BY doc_id
        )
        SELECT doc_id, size, text_crc32, 'key' AS law, shard,
               row_number() OVER (PARTITION BY shard ORDER BY doc_id) - 1 AS slot, grown_shard
        FROM sized JOIN homes USING (doc_id)
    """
}
