"""Exact de-duplication by exchange of Golomb-coded fingerprints.

Senders keep doc ids and digests in packet rows on disk and send owners only coded
fingerprints; owners answer with duplicate bitmaps. Only rows whose fingerprint is
held twice have their texts shuffled, grouped by the text bytes themselves.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import exchange
from ._runtime import bounded_broadcast, documents, materialise

KEY_BITS = 48
FLUSH_ROWS = 500_000

_PACKET = pa.schema(
    [
        ("part", pa.int64()),
        ("owner", pa.int32()),
        ("code", pa.binary()),
        ("fps", pa.list_(pa.int64())),
        ("ids", pa.list_(pa.int64())),
        ("shas", pa.list_(pa.binary())),
    ]
)
_PACKET_DDL = "part long, owner int, code binary, fps array<long>, ids array<long>, shas array<binary>"


def _packer(owner_bits: int):
    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task, seq, held, rows = TaskContext.get().partitionId(), 0, [], 0

        def flush() -> pa.RecordBatch:
            table = pa.Table.from_batches(held).combine_chunks()
            fps = table["fp"].to_numpy().astype(np.uint64)
            order = np.argsort(fps, kind="stable")
            ranked = fps[order]
            table = table.take(pa.array(order))
            ids, shas = table["doc_id"], table["sha"]
            cols = {name: [] for name in _PACKET.names}
            for owner, a, b in exchange.owner_slices(ranked, owner_bits, KEY_BITS):
                base = exchange.owner_base(owner, owner_bits, KEY_BITS)
                cols["part"].append((task << 20) | seq)
                cols["owner"].append(owner)
                cols["code"].append(exchange.rice_encode(np.unique(ranked[a:b]) - base))
                cols["fps"].append(ranked[a:b].astype(np.int64))
                cols["ids"].append(ids.slice(a, b - a).to_pylist())
                cols["shas"].append(shas.slice(a, b - a).to_pylist())
            return pa.RecordBatch.from_arrays([pa.array(cols[f.name], f.type) for f in _PACKET], schema=_PACKET)

        for batch in batches:
            if batch.num_rows:
                held.append(batch)
                rows += batch.num_rows
            if rows >= FLUSH_ROWS:
                yield flush()
                seq, held, rows = seq + 1, [], 0
        if rows:
            yield flush()

    return pack


def _own(packets: pd.DataFrame) -> pd.DataFrame:
    return pd.DataFrame(
        {"part": packets["part"], "owner": packets["owner"], "bitmap": exchange.answer(list(packets["code"]))}
    )


def _unpack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for row in batch.to_pylist():
            fps = np.asarray(row["fps"], dtype=np.int64)
            _, inverse, counts = np.unique(fps, return_inverse=True, return_counts=True)
            suspect = (exchange.read_bits(row["bitmap"], len(counts)) | (counts > 1))[inverse]
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array(row["ids"], pa.int64()),
                    pa.array(fps),
                    pa.array(row["shas"], pa.binary()),
                    pa.array(suspect),
                ],
                names=["doc_id", "fp", "sha", "suspect"],
            )


def exact_dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Group equal texts; of each group the row with the largest id stays.

    Null text counts as empty. Rows that repeat an id and its text belong to one group
    and exactly one of them is kept. A null id is smaller than any other. An empty
    table gives no rows; other columns of the input are ignored.
    Returns doc_id, keep_id, group_size, kept, text_sha256.
    """
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), text.alias("t")).withColumn(
        "fp", F.shiftrightunsigned(F.xxhash64("t"), 64 - KEY_BITS)
    )
    owner_bits = exchange.owner_bits_for(docs.count())
    packets = materialise(
        rows.select("doc_id", "fp", F.unhex(F.sha2("t", 256)).alias("sha")).mapInArrow(_packer(owner_bits), _PACKET_DDL),
        "op10-packets",
    )
    bitmaps = (
        packets.select("part", "owner", "code")
        .groupBy("owner")
        .applyInPandas(_own, "part long, owner int, bitmap binary")
    )
    members = materialise(
        packets.select("part", "owner", "fps", "ids", "shas")
        .join(bitmaps, ["part", "owner"])
        .mapInArrow(_unpack, "doc_id long, fp long, sha binary, suspect boolean"),
        "op10-members",
    )
    suspects = materialise(members.filter("suspect").select("fp").distinct(), "op10-suspects")
    groups = materialise(
        rows.join(bounded_broadcast(suspects), "fp", "left_semi")
        .groupBy("t")
        .agg(F.max("doc_id").alias("keep_id"), F.count(F.lit(1)).alias("group_size"))
        .filter("group_size > 1")
        .select(F.unhex(F.sha2("t", 256)).alias("sha"), "keep_id", "group_size"),
        "op10-groups",
    )
    joined = members.join(bounded_broadcast(groups), "sha", "left")
    digest = F.lower(F.hex("sha")).alias("text_sha256")
    single = joined.filter(F.col("group_size").isNull()).select(
        "doc_id",
        F.col("doc_id").alias("keep_id"),
        F.lit(1).cast("long").alias("group_size"),
        F.lit(True).alias("kept"),
        digest,
    )
    in_group = joined.filter(F.col("group_size").isNotNull())
    wins = F.col("doc_id").eqNullSafe(F.col("keep_id"))
    losing = in_group.filter(~wins).select("doc_id", "keep_id", "group_size", F.lit(False).alias("kept"), digest)
    nth = F.row_number().over(Window.partitionBy("sha").orderBy("doc_id"))
    winning = (
        in_group.filter(wins)
        .withColumn("nth", nth)
        .select("doc_id", "keep_id", "group_size", (F.col("nth") == 1).alias("kept"), digest)
    )
    return single.unionByName(losing).unionByName(winning)


def keep_distinct(docs: DataFrame) -> DataFrame:
    """The documents that exact_dedup keeps, with all their columns."""
    verdicts = exact_dedup(docs).select("doc_id", F.unhex("text_sha256").alias("mark"), "kept")
    digest = F.unhex(F.sha2(F.coalesce(F.col("text").cast("string"), F.lit("")), 256))
    return keep_rows(docs, materialise(verdicts, "op10-verdicts"), digest)


def keep_rows(docs: DataFrame, verdicts: DataFrame, mark: Column) -> DataFrame:
    """Rows of docs that verdicts (doc_id, mark, kept) keep; `mark` gives a row's mark from its columns.

    Ids without a kept row are anti-joined, so the texts move only if there are too many to
    broadcast. Where an id has kept and dropped rows, rows meet their verdict by id and mark;
    only rows that repeat both, and are kept fewer times than they occur, are reduced to one.
    """
    n_kept, n = F.sum(F.col("kept").cast("long")).alias("n_kept"), F.count(F.lit(1)).alias("n")
    partial = materialise(verdicts.groupBy("doc_id").agg(n_kept, n).filter("n_kept < n"), "keep-rows")
    dropped = bounded_broadcast(partial.filter("n_kept = 0").select(F.col("doc_id").alias("dropped_id")))
    out = docs.join(dropped, docs["doc_id"].eqNullSafe(dropped["dropped_id"]), "left_anti")
    mixed = partial.filter("n_kept > 0").select(F.col("doc_id").alias("mixed_id"))
    if mixed.isEmpty():
        return out
    mixed = bounded_broadcast(mixed)
    judged = verdicts.join(mixed, verdicts["doc_id"].eqNullSafe(mixed["mixed_id"]), "left_semi")
    cut = materialise(
        judged.groupBy(F.col("doc_id").alias("cut_id"), F.col("mark").alias("cut_mark"))
        .agg(n_kept, n)
        .filter("n_kept < n")
        .select("cut_id", "cut_mark", (F.col("n_kept") > 0).alias("cut_to_one")),
        "keep-rows-cut",
    )
    of_mixed = out["doc_id"].eqNullSafe(mixed["mixed_id"])
    marked = out.join(mixed, of_mixed, "left_semi").withColumn("own_mark", mark)
    few = bounded_broadcast(cut)
    met = marked.join(few, marked["doc_id"].eqNullSafe(few["cut_id"]) & (marked["own_mark"] == few["cut_mark"]), "left")
    stay = out.join(mixed, of_mixed, "left_anti").unionByName(met.filter("cut_to_one IS NULL").select(*docs.columns))
    if cut.filter("cut_to_one").isEmpty():
        return stay
    return stay.unionByName(met.filter("cut_to_one").dropDuplicates(["cut_id", "cut_mark"]).select(*docs.columns))


def op10_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup(documents(spark, sf_dir))


ORACLE_SQL = {
    "op10_exact_dedup": """
        SELECT doc_id, max(doc_id) OVER g AS keep_id, count(*) OVER g AS group_size,
               doc_id = max(doc_id) OVER g AS kept, sha256(coalesce(text, '')) AS text_sha256
        FROM documents WINDOW g AS (PARTITION BY coalesce(text, ''))
    """
}
