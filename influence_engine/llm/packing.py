"""Best-fit packing planned on the histogram of piece lengths."""

from __future__ import annotations

import zlib
from bisect import bisect_left, insort
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ._runtime import documents, materialise, release_memory
from .tokens import public_path, runs_of, word_encoder

CAPACITY = 4096
END_ID = 1
_PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"


def plan_slots(histogram: dict[int, int], capacity: int) -> np.ndarray:
    """Best fit, longest first, over counts.

    Sequences with equal room are handled as one run of neighbouring numbers, so the work
    and the plan depend on the capacity, not on the number of documents.
    Rows: length, first rank, first sequence, pieces of this length in each sequence, offset.
    """
    rooms: list[int] = []
    runs: dict[int, list[tuple[int, int]]] = defaultdict(list)
    slots, opened = [], 0

    def put(room: int, first: int, n: int) -> None:
        if room and n:
            if not runs[room]:
                insort(rooms, room)
            runs[room].append((first, n))

    for length in sorted(histogram, reverse=True):
        left, rank = histogram[length], 0
        while left:
            at = bisect_left(rooms, length)
            if at < len(rooms):
                room = rooms[at]
                first, n = runs[room].pop()
                if not runs[room]:
                    rooms.pop(at)
            else:
                room, first = capacity, opened
                n = -(-left // (capacity // length))
                opened += n
            each = room // length
            take = min(n, left // each)
            if take == 0:
                each, take = left, 1
            slots.append((length, rank, first, each, capacity - room))
            put(room, first + take, n - take)
            put(room - each * length, first, take)
            rank, left = rank + each * take, left - each * take
    return np.array(slots, dtype=np.int64).reshape(-1, 5)


def token_pieces(docs: DataFrame, model_path: str, capacity: int, end_id: int) -> DataFrame:
    """Each document's ids and the end id, cut only where longer than the capacity."""

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, end = word_encoder(model_path), np.array([end_id], dtype="<u4")
        for b in batches:
            out: list[list[int]] = [[], [], [], [], []]
            texts = b.column("t").to_pylist()
            coded = (x for a, z in runs_of(map(len, texts)) for x in encoder.encode_many(texts[a:z]))
            for i, ids in zip(b.column("doc_id").to_pylist(), coded):
                ids = np.concatenate([ids, end])
                for piece, at in enumerate(range(0, len(ids), capacity)):
                    part = ids[at : at + capacity]
                    for col, value in zip(out, (i, piece, at, len(part), zlib.crc32(part.tobytes()))):
                        col.append(value)
            types = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
            yield pa.RecordBatch.from_arrays(
                [pa.array(c, k) for c, k in zip(out, types)], names=["doc_id", "piece", "start", "length", "ids_crc32"]
            )
        release_memory()

    return docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        F.coalesce(F.col("text").cast("string"), F.lit("")).cast("binary").alias("t"),
    ).mapInArrow(cut, _PIECES)


def pack(
    docs: DataFrame, model_path: str, capacity: int = CAPACITY, end_id: int = END_ID, per_bucket: int = 20_000
) -> DataFrame:
    """Pack all documents into few sequences of at most capacity tokens.

    Only the length histogram (at most capacity rows) reaches the driver. A piece's rank within
    its length is counted in hash buckets, so a length that a third of all pieces share is
    spread over tasks; the plan maps (length, rank) to a place.
    Null text is an empty document and gives one piece, the end id alone. A repeated row is
    packed as often as it occurs; a null id is carried. An empty table gives no rows.
    Returns doc_id, piece, start, length, ids_crc32, sequence_id, offset.
    """
    pieces = materialise(token_pieces(docs, model_path, capacity, end_id), "op8-pieces")
    n_buckets = max(8, min(4096, pieces.count() // per_bucket))
    dealt = pieces.withColumn("bucket", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32"), F.lit(n_buckets)).cast("int"))
    tallies = materialise(dealt.groupBy("length", "bucket").agg(F.count(F.lit(1)).alias("n")), "op8-tallies")
    histogram = {r["length"]: r["n"] for r in tallies.groupBy("length").agg(F.sum("n").alias("n")).collect()}
    slots = plan_slots(histogram, capacity)
    slots = slots[np.lexsort((slots[:, 1], slots[:, 0]))]
    before = Window.partitionBy("length").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    offsets = tallies.select("length", "bucket", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    nth = F.row_number().over(Window.partitionBy("length", "bucket").orderBy("doc_id", "piece", "ids_crc32"))
    ranked = dealt.withColumn("nth", nth).join(offsets, ["length", "bucket"]).withColumn("rank", F.col("base") + F.col("nth") - 1)
    spark = docs.sparkSession
    shared = spark.sparkContext.broadcast(slots)

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        plan = shared.value
        width = int(plan[:, 1].max(initial=0)) + 1
        keys = plan[:, 0].astype(object) * width + plan[:, 1] if width > 2**50 else plan[:, 0] * width + plan[:, 1]
        for b in batches:
            length, rank = b.column("length").to_numpy(), b.column("rank").to_numpy()
            slot = plan[np.searchsorted(keys, length * width + np.minimum(rank, width - 1), side="right") - 1]
            nth_in = rank - slot[:, 1]
            names = ["doc_id", "piece", "start", "length", "ids_crc32"]
            yield pa.RecordBatch.from_arrays(
                [b.column(n) for n in names]
                + [pa.array(slot[:, 2] + nth_in // slot[:, 3]), pa.array(slot[:, 4] + nth_in % slot[:, 3] * length)],
                names=[*names, "sequence_id", "offset"],
            )

    return ranked.select("doc_id", "piece", "start", "length", "ids_crc32", "rank").mapInArrow(
        place, _PIECES + ", sequence_id long, offset long"
    )


def op8_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(documents(spark, sf_dir), public_path("word_bpe_49k.json"))
