"""Token ids as binary output: wavelet-matrix shard files, written and read back."""

from __future__ import annotations

import io
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyarrow import fs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import wavelet
from ._runtime import documents, materialise, release_memory, work_path
from .tokens import public_path, runs_of, word_encoder

END_ID = 2
SEGMENT_TOKENS = 1 << 20
#: Bytes of text for each shard file.
SHARD_BYTES = 16 << 20


def _open(uri: str) -> tuple[fs.FileSystem, str]:
    return fs.FileSystem.from_uri(uri.replace("s3a://", "s3://", 1))


def write_shards(docs: DataFrame, model_path: str, folder: str, end_id: int = END_ID, shards: int | None = None) -> DataFrame:
    """Encode every whole text and write shard files in ascending doc_id order.

    Files are named by shard number and put in place by a rename, so a task that runs again
    writes the same file again. Null text is empty; null ids come first; repeated ids stay
    neighbours. Returns the manifest: shard, path, n_docs, n_tokens, n_bytes.
    """
    rows = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("t")
    )
    if shards is None:
        size = rows.agg(F.sum(F.octet_length("t").cast("long"))).first()[0] or 0
        shards = max(8, -(-size // SHARD_BYTES))

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, end = word_encoder(model_path), np.array([end_id], dtype="<u4")
        shard = TaskContext.get().partitionId()
        store, root = _open(folder)
        store.create_dir(root, recursive=True)
        name, draft = f"{root}/shard-{shard:06d}.wmx", f"{root}/.draft-{shard:06d}-{uuid.uuid4().hex}"
        n_docs = n_tokens = n_bytes = held = 0
        ids: list = []
        own: list[np.ndarray] = []
        with store.open_output_stream(draft) as out:

            def flush() -> int:
                sizes = np.array([len(x) for x in own], dtype=np.int64)
                segment = wavelet.encode_segment(np.concatenate(own), np.cumsum(sizes) - sizes, ids)
                out.write(segment)
                return len(segment)

            for b in batches:
                texts, keys = b.column("t").to_pylist(), b.column("doc_id").to_pylist()
                for a, z in runs_of(map(len, texts)):
                    for key, coded in zip(keys[a:z], encoder.encode_many(texts[a:z])):
                        coded = np.concatenate([coded, end])
                        own.append(coded.astype(np.uint16) if int(coded.max()) < 1 << 16 else coded)
                        ids.append(key)
                        held += len(coded)
                        n_docs, n_tokens = n_docs + 1, n_tokens + len(coded)
                        if held >= SEGMENT_TOKENS:
                            n_bytes += flush()
                            ids, own, held = [], [], 0
            if own:
                n_bytes += flush()
        release_memory()
        if n_docs:
            store.move(draft, name)
        else:
            store.delete_file(draft)
            return
        yield pa.RecordBatch.from_pylist(
            [{"shard": shard, "path": f"{folder}/shard-{shard:06d}.wmx", "n_docs": n_docs, "n_tokens": n_tokens, "n_bytes": n_bytes}]
        )

    ordered = rows.repartitionByRange(shards, "doc_id").sortWithinPartitions("doc_id", "t")
    binary = ordered.select("doc_id", F.col("t").cast("binary").alias("t"))
    return materialise(binary.mapInArrow(write, "shard long, path string, n_docs long, n_tokens long, n_bytes long"), "op5-manifest")


def read_shards(manifest: DataFrame) -> DataFrame:
    """Read shard files back: doc_id, start, n_tokens, ids_crc32 of every document.

    The manifest has one row for each file; only it reaches the driver.
    """
    spark = manifest.sparkSession
    files = sorted((r["shard"], r["path"], r["n_tokens"]) for r in manifest.collect())
    begins = np.cumsum([0, *(n for _, _, n in files)]).tolist()
    listed = [(path, begin) for (_, path, _), begin in zip(files, begins)]
    out = "doc_id long, start long, n_tokens long, ids_crc32 long"
    if not listed:
        return spark.createDataFrame([], out)

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for row in b.to_pylist():
                store, path = _open(row["path"])
                size, start = store.get_file_info(path).size, row["begin"]
                with store.open_input_file(path) as file:
                    for segment in wavelet.segments(file, size):
                        ids = segment.tokens()
                        edges = [*segment.doc_starts.tolist(), len(ids)]
                        yield pa.RecordBatch.from_arrays(
                            [
                                pa.array(segment.doc_ids, pa.int64()),
                                pa.array(np.array(edges[:-1], dtype=np.int64) + start),
                                pa.array(np.diff(edges), pa.int64()),
                                pa.array([zlib.crc32(ids[x:y].tobytes()) for x, y in zip(edges, edges[1:])], pa.int64()),
                            ],
                            names=["doc_id", "start", "n_tokens", "ids_crc32"],
                        )
                        start += segment.n

    paths = spark.createDataFrame(listed, "path string, begin long").repartition(len(listed))
    return paths.mapInArrow(read, out)


def load_segment(raw: bytes) -> wavelet.Segment:
    return wavelet.Segment(io.BytesIO(raw))


def op5_wavelet_output(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = work_path(spark, "op5-shards")
    return read_shards(write_shards(documents(spark, sf_dir), public_path("word_bpe_49k.json"), folder))
