"""Approximate nearest neighbours by an inverted multi-index.

Vector halves are quantised apart; a cell is a pair of centroids. A query takes pairs in the
order of summed distance from a heap until the cells hold as many entries as needed, and the
entries found are ranked by the inner product of the original vectors. Centroids grow with the
fourth root of the rows, so a cell holds about the square root of them. How many entries are
needed is measured on some queries, whose exact neighbours among all entries are found first.
Lists of entries are held in blocks of a bounded size, and queries stream past them.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ._runtime import materialise, to_matrix

K = 20
#: Rows that codebooks are fitted on, and rows whose exact neighbours tell how far to probe.
SAMPLE = 20_000
CALIBRATION = 128
#: Centroids of a half at most; the table of cells grows with their square.
CENTROIDS = 1_024
#: Wanted share of true neighbours among probed entries, on the calibration rows.
RECALL = 0.96
QUERY_EVERY = 20
#: Entries that a task holds at a time.
BLOCK = 20_000
_TILE = 256


def usable(vector: Column) -> Column:
    """Neither null, nor holding null or non-finite components, nor zero, nor empty."""
    whole = F.forall(vector, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))))
    return vector.isNotNull() & F.coalesce(whole, F.lit(False)) & F.coalesce(F.exists(vector, lambda x: x != 0), F.lit(False))


def _kmeans(x: np.ndarray, k: int, seed: int, rounds: int = 12) -> np.ndarray:
    rng = np.random.default_rng(seed)
    centres = np.unique(x, axis=0)
    centres = centres[rng.permutation(len(centres))[:k]].copy()
    for _ in range(rounds):
        near = _nearest(x, centres)
        total = np.zeros_like(centres)
        np.add.at(total, near, x)
        n = np.bincount(near, minlength=len(centres))
        centres[n > 0] = total[n > 0] / n[n > 0, None]
    return centres


def _nearest(x: np.ndarray, centres: np.ndarray) -> np.ndarray:
    return ((centres * centres).sum(axis=1) - 2 * x @ centres.T).argmin(axis=1)


def centroids_for(rows: int, most: int = CENTROIDS) -> int:
    return int(max(1, min(most, round(3.2 * rows**0.25))))


class Codebooks:
    """Centroids of both halves."""

    def __init__(self, sample: np.ndarray, centroids: int):
        self.split = sample.shape[1] // 2
        self.halves = [_kmeans(h, centroids, i) for i, h in enumerate(self._cut(sample))]

    def _cut(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        return x[:, : self.split], x[:, self.split :]

    def cells(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        a, b = self._cut(x)
        return _nearest(a, self.halves[0]), _nearest(b, self.halves[1])

    def traverse(self, q: np.ndarray, sizes: list[list[int]], wanted: float) -> list[tuple[int, int]]:
        """Pairs in the order of the summed distance (the negative inner product), from a heap.

        The heap holds the next pair of each first centroid that has been opened; the following
        first centroid is opened when its predecessor gives its first pair.
        """
        far = [-(h @ part) for h, part in zip(self.halves, (q[: self.split], q[self.split :]))]
        first, second = (np.argsort(f, kind="stable").tolist() for f in far)
        a, b = far[0][first].tolist(), far[1][second].tolist()
        heap, out, held = [(a[0] + b[0], 0, 0)], [], 0
        while heap and held < wanted:
            _, i, j = heap[0]
            n = sizes[first[i]][second[j]]
            if n:
                out.append((first[i], second[j]))
                held += n
            if j + 1 < len(b):
                heapq.heapreplace(heap, (a[i] + b[j + 1], i, j + 1))
            else:
                heapq.heappop(heap)
            if j == 0 and i + 1 < len(a):
                heapq.heappush(heap, (a[i + 1] + b[0], i + 1, 0))
        return out


def _needed(entries: DataFrame, books: Codebooks, sizes: np.ndarray, ids: np.ndarray, q: np.ndarray, k: int, recall: float) -> int:
    """Entries to probe so that this part of the calibration rows' exact neighbours is among them.

    Each task sends at most k rows for each of the calibration rows.
    """
    shared = entries.sparkSession.sparkContext.broadcast((ids, q))

    def exact(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, q = shared.value
        kept = pd.DataFrame({"query_id": [], "c1": [], "c2": [], "score": []})
        for b in batches:
            if b.num_rows:
                e = b.select(["vec_id", "c1", "c2"]).to_pandas()
                score = q @ to_matrix(b.column("v")).T
                score[ids[:, None] == e["vec_id"].to_numpy()[None, :]] = -np.inf
                n = min(k, len(e))
                at = np.argpartition(-score, n - 1, axis=1)[:, :n].ravel()
                row = np.repeat(np.arange(len(ids)), n)
                found = pd.DataFrame({"query_id": ids[row], "c1": e["c1"].to_numpy()[at], "c2": e["c2"].to_numpy()[at], "score": score[row, at]})
                kept = pd.concat([kept, found[found["score"] > -np.inf]]).sort_values("score", ascending=False).groupby("query_id").head(k)
        if len(kept):
            yield pa.RecordBatch.from_pandas(kept.astype({"query_id": "int64", "c1": "int32", "c2": "int32", "score": "float64"}), preserve_index=False)

    order = Window.partitionBy("query_id").orderBy(F.desc("score"))
    found = entries.mapInArrow(exact, "query_id long, c1 int, c2 int, score double").withColumn("nth", F.row_number().over(order))
    wanted: dict[int, list] = {}
    for r in found.filter(F.col("nth") <= k).collect():
        wanted.setdefault(r["query_id"], []).append((r["c1"], r["c2"]))
    reached, listed = [], sizes.tolist()
    for i, v in zip(ids.tolist(), q):
        upto, held = {}, 0
        for cell in books.traverse(v, listed, np.inf):
            held += int(sizes[cell])
            upto[cell] = held
        reached += [upto[cell] for cell in wanted.get(i, [])]
    return int(np.quantile(reached, recall)) + 1 if reached else int(sizes.sum())


def _best(e: np.ndarray, ids: np.ndarray, second: np.ndarray, q: np.ndarray, own: np.ndarray, cells: list, k: int) -> list[np.ndarray]:
    """The k best of some entries for each of some queries, among the cells that it probes: query, entry, score."""
    probed = np.zeros((len(q), int(second.max()) + 1), dtype=bool)
    for i, mine in enumerate(cells):
        mine = np.asarray(mine)
        probed[i, mine[mine < probed.shape[1]]] = True
    score = q @ e.T
    score[~probed[:, second] | (own[:, None] == ids[None, :])] = -np.inf
    n = min(k, len(ids))
    bound = np.partition(score, len(ids) - n, axis=1)[:, len(ids) - n]
    # equal vectors may differ in the last place here, so near ties are kept and scored again
    rows, cols = np.nonzero((score >= bound[:, None] - 1e-9 * np.maximum(1, np.abs(bound[:, None]))) & (score > -np.inf))
    exact = (q[rows] * e[cols]).sum(axis=1)
    order = np.lexsort((ids[cols], -exact, rows))
    rows, cols, exact = rows[order], cols[order], exact[order]
    keep = np.arange(len(rows)) - np.searchsorted(rows, rows) < n
    return [own[rows[keep]], ids[cols[keep]], exact[keep]]


def _stream(k: int):
    """Rows come list by list, a list's entries before the queries that probe it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, parts, block = None, [], None
        for b in batches:
            keys = np.stack([b.column("c1").to_numpy(), b.column("chunk").to_numpy(), b.column("kind").to_numpy()], axis=1)
            edges = np.flatnonzero(np.r_[True, (keys[1:] != keys[:-1]).any(axis=1)]) if len(keys) else []
            for a, z in zip(edges, [*edges[1:], len(keys)]):
                part, kind = b.slice(a, z - a), keys[a, 2]
                if at != tuple(keys[a, :2]):
                    at, parts, block = tuple(keys[a, :2]), [], None
                ids, v = part.column("id").to_numpy(), to_matrix(part.column("v"))
                if kind == 0:
                    parts.append((v, ids, part.column("c2").to_numpy()))
                    continue
                if parts:
                    block, parts = [np.concatenate(x) for x in zip(*parts)], []
                if block is None:
                    continue
                cells = part.column("cells").to_pylist()
                for i in range(0, len(ids), _TILE):
                    found = _best(*block, v[i : i + _TILE], ids[i : i + _TILE], cells[i : i + _TILE], k)
                    yield pa.RecordBatch.from_arrays([pa.array(x) for x in found], names=["query_id", "vec_id", "score"])

    return run


def search(
    vectors: DataFrame,
    query_every: int = QUERY_EVERY,
    k: int = K,
    centroids: int | None = None,
    recall: float = RECALL,
    id_col: str = "vec_id",
    vector_col: str = "embedding",
    block: int = BLOCK,
) -> DataFrame:
    """The k nearest found for each query: rows whose id is divisible by query_every.

    Every usable row is indexed. Null, zero and non-finite vectors and null ids take no part,
    and of vectors of several lengths only those of the commonest (then longest) do. Repeated
    rows count once. Of equal vectors only the k + 1 smallest ids can be among anyone's k nearest
    with ties going to smaller ids, so the index keeps those. An empty table gives no rows.
    Returns query_id, rank, vec_id, score.
    """
    spark = vectors.sparkSession
    out_schema = "query_id long, rank int, vec_id long, score double"
    kind = "float" if vectors.schema[vector_col].dataType.simpleString() == "array<float>" else "double"
    valid = (
        vectors.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vector_col).cast(f"array<{kind}>").alias("v"))
        .filter(F.col("vec_id").isNotNull() & usable(F.col("v")))
        .withColumn("dim", F.size("v"))
    )
    dims = valid.groupBy("dim").count().orderBy(F.desc("count"), F.desc("dim")).first()
    if dims is None:
        return spark.createDataFrame([], out_schema)
    rows = materialise(valid.filter(F.col("dim") == dims["dim"]).select("vec_id", "v").distinct(), "op6-vectors")
    drawn = rows.orderBy(F.xxhash64("vec_id"), "vec_id").limit(SAMPLE).toArrow()
    sample = to_matrix(drawn["v"].combine_chunks())
    books = Codebooks(sample, min(centroids or centroids_for(rows.count()), len(sample)))
    shared = spark.sparkContext.broadcast(books)

    def assign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                c1, c2 = shared.value.cells(to_matrix(b.column("v")))
                yield pa.RecordBatch.from_arrays(
                    [b.column("vec_id"), b.column("v"), pa.array(c1, pa.int32()), pa.array(c2, pa.int32())],
                    names=["vec_id", "v", "c1", "c2"],
                )

    nth = F.row_number().over(Window.partitionBy("v").orderBy("vec_id"))
    first_of_equal = rows.withColumn("nth", nth).filter(F.col("nth") <= k + 1).drop("nth")
    entries = materialise(first_of_equal.mapInArrow(assign, f"vec_id long, v array<{kind}>, c1 int, c2 int"), "op6-entries")
    # at most centroids squared rows
    sizes = np.zeros((len(books.halves[0]), len(books.halves[1])), dtype=np.int64)
    for r in entries.groupBy("c1", "c2").count().collect():
        sizes[r["c1"], r["c2"]] = r["count"]
    wanted = _needed(entries, books, sizes, drawn["vec_id"].to_numpy()[:CALIBRATION], sample[:CALIBRATION], k, recall)

    listed = sizes.tolist()

    def probe(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            of, c1s, lists = [], [], []
            for i, v in enumerate(to_matrix(b.column("v"))):
                by_first: dict[int, list[int]] = {}
                for c1, c2 in shared.value.traverse(v, listed, wanted):
                    by_first.setdefault(c1, []).append(c2)
                of += [i] * len(by_first)
                c1s += by_first
                lists += by_first.values()
            yield pa.RecordBatch.from_arrays(
                [b.column("vec_id").take(pa.array(of, pa.int64())), b.column("v").take(pa.array(of, pa.int64())), pa.array(c1s, pa.int32()), pa.array(lists, pa.list_(pa.int32()))],
                names=["id", "v", "c1", "cells"],
            )

    # a list larger than a block is dealt over chunks by id; each query meets all of them
    chunks = np.maximum(1, -(-sizes.sum(axis=1) // block)).tolist()
    n_chunks = F.element_at(F.array(*[F.lit(int(n)) for n in chunks]), F.col("c1") + 1)
    columns = ["c1", "chunk", "kind", "id", "v", "c2", "cells"]
    stored = entries.select(
        "c1",
        F.pmod(F.xxhash64("vec_id"), n_chunks).cast("int").alias("chunk"),
        F.lit(0).alias("kind"),
        F.col("vec_id").alias("id"),
        "v",
        "c2",
        F.lit(None).cast("array<int>").alias("cells"),
    )
    asked = (
        rows.filter(F.col("vec_id") % query_every == 0)
        .mapInArrow(probe, f"id long, v array<{kind}>, c1 int, cells array<int>")
        .withColumn("chunk", F.explode(F.sequence(F.lit(0), (n_chunks - 1).cast("int"))))
        .withColumn("kind", F.lit(1))
        .withColumn("c2", F.lit(0))
    )
    met = stored.select(columns).unionByName(asked.select(columns)).repartition("c1", "chunk")
    found = met.sortWithinPartitions("c1", "chunk", "kind", "id").mapInArrow(_stream(k), "query_id long, vec_id long, score double")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op6_multi_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    return search(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))
