"""Scores of all candidates for all queries, with top-k kept before the shuffle.

The inverse curvature is folded into the query side: cos(R^-1/2 q, R^-1/2 m) needs R^-1 q and
the norms of both sides only, so the stored index serves any task and any mixing weight.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.arrow import to_matrix
from .curvature import as_arrays, block_names
from .gradients import ID
from .work import bounded_broadcast, materialise

#: Bytes of query vectors that go to the tasks at a time.
TILE_BYTES = 256 << 20
SCORE_DIGITS = 8


def _fold(g: np.ndarray, inverse: np.ndarray | None) -> np.ndarray:
    if inverse is None:
        return g
    return np.einsum("sij,nsj->nsi", inverse, g.reshape(len(g), *inverse.shape[:2])).reshape(len(g), -1)


def _norms(parts: list[np.ndarray], folded: list[np.ndarray]) -> np.ndarray:
    return np.sqrt(sum((a * b).sum(axis=1) for a, b in zip(parts, folded)))


def keep_best(kept_score: np.ndarray, kept_id: np.ndarray, s: np.ndarray, ids: np.ndarray, k: int, best: float = 1.0) -> tuple[np.ndarray, np.ndarray]:
    """Each query's k best of what it kept and of a batch's scores s (query by candidate); ties to the smaller id, NaN last.

    The batch is cut to k a query without a sort: all before the k-th value, and of those equal
    to it the first by id.
    """
    order = np.argsort(ids, kind="stable")
    ids, s = ids[order], s[:, order]
    if s.shape[1] > k:
        key = np.where(np.isnan(s), np.inf, -best * s)
        bound = np.partition(key, k - 1, axis=1)[:, k - 1 : k]
        before, level = key < bound, key == bound
        take = before | (level & (np.cumsum(level, axis=1) <= k - before.sum(axis=1, keepdims=True)))
        at = np.nonzero(take)[1].reshape(len(s), k)
        ids, s = ids[at], np.take_along_axis(s, at, axis=1)
    kept_score = np.hstack([kept_score, s])
    kept_id = np.hstack([kept_id, np.broadcast_to(ids, s.shape)])
    order = np.lexsort((kept_id, np.where(np.isnan(kept_score), np.inf, -best * kept_score)), axis=1)[:, :k]
    return np.take_along_axis(kept_score, order, axis=1), np.take_along_axis(kept_id, order, axis=1)


def score_top_k(
    index: DataFrame,
    queries: DataFrame,
    k: int = 10,
    inverse: DataFrame | None = None,
    unit_norm: bool = True,
    ascending: bool = False,
    sign: float = 1.0,
    factor: str | None = None,
    tile_bytes: int = TILE_BYTES,
    copies: DataFrame | None = None,
) -> DataFrame:
    """(query_id, rank, example_id, score): the k best candidates of each query, exactly.

    All candidates are scanned once for each tile of queries; a task sends at most k rows for
    each query. Scores rank on 8 decimals, then by id. A zero vector under unit norm scores
    null and ranks last. `ascending` gives the most negative ones. `factor` names an index
    column that multiplies a candidate's scores. `copies` (example_id, copies) has the k smallest
    ids of the examples that a row stands for, its own the first of them.
    """
    names = block_names(index)
    spark = index.sparkSession
    folds = as_arrays(inverse) if inverse is not None else {}
    asked = queries.select(ID, *names)
    held = asked.agg(F.coalesce(F.sum(sum((F.size(n) for n in names), F.lit(1))), F.lit(0)).alias("n")).first()["n"] * 8
    tiles = max(1, -(-held // tile_bytes))
    if tiles > 1:
        asked = materialise(asked.withColumn("tile", F.pmod(F.xxhash64(ID), F.lit(tiles))), "query-tiles")
    best = -1.0 if ascending else 1.0
    found = None
    for at in range(tiles):
        # one tile at a time reaches the driver
        wanted = (asked.filter(F.col("tile") == at) if tiles > 1 else asked).toArrow()
        ids = np.array(wanted[ID].to_pylist(), dtype=np.int64)
        own = [to_matrix(wanted[n]) for n in names]
        folded = [_fold(p, folds.get(n)) for p, n in zip(own, names)]
        shared = spark.sparkContext.broadcast((ids, folded, _norms(own, folded), folds))

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            q_ids, y, q_norm, inv = shared.value
            kept_score, kept_id = np.empty((len(q_ids), 0)), np.empty((len(q_ids), 0), dtype=np.int64)
            for b in batches:
                if not b.num_rows or not len(q_ids):
                    continue
                g = [to_matrix(b.column(b.schema.get_field_index(n))) for n in names]
                s = sign * sum(yy @ gg.T for yy, gg in zip(y, g))
                if unit_norm:
                    m_norm = _norms(g, [_fold(gg, inv.get(n)) for gg, n in zip(g, names)])
                    scale = q_norm[:, None] * m_norm[None, :]
                    s = np.divide(s, scale, out=np.full_like(s, np.nan), where=scale > 0)
                if factor:
                    s = s * b.column(b.schema.get_field_index(factor)).to_numpy()[None, :]
                s = np.round(s, SCORE_DIGITS)
                kept_score, kept_id = keep_best(kept_score, kept_id, s, b.column(0).to_numpy(), k, best)
            n = kept_id.shape[1]
            flat = kept_score.ravel()
            yield pa.RecordBatch.from_arrays(
                [pa.array(np.repeat(q_ids, n)), pa.array(kept_id.ravel()), pa.array(flat, mask=np.isnan(flat))],
                names=["query_id", ID, "score"],
            )

        columns = [ID, *names, *([factor] if factor else [])]
        part = index.select(columns).mapInArrow(run, f"query_id long, {ID} long, score double")
        found = part if found is None else found.unionByName(part)
    found = top_k(found, k, ascending)
    if copies is not None:
        # a row outside the best k has k rows before it, and their ids precede all of its copies
        held = found.join(copies.select(ID, "copies"), ID)
        found = top_k(held.select("query_id", F.explode("copies").alias(ID), "score"), k, ascending)
    return found


def top_k(scores: DataFrame, k: int, ascending: bool = False) -> DataFrame:
    """Rank within each query; the filter on row_number limits groups before the shuffle."""
    order = F.asc_nulls_last("score") if ascending else F.desc_nulls_last("score")
    nth = F.row_number().over(Window.partitionBy("query_id").orderBy(order, ID))
    return scores.withColumn("rank", nth).filter(F.col("rank") <= k).select("query_id", "rank", ID, "score")


def score_pairs(pairs: DataFrame, index: DataFrame, queries: DataFrame, unit_norm: bool = True) -> DataFrame:
    """Scores of given (query_id, example_id) pairs: the rerank path, and pools of few candidates."""
    from ..functions.vectors import vec_dot

    names = block_names(index)

    def whole(df: DataFrame, key: str, out: str) -> DataFrame:
        return df.select(F.col(ID).alias(key), F.concat(*names).cast("array<double>").alias(out))

    joined = pairs.join(whole(queries, "query_id", "q"), "query_id").join(whole(index, ID, "m"), ID)
    dot = vec_dot(F.col("q"), F.col("m"))
    if unit_norm:
        dot = dot / F.nullif(F.sqrt(vec_dot(F.col("q"), F.col("q")) * vec_dot(F.col("m"), F.col("m"))), F.lit(0.0))
    return joined.select("query_id", ID, F.round(dot, SCORE_DIGITS).alias("score"))


def over_checkpoints(rankings: list[DataFrame], weights: list[float] | None = None) -> DataFrame:
    """Weighted sum of scores (query_id, example_id, score) over checkpoints."""
    weights = weights or [1.0] * len(rankings)
    total = None
    for scores, w in zip(rankings, weights):
        part = scores.select("query_id", ID, (F.col("score") * w).alias("score"))
        total = part if total is None else total.unionByName(part)
    return total.groupBy("query_id", ID).agg(F.round(F.sum("score"), SCORE_DIGITS).alias("score"))


def all_scores(index: DataFrame, queries: DataFrame, unit_norm: bool = False) -> DataFrame:
    """Every pair's score by a nested-loop join in SQL; for few queries of small dimension."""
    from ..functions.vectors import vec_dot

    names = block_names(index)
    q = queries.select(F.col(ID).alias("query_id"), F.concat(*names).cast("array<double>").alias("q"))
    m = index.select(ID, F.concat(*names).cast("array<double>").alias("m"))
    dot = vec_dot(F.col("q"), F.col("m"))
    if unit_norm:
        dot = dot / F.nullif(F.sqrt(vec_dot(F.col("q"), F.col("q")) * vec_dot(F.col("m"), F.col("m"))), F.lit(0.0))
    return m.crossJoin(bounded_broadcast(q)).select("query_id", ID, F.round(dot, SCORE_DIGITS).alias("score"))
