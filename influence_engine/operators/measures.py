"""Measures over rankings: MRR, recall, tail-patch, judge errors, overlap, fidelity."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .gradients import ID
from .work import bounded_broadcast


def first_hits(ranked: DataFrame, verdicts: DataFrame, queries: DataFrame, k: int = 10, by: list[str] | None = None) -> DataFrame:
    """Rank of the first entailing hit of each query, null where there is none in the top k."""
    by = by or []
    hits = (
        ranked.filter(F.col("rank") <= k)
        .join(verdicts.filter("entails").select("query_id", ID), ["query_id", ID], "left_semi")
        .groupBy(*by, "query_id")
        .agg(F.min("rank").alias("first_rank"))
    )
    base = queries.select("query_id").distinct()
    if by:
        base = base.crossJoin(bounded_broadcast(ranked.select(*by).distinct()))
    return base.join(hits, [*by, "query_id"], "left")


def mrr_recall(ranked: DataFrame, verdicts: DataFrame, queries: DataFrame, k: int = 10, by: list[str] | None = None) -> DataFrame:
    """Mean reciprocal rank (0 without a hit) and share of queries with a hit in the top k."""
    found = first_hits(ranked, verdicts, queries, k, by)
    aggs = [
        F.avg(F.coalesce(1 / F.col("first_rank"), F.lit(0.0))).alias("mrr"),
        F.avg(F.col("first_rank").isNotNull().cast("double")).alias(f"recall_at_{k}"),
        F.count(F.lit(1)).alias("n_queries"),
    ]
    return found.groupBy(*by).agg(*aggs) if by else found.agg(*aggs)


def tail_patch(deltas: DataFrame, k: int = 10, by: list[str] | None = None) -> DataFrame:
    """Mean over a query's top k, then over queries."""
    by = by or []
    per_query = deltas.filter(F.col("rank") <= k).groupBy(*by, "query_id").agg(F.avg("delta").alias("mean_delta"))
    return per_query.groupBy(*by).agg(F.avg("mean_delta").alias("tail_patch")) if by else per_query.agg(F.avg("mean_delta").alias("tail_patch"))


def tail_patch_by_k(deltas: DataFrame, by: list[str] | None = None) -> DataFrame:
    """The tail-patch for every k, from running means along ranks."""
    by = by or []
    along = Window.partitionBy(*by, "query_id").orderBy("rank").rowsBetween(Window.unboundedPreceding, 0)
    running = deltas.withColumn("v", F.avg("delta").over(along))
    return running.groupBy(*by, F.col("rank").alias("k")).agg(F.avg("v").alias("tail_patch"))


def judge_errors(verdicts: DataFrame, truth: DataFrame) -> DataFrame:
    """False positives and negatives of verdicts (entails) against truth pairs."""
    joined = verdicts.join(truth.select("query_id", ID, F.lit(True).alias("true_hit")), ["query_id", ID], "left")
    hit = F.coalesce("true_hit", F.lit(False))
    counts = joined.agg(
        F.count_if(hit).alias("positives"),
        F.count_if(~hit).alias("negatives"),
        F.count_if(hit & ~F.col("entails")).alias("false_negatives"),
        F.count_if(~hit & F.col("entails")).alias("false_positives"),
    )
    return counts


def overlap(ranked: DataFrame, k: int = 10, by: str = "method") -> DataFrame:
    """Mean share of the top k that two methods have in common, for each pair of methods."""
    top = ranked.filter(F.col("rank") <= k).select(by, "query_id", ID)
    other = top.withColumnRenamed(by, "other")
    shared = top.join(other, ["query_id", ID]).filter(F.col(by) < F.col("other"))
    n_queries = top.select("query_id").distinct().count()
    return shared.groupBy(by, "other").agg((F.count(F.lit(1)) / (k * max(1, n_queries))).alias("overlap"))


def ratios(found: DataFrame, by: str, measure: str) -> DataFrame:
    """How many times one method's measure is another's; methods at 0 are no denominators."""
    a = found.select(F.col(by), F.col(measure).alias("a"))
    b = found.select(F.col(by).alias("other"), F.col(measure).alias("b")).filter("b > 0")
    return a.join(b, F.col(by) != F.col("other")).select(by, "other", F.round(F.col("a") / F.col("b"), 6).alias("ratio"))


def fidelity(projected: DataFrame, exact: DataFrame) -> DataFrame:
    """Correlation of two score tables over their common pairs."""
    joined = projected.select("query_id", ID, F.col("score").alias("a")).join(
        exact.select("query_id", ID, F.col("score").alias("b")), ["query_id", ID]
    )
    return joined.agg(F.corr("a", "b").alias("correlation"), F.count(F.lit(1)).alias("n_pairs"))


def cosine_sums(vectors: dict[str, np.ndarray], asked: np.ndarray, exact: str) -> dict[str, np.ndarray]:
    """Sums over examples from which `fidelity_of_sums` has the correlation over all pairs of a query and an example.

    The product of two cosines is an inner product of outer products, so sums over pairs are
    products of sums over either side. Pairs with a zero vector have no cosine and stay out.
    """
    units, whole = {}, {}
    for name, v in vectors.items():
        length = np.sqrt((v * v).sum(axis=1))
        whole[name] = length > 0
        units[name] = np.divide(v, length[:, None], out=np.zeros_like(v), where=whole[name][:, None])
    out = {}
    for side, rows in (("m", np.ones(len(asked), bool)), ("q", asked)):
        b = units[exact][rows]
        out[f"{side}:rows"], out[f"{side}:bb"] = np.array([float(rows.sum())]), b.T @ b
        for name in vectors.keys() - {exact}:
            both = (whole[name] & whole[exact])[rows]
            u, v = units[name][rows][both], b[both]
            key = f"{side}:{name}"
            out |= {f"{key}:n": np.array([float(both.sum())]), f"{key}:a": u.sum(axis=0), f"{key}:b": v.sum(axis=0), f"{key}:aa": u.T @ u, f"{key}:ab": u.T @ v}
            if not both.all():
                out[f"{key}:off"] = b[~both].T @ b[~both]
    return out


def fidelity_of_sums(sums: dict[str, np.ndarray], name: str) -> tuple[float | None, int]:
    """Correlation of a projection's cosines with the exact ones, and the number of pairs."""
    both = lambda k: float((sums[f"q:{name}:{k}"] * sums[f"m:{name}:{k}"]).sum())
    n_pairs = int(sums.get("q:rows", [0])[0]) * int(sums.get("m:rows", [0])[0])
    n = both("n") if n_pairs else 0
    if not n:
        return None, n_pairs
    bb = [sums[f"{s}:bb"] - sums.get(f"{s}:{name}:off", 0) for s in "qm"]
    a, b = both("a") / n, both("b") / n
    spread = (both("aa") / n - a * a) * (float((bb[0] * bb[1]).sum()) / n - b * b)
    return ((both("ab") / n - a * b) / float(np.sqrt(spread)) if spread > 0 else None), n_pairs


def accuracy(predictions: DataFrame, facts: DataFrame) -> DataFrame:
    """Share of predictions that contain an alias, both without case and stop words."""
    from ..functions.textops import normalise

    said = F.concat(F.lit(" "), normalise(F.col("prediction")), F.lit(" "))
    right = F.exists("aliases", lambda a: said.contains(F.concat(F.lit(" "), normalise(a), F.lit(" "))))
    return predictions.join(facts, "fact_id").select("query_id", "fact_id", "prediction", right.alias("correct"))
