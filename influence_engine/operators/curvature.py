"""Block-diagonal curvature: autocorrelation of indexed gradients, mixing, inversion.

A curvature table has one row for each sub-block: (block, sub, vals), vals row-major.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.arrow import from_matrix, to_matrix
from .gradients import ID, TIMES

_DDL = "block string, sub int, vals array<double>"


def block_names(index: DataFrame) -> list[str]:
    return [f.name for f in index.schema if f.dataType.typeName() == "array" and f.name != ID]


def autocorrelation(index: DataFrame, size: int, scale: str = "mean", sample: float = 1.0, blocks: list[str] | None = None) -> DataFrame:
    """Sum or mean of g g' over examples for each sub-block of that size, in one pass.

    Tasks keep running sums and send one row for each sub-block; vectors are never shuffled.
    A row with `times` counts that often.
    A sample below 1 takes examples by a hash of their id.
    """
    names = blocks or block_names(index)
    weighted = TIMES in index.columns
    rows = index.select(ID, *names, *([TIMES] if weighted else []))
    if sample < 1:
        rows = rows.filter(F.pmod(F.xxhash64(ID), F.lit(1_000_000)) < int(sample * 1_000_000))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[str, np.ndarray] = {}
        n = 0
        for b in batches:
            if b.num_rows:
                times = b.column(b.schema.get_field_index(TIMES)).to_numpy() if weighted else None
                n += b.num_rows if times is None else int(times.sum())
                for name in names:
                    g = to_matrix(b.column(b.schema.get_field_index(name))).reshape(b.num_rows, -1, size)
                    total[name] = total.get(name, 0) + np.einsum("nsi,nsj->sij", g if times is None else g * times[:, None, None], g)
        out = {"block": [], "sub": [], "n": [], "vals": []}
        for name, t in total.items():
            for sub, m in enumerate(t):
                for col, value in zip(out.values(), (name, sub, n, m.ravel().tolist())):
                    col.append(value)
        yield pa.RecordBatch.from_pydict(out, schema=pa.schema([("block", pa.string()), ("sub", pa.int32()), ("n", pa.int64()), ("vals", pa.list_(pa.float64()))]))

    def add(parts: pd.DataFrame) -> pd.DataFrame:
        m = np.sum(np.stack([np.asarray(v) for v in parts["vals"]]), axis=0)
        if scale == "mean":
            m = m / parts["n"].sum()
        return pd.DataFrame({"block": [parts["block"].iloc[0]], "sub": [parts["sub"].iloc[0]], "vals": [m.tolist()]})

    return rows.mapInArrow(run, "block string, sub int, n long, vals array<double>").groupBy("block", "sub").applyInPandas(add, _DDL)


def mix(r_eval: DataFrame, r_train: DataFrame, lam: float) -> DataFrame:
    """lam of the evaluation's curvature plus the rest of the training's."""
    return (
        r_eval.withColumnRenamed("vals", "e")
        .join(r_train.withColumnRenamed("vals", "t"), ["block", "sub"])
        .select("block", "sub", F.zip_with("e", "t", lambda e, t: lam * e + (1 - lam) * t).alias("vals"))
    )


def _damped(vals, damping: float) -> np.ndarray:
    n = int(round(np.sqrt(len(vals))))
    m = np.asarray(vals, dtype=np.float64).reshape(n, n)
    return m + damping * np.trace(m) / n * np.eye(n)


def invert(r: DataFrame, damping: float = 1e-6, power: float = -1.0, method: str = "eigh") -> DataFrame:
    """R to the power -1 or -1/2, a sub-block in each task.

    Damping adds that part of the mean diagonal. Methods: `eigh`; `cholesky` (power -1 as the
    product of triangular inverses); `diag` keeps the diagonal alone. Scores depend on R to
    the -1 alone, so all full methods rank alike.
    """

    def run(parts: pd.DataFrame) -> pd.DataFrame:
        out = []
        for vals in parts["vals"]:
            m = _damped(vals, damping)
            if method == "diag":
                inv = np.diag(np.maximum(np.diag(m), 1e-300) ** power)
            elif method == "cholesky":
                low = np.linalg.inv(np.linalg.cholesky(m))
                inv = low.T @ low if power == -1 else low
            else:
                w, q = np.linalg.eigh(m)
                inv = (q * np.maximum(w, 1e-300) ** power) @ q.T
            out.append(inv.ravel().tolist())
        return parts.assign(vals=out)

    return r.groupBy("block", "sub").applyInPandas(run, _DDL)


def choose_lambda(r_eval: DataFrame, r_train: DataFrame, top: int | None = None) -> float:
    """Mixing weight at which about `top` components of the evaluation outweigh the training.

    Eigenpairs of the evaluation's curvature are pooled over sub-blocks. With e the top-th
    eigenvalue and t the training's curvature along its direction, lam = t / (t + e), so lam
    grows with the size of training gradients. By default top is 1000 in 65536.
    """

    def pairs(parts: pd.DataFrame) -> pd.DataFrame:
        out = []
        for e, t in zip(parts["e"], parts["t"]):
            n = int(round(np.sqrt(len(e))))
            w, q = np.linalg.eigh(np.asarray(e).reshape(n, n))
            along = np.einsum("ik,ij,jk->k", q, np.asarray(t).reshape(n, n), q)
            out.append(pd.DataFrame({"e": w, "t": along}))
        return pd.concat(out)

    joined = r_eval.withColumnRenamed("vals", "e").join(r_train.withColumnRenamed("vals", "t"), ["block", "sub"])
    found = joined.groupBy("block", "sub").applyInPandas(pairs, "e double, t double")
    if top is None:
        top = -(-found.count() * 1000 // 65536)
    last = found.orderBy(F.desc("e")).limit(top).orderBy("e").first()
    return float(last["t"] / max(last["t"] + last["e"], 1e-300)) if last else 0.0


def as_arrays(r: DataFrame, most_bytes: int = 2 << 30) -> dict[str, np.ndarray]:
    """Curvature as (subs, size, size) arrays for kernels; refuses more than most_bytes.

    It grows with dimension times sub-block size, not with the number of examples.
    """
    held = r.agg(F.sum(F.size("vals")).alias("n")).first()["n"] or 0
    if held * 8 > most_bytes:
        raise ValueError(f"curvature takes {held * 8} bytes; use smaller sub-blocks or score block by block")
    rows = sorted(r.collect(), key=lambda x: (x["block"], x["sub"]))
    out: dict[str, list] = {}
    for row in rows:
        n = int(round(np.sqrt(len(row["vals"]))))
        out.setdefault(row["block"], []).append(np.array(row["vals"]).reshape(n, n))
    return {k: np.stack(v) for k, v in out.items()}


def whiten(index: DataFrame, root: DataFrame) -> DataFrame:
    """Multiply every sub-block of every example by the root: the unnormalised final vectors."""
    names = block_names(index)
    shared = index.sparkSession.sparkContext.broadcast(as_arrays(root))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                cols = []
                for name in names:
                    m = shared.value[name]
                    g = to_matrix(b.column(b.schema.get_field_index(name))).reshape(b.num_rows, *m.shape[:2])
                    cols.append(from_matrix(np.einsum("sij,nsj->nsi", m, g).reshape(b.num_rows, -1)))
                yield pa.RecordBatch.from_arrays([b.column(0), *cols], names=[ID, *names])

    ddl = f"{ID} long" + "".join(f", {n} array<double>" for n in names)
    return index.select(ID, *names).mapInArrow(run, ddl)
