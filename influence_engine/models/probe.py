"""Probe models with closed-form gradients.

A model offers `columns` (what its kernels read), `layers` (name to shape) and
`gradients(batch, output)`, which gives one rows-by-columns matrix per example and layer.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.arrow import to_matrix as matrix

OUTPUTS = ("loss", "margin_token", "margin_example", "logit")


class SoftmaxProbe:
    """Softmax over class weights; the gradient is residual outer vector, one row for each class."""

    columns = ["embedding", "label"]

    def __init__(self, weights: np.ndarray, scale: float = 8.0):
        self.weights, self.scale = weights, scale
        self.layers = {"w": weights.shape}

    @classmethod
    def from_means(cls, vectors: DataFrame, scale: float = 8.0) -> SoftmaxProbe:
        """Class means as weights; one small row for each class reaches the driver."""

        def run(batches):
            total, n = {}, {}
            for b in batches:
                x, labels = matrix(b.column("embedding")), b.column("label").to_numpy()
                for c in np.unique(labels).tolist():
                    total[c] = total.get(c, 0) + x[labels == c].sum(axis=0)
                    n[c] = n.get(c, 0) + int((labels == c).sum())
            if n:
                yield pa.RecordBatch.from_pydict({"label": pa.array(list(n), pa.int32()), "n": list(n.values()), "s": [total[c] for c in n]})

        def add(parts):
            return parts.iloc[:1].assign(n=[parts["n"].sum()], s=[np.sum(np.stack(parts["s"]), axis=0)])

        ddl = "label int, n long, s array<double>"
        rows = vectors.select(F.col("label").cast("int").alias("label"), F.col("embedding").cast("array<double>").alias("embedding"))
        sums = rows.filter("label IS NOT NULL AND embedding IS NOT NULL").mapInArrow(run, ddl).groupBy("label").applyInPandas(add, ddl).collect()
        out = np.zeros((max(r["label"] for r in sums) + 1, len(sums[0]["s"])))
        for r in sums:
            out[r["label"]] = np.array(r["s"]) / r["n"]
        return cls(out, scale)

    def probabilities(self, x: np.ndarray) -> np.ndarray:
        z = self.scale * x @ self.weights.T
        z = np.exp(z - z.max(axis=1, keepdims=True))
        return z / z.sum(axis=1, keepdims=True)

    def target_probability(self, batch: pa.RecordBatch) -> np.ndarray:
        p = self.probabilities(matrix(batch.column("embedding")))
        return p[np.arange(len(p)), batch.column("label").to_numpy()]

    def residuals(self, x: np.ndarray, labels: np.ndarray, output: str = "loss") -> np.ndarray:
        """Derivative of the output by the logits: loss, log-odds margin, or the target's logit."""
        p = self.probabilities(x)
        hit = np.zeros_like(p)
        hit[np.arange(len(p)), labels] = 1
        if output == "logit":
            return hit
        r = p - hit
        if output in ("margin_token", "margin_example"):
            # one token for each example, so both margins agree here
            return -r / (1 - p[np.arange(len(p)), labels])[:, None]
        return r

    def gradients(self, batch: pa.RecordBatch, output: str = "loss") -> dict[str, np.ndarray]:
        x, labels = matrix(batch.column("embedding")), batch.column("label").to_numpy()
        r = self.residuals(x, labels, output)
        return {"w": self.scale * r[:, :, None] * x[:, None, :]}


class LogisticProbe:
    """Two sigmoid heads on hashed words; each head is a layer of one row."""

    columns = ["features", "quality", "toxic"]
    heads = ("quality", "toxic")

    def __init__(self, weights: np.ndarray):
        self.weights = weights
        self.layers = {h: (1, weights.shape[1]) for h in self.heads}

    @staticmethod
    def featurise(docs: DataFrame, width: int = 64) -> DataFrame:
        """Unit-length counts of words hashed by MD5; text is read whole."""
        from ..functions.textops import tokenise
        from ..functions.vectors import vec_norm

        buckets = F.transform(
            tokenise(F.col("text")),
            lambda w: F.pmod(F.conv(F.substring(F.md5(w), 1, 8), 16, 10).cast("long"), F.lit(width)).cast("int"),
        )
        counts = F.aggregate(
            buckets,
            F.array_repeat(F.lit(0.0), width),
            lambda acc, b: F.transform(acc, lambda x, i: F.when(i == b, x + 1).otherwise(x)),
        )
        raw = docs.withColumn("raw", counts)
        return raw.withColumn("features", F.transform("raw", lambda x: x / F.greatest(vec_norm(F.col("raw")), F.lit(1e-12)))).drop("raw")

    @classmethod
    def fit(cls, data: DataFrame, width: int = 64, steps: int = 20, rate: float = 4.0) -> LogisticProbe:
        """Gradient descent; every step sums gradients in the tasks and moves on the driver."""
        model = cls(np.zeros((2, width)))
        data = data.select(*cls.columns)
        for _ in range(steps):
            shared = data.sparkSession.sparkContext.broadcast(model)

            def sums(batches, shared=shared):
                total, n = np.zeros((2, width)), 0
                for b in batches:
                    g = shared.value.gradients(b)
                    total += np.stack([g[h].sum(axis=0)[0] for h in cls.heads])
                    n += b.num_rows
                yield pa.RecordBatch.from_pydict({"n": [n], "g": [total.ravel().tolist()]})

            parts = data.mapInArrow(sums, "n long, g array<double>").collect()
            n = max(1, sum(r["n"] for r in parts))
            model = cls(model.weights - rate * sum(np.array(r["g"]) for r in parts).reshape(2, width) / n)
            shared.unpersist()
        return model

    def gradients(self, batch: pa.RecordBatch, output: str = "loss") -> dict[str, np.ndarray]:
        x = matrix(batch.column("features"))
        out = {}
        for i, head in enumerate(self.heads):
            p = 1 / (1 + np.exp(-x @ self.weights[i]))
            r = p - batch.column(head).to_numpy()
            out[head] = r[:, None, None] * x[:, None, :]
        return out


class ExternalGradients:
    """Ready-made gradient vectors in a column; one layer of one row."""

    def __init__(self, column: str, width: int):
        self.columns, self.column = [column], column
        self.layers = {"g": (1, width)}

    def gradients(self, batch: pa.RecordBatch, output: str = "loss") -> dict[str, np.ndarray]:
        return {"g": matrix(batch.column(self.column))[:, None, :]}
