"""From examples to an index of projected, moment-corrected gradients.

An index has one row for each example and one array column for each block of layers, so all
blocks of an example lie together, scores need no shuffle, and a scan of few blocks reads
only their Parquet columns.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.arrow import from_matrix

ID = "example_id"
#: Column of an index that says how many examples a row stands for; without it each stands for itself.
TIMES = "times"
#: Parameters whose sums travel in one row.
STRETCH = 1 << 16


@dataclass(frozen=True)
class IndexSpec:
    """Which layers form which block, how they are projected, what is differentiated."""

    blocks: dict[str, list[str]]
    projection: object
    output: str = "loss"
    moment: dict[str, np.ndarray] | None = None
    eps: float = 1e-12
    precision: str = "double"
    extra: list[str] = field(default_factory=list)

    def with_(self, **changes) -> IndexSpec:
        return IndexSpec(**{**self.__dict__, **changes})


def correct(g: np.ndarray, v: np.ndarray | tuple[np.ndarray, np.ndarray], eps: float) -> np.ndarray:
    """Divide by the root of the second moment, held in full or as (row, column) factors."""
    if isinstance(v, tuple):
        rows, cols = v
        v = rows[:, None] * cols[None, :] / max(float(rows.mean()), 1e-300)
    return g / np.sqrt(v + eps)


def project_batch(model, batch: pa.RecordBatch, spec: IndexSpec) -> dict[str, np.ndarray]:
    """Block vectors of a batch. A model may offer a fused path that never builds layer gradients."""
    if hasattr(model, "projected"):
        return model.projected(batch, spec)
    grads = model.gradients(batch, spec.output)
    out = {}
    for block, layers in spec.blocks.items():
        parts = []
        for layer in layers:
            g = grads[layer]
            if spec.moment is not None:
                g = correct(g, spec.moment[layer], spec.eps)
            parts.append(spec.projection.apply(layer, g))
        out[block] = np.concatenate(parts, axis=1) if parts else np.empty((batch.num_rows, 0))
    return out


def classes(examples: DataFrame, columns: list[str], k: int = 10) -> DataFrame:
    """One row for each distinct input: (example_id, the columns, times, copies).

    Examples of equal inputs have equal gradients, so one row stands for all: the smallest id
    names it, `times` counts them all, and `copies` are the k smallest ids, which are all that
    a ranking of k can hold of them.
    """
    nth = F.row_number().over(Window.partitionBy(*columns).orderBy(ID))
    # the filter on row_number limits the groups of each task before the shuffle
    first = examples.select(ID, *columns).withColumn("nth", nth).filter(F.col("nth") <= k)
    first = first.groupBy(*columns).agg(F.sort_array(F.collect_list(ID)).alias("copies"))
    counted = examples.groupBy(*columns).agg(F.count(F.lit(1)).alias(TIMES))
    return first.join(counted, columns).select(F.get("copies", F.lit(0)).alias(ID), *columns, TIMES, "copies")


def build_index(examples: DataFrame, model, spec: IndexSpec) -> DataFrame:
    """(example_id, one array per block, extra columns); a narrow map, nothing is shuffled."""
    spark = examples.sparkSession
    shared = spark.sparkContext.broadcast((model, spec))
    kind = pa.float64() if spec.precision == "double" else pa.float32()
    names = list(spec.blocks)
    ddl = f"{ID} long" + "".join(f", {b} array<{spec.precision}>" for b in names)
    ddl += "".join(f", {c} {examples.schema[c].dataType.simpleString()}" for c in spec.extra)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model, spec = shared.value
        for b in batches:
            if b.num_rows:
                found = project_batch(model, b, spec)
                cols = [from_matrix(found[x], kind) for x in names]
                extra = [b.column(b.schema.get_field_index(c)) for c in spec.extra]
                yield pa.RecordBatch.from_arrays([b.column(0), *cols, *extra], names=[ID, *names, *spec.extra])

    need = list(dict.fromkeys([*model.columns, *spec.extra]))
    return examples.select(F.col(ID).cast("long").alias(ID), *need).mapInArrow(run, ddl)


def write_index(index: DataFrame, path: str, shards: int = 8, mode: str = "error") -> None:
    """Index sink: shards by id, ids sorted within a file so that id ranges prune row groups."""
    index.withColumn("shard", F.pmod(F.xxhash64(ID), F.lit(shards)).cast("int")).repartition(shards, "shard").sortWithinPartitions(
        "shard", ID
    ).write.mode(mode).partitionBy("shard").option("parquet.enable.dictionary", "false").parquet(path)


def read_index(spark: SparkSession, path: str, blocks: list[str] | None = None, shards: list[int] | None = None) -> DataFrame:
    """Index source: only the asked blocks' columns and shards' folders are read."""
    found = spark.read.parquet(path)
    if shards is not None:
        found = found.filter(F.col("shard").isin(shards))
    names = blocks or [c for c in found.columns if c not in (ID, "shard")]
    return found.select(ID, *names)


def footprint(index: DataFrame, dim: int, width: int = 4) -> DataFrame:
    """Bytes that the vectors take: examples times dimension times width."""
    return index.agg(F.count(F.lit(1)).alias("n_examples")).select(
        "n_examples", F.lit(dim).cast("long").alias("dim"), (F.col("n_examples") * dim * width).alias("index_bytes")
    )


def sum_arrays(examples: DataFrame, columns: list[str], parts) -> dict[str, np.ndarray]:
    """Sums, flat, of the named arrays that `parts` gives for each batch; tasks send one partial sum each."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[str, np.ndarray] = {}
        for b in batches:
            if b.num_rows:
                for layer, x in parts(b).items():
                    total[layer] = total.get(layer, 0) + x
        for layer, x in total.items():
            flat = x.ravel()
            for at in range(0, len(flat), STRETCH):
                yield pa.RecordBatch.from_pydict({"layer": [layer], "at": [at], "s": [flat[at : at + STRETCH]]})

    def add(parts: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"layer": parts["layer"].iloc[:1], "at": parts["at"].iloc[:1], "s": [np.sum(np.stack(parts["s"]), axis=0)]})

    ddl = "layer string, at long, s array<double>"
    found = examples.select(F.col(ID).cast("long").alias(ID), *columns).mapInArrow(run, ddl)
    # sums of the tasks meet stretch by stretch, so the driver gets a row for each stretch of a layer
    summed = sorted(found.groupBy("layer", "at").applyInPandas(add, ddl).collect(), key=lambda r: (r["layer"], r["at"]))
    out: dict[str, list] = {}
    for r in summed:
        out.setdefault(r["layer"], []).append(np.array(r["s"]))
    return {layer: np.concatenate(x) for layer, x in out.items()}


def layer_sums(examples: DataFrame, model, output: str, reduce) -> tuple[int, dict[str, np.ndarray]]:
    """Sum `reduce(gradients)` of each layer over all examples."""
    shared = examples.sparkSession.sparkContext.broadcast(model)

    def parts(b: pa.RecordBatch) -> dict[str, np.ndarray]:
        return {"": np.array([float(b.num_rows)])} | {layer: reduce(g) for layer, g in shared.value.gradients(b, output).items()}

    found = sum_arrays(examples, model.columns, parts)
    return int(found.pop("", [0])[0]), found


def diagonal_moment(examples: DataFrame, model, output: str = "loss") -> dict[str, np.ndarray]:
    """Mean squared gradient of every parameter, in one pass."""
    n, sums = layer_sums(examples, model, output, lambda g: (g * g).sum(axis=0))
    return {layer: (s / max(n, 1)).reshape(model.layers[layer]) for layer, s in sums.items()}


def factored(moment: dict[str, np.ndarray]) -> dict[str, tuple[np.ndarray, np.ndarray]]:
    """Row and column means, as optimisers with factored moments keep them."""
    return {layer: (v.mean(axis=1), v.mean(axis=0)) for layer, v in moment.items()}


def moving_average(moments: list[dict[str, np.ndarray]], beta: float = 0.999) -> dict[str, np.ndarray]:
    """Exponential average over ordered moments, corrected for its start."""
    out: dict[str, np.ndarray] = {}
    for m in moments:
        for layer, v in m.items():
            out[layer] = beta * out.get(layer, np.zeros_like(v)) + (1 - beta) * v
    return {layer: v / (1 - beta ** len(moments)) for layer, v in out.items()}
