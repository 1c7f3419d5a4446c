"""SimHash near-duplicates: vantage-point trees over 64-bit fingerprints.

Fingerprints are parted by their Hamming distance to vantage points: at each node those within
a threshold go below, the others above. A distance obeys the triangle bound, so a fingerprint
whose search ball reaches over the threshold also enters the shard below, and every linked pair
meets in some shard. To keep that overlap small a distance budget of k bits is shared out: of
k // 2 + 1 disjoint bit blocks one holds at most k // blocks of a pair's differing bits, and
there is one tree for each block. Shards that are still large are parted again, by all 64 bits
and at the median distance, until none is. Within a shard a vantage-point tree finds the exact
pairs and prunes branches that lie farther apart than k.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import spans
from ._runtime import bounded_broadcast, documents, materialise, release_memory
from .components import connected_components
from .exact_dedup import keep_rows
from .tokens import runs_of

SHINGLE = 3
MAX_BITS = 2
#: Fingerprints in a shard beyond which it is parted again.
SHARD = 8_192
#: Levels that one pass over the fingerprints parts at most.
LEVELS_AT_ONCE = 32
_TILE = 512
_CHUNK = 1 << 16
_TURN = np.uint64(0x9E3779B97F4A7C15)


def fingerprints(texts: list[bytes], shingle: int = SHINGLE) -> np.ndarray:
    """SimHash of whole UTF-8 texts over XXH64 (seed 42) of word shingles; no words give 0."""
    raw = b"\n".join(texts).lower()
    starts, ends = spans.words(raw)
    sizes = np.fromiter(map(len, texts), dtype=np.int64, count=len(texts))
    edges = np.searchsorted(starts, np.cumsum(np.r_[0, sizes + 1]))
    plain = b" ".join(raw.split())
    place = np.cumsum(np.r_[0, ends - starts + 1])
    n_words = np.diff(edges)
    n_shingles = np.where(n_words == 0, 0, np.maximum(n_words - shingle + 1, 1))
    doc = np.repeat(np.arange(len(texts)), n_shingles)
    nth = np.arange(len(doc)) - np.repeat(np.cumsum(n_shingles) - n_shingles, n_shingles)
    first = edges[:-1][doc] + nth
    begin, end = place[first], place[np.minimum(first + shingle, edges[1:][doc])] - 1
    counts = np.zeros((len(texts), 64), dtype=np.int64)
    digest = xxhash.xxh64_intdigest
    for at in range(0, len(doc), _CHUNK):
        pairs = zip(begin[at : at + _CHUNK].tolist(), end[at : at + _CHUNK].tolist())
        h = np.array([digest(plain[a:b], 42) for a, b in pairs], dtype="<u8")
        bits = np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        own = doc[at : at + _CHUNK]
        cuts = np.flatnonzero(np.r_[True, own[1:] != own[:-1]])
        counts[own[cuts]] += np.add.reduceat(bits, cuts, axis=0, dtype=np.int32)
    set_bits = counts * 2 > n_shingles[:, None]
    return np.packbits(set_bits, axis=1, bitorder="little").view("<u8").ravel()


_ALL = np.uint64((1 << 64) - 1)


def _blocks(parts: int) -> list[np.uint64]:
    cuts = np.linspace(0, 64, parts + 1).astype(int).tolist()
    return [np.uint64(((1 << (b - a)) - 1) << a) for a, b in zip(cuts, cuts[1:])]


def _ends(path: np.ndarray, above: np.ndarray) -> np.ndarray:
    """Path of the shard below or above a node."""
    return spans.mix(path + (above.astype(np.uint64) + np.uint64(1)) * _TURN)


def part(path: np.ndarray, fps: np.ndarray, block: np.uint64, radius: int, threshold: np.ndarray | int) -> tuple[np.ndarray, np.ndarray]:
    """One level: fingerprints in the shards below and above, those near the threshold in both."""
    far = np.bitwise_count((fps ^ spans.mix(path)) & block).astype(np.int64)
    below, above = far <= threshold + radius, far > threshold
    paths = [_ends(path[below], np.zeros(int(below.sum()))), _ends(path[above], np.ones(int(above.sum())))]
    return np.concatenate(paths), np.concatenate([fps[below], fps[above]])


class Forest:
    """Groups among numbered items; a group's label is its smallest item."""

    def __init__(self, n: int):
        self.label = np.arange(n)

    def _settle(self) -> None:
        while True:
            up = self.label[self.label]
            if np.array_equal(up, self.label):
                return
            self.label = up

    def join(self, a: np.ndarray, b: np.ndarray) -> None:
        while len(a):
            x, y = self.label[a], self.label[b]
            differ = x != y
            a, b, x, y = a[differ], b[differ], x[differ], y[differ]
            np.minimum.at(self.label, np.maximum(x, y), np.minimum(x, y))
            self._settle()


def _join_tile(fps: np.ndarray, a: np.ndarray, b: np.ndarray, bits: int, forest: Forest) -> None:
    for i in range(0, len(a), _TILE):
        for j in range(0, len(b), _TILE):
            x, y = a[i : i + _TILE], b[j : j + _TILE]
            near = np.bitwise_count(fps[x][:, None] ^ fps[y][None, :]) <= bits
            p, q = np.nonzero(near)
            forest.join(x[p], y[q])


def link_within(fps: np.ndarray, items: np.ndarray, bits: int, forest: Forest) -> None:
    """Join all pairs of the items within the distance, by a vantage-point tree."""
    stack = [items]
    while stack:
        some = stack.pop()
        if len(some) <= _TILE:
            _join_tile(fps, some, some, bits, forest)
            continue
        for vantage in (fps[some[0]], ~fps[some[0]] ^ np.uint64(0x5555555555555555), fps[some[len(some) // 2]]):
            far = np.bitwise_count(fps[some] ^ vantage).astype(np.int64)
            half = int(np.median(far))
            inner = far <= half
            if inner.all():
                inner = far < half
            if inner.any() and not inner.all():
                break
        else:
            _join_tile(fps, some, some, bits, forest)
            continue
        edge_in, edge_out = far[inner].max(), far[~inner].min()
        stack += [some[inner], some[~inner]]
        for d in range(int(edge_out) - bits, int(edge_in) + 1):
            ring = some[inner & (far == d)]
            _join_tile(fps, ring, some[~inner & (far <= d + bits)], bits, forest)


def _link_runs(paths: np.ndarray, fps: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """Spanning links among equal neighbouring paths."""
    forest = Forest(len(fps))
    starts = np.flatnonzero(np.r_[True, paths[1:] != paths[:-1]])
    sizes = np.diff(np.r_[starts, len(paths)])
    large = sizes > 64
    live = np.flatnonzero(~np.repeat(large, sizes))
    for step in range(1, 64):
        live = live[live + step < len(paths)]
        live = live[paths[live] == paths[live + step]]
        if not len(live):
            break
        near = live[np.bitwise_count(fps[live] ^ fps[live + step]) <= bits]
        forest.join(near, near + step)
    for a, n in zip(starts[large].tolist(), sizes[large].tolist()):
        link_within(fps, np.arange(a, a + n), bits, forest)
    moved = np.flatnonzero(forest.label != np.arange(len(fps)))
    return fps[moved], fps[forest.label[moved]]


_ROUTED = "path long, fp long, far int"


def _routed(path: np.ndarray, fps: np.ndarray) -> pa.RecordBatch:
    """Shard, fingerprint, and its distance to the vantage point that would part the shard next."""
    far = np.bitwise_count(fps ^ spans.mix(path)).astype(np.int32)
    return pa.RecordBatch.from_arrays([pa.array(path.view(np.int64)), pa.array(fps.view(np.int64)), pa.array(far)], names=["path", "fp", "far"])


def _plant(bits: int, levels: int):
    """Part fingerprints by the first levels of each block's tree, at half the block's width."""
    blocks = _blocks(bits // 2 + 1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for tree, block in enumerate(blocks):
                fps = b.column("fp").to_numpy().view(np.uint64)
                path = spans.mix(np.full(len(fps), tree + 1, dtype=np.uint64))
                for _ in range(levels):
                    path, fps = part(path, fps, block, bits // len(blocks), int(np.bitwise_count(block)) // 2)
                yield _routed(path, fps)

    return run


def _split(bits: int):
    """Part shards by all bits, at the threshold of each."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            path, fps = (b.column(c).to_numpy().view(np.uint64) for c in ("path", "fp"))
            yield _routed(*part(path, fps, _ALL, bits, b.column("threshold").to_numpy()))

    return run


def _link(bits: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        paths, fps = np.empty(0, np.int64), np.empty(0, np.uint64)

        def linked(n: int) -> pa.RecordBatch:
            a, b = _link_runs(paths[:n], fps[:n], bits)
            return pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], names=["a", "b"])

        for batch in batches:
            paths = np.r_[paths, batch.column("path").to_numpy()]
            fps = np.r_[fps, batch.column("fp").to_numpy().view(np.uint64)]
            whole = int(np.searchsorted(paths, paths[-1])) if len(paths) else 0
            if whole:
                yield linked(whole)
                paths, fps = paths[whole:], fps[whole:]
        if len(paths):
            yield linked(len(paths))

    return run


def shards(distinct: DataFrame, bits: int = MAX_BITS, most: int = SHARD) -> DataFrame:
    """(path, fp): distinct fingerprints in shards of at most `most`, linked ones together in one at least.

    The first pass takes as many levels as random fingerprints need; then every shard that is
    too large is parted at its own median distance, pass by pass. A shard whose distances all
    lie so close together that a search ball covers them cannot be parted and stays whole; it
    holds few fingerprints, as they differ in few bits.
    """
    n, levels = distinct.count(), 0
    while n * 0.63**levels > most and levels < LEVELS_AT_ONCE:
        levels += 1
    routed = materialise(distinct.select("fp").mapInArrow(_plant(bits, levels), _ROUTED), "op3-routed")
    done = None
    while True:
        sizes = routed.groupBy("path").agg(
            F.count(F.lit(1)).alias("n"), F.min("far").alias("least"), F.max("far").alias("most"), F.percentile_approx("far", 0.5).alias("median")
        )
        large = sizes.filter((F.col("n") > most) & (F.col("most") - F.col("least") > 2 * bits + 1)).select(
            "path", F.least("median", F.col("most") - bits - 1).alias("threshold")
        )
        large = materialise(large, "op3-large")
        n_large = large.count()
        few = bounded_broadcast(large, rows=n_large)
        small = (routed.join(few, "path", "left_anti") if n_large else routed).select("path", "fp")
        done = small if done is None else done.unionByName(small)
        if not n_large:
            return done
        routed = materialise(routed.join(few, "path").mapInArrow(_split(bits), _ROUTED), "op3-routed")


def near_pairs(distinct: DataFrame, bits: int = MAX_BITS, most: int = SHARD) -> DataFrame:
    """Links (a, b) that span every group of distinct fingerprints (fp) within the distance."""
    # ordered by fingerprint too, so that a task that runs again gives the same spanning links
    return shards(distinct, bits, most).repartition("path").sortWithinPartitions("path", "fp").mapInArrow(_link(bits), "a long, b long")


def _bytes(text_col: str) -> Column:
    return F.coalesce(F.col(text_col).cast("string"), F.lit("")).cast("binary")


def _in_runs(texts: list[bytes]) -> np.ndarray:
    """Fingerprints as signed numbers, from runs of texts of a bounded size."""
    parts = [fingerprints(texts[a:z]) for a, z in runs_of(map(len, texts))]
    return (np.concatenate(parts) if parts else np.empty(0, np.uint64)).view(np.int64)


def _hexed(fp: Column | str) -> Column:
    return F.lpad(F.lower(F.hex(fp)), 16, "0")


def near_duplicates(docs: DataFrame, bits: int = MAX_BITS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Fingerprint and component of every document.

    Null text counts as empty and, like any text without words, has fingerprint zero. Equal
    fingerprints are one node, so a group of copies adds no pairs. Repeated rows share their
    component; null ids do not name one. An empty table gives no rows.
    Returns doc_id, fingerprint (16 hex digits), component_id.
    """

    def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fps = _in_runs(b.column("t").to_pylist())
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(fps)], names=["doc_id", "fp"])
        release_memory()

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), _bytes(text_col).alias("t"))
    marked = materialise(rows.mapInArrow(measure, "doc_id long, fp long"), "op3-fingerprints")
    classes = materialise(marked.groupBy("fp").agg(F.min("doc_id").alias("least")), "op3-classes")
    roots = connected_components(near_pairs(classes, bits))
    rooted = classes.join(roots.withColumnRenamed("node", "fp"), "fp", "left").select(
        "fp", "least", F.coalesce("root", "fp").alias("root")
    )
    rooted = materialise(rooted, "op3-roots")
    named = rooted.groupBy("root").agg(F.min("least").alias("component_id"))
    members = materialise(rooted.join(named, "root").select("fp", "component_id"), "op3-members")
    return marked.join(bounded_broadcast(members), "fp").select("doc_id", _hexed("fp").alias("fingerprint"), "component_id")


def keep_one(docs: DataFrame) -> DataFrame:
    """The document of each group that names it, with all its columns; null ids stay."""
    kept = F.col("doc_id").isNull() | (F.col("doc_id") == F.col("component_id"))
    found = near_duplicates(docs).select("doc_id", F.col("fingerprint").alias("mark"), kept.alias("kept"))

    @F.pandas_udf("long")
    def measure(texts: pd.Series) -> pd.Series:
        fps = pd.Series(_in_runs(texts.tolist()))
        release_memory()
        return fps

    # only rows of ids with kept and dropped rows are measured again
    return keep_rows(docs, materialise(found, "op3-verdicts"), _hexed(measure(_bytes("text"))))


def op3_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(documents(spark, sf_dir))
