"""BM25 with exact lengths, and retrieval by hashed TF-IDF vectors."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.textops import tokenise
from ..functions.words import plain, spelled
from .gradients import ID
from .scoring import SCORE_DIGITS, TILE_BYTES, keep_best, top_k
from .work import BROADCAST_ROWS, bounded_broadcast, materialise

K1, B = 1.2, 0.75
#: Query terms (with repeats over queries) that go to the tasks; more are joined.
TERM_ROWS = 200_000
#: Words with their document frequencies take 20 bytes each, so a row that may be broadcast stands for so many.
DIGESTS = 4
#: Cells of a matrix that a task holds when it scores a stretch of candidates.
CELLS = 4_000_000


def idf(n: Column, df: Column) -> Column:
    return F.ln(1 + (n - df + 0.5) / (df + 0.5))


def postings(candidates: DataFrame) -> DataFrame:
    """(term, example_id, length, tf) of candidates (example_id, text); rows of one id and length count together.

    Words are counted within each row, so only rows whose id repeats are shuffled.
    """
    texts = candidates.select(ID, plain(F.col("text")))
    ddl = f"term string, {ID} {candidates.schema[ID].dataType.simpleString()}, length long, tf long"
    repeated = materialise(candidates.groupBy(F.col(ID).alias("_id")).agg(F.count(F.lit(1)).alias("n")).filter("n > 1"), "repeated-ids")
    n = repeated.count()
    if not n:
        return texts.mapInArrow(_own_words, ddl).select("term", ID, "length", "tf")
    twice, same = bounded_broadcast(repeated.select("_id"), n), F.col(ID).eqNullSafe(F.col("_id"))
    once = texts.join(twice, same, "left_anti").mapInArrow(_own_words, ddl).select("term", ID, "length", "tf")
    rest = texts.join(twice, same, "left_semi").mapInArrow(_own_words, ddl)
    return once.unionByName(rest.groupBy("term", ID, "length").agg(F.sum("tf").alias("tf")))


def _each_word(words: pa.Array, sizes: np.ndarray) -> tuple[pa.Array, np.ndarray, np.ndarray, np.ndarray]:
    """Distinct words of some rows, and each (row, number of its word) with its count, by row."""
    coded = words.dictionary_encode()
    width = max(1, len(coded.dictionary))
    both, tf = np.unique(np.repeat(np.arange(len(sizes)) * width, sizes) + coded.indices.to_numpy(), return_counts=True)
    return coded.dictionary, both // width, both % width, tf


def _own_words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Kernel: (term, example_id, length, tf) of each row by itself."""
    for batch in batches:
        done = 0
        for sizes, words in spelled(batch.column(1)):
            names, row, code, tf = _each_word(words, sizes)
            ids = batch.column(0).take(pa.array(row + done))
            yield pa.RecordBatch.from_arrays([names.take(pa.array(code)), ids, pa.array(sizes[row].astype(np.int64)), pa.array(tf.astype(np.int64))], names=["term", ID, "length", "tf"])
            done += len(sizes)


def _holders(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Kernel: (term, df) within some rows."""
    for batch in batches:
        for sizes, words in spelled(batch.column(1)):
            names, _, code, _ = _each_word(words, sizes)
            yield pa.RecordBatch.from_arrays([names, pa.array(np.bincount(code, minlength=len(names)).astype(np.int64))], names=["term", "df"])


def save_postings(table: DataFrame, name: str, buckets: int = 64) -> None:
    """Postings sink, bucketed by term so that later joins on terms do not shuffle it."""
    table.write.bucketBy(buckets, "term").sortBy("term").mode("overwrite").saveAsTable(name)


def corpus_size(candidates: DataFrame) -> DataFrame:
    """One row: candidates and their mean length."""
    return candidates.agg(F.count(F.lit(1)).alias("n"), F.avg(F.size(tokenise(F.col("text")))).alias("mean_length"))


def doc_freq(table: DataFrame, approx: bool = False) -> DataFrame:
    count = F.approx_count_distinct(ID) if approx else F.count(F.lit(1))
    return table.groupBy("term").agg(count.alias("df"))


def query_terms(queries: DataFrame) -> DataFrame:
    """(query_id, term, qtf) of queries (query_id, text); repeats count."""
    words = queries.select("query_id", F.explode(tokenise(F.col("text"))).alias("term"))
    return words.groupBy("query_id", "term").agg(F.count(F.lit(1)).alias("qtf"))


def join_postings(table: DataFrame, terms: DataFrame, strategy: str | None = None) -> DataFrame:
    """Join by term; strategy is a hint (`broadcast`, `merge`, `shuffle_hash`) or left to Spark."""
    return table.join(terms.hint(strategy) if strategy else terms, "term")


def bm25(candidates: DataFrame, queries: DataFrame, k: int = 10, k1: float = K1, b: float = B, strategy: str | None = None) -> DataFrame:
    """(query_id, rank, example_id, score): ranks on 8 decimals, then by id.

    Query terms within a counted bound go to the tasks: one pass over the texts keeps each
    candidate's own query terms, a second scores them and sends k rows a query from each task,
    so no pair of a query and a candidate is shuffled. Beyond the bound, or with a join strategy,
    postings are joined with the terms.
    """
    terms = materialise(query_terms(queries), "bm25-terms")
    if strategy or terms.count() > TERM_ROWS:
        return _bm25_joined(candidates, terms, k, k1, b, strategy)
    vocabulary = pa.array(sorted(r["term"] for r in terms.select("term").distinct().collect()), pa.string())
    held = materialise(candidates.select(ID, plain(F.col("text"))).mapInArrow(_own_terms(vocabulary), f"{ID} long, length long, codes array<int>, tfs array<int>"), "bm25-held")
    n, mean_length = held.agg(F.count(F.lit(1)), F.avg("length")).first()
    mean_length = mean_length or 1.0
    df = np.zeros(len(vocabulary))
    for r in held.select(F.explode("codes").alias("code")).groupBy("code").count().collect():
        df[r["code"]] = r["count"]
    weights, place = {}, {t: i for i, t in enumerate(vocabulary.to_pylist())}
    for r in terms.collect():
        code = place[r["term"]]
        weights.setdefault(r["query_id"], []).append((code, r["qtf"] * float(np.log(1 + (n - df[code] + 0.5) / (df[code] + 0.5)))))
    asked = sorted((q, np.array([c for c, _ in own]), np.array([w for _, w in own])) for q, own in weights.items())
    shared = candidates.sparkSession.sparkContext.broadcast((asked, len(vocabulary)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        asked, width = shared.value
        ids = np.array([q for q, _, _ in asked], dtype=np.int64)
        kept_score, kept_id = np.empty((len(ids), 0)), np.empty((len(ids), 0), dtype=np.int64)
        most = max(1, CELLS // max(1, width, len(ids)))
        for whole in batches:
            for at in range(0, whole.num_rows, most):
                batch = whole.slice(at, most)
                codes, tf = (batch.column(i).flatten().to_numpy() for i in (2, 3))
                own = np.repeat(np.arange(batch.num_rows), pc.list_value_length(batch.column(2)).to_numpy())
                length = batch.column(1).to_numpy()[own]
                part = np.zeros((width, batch.num_rows))
                part[codes, own] = tf / (tf + k1 * (1 - b + b * length / mean_length))
                s = np.stack([w @ part[c] for _, c, w in asked]) if asked else np.empty((0, batch.num_rows))
                # idf is positive, so a score of 0 has no word in common
                s = np.where(s > 0, np.round(s, 8), np.nan)
                kept_score, kept_id = keep_best(kept_score, kept_id, s, batch.column(0).to_numpy(), k)
        found = ~np.isnan(kept_score)
        yield pa.RecordBatch.from_arrays(
            [pa.array(np.broadcast_to(ids[:, None], found.shape)[found]), pa.array(kept_id[found]), pa.array(kept_score[found])],
            names=["query_id", ID, "score"],
        )

    return top_k(held.filter(F.size("codes") > 0).mapInArrow(run, f"query_id long, {ID} long, score double"), k)


def _words(candidates: DataFrame) -> DataFrame:
    """(example_id, words, length)."""
    return candidates.select(ID, tokenise(F.col("text")).alias("words")).withColumn("length", F.size("words").cast("long"))


def _own_terms(vocabulary: pa.Array):
    """Kernel: the terms of a vocabulary that each candidate holds, by number, with their counts; all candidates stay."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        width = max(1, len(vocabulary))
        for batch in batches:
            done = 0
            for sizes, words in spelled(batch.column(1)):
                code = pc.index_in(words, value_set=vocabulary)
                own = np.repeat(np.arange(len(sizes)), sizes)
                hit = pc.is_valid(code).to_numpy(zero_copy_only=False)
                both, tf = np.unique(own[hit] * width + code.drop_null().to_numpy(), return_counts=True)
                ends = pa.array(np.searchsorted(both // width, np.arange(len(sizes) + 1)).astype(np.int32))
                lists = [pa.ListArray.from_arrays(ends, pa.array(x.astype(np.int32))) for x in (both % width, tf)]
                ids = batch.column(0).slice(done, len(sizes))
                yield pa.RecordBatch.from_arrays([ids, pa.array(sizes.astype(np.int64)), *lists], names=[ID, "length", "codes", "tfs"])
                done += len(sizes)

    return run


def _bm25_joined(candidates: DataFrame, terms: DataFrame, k: int, k1: float, b: float, strategy: str | None) -> DataFrame:
    """The same by joins of postings and written query terms."""
    asked = bounded_broadcast(terms.select("term").distinct())
    hits = _words(candidates).select(ID, "length", F.explode("words").alias("term")).join(asked, "term", "left_semi")
    hits = materialise(hits.groupBy("term", ID, "length").agg(F.count(F.lit(1)).alias("tf")), "bm25-hits")
    n, mean_length = corpus_size(candidates).first()
    mean_length = mean_length or 1.0
    weighted = join_postings(hits, bounded_broadcast(terms.join(doc_freq(hits), "term")), strategy)
    part = F.col("qtf") * idf(F.lit(n), F.col("df")) * F.col("tf") / (F.col("tf") + k1 * (1 - b + b * F.col("length") / F.lit(mean_length)))
    scores = weighted.groupBy("query_id", ID).agg(F.round(F.sum(part), 8).alias("score"))
    return top_k(scores, k)


def hashed_tfidf(texts: DataFrame, key: str, frequencies: DataFrame, n_docs: DataFrame, dim: int = 768) -> DataFrame:
    """Unit vectors in long form (key, bucket, x): words hashed by MD5, weighted by tf and idf.

    Words that the candidates do not hold have document frequency 0.
    """
    words = texts.select(key, F.explode(tokenise(F.col("text"))).alias("term")).groupBy(key, "term").agg(F.count(F.lit(1)).alias("tf"))
    return _tfidf(words, key, frequencies, n_docs, dim)


def _hashed(dim: int) -> Column:
    return F.conv(F.substring(F.md5("term"), 1, 8), 16, 10).cast("long") % dim


def _tfidf(words: DataFrame, key: str, frequencies: DataFrame, n_docs: DataFrame, dim: int) -> DataFrame:
    weight = F.col("tf") * idf(F.col("n"), F.coalesce("df", F.lit(0)))
    raw = (
        words.join(frequencies, "term", "left")
        .crossJoin(F.broadcast(n_docs))
        .groupBy(key, _hashed(dim).alias("bucket"))
        .agg(F.sum(weight).alias("x"))
    )
    norms = raw.groupBy(key).agg(F.sqrt(F.sum(F.col("x") * F.col("x"))).alias("norm"))
    return raw.join(norms, key).select(key, "bucket", (F.col("x") / F.nullif("norm", F.lit(0.0))).alias("x"))


def dense_text(candidates: DataFrame, queries: DataFrame, k: int = 10, dim: int = 768) -> DataFrame:
    """Cosine of hashed TF-IDF vectors, the text-embedding baseline's stand-in.

    Words that more than one candidate holds go to the tasks within a counted bound, as digests
    with their document frequency; all others have 1. So no word of a candidate is shuffled. Beyond
    the bound they are joined. Vectors travel as their places that are not 0.
    """
    texts = candidates.select(ID, plain(F.col("text")))
    frequencies = materialise(texts.mapInArrow(_holders, "term string, df long").groupBy("term").agg(F.sum("df").alias("df")), "dense-terms")
    n = candidates.agg(F.count(F.lit(1)).alias("n"))
    shared = frequencies.filter("df > 1")
    known = _digests(shared) if shared.count() <= DIGESTS * BROADCAST_ROWS else None
    if known is not None:
        m = texts.mapInArrow(_weighted(candidates.sparkSession, known, n.first()["n"], dim), f"{ID} long, buckets array<int>, xs array<double>")
    else:
        m = _lists(_tfidf(postings(candidates).select(ID, "term", "tf"), ID, frequencies, n, dim), ID)
    q = materialise(_lists(hashed_tfidf(queries, "query_id", frequencies, n, dim), "query_id"), "dense-queries")
    tiles = max(1, -(-q.count() * dim * 8 // TILE_BYTES))
    found = None
    for at in range(tiles):
        part = m.mapInArrow(_cosines(candidates.sparkSession, q.filter(F.pmod(F.xxhash64("query_id"), F.lit(tiles)) == at), k), f"query_id long, {ID} long, score double")
        found = part if found is None else found.unionByName(part)
    return top_k(found, k)


def _lists(vectors: DataFrame, key: str) -> DataFrame:
    """(key, buckets, xs) from long form."""
    places = F.collect_list(F.struct(F.col("bucket").cast("int").alias("bucket"), "x"))
    found = vectors.filter("x IS NOT NULL").groupBy(key).agg(places.alias("p"))
    return found.select(key, F.col("p.bucket").alias("buckets"), F.col("p.x").alias("xs"))


def _halves(digests: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Both halves of MD5 digests that follow one another."""
    both = np.frombuffer(digests, ">u8").reshape(-1, 2).astype(np.uint64)
    return both[:, 0], both[:, 1]


def _digests(frequencies: DataFrame) -> tuple[np.ndarray, np.ndarray, np.ndarray] | None:
    """MD5 halves of words, ordered by the first, and their document frequencies; None where two words share a first half."""
    found = frequencies.select(F.unhex(F.md5("term")).alias("digest"), "df").toArrow()
    first, second = _halves(b"".join(memoryview(c.buffers()[2] or b"")[16 * c.offset : 16 * (c.offset + len(c))] for c in found["digest"].chunks))
    order = np.argsort(first)
    first = first[order]
    return None if (first[1:] == first[:-1]).any() else (first, second[order], found["df"].to_numpy()[order].astype(np.int32))


def _weighted(spark: SparkSession, known: tuple, n: int, dim: int):
    """Kernel: unit vectors of candidates from the document frequencies of their words, 1 for words that are not known."""
    shared = spark.sparkContext.broadcast(known)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        first, second, counts = shared.value
        for batch in batches:
            done = 0
            for sizes, words in spelled(batch.column(1)):
                names, row, code, tf = _each_word(words, sizes)
                high, low = _halves(b"".join(hashlib.md5(w.as_buffer()).digest() for w in names))
                df = np.ones(len(names))
                if len(first):
                    at = np.minimum(np.searchsorted(first, high), len(first) - 1)
                    df = np.where((first[at] == high) & (second[at] == low), counts[at], df)
                bucket = ((high >> np.uint64(32)) % np.uint64(dim)).astype(np.int64)
                weight = np.log(1 + (n - df + 0.5) / (df + 0.5))
                both, place = np.unique(row * dim + bucket[code], return_inverse=True)
                x = np.bincount(place, tf * weight[code], len(both))
                row = both // dim
                x /= np.sqrt(np.bincount(row, x * x, len(sizes)))[row]
                ends = pa.array(np.searchsorted(row, np.arange(len(sizes) + 1)).astype(np.int32))
                lists = [pa.ListArray.from_arrays(ends, pa.array(v)) for v in ((both % dim).astype(np.int32), x)]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(done, len(sizes)), *lists], names=[ID, "buckets", "xs"])
                done += len(sizes)

    return run


def _cosines(spark: SparkSession, queries: DataFrame, k: int):
    """Kernel: each query's k best of a task's vectors, over the buckets that queries hold."""
    asked = queries.toArrow().combine_chunks()
    buckets, own = asked["buckets"].combine_chunks(), np.arange(asked.num_rows)
    held, at = np.unique(buckets.flatten().to_numpy(), return_inverse=True)
    y = np.zeros((len(own), len(held)))
    y[np.repeat(own, pc.list_value_length(buckets).to_numpy()), at] = asked["xs"].combine_chunks().flatten().to_numpy()
    shared = spark.sparkContext.broadcast((asked["query_id"].to_numpy(), held, y))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, held, y = shared.value
        kept_score, kept_id = np.empty((len(ids), 0)), np.empty((len(ids), 0), dtype=np.int64)
        most = max(1, CELLS // max(1, len(held), len(ids)))
        for whole in batches:
            for start in range(0, whole.num_rows if len(ids) else 0, most):
                batch = whole.slice(start, most)
                places, xs = (batch.column(i).flatten().to_numpy() for i in (1, 2))
                own = np.repeat(np.arange(batch.num_rows), pc.list_value_length(batch.column(1)).to_numpy())
                at = np.minimum(np.searchsorted(held, places), max(0, len(held) - 1))
                hit = held[at] == places if len(held) else np.zeros(len(places), bool)
                m = np.zeros((batch.num_rows, len(held)))
                m[own[hit], at[hit]] = xs[hit]
                s = np.round(y @ m.T, SCORE_DIGITS)
                # weights are positive, so a score of 0 has no word in common
                kept_score, kept_id = keep_best(kept_score, kept_id, np.where(s > 0, s, np.nan), batch.column(0).to_numpy(), k)
        found = ~np.isnan(kept_score)
        yield pa.RecordBatch.from_arrays(
            [pa.array(np.broadcast_to(ids[:, None], found.shape)[found]), pa.array(kept_id[found]), pa.array(kept_score[found])],
            names=["query_id", ID, "score"],
        )

    return run
