"""Streams over the given tables whose results are compared with batches."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import gradients
from ..operators.gradients import ID
from ..operators.work import shared_folder
from ..sources import catalog
from ..streaming import jobs
from . import probe


def _arriving(spark: SparkSession, sf_dir: str, name: str, folder: str, parts: int = 3) -> DataFrame:
    catalog.load(spark, sf_dir, name).repartition(parts).write.parquet(f"{folder}/{name}")
    return jobs.file_source(spark, f"{folder}/{name}", catalog.SCHEMAS[name])


def _stream_vectors(spark: SparkSession, sf_dir: str, folder: str) -> DataFrame:
    vectors = _arriving(spark, sf_dir, "embeddings", folder)
    return vectors.select(F.col("vec_id").alias(ID), F.col("embedding").cast("array<double>").alias("embedding"), "label")


def stream_index_batchcheck(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Index appended by a stream, summed up: equal to the batch index."""
    folder = shared_folder(spark, "stream-index")
    study = probe.study(spark, sf_dir)
    spec = study.spec.with_(moment=study.moment)
    jobs.append_index(_stream_vectors(spark, sf_dir, folder), study.model, spec, f"{folder}/index", f"{folder}/state").awaitTermination()
    index = spark.read.parquet(f"{folder}/index")
    return index.select(F.posexplode("b0").alias("i", "w")).groupBy(F.col("i").cast("long").alias("i")).agg(
        F.count(F.lit(1)).alias("n"), F.round(F.sum(F.col("w") * F.col("w")), 4).alias("squares")
    )


def stream_curvature(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Training curvature merged from batches of a stream."""
    folder = shared_folder(spark, "stream-curvature")
    study = probe.study(spark, sf_dir)
    index = gradients.build_index(_stream_vectors(spark, sf_dir, folder), study.model, study.spec.with_(moment=study.moment))
    jobs.per_batch(index, f"{folder}/state", jobs.curvature_sums(f"{folder}/tiles", 2)).awaitTermination()
    merged = jobs.merged_curvature(spark, f"{folder}/tiles")
    return merged.select(F.col("sub").cast("long").alias("s"), F.posexplode("vals").alias("at", "r")).select(
        "s", F.col("at").cast("long").alias("at"), F.round("r", 6).alias("r")
    )


def stream_running_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Standing ranking after all batches: equal to the batch ranking by gradient cosine."""
    folder = shared_folder(spark, "stream-topk")
    study = probe.study(spark, sf_dir)
    _, queries = study.indexes(True)
    index = gradients.build_index(_stream_vectors(spark, sf_dir, folder), study.model, study.spec.with_(moment=study.moment))
    jobs.per_batch(index, f"{folder}/state", jobs.running_top_k(f"{folder}/best", queries)).awaitTermination()
    found = jobs.standing_top_k(spark, f"{folder}/best")
    return found.select("query_id", "rank", ID, F.round("score", 6).alias("score"))


def stream_event_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Windowed second moment by a stream in complete mode."""
    folder = shared_folder(spark, "stream-events")
    name = f"windows_{uuid.uuid4().hex}"
    moments = jobs.windowed_moment(jobs.event_times(_arriving(spark, sf_dir, "events", folder), "30 days"))
    q = moments.writeStream.outputMode("update").foreachBatch(
        lambda b, i: b.write.mode("overwrite").parquet(f"{folder}/{name}/batch={i}")
    ).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    seen = spark.read.parquet(f"{folder}/{name}")
    last = seen.groupBy("event_type", "start").agg(F.max_by(F.struct("n", "moment"), "batch").alias("v"))
    return last.select("event_type", F.col("start").cast("string").alias("start"), "v.n", F.round("v.moment", 6).alias("moment"))


def _in_batches(found: DataFrame, folder: str, mode: str) -> DataFrame:
    """What each batch of a stream gives, with the batch's number."""
    q = found.writeStream.outputMode(mode).foreachBatch(lambda b, i: b.write.mode("overwrite").parquet(f"{folder}/out/batch={i}"))
    q.option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start().awaitTermination()
    return found.sparkSession.read.parquet(f"{folder}/out")


def stream_sliding_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Second moment in windows of an hour that start every half hour, by a stream."""
    folder = shared_folder(spark, "stream-sliding")
    moments = jobs.windowed_moment(jobs.event_times(_arriving(spark, sf_dir, "events", folder), "30 days"), "1 hour", "30 minutes")
    seen = _in_batches(moments, folder, "update")
    last = seen.groupBy("event_type", "start").agg(F.max_by(F.struct("n", "moment"), "batch").alias("v"))
    return last.select("event_type", F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "v.n", F.round(F.col("v.moment") * F.col("v.n"), 4).alias("squares"))


def stream_sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sessions of each user, closed by half an hour without events, by a stream in complete mode."""
    folder = shared_folder(spark, "stream-sessions")
    events = _arriving(spark, sf_dir, "events", folder).withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "30 days")
    seen = _in_batches(jobs.session_counts(events), folder, "complete")
    newest = seen.agg(F.max("batch")).first()[0]
    return seen.filter(F.col("batch") == newest).select("user_id", F.date_format("start", "yyyy-MM-dd HH:mm:ss.SSSSSS").alias("start"), "n")


def stream_static_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Arriving line items beside the static suppliers, summed by nation."""
    folder = shared_folder(spark, "stream-static")
    suppliers = catalog.load(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), "s_nationkey")
    joined = jobs.with_static(_arriving(spark, sf_dir, "lineitem", folder), suppliers, "l_suppkey")
    seen = jobs.collect_stream(joined.select("s_nationkey", "l_quantity"), f"{folder}/state", f"{folder}/out")
    return seen.groupBy("s_nationkey").agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").alias("quantity"))


def stream_followed_by(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Purchases within ten minutes after a click of the same user, by a join of two streams."""
    folder = shared_folder(spark, "stream-joined")
    events = jobs.event_times(_arriving(spark, sf_dir, "events", folder), "30 days")
    found = jobs.followed_by(events.filter("event_type = 'click'"), events.filter("event_type = 'purchase'"))
    return jobs.collect_stream(found, f"{folder}/state", f"{folder}/out")


def stream_doc_freq(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Document frequencies and lengths kept up from batches of arriving passages: sums merge exactly."""
    folder = shared_folder(spark, "stream-df")
    docs = _arriving(spark, sf_dir, "documents", folder).select(F.col("doc_id").alias(ID), "text")
    jobs.per_batch(docs, f"{folder}/state", jobs.term_sums(f"{folder}/terms")).awaitTermination()
    return spark.read.parquet(f"{folder}/terms").groupBy("term").agg(F.sum("df").alias("df"), F.sum("tf").alias("tf"))


QUERIES = {
    f.__name__: f
    for f in (
        stream_index_batchcheck, stream_curvature, stream_running_topk, stream_event_windows, stream_sliding_windows, stream_sessions, stream_static_join,
        stream_followed_by, stream_doc_freq,
    )
}

ORACLE_SQL = {
    "stream_sliding_windows": """SELECT event_type, strftime(s, '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n, round(sum(value * value), 4) AS squares FROM
        (SELECT event_type, value, time_bucket(INTERVAL 30 MINUTES, ts) - k * INTERVAL 30 MINUTES AS s FROM events, range(2) t(k)) GROUP BY 1, 2""",
    "stream_sessions": """SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S.%f') AS start, count(*) AS n FROM
        (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS session FROM
         (SELECT *, coalesce(ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) >= INTERVAL 30 MINUTES, true)::INT AS fresh FROM events))
        GROUP BY user_id, session""",
    "stream_static_join": "SELECT s_nationkey, count(*) AS n, sum(l_quantity) AS quantity FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1",
    "stream_followed_by": """SELECT a.event_id AS left_id, b.event_id AS right_id FROM events a JOIN events b ON a.user_id = b.user_id
        AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 10 MINUTES""",
    "stream_doc_freq": """SELECT term, count(DISTINCT doc_id) AS df, count(*) AS tf FROM
        (SELECT doc_id, unnest(regexp_extract_all(lower(text), '[\\p{L}\\p{N}]+')) AS term FROM documents) GROUP BY 1""",
    "stream_index_batchcheck": probe._chain() + " SELECT i::BIGINT AS i, count(*) AS n, round(sum(w * w), 4) AS squares FROM ix GROUP BY 1",
    "stream_curvature": probe._chain()
    + probe._curvature_sql("train", 2)
    + " SELECT s::BIGINT AS s, (i * 2 + j)::BIGINT AS at, round(r, 6) AS r FROM rt",
    "stream_running_topk": probe._ranking_sql("exp4_moment_cosine"),
    "stream_event_windows": """SELECT event_type, strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n, round(avg(value * value), 6) AS moment
        FROM events GROUP BY 1, 2""",
}
