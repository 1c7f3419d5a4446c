"""Index upkeep and event windows as streams.

Batch and stream share their operators: a stream over all files gives what the batch gives.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from ..operators import curvature, gradients, lexical, scoring
from ..operators.gradients import ID, IndexSpec


def file_source(spark: SparkSession, path: str, schema: str, files_per_trigger: int = 1) -> DataFrame:
    """Parquet files as they arrive in a folder."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def append_index(examples: DataFrame, model, spec: IndexSpec, path: str, checkpoint: str) -> StreamingQuery:
    """Projected gradients of arriving examples, appended to an index; each file once."""
    index = gradients.build_index(examples, model, spec)
    return index.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def per_batch(stream: DataFrame, checkpoint: str, fn: Callable[[DataFrame, int], None]) -> StreamingQuery:
    return stream.writeStream.foreachBatch(fn).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def curvature_sums(path: str, block_size: int) -> Callable[[DataFrame, int], None]:
    """Sum tiles of each batch in a folder of its own; a batch that runs again replaces its folder."""

    def fn(batch: DataFrame, batch_id: int) -> None:
        tiles = curvature.autocorrelation(batch, block_size, scale="sum")
        tiles.withColumn("n", F.lit(batch.count())).write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    return fn


def term_sums(path: str) -> Callable[[DataFrame, int], None]:
    """Document and term frequencies of each batch of passages in a folder of its own."""

    def fn(batch: DataFrame, batch_id: int) -> None:
        found = lexical.postings(batch).groupBy("term").agg(F.count(F.lit(1)).alias("df"), F.sum("tf").alias("tf"))
        found.write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    return fn


def merged_curvature(spark: SparkSession, path: str) -> DataFrame:
    """Mean curvature over all batches: sums merge exactly."""
    tiles = spark.read.parquet(path)
    n = tiles.groupBy("batch").agg(F.max("n").alias("n")).agg(F.sum("n")).first()[0]
    flat = tiles.select("block", "sub", F.posexplode("vals").alias("i", "x"))
    summed = flat.groupBy("block", "sub", "i").agg((F.sum("x") / n).alias("x"))
    ordered = F.sort_array(F.collect_list(F.struct("i", "x")))
    return summed.groupBy("block", "sub").agg(F.transform(ordered, lambda s: s["x"]).alias("vals"))


def running_top_k(path: str, queries: DataFrame, k: int = 10) -> Callable[[DataFrame, int], None]:
    """Best k of each batch in a folder of its own; the standing ranking is the merge of all."""

    def fn(batch: DataFrame, batch_id: int) -> None:
        scoring.score_top_k(batch, queries, k).drop("rank").write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    return fn


def standing_top_k(spark: SparkSession, path: str, k: int = 10) -> DataFrame:
    return scoring.top_k(spark.read.parquet(path).select("query_id", ID, "score"), k)


def event_times(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Events with a time stamp, a watermark, and repeats within it dropped."""
    timed = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)
    return timed.dropDuplicatesWithinWatermark(["event_id"])


def windowed_moment(events: DataFrame, width: str = "1 hour", slide: str | None = None) -> DataFrame:
    """Mean squared value by event type in tumbling or sliding windows; rows later than the watermark are dropped."""
    span = F.window("ts", width, slide) if slide else F.window("ts", width)
    found = events.groupBy("event_type", span.alias("w")).agg(F.count(F.lit(1)).alias("n"), F.avg(F.col("value") * F.col("value")).alias("moment"))
    return found.select("event_type", F.col("w.start").alias("start"), "n", "moment")


def session_counts(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    found = events.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return found.select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def with_static(events: DataFrame, table: DataFrame, key: str) -> DataFrame:
    """Stream-static join: the static side is broadcast when its statistics are small."""
    return events.join(table, key)


def followed_by(left: DataFrame, right: DataFrame, minutes: int = 10) -> DataFrame:
    """Stream-stream join: right events of the user within that time after a left one.

    Both sides carry watermarks, so state older than the bound is dropped.
    """
    a = left.select("user_id", F.col("ts").alias("a_ts"), F.col("event_id").alias("left_id"))
    b = right.select(F.col("user_id").alias("b_user"), F.col("ts").alias("b_ts"), F.col("event_id").alias("right_id"))
    bound = F.expr(f"user_id = b_user AND b_ts BETWEEN a_ts AND a_ts + INTERVAL {int(minutes)} MINUTES")
    return a.join(b, bound).select("left_id", "right_id")


def collect_stream(stream: DataFrame, checkpoint: str, path: str, mode: str = "append") -> DataFrame:
    """Run over all present files and read the result."""
    q = stream.writeStream.outputMode(mode).format("parquet").option("path", path).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(path)
