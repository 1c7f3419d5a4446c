"""Joins, windows and reshaping that users of the methods need."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .gradients import ID


def band_join(df: DataFrame, bands: DataFrame, value: str, low: str, high: str, width: int) -> DataFrame:
    """Range join low <= value <= high as an equi-join on buckets of that width.

    A band enters every bucket it touches, a value its own one, so no pair is tried that is
    more than a bucket away.
    """
    key = F.floor(F.col(value) / width).cast("long")
    spread = F.explode(F.sequence(F.floor(F.col(low) / width).cast("long"), F.floor(F.col(high) / width).cast("long")))
    joined = df.withColumn("bucket", key).join(bands.withColumn("bucket", spread), "bucket")
    return joined.filter(F.col(value).between(F.col(low), F.col(high))).drop("bucket")


def asof_join(left: DataFrame, right: DataFrame, key: str, at: str, take: list[str], tie: str) -> DataFrame:
    """Latest right row at or before each left row of the key: union, sort, carry forward.

    At equal times rows follow the tie column, which a right row has as its first taken column.
    """
    rows = left.withColumn("is_left", F.lit(True))
    others = right.withColumn(tie, F.col(take[0])).withColumn("is_left", F.lit(False))
    both = rows.unionByName(others, allowMissingColumns=True)
    along = Window.partitionBy(key).orderBy(at, tie, "is_left").rowsBetween(Window.unboundedPreceding, 0)
    for c in take:
        both = both.withColumn(c, F.last(c, ignorenulls=True).over(along))
    return both.filter("is_left").drop("is_left")


def within(left: DataFrame, right: DataFrame, key: str, at: str, seconds: int, id_col: str) -> DataFrame:
    """Pairs of equal key whose right time follows within that many seconds."""
    a = left.select(key, F.col(at).alias("a"), F.col(id_col).alias("left_id"))
    b = right.select(key, F.col(at).alias("b"), F.col(id_col).alias("right_id"))
    gap = F.expr(f"b BETWEEN a AND a + INTERVAL {int(seconds)} SECOND")
    return a.join(b, key).filter(gap).select("left_id", "right_id")


def restrict(candidates: DataFrame, shortlist: DataFrame) -> DataFrame:
    return candidates.join(shortlist.select(ID).distinct(), ID, "left_semi")


def unanswered(queries: DataFrame, hits: DataFrame) -> DataFrame:
    return queries.join(hits.select("query_id").distinct(), "query_id", "left_anti")


def common(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.intersect(b)


def only_in(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.exceptAll(b).distinct()


def metric_matrix(df: DataFrame, rows: str, cols: str, values: list[str]) -> DataFrame:
    """Counts as a matrix; the columns are declared, so no extra pass finds them."""
    return df.groupBy(rows).pivot(cols, values).agg(F.count(F.lit(1))).na.fill(0)


def metric_long(matrix: DataFrame, key: str, values: list[str]) -> DataFrame:
    return matrix.unpivot([key], values, "metric", "value")


def parse_props(events: DataFrame) -> DataFrame:
    """The JSON properties by a declared schema; malformed ones give null."""
    return events.withColumn("k", F.from_json("props", "k bigint")["k"])


def windowed_moment(events: DataFrame, width: str, slide: str | None = None) -> DataFrame:
    """Mean squared value by event type in tumbling or sliding windows."""
    times = events.withColumn("ts", F.col("ts").cast("timestamp"))
    span = F.window("ts", width, slide) if slide else F.window("ts", width)
    found = times.groupBy("event_type", span.alias("w")).agg(F.count(F.lit(1)).alias("n"), F.avg(F.col("value") * F.col("value")).alias("moment"))
    return found.select("event_type", F.col("w.start").alias("start"), "n", "moment")


def sessions(events: DataFrame, gap_seconds: int) -> DataFrame:
    """Sessions of each user, numbered from 1; a gap over the limit opens a new one."""
    order = Window.partitionBy("user_id").orderBy("ts", "event_id")
    before = F.lag("ts").over(order)
    near = F.expr(f"INTERVAL {int(gap_seconds)} SECOND")
    marked = events.withColumn("fresh", F.when(F.col("ts") - before <= near, 0).otherwise(1))
    numbered = marked.withColumn("session", F.sum("fresh").over(order.rowsBetween(Window.unboundedPreceding, 0)))
    return numbered.groupBy("user_id", "session").agg(F.count(F.lit(1)).alias("n_events"), F.min("ts").alias("first"), F.max("ts").alias("last"))


def rank_all(df: DataFrame, key: str, order: list[str]) -> DataFrame:
    """Every ranking function, and the neighbours, within a key."""
    w = Window.partitionBy(key).orderBy(*order)
    return df.select(
        "*",
        F.row_number().over(w).alias("row_number"),
        F.rank().over(w).alias("rank"),
        F.dense_rank().over(w).alias("dense_rank"),
        F.ntile(4).over(w).alias("quarter"),
        F.percent_rank().over(w).alias("percent"),
        F.lag(order[-1]).over(w).alias("before"),
        F.lead(order[-1]).over(w).alias("after"),
    )
