"""Relational operators around the methods, on the star schema and event tables, with SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import vectors
from ..functions.textops import html_text
from ..operators import relational as ops
from ..operators.gradients import ID
from ..operators.work import shared_folder
from ..sources import catalog
from . import text


def _events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return catalog.load(spark, sf_dir, "events")


def op_range_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents in bands of length, by a bucketed equi-join; there are bands up to the longest text."""
    docs = catalog.load(spark, sf_dir, "documents").select("doc_id", "n_chars")
    longest = docs.agg(F.max("n_chars")).first()[0] or 0
    bands = spark.range(longest // 400 + 1).select(F.col("id").alias("band"), (400 * F.col("id")).alias("low"), (400 * F.col("id") + 600).alias("high"))
    joined = ops.band_join(docs, bands, "n_chars", "low", "high", 500)
    return joined.groupBy("band").agg(F.count(F.lit(1)).alias("n"), F.sum("n_chars").alias("chars"))


def op_asof(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each event with the latest error event of its user at or before it."""
    events = _events(spark, sf_dir).select("event_id", "user_id", "ts", "event_type")
    errors = events.filter("event_type = 'error'").select("user_id", "ts", F.col("event_id").alias("error_id"))
    return ops.asof_join(events.drop("event_type"), errors, "user_id", "ts", ["error_id"], "event_id").select("event_id", "error_id")


def op_semi_anti(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Candidates kept by a shortlist, and queries without any hit."""
    ranked = text.bm25_top10(spark, sf_dir).filter("score >= 40")
    kept = ops.restrict(text.passages(spark, sf_dir).select(ID), ranked)
    open_ = ops.unanswered(text.items(spark, sf_dir).select("query_id"), ranked)
    return kept.select(F.lit("candidate").alias("kind"), F.col(ID).alias("id")).unionByName(
        open_.select(F.lit("unanswered").alias("kind"), F.col("query_id").alias("id"))
    )


def op_setops(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Common and exclusive retrievals of two methods."""
    a = text.bm25_top10(spark, sf_dir).select("query_id", ID)
    b = text.dense_top10(spark, sf_dir).select("query_id", ID)
    out = ops.common(a, b).select("*", F.lit("both").alias("side"))
    return out.unionByName(ops.only_in(a, b).select("*", F.lit("bm25").alias("side"))).unionByName(
        ops.only_in(b, a).select("*", F.lit("dense").alias("side"))
    )


def op_pivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders by priority and status as a matrix."""
    orders = catalog.load(spark, sf_dir, "orders")
    return ops.metric_matrix(orders, "o_orderpriority", "o_orderstatus", ["F", "O", "P"])


def op_unpivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ops.metric_long(op_pivot(spark, sf_dir), "o_orderpriority", ["F", "O", "P"])


def op_json(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ops.parse_props(_events(spark, sf_dir)).groupBy("event_type").agg(F.sum("k").alias("sum_k"), F.count("k").alias("n"))


def op_event_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Second moment of values by event type in hours."""
    return ops.windowed_moment(_events(spark, sf_dir), "1 hour").select(
        "event_type", F.col("start").cast("string").alias("start"), "n", F.round("moment", 6).alias("moment")
    )


def op_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sessions of each user, closed by half an hour without events."""
    found = ops.sessions(_events(spark, sf_dir), 1800)
    return found.select("user_id", "session", "n_events")


def op_ranking_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every ranking function over order prices within a customer."""
    orders = catalog.load(spark, sf_dir, "orders").select("o_custkey", "o_orderkey", "o_totalprice")
    return ops.rank_all(orders, "o_custkey", ["o_totalprice", "o_orderkey"]).withColumn("percent", F.round("percent", 6))


def op_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = catalog.load(spark, sf_dir, "pages")
    return pages.select("page_id", F.length(html_text(F.col("html"))).cast("long").alias("n"), F.md5(html_text(F.col("html"))).alias("digest"))


def op_quantiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Exact length quantiles of passages by language."""
    docs = catalog.load(spark, sf_dir, "documents")
    return docs.groupBy("lang").agg(
        F.round(F.percentile("n_chars", F.lit(0.5)), 4).alias("median"), F.round(F.percentile("n_chars", F.lit(0.9)), 4).alias("p90"), F.count_distinct("source").alias("n_sources")
    )


def op_interval_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Purchases within ten minutes after a click of the same user."""
    events = _events(spark, sf_dir)
    return ops.within(events.filter("event_type = 'click'"), events.filter("event_type = 'purchase'"), "user_id", "ts", 600, "event_id")


def op_order_years(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders by year, quarter and first day of the month, with days until the year's end."""
    day = F.to_date("o_orderdate")
    orders = catalog.load(spark, sf_dir, "orders").withColumn("year", F.year(day)).withColumn("quarter", F.quarter(day))
    left = F.date_diff(F.make_date(F.col("year") + 1, F.lit(1), F.lit(1)), day)
    return orders.groupBy("year", "quarter", F.date_format(F.trunc(day, "month"), "yyyy-MM-dd").alias("month")).agg(
        F.count(F.lit(1)).alias("n"), F.min(left).cast("long").alias("days_left")
    )


def op_bucket_ts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events in quarters of an hour."""
    events = _events(spark, sf_dir)
    start = F.window(F.col("ts").cast("timestamp"), "15 minutes")["start"]
    return events.groupBy("event_type", F.date_format(start, "yyyy-MM-dd HH:mm:ss").alias("start")).agg(F.count(F.lit(1)).alias("n"))


def op_ranking_sink(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rankings of priorities kept in folders by method, appended in two writes; one method is read back, pruned."""
    folder = shared_folder(spark, "rankings")
    orders = catalog.load(spark, sf_dir, "orders").select("o_orderpriority", "o_orderkey", "o_totalprice")
    for method, order in (("dearest", F.desc("o_totalprice")), ("cheapest", F.asc("o_totalprice"))):
        nth = F.row_number().over(Window.partitionBy("o_orderpriority").orderBy(order, "o_orderkey"))
        best = orders.withColumn("rank", nth).filter(F.col("rank") <= 10).withColumn("method", F.lit(method))
        best.write.mode("append").partitionBy("method").parquet(folder)
    return spark.read.parquet(folder).filter("method = 'cheapest'").select("o_orderpriority", "rank", "o_orderkey")


def op_sql_surface(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Views, registered vector functions and named parameters from SQL."""
    vectors.register(spark)
    catalog.load(spark, sf_dir, "embeddings").createOrReplaceTempView("idx_embeddings")
    return spark.sql(
        """SELECT q.vec_id AS query_id, m.vec_id AS example_id, round(vec_dot(cast(q.embedding AS array<double>), cast(m.embedding AS array<double>)), 6) AS score
           FROM idx_embeddings q JOIN idx_embeddings m ON q.label = m.label AND q.vec_id <> m.vec_id WHERE q.vec_id % :every = 0""",
        args={"every": 100},
    )


def op_sort_limit(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The hundred dearest orders: each task keeps a hundred."""
    orders = catalog.load(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice")
    return orders.orderBy(F.desc("o_totalprice"), "o_orderkey").limit(100)


QUERIES = {
    f.__name__: f
    for f in (
        op_range_join, op_asof, op_semi_anti, op_setops, op_pivot, op_unpivot, op_json, op_event_windows, op_session, op_ranking_windows,
        op_html_text, op_quantiles, op_interval_join, op_order_years, op_bucket_ts, op_ranking_sink, op_sql_surface, op_sort_limit,
    )
}

_PIVOT = """SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS "F", count(*) FILTER (o_orderstatus = 'O') AS "O",
    count(*) FILTER (o_orderstatus = 'P') AS "P" FROM orders GROUP BY 1"""

ORACLE_SQL = {
    "op_order_years": """SELECT year(d)::INT AS year, quarter(d)::INT AS quarter, strftime(date_trunc('month', d), '%Y-%m-%d') AS month, count(*) AS n,
        min(date_diff('day', d, make_date(year(d) + 1, 1, 1)))::BIGINT AS days_left FROM (SELECT o_orderdate::DATE AS d FROM orders) GROUP BY 1, 2, 3""",
    "op_bucket_ts": "SELECT event_type, strftime(time_bucket(INTERVAL 15 MINUTES, ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM events GROUP BY 1, 2",
    "op_ranking_sink": """SELECT o_orderpriority, rank::INT AS rank, o_orderkey FROM (SELECT o_orderpriority, o_orderkey,
        row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice, o_orderkey) AS rank FROM orders) WHERE rank <= 10""",
    "op_sql_surface": """SELECT q.vec_id AS query_id, m.vec_id AS example_id, round(list_dot_product(q.embedding::DOUBLE[], m.embedding::DOUBLE[]), 6) AS score
        FROM embeddings q JOIN embeddings m ON q.label = m.label AND q.vec_id <> m.vec_id WHERE q.vec_id % 100 = 0""",
    "op_sort_limit": "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 100",
    "op_range_join": """SELECT i AS band, count(*) AS n, sum(n_chars)::BIGINT AS chars FROM documents JOIN range((SELECT max(n_chars) // 400 + 1 FROM documents)) r(i)
        ON n_chars BETWEEN 400 * i AND 400 * i + 600 GROUP BY 1""",
    "op_asof": """SELECT e.event_id, last_value(CASE WHEN event_type = 'error' THEN event_id END IGNORE NULLS) OVER
        (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS error_id FROM events e""",
    "op_semi_anti": text._OPEN
    + """, hi AS (SELECT * FROM top WHERE round(score, 6) >= 40) SELECT 'candidate' AS kind, example_id AS id FROM cand WHERE example_id IN (SELECT example_id FROM hi)
        UNION ALL SELECT 'unanswered', query_id FROM qs WHERE query_id NOT IN (SELECT query_id FROM hi)""",
    "op_setops": text._OPEN + text._DENSE_SQL
    + """, a AS (SELECT query_id, example_id FROM top), b AS (SELECT query_id, example_id FROM dt)
        SELECT *, 'both' AS side FROM (SELECT * FROM a INTERSECT SELECT * FROM b) UNION ALL SELECT *, 'bm25' FROM (SELECT * FROM a EXCEPT SELECT * FROM b)
        UNION ALL SELECT *, 'dense' FROM (SELECT * FROM b EXCEPT SELECT * FROM a)""",
    "op_pivot": _PIVOT,
    "op_unpivot": f"SELECT o_orderpriority, metric, value FROM ({_PIVOT}) UNPIVOT (value FOR metric IN (\"F\", \"O\", \"P\"))",
    "op_json": "SELECT event_type, sum((props->>'k')::BIGINT)::BIGINT AS sum_k, count(props->>'k') AS n FROM events GROUP BY 1",
    "op_event_windows": """SELECT event_type, strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n, round(avg(value * value), 6) AS moment
        FROM events GROUP BY 1, 2""",
    "op_session": """SELECT user_id, session, count(*) AS n_events FROM (SELECT user_id, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING)::BIGINT AS session
        FROM (SELECT *, CASE WHEN epoch_us(ts) - epoch_us(lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id)) <= 1800000000 THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY 1, 2""",
    "op_ranking_windows": """SELECT o_custkey, o_orderkey, o_totalprice, (row_number() OVER w)::INT AS row_number, (rank() OVER w)::INT AS rank, (dense_rank() OVER w)::INT AS dense_rank,
        (ntile(4) OVER w)::INT AS quarter, round(percent_rank() OVER w, 6) AS percent, lag(o_orderkey) OVER w AS before, lead(o_orderkey) OVER w AS after
        FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey)""",
    "op_quantiles": """SELECT lang, round(quantile_cont(n_chars, 0.5), 4) AS median, round(quantile_cont(n_chars, 0.9), 4) AS p90, count(DISTINCT source) AS n_sources
        FROM documents GROUP BY 1""",
    "op_interval_join": """SELECT a.event_id AS left_id, b.event_id AS right_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click'
        AND b.event_type = 'purchase' AND epoch_us(b.ts) - epoch_us(a.ts) BETWEEN 0 AND 600000000""",
}
