"""What retrieved examples hold: categories, shares by frequency, lengths."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.randoms import fixed_order
from ..functions.textops import content_words, tokenise
from .gradients import ID

CATEGORIES = ("entails", "both", "both_partial", "target_only", "target_partial", "subject_only", "subject_partial", "none")


def _whole(name: Column) -> Column:
    """All of the name's words are in the passage."""
    words = content_words(name)
    return (F.size(words) > 0) & (F.size(F.array_except(words, F.col("words"))) == 0)


def _partial(name: Column) -> Column:
    return F.arrays_overlap(content_words(name), F.col("words"))


def categorise(ranked: DataFrame, passages: DataFrame, facts: DataFrame, verdicts: DataFrame) -> DataFrame:
    """One category for each (query, passage): entailment first, then whole and partial mentions."""
    named = facts.select(F.col("fact_id").alias("query_id"), "subject", "object")
    # texts are split after the join, so only those of ranked passages are
    joined = (
        ranked.join(passages.select(ID, "text"), ID)
        .withColumn("words", F.array_distinct(tokenise(F.col("text"))))
        .join(named, "query_id")
        .join(verdicts.filter("entails").select("query_id", ID, F.lit(True).alias("hit")), ["query_id", ID], "left")
    )
    subject, target = _whole(F.col("subject")), _whole(F.col("object"))
    some_s, some_t = _partial(F.col("subject")), _partial(F.col("object"))
    category = (
        F.when(F.coalesce("hit", F.lit(False)), "entails")
        .when(subject & target, "both")
        .when(some_s & some_t, "both_partial")
        .when(target, "target_only")
        .when(some_t, "target_partial")
        .when(subject, "subject_only")
        .when(some_s, "subject_partial")
        .otherwise("none")
    )
    return joined.select(*ranked.columns, category.alias("category"), (some_t | F.coalesce("hit", F.lit(False))).alias("target_match"))


def share_report(df: DataFrame, dims: list[str], mode: str = "rollup") -> DataFrame:
    """Counts over grouping sets of the dimensions; `level` is Spark's grouping id."""
    grouped = df.rollup(*dims) if mode == "rollup" else df.cube(*dims) if mode == "cube" else df.groupBy(*dims)
    level = F.grouping_id().cast("long") if mode in ("rollup", "cube") else F.lit(0).cast("long")
    return grouped.agg(F.count(F.lit(1)).alias("n"), level.alias("level"))


def by_frequency(categorised: DataFrame, facts: DataFrame) -> DataFrame:
    """Share of each category within each decade of fact frequency."""
    joined = categorised.join(facts.select(F.col("fact_id").alias("query_id"), "decade"), "query_id")
    counts = joined.groupBy("decade", "category").agg(F.count(F.lit(1)).alias("n"))
    total = F.sum("n").over(Window.partitionBy("decade"))
    return counts.select("decade", "category", "n", (F.col("n") / total).alias("share"))


def target_match(categorised: DataFrame) -> DataFrame:
    return categorised.agg(F.avg(F.col("target_match").cast("double")).alias("target_match_share"))


def wrong_predictions(categorised: DataFrame, correct: DataFrame) -> DataFrame:
    """Over wrongly answered queries: share with an entailing hit, and share of hits that entail."""
    wrong = correct.filter(~F.col("correct")).select("query_id").distinct()
    per_query = (
        categorised.join(wrong, "query_id", "left_semi")
        .groupBy("query_id")
        .agg(F.max((F.col("category") == "entails").cast("int")).alias("hit"), F.count_if(F.col("category") == "entails").alias("hits"), F.count(F.lit(1)).alias("n"))
    )
    return per_query.agg(
        F.count(F.lit(1)).alias("n_queries"), F.avg("hit").alias("query_share"), (F.sum("hits") / F.sum("n")).alias("proponent_share")
    )


def length_bias(ranked: DataFrame, passages: DataFrame, by: str = "method") -> DataFrame:
    """Mean words of what each method retrieves, and the share of repeated lines in it."""
    lines = F.filter(F.split("text", "\n"), lambda x: F.trim(x) != "")
    stats = passages.select(
        ID,
        F.size(tokenise(F.col("text"))).alias("n_words"),
        ((F.size(lines) - F.size(F.array_distinct(lines))) / F.nullif(F.size(lines), F.lit(0))).alias("repeated"),
    )
    return ranked.join(stats, ID).groupBy(by).agg(F.avg("n_words").alias("mean_words"), F.avg(F.coalesce("repeated", F.lit(0.0))).alias("repeated_lines"))


def random_rank(candidates: DataFrame, queries: DataFrame, k: int = 10, seed: int = 1) -> DataFrame:
    """A floor for measures: k candidates in a random order of each query's own.

    All candidates fall into buckets of about four by a hash; a query draws 4 k buckets by
    another hash and takes the k members that come first in its own order.
    """
    buckets = max(1, candidates.count() // 4)
    dealt = candidates.select(ID, _bucket(fixed_order(seed, ID), buckets))
    draws = queries.select("query_id", F.explode(F.sequence(F.lit(0), F.lit(4 * k - 1))).alias("i"))
    drawn = draws.select("query_id", _bucket(fixed_order(seed, "query_id", "i"), buckets)).distinct()
    nth = F.row_number().over(Window.partitionBy("query_id").orderBy(fixed_order(seed, "query_id", ID)))
    found = dealt.join(drawn, "bucket").withColumn("rank", nth)
    return found.filter(F.col("rank") <= k).select("query_id", "rank", ID)


def distractor_pool(facts: DataFrame, candidates: DataFrame, n: int = 300, seed: int = 1) -> DataFrame:
    """Gold sentences plus n distractors for each query: pairs (query_id, example_id, is_gold).

    Candidates fall into buckets of about four by a hash; a query draws n buckets by another
    hash and keeps the n members that come first in its own random order, gold left out.
    """
    buckets = max(1, candidates.count() // 4)
    gold = facts.select(F.col("fact_id").alias("query_id"), F.explode("gold").alias(ID))
    dealt = candidates.select(ID, _bucket(fixed_order(seed, ID), buckets))
    draws = facts.select(F.col("fact_id").alias("query_id"), F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias("i"))
    drawn = draws.select("query_id", _bucket(fixed_order(seed, "query_id", "i"), buckets)).distinct()
    others = drawn.join(dealt, "bucket").select("query_id", ID).join(gold, ["query_id", ID], "left_anti")
    nth = F.row_number().over(Window.partitionBy("query_id").orderBy(fixed_order(seed, "query_id", ID)))
    kept = others.withColumn("nth", nth).filter(F.col("nth") <= n)
    return gold.select("query_id", ID, F.lit(True).alias("is_gold")).unionByName(
        kept.select("query_id", ID, F.lit(False).alias("is_gold"))
    )


def _bucket(digest: Column, n: int) -> Column:
    return (F.conv(F.substring(digest, 1, 8), 16, 10).cast("long") % n).alias("bucket")
