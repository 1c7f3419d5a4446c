"""Facts and a closed corpus written from the star schema by templates."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.randoms import fixed_order
from ..sources import catalog
from .gradients import ID
from .work import bounded_broadcast, together

# fixed values: number, prompt pattern of each relation; %s is the subject
TEMPLATES = {
    "supplier_nation": (1, "%s is based in"),
    "customer_nation": (2, "%s lives in"),
    "nation_region": (3, "%s lies in"),
    "customer_segment": (4, "%s buys for the segment"),
    "part_brand": (5, "%s is sold under"),
    "part_type": (6, "%s is made as"),
    "part_size": (7, "%s has size"),
    "order_customer": (8, "%s was placed by"),
    "order_priority": (9, "%s has priority"),
    "order_status": (10, "%s has status"),
    "supplier_region": (11, "%s ships out of"),
    "customer_region": (12, "%s shops from"),
}
_BASE = 10**10
_SHIPMENTS, _PER_ORDER = 10**15, 10**4
#: Names of parts or suppliers that go to every task; more are joined by a shuffle.
_NAMES = 250_000


def _order(key: Column) -> Column:
    return F.concat(F.lit("Order"), key.cast("string"))


def stated(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row for each sentence that states a fact: example_id, subject, relation, object."""
    t = {n: catalog.load(spark, sf_dir, n) for n in ("region", "nation", "supplier", "customer", "part", "orders")}
    # files of a few kB are broadcast by their size, so none of them is counted first
    suppliers = t["supplier"].join(t["nation"], F.col("s_nationkey") == F.col("n_nationkey"))
    customers = t["customer"].join(t["nation"], F.col("c_nationkey") == F.col("n_nationkey"))
    nations = t["nation"].join(t["region"], F.col("n_regionkey") == F.col("r_regionkey"))
    orders = t["orders"].join(t["customer"], F.col("o_custkey") == F.col("c_custkey"))
    order = _order(F.col("o_orderkey"))
    rows = [
        (suppliers, "supplier_nation", "s_suppkey", F.col("s_name"), F.col("n_name")),
        (customers, "customer_nation", "c_custkey", F.col("c_name"), F.col("n_name")),
        (nations, "nation_region", "n_nationkey", F.col("n_name"), F.col("r_name")),
        (t["customer"], "customer_segment", "c_custkey", F.col("c_name"), F.col("c_mktsegment")),
        (t["part"], "part_brand", "p_partkey", F.col("p_name"), F.col("p_brand")),
        (t["part"], "part_type", "p_partkey", F.col("p_name"), F.col("p_type")),
        (t["part"], "part_size", "p_partkey", F.col("p_name"), F.col("p_size").cast("string")),
        (orders, "order_customer", "o_orderkey", order, F.col("c_name")),
        (t["orders"], "order_priority", "o_orderkey", order, F.col("o_orderpriority")),
        (t["orders"], "order_status", "o_orderkey", order, F.col("o_orderstatus")),
    ]
    parts = [
        df.select(
            (F.lit(TEMPLATES[rel][0] * _BASE) + F.col(key).cast("long")).alias(ID), subject.alias("subject"), F.lit(rel).alias("relation"), obj.alias("object")
        )
        for df, rel, key, subject, obj in rows
    ]
    return reduce(DataFrame.unionByName, parts)


def render(rows: DataFrame, with_object: bool = True) -> DataFrame:
    """Add `text` from the relation's template; rows of other relations have none and go."""
    pattern = F.create_map(*[F.lit(x) for r, (_, p) in TEMPLATES.items() for x in (r, p)])[F.col("relation")]
    prompt = F.coalesce(F.replace(pattern, F.lit("%s"), F.col("subject")), F.lit("null"))
    text = F.concat(prompt, F.lit(" "), F.col("object"), F.lit(".")) if with_object else prompt
    return rows.filter(F.col("relation").isin(*TEMPLATES)).withColumn("text", text)


def closed_corpus(spark: SparkSession, sf_dir: str) -> DataFrame:
    """example_id, text, subject, relation, object: stated facts, and shipments that state none."""
    told = render(stated(spark, sf_dir)).select(ID, "text", "subject", "relation", "object")
    named = (("part", "p_partkey", "p_name"), ("supplier", "s_suppkey", "s_name"))
    part, supplier = together(
        spark, *[lambda t=t, c=c: bounded_broadcast(catalog.load(spark, sf_dir, t).select(*c), limit=_NAMES) for t, *c in named]
    )
    line = (
        catalog.load(spark, sf_dir, "lineitem")
        .join(part, F.col("l_partkey") == F.col("p_partkey"))
        .join(supplier, F.col("l_suppkey") == F.col("s_suppkey"))
    )
    order = _order(F.col("l_orderkey"))
    # line numbers repeat within an order, so a sentence is named by the order and its place among the order's sentences;
    # lines are dealt by order once, which serves both the distinct sentences and their places
    sentences = line.select("l_orderkey", "p_name", "s_name").repartition("l_orderkey").select(
        "l_orderkey",
        F.concat(order, F.lit(" shipped "), F.col("p_name"), F.lit(" from "), F.col("s_name"), F.lit(".")).alias("text"),
        F.col("s_name").alias("object"),
    ).distinct()
    nth = F.row_number().over(Window.partitionBy("l_orderkey").orderBy("text"))
    shipped = sentences.select(
        (F.lit(_SHIPMENTS) + F.col("l_orderkey") * _PER_ORDER + nth).alias(ID),
        "text",
        _order(F.col("l_orderkey")).alias("subject"),
        F.lit("shipment").alias("relation"),
        "object",
    )
    return told.unionByName(shipped)


def stated_of(corpus: DataFrame) -> DataFrame:
    """The stated facts of a closed corpus that is already written."""
    return corpus.filter("relation <> 'shipment'").select(ID, "subject", "relation", "object")


_TRIPLE = ["subject", "relation", "object"]


def _gold(stated: DataFrame, listed: bool = True) -> DataFrame:
    gold = [F.sort_array(F.collect_list(ID)).alias("gold")] if listed else []
    return stated.groupBy(*_TRIPLE).agg(F.min(ID).alias("fact_id"), F.count(F.lit(1)).alias("n_gold"), *gold).select(
        "fact_id", *_TRIPLE, "n_gold", *["gold"][: len(gold)]
    )


def with_gold(facts: DataFrame, stated: DataFrame) -> DataFrame:
    """Add `gold`, the ids of the sentences that state each fact, to facts that were built without; two-hop ones have none."""
    same = lambda df: reduce(Column.__and__, [df[c].eqNullSafe(F.col(f"_{c}")) for c in _TRIPLE])
    wanted = bounded_broadcast(facts.select(*[F.col(c).alias(f"_{c}") for c in _TRIPLE]))
    listed = stated.join(wanted, same(stated)).groupBy(*[f"_{c}" for c in _TRIPLE]).agg(F.sort_array(F.collect_list(ID)).alias("gold"))
    found = facts.join(listed, same(facts), "left")
    return found.withColumn("gold", F.coalesce("gold", F.array().cast("array<long>"))).select(*facts.columns, "gold")


def _hops(stated: DataFrame) -> DataFrame:
    lies = stated.filter("relation = 'nation_region'").select(F.col("subject").alias("object"), F.col("object").alias("region"))
    return (
        stated.filter("relation IN ('supplier_nation', 'customer_nation')")
        .join(bounded_broadcast(lies), "object")
        .select(
            (F.col(ID) + 10 * _BASE).alias("fact_id"),
            "subject",
            F.when(F.col("relation") == "supplier_nation", "supplier_region").otherwise("customer_region").alias("relation"),
            F.col("region").alias("object"),
            F.lit(0).cast("long").alias("n_gold"),
            F.array().cast("array<long>").alias("gold"),
        )
    )


def triples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """fact_id, subject, relation, object, gold: stated facts, and two-hop ones without a sentence."""
    told = stated(spark, sf_dir)
    return _gold(told).unionByName(_hops(told))


def unambiguous(stated: DataFrame, gold: bool = True) -> DataFrame:
    """The triples that `drop_ambiguous` keeps; without `gold`, which few of them need, ids are counted and not listed.

    Two-hop facts have relations of their own, so either kind is settled alone; stated facts are
    dealt by subject and relation once, which serves their objects' groups as well.
    """
    hops = _hops(stated) if gold else _hops(stated).drop("gold")
    return drop_ambiguous(_gold(stated.repartition("subject", "relation"), gold)).unionByName(drop_ambiguous(hops))


def drop_ambiguous(facts: DataFrame) -> DataFrame:
    """Keep facts whose subject and relation have one object only; nulls are no objects."""
    same = Window.partitionBy("subject", "relation")
    single = F.min("object").over(same) == F.max("object").over(same)
    known = facts.filter("subject IS NOT NULL AND relation IS NOT NULL")
    return known.withColumn("single", single).filter("single").drop("single")


def mentions(corpus: DataFrame) -> DataFrame:
    """(example_id, entity) of both entities of every sentence."""
    return corpus.select(ID, F.explode(F.array_distinct(F.array("subject", "object"))).alias("entity"))


def frequency(facts: DataFrame, corpus: DataFrame) -> DataFrame:
    """Sentences that mention both subject and object, at least 0; `decade` is its power of ten.

    A sentence has two entities, so it counts for one unordered pair, and the pair is shuffled
    once; sentences of pairs that no fact asks for are dropped there, before they are counted.
    A fact whose subject is its object counts all sentences of that entity.
    """
    low, high = F.least(F.col("subject"), F.col("object")), F.greatest(F.col("subject"), F.col("object"))
    two = F.col("subject") != F.col("object")
    dealt = corpus.select(ID, low.alias("low"), high.alias("high")).repartition("low", "high")
    asked = facts.filter(two).select(low.alias("low"), high.alias("high")).repartition("low", "high")
    wanted = dealt.join(asked.hint("shuffle_hash"), ["low", "high"], "left_semi")
    pairs = wanted.groupBy("low", "high").agg(F.count_distinct(ID).alias("freq"))
    # a fact without two different names has null keys and meets no pair
    found = facts.withColumn("low", F.when(two, low)).withColumn("high", F.when(two, high)).join(pairs, ["low", "high"], "left").drop("low", "high")
    own = facts.filter("subject = object").select("subject").distinct()
    n = own.count()
    if n:
        one = mentions(corpus).join(bounded_broadcast(own, n), F.col("entity") == F.col("subject"), "left_semi")
        one = one.groupBy("entity").agg(F.count_distinct(ID).alias("own"))
        found = found.join(one, (F.col("subject") == F.col("object")) & (F.col("entity") == F.col("subject")), "left")
        found = found.withColumn("freq", F.coalesce("freq", "own")).drop("entity", "own")
    freq = F.coalesce("freq", F.lit(0)).cast("long")
    return found.withColumn("freq", freq).withColumn("decade", decade(F.col("freq"))).select(*facts.columns, "freq", "decade")


def decade(n: Column) -> Column:
    return F.when(n > 0, F.floor(F.log10(n)).cast("int")).otherwise(F.lit(-1))


def cap_targets(facts: DataFrame, most: int, seed: int = 1) -> DataFrame:
    """At most so many facts of each object, the first of the fixed draw."""
    nth = F.row_number().over(Window.partitionBy("object").orderBy(fixed_order(seed, "fact_id")))
    return facts.withColumn("nth", nth).filter(F.col("nth") <= most).drop("nth")


def sample(facts: DataFrame, per_decade: int, seed: int = 1, cap_per_target: int | None = None) -> DataFrame:
    """A fixed draw, as many for each decade of frequency, with common targets thinned out first."""
    if cap_per_target is not None:
        facts = cap_targets(facts, cap_per_target, seed)
    nth = F.row_number().over(Window.partitionBy("decade").orderBy(fixed_order(seed, "fact_id")))
    return facts.withColumn("nth", nth).filter(F.col("nth") <= per_decade).drop("nth")


def cap_all_wrong(facts: DataFrame, correct: DataFrame, most: int, seed: int = 1) -> DataFrame:
    """Keep at most that many facts that every model gets wrong (fact_id, correct)."""
    known = correct.groupBy("fact_id").agg(F.max("correct").alias("any_correct"))
    joined = facts.join(known, "fact_id", "left").withColumn("any_correct", F.coalesce("any_correct", F.lit(False)))
    # a limit with an order keeps that many rows in each task and of them that many in the end
    missed = joined.filter(~F.col("any_correct")).orderBy(fixed_order(seed, "fact_id"), "fact_id").limit(most)
    return joined.filter("any_correct").unionByName(missed).drop("any_correct")


def queries(facts: DataFrame) -> DataFrame:
    """query_id, fact_id, prompt, target, text (both)."""
    return render(facts, with_object=False).select(
        F.col("fact_id").alias("query_id"), "fact_id", F.col("text").alias("prompt"), F.col("object").alias("target"), F.concat_ws(" ", "text", "object").alias("text")
    )


def gold_verdicts(facts: DataFrame) -> DataFrame:
    """Exact entailment by provenance."""
    return facts.select(F.col("fact_id").alias("query_id"), F.explode("gold").alias(ID), F.lit(True).alias("entails"))


def gold_rankings(facts: DataFrame) -> DataFrame:
    """Gold sentences as a ranking, for the tail-patch reference."""
    return facts.select(F.col("fact_id").alias("query_id"), F.posexplode("gold").alias("pos", ID)).select(
        "query_id", (F.col("pos") + 1).alias("rank"), ID, F.lit(1.0).alias("score")
    )
