"""Mixing sources to target weights by pivotal rounding, in DataFrame functions alone.

A source's target gives each of its documents the same fractional number of copies. Its
whole part is taken at once. The fractional parts are rounded in pairs: words move from one
document to the other, in a direction drawn at random so that expectations stay, until one
of the two has no fraction left. Words moved are words kept, so a source's sum does not
change until its last document. Documents are paired within buckets; the one left over from
each bucket meets those of other buckets, level by level, as a reduction tree. Rows that repeat
an id and a size in a source are one unit with a count: among themselves they round at once, and
what is left of them is a single fraction, so no id can fill a bucket.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ._runtime import bounded_broadcast, documents, materialise

WEIGHTS = (3.0, 1.0, 2.0)
SHARE = 1.5
CAP = 2.0
#: Documents, or residuals of buckets, that one bucket pairs.
FAN_IN = 128
#: Equal rows that one row is repeated into at a time.
RUN = 65_536
_UNIT = "struct<size:bigint,doc_id:bigint,p:double>"
_DONE = "array<struct<doc_id:bigint,size:bigint,extra:int>>"


def word_count(text: Column) -> Column:
    """Runs of characters other than ASCII white space; null has none."""
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def source_targets(sizes: DataFrame, weights=WEIGHTS, share: float = SHARE, cap: float = CAP) -> DataFrame:
    """Targets of sources (source, source_size), by code point, null last.

    Weights repeat along that order. A target stops at cap times its source's size; the excess
    goes to the others by weight, round by round, until none is above; a round is one aggregate.
    Sources are numbered in ranges, so no task holds them all.
    """
    cycle = F.array(*[F.lit(float(w)) for w in weights])
    weighted = materialise(
        _numbered(sizes).select(
            "source",
            "source_size",
            F.element_at(cycle, (F.col("nth") % len(weights) + 1).cast("int")).alias("weight"),
            (F.col("source_size") * F.lit(float(cap))).alias("limit"),
        ),
        "op1-weights",
    )
    total = float(share) * (weighted.agg(F.sum("source_size")).first()[0] or 0)
    level, n_full = 0.0, -1
    while True:
        full = (F.col("limit") <= F.col("weight") * F.lit(level)) if n_full >= 0 else F.lit(False)
        held, open_weight, n = weighted.agg(
            F.coalesce(F.sum(F.when(full, F.col("limit"))), F.lit(0.0)), F.sum(F.when(~full, F.col("weight"))), F.count_if(full)
        ).first()
        if n == n_full or open_weight is None:
            break
        level, n_full = (total - held) / open_weight, n
    target = F.least(F.col("limit"), F.col("weight") * F.lit(level)) if open_weight is not None else F.col("limit")
    return weighted.select("source", "source_size", target.alias("target"))


def _numbered(sizes: DataFrame) -> DataFrame:
    """Sources with their place `nth` in the order by code point, null last."""
    order = F.col("source").asc_nulls_last()
    placed = materialise(sizes.repartitionByRange(order).withColumn("part", F.spark_partition_id()), "op1-ranges")
    # one row for each partition
    tallies = placed.groupBy("part").agg(F.count(F.lit(1)).alias("n"))
    before = Window.partitionBy(F.lit(0)).orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    bases = tallies.select("part", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    own = F.row_number().over(Window.partitionBy("part").orderBy(order)) - 1
    return placed.withColumn("own", own).join(bounded_broadcast(bases), "part").withColumn("nth", F.col("base") + F.col("own"))


def _repeated(rows: DataFrame) -> DataFrame:
    """Each row n times; rows that repeat very often are spread over tasks first."""
    runs = F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("n") - 1) / RUN)))
    often = rows.filter(F.col("n") > RUN).withColumn("run", runs)
    often = often.withColumn("n", F.least(F.lit(RUN).cast("long"), F.col("n") - F.col("run") * RUN)).repartition("run").drop("run")
    return rows.filter(F.col("n").between(1, RUN)).unionByName(often).withColumn("n", F.explode(F.sequence(F.lit(1).cast("long"), "n"))).drop("n")


def _uniform(seed: int, a: Column, b: Column) -> Column:
    """A number in [0, 1) that depends on its arguments alone."""
    return F.shiftrightunsigned(F.xxhash64(F.lit(seed), a, b), 11) * F.lit(2.0**-53)


def _transfer(seed: int):
    """One step of the fold: the unit carried so far meets the next one."""

    def step(state: Column, unit: Column) -> Column:
        held, cw, cp = state["held"], state["held"]["size"].cast("double"), state["held"]["p"]
        xw, xp = unit["size"].cast("double"), unit["p"]
        full_c, empty_x = (1 - cp) * cw, xp * xw
        empty_c, full_x = cp * cw, (1 - xp) * xw
        gain, loss = F.least(full_c, empty_x), F.least(empty_c, full_x)
        rises = _uniform(seed, held["doc_id"], unit["doc_id"]) * (gain + loss) < loss

        def done(u: Column, extra: int) -> Column:
            return F.struct(u["doc_id"].alias("doc_id"), u["size"].alias("size"), F.lit(extra).alias("extra"))

        def carried(u: Column, p: Column) -> Column:
            return F.struct(u["size"].alias("size"), u["doc_id"].alias("doc_id"), p.cast("double").alias("p")).cast(_UNIT)

        def pair(settled: Column, rest: Column) -> Column:
            return F.struct(rest.alias("held"), F.array_append(state["done"], settled).alias("done"))

        return (
            F.when(held.isNull(), F.struct(carried(unit, xp).alias("held"), state["done"].alias("done")))
            .when(rises & (full_c <= empty_x), pair(done(held, 1), carried(unit, xp - gain / xw)))
            .when(rises, pair(done(unit, 0), carried(held, cp + gain / cw)))
            .when(empty_c <= full_x, pair(done(held, 0), carried(unit, xp + loss / xw)))
            .otherwise(pair(done(unit, 1), carried(held, cp - loss / cw)))
        )

    return step


def _round_buckets(units: DataFrame, seed: int) -> DataFrame:
    """Settle all but one unit (source, bucket, size, doc_id, p) of each bucket."""
    empty = F.struct(F.lit(None).cast(_UNIT).alias("held"), F.array().cast(_DONE).alias("done"))
    listed = F.sort_array(F.collect_list(F.struct("size", "doc_id", "p")), asc=False)
    return (
        units.groupBy("source", "bucket")
        .agg(listed.alias("units"))
        .select("source", "bucket", F.aggregate("units", empty, _transfer(seed)).alias("state"))
        .select("source", "bucket", "state.held", "state.done")
    )


def mix(
    docs: DataFrame,
    weights=WEIGHTS,
    share: float = SHARE,
    cap: float = CAP,
    seed: int = 20,
    id_col: str = "doc_id",
    text_col: str = "text",
    source_col: str = "source",
) -> DataFrame:
    """Copies of every document so that each source's words come to its target.

    Size is the number of words; null or empty text has none and takes none. A null source is
    a source of its own, ordered last. The last document of a source is rounded to the nearer
    side, so a source misses its target by half a document at most. Draws depend on ids and
    sizes alone, so reruns agree. Repeated rows are documents of their own. An empty table
    gives no rows; other columns are ignored.
    Returns doc_id, size, source_size, target, taken, copies, source.
    """
    rows = docs.select(
        F.col(id_col).cast("long").alias("doc_id"),
        F.col(source_col).cast("string").alias("source"),
        word_count(F.col(text_col).cast("string")).alias("size"),
    )
    units = materialise(rows.groupBy("source", "doc_id", "size").agg(F.count(F.lit(1)).alias("n")), "op1-units")
    sizes = units.groupBy("source").agg(F.sum(F.col("size") * F.col("n")).alias("source_size"), F.count_if(F.col("size") > 0).alias("n_units"))
    targets = source_targets(sizes.select("source", "source_size"), weights, share, cap)
    ratio = F.when(F.col("source_size") > 0, F.least(F.col("target") / F.col("source_size"), F.lit(cap))).otherwise(0.0)
    per_source = (
        targets.withColumn("whole", F.floor(ratio).cast("int"))
        .withColumn("p", ratio - F.col("whole"))
        .withColumnRenamed("source", "s_source")
        .join(sizes.select(F.col("source").alias("n_source"), "n_units"), F.col("s_source").eqNullSafe(F.col("n_source")))
        .drop("n_source")
    )
    per_source = materialise(per_source, "op1-sources")
    n_sources, most = per_source.agg(F.count(F.lit(1)), F.max("n_units")).first()
    small = bounded_broadcast(per_source, rows=n_sources)
    # of n equal rows `up` get one more copy at once, and a fraction is left for one of them
    known = (
        units.join(small, units["source"].eqNullSafe(small["s_source"]))
        .drop("s_source")
        .withColumn("p", F.when(F.col("size") > 0, F.col("p")).otherwise(0.0))
        .withColumn("whole", F.when(F.col("size") > 0, F.col("whole")).otherwise(0))
        .withColumn("up", F.floor(F.col("n") * F.col("p")))
        .withColumn("left", F.col("n") * F.col("p") - F.col("up"))
    )
    spread = F.ceil(F.col("n_units") / F.lit(FAN_IN))
    level = _round_buckets(
        known.filter("left > 0").select(
            "source", "doc_id", "size", F.col("left").alias("p"), F.pmod(F.xxhash64(F.lit(seed), "doc_id", "size"), spread).alias("bucket")
        ),
        seed,
    )
    settled, buckets, depth = [], -(-(most or 0) // FAN_IN), 0
    while True:
        level = materialise(level, f"op1-level{depth}")
        settled.append(level.select("source", F.explode("done").alias("u")).select("source", "u.*"))
        if buckets <= 1:
            break
        depth, buckets = depth + 1, -(-buckets // FAN_IN)
        units_left = level.select("source", F.floor(F.col("bucket") / FAN_IN).alias("bucket"), "held.*")
        level = _round_buckets(units_left, seed + depth)
    settled.append(level.select("source", "held.doc_id", "held.size", (F.col("held.p") >= 0.5).cast("int").alias("extra")))
    fractional = settled[0]
    for part in settled[1:]:
        fractional = fractional.unionByName(part)
    columns = ["doc_id", "size", "source_size", "target", "copies", "source"]
    with_extra = fractional.join(small, fractional["source"].eqNullSafe(small["s_source"])).withColumn(
        "copies", F.col("whole") + F.col("extra")
    )
    counts = F.array(
        F.struct((F.col("whole") + 1).alias("copies"), F.col("up").alias("n")),
        F.struct(F.col("whole").alias("copies"), (F.col("n") - F.col("up") - (F.col("left") > 0).cast("long")).alias("n")),
    )
    at_once = known.filter("left = 0 OR n > 1").select("doc_id", "size", "source_size", "target", "source", F.inline(counts))
    return (
        with_extra.select(columns)
        .unionByName(_repeated(at_once).select(columns))
        .select("doc_id", "size", "source_size", "target", (F.col("copies") * F.col("size")).alias("taken"), "copies", "source")
    )


def take_mix(docs: DataFrame, seed: int = 20) -> DataFrame:
    """The mixed documents with all their columns, each as often as the mix takes it.

    Rows are matched by id and source. Rows that repeat both share the mean of their copies: its
    whole part is taken of each, and a hash of the text decides on the rest.
    """
    copies = mix(docs, seed=seed).groupBy(F.col("doc_id").alias("mix_id"), F.col("source").alias("mix_source")).agg(F.avg("copies").alias("mix_mean"))
    same = docs["doc_id"].cast("long").eqNullSafe(copies["mix_id"]) & docs["source"].cast("string").eqNullSafe(copies["mix_source"])
    share = F.col("mix_mean") - F.floor("mix_mean")
    more = _uniform(seed, F.xxhash64("text"), F.lit(0)) < share
    taken = docs.join(copies.filter("mix_mean > 0"), same).withColumn("mix_copies", (F.floor("mix_mean") + more.cast("int")).cast("int"))
    return taken.filter("mix_copies > 0").withColumn("mix_copy", F.explode(F.sequence(F.lit(1), "mix_copies"))).select(docs.columns)


def op1_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix(documents(spark, sf_dir))
