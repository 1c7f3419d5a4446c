"""Queries on passages and on the closed corpus, with DuckDB SQL of the same values."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.textops import tf_map, tokenise
from ..operators import facts as fx
from ..operators import headroom, judge, lexical, measures
from ..operators.gradients import ID
from ..operators.work import materialise, shared_folder, written
from ..sources import catalog

DIM, PER_DECADE, TARGET_CAP, SEED, DISTRACTORS, WRONG_CAP = 64, 30, 20, 1, 300, 50


def passages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return catalog.load(spark, sf_dir, "documents").select(F.col("doc_id").alias(ID), "text")


def items(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Open-set queries: query_id, text, and its halves as prompt and target."""
    words = F.split("text", " ")
    half = F.floor(F.size(words) / 2).cast("int")
    return catalog.load(spark, sf_dir, "benchmark").select(
        F.col("item_id").alias("query_id"),
        "text",
        F.array_join(F.slice(words, 1, half), " ").alias("prompt"),
        F.array_join(F.slice(words, half + 1, F.size(words)), " ").alias("target"),
    )


def _out(df: DataFrame) -> DataFrame:
    return df.select("query_id", "rank", ID, F.round("score", 6).alias("score"))


def bm25_postings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lexical.postings(passages(spark, sf_dir)).select("term", ID, "tf", "length")


def bm25_doc_freq(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lexical.doc_freq(lexical.postings(passages(spark, sf_dir)))


def bm25_top10(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _out(lexical.bm25(passages(spark, sf_dir), items(spark, sf_dir)))


def hashed_tfidf_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = passages(spark, sf_dir)
    n = docs.agg(F.count(F.lit(1)).alias("n"))
    vectors = lexical.hashed_tfidf(docs, ID, lexical.doc_freq(lexical.postings(docs)), n, DIM)
    return vectors.withColumn("x", F.round("x", 6))


def dense_top10(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _out(lexical.dense_text(passages(spark, sf_dir), items(spark, sf_dir), dim=DIM))


def sentence_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = judge.sentence_windows(passages(spark, sf_dir))
    return found.select(ID, F.col("start").cast("long").alias("start"), F.md5("window").alias("digest"))


def _judged(spark: SparkSession, sf_dir: str, pairs: DataFrame) -> DataFrame:
    docs = passages(spark, sf_dir)
    weights = lexical.doc_freq(lexical.postings(docs))
    return judge.judge(pairs, docs, items(spark, sf_dir), weights, docs.agg(F.count(F.lit(1)).alias("n")))


def judge_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    scored = _judged(spark, sf_dir, bm25_top10(spark, sf_dir).select("query_id", ID))
    return scored.withColumn("score", F.round("score", 6))


def judge_errors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Judge against exact containment, over what BM25 and chance retrieve and all containing passages."""
    truth = judge.containment(passages(spark, sf_dir), items(spark, sf_dir))
    pairs = truth.unionByName(bm25_top10(spark, sf_dir).select("query_id", ID)).distinct()
    return measures.judge_errors(_judged(spark, sf_dir, pairs), truth)


def open_bm25_metrics(spark: SparkSession, sf_dir: str) -> DataFrame:
    ranked = bm25_top10(spark, sf_dir)
    verdicts = _judged(spark, sf_dir, ranked.select("query_id", ID))
    found = measures.mrr_recall(ranked, verdicts, items(spark, sf_dir))
    return found.select(F.round("mrr", 6).alias("mrr"), F.round("recall_at_10", 6).alias("recall_at_10"), "n_queries")


def _both_methods(spark: SparkSession, sf_dir: str) -> DataFrame:
    a = bm25_top10(spark, sf_dir).withColumn("method", F.lit("bm25"))
    return a.unionByName(dense_top10(spark, sf_dir).withColumn("method", F.lit("dense")))


def method_overlap(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.overlap(_both_methods(spark, sf_dir)).withColumn("overlap", F.round("overlap", 6))


def length_bias(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = headroom.length_bias(_both_methods(spark, sf_dir), passages(spark, sf_dir))
    return found.select("method", F.round("mean_words", 6).alias("mean_words"), F.round("repeated_lines", 6).alias("repeated_lines"))


def random_rank(spark: SparkSession, sf_dir: str) -> DataFrame:
    return headroom.random_rank(passages(spark, sf_dir), items(spark, sf_dir))


def open_queries(spark: SparkSession, sf_dir: str) -> DataFrame:
    return items(spark, sf_dir).select("query_id", "prompt", "target")


def _replies(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = Window.partitionBy("conv_id").orderBy("turn")
    table = catalog.load(spark, sf_dir, "conversations")
    paired = table.withColumn("next_role", F.lead("role").over(turns)).withColumn("next_text", F.lead("text").over(turns))
    return paired.filter("role = 'user' AND next_role = 'assistant'")


def dialogue(spark: SparkSession, sf_dir: str) -> DataFrame:
    """example_id, conv_id, prompt, target, text of every user turn and the assistant turn that follows."""
    prompt, target = F.coalesce("text", F.lit("")), F.coalesce("next_text", F.lit(""))
    return _replies(spark, sf_dir).select(
        (F.col("conv_id") * 10**6 + F.col("turn")).alias(ID), "conv_id", prompt.alias("prompt"), target.alias("target"), F.concat_ws(" ", prompt, target).alias("text")
    )


def dialogue_queries(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A user turn as prompt and the assistant turn that follows as target; `target_from` counts prompt words."""
    return _replies(spark, sf_dir).select(
        "conv_id",
        "turn",
        F.md5("text").alias("prompt_digest"),
        F.md5("next_text").alias("target_digest"),
        F.size(tokenise(F.col("text"))).cast("long").alias("target_from"),
    )


# --- facts


def unambiguous(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fx.unambiguous(fx.stated(spark, sf_dir))


def _known(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The unambiguous facts, written once for a session."""
    return written(spark, (sf_dir, "unambiguous"), lambda: fx.unambiguous(fx.stated_of(corpus(spark, sf_dir)), gold=False))


def with_frequency(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fx.frequency(_known(spark, sf_dir), corpus(spark, sf_dir))


def corpus(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The closed corpus, written once for a session."""
    return written(spark, (sf_dir, "closed-corpus"), lambda: fx.closed_corpus(spark, sf_dir))


def sampled(spark: SparkSession, sf_dir: str, per_decade: int = PER_DECADE) -> DataFrame:
    """The sampled facts, written once for a session."""

    def build() -> DataFrame:
        # targets are thinned out by the draw alone, so only facts that stay are counted
        capped = fx.cap_targets(_known(spark, sf_dir), TARGET_CAP, SEED)
        counted = fx.frequency(materialise(capped, "capped"), corpus(spark, sf_dir))
        drawn = materialise(fx.sample(counted, per_decade, SEED), "drawn")
        return fx.with_gold(drawn, fx.stated_of(corpus(spark, sf_dir)))

    return written(spark, (sf_dir, per_decade, "facts"), build)


def facts_triples(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fx.triples(spark, sf_dir).drop("gold")


def facts_unambiguous(spark: SparkSession, sf_dir: str) -> DataFrame:
    return unambiguous(spark, sf_dir).drop("gold")


def facts_frequency(spark: SparkSession, sf_dir: str) -> DataFrame:
    return with_frequency(spark, sf_dir).select("fact_id", "freq", "decade")


def facts_prompts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fx.queries(unambiguous(spark, sf_dir)).select("fact_id", "prompt", "target")


def facts_target_cap(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fx.sample(with_frequency(spark, sf_dir), 10**9, SEED, TARGET_CAP).select("fact_id", "object")


def facts_cap_all_wrong(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Facts that a guess of each relation's commonest object misses are kept up to a limit; others all stay."""
    facts = unambiguous(spark, sf_dir)
    counts = facts.groupBy("relation", "object").agg(F.count(F.lit(1)).alias("n"))
    first = F.row_number().over(Window.partitionBy("relation").orderBy(F.desc("n"), "object"))
    guess = counts.withColumn("nth", first).filter("nth = 1").select("relation", F.col("object").alias("guess"))
    correct = facts.join(guess, "relation").select("fact_id", (F.col("object") == F.col("guess")).alias("correct"))
    return fx.cap_all_wrong(facts, correct, WRONG_CAP, SEED).select("fact_id", "object")


def method_ratios(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How many times one method's accuracy on passages is another's."""
    ranked = _both_methods(spark, sf_dir)
    verdicts = _judged(spark, sf_dir, ranked.select("query_id", ID))
    return measures.ratios(measures.mrr_recall(ranked, verdicts, items(spark, sf_dir), by=["method"]), "method", "mrr")


def bm25_merge_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same ranking with postings and terms joined by a sort-merge join."""
    return _out(lexical.bm25(passages(spark, sf_dir), items(spark, sf_dir), strategy="merge"))


def selected_candidates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Candidates of one language and of bounded length, null-safe and pushed to the scan."""
    docs = catalog.load(spark, sf_dir, "documents")
    return catalog.select_candidates(docs, lang="en", min_chars=500, max_chars=20_000).select("doc_id", "source", "n_chars")


def prompt_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Prompts written as JSON, CSV, Parquet and text lines and read back by one loader."""
    folder = shared_folder(spark, "prompts")
    line = lambda c: F.translate(c, "\n", " ").alias(c)
    own = items(spark, sf_dir).select("query_id", line("prompt"), line("target"))
    own.write.json(f"{folder}/json")
    own.write.option("header", "true").csv(f"{folder}/csv")
    own.write.parquet(f"{folder}/parquet")
    own.select(F.concat_ws("\t", "prompt", "target").alias("value")).write.text(f"{folder}/text")
    found = None
    for kind in ("json", "csv", "parquet", "text"):
        part = catalog.load_prompts(spark, f"{folder}/{kind}", kind).select(F.lit(kind).alias("kind"), "prompt", "target")
        found = part if found is None else found.unionByName(part)
    return found


def term_maps(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Term frequencies of benchmark items as maps; the most frequent word of each, ties by word."""
    table = catalog.load(spark, sf_dir, "benchmark").select("item_id", F.explode(tf_map(tokenise(F.col("text")))).alias("term", "n"))
    best = F.min(F.struct(-F.col("n"), F.col("term")))
    return table.groupBy("item_id").agg(F.count(F.lit(1)).alias("n_terms"), best.alias("b")).select(
        "item_id", "n_terms", F.col("b.term").alias("term"), (-F.col("b.col1")).cast("long").alias("n")
    )


def bucketed_postings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Postings kept in a table bucketed by term and counted from there without a shuffle."""
    name = f"postings_{uuid.uuid4().hex}"
    lexical.save_postings(lexical.postings(passages(spark, sf_dir)), name, 8)
    found = materialise(lexical.doc_freq(spark.table(name)), "bucketed")
    spark.sql(f"DROP TABLE {name}")
    return found


def facts_sample(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sampled(spark, sf_dir).select("fact_id", "decade")


def closed_corpus(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fx.closed_corpus(spark, sf_dir)


def closed_bm25_top10(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _out(lexical.bm25(corpus(spark, sf_dir), fx.queries(sampled(spark, sf_dir))))


def closed_mrr_recall(spark: SparkSession, sf_dir: str) -> DataFrame:
    drawn = sampled(spark, sf_dir)
    found = measures.mrr_recall(closed_bm25_top10(spark, sf_dir), fx.gold_verdicts(drawn), fx.queries(drawn))
    return found.select(F.round("mrr", 6).alias("mrr"), F.round("recall_at_10", 6).alias("recall_at_10"), "n_queries")


def distractor_pool(spark: SparkSession, sf_dir: str) -> DataFrame:
    return headroom.distractor_pool(sampled(spark, sf_dir), corpus(spark, sf_dir), DISTRACTORS, SEED)


def _categorised(spark: SparkSession, sf_dir: str) -> DataFrame:
    drawn = sampled(spark, sf_dir)
    return headroom.categorise(closed_bm25_top10(spark, sf_dir), corpus(spark, sf_dir), drawn, fx.gold_verdicts(drawn))


def proponent_categories(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _categorised(spark, sf_dir).select("query_id", "rank", ID, "category", "target_match")


def category_by_decade(spark: SparkSession, sf_dir: str) -> DataFrame:
    return headroom.by_frequency(_categorised(spark, sf_dir), sampled(spark, sf_dir)).withColumn("share", F.round("share", 6))


def _with_relation(spark: SparkSession, sf_dir: str) -> DataFrame:
    drawn = sampled(spark, sf_dir).select(F.col("fact_id").alias("query_id"), "relation", "decade")
    return _categorised(spark, sf_dir).join(drawn, "query_id")


def category_by_decade_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return headroom.share_report(_with_relation(spark, sf_dir), ["decade", "category"], "rollup")


def category_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    return headroom.share_report(_with_relation(spark, sf_dir), ["relation", "category"], "cube")


def target_match_share(spark: SparkSession, sf_dir: str) -> DataFrame:
    return headroom.target_match(_categorised(spark, sf_dir)).withColumn("target_match_share", F.round("target_match_share", 6))


# --- the same in DuckDB

_WORDS = "regexp_extract_all(lower({0}), '[\\p{{L}}\\p{{N}}]+')"


def _words(col: str) -> str:
    return _WORDS.format(col)


_DOCS = "cand AS (SELECT doc_id AS example_id, text FROM documents), qs AS (SELECT item_id AS query_id, text FROM benchmark)"


def _bm25_sql(head: str) -> str:
    """Views over cand(example_id, text) and qs(query_id, text): po, df, sz, top."""
    return f"""
        WITH {head},
        wd AS (SELECT example_id, {_words('text')} AS ws FROM cand),
        po AS (SELECT term, example_id, count(*) AS tf, any_value(length) AS length FROM
               (SELECT example_id, len(ws)::BIGINT AS length, unnest(ws) AS term FROM wd) GROUP BY 1, 2),
        df AS (SELECT term, count(*) AS df FROM po GROUP BY 1),
        sz AS (SELECT count(*) AS n, avg(len(ws)) AS al FROM wd),
        qt AS (SELECT query_id, term, count(*) AS qtf FROM (SELECT query_id, unnest({_words('text')}) AS term FROM qs) GROUP BY 1, 2),
        bs AS (SELECT query_id, example_id, round(sum(qtf * ln(1 + (n - df + 0.5) / (df + 0.5)) * tf /
                 (tf + {lexical.K1} * (1 - {lexical.B} + {lexical.B} * length / al))), 8) AS score
               FROM po JOIN qt USING (term) JOIN df USING (term), sz GROUP BY 1, 2),
        top AS (SELECT query_id, rank::INT AS rank, example_id, score FROM
                (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, example_id) AS rank FROM bs) WHERE rank <= 10)"""


def _tfidf_sql(key: str, table: str) -> str:
    return f"""SELECT {key}, bucket, w / sqrt(sum(w * w) OVER (PARTITION BY {key})) AS x FROM
        (SELECT {key}, ('0x' || substr(md5(term), 1, 8))::BIGINT % {DIM} AS bucket, sum(tf * ln(1 + (n - coalesce(df, 0) + 0.5) / (coalesce(df, 0) + 0.5))) AS w
         FROM {table} LEFT JOIN df USING (term), sz GROUP BY 1, 2)"""


_DENSE_SQL = f""",
    mv AS ({_tfidf_sql('example_id', 'po')}),
    qv AS ({_tfidf_sql('query_id', '(SELECT query_id, term, qtf AS tf FROM qt)')}),
    ds AS (SELECT query_id, example_id, round(sum(mv.x * qv.x), 8) AS score FROM mv JOIN qv USING (bucket) GROUP BY 1, 2),
    dt AS (SELECT query_id, rank::INT AS rank, example_id, score FROM
           (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, example_id) AS rank FROM ds) WHERE rank <= 10)"""

_WINDOWS_SQL = """
    sn AS (SELECT example_id, list_filter(list_transform(regexp_split_to_array(text, '[.!?\\n]+'), lambda s: trim(s, ' ')), lambda s: s <> '') AS s FROM cand),
    wi AS (SELECT example_id, st AS start, array_to_string(s[st + 1 : st + 3], ' ') AS wtext FROM
           (SELECT example_id, s, unnest(range(0, greatest(len(s) - 3, 0) + 1)) AS st FROM sn WHERE len(s) > 0))"""


def _judge_sql(pairs: str) -> str:
    return f""",
    {_WINDOWS_SQL},
    pr AS (SELECT DISTINCT query_id, example_id FROM ({pairs})),
    hw AS (SELECT query_id, term, ln(1 + (n - coalesce(df, 0) + 0.5) / (coalesce(df, 0) + 0.5)) AS w FROM
           (SELECT DISTINCT query_id, term FROM qt) LEFT JOIN df USING (term), sz),
    ht AS (SELECT query_id, sum(w) AS total FROM hw GROUP BY 1),
    ww AS (SELECT DISTINCT example_id, start, unnest({_words('wtext')}) AS term FROM wi WHERE example_id IN (SELECT example_id FROM pr)),
    ws2 AS (SELECT pr.query_id, pr.example_id, start, sum(w) AS got FROM pr JOIN ww USING (example_id) JOIN hw ON hw.query_id = pr.query_id AND hw.term = ww.term GROUP BY 1, 2, 3),
    jd AS (SELECT pr.query_id, pr.example_id, round(coalesce(max(got / total), 0), 8) AS score FROM pr LEFT JOIN ws2 USING (query_id, example_id)
           JOIN ht ON ht.query_id = pr.query_id GROUP BY 1, 2),
    ve AS (SELECT *, score >= {judge.THRESHOLD} AS entails FROM jd)"""


_MRR_SQL = """
    SELECT round(avg(coalesce(1.0 / fr, 0)), 6) AS mrr, round(avg((fr IS NOT NULL)::INT), 6) AS recall_at_10, count(*) AS n_queries FROM
    (SELECT qs.query_id, min(CASE WHEN entails THEN rank END) AS fr FROM qs LEFT JOIN top ON top.query_id = qs.query_id
     LEFT JOIN ve ON ve.query_id = top.query_id AND ve.example_id = top.example_id GROUP BY 1)"""

_BOTH_SQL = ", mt AS (SELECT 'bm25' AS method, * FROM top UNION ALL SELECT 'dense', * FROM dt)"


def _stated_sql() -> str:
    """Views st (stated facts), tp (template prompts), cc (closed corpus)."""
    n = {r: k * 10**10 for r, (k, _) in fx.TEMPLATES.items()}
    parts = [
        f"SELECT {n['supplier_nation']} + s_suppkey AS example_id, s_name AS subject, 'supplier_nation' AS relation, n_name AS object FROM supplier JOIN nation ON s_nationkey = n_nationkey",
        f"SELECT {n['customer_nation']} + c_custkey, c_name, 'customer_nation', n_name FROM customer JOIN nation ON c_nationkey = n_nationkey",
        f"SELECT {n['nation_region']} + n_nationkey, n_name, 'nation_region', r_name FROM nation JOIN region ON n_regionkey = r_regionkey",
        f"SELECT {n['customer_segment']} + c_custkey, c_name, 'customer_segment', c_mktsegment FROM customer",
        f"SELECT {n['part_brand']} + p_partkey, p_name, 'part_brand', p_brand FROM part",
        f"SELECT {n['part_type']} + p_partkey, p_name, 'part_type', p_type FROM part",
        f"SELECT {n['part_size']} + p_partkey, p_name, 'part_size', p_size::VARCHAR FROM part",
        f"SELECT {n['order_customer']} + o_orderkey, 'Order' || o_orderkey, 'order_customer', c_name FROM orders JOIN customer ON o_custkey = c_custkey",
        f"SELECT {n['order_priority']} + o_orderkey, 'Order' || o_orderkey, 'order_priority', o_orderpriority FROM orders",
        f"SELECT {n['order_status']} + o_orderkey, 'Order' || o_orderkey, 'order_status', o_orderstatus FROM orders",
    ]
    patterns = ", ".join(f"('{r}', '{p}')" for r, (_, p) in fx.TEMPLATES.items())
    return f"""
        st AS ({' UNION ALL '.join(parts)}),
        tp AS (SELECT * FROM (VALUES {patterns}) t(relation, pattern)),
        cc AS (SELECT example_id, replace(pattern, '%s', subject) || ' ' || object || '.' AS text, subject, relation, object FROM st JOIN tp USING (relation)
               UNION ALL SELECT {10**15} + l_orderkey * {10**4} + row_number() OVER (PARTITION BY l_orderkey ORDER BY text), text, 'Order' || l_orderkey, 'shipment', object
               FROM (SELECT DISTINCT l_orderkey, 'Order' || l_orderkey || ' shipped ' || p_name || ' from ' || s_name || '.' AS text, s_name AS object
               FROM lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey))"""


def _facts_sql() -> str:
    """Views fa (triples), fu (unambiguous), ff (with frequency), fc (targets capped), fs (sample)."""
    return f"""{_stated_sql()},
        fa AS (SELECT min(example_id) AS fact_id, subject, relation, object, count(*) AS n_gold FROM st GROUP BY 2, 3, 4
               UNION ALL SELECT a.example_id + {10 * 10**10}, a.subject, CASE a.relation WHEN 'supplier_nation' THEN 'supplier_region' ELSE 'customer_region' END, b.object, 0
               FROM st a JOIN st b ON b.relation = 'nation_region' AND b.subject = a.object WHERE a.relation IN ('supplier_nation', 'customer_nation')),
        fu AS (SELECT * FROM fa WHERE (subject, relation) IN (SELECT (subject, relation) FROM fa GROUP BY subject, relation HAVING count(DISTINCT object) = 1)),
        me AS (SELECT DISTINCT example_id, unnest([subject, object]) AS entity FROM cc),
        fq AS (SELECT fact_id, count(DISTINCT a.example_id) AS freq FROM fu JOIN me a ON a.entity = subject JOIN me b ON b.entity = object AND b.example_id = a.example_id GROUP BY 1),
        ff AS (SELECT fu.*, coalesce(freq, 0)::BIGINT AS freq, CASE WHEN coalesce(freq, 0) > 0 THEN floor(log10(freq))::INT ELSE -1 END AS decade FROM fu LEFT JOIN fq USING (fact_id)),
        fc AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY object ORDER BY md5('{SEED}:' || fact_id)) AS nth FROM ff) WHERE nth <= {TARGET_CAP}),
        fs AS (SELECT * FROM (SELECT * EXCLUDE (nth), row_number() OVER (PARTITION BY decade ORDER BY md5('{SEED}:' || fact_id)) AS nth FROM fc) WHERE nth <= {PER_DECADE})"""


_CLOSED_HEAD = (
    _facts_sql()
    + """, cand AS (SELECT example_id, text FROM cc),
        qs AS (SELECT fact_id AS query_id, replace(pattern, '%s', subject) || ' ' || object AS text FROM fs JOIN tp USING (relation)),
        gd AS (SELECT fact_id AS query_id, st.example_id, true AS entails FROM fs JOIN st ON st.subject = fs.subject AND st.relation = fs.relation AND st.object = fs.object)"""
)


def _names(col: str) -> str:
    from ..functions.textops import STOPWORDS

    stop = ", ".join(f"'{w}'" for w in STOPWORDS)
    return f"list_filter(list_distinct({_words(col)}), lambda w: NOT list_contains([{stop}], w))"


_CATEGORY_SQL = f""",
    cw AS (SELECT example_id, ws FROM wd WHERE example_id IN (SELECT example_id FROM top)),
    nm AS (SELECT fact_id AS query_id, relation, decade, {_names('subject')} AS sw, {_names('object')} AS ow FROM fs),
    fl AS (SELECT top.query_id, rank, top.example_id, relation, decade, coalesce(entails, false) AS hit,
              len(sw) > 0 AND list_has_all(ws, sw) AS s, list_has_any(ws, sw) AS sp, len(ow) > 0 AND list_has_all(ws, ow) AS o, list_has_any(ws, ow) AS op
           FROM top JOIN cw USING (example_id) JOIN nm ON nm.query_id = top.query_id LEFT JOIN gd ON gd.query_id = top.query_id AND gd.example_id = top.example_id),
    ca AS (SELECT *, CASE WHEN hit THEN 'entails' WHEN s AND o THEN 'both' WHEN sp AND op THEN 'both_partial' WHEN o THEN 'target_only' WHEN op THEN 'target_partial'
              WHEN s THEN 'subject_only' WHEN sp THEN 'subject_partial' ELSE 'none' END AS category, op OR hit AS target_match FROM fl)"""


def _bucket_sql(digest: str, table: str = "cc") -> str:
    return f"('0x' || substr({digest}, 1, 8))::BIGINT % (SELECT count(*) // 4 FROM {table})"


_POOL_SQL = f"""
    WITH {_CLOSED_HEAD},
    de AS (SELECT example_id, {_bucket_sql(f"md5('{SEED}:' || example_id)")} AS bucket FROM cc),
    dr AS (SELECT DISTINCT fact_id AS query_id, {_bucket_sql(f"md5('{SEED}:' || fact_id || ':' || i)")} AS bucket FROM fs, range({DISTRACTORS}) r(i)),
    ot AS (SELECT query_id, example_id, row_number() OVER (PARTITION BY query_id ORDER BY md5('{SEED}:' || query_id || ':' || example_id)) AS nth
           FROM dr JOIN de USING (bucket) WHERE (query_id, example_id) NOT IN (SELECT (query_id, example_id) FROM gd))
    SELECT query_id, example_id, true AS is_gold FROM gd UNION ALL SELECT query_id, example_id, false FROM ot WHERE nth <= {DISTRACTORS}"""

_OPEN = _bm25_sql(_DOCS)
_CLOSED = _bm25_sql(_CLOSED_HEAD)
_TOP_OUT = " SELECT query_id, rank, example_id, round(score, 6) AS score FROM "
_FACTS = "WITH " + _facts_sql()

QUERIES = {
    f.__name__: f
    for f in (
        bm25_postings, bm25_doc_freq, bm25_top10, hashed_tfidf_vectors, dense_top10, sentence_windows, judge_scores, judge_errors, open_bm25_metrics,
        method_overlap, length_bias, random_rank, open_queries, dialogue_queries, facts_triples, facts_unambiguous, facts_frequency, facts_prompts,
        facts_target_cap, facts_sample, closed_corpus, closed_bm25_top10, closed_mrr_recall, distractor_pool, proponent_categories, category_by_decade,
        category_by_decade_rollup, category_cube, target_match_share, facts_cap_all_wrong, method_ratios, bm25_merge_join, selected_candidates,
        prompt_sets, term_maps, bucketed_postings,
    )
}

ORACLE_SQL = {
    "bm25_postings": _OPEN + " SELECT term, example_id, tf, length FROM po",
    "bm25_doc_freq": _OPEN + " SELECT term, df FROM df",
    "bm25_top10": _OPEN + _TOP_OUT + "top",
    "hashed_tfidf_vectors": _OPEN + _DENSE_SQL + " SELECT example_id, bucket, round(x, 6) AS x FROM mv",
    "dense_top10": _OPEN + _DENSE_SQL + _TOP_OUT + "dt",
    "sentence_windows": f"WITH {_DOCS}, {_WINDOWS_SQL} SELECT example_id, start, md5(wtext) AS digest FROM wi",
    "judge_scores": _OPEN + _judge_sql("SELECT query_id, example_id FROM top") + " SELECT query_id, example_id, round(score, 6) AS score, entails FROM ve",
    "judge_errors": _OPEN
    + ", tr AS (SELECT query_id, example_id FROM cand JOIN qs ON contains(cand.text, qs.text))"
    + _judge_sql("SELECT query_id, example_id FROM tr UNION SELECT query_id, example_id FROM top")
    + """ SELECT count(*) FILTER (hit) AS positives, count(*) FILTER (NOT hit) AS negatives, count(*) FILTER (hit AND NOT entails) AS false_negatives,
          count(*) FILTER (NOT hit AND entails) AS false_positives FROM (SELECT ve.*, tr.query_id IS NOT NULL AS hit FROM ve LEFT JOIN tr USING (query_id, example_id))""",
    "open_bm25_metrics": _OPEN + _judge_sql("SELECT query_id, example_id FROM top") + _MRR_SQL,
    "method_overlap": _OPEN + _DENSE_SQL + _BOTH_SQL
    + """ SELECT a.method, b.method AS other, round(count(*) / (10.0 * (SELECT count(DISTINCT query_id) FROM mt)), 6) AS overlap
          FROM mt a JOIN mt b ON a.query_id = b.query_id AND a.example_id = b.example_id AND a.method < b.method GROUP BY 1, 2""",
    "length_bias": _OPEN + _DENSE_SQL + _BOTH_SQL
    + """, ls AS (SELECT example_id, len(ws) AS n_words, (len(l) - len(list_distinct(l)))::DOUBLE / nullif(len(l), 0) AS rp FROM
                 (SELECT example_id, ws, list_filter(string_split(text, chr(10)), lambda y: trim(y, ' ') <> '') AS l FROM wd JOIN cand USING (example_id)))
          SELECT method, round(avg(n_words), 6) AS mean_words, round(avg(coalesce(rp, 0)), 6) AS repeated_lines FROM mt JOIN ls USING (example_id) GROUP BY 1""",
    "random_rank": f"""WITH {_DOCS}, de AS (SELECT example_id, {_bucket_sql("md5('1:' || example_id)", "cand")} AS bucket FROM cand),
        dr AS (SELECT DISTINCT query_id, {_bucket_sql("md5('1:' || query_id || ':' || i)", "cand")} AS bucket FROM qs, range(40) r(i))
        SELECT query_id, rank::INT AS rank, example_id FROM (SELECT query_id, example_id, row_number() OVER (PARTITION BY query_id
        ORDER BY md5('1:' || query_id || ':' || example_id)) AS rank FROM dr JOIN de USING (bucket)) WHERE rank <= 10""",
    "open_queries": """SELECT item_id AS query_id, array_to_string(w[1 : len(w) // 2], ' ') AS prompt, array_to_string(w[len(w) // 2 + 1 :], ' ') AS target
        FROM (SELECT item_id, string_split(text, ' ') AS w FROM benchmark)""",
    "dialogue_queries": f"""SELECT conv_id, turn, md5(text) AS prompt_digest, md5(nt) AS target_digest, len({_words('text')})::BIGINT AS target_from FROM
        (SELECT *, lead(role) OVER w AS nr, lead(text) OVER w AS nt FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn))
        WHERE role = 'user' AND nr = 'assistant'""",
    "facts_triples": _FACTS + " SELECT fact_id, subject, relation, object, n_gold FROM fa",
    "facts_unambiguous": _FACTS + " SELECT fact_id, subject, relation, object, n_gold FROM fu",
    "facts_frequency": _FACTS + " SELECT fact_id, freq, decade FROM ff",
    "facts_prompts": _FACTS + " SELECT fact_id, replace(pattern, '%s', subject) AS prompt, object AS target FROM fu JOIN tp USING (relation)",
    "facts_target_cap": _FACTS + " SELECT fact_id, object FROM fc",
    "facts_cap_all_wrong": _FACTS
    + f""", gu AS (SELECT relation, object AS guess FROM (SELECT relation, object, row_number() OVER (PARTITION BY relation ORDER BY count(*) DESC, object) AS nth
          FROM fu GROUP BY 1, 2) WHERE nth = 1), jo AS (SELECT fact_id, object, object = guess AS ok FROM fu JOIN gu USING (relation))
        SELECT fact_id, object FROM jo WHERE ok UNION ALL (SELECT fact_id, object FROM jo WHERE NOT ok ORDER BY md5('{SEED}:' || fact_id), fact_id LIMIT {WRONG_CAP})""",
    "method_ratios": _OPEN + _DENSE_SQL + _BOTH_SQL + _judge_sql("SELECT query_id, example_id FROM mt")
    + """, mm AS (SELECT method, avg(coalesce(1.0 / fr, 0)) AS mrr FROM (SELECT ms.method, qs.query_id, min(CASE WHEN entails THEN rank END) AS fr
          FROM qs CROSS JOIN (SELECT DISTINCT method FROM mt) ms LEFT JOIN mt ON mt.query_id = qs.query_id AND mt.method = ms.method
          LEFT JOIN ve ON ve.query_id = mt.query_id AND ve.example_id = mt.example_id GROUP BY 1, 2) GROUP BY 1)
        SELECT a.method, b.method AS other, round(a.mrr / b.mrr, 6) AS ratio FROM mm a JOIN mm b ON a.method <> b.method AND b.mrr > 0""",
    "bm25_merge_join": _OPEN + _TOP_OUT + "top",
    "selected_candidates": "SELECT doc_id, source, n_chars FROM documents WHERE n_chars BETWEEN 500 AND 20000 AND lang IS NOT DISTINCT FROM 'en'",
    "prompt_sets": """SELECT kind, replace(array_to_string(w[1 : len(w) // 2], ' '), chr(10), ' ') AS prompt,
        replace(array_to_string(w[len(w) // 2 + 1 :], ' '), chr(10), ' ') AS target FROM (SELECT string_split(text, ' ') AS w FROM benchmark), (VALUES ('json'), ('csv'), ('parquet'), ('text')) k(kind)""",
    "term_maps": f"""SELECT item_id, count(*) AS n_terms, first(term ORDER BY n DESC, term) AS term, max(n) AS n FROM
        (SELECT item_id, term, count(*) AS n FROM (SELECT item_id, unnest({_words('text')}) AS term FROM benchmark) GROUP BY 1, 2) GROUP BY 1""",
    "bucketed_postings": _OPEN + " SELECT term, df FROM df",
    "facts_sample": _FACTS + " SELECT fact_id, decade FROM fs",
    "closed_corpus": "WITH " + _stated_sql() + " SELECT * FROM cc",
    "closed_bm25_top10": _CLOSED + _TOP_OUT + "top",
    "closed_mrr_recall": _CLOSED + ", ve AS (SELECT * FROM gd)" + _MRR_SQL,
    "distractor_pool": _POOL_SQL,
    "proponent_categories": _CLOSED + _CATEGORY_SQL + " SELECT query_id, rank, example_id, category, target_match FROM ca",
    "category_by_decade": _CLOSED + _CATEGORY_SQL
    + " SELECT decade, category, count(*) AS n, round(count(*) / sum(count(*)) OVER (PARTITION BY decade), 6) AS share FROM ca GROUP BY 1, 2",
    "category_by_decade_rollup": _CLOSED + _CATEGORY_SQL
    + " SELECT decade, category, count(*) AS n, grouping(decade, category) AS level FROM ca GROUP BY ROLLUP (decade, category)",
    "category_cube": _CLOSED + _CATEGORY_SQL
    + " SELECT relation, category, count(*) AS n, grouping(relation, category) AS level FROM ca GROUP BY CUBE (relation, category)",
    "target_match_share": _CLOSED + _CATEGORY_SQL + " SELECT round(avg(target_match::INT), 6) AS target_match_share FROM ca",
}
