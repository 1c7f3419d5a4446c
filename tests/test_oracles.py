"""Queries against their DuckDB SQL on the smallest tables."""

import glob
import os

import duckdb
import pytest

from influence_engine.plans import catalogue

SF = "/root/testdata/sf0.001"
NAMES = [
    "score_mixed_cosine_top10",
    "score_margin_influence_block2",
    "score_prob_factor",
    "score_bilinear_diag",
    "project_one_sided",
    "autocorr_mixed",
    "lambda_choice_diag",
    "probe_tail_patch_by_k",
    "bm25_top10",
    "dense_top10",
    "judge_errors",
    "closed_mrr_recall",
    "category_by_decade_rollup",
    "distractor_pool",
    "op_range_join",
    "op_asof",
    "op_session",
    "op_unpivot",
    "op_interval_join",
    "stream_running_topk",
    "score_over_checkpoints",
    "score_over_checkpoints_normalised",
    "score_subsampled",
    "score_x_plain_mixed_dot",
    "moment_moving_average",
    "moment_factored",
    "random_rank",
    "facts_frequency",
    "facts_cap_all_wrong",
    "closed_corpus",
    "method_ratios",
    "selected_candidates",
    "prompt_sets",
    "term_maps",
    "bucketed_postings",
    "bm25_merge_join",
    "op_order_years",
    "op_bucket_ts",
    "op_ranking_sink",
    "op_sql_surface",
    "op_sort_limit",
    "stream_sliding_windows",
    "stream_sessions",
    "stream_static_join",
    "stream_followed_by",
    "stream_doc_freq",
]


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for path in glob.glob(f"{SF}/*.parquet"):
        con.sql(f"CREATE VIEW {os.path.basename(path)[:-8]} AS SELECT * FROM '{path}'")
    return con


def canonical(rows, names):
    order = sorted(range(len(names)), key=lambda i: names[i])
    out = []
    for r in rows:
        cells = [r[i] for i in order]
        out.append(tuple(f"{c + 0.0:.5f}" if isinstance(c, float) else str(c) for c in cells))
    return sorted(out)


@pytest.mark.parametrize("name", NAMES)
def test_same_values(spark, duck, name):
    df = catalogue.QUERIES[name](spark, SF)
    rel = duck.sql(catalogue.ORACLE_SQL[name])
    assert sorted(df.columns) == sorted(rel.columns)
    assert canonical(df.collect(), df.columns) == canonical(rel.fetchall(), rel.columns)


def test_every_query_with_sql_exists():
    assert set(catalogue.ORACLE_SQL) <= set(catalogue.QUERIES)
