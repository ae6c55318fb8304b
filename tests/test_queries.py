"""Queries against their SQL on the smallest tables, and what their plans must not hold."""

import math
import os

import duckdb
import pytest

from rowfold.plans import inspect
from rowfold.queries import all_oracles, all_queries

SF = "/root/testdata/sf0.001"
TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
#: Exact answers that are quick on the smallest tables.
CHECKED = (
    "ols_doclen", "ols_event_time", "ols_price", "ols_price_expr", "ols_price_block", "ols_group_segment", "ols_rank_deficient", "ols_weighted", "logit_return", "kmeans_points_implicit", "kmeans_points_explicit",
    "kmeans_points_fused", "nb_categorical", "nb_gaussian", "tree_root_gain", "tree_root_gini", "assoc_pairs", "assoc_rules", "cm_cells", "cm_point", "fm_bitmaps", "profile_orders", "profile_embeddings",
    "quantiles_discrete", "quantiles_bisect", "array_ops", "sparse_ops", "tfidf", "feat_edge", "feat_position", "viterbi_fold", "viterbi_topk", "forward_backward", "trigram_index", "ner_entities", "join_left",
    "join_asof_prev_event", "agg_cube", "win_range_time", "win_state_ewma", "recursive_series", "stream_ols", "stream_session", "sql_ols_facade", "udtf_tokenize", "validate_errors", "stream_late",
    "viterbi_all_documents", "crf_loglik", "gram_measures", "pages_text", "udtf_profile", "named_callback", "win_distribution", "sub_exists", "sub_in", "sub_scalar", "sub_select_list", "sub_lateral", "stream_countmin",
    "stream_window_profile", "stream_kmeans", "svm_gd", "predict_svm", "logit_gd", "feat_onehot", "feat_standardise", "feat_hash", "guard_finite", "kmeans_embed", "assoc_pairs_fpgrowth", "eval_scores", "cm_error",
)

pytestmark = pytest.mark.skipif(not os.path.isdir(SF), reason="the given tables are not here")


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"create view {t} as select * from '{SF}/{t}.parquet'")
    return con


def _same(a, b):
    if isinstance(a, float) or isinstance(b, float):
        return a is not None and b is not None and (math.isclose(a, b, rel_tol=1e-6, abs_tol=2e-4) or math.isnan(a) and math.isnan(b)) or a is b
    return str(a) == str(b)


@pytest.mark.parametrize("name", CHECKED)
def test_query(spark, duck, name):
    df = all_queries()[name](spark, SF)
    got = sorted((tuple(r[c] for c in sorted(df.columns)) for r in df.collect()), key=str)
    c = duck.execute(all_oracles()[name])
    cols = [x[0] for x in c.description]
    assert sorted(cols) == sorted(df.columns)
    want = sorted((tuple(r[cols.index(k)] for k in sorted(cols)) for r in c.fetchall()), key=str)
    assert len(got) == len(want)
    assert all(all(_same(p, q) for p, q in zip(a, b)) for a, b in zip(got, want))


def test_every_oracle_has_a_query():
    assert set(all_oracles()) <= set(all_queries())


def test_plans(spark):
    s = inspect.stats(all_queries()["ols_price"](spark, SF))
    assert s["row_python"] == 0 and s["cartesian"] == 0 and s["exchanges"] <= 2
    assert set(s["columns"]) <= {"l_quantity", "l_discount", "l_tax", "l_extendedprice", "l_partkey", "l_orderkey"}
    e = inspect.stats(all_queries()["ols_group_brand"](spark, SF))
    assert e["row_python"] == 0


@pytest.mark.parametrize("name", ("gd_square", "recursive_series", "sgd_epochs"))
def test_more_queries(spark, duck, name):
    test_query(spark, duck, name)


def test_series_and_late_rows_come_from_given_tables():
    for name, t in (("gd_square", "events"), ("recursive_series", "lineitem"), ("stream_late", "events")):
        assert f"from {t}" in all_oracles()[name]


def test_sessions_are_summed_in_tasks_and_kept_as_files(spark):
    """No memory table, which brings every session of every batch to the driver."""
    before = {t.name for t in spark.catalog.listTables()}
    df = all_queries()["stream_session"](spark, SF)
    assert {t.name for t in spark.catalog.listTables()} == before
    folders = {f.rsplit("/", 1)[0] for f in df.inputFiles()}
    assert len(folders) == 1 and "/summed-" in folders.pop()
