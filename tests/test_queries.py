"""Catalogue queries against their SQL on the smallest tables, and the standing examples."""

import duckdb
import pytest

import __spark_entry__ as entry
from gridmatch import catalog
from gridmatch.tables import NAMES

D = "/root/testdata/sf0.001"
FAST = ["scan_topk_p22", "scan_topk_sql_p23", "bound_verify_topk_p22", "radius_topk_p22", "threshold_topk_p22", "frontier_topk_p22", "range_regions_p22", "corner_dp_p23", "corner_dp_expr_p22", "exact_region_2x3", "best_run_p13", "str_leaf_boxes", "incremental_nn_batch2", "range_pairs", "stream_tiles", "stream_sessions", "stream_dedup", "glyph_tiles", "topk_region_asia", "threshold_topk_batch1", "frontier_topk_wave1", "store_threshold_topk_p25", "store_frontier_topk_p25", "scan_counters_p25", "walks_agree", "region_connected", "region_sink_class", "region_algebra", "overlaps_dihedral", "topk_missed", "sweep_recursive", "nearest_query_tile", "distance_l2", "score_log_odds", "hash_queries", "strip_truth", "pca_variance_vectors"]


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in NAMES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{D}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", FAST)
def test_against_sql(spark, duck, name):
    got = catalog.queries()[name](spark, D)
    want = duck.execute(catalog.oracles()[name])
    columns = [c[0] for c in want.description]
    assert sorted(columns) == sorted(got.columns)
    assert sorted(map(str, map(tuple, got.select(*columns).collect()))) == sorted(map(str, want.fetchall()))


def test_golden_regions(spark):
    rows = entry.entry(spark).orderBy("score", ascending=False).limit(2).collect()
    assert [tuple(r)[:4] for r in rows] == [(3, 2, 4, 696), (3, 5, 3, 493)]


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_sql_search_runs_no_python(spark):
    plan = catalog.queries()["scan_topk_sql_p22"](spark, D)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan and "BroadcastNestedLoopJoin" in plan


def test_box_filters_reach_the_scan(spark):
    from gridmatch.catalog.base import SPEC, patch, tiles
    from gridmatch.index.packed import PackedIndex

    t = tiles(spark, D)
    plan = PackedIndex.build(t).within(patch(t), SPEC, 50)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [" in plan and "f0" in plan.split("PushedFilters")[1]


def test_bad_arguments(spark):
    from gridmatch.score.functions import ScoreSpec

    with pytest.raises(ValueError):
        ScoreSpec(lam=-1)
    with pytest.raises(ValueError):
        ScoreSpec(metric="cosine")
