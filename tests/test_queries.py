"""Queries against their SQL twins on the smallest tables."""

import glob
import inspect
import os

import duckdb
import pytest

from edgesplit import workloads
from edgesplit.queries import ORACLES, QUERIES

from .conftest import SF

FAST = [
    "graph_cust_part", "graph_doc_line", "graph_user_next", "graph_page_link", "degree_histogram", "dbh_rf", "grid_assign", "pds_assign", "lpt_nation", "two_candidate_one_batch", "cluster_round_nation_planted", "hdrf_one_batch",
    "certificates_sequential", "pagerank_3", "cc_labels", "report_cube", "replica_bitmaps", "sql_portable_hash", "stream_dbh", "session_edges", "asof_cluster_snapshot", "evaluations_bound", "rf_stateless", "load_statistics", "cluster_proposals_residual",
    "replica_bitmaps_wide", "cover_sketches", "udaf_merge_masks", "arrow_udf_pair_score", "udtf_candidates", "udtf_lpt", "map_policies", "cluster_quality_nation", "state_size_nation", "dbh_given_degrees", "window_recent_degree", "session_windows", "complexity_in_k",
]


def canonical(rows, columns):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    text = lambda x: "null" if x is None or x != x else repr(float(x)) if isinstance(x, (int, float)) and not isinstance(x, bool) else str(x)
    return sorted(tuple(text(r[i]) for i in order) for r in rows)


@pytest.fixture(scope="module")
def duck():
    db = duckdb.connect()
    for path in glob.glob(f"{SF}/*.parquet"):
        db.sql(f"create view {os.path.basename(path)[:-8]} as select * from '{path}'")
    return db


@pytest.mark.parametrize("name", FAST)
def test_matches_sql(spark, duck, name):
    got = QUERIES[name](spark, SF)
    want = duck.sql(ORACLES[name])
    assert sorted(got.columns) == sorted(want.columns)
    assert canonical([tuple(r) for r in got.collect()], got.columns) == canonical(want.fetchall(), want.columns)


def test_names():
    assert set(ORACLES) <= set(QUERIES)


def test_experiments_cover_every_k(spark):
    assert {r["k"] for r in QUERIES["w_full_scan"](spark, SF).collect()} == {4, 32, 128, 256}


def test_the_main_grid_is_whole(spark):
    """Seven graphs, each threshold of the hybrid, three runs with seconds and memory."""
    assert len(set(workloads.MAIN_GRAPHS)) == 7 and inspect.signature(workloads.main_grid).parameters["graphs"].default == workloads.MAIN_GRAPHS
    rows = workloads.main_grid(spark, SF, graphs=("order_part", "cust_order"), ks=(4,), methods=("cluster_guided", "hep")).collect()
    kinds = (("cluster_guided", ""), ("hep", "100"), ("hep", "10"), ("hep", "1"), ("dbh", ""))
    assert sorted((r["graph"], r["method"], r["variant"]) for r in rows) == sorted((g, m, v) for g in ("order_part", "cust_order") for m, v in kinds)
    assert all(r["runs"] == 3 and r["rf"] >= 1 and r["seconds"] > 0 and r["sd_s"] is not None for r in rows)
    assert all((r["memory_mb"] is None) == (r["method"] == "dbh") for r in rows)
