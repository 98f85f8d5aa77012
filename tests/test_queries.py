"""Queries against their SQL. All of them take minutes: CADENZA_ALL=1 runs every one, else one of each kind."""

import os

import pytest

import __spark_entry__ as entry
from cadenza.plans import catalogue
from tests.duck import duck, same

SOME = [
    "series_supplier_walk", "series_event_walk", "normal_form", "dft_features", "mavg_circular", "stretch_series", "compose_transforms", "safety_verdicts", "safety_counterexample", "index_nodes_cover", "example_smoothing", "example_stretch",
    "range_mavg", "range_mavg_twosided", "range_rect_scale", "range_stretch", "range_translation_folded", "range_subset", "range_real_vectors", "scan_abandon", "join_a_full", "join_b_abandon", "join_c_index", "join_d_index_mavg", "join_tree", "join_grid",
    "join_reverse", "knn_mavg", "knn_join", "dissimilarity_range", "false_hits", "surface_asof_fill", "surface_setops", "sql_functions", "stream_session", "stream_sliding_dft",
]


@pytest.fixture(scope="module")
def con(sf):
    return duck(sf)


@pytest.mark.parametrize("name", sorted(catalogue.oracle_sql()) if os.environ.get("CADENZA_ALL") else SOME)
def test_query_equals_sql(spark, sf, con, name):
    assert same(catalogue.queries()[name](spark, sf), con.sql(catalogue.oracle_sql()[name]))


def test_each_sql_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_entry(spark):
    assert entry.entry(spark).columns == ["id_l", "id_r", "dist"]


def test_identity_reaches_the_same_nodes(spark, sf):
    rows = catalogue.queries()["measure_nodes"](spark, sf).collect()
    by = {k: sorted((r.level, r.nodes, r.reached) for r in rows if r.kind == k) for k in ("none", "identity")}
    assert by["none"] == by["identity"] and len(by["none"]) > 1
