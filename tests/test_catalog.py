"""Registered queries against their SQL on the smallest tables, and properties of plans."""

import math
import os

import duckdb
import pytest

from dyngraph.catalog import ORACLES, QUERIES

#: One of each family; the driver runs them all.
CHOSEN = [
    "edges_copurchase", "edges_talk", "edges_link", "snap_sliding_validity", "snap_delta_removed", "region_khop2", "region_locality", "client_cut_edges", "part_components", "part_vote_cut",
    "part_refine_moves", "part_extend_hop2", "q_entropy", "q_cov_train_val_test", "x_hop2_complete", "x_residual_by_mode", "x_scope_region", "cost_model_paper", "ev_map_global", "ev_negatives", "ev_cut_edge_task",
    "ev_f1_macro", "pv_dimension", "j_asof", "j_interval", "a_rollup", "w_islands", "s_except_all", "st_tumbling_edges", "st_placement", "u_sql_function",
]


def norm(v):
    if isinstance(v, float):
        return round(v, 6) + 0.0 if math.isfinite(v) else str(v)
    return v


@pytest.mark.parametrize("name", CHOSEN)
def test_against_sql(spark, sf, name):
    con = duckdb.connect()
    for t in os.listdir(sf):
        con.execute(f"CREATE VIEW {t[:-8]} AS SELECT * FROM '{sf}/{t}'")
    df = QUERIES[name](spark, sf)
    want = con.execute(ORACLES[name])
    names = [c[0] for c in want.description]
    assert sorted(df.columns) == sorted(names)
    key = lambda r: [(str(type(v)), str(v)) for v in r]
    a = sorted(([norm(r[c]) for c in sorted(names)] for r in df.collect()), key=key)
    b = sorted(([norm(r[names.index(c)]) for c in sorted(names)] for r in want.fetchall()), key=key)
    assert a == b


@pytest.mark.parametrize("size", ["sf0.001", "sf0.01"])
def test_client_count_and_validity_against_sql(spark, sf, size):
    test_against_sql(spark, os.path.join(os.path.dirname(sf), size), "part_count_valid")


def test_plans_have_no_cartesian_product_and_push_filters(spark, sf):
    from dyngraph.plans.explain import operators, pushed
    from dyngraph.sources.tables import table

    for name in ("x_hop2_complete", "region_khop2", "part_vote_cut"):
        assert "CartesianProduct" not in operators(QUERIES[name](spark, sf))
    df = table(spark, sf, "orders", "o_orderkey", "o_orderstatus").filter("o_orderstatus = 'F'")
    assert "o_orderstatus" in pushed(df)


def test_entry_gives_rows(spark):
    import __spark_entry__

    assert not __spark_entry__.entry(spark).isEmpty()
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())
