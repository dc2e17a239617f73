"""Corrections on a worked example, against matrices, and their invariants."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from dyngraph.functions import cost, quality
from dyngraph.operators import clients, exchange, message
from dyngraph.sources import graphs

EDGES = [(1, 2), (1, 3), (2, 3), (4, 5), (5, 6), (3, 4)]


def small(spark, edges=EDGES, split=3):
    e = spark.createDataFrame([(a, b, 0) for a, b in edges], "a long, b long, first int")
    v = graphs.vertices(e)
    asg = v.select("vid", (F.col("vid") > split).cast("int").alias("part"))
    x = v.select("vid", F.array(F.when(F.col("vid") < 10, F.pow(F.lit(10), F.col("vid") - 1)).otherwise(F.col("vid") * 7).cast("long")).alias("x"))
    return clients.placed(e, asg), asg, x


def values(df):
    return {r["vid"]: r["x"][0] for r in df.collect()}


def test_worked_example(spark):
    ee, _, x = small(spark)
    assert values(exchange.hop1(ee, x, d=1)) == {3: 1000, 4: 100}
    assert values(exchange.hop2(ee, x, "complete", d=1)) == {1: 1000, 2: 1000, 3: 12100, 4: 1211, 5: 100}
    assert values(exchange.hop2(ee, x, "printed", d=1)) == {3: 12200, 4: 2211}
    assert values(exchange.hop2(ee, x, "printed_excl_self", d=1)) == {3: 12100, 4: 1211}
    assert values(exchange.truth(ee, x, 2, 1)) == {1: 1333, 2: 1333, 3: 12433, 4: 123211, 5: 232100, 6: 221000}


def test_complete_equals_matrix_power(spark):
    rng = np.random.default_rng(0)
    n = 30
    edges = sorted({(min(a, b), max(a, b)) for a, b in rng.integers(1, n, (80, 2)).tolist() if a != b})
    ee, _, x = small(spark, edges, split=15)
    adj = np.eye(n + 1, dtype=object)
    for a, b in edges:
        adj[a, b] = adj[b, a] = 1
    feats = values(x)
    vec = np.array([feats.get(i, 0) for i in range(n + 1)], dtype=object)
    got = values(exchange.apply(exchange.local_states(ee, x, 2, 1), exchange.hop2(ee, x, d=1)))
    want = adj.dot(adj.dot(vec))
    assert all(got[i] == want[i] for i in got)


def test_one_client_needs_no_message(spark):
    ee, asg, x = small(spark, split=100)
    assert exchange.outbox(ee, x, asg, 0, d=1).isEmpty()
    assert quality.cut_ratio(ee).first()["cut"] == 0


def test_region_restricts_receivers_only(spark):
    ee, _, x = small(spark)
    region = spark.createDataFrame([(1,), (3,)], "vid long")
    assert values(exchange.hop2(ee, x, region=region, d=1)) == {1: 1000, 3: 12100}


def test_conservation_of_first_corrections(spark):
    ee, _, x = small(spark)
    feats, sent = values(x), values(exchange.hop1(ee, x, d=1))
    degree = {r["vid"]: r["remote"] for r in clients.remote_neighbours(ee).collect()}
    assert sum(sent.values()) == sum(feats[v] * n for v, n in degree.items())


def test_schedules_and_limits(spark):
    assert [s.firings(5, 10) for s in exchange.SCHEDULES] == [10, 10, 1, 1]
    ee, asg, x = small(spark)
    with pytest.raises(ValueError):
        exchange.outbox(ee, x, asg, 0, hops=3)
    assert exchange.outbox(ee, x, asg, 0, hops=1, min_group=2, d=1).isEmpty()


def test_cost_model(spark):
    p = spark.createDataFrame([("a", 1, 0.0006, 42000, 100, 4, 8, 0.1)], "name string, firings long, ratio double, edges long, dim long, width long, snaps long, latency double")
    r = cost.model(p).first()
    assert (r["bytes"], r["seconds"]) == (10080.0, 0.8)


def test_isolated_vertex_keeps_its_vector(spark):
    ee, _, x = small(spark)
    more = x.unionAll(spark.createDataFrame([(9, [7])], "vid long, x array<long>"))
    assert values(message.aggregate(ee, more, "sum", d=1))[9] == 7
