"""Snapshots, regions, partitioner, recurrent states, training: brute force and invariants."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from dyngraph.functions import evaluate
from dyngraph.operators import exchange, partition, partition_rivals, primitives, recurrent, region, snapshots, trainer
from dyngraph.sources import graphs


def frame(spark, edges):
    return spark.createDataFrame([(min(a, b), max(a, b), t) for a, b, t in edges], "a long, b long, first int")


def rows(df, *cols):
    return sorted(tuple(r[c] for c in cols) for r in df.collect())


def test_sliding_returns_after_a_gap(spark):
    ev = spark.createDataFrame([(1, 2, 0), (1, 2, 1), (1, 2, 7)], "a long, b long, snap int")
    assert rows(snapshots.sliding(ev, 3), "since", "until") == [(0, 3), (7, 9)]
    live = snapshots.sliding(ev, 3)
    assert rows(snapshots.delta(live, 4), "a", "b", "op") == [(1, 2, "-")]
    assert rows(snapshots.delta(live, 7), "a", "b", "op") == [(1, 2, "+")]


def test_empty_delta_has_no_region(spark):
    e = frame(spark, [(1, 2, 0)])
    assert region.khop(e, region.seeds(e, 5), 2).isEmpty()


def test_khop_and_rings(spark):
    e = frame(spark, [(1, 2, 0), (2, 3, 0), (3, 4, 0), (4, 5, 1)])
    seeds = region.seeds(e, 1)
    assert rows(seeds, "vid") == [(4,), (5,)]
    assert rows(region.khop(e, seeds, 2), "vid", "hop") == [(2, 2), (3, 1), (4, 0), (5, 0)]
    assert rows(region.rings(e, seeds, 2), "layer", "vid") == [(1, 4), (1, 5), (2, 3), (2, 4), (2, 5)]


def test_components_against_union_find(spark):
    rng = np.random.default_rng(1)
    edges = [(int(a), int(b)) for a, b in rng.integers(0, 200, (150, 2)) if a != b]
    parent = list(range(200))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in edges:
        parent[max(find(a), find(b))] = min(find(a), find(b))
    got = dict(rows(primitives.components(frame(spark, [(a, b, 0) for a, b in edges])), "vid", "label"))
    assert got == {v: find(v) for v in got} and set(got) == {v for e in edges for v in e}


def test_first_placement_covers_disconnected_graph(spark):
    e = frame(spark, [(i, i + 1, 0) for i in range(0, 20, 2)] + [(100, i, 0) for i in range(101, 110)])
    asg = partition.initial(e, None, partition.Config(3, rounds=1))
    got = rows(asg, "vid", "part")
    assert len(got) == len({v for v, _ in got}) == 30 and {p for _, p in got} <= {0, 1, 2}


def test_extension_keeps_old_vertices_and_places_chains(spark):
    e = frame(spark, [(1, 2, 0), (3, 4, 0), (2, 5, 1), (5, 6, 1), (7, 8, 1)])
    prev = spark.createDataFrame([(1, 0), (2, 0), (3, 1), (4, 1), (99, 1)], "vid long, part int")
    got = dict(rows(partition.extend(prev, e, None, partition.Config(2, rounds=1)), "vid", "part"))
    assert {v: got[v] for v in (1, 2, 3, 4)} == {1: 0, 2: 0, 3: 1, 4: 1}
    assert got[5] == got[6] == 0 and 99 not in got and {7, 8} <= set(got)


def test_changed_client_count_starts_anew(spark):
    prev = spark.createDataFrame([(1, 0), (2, 5)], "vid long, part int")
    assert not partition.is_valid(prev, 6, 4) and not partition.is_valid(prev, 4, 5) and partition.is_valid(prev, 6, 6) and not partition.is_valid(None, 4, 4)


def test_modularity_finds_two_cliques(spark):
    clique = lambda o: [(o + i, o + j, 0) for i in range(5) for j in range(i)]
    label = dict(rows(partition_rivals.modularity(frame(spark, clique(0) + clique(10) + [(0, 10, 0)])), "vid", "label"))
    assert len({label[i] for i in range(5)}) == len({label[10 + i] for i in range(5)}) == 1 and label[0] != label[10]


def test_gru_matrix_equals_scalar(spark):
    w = {"wz": 0.5, "uz": -0.2, "wr": 0.1, "ur": 0.7, "wh": 1.0, "uh": -0.5}
    full = {k: np.array([[v]]) for k, v in w.items()} | {f"b{g}": np.zeros(1) for g in "zrh"}
    cur = spark.createDataFrame([(1, [0.3]), (2, [-1.0])], "vid long, x array<double>")
    prev = spark.createDataFrame([(1, [0.5])], "vid long, x array<double>")
    a = {r["vid"]: r["x"][0] for r in recurrent.gru(cur, prev, full).collect()}
    flat = lambda df: df.select("vid", F.get("x", F.lit(0)).alias("x"))
    b = {r["vid"]: r["x"] for r in recurrent.gru_scalar(flat(cur), flat(prev), w).collect()}
    assert a == pytest.approx(b)


@pytest.mark.parametrize("task", ["class", "link"])
def test_gradient_by_finite_differences(task):
    rng = np.random.default_rng(2)
    s = trainer.Settings(hidden=3, layers=2)
    m = trainer.model(2, 3, s)
    src, dst = np.array([0, 1, 1, 2, 3, 0]), np.array([1, 0, 2, 1, 0, 3])
    x = rng.normal(size=(4, 2))
    mul = trainer._adjacency(4, src, dst, "mean")
    y = np.array([0, 2, -1, 1])
    pairs = np.array([[0, 1, 1], [1, 2, 1], [2, 3, 0]])
    _, g = trainer.loss_and_gradient(m, x, mul, task, y, pairs)
    for k in m:
        if task == "link" and k == "out":
            continue
        for i in np.ndindex(m[k].shape):
            up, down = ({**m, k: m[k].copy()} for _ in range(2))
            up[k][i] += 1e-6
            down[k][i] -= 1e-6
            num = (trainer.loss_and_gradient(up, x, mul, task, y, pairs)[0] - trainer.loss_and_gradient(down, x, mul, task, y, pairs)[0]) / 2e-6
            assert g[k][i] == pytest.approx(num, abs=1e-5)


def test_ranking_skips_queries_without_positive_and_orders_ties(spark):
    s = spark.createDataFrame([(1, 10, 0.5, 0), (1, 11, 0.5, 1), (2, 10, 0.9, 0), (3, 1, 0.1, 1)], "query long, cand long, score double, y int")
    assert evaluate.mrr(s).first()["mrr"] == 0.75
    assert evaluate.mrr(s, "optimistic").first()["mrr"] == 1.0
    assert evaluate.map_by_query(s).first()["queries"] == 2


def test_link_measures_rank_every_query_as_the_listed_pairs_do(spark):
    rng = np.random.default_rng(3)
    x = np.round(rng.normal(size=(60, 3)), 1)  # coarse, so that scores tie
    x[40:] = x[:20]
    h = spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(x)], "vid long, x array<double>")
    links = {(int(a), int(b)) for a, b in rng.integers(0, 64, (70, 2)) if a != b}  # vertices 60 to 63 have no state
    pos = spark.createDataFrame(sorted(links), "query long, cand long")
    cands = spark.range(50).toDF("vid")  # 50 to 59 come as positives only
    listed = {(a, b): 1 for a, b in links if max(a, b) < 60}
    listed |= {(a, b): 0 for a in {a for a, _ in links if a < 60} for b in range(50) if a != b and (a, b) not in links}
    pairs = spark.createDataFrame([(a, b, y) for (a, b), y in listed.items()], "u long, v long, y int")
    sc = evaluate.dot_scores(h, pairs).select(pairs.u.alias("query"), pairs.v.alias("cand"), "score", "y")
    want = (*evaluate.mrr(sc).first(), evaluate.map_by_query(sc).first()["map"], evaluate.accuracy(sc).first()["accuracy"])
    assert tuple(evaluate.link_measures(h, pos, cands).first()) == want
    assert tuple(evaluate.link_measures(h, pos, cands, block=25, rows=60).first()) == want
    assert tuple(evaluate.link_measures(h, pos.limit(0), cands).first()) == (0, None, None, None)


def test_counts_ahead_equal_plain_comparison():
    rng = np.random.default_rng(4)
    c = rng.normal(size=(3000, 6)) * [3, 1, 1, 0.1, 0.1, 0.01]
    c[2000:] = c[:1000]
    ids = rng.permutation(3000)
    k = rng.integers(0, 3000, 500)
    q, plain = rng.normal(size=(500, 6)), np.zeros((500, 3000))
    for dim in range(6):
        plain = plain + q[:, dim, None] * c[None, :, dim]
    s = plain[np.arange(500), k]
    want = ((plain > s[:, None]) | ((plain == s[:, None]) & (ids[None] < ids[k][:, None]))).sum(axis=1)
    assert (evaluate.ahead(q, s, ids[k], c, ids, size=64, chunk=100) == want).all()


def test_chosen_region_stops_growing_once_it_is_too_large(spark, monkeypatch):
    e = frame(spark, [(8 * i, 8 * i + 8, 0) for i in range(1, 12)] + [(8, 40, 1)])
    now = snapshots.at(e, 1)
    hops, khop = [], region.khop
    monkeypatch.setattr(region, "khop", lambda edges, start, k: hops.append(k) or khop(edges, start, k))
    for above, taken in ((0.9, [0, 1, 1]), (0.4, [0, 1]), (0.1, [0])):
        hops.clear()
        found = {tuple(r) for r in region.chosen(e, 1, 2, above).select("vid", "hop").collect()}
        assert hops == taken
        want = khop(now, region.seeds(e, 1), 2) if above == 0.9 else graphs.vertices(now).selectExpr("vid", "0")
        assert found == {tuple(r) for r in want.collect()}


def test_counts_take_few_of_all_products():
    met = []

    class Counted(np.ndarray):
        def __array_ufunc__(self, ufunc, method, *inputs, **named):
            out = getattr(ufunc, method)(*(np.asarray(i) for i in inputs), **named)
            met.append(out.size if ufunc is np.matmul else 0)
            return out

    c = np.random.default_rng(5).normal(size=(40_000, 4)) * [1, 1, 0.05, 0.01]
    q, s, plain = c[:64], c[:64, 0] * 0.3, np.zeros((64, len(c)))
    for dim in range(4):
        plain = plain + q[:, dim, None] * c[None, :, dim]
    n = evaluate.ahead(q.view(Counted), s, np.full(64, -1), c.view(Counted), np.arange(len(c)))
    assert (n == (plain > s[:, None]).sum(axis=1)).all()
    assert sum(met) - c.size - q.size < 0.1 * plain.size


def test_every_vertex_with_a_new_link_is_a_query(spark):
    from dyngraph.catalog.learning import _ranked

    e = frame(spark, [(8, 16, 0), (16, 24, 0), (24, 32, 0), (8, 24, 1), (16, 32, 1)])
    h = spark.createDataFrame([(8 * i, [float(i), 1.0]) for i in range(1, 5)], "vid long, x array<double>")
    assert _ranked(e, h, 1).first()["queries"] == 4


def _vectors(spark, tmp_path, x):
    spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(x)], "vec_id long, embedding array<float>").write.parquet(f"{tmp_path}/embeddings.parquet")
    x = x.astype(np.float32).astype(np.float64)
    n, plain = np.sqrt((x * x).sum(axis=1)), np.zeros((len(x), len(x)))
    for i in range(len(x)):
        plain[i] = (x[i] * x).sum(axis=1) / (n[i] * n)
        plain[i, i] = -2
    return plain


def test_nearest_vectors_tie_by_id_in_any_block(spark, tmp_path):
    x = np.random.default_rng(6).normal(size=(120, 8))
    x[20:70] = x[3]  # more copies than places, dealt over all blocks
    plain = _vectors(spark, tmp_path, x)
    want = sorted((i * 8 + 6, int(j) * 8 + 6) for i in range(120) for j in np.lexsort((np.arange(120), -plain[i]))[:3])
    assert rows(graphs.vec(spark, str(tmp_path), block=50), "x", "y") == want


def test_hashed_neighbours_list_no_pairs_and_equal_brute_force(spark, tmp_path):
    from dyngraph.plans.explain import operators

    x = np.random.default_rng(7).normal(size=(150, 8))
    x[20:60] = x[3]
    plain = _vectors(spark, tmp_path, x)
    planes = np.random.default_rng(5).normal(size=(4, 2, 8))
    side = np.einsum("tbw,nw->ntb", planes, x.astype(np.float32).astype(np.float64)) >= 0
    met = (side[:, None] == side[None]).all(axis=3).any(axis=2)
    plain[~met] = -2
    order = [np.lexsort((np.arange(150), -plain[i]))[:3] for i in range(150)]
    want = sorted((i * 8 + 6, int(j) * 8 + 6) for i in range(150) for j in order[i] if plain[i, j] > -2)
    found = graphs.vec_hashed(spark, str(tmp_path), bits=2, tables=4, block=30)
    assert rows(found, "x", "y") == want
    assert "SortMergeJoin" not in operators(found)


def test_sums_by_row_equal_add_at_to_the_last_bit():
    rng = np.random.default_rng(8)
    x, at = rng.normal(size=(900, 3)), rng.integers(0, 40, 900)
    got, want = (rng.normal(size=(50, 3)),) * 2
    got, want = got.copy(), want.copy()
    trainer.add_at(got, at, x)
    np.add.at(want, at, x)
    assert (got == want).all()


def test_runs_share_what_does_not_hang_on_the_model():
    held, made = trainer.Held(), []
    assert [trainer.once(held, ("a",), lambda: made.append(1) or len(made)) for _ in range(3)] == [1, 1, 1]


def test_hub_and_duplicates_make_one_edge_each(spark):
    ev = spark.createDataFrame([(1, 2, 3), (2, 1, 1), (1, 1, 0)] + [(0, i, 0) for i in range(3, 50)], "x long, y long, snap int")
    e = graphs.undirected(ev)
    assert e.count() == 48 and e.filter("a = 1 and b = 2").first()["first"] == 1


def test_balance_first_fills_the_lightest(spark):
    both = spark.createDataFrame([(i, 1000 + i) for i in range(59)] + [(2000 + i, 3000 + i) for i in range(40)], "src long, dst long")
    both = both.unionAll(both.select("dst", "src"))
    held = spark.createDataFrame([(i, 0) for i in range(59)], "vid long, part int")
    new = spark.createDataFrame([(2000 + i,) for i in range(40)], "vid long")
    got = partition.place(both, new, held, None, partition.Config(4, primary="balance")).groupBy("part").count().collect()
    assert sorted((r["part"], r["count"]) for r in got) == [(1, 14), (2, 13), (3, 13)]
    assert partition.place(both, new.limit(0), held, None, partition.Config(4, primary="balance")).isEmpty()


def test_multilevel_keeps_every_vertex_where_matching_stalls(spark):
    e = spark.createDataFrame([(0, i) for i in range(1, 101)] + [(200, 201), (202, 203)], "a long, b long")
    got = partition_rivals.multilevel(e, 2, coarse=5)
    assert got.count() == got.select("vid").distinct().count() == 105


def test_gradient_of_the_cell_by_differences():
    rng = np.random.default_rng(2)
    s = trainer.Settings(hidden=3, layers=2)
    m = trainer.model(2, 3, s)
    x, prev, y = rng.normal(size=(5, 2)), rng.normal(size=(5, 3)), np.array([0, 1, 2, -1, 0])
    mul = trainer._adjacency(5, np.array([0, 1, 2, 3]), np.array([1, 0, 3, 2]), "mean")
    _, g = trainer.loss_and_gradient(m, x, mul, "class", y, None, None, prev)
    assert {"g_wz", "g_uh", "g_br"} <= set(g)
    for k in m:
        for i in range(m[k].size):
            up, down = ({n: v.copy() for n, v in m.items()} for _ in range(2))
            up[k].flat[i] += 1e-6
            down[k].flat[i] -= 1e-6
            num = (trainer.loss_and_gradient(up, x, mul, "class", y, None, None, prev)[0] - trainer.loss_and_gradient(down, x, mul, "class", y, None, None, prev)[0]) / 2e-6
            assert abs(num - g[k].flat[i]) < 1e-5, (k, i)


def test_importance_holds_what_mattered_before():
    import pandas as pd

    s = trainer.Settings(task="class", hidden=3, epochs=4, importance=1.0)
    m = trainer.model(2, 3, s)
    rng = np.random.default_rng(4)
    nodes = pd.DataFrame({"part": 0, "vid": range(8), "x": list(rng.normal(size=(8, 2))), "extra": [np.zeros(2)] * 8, "prev": [np.zeros(3)] * 8, "y": [0, 1, 2, 0, 1, 2, 0, 1], "train": True})
    pairs = pd.DataFrame({"part": 0, "src": [0, 1, 2, 3], "dst": [1, 0, 3, 2]})

    def step(anchor):
        got = trainer.local_step(nodes, pairs, anchor, anchor, s)
        return {k: np.array(v).reshape(m[k].shape) for k, v in zip(got["name"], got["data"], strict=True)}

    free, held = step(m), step({**m, "i_out": np.full_like(m["out"], 5.0)})
    assert np.abs(held["out"] - m["out"]).sum() < np.abs(free["out"] - m["out"]).sum()
    weights = np.concatenate([v.ravel() for k, v in free.items() if k.startswith("i_")])
    assert weights.mean() == pytest.approx(1) and weights.min() >= 0 and weights.std() > 0
    assert set(free) == set(m)


def test_schedules_cell_and_hops_change_the_training(spark, sf):
    from dataclasses import replace

    from dyngraph.catalog import learning
    from dyngraph.sources import graphs
    from dyngraph.sources.tables import materialise

    e = materialise(graphs.edges(spark, sf, "copurchase"), "edges")
    asg = materialise(graphs.by_key(graphs.vertices(e), 3), "assignment")
    base = trainer.Settings(task="class", hidden=4, rounds=2, epochs=2)
    feats, y = learning._features(spark, sf, e), learning.segments(spark, sf)
    loss = {}
    for name, s in (("none", replace(base, scheme="none")), ("last", base), ("first", replace(base, schedule=exchange.Schedule("first", "all"))), ("plain", replace(base, cell="")), ("two", replace(base, hops=2))):
        _, log, _ = trainer.live_update(e, 9, feats, y, asg, s, 5, first=8)
        loss[name] = [round(r["loss"], 9) for r in log]
    assert loss["none"][0] == loss["last"][0] != loss["first"][0]  # an exchange after the last epoch serves the next round
    assert loss["none"][1] != loss["last"][1] and len({tuple(v) for v in loss.values()}) == 5
