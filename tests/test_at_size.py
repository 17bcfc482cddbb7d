"""What lets queries meet larger tables: whole sets, answers in batches, few vertices entered."""

import numpy as np
import pyarrow as pa
import pytest

from epsgraph import registry, workloads
from epsgraph.functions import tables
from epsgraph.functions.metrics import metric
from epsgraph.functions.trees import CoverTree
from epsgraph.operators import definitions, implicit, points
from epsgraph.plans import experiments
from tests.conftest import TINY


def test_speedups_run_every_set_and_radius(spark, monkeypatch):
    monkeypatch.setattr(experiments, "seconds", lambda df: 1.0)
    monkeypatch.setattr(experiments.baselines, "pca_sort_graph", lambda *a, **kw: None)
    monkeypatch.setattr(experiments, "_methods", lambda *a, **kw: {m: lambda: None for m in ("landmark_collective", "landmark_ring", "ring")})
    rows = registry.ALL["experiment_speedups"][0](spark, TINY).collect()
    assert {(r.dataset, r.eps) for r in rows} == {(n, float(eps)) for n in ("e64", "lgd", "uc") for eps in workloads.SETS[n].radii}
    assert len(rows) == 3 * 3 * 3 * 3


def test_near_pairs_go_out_in_batches(spark, monkeypatch):
    monkeypatch.setattr(tables, "BATCH", 100)
    rng = np.random.default_rng(0)
    x = rng.integers(0, 4, (60, 2)).astype(float)
    held = tables.NearPairs.func()
    for lo in (0, 25):
        n = len(x[lo : lo + 25] if lo == 0 else x[lo:])
        held.eval(pa.record_batch({"label": [0] * n, "pid": np.arange(lo, lo + n), "vec": x[lo : lo + n].tolist()}), pa.array([1.5] * n))
    found = list(held.terminate())
    want = {(a, b) for a in range(60) for b in range(a + 1, 60) if np.sqrt(((x[a] - x[b]) ** 2).sum()) <= 1.5}
    got = [p for t in found for p in zip(t["src"].to_pylist(), t["dst"].to_pylist())]
    assert all(t.num_rows <= 100 for t in found) and len(found) > 1 and len(got) == len(want) and set(got) == want
    for name in ("udtf_near_pairs", "udtf_tree_nodes"):
        assert "ArrowEvalPythonUDTF" in registry.ALL[name][0](spark, TINY)._jdf.queryExecution().toString()


def test_tree_costs_ask_points_that_lie_together(spark, monkeypatch):
    rng = np.random.default_rng(0)
    x = rng.random((3000, 2))
    p = spark.createDataFrame([(k, v) for k, v in enumerate(x.tolist())], "pid long, vec array<double>")
    entered = []
    query = CoverTree.query

    def counted(tree, q, eps, bound=None):
        entered.append(np.ptp(q, axis=0).prod())
        return query(tree, q, eps, bound)

    tree = CoverTree(x, m := metric("l2"), leaf_size=1)
    order, last = tree.numbered()
    assert sorted(order.tolist()) == list(range(3000)) and last[0] == 2999
    m.evaluations = 0
    for at in range(0, 3000, 500):
        counted(tree, x[order[at : at + 500]], 0.01)
    asked, m.evaluations = m.evaluations, 0
    assert np.mean(entered) < 0.7  # in order of their ids each strip spans the whole square
    tree.query(x, 0.01)
    assert definitions.tree_stats(p, 0.01, "l2", leaf_size=1).first().query_distances == asked == m.evaluations
    assert CoverTree(x[:0], m).numbered()[0].tolist() == []


def test_tree_costs_are_one_job_of_many_trees(spark, monkeypatch):
    jobs, stats = [], definitions.tree_stats
    monkeypatch.setattr(experiments.definitions, "tree_stats", lambda *a, **kw: (jobs.append(a[1]), stats(*a, **kw))[1])
    first = type(spark.range(1)).first
    monkeypatch.setattr(type(spark.range(1)), "first", lambda df: pytest.fail("a tree of its own") if "query_distances" in df.columns else first(df))
    rows = registry.ALL["experiment_tree_costs"][0](spark, TINY).collect()
    assert len(jobs) == 15 and len(rows) == 45
    assert {r.dataset for r in rows} == {"e2", "e4", "e8", "e64", "p2"} and all(0 < r.value < 3 for r in rows)


@pytest.mark.parametrize("most", [1, 1 << 18])
def test_members_do_not_travel_with_edges(spark, monkeypatch, most):
    monkeypatch.setattr(points, "MOST_MEMBERS", most)
    members = {5: [5, 105], 1: [1, 101, 201], 7: [7], 9: [9, 12]}
    groups = spark.createDataFrame([(r, [0.0], m) for r, m in members.items()], "rep long, vec array<double>, members array<long>")
    edges = [(5, 1, 0.5), (1, 7, 0.25), (9, 5, 0.75), (7, 9, 1.0)]
    found = points.expand(spark.createDataFrame(edges, points.EDGE), groups)
    want = {(min(a, b), max(a, b), d) for s, t, d in edges for a in members[s] for b in members[t]}
    want |= {(min(a, b), max(a, b), 0.0) for m in members.values() for a in m for b in m if a != b}
    rows = [tuple(r) for r in found.collect()]
    assert len(rows) == len(want) and set(rows) == want
    assert "Join" not in found._jdf.queryExecution().executedPlan().toString()
    assert points.expand(spark.createDataFrame([], points.EDGE), groups.limit(0)).count() == 0


def test_flow_entries_are_bounded_by_groups_of_points(monkeypatch):
    rng = np.random.default_rng(0)
    x = rng.random((3000, 2))
    x[100:110] = x[100]
    pid = rng.permutation(3000) * 3
    value = 1 / (1 + rng.random(3000))
    home = np.flatnonzero(((x - 0.5) ** 2).sum(1) < 0.01)

    def run(fewest):
        monkeypatch.setattr(implicit, "FEWEST_BOUNDED", fewest)
        m = metric("l2")
        f = implicit._Flow(m, 0.15, pa.table({"pid": pid[home], "vec": x[home].tolist()}), 2.0, 20)
        f.add(pa.record_batch({"pid": pid, "vec": x.tolist(), "value": value}))
        return {(r["src"], r["dst"]): r["value"] for b in f.result() for r in b.to_pylist()}, m.evaluations

    (plain, all_), (bounded, fewer) = run(10**9), run(0)
    assert plain.keys() == bounded.keys() and len(plain) >= 20 * len(home) and fewer < 0.7 * all_
    assert all(abs(plain[k] - v) < 1e-12 for k, v in bounded.items())
