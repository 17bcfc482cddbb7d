"""Queries over whole tables against brute force on small ones, with ids that no modulo filter keeps."""

import pyarrow as pa
import pyarrow.parquet as pq
import numpy as np
import pytest

from pyspark.sql import functions as F

from epsgraph import registry, workloads
from epsgraph.operators import downstream, measures
from epsgraph.plans import experiments
from tests.conftest import TINY


def near(pids, x, eps):
    """{(src, dst): dist} over all pairs."""
    d = np.sqrt(((x[:, None, :] - x[None, :, :]) ** 2).sum(-1))
    return {(min(a, b), max(a, b)): d[i, j] for i, a in enumerate(pids) for j, b in enumerate(pids) if i < j and d[i, j] <= eps}


def check_edges(df, want):
    got = {(r.src, r.dst): r.dist for r in df.collect()}
    assert len(got) == df.count() and got.keys() == want.keys() and want
    assert all(abs(got[k] - want[k]) < 1e-5 for k in want)


@pytest.fixture(scope="module")
def lines(tmp_path_factory):
    """A folder with 300 lines, copies of payloads among them, and their points in the order of their ids."""
    rng = np.random.default_rng(0)
    n = 300
    key = np.arange(n) * 20 + 7
    qty, disc, tax = rng.integers(1, 9, n), rng.integers(0, 3, n), rng.integers(0, 3, n)
    flag, status = rng.choice(list("ANR"), n), rng.choice(list("FO"), n)
    t = pa.table({"l_orderkey": key, "l_partkey": key, "l_suppkey": key, "l_linenumber": np.ones(n, np.int32), "l_quantity": qty.astype(float), "l_extendedprice": np.ones(n), "l_discount": disc / 100, "l_tax": tax / 100, "l_returnflag": flag, "l_linestatus": status})
    d = tmp_path_factory.mktemp("lines")
    pq.write_table(t, d / "lineitem.parquet")
    return str(d), np.column_stack([qty, disc, tax, *[10.0 * (flag == v) for v in "ANR"], *[10.0 * (status == v) for v in "FO"]])


@pytest.mark.parametrize("name", ["graph_landmark_coll_lgf", "graph_pca_sort_lgf"])
def test_graphs_of_all_line_items(spark, lines, name):
    d, x = lines
    check_edges(registry.ALL[name][0](spark, d), near(range(1, len(x) + 1), x, 3.2))


def test_statistics_of_all_line_items(spark, lines):
    d, x = lines
    rows = {r.eps: r for r in registry.ALL["graph_stats_sweep_w5"][0](spark, d).collect()}
    assert set(rows) == {1.5, 3.2, 6.1}
    for eps, r in rows.items():
        degree = np.zeros(len(x), int)
        for a, b in (want := near(range(len(x)), x, eps)):
            degree[[a, b]] += 1
        assert (r.n, r.pairs, r.directed, r.max_degree, r.isolated) == (len(x), len(want), 2 * len(want), degree.max(), (degree == 0).sum())
        assert abs(r.avg_degree - degree.mean()) < 1e-5


@pytest.mark.parametrize("how", ["cyclic", "lpt"])
def test_balance_of_all_line_items(spark, lines, how):
    d, x = lines
    r = registry.ALL[f"balance_{how}"][0](spark, d).first()
    assert r.mean_cell * r.cells == pytest.approx(len(x))


@pytest.fixture(scope="module")
def clicks(tmp_path_factory):
    """A folder with 300 events of odd ids in two days, and their ids, values and seconds."""
    rng = np.random.default_rng(1)
    n = 300
    pid, x, t = np.arange(n) * 10 + 3, rng.random(n).round(3) * 9, 1_704_067_200 + rng.integers(0, 2 * 86400, n)
    d = tmp_path_factory.mktemp("clicks")
    pq.write_table(pa.table({"event_id": pid, "ts": pa.array(t * 1_000_000, pa.timestamp("us")), "value": x}), d / "events.parquet")
    return str(d), pid.tolist(), x, t


def test_stream_graph_of_all_events(spark, clicks):
    d, pid, x, _ = clicks
    check_edges(registry.ALL["stream_graph_value1d"][0](spark, d), near(pid, x[:, None], 0.05))


def test_timed_stream_graph_of_all_events(spark, clicks):
    d, pid, x, t = clicks
    at = dict(zip(pid, t.tolist()))
    want = {(a, b): v for (a, b), v in near(pid, x[:, None], 0.5).items() if abs(at[a] - at[b]) <= 86400}
    check_edges(registry.ALL["stream_graph_timed"][0](spark, d), want)


def test_graph_of_all_orders(spark, tmp_path):
    rng = np.random.default_rng(2)
    n = 200
    price, day = (rng.random(n) * 1e5).round(2), rng.integers(0, 900, n)
    key = np.arange(n) * 5 + 2
    pq.write_table(pa.table({"o_orderkey": key, "o_totalprice": price, "o_orderdate": pa.array(np.datetime64("1992-01-01") + day)}), tmp_path / "orders.parquet")
    check_edges(registry.ALL["graph_auto_o2"][0](spark, str(tmp_path)), near(key.tolist(), np.column_stack([price / 1000, day / 10]), 5.003))


def test_geodesics_go_to_the_end_of_a_long_path_or_refuse(spark):
    n = 67
    e = spark.createDataFrame([(i, i + 1, 1.0) for i in range(n - 1)], "src long, dst long, dist double").coalesce(1)
    assert {r.pid: r.dist for r in downstream.geodesics(e, [0]).collect()} == {i: float(i) for i in range(n)}
    with pytest.raises(RuntimeError):
        downstream.geodesics(e, [0], max_hops=3)


def test_lattice_of_all_parts(spark, tmp_path):
    """Keys with gaps: an edge needs both of its ends in the table."""
    keys = [0, 1, 2, 4, 5, 7, 8, 11, 12, 15, 15]
    pq.write_table(pa.table({"p_partkey": keys}), tmp_path / "part.parquet")
    got = sorted((r.src, r.dst) for r in registry.ALL["ds_lattice_edges"][0](spark, str(tmp_path)).collect())
    assert got == sorted([(a, a + 1) for a in set(keys) if a % 4 < 3 and a + 1 in keys] + [(a, a + 4) for a in set(keys) if a + 4 in keys])


def test_statistics_of_parts_do_not_pair_copies(spark, tmp_path):
    """60,000 copies of two payloads: 1.8 thousand million pairs, of which none is written."""
    n = 60_000
    one = np.arange(n) % 3 == 0
    pq.write_table(pa.table({"p_partkey": np.arange(n), "p_size": one.astype(np.int32) * 9 + 1, "p_retailprice": np.where(one, 10.0, 900.0)}), tmp_path / "part.parquet")
    a, b = n // 3, n - n // 3
    for r in registry.ALL["graph_stats_sweep_w14"][0](spark, str(tmp_path)).collect():
        assert (r.n, r.pairs, r.max_degree, r.isolated) == (n, a * (a - 1) // 2 + b * (b - 1) // 2, b - 1, 0)


def test_copies_of_orders_meet_once(spark, tmp_path, monkeypatch):
    rng = np.random.default_rng(2)
    price, day = np.repeat(rng.integers(1, 40, 12), 25) * 1000.0, np.repeat(rng.integers(0, 100, 12), 25)
    key = rng.permutation(300) * 3 + 1
    pq.write_table(pa.table({"o_orderkey": key, "o_totalprice": price, "o_orderdate": np.datetime64("1992-01-01") + day}), tmp_path / "orders.parquet")
    met, build = [], registry.planner.near_graph
    monkeypatch.setattr(registry.planner, "near_graph", lambda p, *a, **kw: (met.append(p.count()), build(p, *a, **kw))[1])
    x = np.column_stack([price / 1000, day / 10])
    check_edges(registry.ALL["graph_auto_o2"][0](spark, str(tmp_path)), near(key.tolist(), x, 5.003))
    assert met == [len(np.unique(x, axis=0))]


def test_ranks_in_ranges_are_those_of_one_window(spark):
    rows = [(None if k % 17 == 0 else (k * 37) % 50, k % 7, k) for k in range(400)]
    df = spark.createDataFrame(rows, "a long, b long, c long").repartition(5)
    got = {(r.a, r.b, r.c): r.pid for r in workloads.ranked(df, "a", "b", "c").collect()}
    order = sorted(got, key=lambda r: (r[0] is not None, r[0] or 0, r[1], r[2]))
    assert [got[r] for r in order] == list(range(1, 401))
    assert workloads.ranked(df.limit(0), "a", "b", "c").count() == 0


@pytest.mark.parametrize("most", [1_000_000, 10])
def test_kinds_of_lines_have_the_smallest_rank_of_their_copies(spark, monkeypatch, most):
    monkeypatch.setattr(workloads, "MOST_KINDS", most)
    want = workloads.line_flags_all(spark, TINY).groupBy("vec").agg(F.min("pid").alias("pid")).select("pid", "vec")
    got = workloads.line_kinds(spark, TINY)
    assert got.count() == want.count() > 1000 and not got.exceptAll(want).count()
    assert "SinglePartition" not in got._jdf.queryExecution().toString()


def test_counts_without_distances_are_those_with_them(spark):
    p, m = workloads.SETS["e8"].build(spark, TINY), workloads.SETS["e8"].metric()
    for build in experiments._methods(p, 0.289, m, 8).keys():
        a, b = (measures.work_stats(experiments._methods(p, 0.289, m, 8, report=r)[build]()).first() for r in (True, "counts"))
        assert all(a[c] == b[c] for c in ("pairs", "rows_moved", "most_home_rows", "build_distances", "home_distances", "guest_distances"))


@pytest.mark.parametrize("name", ["graph_landmark_coll_lgf", "graph_pca_sort_lgf"])
def test_copies_of_lines_are_written_out_of_rounded_and_kept_groups(spark, lines, name):
    plan = registry.queries()[name](spark, lines[0])._jdf.queryExecution().optimizedPlan().toString().split("\n")
    assert any("InMemoryRelation" in p for p in plan)
    assert min(k for k, p in enumerate(plan) if "round(dist" in p) > max(k for k, p in enumerate(plan) if "Generate explode(md" in p)
