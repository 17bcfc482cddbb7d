"""Every method returns the same edges; kernels and definitions on hand-made sets."""

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from epsgraph.functions.metrics import custom, edit_to, jaccard_to, metric, objects
from epsgraph.functions.trees import INDEXES, CoverTree
from epsgraph.operators import baselines, definitions, downstream, landmark, measures, ring
from epsgraph.operators.points import collapse, expand, points
from epsgraph.plans import planner
from epsgraph.workloads import SETS
from tests.conftest import SF


def frame(spark, vecs, kind="array<double>"):
    return spark.createDataFrame([(i, v) for i, v in enumerate(vecs)], f"pid long, vec {kind}")


def plain(vecs, eps, m):
    out = set()
    for i in range(len(vecs)):
        for j in range(i + 1, len(vecs)):
            if m(vecs[i], vecs[j]) <= eps:
                out.add((i, j))
    return out


def l2(a, b):
    return sum((x - y) ** 2 for x, y in zip(a, b)) ** 0.5


def found(df):
    rows = [(r.src, r.dst) for r in df.collect()]
    assert len(rows) == len(set(rows)) and all(a < b for a, b in rows)
    return set(rows)


BUILDERS = {
    "brute": lambda p, e: ring.brute_graph(p, e, n=3),
    "join": lambda p, e: ring.brute_graph(p, e, how="join"),
    **{f"ring{n}": (lambda p, e, n=n: ring.ring_graph(p, e, n=n, leaf_size=2)) for n in (1, 2, 3, 4, 5)},
    "full ring": lambda p, e: ring.ring_graph(p, e, n=4, halve=False),
    "grid": lambda p, e: ring.grid_graph(p, e, n=3),
    "landmark": lambda p, e: landmark.landmark_graph(p, e, m=4, leaf_size=1),
    "more centres than points": lambda p, e: landmark.landmark_graph(p, e, m=500),
    "ring ghosts": lambda p, e: landmark.landmark_graph(p, e, m=4, ghost="ring", rounds=2),
    "full ghosts": lambda p, e: landmark.landmark_graph(p, e, m=4, half_ghosts=False),
    "greedy": lambda p, e: landmark.landmark_graph(p, e, m=4, how="greedy"),
    "pca": lambda p, e: baselines.pca_sort_graph(p, e),
    "pca local": lambda p, e: baselines.pca_sort_graph(p, e, how="local"),
    "auto": lambda p, e: planner.near_graph(p, e),
}
LATTICE = [[float(x), float(y)] for x in range(4) for y in range(4)]
CASES = {
    "lattice 1": (LATTICE, 1.0, 24), "lattice 1.5": (LATTICE, 1.5, 42), "line": ([[float(i)] for i in range(10)], 1.0, 9),
    "equal": ([[1.0, 2.0]] * 5, 0.5, 10), "one": ([[1.0]], 1.0, 0), "two at eps": ([[0.0], [1.0]], 1.0, 1),
}


@pytest.mark.parametrize("name", BUILDERS)
def test_methods_on_hand_made_sets(spark, name):
    for vecs, eps, n in CASES.values():
        got = found(BUILDERS[name](frame(spark, vecs), eps))
        assert len(got) == n and got == plain(vecs, eps, l2)


@pytest.mark.parametrize("name", ["ring3", "grid", "landmark", "ring ghosts", "auto", "pca"])
def test_methods_on_no_points(spark, name):
    assert BUILDERS[name](frame(spark, []), 1.0).count() == 0


@pytest.mark.parametrize("index", INDEXES)
@pytest.mark.parametrize("k, eps", [(2, 0.05), (8, 0.289), (64, 1.249)])
def test_indexes_equal_a_scan(spark, index, k, eps):
    m = metric("l2")
    x = np.array([r.vec for r in SETS[f"e{k}"].build(spark, SF).orderBy("pid").collect()])
    want = {(i, j) for i, j in zip(*np.nonzero(m.table(x, x) <= eps))}
    i, j, d = INDEXES[index](x, m).query(x, eps)
    assert set(zip(i, j)) == want and len(i) == len(want) and (d <= eps).all()


@pytest.mark.parametrize("options", [dict(leaf_size=1, bailout=1.0), dict(leaf_size=1, bailout=1.0, threshold="level"), dict(leaf_size=1, bailout=1.0, threshold="level", levels="strict"), dict(leaf_size=8), dict(leaf_size=1, bailout=1.0, triangle_skip=False)])
def test_cover_tree_invariants_and_queries(options):
    m = metric("l2")
    x = np.random.default_rng(0).random((150, 2))
    x[10:20] = x[5]
    t = CoverTree(x, m, **options)
    bad = t.violations()
    assert not any(v for k, v in bad.items() if k != "shrinking" or options.get("levels") != "strict")
    for bound in ("radius", "level") if options.get("levels") != "strict" else ("radius",):
        i, j, _ = t.query(x, 0.1, bound)
        assert set(zip(i, j)) == set(zip(*np.nonzero(m.table(x, x) <= 0.1)))
    assert (t.counts(x, 0.3) == (m.table(x, x) <= 0.3).sum(1)).all()
    assert t.sizes()[0] == 150 and sum(r[6] for r in t.rows(np.arange(150))) == sum(v is not None for v in t.members)


def test_triangle_skip_saves_distances():
    x = np.random.default_rng(0).random((400, 2))
    m = metric("l2")
    cost = []
    for skip in (True, False):
        m.evaluations = 0
        CoverTree(x, m, triangle_skip=skip).query(x, 0.05)
        cost.append(m.evaluations)
    assert cost[0] < cost[1] < 400 * 400


@pytest.mark.parametrize("name, tries", [("edit", ["", "a", "ab", "abc", "é", "aé", "kitten", "sitting"]), ("jaccard", [[1], [1, 2], [2, 3], [1, 2, 3]]), ("hamming", [[0], [1], [3], [-1], [7]]), ("l1", LATTICE[:6]), ("linf", LATTICE[:6]), ("angular", LATTICE[1:6]), ("chord", LATTICE[1:6]), ("w1", [[0.5, 1.0], [0.2, 1.0], [1.0, 1.0]])])
def test_metrics_agree_with_their_native_forms_and_axioms(spark, name, tries):
    kind = {"edit": "string", "jaccard": "array<int>", "hamming": "array<bigint>"}.get(name, "array<double>")
    p, m = frame(spark, tries, kind), metric(name)
    if m.native:
        a, b = p.alias("a"), p.alias("b")
        rows = a.crossJoin(b).select(F.col("a.pid").alias("i"), F.col("b.pid").alias("j"), m.native(F.col("a.vec"), F.col("b.vec")).alias("d")).collect()
        x = m.decode(pa.array(tries, {"edit": pa.string(), "jaccard": pa.list_(pa.int32()), "hamming": pa.list_(pa.int64())}.get(name, pa.list_(pa.float64()))))
        table = m.table(x, x)
        assert all(abs(table[r.i, r.j] - r.d) < 1e-7 for r in rows)
    assert baselines.check_metric(p, name).agg(F.sum("violations")).first()[0] == 0


def test_cosine_is_no_metric(spark):
    p = frame(spark, [[1.0, 0.0], [0.7, 0.7], [0.0, 1.0]])
    assert baselines.check_metric(p, "cosine").filter("violations > 0").count() == 1
    with pytest.raises(ValueError):
        planner.near_graph(p, 0.3, "cosine", method="ring")


def plain_edit(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        new = [i]
        for j, y in enumerate(b, 1):
            new.append(min(row[j - 1] + (x != y), row[j] + 1, new[j - 1] + 1))
        row = new
    return row[-1]


def test_edit_and_jaccard_kernels_equal_plain_ones():
    rng = np.random.default_rng(2)
    words = ["", "a", "kitten", "sitting", "漢字", *("".join(rng.choice(list("abcé"), rng.integers(0, 30))) for _ in range(60))]
    for x in words[:20]:
        assert edit_to(objects(words), x).tolist() == edit_to(objects(words), x, 64).tolist() == [plain_edit(x, y) for y in words]
    assert edit_to(objects([]), "a").tolist() == []
    sets = [np.unique(rng.integers(0, 20, rng.integers(0, 12))) for _ in range(40)] + [np.empty(0, int)]
    for x in sets:
        want = [1 - len(set(x) & set(y)) / len(set(x) | set(y)) if len(x) or len(y) else 0.0 for y in sets]
        assert jaccard_to(objects(sets), x) == pytest.approx(want)


def test_strings(spark):
    assert found(landmark.landmark_graph(frame(spark, ["", "a", "ab", "abc"], "string"), 1, "edit", 2)) == {(0, 1), (1, 2), (2, 3)}


def test_bad_points(spark):
    df = spark.createDataFrame([(1, [1.0]), (2, None), (3, [float("nan")]), (None, [1.0]), (4, [None])], "pid long, vec array<double>")
    assert [r.pid for r in points(df, "pid", "vec").collect()] == [1]
    with pytest.raises(Exception):
        points(df, "pid", "vec", on_bad="error").collect()
    with pytest.raises(ValueError):
        planner.near_graph(points(df, "pid", "vec"), -1.0)


def test_collapse_and_expand(spark):
    vecs = [[0.0], [0.0], [1.0], [0.0], [5.0]]
    p = frame(spark, vecs)
    e, g = baselines.over_distinct(p, lambda q: ring.grid_graph(q, 1.0))
    assert found(e) == plain(vecs, 1.0, l2) and collapse(p).count() == 3
    short, _ = baselines.over_distinct(p, lambda q: ring.grid_graph(q, 1.0), expanded=False)
    assert {r.pid: r.degree for r in baselines.weighted_degrees(short, g).collect()} == {0: 3, 1: 3, 2: 3, 3: 3, 4: 0}
    assert expand(short, g).count() == e.count()


def test_greedy_centres_form_a_net(spark):
    p = SETS["e4"].build(spark, SF)
    cs = landmark.centers(p, 12, "greedy")
    kind, gaps = p.schema["vec"].dataType, []
    for k in range(2, 13):
        gaps.append(definitions.separation(cs[:k], "l2", kind))
    assert all(a >= b for a, b in zip(gaps, gaps[1:]))
    assert definitions.is_r_net(p, cs, definitions.coverage_radius(p, cs).first()[0])


@pytest.mark.parametrize("seed", range(20))
def test_longest_first_assignment_bound(seed):
    from itertools import product

    loads = np.random.default_rng(seed).integers(1, 50, 7).astype(float).tolist()
    best = min(max(sum(x for x, t in zip(loads, way) if t == k) for k in range(3)) for way in product(range(3), repeat=7))
    by = [0.0] * 3
    for x, t in zip(loads, landmark.assign_cells(loads, 3)):
        by[t] += x
    assert max(by) <= (4 / 3 - 1 / 9) * best + 1e-9


@pytest.mark.parametrize("bound", ["bisector", "both"])
def test_ghosts_cover_every_cross_pair(spark, bound):
    p = SETS["e4"].build(spark, SF)
    cs = landmark.centers(p, 16)
    a = landmark.assign(p, cs, metric("l2"), 0.141)
    radii = {r.cell: r.radius for r in landmark.cell_stats(a).collect()}
    home = {r.pid: r.home for r in a.collect()}
    sent = {(r.pid, r.cell) for r in landmark.ghosts(a, 0.141, radii, bound, half=True).collect()}
    for r in ring.brute_graph(p, 0.141).collect():
        if home[r.src] != home[r.dst]:
            assert ((r.src, home[r.dst]) in sent) + ((r.dst, home[r.src]) in sent) == 1


def test_all_points_become_ghosts_in_high_dimension(spark):
    """Ghosts a point: few where the intrinsic dimension is low, all cells where it is high."""
    share = {}
    for k, eps in ((2, 0.05), (64, 1.249)):
        p = SETS[f"e{k}"].build(spark, SF)
        n = measures.ghost_stats(p, landmark.centers(p, 16), eps).agg(F.sum("ghosts")).first()[0]
        share[k] = n / p.count()
    assert share[2] < 5 and share[64] > 14


def test_two_sets(spark):
    a, b = frame(spark, LATTICE), frame(spark, [[x + 0.5, y] for x, y in LATTICE])
    got = {(r.left, r.right) for r in landmark.near_join(a, b, 0.6, m=3).collect()}
    assert got == {(i, j) for i, x in enumerate(LATTICE) for j, (u, v) in enumerate(LATTICE) if l2(x, [u + 0.5, v]) <= 0.6}


def test_downstream_on_the_lattice(spark):
    p = frame(spark, LATTICE)
    e = ring.grid_graph(p, 1.5)
    assert downstream.triangles(e).count() == 36 and downstream.rips(e, p).first().euler == 16 - 42 + 36
    d = {r.pid: r.dist for r in downstream.geodesics(ring.grid_graph(p, 1.0), [0]).collect()}
    assert d == {i: float(x + y) for i, (x, y) in enumerate(LATTICE)}
    far = frame(spark, [*LATTICE, [50.0, 50.0]])
    c = downstream.dbscan(ring.grid_graph(far, 1.0), far, 4).collect()
    assert {r.pid for r in c if r.kind == "noise"} == {16} and {r.pid for r in c if r.kind == "border"} == {0, 3, 12, 15}
    assert {r.cluster for r in c if r.kind != "noise"} == {1}
    assert downstream.components(ring.grid_graph(far, 1.0), far).select("component").distinct().count() == 2


def test_lattice_source_and_hand_over(spark):
    from epsgraph.sources.edges import register

    register(spark)
    e = spark.read.format("lattice_edges").option("side", 4).load()
    assert {(r.src, r.dst) for r in e.collect()} == plain(LATTICE, 1.0, l2)


def test_tree_by_levels(spark):
    p = SETS["e2"].build(spark, SF)
    rows = definitions.build_tree_df(p, leaf_size=8).collect()
    by = {r.hub: r for r in rows}
    assert len(by) == len(rows) and sum(r.size for r in rows if r.is_leaf) == 500
    for r in rows:
        kids = [k for k in rows if k.parent == r.hub]
        assert r.is_leaf != bool(kids) and (not kids or sum(k.size for k in kids) == r.size)
        assert all(k.radius <= r.radius / 2 + 1e-9 for k in kids)
    x = np.array([r.vec for r in p.orderBy("pid").collect()])
    assert definitions.build_tree_df(p.limit(0)).count() == 0 and max(r.depth for r in rows) < 15 and len(x) == 500


@pytest.mark.parametrize("n", [1, 40, 300])
@pytest.mark.parametrize("kind", ["plane", "ties", "copies"])
def test_grouped_centres_equal_a_scan_of_all(n, kind):
    rng = np.random.default_rng(n)
    c = {"plane": rng.random((n, 2)), "ties": rng.integers(0, 6, (n, 2)).astype(float), "copies": np.ones((n, 2))}[kind]
    x = rng.random((500, 2)) if kind == "plane" else rng.integers(0, 6, (500, 2)).astype(float)
    m = metric("l2")
    d = m.table(x, c)
    home = d.argmin(1)
    dmin = d[np.arange(500), home]
    groups = landmark.CentreGroups(c, m)
    m.evaluations = 0
    groups.search(x, None)
    assert m.evaluations <= 500 * (n + len(groups.heads)) and (n < 300 or kind != "plane" or m.evaluations < 500 * n / 3)
    for bound in (None, lambda v: (v + 0.1)[:, None], lambda v: np.linspace(0, 1, n)[None, :]):
        got = groups.search(x, bound)
        assert (got[0] == home).all() and (got[1] == dmin).all()
        if bound is not None:
            near = d <= bound(dmin)
            near[np.arange(500), home] = False
            row, cell = np.nonzero(near)
            assert got[2].tolist() == row.tolist() and got[3].tolist() == cell.tolist() and (got[4] == d[row, cell]).all()


def test_user_metric(spark):
    gap = custom("gap", lambda block, x: np.abs(block - x)[:, 0], lambda c: np.array(c.to_pylist(), float))
    p = spark.createDataFrame([(i, [float(i * i)]) for i in range(30)], "pid long, vec array<double>")
    got = {(r.src, r.dst) for r in landmark.landmark_graph(p, 20.0, gap, 4).collect()}
    assert got == {(i, j) for i in range(30) for j in range(i + 1, 30) if j * j - i * i <= 20}


@pytest.mark.parametrize("index", INDEXES)
def test_self_queries_find_each_pair_once(index):
    x, m = np.random.default_rng(3).random((700, 2)), metric("l2")
    x[10:40] = x[5]
    got = [(min(a, b), max(a, b)) for i, j, _ in INDEXES[index](x, m).self_query(0.07, 100) for a, b in zip(i, j)]
    assert len(got) == len(set(got)) and set(got) == {(i, j) for i, j in zip(*np.nonzero(m.table(x, x) <= 0.07)) if i < j}


def test_self_query_measures_about_half():
    x, m = np.random.default_rng(4).random((1000, 3)), metric("l2")
    t = CoverTree(x, m)
    m.evaluations = 0
    t.query(x, 0.1)
    asked, m.evaluations = m.evaluations, 0
    list(t.self_query(0.1))
    assert m.evaluations < 0.65 * asked


def test_stored_trees(spark):
    p = SETS["e4"].build(spark, SF)
    got = found(definitions.stored_tree_graph(definitions.tree_rows(p), p.orderBy(F.desc("pid")), 0.141))
    assert got == found(ring.brute_graph(p, 0.141))
    parts = p.withColumn("part", (F.col("pid") % 3).cast("int"))
    got = found(definitions.stored_tree_graph(definitions.tree_rows(parts, part="part", leaf_size=2), parts, 0.141, part="part"))
    assert got == {(a, b) for a, b in found(ring.brute_graph(p, 0.141)) if a % 3 == b % 3}
    rows = CoverTree(x := np.arange(9.0).reshape(9, 1), metric("l2"), leaf_size=2).rows(np.arange(9))
    for bad in (rows[1:], [r for r in rows if r[0] != len(rows) - 1]):
        with pytest.raises(ValueError):
            CoverTree.of_rows(bad, np.arange(9), x, metric("l2"))
    with pytest.raises(ValueError):
        CoverTree.of_rows(rows, np.arange(1, 10), x, metric("l2"))
    assert definitions.stored_tree_graph(definitions.tree_rows(p.limit(0)), p.limit(0), 0.1).count() == 0


def test_strict_separation_is_reported():
    t = CoverTree(np.random.default_rng(0).random((300, 2)), metric("l2"), leaf_size=1, bailout=1.0)
    assert "level_separating" not in t.violations() and t.violations(False)["level_separating"] > 0
    line = CoverTree(np.array([[0.0], [100.0]]), metric("l2"), leaf_size=1, bailout=1.0)
    assert line.violations(False)["level_separating"] == 0


@pytest.mark.parametrize("kw", [dict(max_cell=2), dict(max_cell=5, m=1), dict(m=200)])
def test_two_sets_with_heavy_cells(spark, kw):
    a, b = frame(spark, LATTICE * 3), frame(spark, [[x + 0.5, y] for x, y in LATTICE] * 2)
    rows = [(r.left, r.right) for r in landmark.near_join(a, b, 0.6, **kw).collect()]
    assert len(rows) == len(set(rows))
    assert set(rows) == {(i, j) for i, x in enumerate(LATTICE * 3) for j, (u, v) in enumerate(LATTICE * 2) if l2(x, [u + 0.5, v]) <= 0.6}


@pytest.mark.parametrize("build", [lambda p, **k: landmark.landmark_graph(p, 0.289, m=16, **k), lambda p, **k: landmark.landmark_graph(p, 0.289, m=16, ghost="ring", rounds=3, **k), lambda p, **k: landmark.landmark_graph(p, 0.289, m=3, max_cell=50, **k), lambda p, **k: ring.ring_graph(p, 0.289, n=5, **k), lambda p, **k: ring.ring_graph(p, 0.289, n=4, rounds_per_job=1, **k)])
def test_reports_tell_of_the_same_work(spark, build):
    p = SETS["e8"].build(spark, SF)
    r = measures.work_stats(build(p, report=True)).first()
    assert r.pairs == build(p).count() and r.rows_moved > r.guest_rows > 0 and 0 < r.most_home_rows <= 500
    assert r.build_distances > 0 and r.home_distances > 0 and r.guest_distances > 0 and r.largest_over_mean >= 1
    again = measures.work_stats(build(p, report=True)).first()
    assert all(r[c] == again[c] for c in ("pairs", "rows_moved", "build_distances", "home_distances", "guest_distances"))


def test_a_ring_task_holds_its_block_and_no_more(spark):
    p = SETS["e8"].build(spark, SF)
    r = measures.work_stats(ring.ring_graph(p, 0.289, n=10, exact=True, report=True)).first()
    assert r.most_home_rows == 50


def test_lsh_reports_no_false_pairs(spark):
    p = SETS["e8"].build(spark, SF)
    r = baselines.recall(baselines.lsh_pairs(p, 0.289), ring.brute_graph(p, 0.289)).first()
    assert r.extra == 0 and r.exact == 4986 and 0.5 < r.recall <= 1


@pytest.mark.parametrize("files", [1, 7])
def test_metric_stream_in_many_batches(spark, tmp_path, files):
    """Files come in any order of ids; every pair once, whichever point is later."""
    from epsgraph.streaming import streams

    p = SETS["e4"].build(spark, SF)
    cs = landmark.centers(p, 8)
    p.repartition(files, F.xxhash64("pid", F.lit(9))).write.parquet(str(tmp_path / "in"))
    come = spark.readStream.schema(p.schema).option("maxFilesPerTrigger", 2).parquet(str(tmp_path / "in"))
    assert found(streams.drained(streams.metric_graph(come, cs, 0.141))) == found(ring.brute_graph(p, 0.141))


def test_metric_stream_of_strings(spark, tmp_path):
    from epsgraph.streaming import streams

    p = SETS["names"].build(spark, SF)
    p.repartition(3, "pid").write.parquet(str(tmp_path / "in"))
    come = spark.readStream.schema(p.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    got = streams.drained(streams.metric_graph(come, landmark.centers(p, 4, metric="edit"), 3, "edit"))
    assert found(got) == found(ring.brute_graph(p, 3, "edit"))
