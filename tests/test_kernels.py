"""Kernels that must not grow with their output, and joins that must not compare all pairs, against brute force."""

import dataclasses
import time

import numpy as np
import pytest

from epsgraph.functions import metrics, trees
from epsgraph.functions.metrics import metric
from epsgraph.functions.trees import INDEXES, Pace
from epsgraph.operators import baselines, ring, sets
from tests.test_whole_tables import check_edges


@pytest.mark.parametrize("eps", [0.0, 0.1, 0.2, 0.5, 0.9])
def test_jaccard_join_finds_every_pair(spark, eps):
    """Near copies at the threshold, copies, one-element and empty sets, elements that most sets share; no tree over the sets."""
    rng = np.random.default_rng(3)
    some = [set(rng.choice(60, rng.integers(1, 25), replace=False).tolist()) | {100, 101} for _ in range(60)]
    some += [(s - {min(s)}) | {200 + k} for k, s in enumerate(some[:30])] + some[:5] + [{100}, {101}, set(), set(), set(range(20)), set(range(18)), set(range(16))]
    words = [sorted(f"w{v}" for v in s) for s in some]
    df = spark.createDataFrame([(7 * k + 3, w) for k, w in enumerate(words)], "pid long, vec array<string>")
    far = lambda x, y: 1 - len(x & y) / len(x | y) if x | y else 0.0
    want = {(7 * i + 3, 7 * j + 3): far(some[i], some[j]) for i in range(len(some)) for j in range(i + 1, len(some)) if far(some[i], some[j]) <= eps}
    check_edges(sets.jaccard_graph(df, eps), want)


def test_jaccard_join_refuses_what_it_cannot_prove(spark):
    with pytest.raises(ValueError):
        sets.jaccard_graph(spark.createDataFrame([(1, ["a"])], "pid long, vec array<string>"), 1.0)


def _pairs(x, eps):
    d = np.sqrt(((x[:, None] - x[None]) ** 2).sum(-1))
    return {(i, j) for i, j in zip(*np.nonzero(d <= eps)) if i < j}


@pytest.mark.parametrize("index", sorted(INDEXES))
def test_answers_stay_small_however_dense_points_are(index, monkeypatch):
    """900 points of which most lie together: after the first, answers shrink to the pairs allowed."""
    monkeypatch.setattr(trees, "MOST_PAIRS", 1 << 14)
    rng = np.random.default_rng(4)
    x = np.concatenate([rng.normal(0, 0.001, (800, 2)), rng.random((100, 2)) * 4])
    x = x[rng.permutation(len(x))]
    tree = INDEXES[index](x, metric("l2"))
    want, got, sizes = _pairs(x, 0.3), [], []
    for i, j, _ in tree.self_query(0.3):
        got += zip(np.minimum(i, j).tolist(), np.maximum(i, j).tolist())
        sizes.append(len(i))
    assert len(got) == len(set(got)) and set(got) == want and len(sizes) > 3 and max(sizes[1:]) < 1 << 16
    crossed = [(a, b) for at, (i, j, _) in Pace().strips(len(x), lambda lo, hi: tree.query(x[lo:hi], 0.3)) for a, b in zip((i + at).tolist(), j.tolist())]
    assert len(crossed) == 2 * len(want) + len(x) and {c for c in crossed if c[0] < c[1]} == want


def test_tables_of_distances_are_cut(monkeypatch):
    """Hamming distances have no prefilter: their tables are cut into strips, with the same answer."""
    rng = np.random.default_rng(5)
    a, b = (rng.integers(0, 1 << 12, (n, 2)).astype(np.uint64) for n in (300, 170))
    m, seen = metric("hamming"), []
    want = m.within(a, b, 9)
    monkeypatch.setattr(metrics, "MOST_CELLS", 1000)
    monkeypatch.setattr(m, "table", lambda x, y, f=m.table: seen.append(len(x) * len(y)) or f(x, y))
    got = m.within(a, b, 9)
    assert max(seen) <= 1000 and len(want[0]) and all(np.array_equal(g, w) for g, w in zip(got, want))


@pytest.mark.parametrize("how", ["blocks", "local"])
@pytest.mark.parametrize("eps", [0.0, 0.02, 0.4, 9.0])
def test_sorted_search_in_blocks(spark, how, eps):
    """Copies, equal projections, an eps that reaches no, some and all blocks; every block beyond the first has guests."""
    rng = np.random.default_rng(6)
    x = np.concatenate([rng.random((150, 3)), np.repeat(rng.random((5, 3)), 6, axis=0)])
    p = spark.createDataFrame([(3 * k + 1, v) for k, v in enumerate(x.tolist())], "pid long, vec array<double>")
    want = {(3 * i + 1, 3 * j + 1): float(np.sqrt(((x[i] - x[j]) ** 2).sum())) for i, j in _pairs(x, eps)}
    check_edges(baselines.pca_sort_graph(p, eps, how), want)


@pytest.mark.parametrize("dim", [2, 40])
def test_brute_join_deals_out_its_pairs(spark, dim):
    rng = np.random.default_rng(7)
    x = rng.random((120, dim))
    eps = float(np.sqrt(dim) / 3)
    p = spark.createDataFrame([(5 * k + 2, v) for k, v in enumerate(x.tolist())], "pid long, vec array<double>")
    e = ring.brute_graph(p, eps, how="join")
    assert "NestedLoop" not in (plan := e._jdf.queryExecution().executedPlan().toString()) and "Cartesian" not in plan
    check_edges(e, {(5 * i + 2, 5 * j + 2): float(np.sqrt(((x[i] - x[j]) ** 2).sum())) for i, j in _pairs(x, eps)})


def _edit(s, t):
    row = list(range(len(t) + 1))
    for i, c in enumerate(s, 1):
        new = [i]
        for j, e in enumerate(t, 1):
            new.append(min(new[-1] + 1, row[j] + 1, row[j - 1] + (c != e)))
        row = new
    return row[-1]


def test_edit_pairs_by_words_and_by_rows():
    rng = np.random.default_rng(5)
    text = lambda n: "".join(rng.choice(list("abAé日\0 😀"), n))
    a = metrics.objects([text(n) for n in (0, 1, 3, 20, 63, 64, 65, 90)] + ["kitten"])
    b = metrics.objects([text(n) for n in (0, 2, 19, 60, 64, 70, 130)] + ["sitting"])
    want = np.array([[_edit(s, t) for t in b] for s in a], float)
    assert (np.array([metrics.edit_to(b, s) for s in a]) == want).all()
    for eps in (0, 3, 12, 40, 200):
        for x, y, d in ((a, b, want), (b, a, want.T)):
            i, j, found = metrics.edit_pairs(x, y, eps, pairs=7)
            assert sorted(zip(i, j)) == list(zip(*np.nonzero(d <= eps))) and (d[i, j] == found).all()


def test_edit_pairs_of_urls_take_microseconds():
    """1.6 million pairs; a table's rows took some 58 microseconds a pair."""
    rng = np.random.default_rng(6)
    u = metrics.objects([f"https://{rng.choice(['blog', 'www', 'm'])}.{''.join(rng.choice(list('aeiostrn'), 9))}.example.org/en/{k}?page=2&ref=x" for k in rng.integers(0, 10**6, 4000)])
    begin = time.process_time()
    metrics.metric("edit").within(u[:400], u, 12)
    assert time.process_time() - begin < 20


@pytest.mark.parametrize("d,eps,off", [(64, 1.2, 0.0), (3, 0.3, 0.0), (3, 0.3, 1e4), (2, 0.0, 5.0)])
def test_pairs_are_the_same_measured_or_only_found(d, eps, off):
    """The last two offsets leave single precision no room."""
    rng = np.random.default_rng(3)
    a, b = (rng.normal(size=(n, d)) / np.sqrt(d) + off for n in (300, 5000))
    b[:50] = a[:50]
    want = np.sqrt(((a[:, None, :] - b[None, :, :]) ** 2).sum(2))
    for measured in (True, False):
        m = dataclasses.replace(metrics.metric("l2"), measured=measured)
        i, j, dist = m.within(a, b, eps)
        assert sorted(zip(i.tolist(), j.tolist())) == list(map(tuple, np.argwhere(want <= eps).tolist()))
        assert m.evaluations == 300 * 5000
        if measured:
            assert np.allclose(dist, want[i, j], rtol=0, atol=1e-9)


def test_a_large_hub_of_scattered_points_is_left_whole_by_a_sample():
    x = np.random.default_rng(5).normal(size=(6000, 64))
    m = metrics.metric("l2")
    tree = trees.CoverTree(x, m)
    assert tree.bailed == 1 and m.evaluations < 2_000_000  # a quarter of all ordered pairs are 9,000,000
    i, j, _ = trees._joined(list(tree.self_query(9.0)))
    want = np.argwhere(np.triu(np.sqrt(np.maximum((x * x).sum(1)[:, None] + (x * x).sum(1) - 2 * x @ x.T, 0)) <= 9.0, 1))
    assert len(want) > 100 and {(min(p), max(p)) for p in zip(i.tolist(), j.tolist())} == set(map(tuple, want.tolist()))
