"""Queries that find neighbours without writing edges out, against numpy, on sets with a crowd of points all near each other."""

import os

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
import pytest

from epsgraph import registry
from epsgraph.operators import implicit, points
from epsgraph.operators.components import checkpoint_dir


def written(spark):
    """Bytes in the checkpoint folder."""
    return sum(os.path.getsize(os.path.join(at, f)) for at, _, files in os.walk(checkpoint_dir(spark)) for f in files)


@pytest.fixture(scope="module")
def crowd(tmp_path_factory):
    """1,200 vectors within a small ball, 60 apart, a pair and a far one; the folder, the vectors and the ids."""
    rng = np.random.default_rng(3)
    x = np.concatenate([rng.normal(0, 0.01, (1200, 64)), rng.normal(0, 0.12, (60, 64)), np.full((2, 64), 5.0), np.full((1, 64), 9.0)]).astype(np.float32)
    ids = np.concatenate([[0, 1], 7 * rng.permutation(len(x) - 2) + 3])
    d = tmp_path_factory.mktemp("crowd")
    pq.write_table(pa.table({"vec_id": ids, "embedding": list(x), "label": np.zeros(len(x), np.int32)}), d / "embeddings.parquet")
    return str(d), x.astype(float), ids


def distances(x, k):
    return np.sqrt(((x[:, None, :k] - x[None, :, :k]) ** 2).sum(-1))


def test_spectral_without_edges(spark, crowd):
    d, x, ids = crowd
    before = written(spark)
    got = {r.pid: r.value for r in registry.ALL["spectral_e4"][0](spark, d).collect()}
    assert written(spark) - before < 2_000_000
    a = (distances(x, 4) <= 0.141) & ~np.eye(len(x), dtype=bool)
    k, v = a.sum(1), np.ones(len(x))
    for _ in range(5):
        v = a @ (v / np.sqrt(np.maximum(k, 1))) / np.sqrt(np.maximum(k, 1))
        v /= np.sqrt((v * v).sum())
    assert got.keys() == set(ids[k > 0].tolist()) and len(got) < len(x)
    assert max(abs(got[p] - w) for p, w in zip(ids.tolist(), v) if p in got) < 1e-6


def test_geodesics_without_edges(spark, crowd):
    d, x, ids = crowd
    before = written(spark)
    got = {(r.source, r.pid): r.dist for r in registry.ALL["geodesics_e4"][0](spark, d).collect()}
    assert written(spark) - before < 2_000_000
    w = np.where((far := distances(x, 4)) <= 0.141, far, np.inf)
    for s in (0, 1):
        best = w[ids.tolist().index(s)]
        for _ in range(len(x)):
            now = np.minimum(best, (best[:, None] + w).min(0))
            if (now == best).all():
                break
            best = now
        mine = {p: v for (t, p), v in got.items() if t == s}
        assert mine.keys() == set(ids[np.isfinite(best)].tolist())
        assert max(abs(mine[p] - v) for p, v in zip(ids.tolist(), best) if p in mine) < 2e-5


def test_clustering_without_edges(spark, crowd):
    d, x, ids = crowd
    before = written(spark)
    got = {r.pid: (r.triangles, r.clustering) for r in registry.ALL["clustering_e8"][0](spark, d).collect()}
    assert written(spark) - before < 2_000_000
    a = ((distances(x, 8) <= 0.289) & ~np.eye(len(x), dtype=bool)).astype(float)
    k, t = a.sum(1), ((a @ a) * a).sum(1) / 2
    c = np.divide(2 * t, k * (k - 1), out=np.zeros(len(x)), where=k > 1)
    assert got.keys() == set(ids.tolist())
    assert all(got[p][0] == round(n) and abs(got[p][1] - v) < 1e-6 for p, n, v in zip(ids.tolist(), t, c))


@pytest.mark.parametrize("home_rows", [7, 1000])
def test_clustering_in_small_blocks_and_strips(spark, crowd, monkeypatch, home_rows):
    _, x, ids = crowd
    monkeypatch.setattr(implicit, "BIT_BYTES", 1)
    monkeypatch.setattr(implicit, "STRIP", 16)
    some = slice(1100, None)
    p = points.points(spark.createDataFrame(pa.table({"pid": ids[some], "vec": list(x[some, :8])})), "pid", "vec")
    a = ((distances(x[some], 8) <= 0.289) & ~np.eye(len(x[some]), dtype=bool)).astype(float)
    hood = implicit.Neighbourhoods(p, 0.289, "l2", home_rows)
    t = hood.run(implicit._Closed, "pid long, closed long, degree long").groupBy("pid").sum("closed", "degree").collect()
    got = {r[0]: (r[1], r[2]) for r in t}
    assert got == {i: (round(c), round(k)) for i, c, k in zip(ids[some].tolist(), ((a @ a) * a).sum(1), a.sum(1))}


def test_flow_clusters_of_a_crowd(spark, crowd):
    """Paths of two edges through the crowd are some 1.7 billion."""
    d, x, ids = crowd
    got = {r.pid: r.cluster for r in registry.ALL["mcl_e2"][0](spark, d).collect()}
    order = np.argsort(ids)
    x, ids = x[order], ids[order]
    m = (distances(x, 2) <= 0.05).astype(float)
    m /= m.sum(0)
    for _ in range(4):
        v = (m @ m) ** 2
        for j in range(len(x)):
            some = np.flatnonzero(v[:, j] > 0)
            rest = some[np.lexsort((some, -np.round(v[some, j], 12)))[50:]]
            v[rest, j] = 0
        v /= v.sum(0)
        m = np.where(v >= 1e-4, v, 0)
    want = {i: ids[np.flatnonzero(np.round(m[:, j], 6) == np.round(m[:, j], 6).max())[0]] for j, i in enumerate(ids.tolist())}
    assert got == want


def test_no_points(spark):
    p = spark.createDataFrame([], "pid long, vec array<double>")
    assert not implicit.spectral(p, 1.0).count() + implicit.geodesics(p, 1.0, [0]).count() + implicit.local_clustering(p, 1.0).count()
