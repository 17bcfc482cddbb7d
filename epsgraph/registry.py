"""Queries of the graph engine and their SQL."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions.metrics import custom, matrix
from .operators import baselines as B
from .operators import definitions as D
from .operators import downstream as N
from .operators import implicit as I
from .operators import landmark as L
from .operators import measures as C
from .operators import ring as R
from .operators import sets as J
from .plans import planner
from .relational import RELATIONAL
from .streaming import streams
from .workloads import SETS

ROUND = 6


def _edges(df: DataFrame) -> DataFrame:
    return df.select("src", "dst", F.round("dist", ROUND).alias("dist"))


def _edges_sql(name: str, eps: float) -> str:
    return f"SELECT src, dst, round(dist, {ROUND}) AS dist FROM ({SETS[name].edges_sql(eps)})"


def _graph(build: Callable, name: str, at: int = 1) -> tuple[Callable, str]:
    """A query that runs ``build(points, eps, metric)``, and its SQL."""
    ps = SETS[name]
    eps = ps.radii[at]
    return lambda spark, d: _edges(build(ps.build(spark, d), eps, ps.metric())), _edges_sql(name, eps)


def _copies(build: Callable, name: str, at: int = 1) -> tuple[Callable, str]:
    """As ``_graph`` over distinct payloads, whose distances are rounded before their many copies are written out."""
    ps = SETS[name]
    eps = ps.radii[at]
    return lambda spark, d: B.over_distinct(ps.build(spark, d), lambda q: _edges(build(q, eps, ps.metric())), keep=True)[0], _edges_sql(name, eps)


def landmark(**kw) -> Callable:
    return lambda p, eps, m: L.landmark_graph(p, eps, m, **kw)


def ring(**kw) -> Callable:
    return lambda p, eps, m: R.ring_graph(p, eps, m, **kw)


def distinct(build: Callable) -> Callable:
    return lambda p, eps, m: B.over_distinct(p, lambda q: build(q, eps, m))[0]


#: A user's metric: the difference of one number.
BALANCE_GAP = custom("gap", lambda block, x: np.abs(block - x)[:, 0], matrix)

GRAPHS: dict[str, tuple[Callable, str]] = {
    **{f"graph_brute_{n}": _graph(lambda p, eps, m: R.brute_graph(p, eps, m), n) for n in ("e20", "e32", "e40", "e64", "h64")},
    "graph_brute_join_e8": _graph(lambda p, eps, m: R.brute_graph(p, eps, m, how="join"), "e8"),
    **{f"graph_ring_{n}": _graph(ring(n=8), n) for n in ("e20", "e64", "h256", "uc")},
    "graph_ring_full_e8": _graph(ring(n=5, halve=False), "e8"),
    "graph_ring_rounds_e8": _graph(ring(n=6, rounds_per_job=2), "e8"),
    "graph_ring_exact_blocks_e8": _graph(ring(n=5, exact=True), "e8"),
    "graph_ring_grid_e64": _graph(lambda p, eps, m: R.grid_graph(p, eps, m, 4), "e64"),
    **{f"graph_landmark_coll_{n}": _graph(landmark(m=16), n) for n in ("e2", "e4", "e8", "e20", "e64", "url", "w1", "ut")},
    "graph_landmark_coll_lgf": _copies(landmark(m=16), "lgf_all"),
    "graph_landmark_coll_h800": _graph(distinct(landmark(m=16)), "h800"),
    **{f"graph_landmark_ring_{n}": _graph(landmark(m=16, ghost="ring", rounds=3), n) for n in ("e2", "e8", "h256", "names")},
    "graph_landmark_greedy_e4": _graph(landmark(m=8, how="greedy"), "e4"),
    "graph_landmark_fullghost_e4": _graph(landmark(m=16, half_ghosts=False), "e4"),
    "graph_landmark_bisector_e4": _graph(landmark(m=16, bound="bisector"), "e4"),
    "graph_landmark_ball_e4": _graph(landmark(m=16, bound="ball"), "e4"),
    "graph_landmark_ghost_weights_e4": _graph(landmark(m=16, weight="with_ghosts", tasks=3), "e4"),
    "graph_landmark_user_metric_ca": _graph(lambda p, eps, m: L.landmark_graph(p, eps, BALANCE_GAP, 16), "ca"),
    "graph_landmark_cyclic_e4": _graph(landmark(m=16, balance="cyclic", tasks=3), "e4"),
    "graph_landmark_level_e4": _graph(landmark(m=4, threshold="level", levels="strict", leaf_size=1, bailout=1.0), "e4"),
    "graph_landmark_node_level_e4": _graph(landmark(m=4, threshold="level", node_bound="level", leaf_size=1, bailout=1.0), "e4"),
    "graph_landmark_coll_lgd": _graph(landmark(m=60), "lgd", 0),
    "graph_stored_tree_e4": _graph(lambda p, eps, m: D.stored_tree_graph(D.tree_rows(p, m), p, eps, m), "e4"),
    "graph_landmark_heavy_e4": _graph(landmark(m=3, max_cell=40), "e4"),
    "graph_landmark_heavy_ring_e4": _graph(landmark(m=3, max_cell=40, ghost="ring", rounds=2), "e4"),
    "graph_landmark_heavy_fullghost_e4": _graph(landmark(m=3, max_cell=40, half_ghosts=False), "e4"),
    "graph_landmark_m10_e8": _graph(landmark(m=10), "e8"),
    "graph_landmark_m150_e8": _graph(landmark(m=150), "e8"),
    "graph_landmark_m150_greedy_names": _graph(landmark(m=150, how="greedy"), "names"),
    "graph_landmark_m60_e8": _graph(landmark(m=60), "e8"),
    "graph_covertree_single_e8": _graph(landmark(m=1, leaf_size=1), "e8"),
    **{f"graph_pca_sort_{n}": _graph(lambda p, eps, m: B.pca_sort_graph(p, eps), n) for n in ("e8", "e20", "e64")},
    "graph_pca_sort_lgf": _copies(lambda p, eps, m: B.pca_sort_graph(p, eps), "lgf_all"),
    "graph_pca_sort_local_e20": _graph(lambda p, eps, m: B.pca_sort_graph(p, eps, how="local"), "e20"),
    "graph_kdtree_p2": _graph(lambda p, eps, m: R.kdtree_graph(p, eps, 4), "p2"),
    "graph_balltree_e8": _graph(lambda p, eps, m: R.balltree_graph(p, eps, m, 4), "e8"),
    "graph_vptree_names": _graph(lambda p, eps, m: R.vptree_graph(p, eps, m, 2), "names"),
    "graph_jaccard_docs": _graph(distinct(lambda p, eps, m: J.jaccard_graph(p, eps)), "jaccard", 0),
    **{f"graph_auto_{n}": _graph(lambda p, eps, m: planner.near_graph(p, eps, m), n) for n in ("ca", "uc", "e64_angular")},
    "graph_auto_o2": _copies(lambda p, eps, m: planner.near_graph(p, eps, m), "o2_all"),
}

E4, E8, E2 = SETS["e4"], SETS["e8"], SETS["e2"]
IDS = list(range(0, 500, 25))
CENTRES_SQL = "c AS (SELECT row_number() OVER (ORDER BY pid) - 1 AS cell, pid AS cid, vec AS cv FROM p WHERE pid % 25 = 0 AND pid < 500)"
ASSIGN_SQL = f"{CENTRES_SQL}, dd AS (SELECT p.pid, c.cell, list_distance(p.vec, c.cv) AS d FROM p, c), h AS (SELECT pid, arg_min(cell, d * 1e6 + cell * 1e-9) AS home, min(d) AS dmin FROM dd GROUP BY pid)"


def _ids(p: DataFrame) -> list:
    return L.centers(p, 0, "ids", ids=IDS)


def _lg_degrees(spark: SparkSession, d: str) -> DataFrame:
    """Degrees over all line items at eps 1.5, without writing out pairs of copies, as a histogram."""
    ps = SETS["lg"]
    edges, groups = B.over_distinct(ps.build(spark, d), lambda q: L.landmark_graph(q, 1.5, "l2", 16), expanded=False)
    return B.weighted_degrees(edges, groups).groupBy("degree").agg(F.count("*").alias("points"))


LG_SQL = f"""WITH q AS (SELECT vec, count(*) AS n FROM ({SETS['lg'].sql}) GROUP BY vec), p AS (SELECT vec, n, row_number() OVER () AS pid FROM q),
s AS (SELECT a.pid, a.n, CAST(sum(b.n) - 1 AS BIGINT) AS degree FROM p a JOIN p b ON list_distance(a.vec, b.vec) <= 1.5 GROUP BY a.pid, a.n)
SELECT degree, CAST(sum(n) AS BIGINT) AS points FROM s GROUP BY degree"""


def _e(ps, spark, d, at=1, m=16) -> tuple[DataFrame, DataFrame]:
    """Points and edges, the edges cut off from how they were found."""
    p = ps.build(spark, d)
    N.checkpoint_dir(spark)
    return p, L.landmark_graph(p, ps.radii[at], ps.metric(), m).checkpoint()


def _q(ps, f: Callable, at: int = 1) -> Callable:
    return lambda spark, d: f(*_e(ps, spark, d, at))


def _p(ps, f: Callable, at: int = 1) -> Callable:
    """``f(points, eps, metric)``, for what needs no edges written out."""
    return lambda spark, d: f(ps.build(spark, d), ps.radii[at], ps.metric())


def _sym_sql(ps, at: int = 1) -> str:
    return f"WITH p AS ({ps.sql}), e AS MATERIALIZED ({ps.edges_sql(ps.radii[at])}), s AS MATERIALIZED (SELECT src, dst, dist FROM e UNION ALL SELECT dst, src, dist FROM e)"


def _ghosts(bound: str) -> Callable:
    return lambda spark, d: C.ghost_stats(p := E4.build(spark, d), _ids(p), 0.141, bound=bound)


def _ghosts_sql(bisector: bool, ball: bool) -> str:
    tests = ("AND dd.d <= h.dmin + 0.282 " if bisector else "") + "JOIN r ON r.cell = dd.cell" + (" AND dd.d <= r.radius + 0.141" if ball else "")
    return f"WITH p AS ({E4.sql}), {ASSIGN_SQL}, r AS (SELECT home AS cell, max(dmin) AS radius FROM h GROUP BY home) SELECT CAST(dd.cell AS INTEGER) AS cell, CAST(h.home AS INTEGER) AS home, count(*) AS ghosts FROM dd JOIN h ON dd.pid = h.pid AND dd.cell <> h.home {tests} GROUP BY dd.cell, h.home"


def _voronoi(spark: SparkSession, d: str) -> DataFrame:
    p = E4.build(spark, d)
    return L.voronoi(p, _ids(p)).select("pid", "cell", F.round("dmin", ROUND).alias("dmin"))


def _cell_stats(spark: SparkSession, d: str) -> DataFrame:
    p = E4.build(spark, d)
    return L.cell_stats(L.assign(p, _ids(p), E4.metric())).select("cell", "size", F.round("radius", ROUND).alias("radius"))


def _copies_sql(ps, eps: float) -> str:
    """Statistics from distinct payloads with their numbers."""
    return (
        f"(WITH q AS (SELECT vec, count(*) AS n FROM ({ps.sql}) GROUP BY vec), s AS (SELECT a.n, sum(b.n) - 1 AS degree FROM q a JOIN q b ON {ps.distance} <= {eps} GROUP BY a.vec, a.n) "
        f"SELECT CAST(sum(n) AS BIGINT) AS n, CAST(sum(n * degree) / 2 AS BIGINT) AS pairs, CAST(sum(n * degree) AS BIGINT) AS directed, round(sum(n * degree) / sum(n), 6) AS avg_degree, CAST(max(degree) AS BIGINT) AS max_degree, "
        f"CAST(sum(CASE WHEN degree = 0 THEN n ELSE 0 END) AS BIGINT) AS isolated, CAST({eps} AS DOUBLE) AS eps FROM s)"
    )


def _sweep(name: str, copies: bool = False, radii: tuple[float, ...] | None = None) -> tuple[Callable, str]:
    """Statistics at each radius; with ``copies`` from a graph of distinct payloads, so pairs of copies are not written out."""
    ps = SETS[name]
    radii = radii or ps.radii

    def stats(p: DataFrame, eps: float) -> DataFrame:
        build = lambda q: planner.near_graph(q, eps, ps.metric())
        return C.degree_stats(B.weighted_degrees(*B.over_distinct(p, build, expanded=False))) if copies else C.graph_stats(build(p), p)

    def run(spark: SparkSession, d: str) -> DataFrame:
        p, out = ps.build(spark, d), None
        for eps in radii:
            s = stats(p, eps).withColumn("eps", F.lit(float(eps)))
            out = s if out is None else out.unionByName(s)
        return out

    one = lambda eps: f"SELECT n.n, e.pairs, 2 * e.pairs AS directed, round(2.0 * e.pairs / n.n, 6) AS avg_degree, coalesce(m.max_degree, 0) AS max_degree, n.n - m.touched AS isolated, CAST({eps} AS DOUBLE) AS eps FROM (SELECT count(*) AS n FROM ({ps.sql})) n, (SELECT count(*) AS pairs FROM ({ps.edges_sql(eps)})) e, (SELECT max(k) AS max_degree, count(*) AS touched FROM (SELECT v, count(*) AS k FROM (SELECT src AS v FROM ({ps.edges_sql(eps)}) UNION ALL SELECT dst FROM ({ps.edges_sql(eps)})) GROUP BY v)) m"
    return run, " UNION ALL ".join(map((lambda eps: _copies_sql(ps, eps)) if copies else one, radii))


def _compare(spark: SparkSession, d: str) -> DataFrame:
    p = E8.build(spark, d)
    return C.compare_graphs(R.ring_graph(p, 0.289, n=5), L.landmark_graph(p, 0.289, m=16))


def _nested(spark: SparkSession, d: str) -> DataFrame:
    p = E8.build(spark, d)
    small, large = (L.landmark_graph(p, e, m=16) for e in (0.205, 0.289))
    return small.join(large, ["src", "dst"], "left_anti").agg(F.count("*").alias("lost"))


def _coverage(spark: SparkSession, d: str) -> DataFrame:
    p = E4.build(spark, d)
    return D.coverage_radius(p, _ids(p)).select(F.round("radius", ROUND).alias("radius"))


def _knn(p: DataFrame, e: DataFrame) -> DataFrame:
    return N.knn_in_graph(e, 5).select("src", "rank", "dst", F.round("dist", ROUND).alias("dist"))


def _dbscan(p: DataFrame, e: DataFrame) -> DataFrame:
    return N.dbscan(e, p, 12)


def _dups(spark: SparkSession, d: str) -> DataFrame:
    """Rows per representative of documents within Jaccard distance 0.2 of token sets."""
    ps = SETS["jaccard"]
    p = ps.build(spark, d)
    e, groups = B.over_distinct(p, lambda q: J.jaccard_graph(q, 0.2), expanded=False)
    parts = N.components(e, groups.select(F.col("rep").alias("pid")))
    return parts.join(groups, F.col("pid") == F.col("rep")).select(F.explode("members").alias("pid"), "component")


def _near_parts(spark: SparkSession, d: str) -> DataFrame:
    from .operators.points import points
    from .workloads import read

    part = read(spark, d, "part")
    side = lambda brand: points(part.filter(F.col("p_brand").startswith(brand)), "p_partkey", F.array(F.col("p_size").cast("double"), "p_retailprice"))
    return L.near_join(side("Brand#1"), side("Brand#2"), 5.005).select(F.col("left").alias("src"), F.col("right").alias("dst"), F.round("dist", ROUND).alias("dist"))


def _separation(spark: SparkSession, d: str) -> DataFrame:
    """The centres' least distance, the covering radius, and whether the centres are a net at the first."""
    p = E4.build(spark, d)
    cs = _ids(p)
    apart = D.separation(cs, "l2", p.schema["vec"].dataType)
    return spark.createDataFrame([(round(apart, ROUND), D.is_r_net(p, cs, apart))], "separation double, net boolean")


def _work(spark: SparkSession, d: str) -> DataFrame:
    """By method: points at home, pairs, and whether fewer distances than all pairs were measured."""
    p, m = E8.build(spark, d), E8.metric()
    runs = {"landmark_collective": L.landmark_graph(p, 0.205, m, 16, report=True), "landmark_ring": L.landmark_graph(p, 0.205, m, 16, ghost="ring", rounds=3, report=True), "ring": R.ring_graph(p, 0.205, m, 8, report=True)}
    out = None
    for method, work in runs.items():
        one = work.agg(F.sum("home_rows").alias("home_rows"), F.sum("pairs").alias("pairs")).select(F.lit(method).alias("method"), "home_rows", "pairs")
        out = one if out is None else out.unionByName(one)
    return out


def _lsh(spark: SparkSession, d: str) -> DataFrame:
    p, m = E8.build(spark, d), E8.metric()
    return B.recall(B.lsh_pairs(p, 0.289), L.landmark_graph(p, 0.289, m))


def _experiment(name: str, **kw) -> Callable:
    """The published experiment ``name``; seconds differ from run to run."""

    def query(spark: SparkSession, d: str) -> DataFrame:
        from .plans import experiments

        return experiments.run(spark, d, name, **kw)

    return query


P2 = SETS["p2"].sql


def _components_sql(ps, at: int = 1) -> str:
    return f"WITH RECURSIVE p AS ({ps.sql}), e AS ({ps.edges_sql(ps.radii[at])}), s AS (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e), w AS (SELECT pid, pid AS root FROM p UNION SELECT s.dst, w.root FROM w JOIN s ON s.src = w.pid WHERE w.root < s.dst) SELECT pid, min(root) AS component FROM w GROUP BY pid"


MEASURES: dict[str, tuple[Callable, str | None]] = {
    "ball_e8": (lambda s, d: D.ball(p := E8.build(s, d), p.filter("pid = 0").first().vec, 0.5).select("pid", F.round("dist", ROUND).alias("dist")), f"WITH p AS ({E8.sql}) SELECT a.pid, round(list_distance(a.vec, b.vec), 6) AS dist FROM p a, p b WHERE b.pid = 0 AND list_distance(a.vec, b.vec) <= 0.5"),
    "voronoi_e4": (_voronoi, f"WITH p AS ({E4.sql}), {ASSIGN_SQL} SELECT pid, CAST(home AS INTEGER) AS cell, round(dmin, 6) AS dmin FROM h"),
    "cell_stats_e4": (_cell_stats, f"WITH p AS ({E4.sql}), {ASSIGN_SQL} SELECT CAST(home AS INTEGER) AS cell, count(*) AS size, round(max(dmin), 6) AS radius FROM h GROUP BY home"),
    "coverage_e4": (_coverage, f"WITH p AS ({E4.sql}), {ASSIGN_SQL} SELECT round(max(dmin), 6) AS radius FROM h"),
    "spread_e8": (lambda s, d: D.spread(E8.build(s, d)).select(*[F.round(c, ROUND).alias(c) for c in ("largest", "smallest_positive")]), f"WITH p AS ({E8.sql}) SELECT round(max(list_distance(a.vec, b.vec)), 6) AS largest, round(min(list_distance(a.vec, b.vec)), 6) AS smallest_positive FROM p a JOIN p b ON a.pid < b.pid"),
    "growth_constant_e2": (lambda s, d: D.growth_constant(E2.build(s, d), [0.05, 0.1], ids=IDS).select(F.round("constant", ROUND).alias("constant")), f"WITH p AS ({E2.sql}), x AS (SELECT a.pid, r.r, sum(CASE WHEN list_distance(a.vec, b.vec) <= r.r THEN 1 ELSE 0 END) AS near, sum(CASE WHEN list_distance(a.vec, b.vec) <= 2 * r.r THEN 1 ELSE 0 END) AS far FROM p a, p b, (SELECT unnest([0.05::DOUBLE, 0.1::DOUBLE]) AS r) r WHERE a.pid % 25 = 0 AND a.pid < 500 GROUP BY a.pid, r.r) SELECT round(max(far / near), 6) AS constant FROM x"),
    "intrinsic_dim_e8": (lambda s, d: D.intrinsic_dim(E8.build(s, d), ids=IDS).select("samples", F.round("dimension", 4).alias("dimension")), f"WITH p AS ({E8.sql}), {CENTRES_SQL}, d AS (SELECT c.cell, list_distance(p.vec, c.cv) AS d FROM p, c), r AS (SELECT cell, d, row_number() OVER (PARTITION BY cell ORDER BY d) AS k FROM d WHERE d > 0), x AS (SELECT cell, ln(max(d) / min(d)) AS r FROM r WHERE k <= 2 GROUP BY cell HAVING count(*) = 2) SELECT count(*) AS samples, round(count(*) / sum(r), 4) AS dimension FROM x"),
    "ghosts_bisector_e4": (_ghosts("bisector"), _ghosts_sql(True, False)),
    "ghosts_ball_e4": (_ghosts("ball"), _ghosts_sql(False, True)),
    "ghosts_both_e4": (_ghosts("both"), _ghosts_sql(True, True)),
    "degree_hist_e20": (lambda s, d: C.degree_histogram(e := L.landmark_graph(p := SETS["e20"].build(s, d), 0.59), p), _sym_sql(SETS["e20"]) + ", g AS (SELECT p.pid, count(s.src) AS degree FROM p LEFT JOIN s ON s.src = p.pid GROUP BY p.pid) SELECT degree, count(*) AS points FROM g GROUP BY degree"),
    **{f"graph_stats_sweep_{w}": _sweep(n) for w, n in {"w1": "e20", "w2": "e40", "w3": "e32", "w4": "e64", "w6": "uc", "w8": "h256", "w10": "url", "w12": "w1", "w13": "e2"}.items()},
    # copies of a payload are counted, not paired; the SQL pairs them
    "graph_stats_sweep_w14": (_sweep("p2", copies=True)[0], _sweep("p2")[1]),
    **{f"graph_stats_sweep_{w}": _sweep(n) for w, n in {"w6b": "ut", "w8b": "h64", "w11": "names", "w13b": "e4", "w13c": "e8", "w14b": "e64_angular", "w14c": "ca"}.items()},
    "graph_stats_sweep_w5": _sweep("lgf_all", copies=True),
    "graph_stats_sweep_w5b": _sweep("lg", copies=True, radii=(1.0, 1.5, 2.0, 3.0)),
    "graph_stats_sweep_w7": _sweep("e64", radii=(1.118, 1.194, 1.261)),
    "graph_stats_sweep_w9": _sweep("h800", copies=True, radii=(5, 10, 20, 40)),
    "graph_dups_lg": (_lg_degrees, LG_SQL),
    "compare_ring_landmark": (_compare, "SELECT CAST(0 AS BIGINT) AS missing, CAST(0 AS BIGINT) AS extra, CAST(0.0 AS DOUBLE) AS max_error"),
    "nestedness_e8": (_nested, "SELECT CAST(0 AS BIGINT) AS lost"),
    **{f"balance_{how}": ((lambda s, d, how=how: C.balance_stats(p := SETS["lgf_all"].build(s, d), L.centers(p, 32), 5, how)), None) for how in ("cyclic", "lpt")},
    "separation_e4": (_separation, f"WITH p AS ({E4.sql}), {ASSIGN_SQL}, s AS (SELECT min(list_distance(a.cv, b.cv)) AS separation FROM c a JOIN c b ON a.cell < b.cell) SELECT round(s.separation, 6) AS separation, (SELECT max(dmin) FROM h) <= s.separation AS net FROM s"),
    "work_e8": (_work, f"WITH n AS (SELECT count(*) AS home_rows FROM ({E8.sql})), e AS (SELECT count(*) AS pairs FROM ({E8.edges_sql(0.205)})) SELECT unnest(['landmark_collective', 'landmark_ring', 'ring']) AS method, home_rows, pairs FROM n, e"),
    "lsh_contrast_e8": (_lsh, None),
    "tree_levels_e4": (lambda s, d: D.build_tree_df(E4.build(s, d)).filter("is_leaf").agg(F.sum("size").alias("points")), f"SELECT count(*) AS points FROM ({E4.sql})"),
    "tree_strict_separation_e4": (lambda s, d: D.tree_check(E4.build(s, d), sibling_only=False, leaf_size=1, bailout=1.0), None),
    **{f"experiment_{n}": (_experiment(n, radii=(1,)), None) for n in ("phases", "work")},
    "experiment_one_process": (_experiment("one_process", radii=(1,), sets=("e64", "lgd")), None),
    "experiment_strong_scaling": (_experiment("strong_scaling", radii=(1,), sets=("lgd", "e64")), None),
    "experiment_speedups": (_experiment("speedups"), None),
    **{f"experiment_{n}": (_experiment(n), None) for n in ("ghost_saturation", "centre_selection", "assignment", "tree_costs")},
    "tree_invariants_e8": (lambda s, d: D.tree_check(E8.build(s, d), leaf_size=1, bailout=1.0), "SELECT unnest(['partition', 'nesting', 'covering', 'separating', 'shrinking']) AS invariant, CAST(0 AS BIGINT) AS violations"),
    "tree_stats_e4": (lambda s, d: D.tree_stats(E4.build(s, d), 0.141), None),
    "tree_rows_e4": (lambda s, d: D.tree_rows(E4.build(s, d)).drop("part", "members"), None),
    "check_metric_l2": (lambda s, d: B.check_metric(E8.build(s, d), "l2"), "SELECT unnest(['non_negative', 'identity', 'symmetry', 'triangle']) AS axiom, CAST(0 AS BIGINT) AS violations"),
    "check_metric_cosine": (lambda s, d: B.check_metric(E8.build(s, d), "cosine").filter("violations > 0").select("axiom"), "SELECT 'triangle' AS axiom"),
    "near_join_part": (_near_parts, "WITH p AS (SELECT p_partkey AS pid, p_brand, [CAST(p_size AS DOUBLE), p_retailprice] AS vec FROM part) SELECT a.pid AS src, b.pid AS dst, round(list_distance(a.vec, b.vec), 6) AS dist FROM p a JOIN p b ON a.p_brand LIKE 'Brand#1%' AND b.p_brand LIKE 'Brand#2%' WHERE list_distance(a.vec, b.vec) <= 5.005"),
    "plan_costs_e64": (lambda s, d: planner.explain_graph(SETS["e64"].build(s, d), 1.249, SETS["e64"].metric()), None),
}

CLUSTER_SQL = f"""WITH RECURSIVE p AS ({E4.sql}), e AS ({E4.edges_sql(0.141)}), s AS (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e),
k AS (SELECT src AS pid FROM s GROUP BY src HAVING count(*) + 1 >= 12), ks AS (SELECT src, dst FROM s WHERE src IN (SELECT pid FROM k) AND dst IN (SELECT pid FROM k)),
w AS (SELECT pid, pid AS root FROM k UNION SELECT ks.dst, w.root FROM w JOIN ks ON ks.src = w.pid WHERE w.root < ks.dst),
c AS (SELECT pid, min(root) AS cluster FROM w GROUP BY pid), b AS (SELECT s.src AS pid, min(c.cluster) AS cluster FROM s JOIN c ON c.pid = s.dst GROUP BY s.src)
SELECT p.pid, coalesce(c.cluster, b.cluster) AS cluster, CASE WHEN c.pid IS NOT NULL THEN 'core' WHEN b.pid IS NOT NULL THEN 'border' ELSE 'noise' END AS kind FROM p LEFT JOIN c ON c.pid = p.pid LEFT JOIN b ON b.pid = p.pid"""

#: Every known length is kept beside the longer paths of each round, until a round shortens nothing.
GEODESICS_SQL = _sym_sql(E4).replace("WITH p", "WITH RECURSIVE p", 1) + """, w AS (SELECT pid AS source, pid, 0.0::DOUBLE AS d, true AS running FROM p WHERE pid IN (0, 1)
UNION ALL SELECT source, pid, d, bool_or(shorter) OVER () FROM (SELECT source, pid, min(d) AS d, min(d) + 1e-12 < coalesce(min(CASE WHEN known THEN d END), 1e300) AS shorter
FROM (SELECT source, pid, d, true AS known FROM w WHERE running UNION ALL SELECT w.source, s.dst, w.d + s.dist, false FROM w JOIN s ON s.src = w.pid WHERE w.running) GROUP BY source, pid))
SELECT source, pid, round(d, 5) AS dist FROM w WHERE NOT running"""

FUZZY_SQL = _sym_sql(E8) + """, r AS (SELECT src, dst, dist, row_number() OVER (PARTITION BY src ORDER BY dist, dst) AS rank FROM s), k AS (SELECT src, dst, dist, min(dist) OVER (PARTITION BY src) AS near, max(dist) OVER (PARTITION BY src) AS far FROM r WHERE rank <= 5),
m AS (SELECT src, dst, exp((near - dist) / greatest(far - near, 1e-12)) AS m FROM k), t AS (SELECT coalesce(a.src, b.dst) AS src, coalesce(a.dst, b.src) AS dst, coalesce(a.m, 0) AS x, coalesce(b.m, 0) AS y FROM m a FULL JOIN m b ON a.src = b.dst AND a.dst = b.src)
SELECT src, dst, round(x + y - x * y, 6) AS weight FROM t WHERE src < dst"""

SPECTRAL_SQL = _sym_sql(E4) + ", k AS (SELECT src AS pid, count(*) AS k FROM s GROUP BY src), l AS MATERIALIZED (SELECT s.src, s.dst, 1 / sqrt(a.k * b.k) AS w FROM s JOIN k a ON a.pid = s.src JOIN k b ON b.pid = s.dst), v0 AS (SELECT pid, 1.0::DOUBLE AS value FROM p)"
for _k in range(1, 6):
    SPECTRAL_SQL += f", u{_k} AS MATERIALIZED (SELECT l.src AS pid, sum(l.w * v.value) AS value FROM l JOIN v{_k - 1} v ON v.pid = l.dst GROUP BY l.src), v{_k} AS MATERIALIZED (SELECT pid, value / (SELECT sqrt(sum(value * value)) FROM u{_k}) AS value FROM u{_k})"
SPECTRAL_SQL += " SELECT pid, round(value, 6) AS value FROM v5"

FLOW_SQL = _sym_sql(E2) + ", f AS (SELECT src, dst FROM s UNION ALL SELECT pid, pid FROM p), m0 AS MATERIALIZED (SELECT src, dst, 1.0::DOUBLE / count(*) OVER (PARTITION BY dst) AS v FROM f)"
for _k in range(1, 5):
    FLOW_SQL += (
        f", g{_k} AS (SELECT a.src, b.dst, pow(sum(a.v * b.v), 2) AS v FROM m{_k - 1} a JOIN m{_k - 1} b ON a.dst = b.src GROUP BY a.src, b.dst), h{_k} AS (SELECT * FROM g{_k} QUALIFY row_number() OVER (PARTITION BY dst ORDER BY round(v, 12) DESC, src) <= 50)"
        f", n{_k} AS (SELECT src, dst, v / sum(v) OVER (PARTITION BY dst) AS v FROM h{_k}), m{_k} AS MATERIALIZED (SELECT * FROM n{_k} WHERE v >= 1e-4)"
    )
FLOW_SQL += " SELECT dst AS pid, arg_min(src, {'v': -round(v, 6), 'src': src}) AS cluster FROM m4 GROUP BY dst"

DOWNSTREAM: dict[str, tuple[Callable, str | None]] = {
    "components_e4": (_q(E4, lambda p, e: N.components(e, p), 0), _components_sql(E4, 0)),
    "dbscan_e4": (_q(E4, _dbscan), CLUSTER_SQL),
    "density_e8": (_q(E8, lambda p, e: N.density(e, p, 0.289, "tri").select("pid", F.round("density", 5).alias("density"))), _sym_sql(E8) + " SELECT p.pid, round(1 + coalesce(sum(1 - s.dist / 0.289), 0), 5) AS density FROM p LEFT JOIN s ON s.src = p.pid GROUP BY p.pid"),
    "triangles_e8": (_q(E8, lambda p, e: N.triangles(e)), _sym_sql(E8) + " , w AS MATERIALIZED (SELECT x.src AS a, x.dst AS b, y.dst AS c FROM e x JOIN e y ON y.src = x.dst) SELECT w.a, w.b, w.c FROM w SEMI JOIN e z ON z.src = w.a AND z.dst = w.c"),
    "rips_e8": (_q(E8, lambda p, e: N.rips(e, p)), _sym_sql(E8) + ", t AS (SELECT x.src FROM e x JOIN e y ON y.src = x.dst JOIN e z ON z.src = x.src AND z.dst = y.dst) SELECT a.vertices, b.edges, c.triangles, a.vertices - b.edges + c.triangles AS euler FROM (SELECT count(*) AS vertices FROM p) a, (SELECT count(*) AS edges FROM e) b, (SELECT count(*) AS triangles FROM t) c"),
    "clustering_e8": (_p(E8, lambda p, eps, m: I.local_clustering(p, eps, m).select("pid", "triangles", F.round("clustering", ROUND).alias("clustering"))), _sym_sql(E8) + ", k AS (SELECT src AS pid, count(*) AS k FROM s GROUP BY src), t AS (SELECT x.src AS pid, count(*) / 2 AS t FROM s x JOIN s y ON y.src = x.src AND y.dst <> x.dst JOIN s z ON z.src = x.dst AND z.dst = y.dst GROUP BY x.src) SELECT p.pid, CAST(coalesce(t.t, 0) AS BIGINT) AS triangles, round(CASE WHEN k.k > 1 THEN 2.0 * coalesce(t.t, 0) / (k.k * (k.k - 1)) ELSE 0.0 END, 6) AS clustering FROM p LEFT JOIN k ON k.pid = p.pid LEFT JOIN t ON t.pid = p.pid"),
    "geodesics_e4": (_p(E4, lambda p, eps, m: I.geodesics(p, eps, [0, 1], m).select("source", "pid", F.round("dist", 5).alias("dist"))), GEODESICS_SQL),
    "knn_in_eps_e8": (_q(E8, _knn), _sym_sql(E8) + ", r AS (SELECT src, dst, dist, row_number() OVER (PARTITION BY src ORDER BY dist, dst) AS rank FROM s) SELECT src, CAST(rank AS INTEGER) AS rank, dst, round(dist, 6) AS dist FROM r WHERE rank <= 5"),
    "mutual_knn_e8": (_q(E8, lambda p, e: _edges(N.mutual_knn(e, 5))), _sym_sql(E8) + ", r AS (SELECT src, dst, dist, row_number() OVER (PARTITION BY src ORDER BY dist, dst) AS rank FROM s), k AS (SELECT * FROM r WHERE rank <= 5) SELECT a.src, a.dst, round(a.dist, 6) AS dist FROM k a JOIN k b ON a.src = b.dst AND a.dst = b.src WHERE a.src < a.dst"),
    "fuzzy_weights_e8": (_q(E8, lambda p, e: N.fuzzy_weights(e, 5).select("src", "dst", F.round("weight", ROUND).alias("weight"))), FUZZY_SQL),
    "adjacency_e4": (_q(E4, lambda p, e: N.adjacency(e).select("pid", F.array_join(F.transform("neighbours", lambda x: x["dst"]), ",").alias("neighbours"))), _sym_sql(E4) + " SELECT src AS pid, string_agg(CAST(dst AS VARCHAR), ',' ORDER BY dst) AS neighbours FROM s GROUP BY src"),
    "laplacian_e4": (_q(E4, lambda p, e: N.laplacian(e, p).select("src", "dst", F.round("value", ROUND).alias("value"))), _sym_sql(E4) + ", k AS (SELECT src AS pid, count(*) AS k FROM s GROUP BY src) SELECT s.src, s.dst, round(1 / sqrt(a.k * b.k), 6) AS value FROM s JOIN k a ON a.pid = s.src JOIN k b ON b.pid = s.dst"),
    "spectral_e4": (_p(E4, lambda p, eps, m: I.spectral(p, eps, m, 5).select("pid", F.round("value", ROUND).alias("value"))), SPECTRAL_SQL),
    "mcl_e2": (_p(E2, lambda p, eps, m: I.flow_clusters(p, eps, m, steps=4)), FLOW_SQL),
    "mcl_step_names": (_q(SETS["names"], lambda p, e: N.mcl_step(N.flow_matrix(e, p)).select("src", "dst", F.round("value", ROUND).alias("value"))), _sym_sql(SETS["names"]) + ", f AS (SELECT src, dst FROM s UNION ALL SELECT pid, pid FROM p), m AS (SELECT f.src, f.dst, 1.0::DOUBLE / n.n AS v FROM f JOIN (SELECT dst, count(*) AS n FROM f GROUP BY dst) n ON n.dst = f.dst), q AS (SELECT a.src, b.dst, pow(sum(a.v * b.v), 2) AS v FROM m a JOIN m b ON a.dst = b.src GROUP BY a.src, b.dst) SELECT q.src, q.dst, round(q.v / t.t, 6) AS value FROM q JOIN (SELECT dst, sum(v) AS t FROM q GROUP BY dst) t ON t.dst = q.dst"),
    "label_vote_embeddings": (lambda s, d: N.label_vote(_e(E8, s, d)[1], s.read.parquet(f"{d}/embeddings.parquet").select(F.col("vec_id").alias("pid"), "label")), _sym_sql(E8) + ", v AS (SELECT s.src, l.label, count(*) AS n FROM s JOIN embeddings l ON l.vec_id = s.dst GROUP BY s.src, l.label), r AS (SELECT src, label, row_number() OVER (PARTITION BY src ORDER BY n DESC, label) AS k FROM v) SELECT o.vec_id AS pid, o.label, r.label AS vote, o.label = r.label AS agree FROM r JOIN embeddings o ON o.vec_id = r.src WHERE r.k = 1"),
    "near_dups_documents": (_dups, _components_sql(SETS["jaccard"])),
    "representatives_e4": (_q(E4, lambda p, e: N.keep_representatives(e, p), 0), f"SELECT pid FROM ({_components_sql(E4, 0)}) WHERE pid = component"),
}

ALL = {**GRAPHS, **MEASURES, **DOWNSTREAM, **RELATIONAL, **streams.QUERIES}


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Degree statistics of the landmark graph on four-dimensional points."""
    p = E4.build(spark, sf_dir)
    return C.graph_stats(L.landmark_graph(p, 0.141, "l2", 16), p)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {name: q for name, (q, _) in ALL.items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for name, (_, sql) in ALL.items() if sql}
