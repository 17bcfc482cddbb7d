"""The published experiments on the given tables: ``python -m epsgraph.plans.experiments NAME [SF_DIR]``.

Each returns rows (run_stats): method, dataset, eps, blocks, m, phase, seconds, value. Seconds are wall clock to a noop sink, but for the
phases inside kernels, which are sums over tasks. ``radii`` chooses among a set's three radii: all by default and in the registered
``speedups``, the middle one in the other registered queries, two of which also run fewer ``sets``.
"""

from __future__ import annotations

import sys
import time
from collections.abc import Callable, Iterator

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.metrics import Metric
from ..operators import baselines, definitions, landmark, measures, ring
from ..workloads import SETS

SCHEMA = "method string, dataset string, eps double, blocks int, m int, phase string, seconds double, value double"
TABLE_SETS = ("e20", "e32", "e40", "e64", "lgd", "uc")
ALL_RADII = (0, 1, 2)


def seconds(df: DataFrame) -> float:
    begin = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return round(time.perf_counter() - begin, 3)


def _points(spark: SparkSession, d: str, name: str) -> DataFrame:
    p = SETS[name].build(spark, d).persist(StorageLevel.MEMORY_AND_DISK)
    p.count()
    return p


def one_process(spark: SparkSession, d: str, radii: tuple[int, ...] = ALL_RADII, sets: tuple[str, ...] = TABLE_SETS) -> Iterator[tuple]:
    """Sequential sorted search against landmarks with 10 and 60 cells in one task."""
    for name in sets:
        p, m = _points(spark, d, name), SETS[name].metric()
        for eps in (SETS[name].radii[r] for r in radii):
            yield "pca_sort", name, eps, 1, 0, "all", seconds(baselines.pca_sort_graph(p, eps, how="local")), None
            for k in (10, 60):
                yield "landmark_collective", name, eps, 1, k, "all", seconds(landmark.landmark_graph(p, eps, m, k, tasks=1)), None


def _methods(p: DataFrame, eps: float, m: Metric, n: int, **kw) -> dict[str, Callable[[], DataFrame]]:
    """The three distributed methods on ``n`` tasks."""
    return {
        "landmark_collective": lambda: landmark.landmark_graph(p, eps, m, max(n, 4), tasks=n, **kw),
        "landmark_ring": lambda: landmark.landmark_graph(p, eps, m, max(n, 4), tasks=n, ghost="ring", rounds=min(n, 4), **kw),
        "ring": lambda: ring.ring_graph(p, eps, m, n, **kw),
    }


def _warm(methods: dict[str, Callable[[], DataFrame]]) -> None:
    """Runs whose time is not taken, so that the first one that counts starts no workers."""
    for build in methods.values():
        seconds(build())


def speedups(spark: SparkSession, d: str, radii: tuple[int, ...] = ALL_RADII, sets: tuple[str, ...] = ("e64", "lgd", "uc")) -> Iterator[tuple]:
    """Three methods at several block counts; value is the speed-up over the sequential baseline."""
    for name in sets:
        p, m = _points(spark, d, name), SETS[name].metric()
        for eps in (SETS[name].radii[r] for r in radii):
            _warm({"pca_sort": lambda: baselines.pca_sort_graph(p, eps, how="local"), **_methods(p, eps, m, 4)})  # noqa: B023
            base = seconds(baselines.pca_sort_graph(p, eps, how="local"))
            for n in (1, 4, 32):
                for method, build in _methods(p, eps, m, n).items():
                    s = seconds(build())
                    yield method, name, eps, n, max(n, 4), "all", s, round(base / s, 3)


def strong_scaling(spark: SparkSession, d: str, radii: tuple[int, ...] = ALL_RADII, sets: tuple[str, ...] = ("e64", "lgd", "uc", "h256")) -> Iterator[tuple]:
    """The same graphs on 1 to 8 tasks; value is the efficiency, of the seconds on one task over those on n, a task. Tasks stand
    for workers: more than the session has cores gain nothing."""
    for name in sets:
        p, m = _points(spark, d, name), SETS[name].metric()
        for eps in (SETS[name].radii[r] for r in radii):
            one: dict[str, float] = {}
            _warm(_methods(p, eps, m, 8))
            for n in (1, 2, 4, 8):
                for method, build in _methods(p, eps, m, n).items():
                    s = seconds(build())
                    yield method, name, eps, n, max(n, 4), "all", s, round(one.setdefault(method, s) / s / n, 3)


def phases(spark: SparkSession, d: str, radii: tuple[int, ...] = (1,)) -> Iterator[tuple]:
    """What the kernels tell of their phases: assignment and radii (value: rows), trees, pairs within, pairs by rows that come (value:
    distances), waiting for rows (value: rows through the exchange), and the largest over the mean part's seconds."""
    for name in ("lgd", "uc", "e64"):
        p, m = _points(spark, d, name), SETS[name].metric()
        for eps in (SETS[name].radii[r] for r in radii):
            begin = time.perf_counter()
            n = landmark.assign(p, landmark.centers(p, 16), m, eps).count()
            yield "landmark", name, eps, 8, 16, "partition", round(time.perf_counter() - begin, 3), float(n)
            runs = {
                "landmark_collective": lambda: landmark.landmark_graph(p, eps, m, 16, tasks=8, report=True),  # noqa: B023
                "landmark_ring": lambda: landmark.landmark_graph(p, eps, m, 16, tasks=8, ghost="ring", report=True),  # noqa: B023
                "ring": lambda: ring.ring_graph(p, eps, m, 8, report=True),  # noqa: B023
            }
            for method, build in runs.items():
                r = measures.work_stats(build()).first()
                k = 0 if method == "ring" else 16
                for phase in ("build", "home", "guest"):
                    yield method, name, eps, 8, k, phase, round(r[f"{phase}_seconds"], 3), float(r[f"{phase}_distances"])
                yield method, name, eps, 8, k, "wait", round(r.wait_seconds, 3), float(r.rows_moved)
                yield method, name, eps, 8, k, "largest_over_mean", None, round(r.largest_over_mean, 3)


def work(spark: SparkSession, d: str, radii: tuple[int, ...] = (1,)) -> Iterator[tuple]:
    """Counts alone, the same on any machine: rounds, rows through the exchange, most rows held at home, distances, pairs."""
    for name in ("e8", "e64", "lgd", "uc"):
        p, m = _points(spark, d, name), SETS[name].metric()
        n = p.count()
        for eps in (SETS[name].radii[r] for r in radii):
            for method, build in _methods(p, eps, m, 8, report="counts").items():
                r = measures.work_stats(build()).first()
                at = (method, name, eps, 8, 0 if method == "ring" else 8)
                rounds = {"ring": 5, "landmark_ring": 4}.get(method, 1)
                distances = r.build_distances + r.home_distances + r.guest_distances
                for what, v in (("rounds", rounds), ("rows_moved", r.rows_moved), ("most_home_rows", r.most_home_rows), ("pairs", r.pairs), ("distances", distances), ("part_of_all_pairs", round(distances / (n * (n - 1) / 2), 6))):
                    yield *at, what, None, float(v)


def ghost_saturation(spark: SparkSession, d: str) -> Iterator[tuple]:
    """Ghosts a point by dimension and number of centres."""
    for name, eps in (("ca", 5.005), ("o2_all", 5.003), ("p2", 2.005), ("lg", 2.0), ("e2", 0.05), ("e4", 0.141), ("e8", 0.289), ("e64", 1.249)):
        p, m = _points(spark, d, name), SETS[name].metric()
        for k in (16, 64):
            for bound in ("bisector", "both"):
                g = measures.ghost_stats(p, landmark.centers(p, k), eps, m, bound).agg(F.coalesce(F.sum("ghosts"), F.lit(0))).first()[0]
                yield f"ghosts_{bound}", name, eps, 0, k, "count", None, g / max(p.count(), 1)


def centre_selection(spark: SparkSession, d: str) -> Iterator[tuple]:
    """Largest over mean cell, by random and greedy centres."""
    for name in ("h800", "lgd"):
        p, m = _points(spark, d, name), SETS[name].metric()
        for how in ("random", "greedy"):
            r = measures.balance_stats(p, landmark.centers(p, 16, how, metric=m), 4, "lpt", m).first()
            yield how, name, None, 4, 16, "largest_over_mean_cell", None, r.largest_cell / r.mean_cell


def assignment(spark: SparkSession, d: str) -> Iterator[tuple]:
    """Largest load and spread of loads, cyclic and longest first."""
    for name in ("h800", "lgd"):
        p, m = _points(spark, d, name), SETS[name].metric()
        for how in ("cyclic", "lpt"):
            r = measures.balance_stats(p, landmark.centers(p, 32), 5, how, m).first()
            yield how, name, None, 5, 32, "largest_load", None, r.largest_load
            yield how, name, None, 5, 32, "max_min", None, r.max_min


def tree_costs(spark: SparkSession, d: str) -> Iterator[tuple]:
    """Distance evaluations of one tree's build and self query, as parts of all ordered pairs. A tree is one task; they are built side by side."""
    options = {"leaf1": dict(leaf_size=1), "leaf1_level": dict(leaf_size=1, threshold="level"), "leaf32": dict(leaf_size=32)}
    stats, asked = None, []
    for name in ("p2", "e64", "e8", "e4", "e2"):  # the longest first
        p, m = _points(spark, d, name), SETS[name].metric()
        for label, kw in options.items():
            one = definitions.tree_stats(p, SETS[name].radii[1], m, **kw).withColumn("run", F.lit(len(asked)))
            stats = one if stats is None else stats.unionByName(one)
            asked.append((label, name))
    found = {asked[r.run]: r for r in stats.collect()}
    for name in ("e2", "e4", "e8", "e64", "p2"):
        for label in options:
            r = found[label, name]
            for what in ("build", "query", "self_query"):
                yield label, name, SETS[name].radii[1], 0, 0, what, None, r[f"{what}_distances"] / r.brute_distances


EXPERIMENTS = {f.__name__: f for f in (one_process, speedups, strong_scaling, phases, work, ghost_saturation, centre_selection, assignment, tree_costs)}


def run(spark: SparkSession, d: str, name: str, **kw) -> DataFrame:
    rows = [(a, b, None if e is None else float(e), n, m, ph, s, None if v is None else float(v)) for a, b, e, n, m, ph, s, v in EXPERIMENTS[name](spark, d, **kw)]
    spark.catalog.clearCache()
    return spark.createDataFrame(rows, SCHEMA)


if __name__ == "__main__":
    session = SparkSession.builder.config("spark.sql.shuffle.partitions", "8").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    session.sparkContext.setLogLevel("ERROR")
    run(session, sys.argv[2] if len(sys.argv) > 2 else "/root/testdata/sf0.01", sys.argv[1]).show(500, truncate=False)
