"""Measures of graphs, cells and assignments."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.metrics import Metric, resolve
from .landmark import assign, assign_cells, cell_stats, ghosts, with_candidates
from .points import symmetric


def degrees(edges: DataFrame, p: DataFrame) -> DataFrame:
    """(pid, degree) of every point."""
    d = symmetric(edges).groupBy("src").agg(F.count("*").alias("degree"))
    return p.select("pid").join(d, F.col("pid") == F.col("src"), "left").select("pid", F.coalesce("degree", F.lit(0)).alias("degree"))


def degree_histogram(edges: DataFrame, p: DataFrame) -> DataFrame:
    return degrees(edges, p).groupBy("degree").agg(F.count("*").alias("points"))


def graph_stats(edges: DataFrame, p: DataFrame) -> DataFrame:
    """n, pairs, directed, avg_degree, max_degree, isolated."""
    return degree_stats(degrees(edges, p))


def degree_stats(d: DataFrame) -> DataFrame:
    """``graph_stats`` from (pid, degree) of every point."""
    return d.agg(
        F.count("*").alias("n"), (F.sum("degree") / 2).cast("long").alias("pairs"), F.sum("degree").alias("directed"), F.round(F.sum("degree") / F.count("*"), 6).alias("avg_degree"),
        F.max("degree").alias("max_degree"), F.count_if(F.col("degree") == 0).alias("isolated"),
    )


def compare_graphs(a: DataFrame, b: DataFrame) -> DataFrame:
    """(missing, extra, max_error): pairs of b that a lacks, of a that b lacks, and the largest difference of distances."""
    both = a.withColumnRenamed("dist", "x").join(b.withColumnRenamed("dist", "y"), ["src", "dst"], "full")
    return both.agg(F.count_if(F.col("x").isNull()).alias("missing"), F.count_if(F.col("y").isNull()).alias("extra"), F.coalesce(F.max(F.round(F.abs(F.col("x") - F.col("y")), 9)), F.lit(0.0)).alias("max_error"))


def ghost_stats(p: DataFrame, cs: list[tuple[int, object]], eps: float, metric: str | Metric = "l2", bound: str = "both", half: bool = False) -> DataFrame:
    """(cell, home, ghosts): how many points of each home cell are ghosts of each cell."""
    assigned, cells = with_candidates(p, cs, resolve(metric), eps, bound)
    radii = {c: r.radius for c, r in cells.items()}
    return ghosts(assigned, eps, radii, bound, half).groupBy("cell", "home").agg(F.count("*").alias("ghosts"))


def balance_stats(p: DataFrame, cs: list[tuple[int, object]], tasks: int, how: str, metric: str | Metric = "l2") -> DataFrame:
    """(how, cells, tasks, largest_cell, mean_cell, largest_load, max_min): cell sizes and the loads of an assignment."""
    sizes = {r.cell: r.size for r in cell_stats(assign(p, cs, resolve(metric))).collect()}
    loads = [float(sizes.get(c, 0)) for c in range(len(cs))]
    by_task = [0.0] * tasks
    for load, t in zip(loads, assign_cells(loads, tasks, how)):
        by_task[t] += load
    row = (how, len(loads), tasks, max(loads), sum(loads) / len(loads), max(by_task), max(by_task) - min(by_task))
    return p.sparkSession.createDataFrame([row], "how string, cells int, tasks int, largest_cell double, mean_cell double, largest_load double, max_min double")


def work_stats(work: DataFrame) -> DataFrame:
    """One row of a graph's report (``landmark.WORK``): rows moved through the exchange and how many of them are guests, the most
    rows that a part holds at home, pairs, distances of each phase, their seconds, the seconds that kernels wait for rows, and the
    largest over the mean part by seconds at work."""
    busy = F.col("build_seconds") + F.col("home_seconds") + F.col("guest_seconds")
    total = lambda c: F.coalesce(F.sum(c), F.lit(0))
    return work.agg(
        F.countDistinct("part").alias("parts"), total(F.col("home_rows") + F.col("guest_rows")).alias("rows_moved"), total("guest_rows").alias("guest_rows"), F.max("home_rows").alias("most_home_rows"),
        total("pairs").alias("pairs"), *[total(f"{c}_distances").alias(f"{c}_distances") for c in ("build", "home", "guest")],
        *[total(f"{c}_seconds").alias(f"{c}_seconds") for c in ("build", "home", "guest", "wait")], (F.max(busy) / F.avg(busy)).alias("largest_over_mean"),
    )
