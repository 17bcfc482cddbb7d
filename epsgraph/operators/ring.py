"""Graphs over blocks of points: the halved ring, the full ring, the triangular grid, and brute force.

On the ring, block j's structure is built once, and the blocks at the job's offsets come to it one after another, in batches:
a task holds its own block, its structure and one batch. Offsets stop half way round, and an even ring's last offset is done
by the lower half only. Blocks are as many as keep each to ``MOST_ROWS`` points, if their number is not given.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.metrics import Metric, native_l2, resolve
from .components import checkpoint_dir
from .landmark import WORK, cell_kernel
from .points import EDGE, block_of

MOST_ROWS, LEAST_BLOCKS = 50_000, 8
#: Dimensions up to which a join's distance is written out.
MOST_UNROLLED = 32
#: Tasks among which the pairs of blocks of a grid are dealt.
MOST_TASKS = 2048
#: Hash ranges within which ``blocks(exact=True)`` numbers points, a task each.
RANGES = 4096


def block_count(p: DataFrame, n: int | None) -> int:
    return n or max(LEAST_BLOCKS, -(-p.count() // MOST_ROWS))


def blocks(p: DataFrame, n: int, seed: int = 0, exact: bool = False) -> DataFrame:
    """``p`` with ``block``. ``exact`` deals round-robin in hash order, so that sizes differ by one at most: points are numbered
    within ranges of the hash, and the ranges' sizes (a bounded table) give the numbers before them."""
    if not exact:
        return p.withColumn("block", block_of(n, seed))
    h = F.xxhash64("pid", F.lit(seed))
    dealt = p.withColumn("_h", h).withColumn("_range", F.shiftrightunsigned("_h", 64 - (RANGES - 1).bit_length()).cast("int"))
    before = dealt.groupBy("_range").agg(F.count("*").alias("_n")).agg(F.array_sort(F.collect_list(F.struct("_range", "_n"))).alias("a"))
    before = before.select(F.explode(F.transform("a", lambda s: F.struct(s["_range"].alias("_range"), F.aggregate(F.filter("a", lambda t: t["_range"] < s["_range"]), F.lit(0).cast("long"), lambda x, t: x + t["_n"]).alias("_before")))).alias("s")).select("s.*")
    order = Window.partitionBy("_range").orderBy("_h", "pid")
    numbered = dealt.withColumn("_at", F.row_number().over(order)).join(F.broadcast(before), "_range")
    return numbered.withColumn("block", F.pmod(F.col("_at") + F.col("_before"), F.lit(n)).cast("int")).select(*p.columns, "block")


def ring_graph(p: DataFrame, eps: float, metric: str | Metric = "l2", n: int | None = None, halve: bool = True, rounds_per_job: int | None = None, index: str = "cover", seed: int = 0, exact: bool = False, report: bool | str = False, **options) -> DataFrame:
    """Edges by passing blocks around a ring of ``n``; each job does ``rounds_per_job`` offsets (all by default: visiting blocks
    stream past, so more offsets in a job need no more memory, and structures are built once a job). ``report`` gives ``WORK``, a
    row a block and job, instead."""
    m, n = resolve(metric), block_count(p, n)
    dealt = blocks(p, n, seed, exact).select("pid", "vec", F.col("block").alias("home"))
    offsets = list(range(n // 2 + 1 if halve else n))
    step = rounds_per_job or len(offsets)
    out = None
    for at in range(0, len(offsets), step):
        now = [o for o in offsets[at : at + step] if o]
        stay = dealt.select("pid", "vec", "home", F.col("home").alias("part"), F.lit(0).alias("role"))
        rows = stay
        if now:
            come = dealt.withColumn("role", F.explode(F.array(*map(F.lit, now))))
            come = come.withColumn("part", F.pmod(F.col("home") - F.col("role"), F.lit(n)).cast("int"))
            if halve and n % 2 == 0 and n // 2 in now:
                come = come.filter((F.col("role") < n // 2) | (F.col("part") < n // 2))
            rows = stay.unionByName(come.select(*stay.columns))
        rows = rows.select("pid", "vec", "home", F.col("part").alias("cell"), "role", "part", F.lit(True).alias("whole"))
        # on a full ring each pair of blocks meets twice, and the one with the visitor of the larger number counts
        part = rows.repartitionById(n, "part").sortWithinPartitions("part", "role", "pid").mapInArrow(cell_kernel(m, eps, index, options, halve, intra=at == 0, report=report), WORK if report else EDGE)
        if step < len(offsets):
            checkpoint_dir(p.sparkSession)
            part = part.checkpoint()
        out = part if out is None else out.unionByName(part)
    return out


def grid_graph(p: DataFrame, eps: float, metric: str | Metric = "l2", n: int | None = None, index: str = "cover", seed: int = 0, **options) -> DataFrame:
    """The ring's schedule in one job: every pair of ``n`` blocks is a task, each point being in n tasks."""
    m, n = resolve(metric), block_count(p, n)
    met = blocks(p, n, seed).withColumn("with", F.explode(F.sequence(F.lit(0), F.lit(n - 1))))
    i, j = F.least("block", "with"), F.greatest("block", "with")
    # the lower block is at home, the other streams past it
    rows = met.select("pid", "vec", F.col("block").alias("home"), i.alias("cell"), (F.col("with") < F.col("block")).cast("int").alias("role"), (i * n + j).alias("part"), (i == j).alias("whole"))
    place = (F.floor(F.col("cell") * (2 * n - F.col("cell") - 1) / 2) + F.col("part") % n).cast("int")
    tasks = min(n * (n + 1) // 2, MOST_TASKS)
    dealt = rows.withColumn("task", F.pmod(place, F.lit(tasks))).repartitionById(tasks, "task").sortWithinPartitions("part", "role", "pid")
    return dealt.mapInArrow(cell_kernel(m, eps, index, options, True), EDGE)


def brute_graph(p: DataFrame, eps: float, metric: str | Metric = "l2", how: str = "grid", n: int | None = None) -> DataFrame:
    """All pairs: in a grid of blocks, or (``how="join"``) as a non-equi self join on the native distance."""
    m = resolve(metric)
    if how == "grid":
        return grid_graph(p, eps, m, n, index="scan")
    if m.native is None:
        raise ValueError(f"{m.name} has no native expression")
    # the pairs of blocks are keys, so that they are dealt out; the distance of few dimensions is generated code
    n = max(block_count(p, n), 16)
    first = p.select(F.size("vec").alias("d")).first() if m.name == "l2" else None
    dim = first.d if first and first.d <= MOST_UNROLLED else 0
    dealt = blocks(p, n).select("pid", *([F.col("vec")[k].cast("double").alias(f"x{k}") for k in range(dim)] if dim else ["vec"]), "block")
    a = dealt.withColumn("with", F.explode(F.sequence("block", F.lit(n - 1)))).alias("a")
    b = dealt.withColumn("with", F.explode(F.sequence(F.lit(0), F.col("block")))).alias("b")
    dist = native_l2([F.col(f"a.x{k}") for k in range(dim)], [F.col(f"b.x{k}") for k in range(dim)], dim) if dim else m.native(F.col("a.vec"), F.col("b.vec"))
    once = (F.col("a.block") < F.col("b.block")) | (F.col("a.pid") < F.col("b.pid"))
    near = a.join(b, (F.col("a.block") == F.col("b.with")) & (F.col("a.with") == F.col("b.block")) & once & (dist <= eps))
    return near.select(F.least("a.pid", "b.pid").alias("src"), F.greatest("a.pid", "b.pid").alias("dst"), dist.alias("dist"))


def kdtree_graph(p: DataFrame, eps: float, n: int | None = None, **options) -> DataFrame:
    return grid_graph(p, eps, "l2", n, index="kd", **options)


def balltree_graph(p: DataFrame, eps: float, metric: str | Metric = "l2", n: int | None = None, **options) -> DataFrame:
    return grid_graph(p, eps, metric, n, index="ball", **options)


def vptree_graph(p: DataFrame, eps: float, metric: str | Metric = "l2", n: int | None = None, **options) -> DataFrame:
    return grid_graph(p, eps, metric, n, index="vp", **options)
