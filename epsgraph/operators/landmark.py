"""The landmark method: Voronoi cells around a few centres, cells dealt to tasks, and ghosts for pairs across cells.

A point is a ghost of a cell if a pair across could exist: its distance to the cell's centre is at most that to its own
plus 2 eps (bisector), and at most the cell's radius plus eps (ball). Shipping it only to cells of smaller id than its home
finds each cross pair once. The centres are the only broadcast; their number is a parameter.
"""

from __future__ import annotations

import heapq
from collections import Counter
from collections.abc import Iterable, Iterator
from dataclasses import replace
from time import perf_counter

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.metrics import Metric, resolve, slack
from ..functions.trees import INDEXES, Pace
from .points import EDGE, edge_batches

MOST_CENTRE_BYTES = 512 << 20


def centers(p: DataFrame, m: int, how: str = "random", seed: int = 0, metric: str | Metric = "l2", ids: list[int] | None = None) -> list[tuple[int, object]]:
    """(pid, vec) of the centres: the ``m`` of smallest hash, a greedy farthest-first prefix, or given ids."""
    if how == "ids":
        return [tuple(r) for r in p.filter(F.col("pid").isin(*ids)).orderBy("pid").select("pid", "vec").collect()]
    if how == "random":
        return [tuple(r) for r in p.orderBy(F.xxhash64("pid", F.lit(seed)), "pid").limit(m).select("pid", "vec").collect()]
    met = resolve(metric)
    near = p.select("pid", "vec").persist(StorageLevel.DISK_ONLY)
    chosen = [tuple(near.orderBy(F.xxhash64("pid", F.lit(seed)), "pid").first())]

    def farthest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = decoded_centres([v for _, v in chosen], met, kind)
        for b in batches:
            if b.num_rows:
                d = met.table(met.decode(b.column(1)), c).min(1)
                k = int(d.argmax())
                yield pa.RecordBatch.from_arrays([b.column(0)[k : k + 1], b.column(1)[k : k + 1], pa.array(d[k : k + 1])], ["pid", "vec", "d"])

    schema = T.StructType([*near.schema.fields, T.StructField("d", T.DoubleType())])
    kind = near.schema["vec"].dataType
    while len(chosen) < m:
        best = near.mapInArrow(farthest, schema).orderBy(F.desc("d"), "pid").first()
        if best is None or best.d == 0:
            break
        chosen.append((best.pid, best.vec))
    near.unpersist()
    return chosen


def decoded_centres(vecs: list, m: Metric, kind: T.DataType) -> np.ndarray:
    from pyspark.sql.pandas.types import to_arrow_type

    return m.decode(pa.array(vecs, to_arrow_type(kind)))


class CentreGroups:
    """Centres in groups around a farthest-first few of them, so that a point meets only the groups that the triangle inequality
    leaves open: about the square root of their number where cells are well apart, instead of all."""

    def __init__(self, c: np.ndarray, m: Metric, fewest: int = 64):
        self.c, self.m, n = c, m, len(c)
        k = n if n <= fewest or not m.is_metric else int(np.ceil(np.sqrt(n)))
        near, of, heads = np.full(n, np.inf), np.zeros(n, int), []
        at = 0
        while len(heads) < k and (k == n or near[at] > 0):
            heads.append(at)
            if k < n:
                d = m.row(c, c[at])
                closer = d < near
                near[closer], of[closer] = d[closer], len(heads) - 1
                at = int(near.argmax())
            else:
                at += 1
        self.heads = np.array(heads)
        self.members = [np.flatnonzero(of == g) for g in range(len(heads))] if k < n else [np.array([i]) for i in range(n)]
        self.radius = np.array([near[g].max() for g in self.members]) if k < n else np.zeros(n)

    def search(self, x: np.ndarray, within) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Each point's nearest centre (the first of equals) and its distance, and (row, centre, distance) of the other centres
        at most ``within(dmin)`` away, a number a row or a row and centre; none where ``within`` is None."""
        head = self.m.table(x, self.c[self.heads])
        rows = np.arange(len(x))
        g = head.argmin(1)
        dmin, home = head[rows, g], self.heads[g]
        known = {}
        if len(self.heads) < len(self.c):
            for g, (r, who) in enumerate(zip(self.radius, self.members)):
                at = np.flatnonzero(head[:, g] - slack(r) <= slack(dmin))
                if len(at):
                    known[g] = at, self.m.table(x[at], self.c[who])
                    best = known[g][1].argmin(1)
                    d = known[g][1][np.arange(len(at)), best]
                    better = (d < dmin[at]) | (d == dmin[at]) & (who[best] < home[at])
                    dmin[at[better]], home[at[better]] = d[better], who[best[better]]
        if within is None:
            return home, dmin, *(np.empty(0, t) for t in (int, int, float))
        bound, found = np.broadcast_to(within(dmin), (len(x), len(self.c))), []
        if len(self.heads) == len(self.c):
            near = head <= bound
            near[rows, home] = False
            row, cell = np.nonzero(near)
            return home, dmin, row, cell, head[row, cell]
        for g, (r, who) in enumerate(zip(self.radius, self.members)):
            at = np.flatnonzero(head[:, g] - slack(r) <= slack(bound[:, who].max(1)))
            if len(at):
                d = known[g][1] if g in known and np.array_equal(known[g][0], at) else self.m.table(x[at], self.c[who])
                i, j = np.nonzero((d <= bound[at][:, who]) & (who[None, :] != home[at][:, None]))
                found.append((at[i], who[j], d[i, j]))
        row, cell, d = (np.concatenate(v) for v in zip(*found)) if found else (np.empty(0, t) for t in (int, int, float))
        order = np.lexsort((cell, row))
        return home, dmin, row[order], cell[order], d[order]


def assign(p: DataFrame, cs: list[tuple[int, object]], m: Metric, eps: float | None = None, radii: dict[int, float] | None = None) -> DataFrame:
    """pid, vec, home (cell), dmin, and with ``eps`` the candidate cells with their distances: those of the bisector test, or
    with ``radii`` those whose ball grown by eps holds the point. Map only.
    A point that is equally near to several centres belongs to the first."""
    reach = None if radii is None else np.array([slack(radii[c] + eps) if c in radii else -1.0 for c in range(len(cs))])
    kind = p.schema["vec"].dataType
    if sum(len(str(v)) for _, v in cs[:100]) / max(1, min(len(cs), 100)) * len(cs) > MOST_CENTRE_BYTES:
        raise ValueError("too many centres to share")
    shared = p.sparkSession.sparkContext.broadcast([v for _, v in cs])
    fields = [*p.select("pid", "vec").schema.fields, T.StructField("home", T.IntegerType()), T.StructField("dmin", T.DoubleType())]
    if eps is not None:
        fields += [T.StructField("cells", T.ArrayType(T.IntegerType())), T.StructField("far", T.ArrayType(T.DoubleType()))]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        groups = CentreGroups(decoded_centres(shared.value, m, kind), m)
        within = None if eps is None else (lambda dmin: slack(dmin + 2 * eps)[:, None]) if reach is None else (lambda dmin: reach[None, :])
        for whole in batches:
            for b in (whole.slice(k, 2048) for k in range(0, whole.num_rows, 2048)):
                home, dmin, row, cell, far = groups.search(m.decode(b.column(1)), within)
                cols = [b.column(0), b.column(1), pa.array(home.astype(np.int32)), pa.array(dmin)]
                if eps is not None:
                    at = np.concatenate(([0], np.cumsum(np.bincount(row, minlength=b.num_rows)))).astype(np.int32)
                    cols += [pa.ListArray.from_arrays(at, cell.astype(np.int32)), pa.ListArray.from_arrays(at, far)]
                yield pa.RecordBatch.from_arrays(cols, [f.name for f in fields])

    return p.select("pid", "vec").mapInArrow(run, T.StructType(fields))


def voronoi(p: DataFrame, cs: list[tuple[int, object]], metric: str | Metric = "l2") -> DataFrame:
    return assign(p, cs, resolve(metric)).select("pid", F.col("home").alias("cell"), "dmin")


def cell_stats(assigned: DataFrame) -> DataFrame:
    return assigned.groupBy(F.col("home").alias("cell")).agg(F.count("*").alias("size"), F.max("dmin").alias("radius"))


def assign_cells(loads: list[float], n: int, how: str = "lpt") -> list[int]:
    """Cells to ``n`` tasks: cyclic, or longest first to the least loaded (at most 4/3 of the best largest load)."""
    if how == "cyclic":
        return [i % n for i in range(len(loads))]
    heap, out = [(0.0, t) for t in range(n)], [0] * len(loads)
    for i in sorted(range(len(loads)), key=lambda i: (-loads[i], i)):
        load, t = heapq.heappop(heap)
        out[i] = t
        heapq.heappush(heap, (load + loads[i], t))
    return out


def with_candidates(p: DataFrame, cs: list[tuple[int, object]], m: Metric, eps: float, bound: str = "both") -> tuple[DataFrame, dict]:
    """The assignment with the candidates that ``bound`` asks for, and the statistics of cells. The ball's test needs the radii
    first, so it goes over the points twice."""
    if bound not in ("both", "bisector", "ball"):
        raise ValueError(f"no bound {bound!r}")
    stats = lambda a: {r.cell: r for r in cell_stats(a).collect()}
    if bound == "ball":
        cells = stats(assign(p, cs, m))
        return assign(p, cs, m, eps, {c: r.radius for c, r in cells.items()}), cells
    assigned = assign(p, cs, m, eps).persist(StorageLevel.DISK_ONLY)
    return assigned, stats(assigned)


def ghosts(assigned: DataFrame, eps: float, radii: dict[int, float], bound: str = "both", half: bool = True) -> DataFrame:
    """(pid, vec, home, cell): a row for each cell that a point is a ghost of. ``assigned`` holds the candidates of the bisector
    test, or for "ball" those of that test alone; "both" adds the ball's test to the bisector's."""
    t = assigned.select("pid", "vec", "home", F.explode(F.arrays_zip("cells", "far")).alias("g")).select("pid", "vec", "home", F.col("g.cells").alias("cell"), F.col("g.far").alias("far"))
    if half:
        t = t.filter("cell < home")
    if bound == "both":
        reach = F.create_map(*[F.lit(v) for c, r in radii.items() for v in (c, float(slack(r + eps)))]) if radii else F.create_map(F.lit(0), F.lit(0.0))
        t = t.filter(F.col("far") <= reach[F.col("cell")])
    return t.drop("far")


WEIGHTS = {"size": lambda h, g: h, "size_log": lambda h, g: h * np.log2(h + 1), "with_ghosts": lambda h, g: h + g, "square": lambda h, g: h * h}


#: What a kernel tells of a part, instead of its edges. Waiting is for rows: for the exchange and its sort, mostly.
WORK = "part long, cell int, home_rows long, guest_rows long, pairs long, build_distances long, home_distances long, guest_distances long, build_seconds double, home_seconds double, guest_seconds double, wait_seconds double"


def cell_kernel(m: Metric, eps: float, index: str, options: dict, half: bool, intra: bool = True, report: bool | str = False, directed: bool = False):
    """Arrow kernel over rows sorted by (part, role): a part's home rows, then what comes to it, streamed. A part is a cell, or
    of a heavy cell a pair of blocks (i <= j): the first block's rows are at home, the second's come to it. Edges are (smaller, larger),
    or with ``directed`` (guest, home); ``report`` gives a row of ``WORK`` a part instead, "counts" without measuring the pairs that a
    prefilter is sure of (the counts are the same, the seconds are not)."""
    if report == "counts":
        m = replace(m, measured=False)
    names = [c.split()[0] for c in WORK.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part_id, held, tree, pids, own, whole, pace = None, [], None, None, None, True, Pace()
        spent: Counter = Counter()

        def clocked(phase: str, steps: Iterable) -> Iterator:
            steps = iter(steps)
            while True:
                at, known = perf_counter(), m.evaluations
                step = next(steps, None)
                spent[f"{phase}_seconds"] += perf_counter() - at
                spent[f"{phase}_distances"] += m.evaluations - known
                if step is None:
                    return
                yield step

        def structure() -> Iterator[tuple]:
            t = pa.Table.from_batches(held)
            yield INDEXES[index](m.decode(t.column("vec")), m, **options), t.column("pid").to_numpy()

        def told(src: np.ndarray, dst: np.ndarray, d: np.ndarray) -> Iterable[pa.RecordBatch]:
            spent["pairs"] += len(d)
            if report:
                return ()
            return pa.table({"src": src, "dst": dst, "dist": d}).to_batches(max_chunksize=1 << 16) if directed else edge_batches(src, dst, d)

        def inside(tree, pids: np.ndarray) -> Iterator[pa.RecordBatch]:
            if intra and whole:
                for i, j, d in clocked("home", tree.self_query(eps)):
                    yield from told(pids[i], pids[j], d)

        def closed() -> Iterator[pa.RecordBatch]:
            if held:
                yield from inside(*next(clocked("build", structure())))
            if report and part_id is not None:
                row = {"part": part_id, "cell": own} | {k: spent[k] for k in names[2:]}
                yield pa.table({k: pa.array([v], kind) for (k, v), kind in zip(row.items(), [pa.int64(), pa.int32(), *[pa.int64()] * 6, *[pa.float64()] * 4])}).to_batches()[0]
            spent.clear()

        for b in clocked("wait", batches):
            waited = spent.pop("wait_seconds")
            if not b.num_rows:
                continue
            parts, roles = b.column("part").to_numpy(), b.column("role").to_numpy()
            cuts = np.flatnonzero((np.diff(parts) != 0) | (np.diff(roles) != 0)) + 1
            for lo, hi in zip([0, *cuts], [*cuts, b.num_rows]):
                part = b.slice(lo, hi - lo)
                if parts[lo] != part_id:
                    yield from closed()
                    part_id, held, tree, pace = parts[lo], [], None, Pace()
                    own, whole = part.column("cell")[0].as_py(), part.column("whole")[0].as_py()
                spent["wait_seconds"] += waited
                waited = 0.0
                spent["guest_rows" if roles[lo] else "home_rows"] += hi - lo
                if roles[lo] == 0:
                    held.append(part)
                    continue
                if held:
                    tree, pids = next(clocked("build", structure()))
                    held = []
                    yield from inside(tree, pids)
                if tree is None:
                    continue  # a part without home rows has nothing to find
                come = part.column("pid").to_numpy()
                homes = None if half else part.column("home").to_numpy()
                x = m.decode(part.column("vec"))
                for at, (i, j, d) in clocked("guest", pace.strips(len(x), lambda lo, hi: tree.query(x[lo:hi], eps))):  # noqa: B023
                    if homes is not None:
                        keep = homes[i + at] >= own
                        i, j, d = i[keep], j[keep], d[keep]
                    yield from told(come[i + at], pids[j], d)
        yield from closed()

    return run


def landmark_graph(p: DataFrame, eps: float, metric: str | Metric = "l2", m: int = 16, how: str = "random", seed: int = 0, bound: str = "both", half_ghosts: bool = True, ghost: str = "collective", rounds: int = 4, balance: str = "lpt", weight: str = "size", tasks: int | None = None, index: str = "cover", ids: list[int] | None = None, max_cell: int = 50_000, measures: dict | None = None, report: bool | str = False, **options) -> DataFrame:
    """Edges by cells. Cells stay where they are and are built once; their ghosts stream past in batches: in order of id
    (``ghost="collective"``), or (``"ring"``) as ``rounds`` blocks of points going round one after another. A cell of more than ``max_cell``
    points is dealt into blocks, every pair of blocks being a part of its own, so no part holds more at home. ``report`` gives
    the rows, distances and seconds of each part (``WORK``) instead of edges."""
    met = resolve(metric)
    cs = centers(p, m, how, seed, met, ids)
    spark = p.sparkSession
    if not cs:
        return spark.createDataFrame([], WORK if report else EDGE)
    assigned, cells = with_candidates(p, cs, met, eps, bound)
    radii = {c: r.radius for c, r in cells.items()}
    n = tasks or max(1, min(len(cs), int(spark.conf.get("spark.sql.shuffle.partitions"))))
    guests = {r.cell: r["count"] for r in ghosts(assigned, eps, radii, bound, half_ghosts).groupBy("cell").count().collect()} if weight == "with_ghosts" else {}
    loads = [float(WEIGHTS[weight](cells[c].size if c in cells else 0, guests.get(c, 0))) for c in range(len(cs))]
    place = assign_cells(loads, n, balance)
    if measures is not None:
        measures |= {"centres": [c for c, _ in cs], "sizes": {c: r.size for c, r in cells.items()}, "radii": radii, "place": place, "loads": loads}
    blocks = {c: -(-r.size // max_cell) for c, r in cells.items() if r.size > max_cell}
    most = max(blocks.values(), default=1)
    k = F.coalesce(F.create_map(*[F.lit(int(v)) for c in blocks.items() for v in c])[F.col("cell")], F.lit(1)) if blocks else F.lit(1)
    one = F.pmod(F.xxhash64("pid", F.lit(seed + 1)), k).cast("int")
    each = F.sequence(F.lit(0), k - 1)
    home = assigned.select("pid", "vec", "home", F.col("home").alias("cell"))
    come = ghosts(assigned, eps, radii, bound, half_ghosts).select("pid", "vec", "home", "cell")
    if blocks:
        # a home row meets the blocks from its own on, and comes to those before it; ghosts come to every block
        pair = lambda i, j: F.struct(F.least(i, j).alias("i"), F.greatest(i, j).alias("j"), (i < j).cast("int").alias("role"))
        home = home.withColumn("b", one).withColumn("at", F.explode(F.transform(each, lambda j: pair(j, F.col("b")))))
        come = come.withColumn("at", F.explode(F.transform(each, lambda i: F.struct(i.alias("i"), i.alias("j"), F.lit(1).alias("role")))))
    else:
        at = lambda role: F.struct(F.lit(0).alias("i"), F.lit(0).alias("j"), F.lit(role).alias("role"))
        home, come = home.withColumn("at", at(0)), come.withColumn("at", at(1))
    row = ("pid", "vec", "home", "cell", "at.role", ((F.col("cell").cast("long") * most + F.col("at.i")) * most + F.col("at.j")).alias("part"), (F.col("at.i") == F.col("at.j")).alias("whole"))
    home, come = home.select(*row), come.select(*row)
    task = F.element_at(F.array(*map(F.lit, place)), F.col("cell") + 1)
    if blocks:
        task = F.when(F.col("cell").isin(*blocks), F.pmod(F.xxhash64("part"), F.lit(n)).cast("int")).otherwise(task)

    if ghost == "ring":
        come = come.withColumn("role", F.pmod(F.xxhash64("pid", F.lit(seed)), F.lit(rounds)).cast("int") + 1)
    dealt = home.unionByName(come).withColumn("task", task).repartitionById(n, "task").sortWithinPartitions("part", "role", "pid")
    return dealt.mapInArrow(cell_kernel(met, eps, index, options, half_ghosts, report=report), WORK if report else EDGE)


def near_join(a: DataFrame, b: DataFrame, eps: float, metric: str | Metric = "l2", m: int = 16, seed: int = 0, index: str = "cover", max_cell: int = 50_000, **options) -> DataFrame:
    """(left, right, dist) of all pairs across two sets: cells hold ``b``; each point of ``a`` looks up every cell that may hold
    a partner, its own nearest among them, and streams past. A cell of more than ``max_cell`` points is dealt into blocks, each
    a part of its own to which the cell's lookups come."""
    met = resolve(metric)
    cs = centers(b, m, "random", seed, met)
    if not cs:
        return a.sparkSession.createDataFrame([], "left long, right long, dist double")
    home = assign(b, cs, met)
    size = {r.cell: r.size for r in cell_stats(home).collect()}
    looked = assign(a, cs, met, eps).select("pid", "vec", "home", F.explode(F.concat(F.array("home"), F.col("cells"))).alias("cell")).filter(F.col("cell").isin(*size))
    blocks = {c: -(-n // max_cell) for c, n in size.items()}
    most = max(blocks.values())
    k = F.create_map(*[F.lit(int(v)) for c in blocks.items() for v in c])[F.col("cell")]
    row = lambda role: ("pid", "vec", "home", "cell", F.lit(role).alias("role"), (F.col("cell").cast("long") * most + F.col("b")).alias("part"), F.lit(False).alias("whole"))
    stay = home.withColumn("cell", F.col("home")).withColumn("b", F.pmod(F.xxhash64("pid", F.lit(seed + 1)), k)).select(*row(0))
    come = looked.withColumn("b", F.explode(F.sequence(F.lit(0), k - 1))).select(*row(1))
    n = int(a.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = stay.unionByName(come).repartition(n, "part").sortWithinPartitions("part", "role", "pid")
    pairs = dealt.mapInArrow(cell_kernel(met, eps, index, options, True, intra=False, directed=True), EDGE)
    return pairs.select(F.col("src").alias("left"), F.col("dst").alias("right"), "dist")
