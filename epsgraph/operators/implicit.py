"""What a near-neighbour graph tells without its edges written out: a task finds the neighbours of a bounded block of points by itself.

A part is a block of a cell's points at home, and everything that may lie within eps of them: their cell and its ghosts. Rows go
through an exchange as often as a point has parts; pairs are met inside the kernels only.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.metrics import MOST_CELLS, Metric, resolve, slack
from ..functions.trees import CoverTree
from .components import checkpoint_dir
from .downstream import inflated
from .landmark import assign_cells, centers, ghosts, with_candidates

#: Points at home in a part, cells at most, and bytes of bit rows that a task holds.
HOME_ROWS, MOST_CENTRES, BIT_BYTES = 4096, 1024, 104 << 20
#: Points at home in a part of the flow matrix, whose cost grows with all that lies around.
FLOW_ROWS = 512
#: Rows whose neighbours among all of a part are found at a time.
STRIP = 128
#: Of the flow matrix: bounds by groups of points only where more than the first lie around; so many radii are told apart.
FEWEST_BOUNDED, RADII = 2048, 8


class Neighbourhoods:
    """The parts of ``p`` at radius ``eps``; what comes to them lies within ``hops`` times eps. Where ``p`` has no rows, ``cells`` is empty."""

    def __init__(self, p: DataFrame, eps: float, metric: str | Metric = "l2", home_rows: int = HOME_ROWS, seed: int = 0, hops: int = 1):
        self.p, self.eps, self.reach, self.m, self.seed = p, eps, hops * eps, resolve(metric), seed
        cs = centers(p, min(MOST_CENTRES, max(16, p.count() // home_rows)), seed=seed)
        if not cs:
            self.cells = {}
            return
        self.assigned, self.cells = with_candidates(p, cs, self.m, self.reach)
        self.blocks = {c: -(-r.size // home_rows) for c, r in self.cells.items()}
        self.most = max(self.blocks.values())
        parts = [(c * self.most + b, self.cells[c].size / k) for c, k in self.blocks.items() for b in range(k)]
        self.tasks = min(len(parts), max(1, int(p.sparkSession.conf.get("spark.sql.shuffle.partitions"))))
        place = assign_cells([size for _, size in parts], self.tasks)
        self.task_of = F.create_map(*[F.lit(int(v)) for (part, _), t in zip(parts, place) for v in (part, t)])

    def _split(self, cell: str) -> Column:
        return F.create_map(*[F.lit(int(v)) for c in self.blocks.items() for v in c])[F.col(cell)]

    def own(self, of: DataFrame | None = None) -> DataFrame:
        """(pid, vec, part): where each point is at home."""
        a = self.assigned if of is None else of
        block = F.pmod(F.xxhash64("pid", F.lit(self.seed + 1)), self._split("home"))
        return a.withColumn("part", (F.col("home") * self.most + block).cast("int"))

    def come(self, of: DataFrame, *also: str) -> DataFrame:
        """(pid, vec, *also, part): the parts that a point may have neighbours in, its own among them."""
        radii = {c: r.radius for c, r in self.cells.items()}
        packed = of.withColumn("vec", F.struct("vec", *also))
        far = ghosts(packed, self.reach, radii, half=False).select("pid", "vec", "cell")
        here = packed.select("pid", "vec", F.col("home").alias("cell"))
        rows = here.unionByName(far).withColumn("b", F.explode(F.sequence(F.lit(0), self._split("cell") - 1)))
        return rows.select("pid", "vec.*", (F.col("cell") * self.most + F.col("b")).cast("int").alias("part"))

    def dealt(self, home: DataFrame, come: DataFrame) -> DataFrame:
        """Both with ``role`` 0 and 1, part by part, the rows at home first."""
        rows = home.withColumn("role", F.lit(0)).unionByName(come.withColumn("role", F.lit(1)), allowMissingColumns=True)
        return rows.withColumn("task", self.task_of[F.col("part")]).repartitionById(self.tasks, "task").sortWithinPartitions("part", "role")

    def run(self, make, schema: str, also: tuple[str, ...] = (), of: DataFrame | None = None) -> DataFrame:
        """What ``make(metric, eps, home)`` answers for each part, shown in batches what comes: rows of ``of`` (all points, unless given)."""
        come = self.come(self.assigned if of is None else of, *also)
        return self.dealt(self.own().select("pid", "vec", "part"), come).mapInArrow(part_kernel(make, self.m, self.eps), schema)


def part_kernel(make, m: Metric, eps: float):
    """Arrow kernel over rows sorted by (part, role): ``make(m, eps, home)`` once a part, ``add`` for each batch that comes, ``result`` at its end."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, held, now = None, [], None
        for b in batches:
            if not b.num_rows:
                continue
            parts, roles = b.column("part").to_numpy(), b.column("role").to_numpy()
            cuts = np.flatnonzero((np.diff(parts) != 0) | (np.diff(roles) != 0)) + 1
            for lo, hi in zip([0, *cuts], [*cuts, b.num_rows]):
                piece = b.slice(lo, hi - lo)
                if parts[lo] != part:
                    if now is not None:
                        yield from now.result()
                    part, held, now = parts[lo], [], None
                if roles[lo] == 0:
                    held.append(piece)
                elif held or now is not None:
                    if now is None:
                        now, held = make(m, eps, pa.Table.from_batches(held)), []
                    now.add(piece)
        if now is not None:
            yield from now.result()

    return run


class _Part:
    """Points at home, in order of pid, and the strips in which others are held against them."""

    def __init__(self, m: Metric, eps: float, home: pa.Table):
        order = np.argsort(home.column("pid").to_numpy())
        self.m, self.eps, self.pid = m, eps, home.column("pid").to_numpy()[order]
        self.x = m.decode(home.column("vec"))[order]

    def strips(self, batch: pa.RecordBatch) -> Iterator[tuple[slice, np.ndarray, np.ndarray, np.ndarray]]:
        """(rows, pids, points, which of them (rows) lie within eps of which at home (columns), none of itself)."""
        pid, x = batch.column("pid").to_numpy(), self.m.decode(batch.column("vec"))
        step = max(1, MOST_CELLS // 4 // len(self.x))
        for at in range(0, len(pid), step):
            rows = slice(at, at + step)
            near = self.m.near(x[rows], self.x, self.eps)
            k = np.minimum(np.searchsorted(self.pid, pid[rows]), len(self.pid) - 1)
            itself = np.flatnonzero(self.pid[k] == pid[rows])
            near[itself, k[itself]] = False
            yield rows, pid[rows], x[rows], near


class _Sums(_Part):
    def __init__(self, m: Metric, eps: float, home: pa.Table):
        super().__init__(m, eps, home)
        self.total = np.zeros(len(self.x))

    def add(self, batch: pa.RecordBatch) -> None:
        value = batch.column("value").to_numpy()
        for rows, _, _, near in self.strips(batch):
            self.total += value[rows] @ near

    def result(self) -> Iterator[pa.RecordBatch]:
        yield pa.record_batch({"pid": self.pid, "value": self.total})


class _Paths(_Part):
    def __init__(self, m: Metric, eps: float, home: pa.Table):
        super().__init__(m, eps, home)
        self.best: dict[int, np.ndarray] = {}

    def add(self, batch: pa.RecordBatch) -> None:
        source, d = batch.column("source").to_numpy(), batch.column("d").to_numpy()
        for rows, _, x, near in self.strips(batch):
            i, j = np.nonzero(near)
            n = d[rows][i] + self.m.apart(x, self.x, i, j)
            for s in np.unique(source[rows]):
                best = self.best.setdefault(int(s), np.full(len(self.x), np.inf))
                of = source[rows][i] == s
                np.minimum.at(best, j[of], n[of])

    def result(self) -> Iterator[pa.RecordBatch]:
        for s, best in self.best.items():
            ok = np.isfinite(best)
            yield pa.record_batch({"source": np.full(ok.sum(), s), "pid": self.pid[ok], "n": best[ok]})


class _Around(_Part):
    """Keeps all that comes."""

    def __init__(self, m: Metric, eps: float, home: pa.Table):
        super().__init__(m, eps, home)
        self.batches: list[pa.RecordBatch] = []

    def add(self, batch: pa.RecordBatch) -> None:
        self.batches.append(batch)

    def universe(self, m: Metric) -> tuple[pa.Table, np.ndarray, np.ndarray]:
        t = pa.Table.from_batches(self.batches)
        self.batches = []
        return t, t.column("pid").to_numpy(), m.decode(t.column("vec"))


def _words(near: np.ndarray) -> np.ndarray:
    """Rows of conditions as rows of 64-bit words."""
    bits = np.packbits(near, axis=1)
    return np.pad(bits, ((0, 0), (0, -bits.shape[1] % 8))).view(np.uint64)


class _Closed(_Around):
    """Common neighbours of the ends of each edge that has an end at home, each edge of the graph in one of its ends' parts."""

    def result(self) -> Iterator[pa.RecordBatch]:
        _, pid, x = self.universe(self.m)
        wide = -(-len(pid) // 64) * 8
        total = np.zeros(len(pid), np.int64)
        where = np.argsort(pid)
        at_home = where[np.searchsorted(pid[where], self.pid)]
        degree = np.zeros(len(self.pid), np.int64)
        many = max(STRIP, BIT_BYTES // wide)
        for lo in range(0, len(self.pid), many):
            own, ids = slice(lo, lo + many), self.pid[lo : lo + many]
            rows = np.concatenate([self._bits(self.x[k : min(k + STRIP, lo + many)], ids[k - lo : k - lo + STRIP], x, pid) for k in range(lo, min(lo + many, len(self.pid)), STRIP)])
            degree[own] = np.bitwise_count(rows).sum(1, dtype=np.int64)
            count_ = np.zeros(len(ids), np.int64)
            for k in range(0, len(pid), STRIP):
                others = pid[k : k + STRIP]
                near = self.m.near(x[k : k + STRIP], x[at_home[own]], self.eps)
                # of an edge, the end of smaller id where both ids are even or both odd
                near &= ((others[:, None] + ids[None, :]) % 2 == 0) == (ids[None, :] < others[:, None])
                near &= ids[None, :] != others[:, None]
                met = np.flatnonzero(near.any(1))
                if not len(met):
                    continue
                bits = self._bits(x[k + met], others[met], x, pid)
                for b, j in zip(bits, met):
                    i = np.flatnonzero(near[j])
                    common = np.bitwise_count(np.bitwise_and(held := rows[i], b, out=held)).sum(1, dtype=np.uint32).astype(np.int64)
                    count_[i] += common
                    total[k + j] += common.sum()
            total[at_home[own]] += count_
        yield pa.record_batch({"pid": self.pid, "closed": np.zeros(len(self.pid), np.int64), "degree": degree})
        some = total > 0
        yield pa.record_batch({"pid": pid[some], "closed": total[some], "degree": np.zeros(some.sum(), np.int64)})

    def _bits(self, a: np.ndarray, ids: np.ndarray, x: np.ndarray, pid: np.ndarray) -> np.ndarray:
        near = self.m.near(a, x, self.eps)
        near &= ids[:, None] != pid[None, :]
        return _words(near)


def _strong(v: np.ndarray, keep: int) -> np.ndarray:
    """Places of the ``keep`` largest positive entries, and of those that a rank by 12 digits might put before them."""
    some = np.flatnonzero(v > 0)
    if len(some) <= keep:
        return some
    return some[v[some] >= np.partition(v[some], -keep)[-keep] - 2e-12]


def _columns(found: list[tuple[int, np.ndarray, np.ndarray]]) -> pa.RecordBatch:
    n = [len(src) for _, src, _ in found]
    src, value = (np.concatenate([f[k] for f in found]) for k in (1, 2))
    return pa.record_batch({"src": src, "dst": np.repeat([f[0] for f in found], n), "value": value})


class _Flow(_Around):
    """Columns at home of the square of the flow matrix, of each those entries that may be among the ``keep`` strongest.

    An entry is a sum over the points near both its ends. For a group of points (a leaf of a cover tree) the sum over all that lie within eps
    and the leaf's radius of its centre bounds them from above, so most groups are left without being measured: those below the ``keep``-th
    of the exact entries of the best groups."""

    def __init__(self, m: Metric, eps: float, home: pa.Table, inflation: float, keep: int):
        super().__init__(m, eps, home)
        self.inflation, self.keep = inflation, keep

    def groups(self, x: np.ndarray) -> list[tuple[float, np.ndarray, list[np.ndarray]]]:
        """(radius, centres, members) of leaves, a few radii for all; none where there are few points."""
        if len(x) <= FEWEST_BOUNDED:
            return []
        tree = CoverTree(x, self.m, leaf_size=16)
        leaves = sorted((n for n, own in enumerate(tree.members) if own is not None), key=lambda n: tree.radius[n])
        parts = [part.tolist() for part in np.array_split(np.array(leaves), RADII) if len(part)]
        return [(tree.radius[part[-1]], x[[tree.centre[n] for n in part]], [tree.members[n] for n in part]) for part in parts]

    def result(self) -> Iterator[pa.RecordBatch]:
        t, pid, x = self.universe(self.m)
        value = t.column("value").to_numpy()
        where = np.argsort(pid)
        own = value[where[np.searchsorted(pid[where], self.pid)]]
        groups = self.groups(x)
        members = [g for _, _, each in groups for g in each]
        size = np.array([len(g) for g in members], int)

        def sums(near: np.ndarray, to: np.ndarray, eps: float) -> np.ndarray:
            """Of each row and each point of ``to``, the values of the points near the row and within ``eps`` of the point."""
            total, via = np.zeros((len(near), len(to))), np.flatnonzero(near.any(0))
            wide = max(1, 2 * MOST_CELLS // max(1, len(to)))
            for k in (via[c : c + wide] for c in range(0, len(via), wide)):
                total += (near[:, k] * value[k]) @ self.m.near(x[k], to, eps).astype(float)
            return total

        for lo in range(0, len(self.pid), STRIP):
            near = self.m.near(self.x[lo : lo + STRIP], x, self.eps)
            scale = own[lo : lo + STRIP, None]
            if groups:
                bound = np.hstack([sums(near, c, float(slack(self.eps + r))) for r, c, _ in groups]) * scale * (1 + 1e-9)
                order = np.argsort(-bound, axis=1)
                before = np.cumsum(size[order], axis=1) - size[order]
                best = np.zeros(len(members), bool)
                best[order[before < self.keep]] = True
                at = np.concatenate([members[g] for g in np.flatnonzero(best)])
                total = sums(near, x[at], self.eps) * scale
                least = np.partition(total, -self.keep, axis=1)[:, -self.keep, None] if len(at) >= self.keep else np.zeros_like(scale)
                rest = np.flatnonzero(((bound > 0) & (bound**self.inflation >= least**self.inflation * (1 - 1e-9) - 4e-12)).any(0) & ~best)
                if len(rest):
                    more = np.concatenate([members[g] for g in rest])
                    at, total = np.concatenate([at, more]), np.hstack([total, sums(near, x[more], self.eps) * scale])
            else:
                at, total = np.arange(len(x)), sums(near, x, self.eps) * scale
            found = []
            for i, row in zip(self.pid[lo : lo + STRIP], total):
                some = _strong(row**self.inflation, self.keep)
                found.append((i, pid[at[some]], row[some]))
            yield _columns(found)


class _Product:
    """Columns at home of a sparse matrix's square, from those columns that theirs name; again the strongest alone."""

    def __init__(self, m: Metric, eps: float, home: pa.Table, inflation: float, keep: int):
        self.home, self.inflation, self.keep, self.batches = home, inflation, keep, []

    def add(self, batch: pa.RecordBatch) -> None:
        self.batches.append(batch)

    def result(self) -> Iterator[pa.RecordBatch]:
        t = pa.Table.from_batches(self.batches)
        order = np.argsort(t.column("pid").to_numpy())
        ids = t.column("pid").to_numpy()[order]
        lists = t.column("src").combine_chunks().take(pa.array(order))
        ends = lists.offsets.to_numpy()
        names, place = np.unique(lists.values.to_numpy(), return_inverse=True)
        value = t.column("value").combine_chunks().take(pa.array(order)).values.to_numpy()
        found = []
        for dst, src, v in zip(self.home.column("pid").to_pylist(), self.home.column("src").to_pylist(), self.home.column("value").to_pylist()):
            known = np.isin(src, ids)
            at, v = np.searchsorted(ids, np.array(src)[known]), np.array(v)[known]
            lo, n = ends[at], ends[at + 1] - ends[at]
            entry = np.repeat(lo - np.cumsum(n) + n, n) + np.arange(n.sum())
            row = np.bincount(place[entry], value[entry] * np.repeat(v, n), len(names))
            some = _strong(row**self.inflation, self.keep)
            found.append((dst, names[some], row[some]))
        if found:
            yield _columns(found)


def flow_clusters(p: DataFrame, eps: float, metric: str | Metric = "l2", inflation: float = 2.0, steps: int = 8, keep: int = 50, least: float = 1e-4) -> DataFrame:
    """(pid, cluster) as ``downstream.mcl``: the flow matrix's first square from points within two hops, later ones by packed
    columns, each sent to the parts whose columns name it."""
    checkpoint_dir(p.sparkSession)
    hood = Neighbourhoods(p, eps, metric, FLOW_ROWS, hops=2)
    if not hood.cells:
        return p.select("pid", F.col("pid").alias("cluster"))
    entries = "src long, dst long, value double"
    degree = neighbour_sums(hood, p.select("pid", F.lit(1.0).alias("value"))).checkpoint()
    own = hood.own().select("pid", "part")
    m = hood.run(lambda *a: _Flow(*a, inflation, keep), entries, ("value",), hood.assigned.join(degree.select("pid", (1 / (F.col("value") + 1)).alias("value")), "pid"))
    m = inflated(m, inflation, keep).filter(F.col("value") >= least).checkpoint()
    for _ in range(steps - 1):
        columns = m.groupBy(F.col("dst").alias("pid")).agg(F.collect_list(F.struct("src", "value")).alias("e")).select("pid", F.col("e.src").alias("src"), F.col("e.value").alias("value"))
        named = m.join(own, F.col("dst") == F.col("pid")).select(F.col("src").alias("pid"), "part").distinct()
        rows = hood.dealt(columns.join(own, "pid"), columns.join(named, "pid"))
        m = rows.mapInArrow(part_kernel(lambda *a: _Product(*a, inflation, keep), hood.m, eps), entries)
        m = inflated(m, inflation, keep).filter(F.col("value") >= least).checkpoint()
    return m.groupBy(F.col("dst").alias("pid")).agg(F.min_by("src", F.struct(-F.round("value", 6), F.col("src"))).alias("cluster"))


def neighbour_sums(hood: Neighbourhoods, values: DataFrame) -> DataFrame:
    """(pid, value) of every point: the sum of ``values`` (pid, value) over its neighbours."""
    of = hood.assigned.join(values.select("pid", F.col("value").cast("double").alias("value")), "pid")
    return hood.run(_Sums, "pid long, value double", ("value",), of)


def spectral(p: DataFrame, eps: float, metric: str | Metric = "l2", steps: int = 20) -> DataFrame:
    """(pid, value): ``power_iteration`` of the graph's normalised adjacency matrix, points without neighbours left out."""
    checkpoint_dir(p.sparkSession)
    hood = Neighbourhoods(p, eps, metric)
    if not hood.cells:
        return p.select("pid", F.lit(1.0).alias("value")).limit(0)
    degree = neighbour_sums(hood, p.select("pid", F.lit(1.0).alias("value"))).filter("value > 0").withColumnRenamed("value", "k").checkpoint()
    v = p.select("pid", F.lit(1.0).alias("value"))
    for _ in range(steps):
        sums = neighbour_sums(hood, v.join(degree, "pid").select("pid", (F.col("value") / F.sqrt("k")).alias("value")))
        v = sums.join(degree, "pid").select("pid", (F.col("value") / F.sqrt("k")).alias("value")).checkpoint()
        norm = v.agg(F.sqrt(F.sum(F.col("value") * F.col("value"))).alias("norm"))
        v = v.crossJoin(F.broadcast(norm)).select("pid", (F.col("value") / F.col("norm")).alias("value"))
    return v


def geodesics(p: DataFrame, eps: float, sources: list[int], metric: str | Metric = "l2") -> DataFrame:
    """(source, pid, dist): shortest path lengths from those ``sources`` that are points, by relaxing frontiers until none gets shorter."""
    checkpoint_dir(p.sparkSession)
    hood = Neighbourhoods(p, eps, metric)
    best = p.filter(F.col("pid").isin(*sources)).select(F.col("pid").alias("source"), "pid", F.lit(0.0).alias("d")).checkpoint()
    front = best
    while not front.isEmpty():
        # a point may be in the frontier of several sources: rows of its own
        reach = hood.run(_Paths, "source long, pid long, n double", ("source", "d"), hood.assigned.join(front, "pid"))
        shorter = F.col("d").isNull() | (F.col("n") < F.col("d") - 1e-12)
        new = F.col("n").isNotNull() & shorter
        now = best.join(reach, ["source", "pid"], "full").select("source", "pid", F.when(new, F.col("n")).otherwise(F.col("d")).alias("d"), new.alias("new")).checkpoint()
        best, front = now.select("source", "pid", "d"), now.filter("new").select("source", "pid", "d")
    return best.withColumnRenamed("d", "dist")


def local_clustering(p: DataFrame, eps: float, metric: str | Metric = "l2") -> DataFrame:
    """(pid, triangles, clustering): closed part of the pairs of neighbours; 0 below two neighbours."""
    hood = Neighbourhoods(p, eps, metric, 2 * HOME_ROWS)
    if not hood.cells:
        return p.select("pid", F.lit(0).cast("long").alias("triangles"), F.lit(0.0).alias("clustering"))
    t = hood.run(_Closed, "pid long, closed long, degree long").groupBy("pid").agg(F.sum("closed").alias("c"), F.sum("degree").alias("k"))
    # a triangle is closed by two of its edges at each corner
    t = t.select("pid", (F.col("c") / 2).cast("long").alias("triangles"), "k")
    return t.select("pid", "triangles", F.when(F.col("k") > 1, 2 * F.col("triangles") / (F.col("k") * (F.col("k") - 1))).otherwise(0.0).alias("clustering"))
