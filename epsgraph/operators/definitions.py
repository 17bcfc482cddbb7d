"""Balls, nets, Voronoi cells and dimension estimates as operators."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.metrics import Metric, resolve
from ..functions.trees import CoverTree, Pace
from .components import checkpoint_dir
from .landmark import assign, centers, decoded_centres
from .points import EDGE, edge_table

EDGE_NONE = edge_table(*[np.empty(0)] * 3)


def distances_to(p: DataFrame, vec, metric: str | Metric = "l2") -> DataFrame:
    """(pid, dist) from one given payload."""
    m, kind = resolve(metric), p.schema["vec"].dataType

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        x = decoded_centres([vec], m, kind)[0]
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(m.row(m.decode(b.column(1)), x))] if b.num_rows else [b.column(0), pa.array([], pa.float64())], ["pid", "dist"])

    return p.select("pid", "vec").mapInArrow(run, "pid long, dist double")


def ball(p: DataFrame, vec, r: float, metric: str | Metric = "l2") -> DataFrame:
    return distances_to(p, vec, metric).filter(F.col("dist") <= r)


def dist_to_set(p: DataFrame, cs: list[tuple[int, object]], metric: str | Metric = "l2") -> DataFrame:
    """(pid, nearest, dist); ties to the first centre."""
    near = assign(p, cs, resolve(metric))
    return near.select("pid", F.element_at(F.array(*[F.lit(c) for c, _ in cs]), F.col("home") + 1).alias("nearest"), F.col("dmin").alias("dist"))


def coverage_radius(p: DataFrame, cs: list[tuple[int, object]], metric: str | Metric = "l2") -> DataFrame:
    return dist_to_set(p, cs, metric).agg(F.max("dist").alias("radius"))


def separation(cs: list[tuple[int, object]], metric: str | Metric, kind) -> float:
    m = resolve(metric)
    x = decoded_centres([v for _, v in cs], m, kind)
    d = m.table(x, x)
    np.fill_diagonal(d, np.inf)
    return float(d.min())


def is_r_net(p: DataFrame, cs: list[tuple[int, object]], r: float, metric: str | Metric = "l2") -> bool:
    """Whether the set covers within r and is separated by r at least."""
    return coverage_radius(p, cs, metric).first()[0] <= r and separation(cs, metric, p.schema["vec"].dataType) >= r


def _sample(p: DataFrame, n: int, seed: int) -> list[tuple]:
    return centers(p, n, "random", seed)


def spread(p: DataFrame, sample: int | None = None, metric: str | Metric = "l2", seed: int = 0) -> DataFrame:
    """(largest, smallest_positive, spread) of the pair distances; from a hash sample's distances to all points if given."""
    m, kind = resolve(metric), p.schema["vec"].dataType
    if sample is None:
        a, b = p.alias("a"), p.alias("b")
        d = a.join(b, F.col("a.pid") < F.col("b.pid")).select(m.native(F.col("a.vec"), F.col("b.vec")).alias("d"))
    else:
        chosen = _sample(p, sample, seed)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            c = decoded_centres([v for _, v in chosen], m, kind)
            for b in batches:
                if b.num_rows:
                    d = m.table(m.decode(b.column(0)), c)
                    yield pa.record_batch({"d": np.array([d.max(), d[d > 0].min(initial=np.inf)])})

        d = p.select("vec").mapInArrow(run, "d double")
    return d.filter(F.col("d") < float("inf")).agg(F.max("d").alias("largest"), F.min(F.when(F.col("d") > 0, F.col("d"))).alias("smallest_positive")).withColumn("spread", F.col("largest") / F.col("smallest_positive"))


def growth_constant(p: DataFrame, radii: list[float], samples: int = 20, metric: str | Metric = "l2", seed: int = 0, ids: list[int] | None = None) -> DataFrame:
    """(constant): the largest ratio of the points in the doubled ball to those in the ball, over sampled centres and radii."""
    m, kind = resolve(metric), p.schema["vec"].dataType
    chosen = centers(p, 0, "ids", ids=ids) if ids else _sample(p, samples, seed)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = decoded_centres([v for _, v in chosen], m, kind)
        for b in batches:
            if b.num_rows:
                d = m.table(m.decode(b.column(0)), c)
                for k, r in enumerate(radii):
                    yield pa.record_batch({"k": np.full(len(c), k), "c": np.arange(len(c)), "near": (d <= r).sum(0), "far": (d <= 2 * r).sum(0)})

    sums = p.select("vec").mapInArrow(run, "k long, c long, near long, far long").groupBy("k", "c").agg(F.sum("near").alias("near"), F.sum("far").alias("far"))
    return sums.agg(F.max(F.col("far") / F.col("near")).alias("constant"))


def intrinsic_dim(p: DataFrame, samples: int = 200, metric: str | Metric = "l2", seed: int = 0, ids: list[int] | None = None) -> DataFrame:
    """(samples, dimension) by the ratio of the second to the first neighbour distance of sampled or given points."""
    m, kind = resolve(metric), p.schema["vec"].dataType
    chosen = centers(p, 0, "ids", ids=ids) if ids else _sample(p, samples, seed)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = decoded_centres([v for _, v in chosen], m, kind)
        for b in batches:
            if b.num_rows:
                d = m.table(m.decode(b.column(0)), c)
                d = np.sort(np.where(d > 0, d, np.inf), axis=0)[:2]
                yield pa.record_batch({"c": np.tile(np.arange(len(c)), len(d)), "d": d.ravel()})

    two = p.select("vec").mapInArrow(run, "c long, d double").filter(F.col("d") < float("inf")).groupBy("c").agg(F.slice(F.array_sort(F.collect_list("d")), 1, 2).alias("t"))
    two = two.filter(F.size("t") == 2).select(F.log(F.col("t")[1] / F.col("t")[0]).alias("r"))
    return two.agg(F.count("*").alias("samples"), (F.count("*") / F.sum("r")).alias("dimension"))


TREE = "part int, node int, parent int, level int, pid long, radius double, size long, is_leaf boolean, members array<long>"


def _by(p: DataFrame, part: str | None) -> DataFrame:
    return p.select("pid", "vec", (F.lit(0) if part is None else F.col(part)).cast("int").alias("part"))


def tree_rows(p: DataFrame, metric: str | Metric = "l2", part: str | None = None, **options) -> DataFrame:
    """Cover trees as rows (``TREE``), one over all points or one for each value of the column ``part``; a part must fit a task.
    Write them to a table to keep them; ``stored_tree_graph`` takes them up again."""
    m = resolve(metric)

    def run(t: pa.Table) -> pa.Table:
        t = t.sort_by("pid")
        rows = CoverTree(m.decode(t.column("vec")), m, **options).rows(t.column("pid").to_numpy())
        names = ("node", "parent", "level", "pid", "radius", "size", "is_leaf", "members")
        kinds = (pa.int32(), pa.int32(), pa.int32(), pa.int64(), pa.float64(), pa.int64(), pa.bool_(), pa.list_(pa.int64()))
        return pa.table({"part": pa.array([t.column("part")[0].as_py()] * len(rows), pa.int32())} | {n: pa.array(c, k) for n, k, c in zip(names, kinds, zip(*rows))})

    return _by(p, part).groupBy("part").applyInArrow(run, TREE)


def stored_tree_graph(trees: DataFrame, p: DataFrame, eps: float, metric: str | Metric = "l2", part: str | None = None, **options) -> DataFrame:
    """Edges within each part by its stored tree, which is not built again; points and tree rows meet by part. A tree that lacks
    points of its part, or has others, is an error."""
    m = resolve(metric)
    columns = ("node", "parent", "level", "pid", "radius", "size", "is_leaf", "members")

    def run(rows: pa.Table, own: pa.Table) -> pa.Table:
        if not own.num_rows and not rows.num_rows:
            return EDGE_NONE
        ids = own.column("pid").to_numpy()
        tree = CoverTree.of_rows(zip(*(rows.column(c).to_pylist() for c in columns)), ids, m.decode(own.column("vec")), m, **options)
        found = [edge_table(ids[i], ids[j], d) for i, j, d in tree.self_query(eps)]
        return pa.concat_tables(found) if found else EDGE_NONE

    return trees.groupBy("part").cogroup(_by(p, part).groupBy("part")).applyInArrow(run, EDGE)


def tree_check(p: DataFrame, metric: str | Metric = "l2", sibling_only: bool = True, **options) -> DataFrame:
    """(invariant, violations) of one cover tree over all points."""
    m = resolve(metric)

    def run(t: pa.Table) -> pa.Table:
        t = t.sort_by("pid")
        bad = CoverTree(m.decode(t.column("vec")), m, **options).violations(sibling_only)
        return pa.table({"invariant": list(bad), "violations": pa.array(list(bad.values()), pa.int64())})

    return p.withColumn("one", F.lit(0)).groupBy("one").applyInArrow(run, "invariant string, violations long")


def tree_stats(p: DataFrame, eps: float, metric: str | Metric = "l2", **options) -> DataFrame:
    """(vertices, leaves, depth, bailed, build_distances, query_distances, self_query_distances, brute_distances) of a tree and its self query."""
    m = resolve(metric)

    def run(t: pa.Table) -> pa.Table:
        t = t.sort_by("pid")
        x = m.decode(t.column("vec"))
        m.evaluations = 0
        tree = CoverTree(x, m, **options)
        built, m.evaluations = m.evaluations, 0
        # in order of the leaves, points of a strip lie together and enter few vertices; what each measures is the same in any order
        order, _ = tree.numbered()
        for _ in Pace().strips(len(x), lambda lo, hi: tree.query(x[order[lo:hi]], eps)):
            pass
        asked, m.evaluations = m.evaluations, 0
        for _ in tree.self_query(eps):
            pass
        one = {"vertices": len(tree.centre), "leaves": sum(v is not None for v in tree.members), "depth": tree.depth(), "bailed": tree.bailed, "build_distances": built, "query_distances": asked, "self_query_distances": m.evaluations, "brute_distances": len(x) * len(x)}
        return pa.table({k: pa.array([v], pa.int64()) for k, v in one.items()})

    return p.withColumn("one", F.lit(0)).groupBy("one").applyInArrow(run, "vertices long, leaves long, depth long, bailed long, build_distances long, query_distances long, self_query_distances long, brute_distances long")


def build_tree_df(p: DataFrame, metric: str | Metric = "l2", leaf_size: int = 32, threshold: str = "radius", bailout: float = 0.25) -> DataFrame:
    """One cover tree over all points, a Spark job for each level: every open hub is a group, so hubs are split side by side.

    Rows (hub, parent, depth, pid, radius, size, is_leaf); a hub's id is the path of its centres. Points move with their hub
    and its distances; a hub of one level must fit a task, which only the first few levels of a large set put to the test."""
    m = resolve(metric)
    checkpoint_dir(p.sparkSession)
    root = centers(p, 1)
    if not root:
        return p.sparkSession.createDataFrame([], "hub string, parent string, depth int, pid long, radius double, size long, is_leaf boolean")
    kind = p.schema["vec"].dataType
    near = distances_to(p, root[0][1], m)
    open_ = p.join(near, "pid").select(F.lit(str(root[0][0])).alias("hub"), F.lit(root[0][0]).cast("long").alias("centre"), "pid", "vec", "dist").checkpoint()
    out, depth = None, 0

    def split(t: pa.Table) -> pa.Table:
        t = t.sort_by("pid")
        hub, centre = t.column("hub")[0].as_py(), t.column("centre")[0].as_py()
        pids, d = t.column("pid").to_numpy(), t.column("dist").to_numpy()
        cut = None
        if len(pids) > leaf_size and d.max() > 0:
            tree = CoverTree.__new__(CoverTree)
            tree.x, tree.metric, tree.leaf_size, tree.threshold, tree.bailout, tree.skip = m.decode(t.column("vec")), m, leaf_size, threshold, bailout, True
            top = float(d.max())
            tree.centre, tree.radius, tree.level = [int(np.flatnonzero(pids == centre)[0])], [top], [int(np.ceil(np.log2(top)))]
            cut = tree._split(0, np.arange(len(pids)), d)
        if cut is None:
            return t.append_column("child", pa.nulls(len(pids), pa.string())).append_column("next", pa.nulls(len(pids), pa.int64())).append_column("near", pa.nulls(len(pids), pa.float64())).select(names)
        child, nxt, new = np.empty(len(pids), object), np.zeros(len(pids), np.int64), np.zeros(len(pids))
        for c, own, dist in cut:
            child[own], nxt[own], new[own] = f"{hub}.{pids[c]}", pids[c], dist
        return t.append_column("child", pa.array(child, pa.string())).append_column("next", pa.array(nxt)).append_column("near", pa.array(new)).select(names)

    names = ["hub", "centre", "pid", "vec", "dist", "child", "next", "near"]
    schema = f"hub string, centre long, pid long, vec {kind.simpleString()}, dist double, child string, next long, near double"
    while True:
        done = open_.groupBy("hub").applyInArrow(split, schema).checkpoint()
        level = done.groupBy("hub", "centre").agg(F.max("dist").alias("radius"), F.count("*").alias("size"), F.first(F.col("child").isNull()).alias("is_leaf"))
        level = level.select("hub", F.when(F.col("hub").contains("."), F.regexp_extract("hub", r"^(.*)\.[^.]*$", 1)).alias("parent"), F.lit(depth).alias("depth"), F.col("centre").alias("pid"), "radius", "size", "is_leaf")
        out = level if out is None else out.unionByName(level)
        open_ = done.filter(F.col("child").isNotNull()).select(F.col("child").alias("hub"), F.col("next").alias("centre"), "pid", "vec", F.col("near").alias("dist")).checkpoint()
        depth += 1
        if open_.isEmpty():
            return out
