"""What near-neighbour graphs are built for."""

from __future__ import annotations

from itertools import count

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .components import checkpoint_dir, connected_components
from .points import symmetric


def components(edges: DataFrame, p: DataFrame) -> DataFrame:
    """(pid, component) of every point; an isolated point is its own component."""
    c = connected_components(edges)
    return p.select("pid").join(c, F.col("pid") == F.col("id"), "left").select("pid", F.coalesce("component", "pid").alias("component"))


def dbscan(edges: DataFrame, p: DataFrame, min_pts: int) -> DataFrame:
    """(pid, cluster, kind): cores have ``min_pts`` points in their ball, themselves included; a border point takes the smallest
    cluster of its cores; noise has none."""
    both = symmetric(edges)
    core = both.groupBy("src").agg(F.count("*").alias("n")).filter(F.col("n") + 1 >= min_pts).select(F.col("src").alias("core"))
    if min_pts <= 1:
        core = p.select(F.col("pid").alias("core"))
    inner = edges.join(core, F.col("src") == F.col("core"), "left_semi").join(core, F.col("dst") == F.col("core"), "left_semi")
    cores = components(inner, core.withColumnRenamed("core", "pid"))
    near = both.join(cores, F.col("dst") == F.col("pid")).groupBy("src").agg(F.min("component").alias("border"))
    all_ = p.select("pid").join(cores, "pid", "left").join(near, F.col("pid") == F.col("src"), "left")
    kind = F.when(F.col("component").isNotNull(), "core").when(F.col("border").isNotNull(), "border").otherwise("noise")
    return all_.select("pid", F.coalesce("component", "border").alias("cluster"), kind.alias("kind"))


def density(edges: DataFrame, p: DataFrame, eps: float, kernel: str = "flat") -> DataFrame:
    """(pid, density): kernel sums over the neighbours and the point itself."""
    k = {"flat": F.lit(1.0), "tri": 1 - F.col("dist") / eps, "gauss": F.exp(-0.5 * F.pow(F.col("dist") / eps, 2))}[kernel]
    s = symmetric(edges).groupBy("src").agg(F.sum(k).alias("s"))
    return p.select("pid").join(s, F.col("pid") == F.col("src"), "left").select("pid", (F.coalesce("s", F.lit(0.0)) + 1).alias("density"))


def _oriented(edges: DataFrame) -> DataFrame:
    """Each edge from its end of lower degree, so that no vertex has many out-edges."""
    d = symmetric(edges).groupBy("src").agg(F.count("*").alias("n"))
    e = edges.select("src", "dst").join(d.select(F.col("src").alias("src"), F.col("n").alias("ns")), "src").join(d.select(F.col("src").alias("dst"), F.col("n").alias("nd")), "dst")
    first = F.struct("ns", "src") < F.struct("nd", "dst")
    return e.select(F.when(first, F.col("src")).otherwise(F.col("dst")).alias("u"), F.when(first, F.col("dst")).otherwise(F.col("src")).alias("v"))


def triangles(edges: DataFrame) -> DataFrame:
    """(a, b, c) with a < b < c."""
    o = _oriented(edges)
    wedges = o.select("u", F.col("v").alias("x")).join(o.select("u", F.col("v").alias("y")), "u").filter("x < y")
    closed = wedges.join(edges.select(F.col("src").alias("x"), F.col("dst").alias("y")), ["x", "y"])
    s = F.array_sort(F.array("u", "x", "y"))
    return closed.select(s[0].alias("a"), s[1].alias("b"), s[2].alias("c"))


def rips(edges: DataFrame, p: DataFrame) -> DataFrame:
    """(vertices, edges, triangles, euler) of the 2-skeleton."""
    n, e, t = p.agg(F.count("*").alias("vertices")), edges.agg(F.count("*").alias("edges")), triangles(edges).agg(F.count("*").alias("triangles"))
    return n.crossJoin(e).crossJoin(t).withColumn("euler", F.col("vertices") - F.col("edges") + F.col("triangles"))


def local_clustering(edges: DataFrame, p: DataFrame) -> DataFrame:
    """(pid, triangles, clustering): closed part of the pairs of neighbours; 0 below two neighbours."""
    t = triangles(edges).select(F.explode(F.array("a", "b", "c")).alias("pid")).groupBy("pid").agg(F.count("*").alias("t"))
    d = symmetric(edges).groupBy(F.col("src").alias("pid")).agg(F.count("*").alias("k"))
    r = p.select("pid").join(d, "pid", "left").join(t, "pid", "left")
    t0 = F.coalesce("t", F.lit(0))
    return r.select("pid", t0.alias("triangles"), F.when(F.col("k") > 1, 2 * t0 / (F.col("k") * (F.col("k") - 1))).otherwise(0.0).alias("clustering"))


def geodesics(edges: DataFrame, sources: list[int], max_hops: int | None = None) -> DataFrame:
    """(source, pid, dist): shortest path lengths, by relaxing frontiers until none gets shorter; refuses to stop at ``max_hops``."""
    spark = edges.sparkSession
    checkpoint_dir(spark)
    both = symmetric(edges).select("src", "dst", "dist").checkpoint()
    best = spark.createDataFrame([(s, s, 0.0) for s in sources], "source long, pid long, d double").checkpoint()
    front = best
    for hop in count():
        if hop == max_hops:
            raise RuntimeError(f"paths did not settle in {max_hops} hops")
        reach = front.join(both, F.col("pid") == F.col("src")).select("source", F.col("dst").alias("pid"), (F.col("d") + F.col("dist")).alias("n")).groupBy("source", "pid").agg(F.min("n").alias("n"))
        both_ = best.join(reach, ["source", "pid"], "full")
        shorter = F.col("d").isNull() | (F.col("n") < F.col("d") - 1e-12)
        now = both_.select("source", "pid", F.when(shorter & F.col("n").isNotNull(), F.col("n")).otherwise(F.col("d")).alias("d"), (shorter & F.col("n").isNotNull()).alias("new")).checkpoint()
        best, front = now.select("source", "pid", "d"), now.filter("new").select("source", "pid", "d")
        if front.isEmpty():
            break
    return best.withColumnRenamed("d", "dist")


def knn_in_graph(edges: DataFrame, k: int) -> DataFrame:
    """(src, rank, dst, dist): the k nearest among the neighbours; a point's true k nearest where it has k neighbours."""
    w = Window.partitionBy("src").orderBy("dist", "dst")
    return symmetric(edges).withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k).select("src", "rank", "dst", "dist")


def mutual_knn(edges: DataFrame, k: int) -> DataFrame:
    a = knn_in_graph(edges, k)
    b = a.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
    return a.filter("src < dst").select("src", "dst", "dist").join(b, ["src", "dst"], "left_semi")


def fuzzy_weights(edges: DataFrame, k: int) -> DataFrame:
    """(src, dst, weight): exponential membership of each k-nearest edge beyond the nearest distance, scaled by the k-th,
    joined over both directions by the probabilistic sum."""
    n = knn_in_graph(edges, k)
    w = Window.partitionBy("src")
    near, far = F.min("dist").over(w), F.max("dist").over(w)
    m = n.select("src", "dst", F.exp(-(F.col("dist") - near) / F.greatest(far - near, F.lit(1e-12))).alias("m"))
    both = m.unionByName(m.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "m")).filter("src < dst")
    p = both.groupBy("src", "dst").agg(F.sum("m").alias("s"), F.product("m").alias("t"), F.count("*").alias("n"))
    return p.select("src", "dst", F.when(F.col("n") == 2, F.col("s") - F.col("t")).otherwise(F.col("s")).alias("weight"))


def adjacency(edges: DataFrame) -> DataFrame:
    """(pid, neighbours): sorted arrays of (dst, dist)."""
    return symmetric(edges).groupBy(F.col("src").alias("pid")).agg(F.array_sort(F.collect_list(F.struct("dst", "dist"))).alias("neighbours"))


def laplacian(edges: DataFrame, p: DataFrame) -> DataFrame:
    """(src, dst, value) of the normalised adjacency matrix: 1 / sqrt(product of the degrees)."""
    d = symmetric(edges).groupBy("src").agg(F.count("*").alias("n"))
    e = symmetric(edges).join(d.withColumnRenamed("n", "ns"), "src").join(d.select(F.col("src").alias("dst"), F.col("n").alias("nd")), "dst")
    return e.select("src", "dst", (1 / F.sqrt(F.col("ns") * F.col("nd"))).alias("value"))


def power_iteration(m: DataFrame, p: DataFrame, steps: int = 20) -> DataFrame:
    """(pid, value): the leading vector of a symmetric matrix of rows (src, dst, value)."""
    checkpoint_dir(p.sparkSession)
    v = p.select("pid", F.lit(1.0).alias("value"))
    m = m.withColumnRenamed("value", "w").checkpoint()
    for _ in range(steps):
        v = m.join(v, F.col("dst") == F.col("pid")).groupBy(F.col("src").alias("pid")).agg(F.sum(F.col("w") * F.col("value")).alias("value"))
        norm = v.agg(F.sqrt(F.sum(F.col("value") * F.col("value"))).alias("norm"))
        v = v.crossJoin(F.broadcast(norm)).select("pid", (F.col("value") / F.col("norm")).alias("value")).checkpoint()
    return v


def mcl_step(m: DataFrame, inflation: float = 2.0, keep: int | None = None) -> DataFrame:
    """One expand / inflate / prune step on a column-stochastic matrix (src, dst, value)."""
    sq = m.alias("a").join(m.alias("b"), F.col("a.dst") == F.col("b.src")).groupBy(F.col("a.src").alias("src"), F.col("b.dst").alias("dst")).agg(F.sum(F.col("a.value") * F.col("b.value")).alias("value"))
    return inflated(sq, inflation, keep)


def inflated(sq: DataFrame, inflation: float, keep: int | None) -> DataFrame:
    """Powers of the entries, the ``keep`` strongest of each column, its sum one again."""
    grown = sq.select("src", "dst", F.pow("value", F.lit(inflation)).alias("value"))
    if keep:
        w = Window.partitionBy("dst").orderBy(F.desc(F.round("value", 12)), "src")  # sums of any order rank alike
        grown = grown.withColumn("r", F.row_number().over(w)).filter(F.col("r") <= keep).drop("r")
    total = grown.groupBy("dst").agg(F.sum("value").alias("total"))
    return grown.join(total, "dst").select("src", "dst", (F.col("value") / F.col("total")).alias("value"))


def flow_matrix(edges: DataFrame, p: DataFrame) -> DataFrame:
    """Self loops and edges, each column summing to one."""
    whole = symmetric(edges).select("src", "dst").unionByName(p.select(F.col("pid").alias("src"), F.col("pid").alias("dst")))
    n = whole.groupBy("dst").agg(F.count("*").alias("n"))
    return whole.join(n, "dst").select("src", "dst", (1 / F.col("n")).alias("value"))


def mcl(edges: DataFrame, p: DataFrame, inflation: float = 2.0, steps: int = 8, keep: int = 50, least: float = 1e-4) -> DataFrame:
    """(pid, cluster): flow clusters, each point going to the smallest of its strongest attractors."""
    checkpoint_dir(p.sparkSession)
    m = flow_matrix(edges, p)
    for _ in range(steps):
        m = mcl_step(m, inflation, keep).filter(F.col("value") >= least).checkpoint()
    best = m.groupBy(F.col("dst").alias("pid")).agg(F.min_by("src", F.struct(-F.round("value", 6), F.col("src"))).alias("cluster"))
    return best.select("pid", "cluster")


def label_vote(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """(pid, label, vote, agree): the commonest label of the labelled neighbours (smallest on ties) beside the point's own."""
    v = symmetric(edges).join(labels.select(F.col("pid").alias("dst"), F.col("label").alias("l")), "dst").groupBy("src", "l").agg(F.count("*").alias("n"))
    top = v.groupBy("src").agg(F.min_by("l", F.struct(-F.col("n"), F.col("l"))).alias("vote"))
    return labels.join(top, F.col("pid") == F.col("src")).select("pid", "label", "vote", (F.col("label") == F.col("vote")).alias("agree"))


def keep_representatives(edges: DataFrame, p: DataFrame) -> DataFrame:
    """The points that are the smallest of their component."""
    return components(edges, p).filter("pid = component").select("pid")
