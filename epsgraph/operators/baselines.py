"""The principal-component-sorted search, and graphs over collapsed duplicates."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.metrics import Metric, matrix, resolve, slack
from .landmark import cell_kernel
from .points import EDGE, collapse, expand

MOST_ROWS, LEAST_BLOCKS = 16_384, 8


def principal_axis(p: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """(mean, first principal component), from one pass of partial moment sums (d * d numbers a partition)."""

    def moments(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, total, outer = 0, 0.0, 0.0
        for b in batches:
            x = matrix(b.column(0))
            n, total, outer = n + len(x), total + x.sum(0), outer + x.T @ x
        if n:
            d = len(total)
            keys = np.arange(d * d + d + 1)
            yield pa.record_batch({"k": keys, "v": np.concatenate((np.ravel(outer), total, [n]))})

    sums = dict(p.select(F.col("vec").cast("array<double>")).mapInArrow(moments, "k long, v double").groupBy("k").agg(F.sum("v")).collect())
    flat = np.array([sums[k] for k in sorted(sums)])
    if not len(flat):
        return np.zeros(1), np.ones(1)
    d = int((-1 + np.sqrt(4 * len(flat) - 3)) / 2)
    n, mean = flat[-1], flat[d * d : -1] / flat[-1]
    cov = flat[: d * d].reshape(d, d) / n - np.outer(mean, mean)
    axis = np.linalg.eigh(cov)[1][:, -1]
    return mean, axis if axis[np.abs(axis).argmax()] > 0 else -axis


def pca_sort_graph(p: DataFrame, eps: float, how: str = "blocks", n: int | None = None) -> DataFrame:
    """Euclidean only: pairs whose projections on the first principal component differ by eps at most, then measured.

    "blocks" cuts the order of projections into ``n`` blocks (as many as keep each to about ``MOST_ROWS`` points), each a task past
    which the blocks within eps of it stream, every pair of blocks in one of its two tasks; "local" is the sequential form, one block."""
    mean, axis = principal_axis(p)
    m = resolve("l2")
    vec = p.select("pid", F.col("vec").cast("array<double>").alias("vec"))
    options = {"axis": axis, "mean": mean}
    if how == "local":
        whole = vec.select("pid", "vec", *(F.lit(0).alias(c) for c in ("home", "cell", "role", "part")), F.lit(True).alias("whole"))
        return whole.repartition(1).mapInArrow(cell_kernel(m, eps, "sorted", options, True), EDGE)

    def along(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(((matrix(b.column(1)) - mean) * axis).sum(1))], ["pid", "vec", "at"])

    q = vec.mapInArrow(along, "pid long, vec array<double>, at double")
    n = n or max(LEAST_BLOCKS, -(-p.count() // MOST_ROWS))
    cuts = q.select(F.percentile_approx("at", [k / n for k in range(1, n)], 100 * n)).first()[0] or []
    q = q.withColumn("home", F.size(F.filter(F.array(*map(F.lit, cuts)), lambda c: c < F.col("at")))) if cuts else q.withColumn("home", F.lit(0))
    ends = {r.home: r for r in q.groupBy("home").agg(F.min("at").alias("lo"), F.max("at").alias("hi")).collect()}
    if not ends:
        return p.sparkSession.createDataFrame([], EDGE)
    room = eps + 1e-9 * (eps + max(max(abs(r.lo), abs(r.hi)) for r in ends.values())) + 1e-12
    # blocks lie in order, so those within eps of one are neighbours; of a pair the lower one is home where their numbers are both even or both odd
    near = {h: [k for k in ends if min(ends[k].hi, r.hi) + room >= max(ends[k].lo, r.lo)] for h, r in ends.items()}
    first, last = (F.element_at(F.array(*(F.lit(f(near.get(h, [h]))) for h in range(n))), F.col("home") + 1) for f in (min, max))
    host = lambda k: F.when((k + F.col("home")) % 2 == 0, F.least(k, F.col("home"))).otherwise(F.greatest(k, F.col("home")))
    rows = q.withColumn("part", F.explode(F.filter(F.sequence(first, last), lambda k: host(k) == k)))
    rows = rows.select("pid", "vec", "home", F.col("part").alias("cell"), (F.col("part") != F.col("home")).cast("int").alias("role"), "part", F.lit(True).alias("whole"))
    return rows.repartitionById(n, "part").sortWithinPartitions("part", "role", "pid").mapInArrow(cell_kernel(m, eps, "sorted", options, True), EDGE)


def over_distinct(p: DataFrame, build, expanded: bool = True, keep: bool = False) -> tuple[DataFrame, DataFrame]:
    """(edges, groups): ``build`` runs over distinct payloads; edges are between members, or between representatives. ``keep`` holds the
    groups on disk, as they are read several times."""
    groups = collapse(p).persist(StorageLevel.DISK_ONLY) if keep else collapse(p)
    edges = build(groups.select(F.col("rep").alias("pid"), "vec"))
    return (expand(edges, groups) if expanded else edges), groups


def weighted_degrees(edges: DataFrame, groups: DataFrame) -> DataFrame:
    """(pid, degree) of every point, from edges between representatives: cliques of copies are never written out."""
    size = groups.select(F.col("rep").alias("id"), F.size("members").cast("long").alias("size"))
    both = edges.select("src", "dst").unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
    near = both.join(size, F.col("dst") == F.col("id")).groupBy("src").agg(F.sum("size").alias("near"))
    rows = groups.join(near, F.col("rep") == F.col("src"), "left")
    return rows.select(F.explode("members").alias("pid"), (F.coalesce("near", F.lit(0)) + F.size("members") - 1).alias("degree"))


def check_metric(p: DataFrame, metric: str | Metric, samples: int = 40, seed: int = 0) -> DataFrame:
    """(axiom, violations) over all triples of a hash sample of bounded size."""
    m = resolve(metric)
    some = p.orderBy(F.xxhash64("pid", F.lit(seed)), "pid").limit(samples)

    def run(t: pa.Table) -> pa.Table:
        x = m.decode(t.column("vec"))
        d = m.table(x, x)
        tiny = 1e-7 * max(1.0, float(np.abs(d).max()))
        same = {"non_negative": int((d < -tiny).sum()), "identity": int((np.abs(np.diag(d)) > tiny).sum()), "symmetry": int((np.abs(d - d.T) > tiny).sum() // 2), "triangle": int((d[:, None, :] > d[:, :, None] + d[None, :, :] + tiny).sum())}
        return pa.table({"axiom": list(same), "violations": list(same.values())})

    return some.withColumn("one", F.lit(0)).groupBy("one").applyInArrow(run, "axiom string, violations long")


def lsh_pairs(p: DataFrame, eps: float, tables: int = 4, width: float | None = None, seed: int = 0) -> DataFrame:
    """Pairs at most eps apart (l2) that share a bucket of a random projection in one of ``tables``: a contrast to the exact methods,
    which loses pairs but reports none too many."""
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector

    v = p.select("pid", array_to_vector(F.col("vec").cast("array<double>")).alias("vec"))
    model = BucketedRandomProjectionLSH(inputCol="vec", outputCol="buckets", bucketLength=width or 4 * eps, numHashTables=tables, seed=seed).fit(v)
    pairs = model.approxSimilarityJoin(v, v, slack(eps), "dist")
    return pairs.select(F.col("datasetA.pid").alias("src"), F.col("datasetB.pid").alias("dst"), "dist").filter((F.col("src") < F.col("dst")) & (F.col("dist") <= eps))


def recall(found: DataFrame, exact: DataFrame) -> DataFrame:
    """(exact, found, extra, recall): how many of the exact pairs were found, and how many pairs are none."""
    a, b = found.select("src", "dst", F.lit(1).alias("f")), exact.select("src", "dst", F.lit(1).alias("e"))
    n = a.join(b, ["src", "dst"], "full").agg(F.count("e").alias("exact"), F.count_if(F.col("f").isNotNull() & F.col("e").isNotNull()).alias("found"), F.count_if(F.col("e").isNull()).alias("extra"))
    return n.withColumn("recall", F.when(F.col("exact") > 0, F.col("found") / F.col("exact")).otherwise(1.0))
