"""Exact top-k by inner product without random access.

Every candidate block holds one sorted list per dimension. Lists are read from the end that suits the sign of the query's
weight, all to the same depth; each row has a lower and an upper bound from what has been read (unread entries lie between
the list's last entry and its frontier). A query reads on while a row outside its best k may still qualify; then the
scores of the best are resolved. Reading is block-synchronous: the bounds of all queries of a tile are four matrix products;
a query that few rows are left for goes on with those alone. How deep lists are read depends on the data: on 64 independent
dimensions more than nine tenths, on vectors in clusters less (``nra`` tells).

Queries meet candidates in a grid of (query block, candidate block) cells of bounded size, so nothing that grows is
broadcast; the k best of each cell are merged by one window per query.

Defined results: rows with a null id, a null vector, or null or non-finite components take no part; vectors of another
length than the query's are no candidates of it; a row whose id equals the query's is never its own answer; ties go to
the smaller id; a query without candidates returns no row; repeated candidate rows are repeated answers.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import table

OUT = "query_id long, vec_id long, score long"


def quantise(vec: Column, scale: int) -> Column:
    return F.transform(vec, lambda x: F.floor(F.lit(float(scale)) * x.cast("double")).cast("long"))


def usable(vec: Column) -> Column:
    return vec.isNotNull() & F.forall(vec, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x.cast("double")) < float("inf")))


def nra(x: np.ndarray, ids: np.ndarray, q: np.ndarray, qids: np.ndarray, k: int, steps: int = 32, few: int = 16) -> tuple[np.ndarray, ...]:
    """(query position, row position, score, depth) of each query's k best rows; all values are integers below 2**53 in
    doubles. Depth is the part of each list that was read when no outsider could qualify any more.

    Lists are read in ``steps`` equal parts. All queries of the tile go on together, every fourth part first and less at a time
    later, while more than one row in ``few`` may qualify; then each query goes on alone with its few rows, part by part."""
    n, _ = x.shape
    order = np.argsort(x, axis=0, kind="stable")
    lists = np.take_along_axis(x, order, axis=0)
    rank = np.empty(order.shape, np.int32)
    np.put_along_axis(rank, order, np.arange(n, dtype=np.int32)[:, None], axis=0)
    del order
    up, down = np.maximum(q, 0.0), np.minimum(q, 0.0)

    def bounds(rows: np.ndarray | slice, t: int, p: np.ndarray, m: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Upper and lower bounds of rows when t entries of each list are read: an unread entry lies between its list's
        frontier and its last entry. Positive weights read from the top, negative ones from the bottom."""
        v, r = x[rows], rank[rows]
        high, low = r >= n - t, r < t
        return (
            np.where(high, v, lists[n - t]) @ p.T + np.where(low, v, lists[t - 1]) @ m.T,
            np.where(high, v, lists[0]) @ p.T + np.where(low, v, lists[n - 1]) @ m.T,
        )

    at = lambda step: min(n, max(1, -(-n * step // steps)))
    alive, out = np.arange(len(q)), []

    def resolved(j: int, rows: np.ndarray, t: int) -> None:
        score = x[rows] @ q[j]
        best = np.lexsort((ids[rows], -score))[:k]
        out.append((np.full(len(best), j), rows[best], score[best], np.full(len(best), t / n)))

    def alone(j: int, rows: np.ndarray, kth: float, step: int) -> None:
        t = at(step)
        while len(rows) > k and t < n:
            step += 1
            t = at(step)
            upper, lower = bounds(rows, t, up[j], down[j])
            kth = max(kth, np.partition(lower, len(rows) - k)[len(rows) - k])
            rows = rows[upper >= kth]
        resolved(j, rows, t)

    step = 0
    while len(alive):
        step = min(steps, step + max(1, min(steps // 4, (steps - step) // 3)))
        t = at(step)
        upper, lower = bounds(slice(None), t, up[alive], down[alive])
        own = ids[:, None] == qids[alive][None, :]
        lower[own] = -np.inf
        kth = np.partition(lower, n - k, axis=0)[n - k] if n > k else np.full(len(alive), -np.inf)
        rest = (upper >= kth[None, :]) & ~own
        done = (rest.sum(0) <= max(k, n // few)) | (t == n)
        for j in np.flatnonzero(done):
            alone(int(alive[j]), np.flatnonzero(rest[:, j]), kth[j], step)
        alive = alive[~done]
    return tuple(np.concatenate(c) for c in zip(*out)) if out else tuple(np.empty(0, int) for _ in range(4))


def _matrix(t: pa.Table) -> np.ndarray:
    col = t.column("v").combine_chunks()
    return col.flatten().to_numpy(zero_copy_only=False).astype(float).reshape(len(col), -1)


def nra_topk(queries: DataFrame, candidates: DataFrame, k: int = 10, id_col: str = "vec_id", vec_col: str = "embedding", scale: int = 1024, block_rows: int = 4096, tile: int = 256) -> DataFrame:
    """query_id, rank, vec_id, score. Sizes are counted first (one scan of each side) to lay out the grid."""

    def ready(df: DataFrame) -> DataFrame:
        df = df.select(F.col(id_col).cast("long").alias("id"), F.col(vec_col).alias("v0"))
        return df.filter(F.col("id").isNotNull() & usable(F.col("v0"))).select("id", quantise(F.col("v0"), scale).alias("v"), F.size("v0").alias("dim"))

    a, b = ready(queries), ready(candidates)
    nq, nc = a.count(), b.count()
    gq, gc = max(1, -(-nq // block_rows)), max(1, -(-nc // block_rows))
    spread = lambda g: F.pmod(F.xxhash64("id"), F.lit(g)).cast("int")
    each = lambda g: F.explode(F.sequence(F.lit(0), F.lit(g - 1)))
    left = a.withColumn("gq", spread(gq)).withColumn("gc", each(gc))
    right = b.withColumn("gc", spread(gc)).withColumn("gq", each(gq))

    def cell(qs: pa.Table, cs: pa.Table) -> pa.Table:
        found = []
        if qs.num_rows and cs.num_rows:
            qm, qi, cm, ci = _matrix(qs), qs.column("id").to_numpy(), _matrix(cs), cs.column("id").to_numpy()
            for c0 in range(0, len(ci), block_rows):
                rows = slice(c0, c0 + block_rows)
                for q0 in range(0, len(qi), tile):
                    part = slice(q0, q0 + tile)
                    i, r, s, _ = nra(cm[rows], ci[rows], qm[part], qi[part], k)
                    found.append((qi[part][i], ci[rows][r], s.astype(np.int64)))
        cols = [np.concatenate(c).astype(np.int64) for c in zip(*found)] if found else [np.empty(0, np.int64)] * 3
        return pa.table(dict(zip(("query_id", "vec_id", "score"), cols)))

    keys = ("dim", "gq", "gc")
    near = left.groupBy(*keys).cogroup(right.groupBy(*keys)).applyInArrow(cell, OUT)
    w = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return near.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op7_exact_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = table(spark, sf_dir, "embeddings", "vec_id", "embedding")
    return nra_topk(vectors.filter(F.col("vec_id") % 100 == 0), vectors)


OP7_SQL = """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(1024 * CAST(x AS DOUBLE)) AS DOUBLE)) AS e FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL
    AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT q.vec_id AS query_id, c.vec_id, CAST(list_dot_product(q.e, c.e) AS BIGINT) AS score
  FROM v q JOIN v c ON q.vec_id % 100 = 0 AND c.vec_id <> q.vec_id),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s)
SELECT query_id, CAST(rank AS INTEGER) AS rank, vec_id, score FROM r WHERE rank <= 10
"""
