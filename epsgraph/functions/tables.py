"""Table functions: the kernels for SQL users, one partition of a table at a time. Rows come and go in Arrow batches, so that
a task holds its partition's points and one strip of pairs."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.functions import arrow_udtf

from .metrics import Metric, metric
from .trees import CoverTree

#: Rows of an answer that go out at a time.
BATCH = 1 << 16


class _Held:
    def __init__(self):
        self.batches: list[pa.RecordBatch] = []

    def eval(self, rows: pa.RecordBatch) -> None:
        self.batches.append(rows.select(["pid", "vec"]))

    def block(self, name: str) -> tuple[Metric, np.ndarray, np.ndarray]:
        """(metric, pids, points); the batches are let go."""
        t = pa.Table.from_batches(self.batches)
        self.batches = []
        m = metric(name)
        return m, t.column("pid").to_numpy().astype(np.int64), m.decode(t.column("vec"))


@arrow_udtf(returnType="src: bigint, dst: bigint, dist: double")
class NearPairs(_Held):
    """near_pairs(TABLE(points (pid, vec)) PARTITION BY ..., eps): the pairs within each partition, Euclidean."""

    def eval(self, rows: pa.RecordBatch, eps: pa.Array) -> None:
        super().eval(rows)
        self.eps = eps[0].as_py()

    def terminate(self) -> Iterator[pa.Table]:
        if self.batches:
            m, pids, x = self.block("l2")
            for i, j, d in CoverTree(x, m).self_query(self.eps):
                for k in range(0, len(d), BATCH):
                    a, b, dist = pids[i[k : k + BATCH]], pids[j[k : k + BATCH]], d[k : k + BATCH]
                    apart = a != b
                    yield pa.table({"src": np.minimum(a, b)[apart], "dst": np.maximum(a, b)[apart], "dist": dist[apart]})


@arrow_udtf(returnType="vertices: int, depth: int, radius: double, size: bigint")
class TreeNodes(_Held):
    """tree_nodes(TABLE(points) PARTITION BY ...): the cover tree of each partition."""

    def terminate(self) -> Iterator[pa.Table]:
        if self.batches:
            m, _, x = self.block("l2")
            tree = CoverTree(x, m)
            yield pa.table({"vertices": pa.array([len(tree.centre)], pa.int32()), "depth": pa.array([tree.depth()], pa.int32()), "radius": [float(tree.radius[0])], "size": [len(x)]})


def register(spark: SparkSession) -> None:
    spark.udtf.register("near_pairs", NearPairs)
    spark.udtf.register("tree_nodes", TreeNodes)
