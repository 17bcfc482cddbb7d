"""Edge lists as sinks and sources."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def write_edges(edges: DataFrame, path: str, parts: int, kind: str = "parquet") -> None:
    """Partitioned by a bucket of the source id, so that a vertex's edges are found by reading one part."""
    out = edges.withColumn("part", F.pmod("src", F.lit(parts)).cast("int"))
    out.repartition("part").sortWithinPartitions("src", "dst").write.partitionBy("part").format(kind).save(path)


def write_adjacency(edges: DataFrame, path: str) -> None:
    from ..operators.downstream import adjacency

    adjacency(edges).write.parquet(path)


class GridEdges(DataSource):
    """``format("lattice_edges")``: the unit-distance graph of a square lattice (option ``side``), made in parts: a test set of
    known answers at any size."""

    @classmethod
    def name(cls) -> str:
        return "lattice_edges"

    def schema(self) -> str:
        return "src long, dst long, dist double"

    def reader(self, schema):
        return GridReader(int(self.options.get("side", 4)), int(self.options.get("parts", 2)))


class GridReader(DataSourceReader):
    def __init__(self, side: int, parts: int):
        self.side, self.parts = side, parts

    def partitions(self):
        return [InputPartition(i) for i in range(self.parts)]

    def read(self, partition):
        for row in range(partition.value, self.side, self.parts):
            v = np.arange(row * self.side, (row + 1) * self.side)
            down = v if row + 1 < self.side else v[:0]
            src, dst = np.concatenate((v[:-1], down)), np.concatenate((v[1:], down + self.side))
            yield pa.record_batch({"src": src, "dst": dst, "dist": np.ones(len(src))})


def register(spark: SparkSession) -> None:
    spark.dataSource.register(GridEdges)
