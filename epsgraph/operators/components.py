"""Connected components by alternating large-star and small-star steps, on DataFrames."""

from __future__ import annotations

import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def checkpoint_dir(spark: SparkSession) -> str:
    """The shared folder that the session names. Where none is, a local run gets one; on a cluster that is an error, as no
    machine's own folder is seen by the others."""
    sc = spark.sparkContext
    found = sc.getCheckpointDir() or sc.getConf().get("spark.checkpoint.dir")
    if not found:
        if not sc.master.startswith("local") or sc.master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        found = os.path.join(tempfile.gettempdir(), f"epsgraph-{uuid.uuid4().hex}")
    if not sc.getCheckpointDir():
        sc.setCheckpointDir(found)
    return found


def _state(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())


def connected_components(edges: DataFrame, src: str = "src", dst: str = "dst", max_rounds: int = 60) -> DataFrame:
    """(id, component) of every node that has an edge; component is the smallest id of it.

    Each step takes minima per node by a two-phase aggregate and joins them back, so a hub's edges are pre-aggregated and
    the join may be split by adaptive execution. Every round is cut off by a checkpoint in the shared folder."""
    checkpoint_dir(edges.sparkSession)
    e = edges.select(F.greatest(src, dst).alias("a"), F.least(src, dst).alias("b")).filter("a <> b").distinct().checkpoint()
    before = _state(e)
    for _ in range(max_rounds):
        both = e.unionByName(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m"))
        large = both.filter("b > a").join(low, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).filter("a <> b").distinct()
        low = large.groupBy("a").agg(F.min("b").alias("m"))
        # every node points at its smallest neighbour, and so do its other smaller neighbours
        small = large.join(low, "a").select(F.explode(F.array(F.struct(F.col("a").alias("a"), F.col("m").alias("b")), F.struct(F.col("b").alias("a"), F.col("m").alias("b")))).alias("s")).select("s.a", "s.b")
        e = small.filter("a <> b").distinct().checkpoint()
        now = _state(e)
        if now == before:
            break
        before = now
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    pointed = e.select(F.col("a").alias("id"), F.col("b").alias("component"))
    roots = pointed.select(F.col("component").alias("id"), "component").distinct()
    return pointed.unionByName(roots)
