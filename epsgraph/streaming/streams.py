"""Streams over the events table, run until what is there is read (availableNow), and their batch answers."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions.metrics import Metric, resolve
from ..functions.trees import CoverTree
from ..operators.components import checkpoint_dir
from ..operators.landmark import assign, centers, decoded_centres
from ..operators.points import points as to_points
from ..workloads import SETS, read


def events(spark: SparkSession, d: str) -> DataFrame:
    """The table as a file stream, event time as a timestamp."""
    schema = spark.read.parquet(f"{d}/events.parquet").schema
    files = spark.readStream.schema(schema).option("pathGlobFilter", "events*.parquet").option("recursiveFileLookup", True).parquet(d)
    return files.withColumn("ts", F.col("ts").cast("timestamp"))


def drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Runs the stream on what is there; its rows as a table of the shared folder (the last batch's, in complete mode)."""
    spark = stream.sparkSession
    path = f"{checkpoint_dir(spark)}/stream-{uuid.uuid4().hex}"

    def put(batch: DataFrame, n: int) -> None:
        if mode == "append":
            batch.write.mode("append").parquet(f"{path}/out")
        else:
            batch.write.mode("overwrite").parquet(f"{path}/out")

    stream.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{path}/out")


def tumbling(spark: SparkSession, d: str) -> DataFrame:
    e = events(spark, d).withWatermark("ts", "1 hour")
    w = e.groupBy(F.window("ts", "1 day"), "event_type").agg(F.count("*").alias("n"))
    return drained(w.select(F.unix_timestamp("window.start").alias("start"), "event_type", "n"), "complete")


def sliding(spark: SparkSession, d: str) -> DataFrame:
    e = events(spark, d).withWatermark("ts", "1 hour")
    w = e.groupBy(F.window("ts", "6 hours", "1 hour")).agg(F.count("*").alias("n"))
    return drained(w.select(F.unix_timestamp("window.start").alias("start"), "n"), "complete")


def sessions(spark: SparkSession, d: str) -> DataFrame:
    e = events(spark, d).withWatermark("ts", "1 hour")
    w = e.groupBy(F.session_window("ts", "1 day"), "user_id").agg(F.count("*").alias("n"))
    return drained(w.select("user_id", F.unix_timestamp("session_window.start").alias("start"), "n"), "complete")


def deduplicated(spark: SparkSession, d: str) -> DataFrame:
    e = events(spark, d).withWatermark("ts", "1 hour")
    return drained(e.dropDuplicates(["event_id"]).select("event_id", "user_id"))


def static_nearest(spark: SparkSession, d: str, width: float = 50.0) -> DataFrame:
    """Each arriving event by the nearest of a few fixed centres of ``value`` (the smaller on ties): map only."""
    centres = F.array(*[F.lit(width * k) for k in range(10)])
    near = F.array_min(F.transform(centres, lambda c: F.struct(F.abs(F.col("value") - c).alias("d"), c.alias("c"))))
    return drained(events(spark, d).select("event_id", near["c"].alias("centre")))


def interval_join(spark: SparkSession, d: str) -> DataFrame:
    """Clicks followed within an hour by a purchase of the same user: a stream-stream join with bounded state."""
    c = events(spark, d).filter("event_type = 'click'").select(F.col("user_id").alias("u"), F.col("event_id").alias("click"), F.col("ts").alias("t")).withWatermark("t", "1 hour")
    p = events(spark, d).filter("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase"), "ts").withWatermark("ts", "1 hour")
    hit = c.join(p, F.expr("u = user_id AND ts >= t AND ts <= t + INTERVAL 1 HOUR"))
    return drained(hit.select("click", "purchase"))


EDGE_TYPES = {"src": "int64", "dst": "int64", "dist": "float64"}


def _close(q: np.ndarray, x: np.ndarray, eps: float, most: int = 1 << 20) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(positions in q, positions in x) of numbers at most eps apart, by search in the sorted x, about ``most`` pairs at a time."""
    order = np.argsort(x, kind="stable")
    room = eps * (1 + 1e-9) + 1e-12
    lo, hi = np.searchsorted(x[order], q - room), np.searchsorted(x[order], q + room, "right")
    ends = np.cumsum(hi - lo)
    at = 0
    while at < len(q):
        done = ends[at - 1] if at else 0
        to = max(at + 1, int(np.searchsorted(ends, done + most, "right")))
        n = (hi - lo)[at:to]
        i = np.repeat(np.arange(at, to), n)
        j = order[np.arange(len(i)) - np.repeat(np.cumsum(n) - n, n) + np.repeat(lo[at:to], n)]
        ok = np.abs(q[i] - x[j]) <= eps
        yield i[ok], j[ok]
        at = to


def _frame(p: np.ndarray, q: np.ndarray, d: np.ndarray) -> pd.DataFrame:
    return pd.DataFrame({"src": np.minimum(p, q), "dst": np.maximum(p, q), "dist": d}).astype(EDGE_TYPES)


def graph(stream: DataFrame, eps: float, width: float = 1.0) -> DataFrame:
    """(src, dst, dist) of the pairs of a one-dimensional point stream (pid, x) at most eps apart, each once, in the batch of
    its later point. Cells are intervals of ``width`` times eps; a point is kept in its own cell and looks up the cells that its ball
    reaches, so the newer point finds the older whatever their order. State is one list a cell."""
    step = eps * width
    cell = F.floor(F.col("x") / step)
    reach = F.sequence(F.floor((F.col("x") - eps * (1 + 1e-9)) / step), F.floor((F.col("x") + eps * (1 + 1e-9)) / step))
    routed = stream.select("pid", "x", cell.alias("home"), F.explode(reach).alias("cell"))

    def step_(key, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        old_p, old_x = map(list, state.get) if state.exists else ([], [])
        known = len(old_p)
        come = pd.concat(list(parts)).sort_values("pid")
        mine = come[come.home == key[0]]
        old_p += mine.pid.tolist()
        old_x += mine.x.tolist()
        state.update((old_p, old_x))
        p, x, pids, xs = np.array(old_p, np.int64), np.array(old_x, float), come.pid.to_numpy(), come.x.to_numpy()
        for i, j in _close(xs, x, eps):
            new = (j < known) | (p[j] < pids[i])
            yield _frame(pids[i[new]], p[j[new]], np.abs(xs[i[new]] - x[j[new]]))

    return routed.groupBy("cell").applyInPandasWithState(step_, "src long, dst long, dist double", "p array<long>, x array<double>", "append", GroupStateTimeout.NoTimeout)


def metric_graph(stream: DataFrame, centres: list[tuple[int, object]], eps: float, metric: str | Metric = "l2") -> DataFrame:
    """As ``graph``, for points (pid, vec) of any metric and fixed centres (``landmark.centers`` of a batch of past points): an
    arriving point is kept in its nearest centre's cell and looks up every cell that the bisector test leaves open. State is one
    list of points a cell, so centres should be as many as keep cells to what a task can hold."""
    m, kind = resolve(metric), stream.schema["vec"].dataType
    near = assign(stream, centres, m, eps)
    routed = near.select("pid", "vec", "home", F.explode(F.concat(F.array("home"), "cells")).alias("cell"))

    def step_(key, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        old_p, old_x = map(list, state.get) if state.exists else ([], [])
        known = len(old_p)
        come = pd.concat(list(parts)).sort_values("pid")
        mine = come[come.home == key[0]]
        old_p += mine.pid.tolist()
        old_x += [v.tolist() if isinstance(v, np.ndarray) else v for v in mine.vec]
        if not old_p:
            return
        state.update((old_p, old_x))
        p, pids = np.array(old_p, np.int64), come.pid.to_numpy()
        tree = CoverTree(decoded_centres(old_x, m, kind), m)
        q = decoded_centres(come.vec.tolist(), m, kind)
        for at in range(0, len(q), 4096):
            i, j, d = tree.query(q[at : at + 4096], eps)
            new = (j < known) | (p[j] < pids[i + at])
            yield _frame(pids[i[new] + at], p[j[new]], d[new])

    return routed.groupBy("cell").applyInPandasWithState(step_, "src long, dst long, dist double", f"p array<long>, x array<{kind.simpleString()}>", "append", GroupStateTimeout.NoTimeout)


def timed_graph(stream: DataFrame, eps: float, seconds: float) -> DataFrame:
    """As ``graph``, for pairs at most eps apart and at most ``seconds`` apart in event time; ``stream`` is (pid, x, ts) with a
    watermark. Rows behind the watermark are late and dropped; stored points go once no row in time can reach them."""
    reach = F.sequence(F.floor((F.col("x") - eps * (1 + 1e-9)) / eps), F.floor((F.col("x") + eps * (1 + 1e-9)) / eps))
    routed = stream.select("pid", "x", "ts", F.floor(F.col("x") / eps).alias("home"), F.explode(reach).alias("cell"))

    def step_(key, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        held = [list(v) for v in state.get] if state.exists else [[], [], []]
        mark = state.getCurrentWatermarkMs() / 1000
        found = []
        if not state.hasTimedOut:
            come = pd.concat(list(parts))
            come = come.assign(t=come.ts.astype("int64") / (1e9 if come.ts.dtype.str.endswith("[ns]") else 1e6)).sort_values("pid")
            come = come[come.t >= mark]
            mine = come[come.home == key[0]]
            known = len(held[0])
            for into, name in zip(held, ("pid", "x", "t")):
                into += mine[name].tolist()
            p, x, t = np.array(held[0], np.int64), np.array(held[1], float), np.array(held[2], float)
            pids, xs, ts = (come[c].to_numpy() for c in ("pid", "x", "t"))
            for i, j in _close(xs, x, eps):
                new = ((j < known) | (p[j] < pids[i])) & (np.abs(ts[i] - t[j]) <= seconds)
                found.append(_frame(pids[i[new]], p[j[new]], np.abs(xs[i[new]] - x[j[new]])))
        keep = [i for i, t in enumerate(held[2]) if t >= mark - seconds]
        held = [[v[i] for i in keep] for v in held]
        if keep:
            state.update(tuple(held))
            state.setTimeoutTimestamp(int((max(min(held[2]), mark) + seconds) * 1000) + 1)
        elif state.exists:
            state.remove()
        yield from found

    return routed.groupBy("cell").applyInPandasWithState(step_, "src long, dst long, dist double", "p array<long>, x array<double>, t array<double>", "append", GroupStateTimeout.EventTimeTimeout)


def value_graph_timed(spark: SparkSession, d: str) -> DataFrame:
    points = events(spark, d).withWatermark("ts", "1 hour").select(F.col("event_id").alias("pid"), F.col("value").alias("x"), "ts")
    return drained(timed_graph(points, 0.5, 86400)).select("src", "dst", F.round("dist", 6).alias("dist"))


def value_graph(spark: SparkSession, d: str) -> DataFrame:
    points = events(spark, d).select(F.col("event_id").alias("pid"), F.col("value").alias("x"))
    return drained(graph(points, 0.05)).select("src", "dst", F.round("dist", 6).alias("dist"))


def embedding_graph(spark: SparkSession, d: str) -> DataFrame:
    """The graph of the first four components of embeddings as they arrive, over the centres of 16 of them."""
    points = SETS["e4"]
    cs = centers(points.build(spark, d), 16)
    table = spark.read.parquet(f"{d}/embeddings.parquet")
    come = spark.readStream.schema(table.schema).option("recursiveFileLookup", True).option("maxFilesPerTrigger", 4).parquet(f"{d}/embeddings.parquet*")
    vec = F.slice(F.col("embedding").cast("array<double>"), 1, 4)
    return drained(metric_graph(to_points(come, "vec_id", vec), cs, 0.141)).select("src", "dst", F.round("dist", 6).alias("dist"))


QUERIES: dict[str, tuple[Callable, str | None]] = {
    "stream_tumbling": (tumbling, "SELECT CAST(epoch(date_trunc('day', ts)) AS BIGINT) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2"),
    "stream_sliding": (sliding, "SELECT CAST(h AS BIGINT) AS start, count(*) AS n FROM (SELECT unnest(list_transform(range(6), lambda k: CAST(floor(epoch(ts) / 3600) AS BIGINT) * 3600 - k * 3600)) AS h FROM events) GROUP BY h"),
    "stream_session": (sessions, "WITH g AS (SELECT user_id, ts, event_id, CASE WHEN lag(ts) OVER w IS NULL OR epoch(ts) - epoch(lag(ts) OVER w) >= 86400 THEN 1 ELSE 0 END AS f FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), s AS (SELECT *, sum(f) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM g) SELECT user_id, CAST(floor(epoch(min(ts))) AS BIGINT) AS start, count(*) AS n FROM s GROUP BY user_id, k"),
    "stream_dedup": (deduplicated, "SELECT DISTINCT event_id, user_id FROM events"),
    "stream_static_nearest": (static_nearest, "SELECT event_id, c AS centre FROM (SELECT event_id, c, row_number() OVER (PARTITION BY event_id ORDER BY abs(value - c), c) AS k FROM events, (SELECT CAST(unnest(range(10)) * 50 AS DOUBLE) AS c)) WHERE k = 1"),
    "stream_interval_join": (interval_join, "SELECT c.event_id AS click, p.event_id AS purchase FROM events c JOIN events p ON c.user_id = p.user_id AND c.event_type = 'click' AND p.event_type = 'purchase' AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR"),
    "stream_graph_value1d": (value_graph, "WITH p AS (SELECT event_id AS pid, value AS x FROM events) SELECT a.pid AS src, b.pid AS dst, round(abs(a.x - b.x), 6) AS dist FROM p a JOIN p b ON a.pid < b.pid AND abs(a.x - b.x) <= 0.05"),
    "stream_graph_e4": (embedding_graph, f"SELECT src, dst, round(dist, 6) AS dist FROM ({SETS['e4'].edges_sql(0.141)})"),
    "stream_graph_timed": (value_graph_timed, "WITH p AS (SELECT event_id AS pid, value AS x, epoch(ts) AS t FROM events) SELECT a.pid AS src, b.pid AS dst, round(abs(a.x - b.x), 6) AS dist FROM p a JOIN p b ON a.pid < b.pid AND abs(a.x - b.x) <= 0.5 AND abs(a.t - b.t) <= 86400"),
}
