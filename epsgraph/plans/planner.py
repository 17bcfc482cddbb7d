"""A method for a graph, chosen by costs measured on a hash sample of bounded size."""

from __future__ import annotations

from dataclasses import dataclass
from time import perf_counter

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.metrics import Metric, resolve, slack
from ..functions.trees import CoverTree
from ..operators.landmark import decoded_centres, landmark_graph
from ..operators.ring import brute_graph, ring_graph


@dataclass(frozen=True)
class Plan:
    method: str
    m: int
    seconds: float
    ghosts: float
    pairs: float


#: Rows a second through one exchange, for one core: an assumption that only weighs ghosts against distances.
SHUFFLE_ROWS = 200_000.0


def candidates(p: DataFrame, eps: float, metric: str | Metric, sample: int = 1000, seed: int = 0) -> tuple[int, list[Plan]]:
    """(points, plans, cheapest first). Sample figures are scaled: tree work by the visited part, ghosts as they are."""
    m = resolve(metric)
    n = p.count()
    rows = p.orderBy(F.xxhash64("pid", F.lit(seed)), "pid").limit(sample).select("vec").collect()
    if len(rows) < 2:
        return n, [Plan("brute", 1, 0.0, 0.0, 0.0)]
    x = decoded_centres([r[0] for r in rows], m, p.schema["vec"].dataType)
    begin = perf_counter()
    part = x[: min(len(x), 200)]
    d = m.table(part, x)
    speed = max(d.size / max(perf_counter() - begin, 1e-6), 1e3)
    pairs = float((d <= eps).sum() - len(part)) / max(1, len(part) * (len(x) - 1)) * n * (n - 1) / 2
    plans = [Plan("brute", 1, n * n / 2 / speed + n * 8 / SHUFFLE_ROWS, 0.0, pairs)]
    if not m.is_metric:
        return n, plans
    m.evaluations = 0
    CoverTree(x, m).query(part, eps)
    visited = min(1.0, m.evaluations / (len(part) * len(x)))
    plans.append(Plan("ring", 8, n * n / 2 * visited / speed + n * 5 / SHUFFLE_ROWS, 0.0, pairs))
    for k in (8, 16, 32, 64):
        if k > len(x) // 4:
            break
        c = m.table(x, x[:k])
        near = c.min(1, keepdims=True)
        home = c.argmin(1)
        radius = np.array([c[home == i, i].max(initial=0) for i in range(k)])
        ghost = (c <= slack(near + 2 * eps)) & (c <= slack(radius[None, :] + eps))
        ghost[np.arange(len(x)), home] = False
        ghost &= np.arange(k)[None, :] < home[:, None]
        g = float(ghost.sum() / len(x))
        load = np.bincount(home, minlength=k) / len(x) * n
        work = float((load * (load / 2 + ghost.sum(0) / len(x) * n)).sum()) * visited
        plans.append(Plan("landmark_collective" if g <= 2 else "landmark_ring", k, (n * k + work) / speed + n * (1 + g) / SHUFFLE_ROWS, g, pairs))
    return n, sorted(plans, key=lambda q: q.seconds)


def near_graph(p: DataFrame, eps: float, metric: str | Metric = "l2", method: str = "auto", max_edges: float = 1e12, **options) -> DataFrame:
    """All pairs at most eps apart, by the named or the cheapest method; refuses outputs beyond ``max_edges``."""
    m = resolve(metric)
    if eps < 0:
        raise ValueError("eps must not be negative")
    size = 16
    if method == "auto":
        _, plans = candidates(p, eps, m)
        if plans[0].pairs > max_edges:
            raise ValueError(f"about {plans[0].pairs:.3g} edges; ask for degrees, or raise max_edges")
        method, size = plans[0].method, max(plans[0].m, 1)
    if method == "brute":
        return brute_graph(p, eps, m, **options)
    if not m.is_metric:
        raise ValueError(f"{m.name} is no metric: only brute force is exact")
    if method == "ring":
        return ring_graph(p, eps, m, **options)
    return landmark_graph(p, eps, m, **({"m": size} | options), ghost="ring" if method == "landmark_ring" else "collective")


def explain_graph(p: DataFrame, eps: float, metric: str | Metric = "l2") -> DataFrame:
    """(method, m, seconds, ghosts_per_point, pairs, chosen): the estimates behind the choice."""
    _, plans = candidates(p, eps, metric)
    rows = [(q.method, q.m, q.seconds, q.ghosts, q.pairs, i == 0) for i, q in enumerate(plans)]
    return p.sparkSession.createDataFrame(rows, "method string, m int, seconds double, ghosts_per_point double, pairs double, chosen boolean")
