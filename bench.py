"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line. Each time is of a run after a warm-up run of a
small set, ends at a noop sink, and includes everything from the Parquet scan on."""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession

from epsgraph.operators import baselines, landmark, ring
from epsgraph.workloads import SETS

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")

#: (set, radius): the stand-ins of the published sets, at the radius of about 20 neighbours a point.
RUNS = (("e20", 0.59), ("e32", 0.808), ("e40", 0.933), ("e64", 1.194), ("lgf", 1.5), ("uc", 10.44), ("h256", 98), ("e2", 0.025), ("e8", 0.23))
METHODS = {
    "brute": lambda p, eps, m: ring.brute_graph(p, eps, m, n=8),
    "ring": lambda p, eps, m: ring.ring_graph(p, eps, m, n=8),
    "landmark_m10": lambda p, eps, m: landmark.landmark_graph(p, eps, m, m=10),
    "landmark_m60": lambda p, eps, m: landmark.landmark_graph(p, eps, m, m=60),
    "landmark_ring": lambda p, eps, m: landmark.landmark_graph(p, eps, m, m=16, ghost="ring", rounds=4),
    "pca_sort": lambda p, eps, m: baselines.pca_sort_graph(p, eps, how="local"),
}


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", "12g")
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    times: dict[str, float] = {}

    def timed(name: str, build) -> None:
        begin = time.perf_counter()
        build().write.format("noop").mode("overwrite").save()
        times[name] = round(time.perf_counter() - begin, 3)
        spark.catalog.clearCache()

    for method, build in METHODS.items():
        build(SETS["e2"].build(spark, SF_DIR).limit(200), 0.05, SETS["e2"].metric()).count()
    for name, eps in RUNS:
        ps = SETS[name]
        for method, build in METHODS.items():
            if method == "pca_sort" and name == "h256":
                continue
            timed(f"{method}_{name}", lambda: build(ps.build(spark, SF_DIR), eps, ps.metric()))  # noqa: B023
    total = round(sum(times.values()), 3)
    print(json.dumps({"metric": "graphs_total", "value": total, "unit": "sec", "queries": times, "sf": os.path.basename(SF_DIR.rstrip("/")).removeprefix("sf")}))


if __name__ == "__main__":
    main()
