"""Point sets: pid BIGINT, vec <payload>; and edges: src < dst, dist."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

EDGE = "src long, dst long, dist double"


def points(df: DataFrame, pid: str | Column, vec: str | Column, on_bad: str = "drop") -> DataFrame:
    """(pid, vec). Rows with a null id or payload, or null or non-finite components, are dropped or (``on_bad="error"``) refused."""
    p = df.select(F.col(pid).cast("long").alias("pid") if isinstance(pid, str) else pid.cast("long").alias("pid"), (F.col(vec) if isinstance(vec, str) else vec).alias("vec"))
    good = F.col("pid").isNotNull() & F.col("vec").isNotNull()
    kind = p.schema["vec"].dataType.simpleString()
    if kind in ("array<double>", "array<float>"):
        good &= F.forall("vec", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    elif kind.startswith("array"):
        good &= F.forall("vec", lambda x: x.isNotNull())
    if on_bad == "error":
        return p.select("pid", F.when(good, F.col("vec")).otherwise(F.raise_error(F.lit("bad point"))).alias("vec"))
    return p.filter(good)


def collapse(p: DataFrame) -> DataFrame:
    """(rep, vec, members): one row a distinct payload; rep is its smallest pid."""
    # by the hash first, so that sorts seldom compare payloads
    return p.groupBy(F.xxhash64("vec").alias("_h"), "vec").agg(F.min("pid").alias("rep"), F.array_sort(F.collect_set("pid")).alias("members")).drop("_h")


#: Members that a batch of edges between groups brings with it, about.
MOST_MEMBERS = 1 << 18


def _with_members(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(ms, md, dist) of the edges of a part, rows sorted by (part, role): first its groups, then edges, which find theirs among them."""
    part, held, ids = None, [], None
    for b in batches:
        if not b.num_rows:
            continue
        parts, roles = b.column("part").to_numpy(), b.column("role").to_numpy()
        cuts = np.flatnonzero((np.diff(parts) != 0) | (np.diff(roles) != 0)) + 1
        for lo, hi in zip([0, *cuts], [*cuts, b.num_rows]):
            piece = b.slice(lo, hi - lo)
            if parts[lo] != part:
                part, held, ids = parts[lo], [], None
            if roles[lo] == 0:
                held.append(piece.select(["src", "members"]))
                continue
            if held:
                t = pa.Table.from_batches(held).sort_by("src")
                held, ids, lists = [], t.column("src").to_numpy(), t.column("members").combine_chunks()
                size = lists.value_lengths().to_numpy()
            if ids is None:
                continue
            src, dst = piece.column("src").to_numpy(), piece.column("dst").to_numpy()
            i, j = (np.minimum(np.searchsorted(ids, v), len(ids) - 1) for v in (src, dst))
            ok = np.flatnonzero((ids[i] == src) & (ids[j] == dst))
            i, j, dist = i[ok], j[ok], piece.column("dist").to_numpy()[ok]
            ends = np.flatnonzero(np.diff(np.cumsum(size[i].astype(np.int64) + size[j]) // MOST_MEMBERS)) + 1
            for x, y in zip([0, *ends], [*ends, len(i)]):
                if x < y:
                    yield pa.RecordBatch.from_arrays([lists.take(pa.array(i[x:y])), lists.take(pa.array(j[x:y])), pa.array(dist[x:y])], ["ms", "md", "dist"])


def expand(edges: DataFrame, groups: DataFrame) -> DataFrame:
    """Edges between representatives, to edges between all their members, with those inside each group at distance 0.

    Members do not travel with edges, of which a group has many: representatives are dealt into n blocks, an edge goes to the part of
    its pair of blocks, and a group to the 2 n - 1 parts of its block; n grows with the root of the session's partitions."""
    several = groups.select(F.col("rep"), "members")
    n = int(np.ceil(np.sqrt(int(edges.sparkSession.conf.get("spark.sql.shuffle.partitions"))) / 2)) + 1
    each, own = F.sequence(F.lit(0), F.lit(n - 1)), block_of(n, pid="rep")
    to = F.array_union(F.transform(each, lambda k: own * n + k), F.transform(each, lambda k: k * n + own))
    none = F.lit(None)
    bring = several.select(F.explode(to).alias("part"), F.lit(0).alias("role"), F.col("rep").alias("src"), none.cast("long").alias("dst"), none.cast("double").alias("dist"), "members")
    meet = edges.select((block_of(n, pid="src") * n + block_of(n, pid="dst")).alias("part"), F.lit(1).alias("role"), "src", "dst", "dist", none.cast("array<bigint>").alias("members"))
    rows = bring.unionByName(meet).repartitionById(n * n, "part").sortWithinPartitions("part", "role")
    across = rows.mapInArrow(_with_members, "ms array<bigint>, md array<bigint>, dist double")
    across = across.select(F.explode("ms").alias("s"), "md", "dist").select("s", F.explode("md").alias("d"), "dist")
    across = across.select(F.least("s", "d").alias("src"), F.greatest("s", "d").alias("dst"), "dist")
    inside = several.filter(F.size("members") > 1).select(F.posexplode("members").alias("i", "src"), "members")
    inside = inside.select("src", F.explode(F.slice("members", F.col("i") + 2, F.size("members"))).alias("dst"), F.lit(0.0).alias("dist"))
    return across.unionByName(inside)


def block_of(n: int, seed: int = 0, pid: str = "pid") -> Column:
    """Block id of a point by hash: not the physical partition, which adaptive execution may change."""
    return F.pmod(F.xxhash64(pid, F.lit(seed)), F.lit(n)).cast("int")


def edge_table(s: np.ndarray, d: np.ndarray, dist: np.ndarray) -> pa.Table:
    return pa.table({"src": np.minimum(s, d).astype(np.int64), "dst": np.maximum(s, d).astype(np.int64), "dist": np.asarray(dist, float)})


def edge_batches(s: np.ndarray, d: np.ndarray, dist: np.ndarray, rows: int = 1 << 16) -> Iterator[pa.RecordBatch]:
    yield from edge_table(s, d, dist).to_batches(max_chunksize=rows)


def symmetric(edges: DataFrame) -> DataFrame:
    return edges.unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "dist"))
