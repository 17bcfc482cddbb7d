"""Jaccard graphs of sets by an exact prefix-filter join."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Places of the table of counts by which elements are ranked; elements that share a place are ranked by their hash.
PLACES = 1 << 20
#: 64-bit words of the parity sketches, which differ in no more bits than two sets differ in elements: a short one beside each
#: prefix entry, a long one looked up for the pairs that pass.
WORDS, MORE_WORDS = 4, 32

PREFIX = "pid long, n int, w long, " + ", ".join(f"s{k} long" for k in range(WORDS))


def _place(h):
    return F.pmod(h, F.lit(PLACES))


def _parities(h: np.ndarray, row: np.ndarray, n: int, words: int) -> np.ndarray:
    """(n, words): for each row the parity of its elements at each bit."""
    bits = words * 64
    odd = np.bincount(row * bits + ((h >> 32) & (bits - 1)), minlength=n * bits).astype(np.uint8).reshape(n, bits) & 1
    return np.packbits(odd, axis=1, bitorder="little").view(np.int64)


def jaccard_graph(p: DataFrame, eps: float) -> DataFrame:
    """Edges between the sets (``vec``, distinct elements) at most ``eps`` < 1 apart; two empty sets are at distance 0.

    Sets that close share one of their rarest elements, the fewer the smaller ``eps`` is: a set of n elements hands in the
    n - ceil((1 - eps) * n) + 1 first ones, in any one order of all elements. The order here is by counts of hashed elements (a
    table of fixed size), so a clash of hashes costs candidates but no edge. Candidates pass by sizes and parity sketches, then
    full sets are compared."""
    if not 0 <= eps < 1:
        raise ValueError("the prefix filter needs 0 <= eps < 1")
    t = 1 - eps
    hashed = p.select("pid", F.transform("vec", lambda x: F.xxhash64(x)).alias("h"))
    counts = hashed.select(F.explode("h").alias("h")).groupBy(_place(F.col("h")).cast("int").alias("place")).agg(F.count("*").alias("n"))
    rank = np.zeros(PLACES, np.int64)
    for b in counts.toArrow().to_batches():
        rank[b.column(0).to_numpy()] = b.column(1).to_numpy()
    shared = p.sparkSession.sparkContext.broadcast(rank)

    def prefixes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in (whole.slice(k, 512) for k in range(0, whole.num_rows, 512)):
                h = b.column(1).flatten().to_numpy()
                n = b.column(1).value_lengths().to_numpy().astype(np.int64)
                row = np.repeat(np.arange(len(n)), n)
                begin = np.cumsum(n) - n
                words = _parities(h, row, len(n), WORDS)
                order = np.lexsort((h, shared.value[h % PLACES], row))
                first = n - np.ceil(t * n - 1e-9 * (n + 1)).astype(np.int64) + 1
                keep = np.arange(len(h)) - begin[row] < first[row]  # rows stay in order
                at = row[keep]
                yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(at)), pa.array(n[at].astype(np.int32)), pa.array(h[order][keep]), *(pa.array(words[at, k]) for k in range(WORDS))], ["pid", "n", "w", *(f"s{k}" for k in range(WORDS))])

    def sketches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in (whole.slice(k, 512) for k in range(0, whole.num_rows, 512)):
                n = b.column(1).value_lengths().to_numpy()
                words = _parities(b.column(1).flatten().to_numpy(), np.repeat(np.arange(len(n)), n), len(n), MORE_WORDS)
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n.astype(np.int32)), pa.array([w.tobytes() for w in words], pa.binary())], ["pid", "n", "sketch"])

    def agree(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x, y = (np.frombuffer(b"".join(b.column(c).to_pylist()), np.uint64).reshape(b.num_rows, -1) for c in ("x", "y"))
            total = b.column("m").to_numpy().astype(np.int64) + b.column("n").to_numpy()
            may = np.bitwise_count(x ^ y).sum(1, dtype=np.int64) * (1 + t) <= (1 - t) * total + 2e-9 * (total + 1)
            yield pa.RecordBatch.from_arrays([b.column(c).filter(pa.array(may)) for c in ("src", "dst")], ["src", "dst"])

    pre = hashed.mapInArrow(prefixes, PREFIX)
    a, b = pre.alias("a"), pre.alias("b")
    less, more = F.least("a.n", "b.n"), F.greatest("a.n", "b.n")
    apart = sum((F.bit_count(F.col(f"a.s{k}").bitwiseXOR(F.col(f"b.s{k}"))) for k in range(WORDS)), F.lit(0))
    room = 1e-9 * (F.col("a.n") + F.col("b.n") + 1)
    may = (F.col("a.pid") < F.col("b.pid")) & (less >= t * more - room) & (apart * (1 + t) <= (1 - t) * (F.col("a.n") + F.col("b.n")) + 2 * room)
    pairs = a.join(b, (F.col("a.w") == F.col("b.w")) & may).select(F.col("a.pid").alias("src"), F.col("b.pid").alias("dst")).distinct()
    sk = hashed.mapInArrow(sketches, "pid long, n int, sketch binary")
    pairs = pairs.join(sk.select(F.col("pid").alias("src"), F.col("n").alias("m"), F.col("sketch").alias("x")), "src").join(sk.select(F.col("pid").alias("dst"), "n", F.col("sketch").alias("y")), "dst")
    pairs = pairs.select("src", "dst", "m", "n", "x", "y").mapInArrow(agree, "src long, dst long")
    sets = p.select("pid", "vec")
    left, right = sets.select(F.col("pid").alias("src"), F.col("vec").alias("x")), sets.select(F.col("pid").alias("dst"), F.col("vec").alias("y"))
    both = F.size(F.array_intersect("x", "y"))
    near = pairs.join(left, "src").join(right, "dst").select("src", "dst", F.size("x").alias("m"), F.size("y").alias("n"), both.alias("both"))
    edges = near.select("src", "dst", (1 - F.col("both") / (F.col("m") + F.col("n") - F.col("both"))).alias("dist")).filter(F.col("dist") <= eps)
    empty = p.filter(F.size("vec") == 0).select("pid")
    none = empty.select(F.col("pid").alias("src")).join(empty.select(F.col("pid").alias("dst")), F.col("src") < F.col("dst")).withColumn("dist", F.lit(0.0))
    return edges.unionByName(none)
