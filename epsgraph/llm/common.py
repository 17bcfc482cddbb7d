"""Helpers shared by the training-data operators."""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bits of the bitmap of wanted ids: at most 131,072 rows of 64.
BITS = 1 << 23


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def chunks(texts: list[bytes], limit: int = 4 << 20) -> Iterator[tuple[int, int]]:
    """Row ranges of at most ``limit`` bytes, one row at least: bounds what numpy holds at a time."""
    start, size = 0, 0
    for i, t in enumerate(texts):
        if i > start and size + len(t) > limit:
            yield start, i
            start, size = i, 0
        size += len(t)
    if start < len(texts):
        yield start, len(texts)


def slices(batch: pa.RecordBatch, at: int, limit: int = 1 << 20) -> Iterator[tuple[pa.RecordBatch, list[bytes]]]:
    """Slices of a batch with the UTF-8 bytes of their texts (column ``at``, null: empty), of at most ``limit`` bytes, one row
    at least: only a slice's texts are held as Python objects at a time."""
    sizes = pc.fill_null(pc.binary_length(batch.column(at)), 0).to_numpy(zero_copy_only=False)
    ends = np.cumsum(sizes, dtype=np.int64)
    lo = 0
    while lo < batch.num_rows:
        before = ends[lo - 1] if lo else 0
        hi = max(lo + 1, int(np.searchsorted(ends, before + limit, side="right")))
        part = batch.slice(lo, hi - lo)
        yield part, [t or b"" for t in part.column(at).cast(pa.binary()).to_pylist()]
        lo = hi


def maybe_among(rows: DataFrame, column: str, wanted: DataFrame) -> DataFrame:
    """The rows whose id may be one of ``wanted`` (doc_id): a bitmap of the ids' hashes (a bounded table) thins them out
    before they are shuffled for the join that decides."""
    spot = lambda c: F.pmod(F.xxhash64(c), F.lit(BITS))
    words = wanted.select(spot("doc_id").alias("at")).groupBy(F.shiftright("at", 6).alias("word")).agg(F.bit_or(F.expr("shiftleft(1L, cast(at & 63 as int))")).alias("bits"))
    at = rows.withColumn("at", spot(column)).join(F.broadcast(words), F.shiftright("at", 6) == F.col("word"))
    return at.filter(F.expr("getbit(bits, cast(at & 63 as int)) = 1")).select(*rows.columns)


def release_memory() -> None:
    """Gives freed memory back to the system, where its C library can: Spark keeps idle workers, which would hold it beside the JVM."""
    pa.default_memory_pool().release_unused()
    libc = ctypes.CDLL(None)
    if hasattr(libc, "malloc_trim"):
        libc.malloc_trim(0)


def lean(run: Callable) -> Callable:
    """``run`` over a partition's batches, whose freed memory goes back at its end."""

    def released(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from run(batches)
        release_memory()

    return released


def lean_group(run: Callable, large: int = 1 << 20) -> Callable:
    """``run`` of a group's table, after which freed memory goes back if the group was a large one."""

    def released(t: pa.Table) -> pa.Table:
        out = run(t)
        if t.nbytes > large:
            release_memory()
        return out

    return released
