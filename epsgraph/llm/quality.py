"""Quality rules: a base rule on counts, then a hashed n-gram log-likelihood ratio.

``fit_quality`` counts hashed byte n-grams of all documents (raw corpus) and of all trusted ones (labelled good), and takes
the smoothed log ratio of the two multinomials per bucket, kept as fixed-point integers so that sums do not
depend on batching. A document's score is its mean over its n-grams (length-normalised). The threshold is fixed from all
labelled documents: halfway between the trusted ones' 0.1 % quantile and the bad ones' 99 % quantile, never above the
former. Every document is then scored and thresholded by ``score_quality``.

The model is a table of ``buckets`` numbers, a proven bound. Labels stay in a table: labelled texts are found by a join, once
a bitmap of their ids has thinned out the others, and the quantiles by sorting.

Defined results: a null text has no words and fails the base rule; a text shorter than the n-gram scores 0; without
trusted documents every score is 0 and only the base rule rejects; a document labelled both ways counts as bad; repeated
rows are counted and judged one by one; other columns pass through, and result columns come in one struct ``quality``.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import lean, maybe_among, slices, table

#: Fixed values of the base rule.
SYMBOLS = b"#*$%&|<>"
SPACES = b" \t\n\x0b\x0c\r"
MIN_WORDS, MAX_REPEAT_PERCENT = 50, 50
#: Every byte that begins a code point.
LEADS = bytes(b for b in range(256) if b & 0xC0 != 0x80)

#: Fixed-point unit of the log ratios.
UNIT = 1 << 20

FIELDS = (("n_words", pa.int64()), ("word_chars", pa.int64()), ("n_symbols", pa.int64()), ("n_dup_lines", pa.int64()), ("n_repeat_words", pa.int64()), ("base_failed", pa.bool_()), ("score", pa.float64()), ("kept", pa.bool_()))
RESULT = "struct<n_words: bigint, word_chars: bigint, n_symbols: bigint, n_dup_lines: bigint, n_repeat_words: bigint, base_failed: boolean, score: double, kept: boolean>"


@dataclass(frozen=True)
class QualityModel:
    n: int
    ratio: np.ndarray
    threshold: float


def repeated_words(words: list[bytes]) -> int:
    """Words that lie in a 3-word window found twice or more."""
    if len(words) < 4:
        return 0
    seen: dict[bytes, int] = {}
    ids = np.fromiter((seen.setdefault(w, len(seen)) for w in words), np.int64, len(words))
    _, pair = np.unique(ids[:-1] * len(seen) + ids[1:], return_inverse=True)
    _, at, count = np.unique(pair[:-1] * len(seen) + ids[2:], return_inverse=True, return_counts=True)
    twice = count[at] > 1
    covered = np.zeros(len(words), bool)
    for i in range(3):
        covered[i : len(words) - 2 + i] |= twice
    return int(covered.sum())


def base_counts(raw: bytes) -> tuple[int, int, int, int, int, bool]:
    words = raw.split()
    lines = [x for x in raw.split(b"\n") if x.strip()]
    repeats = repeated_words(words)
    failed = len(words) < MIN_WORDS or 100 * repeats > MAX_REPEAT_PERCENT * len(words)
    spaces = len(raw) - len(raw.translate(None, SPACES))
    symbols = len(raw) - len(raw.translate(None, SYMBOLS))
    # a code point is a byte that continues none
    points = len(raw) - len(raw.translate(None, LEADS))
    return len(words), points - spaces, symbols, len(lines) - len(set(lines)), repeats, failed


def gram_buckets(texts: list[bytes], n: int, buckets: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Bucket of the n-gram at each byte of the joined texts, and each text's range of n-gram positions."""
    sizes = np.fromiter(map(len, texts), np.int64, len(texts))
    begin = np.concatenate(([0], np.cumsum(sizes)))[:-1]
    x = np.frombuffer(b"".join(texts) + bytes(n), np.uint8)
    h = np.zeros(len(x) - n + 1, np.uint64)
    for i in range(n):
        h *= np.uint64(0x9E3779B97F4A7C15)
        h += x[i : len(x) - n + 1 + i]
        h += np.uint64(1)
    h ^= h >> np.uint64(29)
    h *= np.uint64(0xBF58476D1CE4E5B9)
    h >>= np.uint64(32)
    return (h.astype(np.uint32) % np.uint32(buckets)).astype(np.int32), begin, begin + np.maximum(sizes - n + 1, 0)


def _labelled(labels: DataFrame) -> DataFrame:
    """(doc_id, good) of every document labelled good or bad, bad if it is both."""
    one = labels.filter(F.col("doc_id").isNotNull() & F.col("quality").isNotNull()).groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.min("quality").alias("quality"))
    return one.filter(F.col("quality").isin(0, 1)).select("doc_id", (F.col("quality") == 1).alias("good"))


def _counted(docs: DataFrame, n: int, buckets: int) -> np.ndarray:
    """How often each bucket's n-grams stand in the texts of ``docs``."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums = np.zeros(buckets, np.int64)
        for b in batches:
            for _, texts in slices(b, 0):
                g, start, stop = gram_buckets(texts, n, buckets)
                inside = np.zeros(len(g) + 1, np.int32)
                np.add.at(inside, start, 1)
                np.add.at(inside, stop, -1)
                inside = np.cumsum(inside, dtype=np.int32)[:-1] > 0
                sums += np.bincount(g[inside], minlength=buckets)
        some = np.flatnonzero(sums)
        yield pa.record_batch({"bucket": some, "n": sums[some]})

    out = np.zeros(buckets)
    for bucket, found in docs.select("text").mapInArrow(lean(count), "bucket long, n long").groupBy("bucket").agg(F.sum("n")).collect():
        out[bucket] = found
    return out


def _quantile(values: DataFrame, n: int, part: float) -> float | None:
    """What ``percentile`` gives for the one column of ``n`` rows, no task holding more than their lower ``part``."""
    if not n:
        return None
    at = part * (n - 1)
    k = int(at)
    two = [r[0] for r in values.orderBy(*values.columns).offset(k).limit(2).collect()]
    return two[0] + (at - k) * (two[-1] - two[0])


def fit_quality(docs: DataFrame, labels: DataFrame, n: int = 4, buckets: int = 1 << 15) -> QualityModel:
    base, known = docs.select(F.col("doc_id").cast("long"), "text"), _labelled(labels)
    # one plan at every size, so that small inputs show what large ones shuffle
    marked = maybe_among(base, "doc_id", known).join(known.hint("merge"), "doc_id").persist(StorageLevel.DISK_ONLY)
    total = np.stack([_counted(base, n, buckets), _counted(marked.filter("good"), n, buckets)])
    smooth = np.log((total + 1) / (total.sum(1, keepdims=True) + buckets))
    ratio = np.round((smooth[1] - smooth[0]) * UNIT).astype(np.int64) if total[1].any() else np.zeros(buckets, np.int64)
    model = QualityModel(n, ratio, float("-inf"))
    if not total[1].any():
        marked.unpersist()
        return model
    scored = score_quality(marked, model).filter(~F.col("quality.base_failed")).select("good", F.col("quality.score").alias("score")).persist(StorageLevel.DISK_ONLY)
    rows = dict(scored.groupBy("good").count().collect())
    low = _quantile(scored.filter("good").select("score"), rows.get(True, 0), 0.001)
    high = _quantile(scored.filter("not good").select(-F.col("score")), rows.get(False, 0), 0.01)
    for held in (marked, scored):
        held.unpersist()
    if low is None:
        return model
    return QualityModel(n, ratio, low if high is None else min(low, (low - high) / 2))


def score_quality(docs: DataFrame, model: QualityModel) -> DataFrame:
    """``docs`` with a struct ``quality``: counts, score and verdict."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    result = pa.struct(list(FIELDS))
    schema = T.StructType([f for f in docs.schema.fields if f.name != "quality"]).add("quality", T._parse_datatype_string(RESULT))
    docs = docs.select(*[f.name for f in schema.fields[:-1]])
    at = docs.columns.index("text")

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for b in batches:
            for part, raws in slices(b, at):
                g, start, stop = gram_buckets(raws, m.n, len(m.ratio))
                sums = np.concatenate(([0], np.cumsum(m.ratio[g])))
                score = (sums[stop] - sums[start]) / np.maximum(stop - start, 1) / UNIT
                counts = [base_counts(r) for r in raws]
                out = [(*c, s, not c[-1] and s >= m.threshold) for c, s in zip(counts, score.tolist())]
                cols = [pa.array(c, kind) for c, (_, kind) in zip(zip(*out), FIELDS)]
                yield pa.RecordBatch.from_arrays([*part.columns, pa.StructArray.from_arrays(cols, fields=list(result))], names=[*b.schema.names, "quality"])

    return docs.mapInArrow(lean(judge), schema)


def op10_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    model = fit_quality(docs, table(spark, sf_dir, "labels", "doc_id", "quality"))
    return score_quality(docs, model).select("doc_id", "quality.*")
