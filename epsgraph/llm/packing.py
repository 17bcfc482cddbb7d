"""Bounded-space online packing of tokenised documents into windows.

Each partition keeps at most ``open_windows`` windows open. A document's tokens go, whole windows first, to the open
window they fit best; when none fits, the fullest is emitted, topped up by a cut of the document where both parts keep
``min_cut`` tokens. Windows still open at the end of a partition are leftovers: their pieces are merged across
``merge_span`` partitions at a time (at most merge_span * open_windows windows in one task) by filling windows in order.

Only leftovers carry token ids from one stage to the other unless ``with_ids``; every piece carries the CRC-32 of its ids
(little-endian unsigned 32-bit).

Defined results: a null text is the empty text (its one token is the end id); null and repeated doc_ids are packed like
any others; a document of any length is cut into as many pieces as needed; other columns are ignored; an empty table
gives no pieces. The pieces of one partition depend on its rows in order, so input should be a scan or another
deterministic plan, as retries then give the same rows.
"""

from __future__ import annotations

import base64
import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table

PIECES = "doc_id long, start long, length long, ids_crc32 long, ids binary, doc_tokens long, sequence_id long, offset long, open_in long"
NAMES = ("doc_id", "start", "length", "ids_crc32", "ids", "doc_tokens", "sequence_id", "offset", "open_in")
SCHEMA = pa.schema([(n, pa.binary() if n == "ids" else pa.int64()) for n in NAMES])


def tokenizer_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def byte_bpe(path: str | None = None) -> Callable[[str], np.ndarray]:
    """Ids of a byte-level BPE tokenizer file as uint32, as the tokenizers library gives them without special tokens added;
    a text that holds the string of one of the file's own tokens has its id there.

    Other texts run through tiktoken where the ranks that lie beside the file name the same vocabulary: the ids are equal
    (tested) at a fifth of the time."""
    import json
    import os

    import public_tokenizers
    from tokenizers import Tokenizer

    path = path or tokenizer_path()
    tok = Tokenizer.from_file(path)
    by_file = lambda text: np.array(tok.encode(text, add_special_tokens=False).ids, np.uint32)
    ranks = path.removesuffix(".json") + ".tiktoken"
    if not os.path.exists(ranks):
        return by_file
    import tiktoken

    with open(path, encoding="utf-8") as f:
        own = [t["content"] for t in json.load(f).get("added_tokens") or ()]
    with open(ranks, "rb") as f:
        table_ = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    enc = tiktoken.Encoding("packing", pat_str=public_tokenizers.PATTERN, mergeable_ranks=table_, special_tokens={})
    return lambda text: by_file(text) if any(t in text for t in own) else np.asarray(enc.encode_to_numpy(text, disallowed_special=()), np.uint32)


class Windows:
    """Open windows of one partition. A piece is (doc_id, start, ids, doc_tokens)."""

    def __init__(self, size: int, most: int, min_cut: int):
        self.size, self.most, self.min_cut = size, most, min_cut
        self.open: list[tuple[int, list]] = []

    def add(self, doc_id, ids: np.ndarray) -> Iterator[list]:
        """Places a document; yields the windows that are full or had to go."""
        total, at = len(ids), 0
        while total - at >= self.size:
            yield [(doc_id, at, ids[at : at + self.size], total)]
            at += self.size
        while at < total:
            need = total - at
            fit = min((i for i, (used, _) in enumerate(self.open) if used + need <= self.size), key=lambda i: -self.open[i][0], default=None)
            if fit is None and len(self.open) < self.most:
                self.open.append((0, []))
                fit = len(self.open) - 1
            if fit is not None:
                used, pieces = self.open[fit]
                pieces.append((doc_id, at, ids[at:], total))
                if used + need == self.size:
                    del self.open[fit]
                    yield pieces
                else:
                    self.open[fit] = (used + need, pieces)
                return
            fullest = max(range(len(self.open)), key=lambda i: self.open[i][0])
            used, pieces = self.open.pop(fullest)
            gap = self.size - used
            if gap >= self.min_cut and need - gap >= self.min_cut:
                pieces.append((doc_id, at, ids[at : at + gap], total))
                at += gap
            yield pieces


def fill(pieces: list[tuple], size: int) -> Iterator[list]:
    """Windows filled one after another, pieces cut where a window ends."""
    window, used = [], 0
    for doc_id, start, ids, total in pieces:
        while len(ids):
            take = min(len(ids), size - used)
            window.append((doc_id, start, ids[:take], total))
            start, ids, used = start + take, ids[take:], used + take
            if used == size:
                yield window
                window, used = [], 0
    if window:
        yield window


def _rows(window: list, sequence: int, open_in: int | None, with_ids: bool) -> Iterator[tuple]:
    offset = 0
    for doc_id, start, ids, total in window:
        raw = ids.astype("<u4").tobytes()
        yield doc_id, start, len(ids), zlib.crc32(raw), raw if with_ids else None, total, sequence, offset, open_in
        offset += len(ids)


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, t.type) for c, t in zip(zip(*rows) if rows else [()] * len(NAMES), SCHEMA)], schema=SCHEMA)


def pack(docs: DataFrame, size: int = 2048, open_windows: int = 64, end_id: int = 1, min_cut: int = 64, merge_span: int = 64, path: str | None = None, with_ids: bool = True) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, ids (null without ``with_ids``), doc_tokens, sequence_id, offset.

    The first stage's rows are persisted on disk, since closed windows and leftovers are read apart."""

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part = TaskContext.get().partitionId()
        encode, windows, n, rows = byte_bpe(path), Windows(size, open_windows, min_cut), 0, []
        end = np.array([end_id], np.uint32)
        for b in batches:
            for doc_id, text in zip(b.column(0).to_pylist(), b.column(1)):
                ids = np.concatenate((encode(text.as_py() or ""), end))
                for w in windows.add(doc_id, ids):
                    rows += _rows(w, (part << 32) + n, None, with_ids)
                    n += 1
                if len(rows) >= 4096:
                    yield _batch(rows)
                    rows = []
        for _, w in windows.open:
            rows += _rows(w, (part << 32) + n, part // merge_span, True)
            n += 1
        if rows:
            yield _batch(rows)

    def merge(t: pa.Table) -> pa.Table:
        t = t.sort_by([("sequence_id", "ascending"), ("offset", "ascending")])
        group = t.column("open_in")[0].as_py()
        cols = [t.column(c).to_pylist() for c in ("doc_id", "start", "ids", "doc_tokens")]
        pieces = [(d, s, np.frombuffer(i, "<u4"), n) for d, s, i, n in zip(*cols)]
        rows: list[tuple] = []
        for n, w in enumerate(fill(pieces, size)):
            rows += _rows(w, ((1 << 30) + group << 32) + n, None, with_ids)
        return pa.Table.from_batches([_batch(rows)])

    placed = docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(place, PIECES).persist(StorageLevel.DISK_ONLY)
    closed = placed.filter(F.col("open_in").isNull())
    merged = placed.filter(F.col("open_in").isNotNull()).groupBy("open_in").applyInArrow(merge, PIECES)
    return closed.unionByName(merged).drop("open_in")


def op5_pack(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents", "doc_id", "text"), with_ids=False).drop("ids")
