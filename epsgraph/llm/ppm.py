"""Language-model scores by prediction by partial matching over bytes.

The pretrained model is a byte-context trie of depth ``ORDER``: symbol counts of contexts of 0..ORDER bytes. A byte counts in
its longest context and, as long as it is new there, in the next shorter one (update exclusion). A text is its UTF-8 bytes between start marks and an end mark (bytes that UTF-8
never uses), so its score is a proper probability. In a context with n counts of d symbols a symbol of count c
has (2c - 1) / 2n and escape d / 2n; after an escape, the symbols of the longer context are excluded; below order 0 the
bytes not yet excluded are equally likely.

On Spark the trie is a table of (ORDER + 1)-grams: a shorter gram's count is the number of different grams one byte
longer that end in it. Symbols seen in a context are seen in its suffixes too, so a gram's code length needs only sums
over grams that share its last bytes: grams are coded by three-byte context (at most 2^24 grams), many contexts at a time,
given the order-2 counts (at most 2^24 of 6 bytes) that all tasks hold. Texts are dealt into batches of bounded bytes;
each asks for the words it holds, the answers are joined by key and meet the batch again. Code lengths are broadcast while
they are few (a checked size) and asked for by batch like words beyond it. Each text is read whole.

``Trie`` is the same model in one process, pretrained or adaptive (learning while it codes).

Defined results: a null text is the empty text, whose score is that of its end mark; null ids belong to the training
part; repeated rows count and are scored one by one; without training texts all bytes are equally likely; other columns are
ignored.
"""

from __future__ import annotations

from math import log10

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import lean, lean_group, release_memory, slices, table

ORDER = 5
START, END = b"\xfe" * ORDER, b"\xff"
ANSWER = "batch int, key long, value double"
#: Bytes of text that are cut into grams at a time.
PIECE = 2 << 20
#: Grams that are coded at a time, about: contexts stay whole.
CODED = 1 << 16
SCORES = "doc_id long, held_out boolean, n_tokens long, n_known long, base_score double, score double"


class Trie:
    """The model in one process: contexts of 0..ORDER bytes with their symbol counts."""

    def __init__(self):
        self.at: dict[bytes, dict[int, int]] = {}

    def learn(self, context: bytes, symbol: int) -> None:
        for k in range(ORDER, -1, -1):
            node = self.at.setdefault(context[ORDER - k :], {})
            node[symbol] = node.get(symbol, 0) + 1
            if node[symbol] > 1:
                return

    def log10(self, context: bytes, symbol: int) -> float:
        out, excluded = 0.0, set()
        for k in range(ORDER, -1, -1):
            node = {s: c for s, c in self.at.get(context[ORDER - k :], {}).items() if s not in excluded}
            if not node:
                continue
            n = sum(node.values())
            if symbol in node:
                return out + log10((2 * node[symbol] - 1) / (2 * n))
            out += log10(len(node) / (2 * n))
            excluded |= node.keys()
        return out - log10(256 - len(excluded))

    def score(self, text: str, adaptive: bool = False) -> float:
        raw, total = START + text.encode() + END, 0.0
        for i in range(ORDER, len(raw)):
            total += self.log10(raw[i - ORDER : i], raw[i])
            if adaptive:
                self.learn(raw[i - ORDER : i], raw[i])
        return total

    def train(self, text: str) -> None:
        raw = START + text.encode() + END
        for i in range(ORDER, len(raw)):
            self.learn(raw[i - ORDER : i], raw[i])


def adaptive_scores(docs: DataFrame) -> DataFrame:
    """(doc_id, score): each text coded by a trie of its own that starts empty and learns as it goes."""

    def run(batches):
        for b in batches:
            scores = [Trie().score(t or "", adaptive=True) for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(scores, pa.float64())], ["doc_id", "score"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, score double")


def grams(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """All grams of the texts, in order, and where each text's begin; each text has one a byte and one for its end."""
    x = np.frombuffer(b"".join(START + t + END for t in texts), np.uint8)
    sizes = np.fromiter(map(len, texts), np.int64, len(texts))
    begin = np.cumsum(sizes + ORDER + 1) - (sizes + ORDER + 1)
    h = np.zeros(len(x) - ORDER, np.int64)
    for i in range(ORDER + 1):
        h <<= 8
        h |= x[i : len(x) - ORDER + i]
    inside = np.ones(len(h), bool)
    for i in range(1, ORDER + 1):
        inside[begin[1:] - i] = False
    return h[inside], begin - ORDER * np.arange(len(texts))


def looked_up(keys: np.ndarray, table_: np.ndarray, values: np.ndarray) -> np.ndarray:
    """The value of each key, all being in the sorted table: different keys are found by hash, and looked up once."""
    found = pa.array(keys).dictionary_encode()
    return values[np.searchsorted(table_, found.dictionary.to_numpy())][found.indices.to_numpy()]


def counted(parts: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    """Sums of counts by key."""
    if not parts:
        return np.empty(0, np.int64), np.empty(0, np.int64)
    keys, at = np.unique(np.concatenate([k for k, _ in parts]), return_inverse=True)
    return keys, np.bincount(at, np.concatenate([c for _, c in parts]), len(keys)).astype(np.int64)


def word_key(w: bytes) -> int:
    """A negative key, as grams have positive ones."""
    return (xxhash.xxh64_intdigest(w) >> 1) - (1 << 63)


def words_of(texts: pa.Array) -> tuple[list[bytes], np.ndarray, np.ndarray]:
    """The different words of lower-cased texts, each word's place among them, and each text's number of words."""
    bare = pc.ascii_trim_whitespace(pc.ascii_lower(texts))
    lists = pc.ascii_split_whitespace(bare)
    # a text without words is split into one empty word
    n = np.where(pc.equal(bare, "").to_numpy(zero_copy_only=False), 0, pc.list_value_length(lists).to_numpy(zero_copy_only=False))
    flat = lists.flatten()
    found = flat.filter(pc.not_equal(flat, "")).dictionary_encode()
    return found.dictionary.cast(pa.binary()).to_pylist(), found.indices.to_numpy(), n


def pieces(group: pa.Table, size: int = PIECE):
    """A batch in slices (text, held_out) of about ``size`` bytes, with the bytes of their texts: only a slice's are held at a time."""
    for b in group.select(["text", "held_out"]).to_batches():
        yield from slices(b, 0, size)


def words_by_piece(group: pa.Table) -> tuple[list[tuple[np.ndarray, np.ndarray, np.ndarray]], np.ndarray, np.ndarray]:
    """Of each piece the keys of its words, each word's place among them and each text's number of words; and a batch's sorted
    keys with their counts in training texts."""
    found, parts = [], []
    for part, _ in pieces(group, 3 * PIECE):
        words, at, n = words_of(part.column(0))
        keys = np.fromiter(map(word_key, words), np.int64, len(words))
        held = part.column(1).to_numpy(zero_copy_only=False)
        parts.append((keys, np.bincount(at[~np.repeat(held, n)], minlength=len(keys))))
        found.append((keys, at, n))
    return found, *counted(parts)


def gram_requests(batches):
    """(key, n): every gram of a partition's texts, with its count in training texts."""
    parts, size = [], 0
    for b in batches:
        held = b.column("held_out")
        for weight in (1, 0):
            for _, texts in slices(b.filter(pc.invert(held) if weight else held), 0, PIECE):
                k, c = np.unique(grams(texts)[0], return_counts=True)  # a sort beats a hash table here
                parts.append((k, c * weight))
                size += len(k)
                if size > 1_500_000:
                    parts = [counted(parts)]
                    size = len(parts[0][0])
                    if size > 750_000:
                        yield pa.record_batch(dict(zip(("key", "n"), parts.pop())))
                        size = 0
    if parts:
        yield pa.record_batch(dict(zip(("key", "n"), counted(parts))))


def batch_grams(group: pa.Table) -> pa.Table:
    """(batch, key): every gram of a batch."""
    keys = np.unique(np.concatenate([np.unique(grams(texts)[0]) for _, texts in pieces(group)]))
    return pa.table({"batch": pa.array(np.full(len(keys), group.column("batch")[0].as_py(), np.int32)), "key": keys})


def word_requests(group: pa.Table) -> pa.Table:
    """(batch, key, n): every word of a batch, with its count in training texts."""
    _, keys, sums = words_by_piece(group)
    return pa.table({"batch": pa.array(np.full(len(keys), group.column("batch")[0].as_py(), np.int32)), "key": keys, "n": sums})


class Shorter:
    """What orders 2 to 0 count, from the sorted keys (two context bytes, symbol) of order 2 and their counts: at most 2^24, none
    above 256."""

    def __init__(self, keys: np.ndarray, counts: np.ndarray):
        self.keys, self.counts = keys.astype(np.int32), counts.astype(np.uint16)
        self.one = np.bincount(keys & 65535, minlength=1 << 16).reshape(256, 256)
        self.zero = (self.one > 0).sum(0)
        context = keys >> 8
        sums = lambda v: np.bincount(context, v, 1 << 16).astype(np.int32)
        self.n2, self.d2, self.e2 = sums(counts), sums(None), sums(self.one[context & 255, keys & 255])
        self.n1, self.d1, self.e1 = self.one.sum(1), (self.one > 0).sum(1), (self.one > 0) @ self.zero

    def two(self, low: np.ndarray) -> np.ndarray:
        if not len(self.keys):
            return np.zeros(len(low), np.int64)
        at = np.minimum(np.searchsorted(self.keys, low.astype(np.int32)), len(self.keys) - 1)
        return np.where(self.keys[at] == low, self.counts[at], 0).astype(np.int64)

    def levels(self, gram: np.ndarray) -> list[tuple]:
        """Of orders 2, 1 and 0: context's n and d, symbol's c, and the part of the order below that is excluded after it."""
        low, last, symbol = gram & 0xFFFFFF, gram >> 8 & 255, gram & 255
        flat = lambda v: np.full(len(gram), v)
        return [
            (self.n2[low >> 8], self.d2[low >> 8], self.two(low), self.e2[low >> 8]),
            (self.n1[last], self.d1[last], self.one[last, symbol], self.e1[last]),
            (flat(self.zero.sum()), flat((self.zero > 0).sum()), self.zero[symbol], flat(0)),
        ]


def code_lengths(gram: np.ndarray, count: np.ndarray, shorter: Shorter) -> np.ndarray:
    """log10 probability of each gram's last byte after the others. ``gram`` holds, for some three-byte contexts, all grams
    that are seen or asked for, each once, ``count`` their training counts."""
    levels = []  # from order ORDER down, as in Shorter.levels
    u, c, at = gram, count, np.arange(len(gram))
    for k in range(ORDER, 2, -1):
        ctx, in_ctx = np.unique(u >> 8, return_inverse=True)
        n, d = np.bincount(in_ctx, c), np.bincount(in_ctx, c > 0)
        low, low_at = np.unique(u & ((1 << 8 * k) - 1), return_inverse=True)
        c_low = np.bincount(low_at, c > 0, len(low)).astype(np.int64) if k > 3 else shorter.two(low)
        e = np.bincount(in_ctx, np.where(c > 0, c_low[low_at], 0))
        levels.append((n[in_ctx][at], d[in_ctx][at], c[at], e[in_ctx][at]))
        u, c, at = low, c_low, low_at[at]
    levels += shorter.levels(gram)
    out, open_ = np.zeros(len(gram)), np.ones(len(gram), bool)
    was_d, was_e = np.zeros(len(gram)), np.zeros(len(gram))
    for n, d, c, e in levels:
        rest_n, rest_d = n - was_e, d - was_d
        use = open_ & (rest_d > 0)
        hit = use & (c > 0)
        out[hit] += np.log10((2 * c[hit] - 1) / (2 * rest_n[hit]))
        escape = use & ~hit
        out[escape] += np.log10(rest_d[escape] / (2 * rest_n[escape]))
        open_ &= ~hit
        was_d, was_e = np.where(n > 0, d, was_d), np.where(n > 0, e, 0)
    out[open_] -= np.log10(256 - was_d[open_])
    return out


def ppm_scores(docs: DataFrame, held_out, batch_bytes: int = 24 << 20, most_grams: int = 8_000_000) -> DataFrame:
    """SCORES and train_tokens for ``docs`` (doc_id, text); learns from the rows where the column ``held_out`` is false.
    The coded trie is broadcast while it has at most ``most_grams`` grams (16 bytes each), and joined by batch beyond."""
    rows = docs.select(F.col("doc_id").cast("long"), F.coalesce("text", F.lit("")).alias("text"), held_out.alias("held_out"))
    size, n_train = rows.agg(F.sum(F.octet_length("text")), F.count_if(~F.col("held_out"))).first()
    n_batches = max(1, -(-(size or 0) // batch_bytes))
    dealt = rows.withColumn("batch", F.pmod(F.xxhash64("doc_id", "text"), F.lit(n_batches)).cast("int"))
    asked = dealt.groupBy("batch").applyInArrow(lean_group(word_requests), "batch int, key long, n long")
    # totals and answers read one exchange by word, so texts are asked once; a word has a row a batch at most
    same = Window.partitionBy("key")
    asked = asked.select("batch", "key", "n", F.sum("n").over(same).alias("total"), F.min("batch").over(same).alias("first"))
    kinds = F.count_if((F.col("total") > 0) & (F.col("batch") == F.col("first")))
    totals = asked.agg((F.coalesce(F.sum("n"), F.lit(0)) + n_train).alias("train_tokens"), (kinds + int(n_train > 0)).alias("kinds"))

    counts = rows.select("text", "held_out").mapInArrow(lean(gram_requests), "key long, n long").groupBy("key").agg(F.sum("n").alias("n")).persist(StorageLevel.DISK_ONLY)
    n_grams = counts.count()
    four = counts.filter("n > 0").select(F.col("key").bitwiseAND(F.lit((1 << 32) - 1)).alias("key")).distinct()
    two = four.groupBy(F.col("key").bitwiseAND(F.lit((1 << 24) - 1)).alias("key")).count().toArrow().sort_by("key")
    shorter = docs.sparkSession.sparkContext.broadcast(Shorter(two.column("key").to_numpy(), two.column("count").to_numpy()))

    def code(group: pa.Table) -> pa.Table:
        key = group.column("key").to_numpy()
        return pa.table({"key": key, "value": code_lengths(key, group.column("n").to_numpy(), shorter.value)})

    context = F.shiftright("key", 8).bitwiseAND(F.lit((1 << 24) - 1))
    part = F.pmod(F.xxhash64(context), F.lit(-(-n_grams // CODED) or 1))
    coded = counts.groupBy(part.alias("part")).applyInArrow(lean_group(code, 32 << 20), "key long, value double")
    # a word whose training count lies in one batch needs no answer there
    answers = asked.filter(F.col("total") != F.col("n")).select("batch", "key", F.col("total").cast("double").alias("value"))
    if n_grams <= most_grams:
        t = coded.toArrow().sort_by("key")
        shared = docs.sparkSession.sparkContext.broadcast((t.column("key").to_numpy(), t.column("value").to_numpy()))
    else:
        shared = None
        wanted = dealt.groupBy("batch").applyInArrow(lean_group(batch_grams), "batch int, key long")
        answers = answers.unionByName(wanted.join(coded, "key"))

    def score(group: pa.Table, answer: pa.Table) -> pa.Table:
        key, value = answer.column("key").to_numpy(), answer.column("value").to_numpy()
        order = np.argsort(key)
        key, value = key[order], value[order]
        del order
        gram, length = shared.value if shared else (key, value)
        release_memory()
        scores, base, known = [], [], []
        for _, texts in pieces(group):
            g, begin = grams(texts)
            scores.append(np.add.reduceat(looked_up(g, gram, length), begin))
        found, seen, counts = words_by_piece(group)
        for words, at, n in found:
            count = counts[np.searchsorted(seen, words)].astype(float)
            if len(key):
                there = np.minimum(np.searchsorted(key, words), len(key) - 1)
                count = np.where(key[there] == words, value[there], count)
            some, begin = n > 0, np.cumsum(n) - n
            base.append(np.full(len(n), log10(n_train + 0.5)))
            known.append(np.full(len(n), int(n_train > 0)))
            if some.any():
                base[-1][some] += np.add.reduceat(np.log10(count + 0.5)[at], begin[some])
                known[-1][some] += np.add.reduceat((count > 0)[at].astype(np.int64), begin[some])
        n = np.concatenate([n for _, _, n in found])
        scores, base, known = map(np.concatenate, (scores, base, known))
        return pa.table({"doc_id": group.column("doc_id"), "held_out": group.column("held_out"), "n_tokens": pa.array(n + 1, pa.int64()), "n_known": pa.array(known, pa.int64()), "base_score": base, "score": scores})

    out = dealt.groupBy("batch").cogroup(answers.groupBy("batch")).applyInArrow(score, SCORES)
    # the texts' one exchange serves requests and scores alike, as all of it is one plan
    out = out.crossJoin(F.broadcast(totals))
    below = F.log10(F.col("train_tokens") + 0.5 * (F.col("kinds") + 1))
    return out.withColumn("base_score", F.col("base_score") - F.col("n_tokens") * below).drop("kinds")


def op1_ppm_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    held = F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 1, F.lit(False))
    return ppm_scores(docs, held)
