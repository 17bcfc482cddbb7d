"""Near-duplicate classes: MinHash signatures, a multi-index Hamming join, and a check on full sets.

A text's set is its distinct shingles of ``words`` words. Texts of equal sets form one class; the rest works on classes.

* Signatures: ``positions`` MinHash values, 16 bits each. The distance of two signatures is the number of positions that
  differ, with mean positions * (1 - similarity).
* Index: positions are split into chunks of five; each chunk gives five keys, every one leaving a position out (the
  allowed chunk error). By the pigeonhole rule two signatures of distance 2 * chunks - 1 or less meet under one key at
  least. ``positions`` is set so that linked sets lie beyond that distance with a probability below 1e-5.
* Links: each class belongs to the family of the most connected pivot of its keys (an original, where there are variants).
  A family is settled in bounded blocks that all hold the pivot, so each set travels once. Where a key then still holds
  several components, what meets the largest of them (under any key) is compared with it and with each other in cells of
  bounded blocks, ordered by size; members of one component never need each other. Tasks count all pairs from postings
  and return only links that join something, so no pairs are written out and no link between components is left out.
* A 64-bit sketch of one-bit MinHash values and the set sizes filter pairs before sets are compared.

Sets travel as sorted 64-bit hashes. Only classes that share a key with another are compared, and only their texts are
fetched. Components come from star contractions on DataFrames; nothing of documents reaches the driver.

Defined results: texts are lower-cased in A-Z only; fewer than ``words`` words are one shingle, the whole sequence; a
null or wordless text has no set, size 0, and is its own component; a null doc_id never names a component and is kept only
where all its members' ids are null; repeated rows are members like any others; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from math import ceil, log, sqrt

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.components import checkpoint_dir, connected_components
from .common import lean, lean_group, maybe_among, slices, table

CHUNK = 5
#: Odd 64-bit multipliers come from this rule, so no table is needed.
GOLDEN = 0x9E3779B97F4A7C15
MASK = (1 << 64) - 1


def odd_numbers(n: int, seed: int) -> np.ndarray:
    out, x = [], seed & MASK
    for _ in range(n):
        x = (x + GOLDEN) & MASK
        z = (x ^ (x >> 30)) * 0xBF58476D1CE4E5B9 & MASK
        z = (z ^ (z >> 27)) * 0x94D049BB133111EB & MASK
        out.append(z ^ (z >> 31) | 1)
    return np.array(out, np.uint64)


def mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def positions_for(similarity: float) -> int:
    """The least multiple of the chunk, 65 at least, whose key guarantee lies 4.3 standard deviations beyond the mean distance."""
    p, n = 1 - similarity, 65
    while 0.4 * n - 0.5 < p * n + 4.3 * sqrt(n * p * (1 - p)):
        n += CHUNK
    return n


def sketch_bound(similarity: float) -> int:
    p = (1 - similarity) / 2
    return ceil(64 * p + 6.5 * sqrt(64 * p * (1 - p)))


class Shingler:
    """Sets of shingle hashes; word hashes are kept for a bounded number of words."""

    def __init__(self, words: int):
        self.words, self.known = words, {}
        self.by = odd_numbers(words, words)

    def sets(self, texts: list[bytes]) -> list[np.ndarray]:
        known, h = self.known, xxhash.xxh64_intdigest
        if len(known) > 400_000:
            known.clear()
        out = []
        for t in texts:
            ws = t.lower().split()
            if not ws:
                out.append(np.empty(0, np.uint64))
                continue
            ids = []
            for w in ws:
                v = known.get(w)
                if v is None:
                    known[w] = v = h(w)
                ids.append(v)
            x = np.array(ids, np.uint64)
            n = min(self.words, len(x))
            s = np.full(len(x) - n + 1, n, np.uint64)
            for i in range(n):
                s = s + x[i : len(x) - n + 1 + i] * self.by[i]
            out.append(np.unique(mix(s)))
        return out


def class_id(s: np.ndarray) -> int:
    return xxhash.xxh3_64_intdigest(s.tobytes()) - (1 << 63)


def signatures(sets: list[np.ndarray], n: int) -> tuple[np.ndarray, np.ndarray]:
    """16-bit MinHash values (rows of n), and 64 one-bit ones as a signed long. No set may be empty."""
    m = max(n, 64)
    a, b = odd_numbers(m, 11), odd_numbers(m, 12)
    u = np.concatenate(sets)
    at = np.cumsum([0, *map(len, sets)])[:-1]
    sig, sketch = np.empty((len(sets), n), np.uint16), np.zeros(len(sets), np.uint64)
    for i in range(m):
        low = mix(np.minimum.reduceat(u * a[i] + b[i], at))
        if i < n:
            sig[:, i] = (low >> np.uint64(48)).astype(np.uint16)
        if i < 64:
            sketch |= (low & np.uint64(1)) << np.uint64(i)
    return sig, sketch.view(np.int64)


def index_keys(sig: np.ndarray) -> np.ndarray:
    """One key for each chunk and left-out position: rows of as many keys as the signature has positions."""
    n = sig.shape[1]
    by, tag = odd_numbers(n, 21), odd_numbers(n, 22)
    terms = (sig.astype(np.uint64) + np.uint64(1)) * by
    whole = terms.reshape(len(sig), n // CHUNK, CHUNK).sum(2, dtype=np.uint64)
    return mix(np.repeat(whole, CHUNK, axis=1) - terms + tag).view(np.int64)


def sketch_documents(docs: DataFrame, words: int, n: int) -> DataFrame:
    """doc_id, text_id (hash of the text), n_shingles, cid (class), sketch, sig; the last three are null for an empty set."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingler = Shingler(words)
        for b in batches:
            for part, texts in slices(b, 1):
                sets = shingler.sets(texts)
                some = [i for i, s in enumerate(sets) if len(s)]
                cid, sk, sg = ([None] * len(sets) for _ in range(3))
                if some:
                    sig, sketch = signatures([sets[i] for i in some], n)
                    for j, i in enumerate(some):
                        cid[i], sk[i], sg[i] = class_id(sets[i]), int(sketch[j]), sig[j].tobytes()
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), pa.array(map(len, sets), pa.int64()), pa.array(cid, pa.int64()), pa.array(sk, pa.int64()), pa.array(sg, pa.binary())], ["doc_id", "text_id", "n_shingles", "cid", "sketch", "sig"])

    return docs.select(F.col("doc_id").cast("long"), "text", F.xxhash64("text")).mapInArrow(lean(run), "doc_id long, text_id long, n_shingles long, cid long, sketch long, sig binary")


def class_keys(classes: DataFrame, n: int) -> DataFrame:
    """(key, cid) for every key of every class."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for part in (b.slice(i, 4096) for i in range(0, b.num_rows, 4096)):
                sig = np.frombuffer(b"".join(part.column(1).to_pylist()), np.uint16).reshape(part.num_rows, n)
                keys = index_keys(sig)
                yield pa.record_batch({"key": keys.ravel(), "cid": np.repeat(part.column(0).to_numpy(zero_copy_only=False), n)})

    return classes.select("cid", "sig").mapInArrow(lean(run), "key long, cid long")


def fetch_sets(docs: DataFrame, wanted: DataFrame, words: int) -> DataFrame:
    """(cid, set) of the wanted (cid, doc_id); a fetched text counts only if its set is the class's."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingler = Shingler(words)
        for b in batches:
            for part, texts in slices(b, 1):
                rows = [(c, s.tobytes()) for c, s in zip(part.column(0).to_pylist(), shingler.sets(texts)) if len(s) and class_id(s) == c]
                yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.binary())], ["cid", "set"])

    d = maybe_among(docs.select(F.col("doc_id").cast("long").alias("d"), "text"), "d", wanted)
    return wanted.join(d, F.col("d").eqNullSafe(F.col("doc_id"))).select("cid", "text").mapInArrow(lean(run), "cid long, set binary").dropDuplicates(["cid"])


def linked(ids: list[int], sets: list[np.ndarray], percent: int, root: np.ndarray | None = None, lead: np.ndarray | None = None) -> list[tuple[int, int]]:
    """Links enough to join all sets that are linked with each other, directly or through others of the list. Every pair is
    counted, by postings of the shingles, unless its ends are joined by then. ``root`` names what is joined beforehand; with
    ``lead`` only pairs with one of these rows count."""
    sizes = np.fromiter(map(len, sets), np.int64, len(sets))
    _, at = np.unique(np.concatenate(sets), return_inverse=True)
    owner = np.repeat(np.arange(len(sets)), sizes)
    order = np.argsort(at, kind="stable")
    posts, ends = owner[order], np.cumsum(np.bincount(at))
    begins = ends - np.bincount(at)
    stops = np.cumsum(sizes)
    root, out = (np.arange(len(sets)) if root is None else root.copy()), []
    for i in range(len(sets)) if lead is None else np.flatnonzero(lead).tolist():
        mine = at[stops[i] - sizes[i] : stops[i]]
        both = np.bincount(np.concatenate([posts[b:e] for b, e in zip(begins[mine].tolist(), ends[mine].tolist())]), minlength=len(sets))
        for j in np.flatnonzero((100 * both >= percent * (sizes[i] + sizes - both)) & (root != root[i])).tolist():
            if root[j] != root[i]:
                out.append((ids[i], ids[j]))
                root[root == root[j]] = root[i]
        if (root == root[0]).all():
            break
    return out


def _pairs(found: list[tuple[int, int]]) -> pa.Table:
    return pa.table({"src": pa.array([f[0] for f in found], pa.int64()), "dst": pa.array([f[1] for f in found], pa.int64())})


def _sets(t: pa.Table) -> list[np.ndarray]:
    return [np.frombuffer(x, np.uint64) for x in t.column("set").to_pylist()]


def family_links(lead: DataFrame, sets: DataFrame, percent: int, most: int = 1 << 19) -> DataFrame:
    """Links within blocks of families (family, cid, size), the family's pivot being in each block. A set travels once and a
    pivot once a block, and a task holds a block of about ``most`` shingles."""
    k = F.ceil(F.sum("size") / most).cast("int")
    blocks = lead.groupBy("family").agg(k.alias("k"))
    rows = lead.join(blocks, "family").select("family", "cid", F.pmod(F.xxhash64("cid"), F.col("k")).cast("int").alias("b"))
    pivots = blocks.select("family", F.col("family").alias("cid"), F.explode(F.sequence(F.lit(0), F.col("k") - 1)).alias("b"))

    def run(t: pa.Table) -> pa.Table:
        return _pairs(linked(t.column("cid").to_pylist(), _sets(t), percent))

    return rows.unionByName(pivots).join(sets, "cid").groupBy("family", "b").applyInArrow(lean_group(run), "src long, dst long")


def cells(rows: DataFrame, weight: Column, most: int, percent: int) -> DataFrame:
    """``rows`` (main, cid, component, size, ...) dealt into the cells (main, g, i, x) in which they are compared.

    A row of the main component needs no other one of it, so blocks of the others (U) meet blocks of the main one (V) and
    each other. Sets more than a size step apart are not compared: a step g holds the sizes of one step and the next.
    A block weighs about ``most``, so a cell is bounded; a row of V travels once a block of U in its step."""
    # a little below the ratio, so that rounding cannot part two sizes that may be linked
    step = F.floor(F.log("size") / F.lit(-log(percent / 100 - 0.005))).cast("int")
    own = rows.withColumn("step", step).withColumn("outer", F.col("component") != F.col("main"))
    own = own.withColumn("g", F.explode(F.array(F.col("step"), F.col("step") - 1))).withColumn("low", F.col("step") == F.col("g"))
    blocks = lambda side: F.coalesce(F.ceil(F.sum(F.when(side, weight)) / most), F.lit(0)).cast("int")
    sizes = own.groupBy("main", "g").agg(blocks(F.col("outer")).alias("ku"), blocks(~F.col("outer")).alias("kv"), F.max("low").alias("some")).filter("some and ku > 0")
    own = own.join(sizes.drop("some"), ["main", "g"]).withColumn("h", F.xxhash64("cid"))
    u, v = F.pmod("h", F.col("ku")).cast("int"), F.expr("cast(pmod(h, greatest(kv, 1)) as int)")
    to = lambda i, x: F.struct(i.cast("int").alias("i"), x.cast("int").alias("x"))
    with_main = F.transform(F.sequence(F.lit(0), F.greatest("kv", F.lit(1)) - 1), lambda x: to(u, x))
    with_others = F.transform(F.filter(F.sequence(F.lit(0), F.col("ku") - 1), lambda j: j != u), lambda j: to(F.least(j, u), F.col("kv") + 1 + F.greatest(j, u)))
    home = F.transform(F.sequence(F.lit(0), F.col("ku") - 1), lambda i: to(i, v))
    return own.withColumn("to", F.explode(F.when(F.col("outer"), F.concat(with_main, with_others)).otherwise(home))).select(*rows.columns, "outer", "low", "g", "to.i", "to.x")


CELL = ("main", "g", "i", "x")


def with_partner(rows: DataFrame, percent: int, near: int, most: int = 8192) -> DataFrame:
    """The rows (main, cid, component, size, sketch) that sizes and sketches allow a link with one of another component."""

    def run(t: pa.Table) -> pa.Table:
        comp, size, sketch = (t.column(c).to_numpy() for c in ("component", "size", "sketch"))
        outer, low = (t.column(c).to_numpy(zero_copy_only=False) for c in ("outer", "low"))
        keep = np.zeros(len(comp), bool)
        for i in np.flatnonzero(outer).tolist():
            ok = (comp != comp[i]) & (100 * np.minimum(size, size[i]) >= percent * np.maximum(size, size[i])) & (low | low[i])
            ok[ok] = np.bitwise_count(sketch[ok] ^ sketch[i]) <= near
            keep |= ok
            keep[i] |= ok.any()
        return t.select(["main", "cid"]).filter(pa.array(keep, pa.bool_()))

    light = cells(rows, F.lit(1), most, percent).select("main", "cid", "component", "size", "sketch", "outer", "low", "g", "i", "x")
    found = light.groupBy(*CELL).applyInArrow(lean_group(run), "main long, cid long").distinct()
    return rows.select("main", "cid", "component", "size").join(found, ["main", "cid"], "left_semi")


def component_links(rows: DataFrame, sets: DataFrame, percent: int, most: int = 1 << 19) -> DataFrame:
    """Links between components (src, dst), enough to join those that any two compared rows link."""

    def run(t: pa.Table) -> pa.Table:
        comp, root = np.unique(t.column("component").to_numpy(), return_inverse=True)
        found = linked(comp[root].tolist(), _sets(t), percent, root, t.column("outer").to_numpy(zero_copy_only=False))
        return _pairs(found)

    dealt = cells(rows, F.col("size"), most, percent).select("cid", "component", "outer", *CELL)
    return dealt.join(sets, "cid").groupBy(*CELL).applyInArrow(lean_group(run), "src long, dst long")


def near_duplicates(docs: DataFrame, words: int = 5, percent: int = 80) -> DataFrame:
    """doc_id, text_id, n_shingles, component_id, class_id, kept: a row for each row of ``docs``.

    ``text_id`` is ``xxhash64(text)``; ``class_id`` names the component whatever the ids are, and is null for an empty set."""
    checkpoint_dir(docs.sparkSession)  # checkpoints keep plans short, so that the driver holds little of them
    similarity = percent / 100
    n, near = positions_for(similarity), sketch_bound(similarity)
    sketched = sketch_documents(docs, words, n).checkpoint()
    classes = sketched.filter(F.col("cid").isNotNull()).groupBy("cid").agg(F.min("doc_id").alias("doc_id"), F.first("n_shingles").alias("size"), F.first("sketch").alias("sketch"), F.first("sig").alias("sig")).checkpoint()

    keys = class_keys(classes, n)
    shared = keys.groupBy("key").agg(F.min("cid").alias("lo"), F.max("cid").alias("hi"), F.count("*").alias("n")).filter("lo <> hi").select("key", "n")
    traits = classes.select("cid", "size", "sketch")
    # members of keys that several classes share
    members = keys.join(shared, "key").join(traits, "cid").checkpoint()
    # a key's pivot is the member that meets most others under its keys: the original, where the others are its variants
    weight = members.groupBy("cid").agg(F.sum("n").alias("weight"))
    pivot_of = members.select("key", "cid").join(weight, "cid").groupBy("key").agg(F.max_by("cid", F.struct("weight", "cid")).alias("pivot"))

    def alike(s1, k1, s2, k2):
        return (100 * F.least(s1, s2) >= percent * F.greatest(s1, s2)) & (F.bit_count(k1.bitwiseXOR(k2)) <= near)

    pivots = traits.join(weight, "cid").select(F.col("cid").alias("pivot"), F.col("size").alias("psize"), F.col("sketch").alias("psketch"), "weight")
    tried = members.join(pivot_of, "key").filter("cid <> pivot").select("cid", "pivot", "size", "sketch").distinct().join(pivots, "pivot")
    tried = tried.filter(alike(F.col("size"), F.col("sketch"), F.col("psize"), F.col("psketch")))
    lead = tried.groupBy("cid").agg(F.max_by("pivot", F.struct("weight", "pivot")).alias("family"), F.first("size").alias("size")).checkpoint()

    wanted = members.select("cid").distinct().join(classes.select("cid", "doc_id"), "cid")
    sets = fetch_sets(docs, wanted, words).checkpoint()
    links = family_links(lead, sets, percent).checkpoint()
    parts = connected_components(links).withColumnRenamed("id", "cid")

    # keys that hold several components yet: all that meet a main component under any key are compared in its cells
    c = F.col
    placed = members.join(parts, "cid", "left").withColumn("component", F.coalesce("component", "cid"))
    mixed = placed.groupBy("key", "component").count().groupBy("key").agg(F.max_by("component", F.struct("count", "component")).alias("main"), F.count("*").alias("kinds")).filter("kinds > 1")
    open_ = placed.join(mixed.select("key", "main"), "key").select("main", "cid", "component", "size", "sketch").distinct().checkpoint()
    meet = with_partner(open_, percent, near).checkpoint()
    more = connected_components(component_links(meet, sets, percent)).select(c("id").alias("component"), c("component").alias("joined"))

    whole = sketched.select("doc_id", "text_id", "n_shingles", "cid").join(parts, "cid", "left").withColumn("component", F.coalesce("component", "cid"))
    whole = whole.join(more, "component", "left").withColumn("component", F.coalesce("joined", "component")).drop("joined")
    named = whole.filter(c("component").isNotNull()).groupBy("component").agg(F.min("doc_id").alias("component_id"))
    out = whole.join(named, "component", "left")
    component_id = F.coalesce("component_id", "doc_id")
    kept = F.coalesce(c("doc_id") == component_id, component_id.isNull())
    return out.select("doc_id", "text_id", "n_shingles", component_id.alias("component_id"), c("component").alias("class_id"), kept.alias("kept"))


def op9_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents", "doc_id", "text"), words=3, percent=85).select("doc_id", "n_shingles", "component_id", "kept")
