"""Language identification by interpolated Kneser-Ney character language models.

Texts are lower-cased, everything but letters becomes one space. Each language's model is trained in one task from a
bounded sample (``chars_per_language``, at most ``total_chars`` over all languages): n-gram hashes in sorted arrays with their
interpolated log-probabilities, context hashes with their back-off weights. The driver merges them into one sorted hash
array per order, whose rows hold one resolved log-probability a language, so that scoring looks every position up once and
only positions unseen in all languages again at lower orders.

A text gets the language of the lowest cross-entropy per character. Its score is a softmax of the cross-entropies
whose temperature is fitted on a held-back tenth of the sample; ``lang`` is ``und`` where that score or the cross-entropy lies
outside the calibrated bounds, ``lang_best`` never rejects a text that has letters.

Defined results: a text that is null or has no letter is ``und`` with score 0; rows with a null language or id are never
learned from; without anything to learn from all texts are ``und``; ties go to the first language in name order; other
columns pass through and results come in one struct ``language``.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import chunks, table

UNKNOWN = "und"
#: Probability of a character that no language has seen, given that it is such.
FLOOR = np.log(1e-4)
BLOB = "lang string, level int, gram binary, ctx binary, suffix binary, logp binary, ctx_key binary, ctx_logw binary, rest double"
RESULT = "struct<lang_best: string, lang: string, score: double, cross_entropy: double>"


def codes(text: str, order: int) -> tuple[np.ndarray, bool]:
    """Code points of the normalised text after ``order`` - 1 spaces, and whether it has a letter."""
    x = np.frombuffer(text.lower().encode("utf-32-le", "replace"), np.uint32)
    kinds, at = np.unique(x, return_inverse=True) if len(x) > 4096 else (x, None)
    letter = np.fromiter((chr(c).isalpha() for c in kinds.tolist()), bool, len(kinds)) if at is not None else _letters(x)
    if at is not None:
        letter = letter[at]
    x = np.where(letter, x, 32)
    keep = letter.copy()
    keep[1:] |= letter[:-1]
    x = x[keep]
    end = 0 if len(x) and x[-1] == 32 else 1
    return np.concatenate((np.full(order - 1, 32, np.uint32), x, np.full(end, 32, np.uint32))), bool(letter.any())


#: ASCII and Latin letters by table, others one by one.
_LATIN = np.fromiter((chr(c).isalpha() for c in range(0x250)), bool, 0x250)


def _letters(x: np.ndarray) -> np.ndarray:
    out = np.zeros(len(x), bool)
    low = x < 0x250
    out[low] = _LATIN[x[low]]
    for i in np.flatnonzero(~low):
        out[i] = chr(x[i]).isalpha()
    return out


def gram_hashes(x: np.ndarray, order: int) -> list[np.ndarray]:
    """Hash of the k-gram that begins at each position, for k = 0..order (position counts shrink by one an order)."""
    out = [np.full(len(x) + 1, 0x243F6A8885A308D3, np.uint64)]
    for k in range(1, order + 1):
        h = out[-1][: len(x) - k + 1] * np.uint64(0x9E3779B97F4A7C15) + x[k - 1 :].astype(np.uint64)
        out.append(h ^ (h >> np.uint64(31)))
    return out


def train(texts: list[str], order: int) -> list[dict]:
    """Levels 1..order of one language: gram, ctx, suffix, logp sorted by gram; ctx_key, ctx_logw; rest (level 1's floor)."""
    xs = [codes(t, order)[0] for t in texts]
    starts = np.cumsum([0, *map(len, xs)])
    x = np.concatenate(xs) if xs else np.empty(0, np.uint32)
    inside = np.ones(max(0, len(x) - order + 1), bool)
    for s in starts[1:-1]:
        inside[s - order + 1 : s] = False
    windows = np.lib.stride_tricks.sliding_window_view(x, order)[inside]
    _, first, count = np.unique(gram_hashes(x, order)[order][inside], return_index=True, return_counts=True)
    reps = windows[first]
    levels: list[tuple[np.ndarray, np.ndarray]] = [(reps, count)]
    for k in range(order - 1, 0, -1):
        _, first, count = np.unique(_hash_rows(levels[0][0][:, 1:]), return_index=True, return_counts=True)
        levels.insert(0, (levels[0][0][first, 1:], count))
    out: list[dict] = []
    for k, (reps, count) in enumerate(levels, 1):
        gram, ctx, suffix = _hash_rows(reps), _hash_rows(reps[:, :-1]), _hash_rows(reps[:, 1:])
        once, twice = int((count == 1).sum()), int((count == 2).sum())
        d = min(0.95, max(0.05, once / (once + 2 * twice))) if once + twice else 0.5
        keys, at = np.unique(ctx, return_inverse=True)
        total, kinds = np.bincount(at, count), np.bincount(at)
        weight = d * kinds / total
        if out:
            lower = np.exp(out[-1]["logp"][np.searchsorted(out[-1]["gram"], suffix)])
        else:
            lower = np.full(len(gram), np.exp(FLOOR))
        p = np.maximum(count - d, 0) / total[at] + weight[at] * lower
        o = np.argsort(gram)
        out.append({"gram": gram[o], "ctx": ctx[o], "suffix": suffix[o], "logp": np.log(p[o]), "ctx_key": keys, "ctx_logw": np.log(weight), "rest": float(np.log(weight[0]) + FLOOR) if k == 1 else 0.0})
    return out


def _hash_rows(rows: np.ndarray) -> np.ndarray:
    h = np.full(len(rows), 0x243F6A8885A308D3, np.uint64)
    for k in range(rows.shape[1]):
        h = h * np.uint64(0x9E3779B97F4A7C15) + rows[:, k].astype(np.uint64)
        h ^= h >> np.uint64(31)
    return h


def _find(keys: np.ndarray, wanted: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    at = np.minimum(np.searchsorted(keys, wanted), max(len(keys) - 1, 0))
    return at, keys[at] == wanted if len(keys) else np.zeros(len(wanted), bool)


@dataclass
class LanguageModel:
    langs: list[str]
    order: int
    gram: list[np.ndarray]  # by level - 1, sorted
    logp: list[np.ndarray]  # rows of one value a language
    ctx: list[np.ndarray]
    logw: list[np.ndarray]
    rest: np.ndarray
    temperature: float = 1.0
    least_score: float = 0.0
    most_entropy: float = float("inf")

    @classmethod
    def merged(cls, models: dict[str, list[dict]], order: int) -> LanguageModel:
        langs = sorted(models)
        m = cls(langs, order, [], [], [], [], np.array([models[n][0]["rest"] for n in langs]))
        for k in range(order):
            parts = [models[n][k] for n in langs]
            ctx = np.unique(np.concatenate([p["ctx_key"] for p in parts]))
            logw = np.zeros((len(ctx), len(langs)), np.float32)
            gram, first = np.unique(np.concatenate([p["gram"] for p in parts]), return_index=True)
            gctx, suffix = (np.concatenate([p[c] for p in parts])[first] for c in ("ctx", "suffix"))
            for j, p in enumerate(parts):
                logw[np.searchsorted(ctx, p["ctx_key"]), j] = p["ctx_logw"]
            if k:
                logp = m.logp[-1][np.searchsorted(m.gram[-1], suffix)] + logw[np.searchsorted(ctx, gctx)]
            else:
                logp = np.tile(m.rest, (len(gram), 1))
            logp = logp.astype(np.float32)
            for j, p in enumerate(parts):
                logp[np.searchsorted(gram, p["gram"]), j] = p["logp"]
            m.gram.append(gram)
            m.logp.append(logp)
            m.ctx.append(ctx)
            m.logw.append(logw)
        return m

    def entropies(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Cross-entropy (nats a character) of each text in each language, and which texts have letters."""
        xs, letters = zip(*(codes(t, self.order) for t in texts))
        sizes = np.fromiter(map(len, xs), np.int64, len(xs))
        begin = np.cumsum(sizes) - sizes
        n = self.order
        hashes = gram_hashes(np.concatenate(xs), n)
        at, hit = _find(self.gram[n - 1], hashes[n])
        rows = self.logp[n - 1][at]
        miss = np.flatnonzero(~hit)
        if len(miss):
            value, open_ = np.zeros((len(miss), len(self.langs))), np.arange(len(miss))
            for k in range(n, 0, -1):
                pos = miss[open_] + (n - k)
                at, hit = _find(self.gram[k - 1], hashes[k][pos])
                value[open_[hit]] += self.logp[k - 1][at[hit]]
                open_, pos = open_[~hit], pos[~hit]
                if not len(open_):
                    break
                at, known = _find(self.ctx[k - 1], hashes[k - 1][pos])
                value[open_[known]] += self.logw[k - 1][at[known]] if k > 1 else 0.0
            value[open_] += self.rest
            rows[miss] = value
        sums = np.empty((len(xs), len(self.langs)))
        for i, (b, s) in enumerate(zip(begin.tolist(), sizes.tolist())):
            sums[i] = rows[b : b + s - n + 1].sum(0, dtype=np.float64)
        return -sums / (sizes - n + 1)[:, None], np.array(letters)

    def scores(self, entropy: np.ndarray) -> np.ndarray:
        z = -(entropy - entropy.min(1, keepdims=True)) * self.temperature
        return np.exp(z) / np.exp(z).sum(1, keepdims=True)

    def calibrated(self, entropy: np.ndarray, truth: np.ndarray) -> LanguageModel:
        """Temperature by likelihood; bounds that 99.5 % of the rightly named texts keep, with slack."""
        if len(truth):
            def loss(t: float) -> float:
                self.temperature = t
                return -float(np.log(np.maximum(self.scores(entropy)[np.arange(len(truth)), truth], 1e-12)).mean())

            self.temperature = min((2.0**k for k in range(-1, 8)), key=loss)
            right = entropy.argmin(1) == truth
            if right.any():
                best = entropy[right].min(1)
                self.least_score = 0.5 * float(np.quantile(self.scores(entropy)[right].max(1), 0.005))
                self.most_entropy = float(best.mean() + max(8 * best.std(), 1.0))
        return self


def fit_languages(docs: DataFrame, order: int = 4, chars_per_language: int = 1_000_000, total_chars: int = 16_000_000) -> LanguageModel | None:
    """Learns from ``docs`` (doc_id, text, lang): a hash sample within the bounds; a tenth of it calibrates."""
    docs = docs.select("doc_id", "text", "lang").filter(F.col("lang").isNotNull() & F.col("text").isNotNull() & F.col("doc_id").isNotNull())
    sizes = docs.groupBy("lang").agg(F.sum(F.length("text")).alias("chars"), F.count("*").alias("n")).collect()
    if not sizes:
        return None
    each = min(chars_per_language, total_chars // len(sizes))
    share = {r.lang: min(1.0, each / max(r.chars, 1)) for r in sizes}
    few = {r.lang for r in sizes if r.n * share[r.lang] < 50}
    cut = F.create_map(*[F.lit(v) for lang, s in share.items() for v in (lang, int(s * (1 << 30)))])[F.col("lang")]
    sample = docs.filter(F.pmod(F.xxhash64("doc_id", "text"), F.lit(1 << 30)) < cut)
    aside = (F.pmod(F.xxhash64("text", "doc_id"), F.lit(10)) == 0) & ~F.col("lang").isin(*few)

    def learn(t: pa.Table) -> pa.Table:
        levels = train(t.column("text").to_pylist(), order)
        raw = lambda a: a.tobytes()
        rows = [{"lang": t.column("lang")[0].as_py(), "level": k, **{c: raw(m[c]) for c in ("gram", "ctx", "suffix", "logp", "ctx_key", "ctx_logw")}, "rest": m["rest"]} for k, m in enumerate(levels, 1)]
        return pa.Table.from_pylist(rows, pa.schema([("lang", pa.string()), ("level", pa.int32()), *[(c, pa.binary()) for c in ("gram", "ctx", "suffix", "logp", "ctx_key", "ctx_logw")], ("rest", pa.float64())]))

    models: dict[str, list[dict]] = {}
    for r in sample.filter(~aside).groupBy("lang").applyInArrow(learn, BLOB).orderBy("lang", "level").collect():
        kinds = {"gram": np.uint64, "ctx": np.uint64, "suffix": np.uint64, "ctx_key": np.uint64, "logp": float, "ctx_logw": float}
        models.setdefault(r.lang, []).append({c: np.frombuffer(r[c], k) for c, k in kinds.items()} | {"rest": r.rest})
    if not models:
        return None
    model = LanguageModel.merged(models, order)
    held = [r for r in sample.filter(aside).select("text", "lang").collect() if r.lang in models]
    if held:
        entropy, letters = model.entropies([r.text for r in held])
        truth = np.array([model.langs.index(r.lang) for r in held])
        model.calibrated(entropy[letters], truth[letters])
    return model


def identify(docs: DataFrame, model: LanguageModel | None) -> DataFrame:
    """``docs`` with a struct ``language``."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    schema = T.StructType([f for f in docs.schema.fields if f.name != "language"]).add("language", T._parse_datatype_string(RESULT))
    docs = docs.select(*[f.name for f in schema.fields[:-1]])
    at = docs.columns.index("text")

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for b in batches:
            texts = [t or "" for t in b.column(at).to_pylist()]
            best, lang, score, ce = [UNKNOWN] * len(texts), [UNKNOWN] * len(texts), [0.0] * len(texts), [None] * len(texts)
            for lo, hi in chunks([t.encode() for t in texts], 1 << 20) if m else ():
                entropy, letters = m.entropies(texts[lo:hi])
                scores, first = m.scores(entropy), entropy.argmin(1)
                for i in np.flatnonzero(letters):
                    j, k = lo + int(i), int(first[i])
                    best[j], score[j], ce[j] = m.langs[k], float(scores[i, k]), float(entropy[i, k])
                    lang[j] = m.langs[k] if score[j] >= m.least_score and ce[j] <= m.most_entropy else UNKNOWN
            out = pa.StructArray.from_arrays([pa.array(best, pa.string()), pa.array(lang, pa.string()), pa.array(score, pa.float64()), pa.array(ce, pa.float64())], ["lang_best", "lang", "score", "cross_entropy"])
            yield pa.RecordBatch.from_arrays([*b.columns, out], names=[*b.schema.names, "language"])

    return docs.mapInArrow(judge, schema)


def op6_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text", "lang")
    fold = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4
    model = fit_languages(docs.filter(fold != 2))
    found = identify(docs.select("doc_id", "text"), model)
    return found.select("doc_id", F.coalesce(fold == 2, F.lit(False)).alias("held_out"), F.col("language.lang_best").alias("lang_pred"), F.col("language.score").alias("score"), F.col("language.lang").alias("lang_or_rejected"), F.col("language.cross_entropy").alias("cross_entropy"))
