import numpy as np

from epsgraph.llm import langid
from epsgraph.llm.common import table
from tests.conftest import SF

TEXTS = {"aa": ["ba bab abba abab", "bab ab"], "bb": ["cdc dcd ccd", "dd cc, Cd!"]}


def plain_kn(texts, order):
    """p(c | context) by the textbook recursion, on strings."""
    padded = [" " * (order - 1) + " ".join("".join(c if c.isalpha() else " " for c in t.lower()).split()) + " " for t in texts]
    counts = [None] * (order + 1)
    counts[order] = {}
    for t in padded:
        for i in range(len(t) - order + 1):
            g = t[i : i + order]
            counts[order][g] = counts[order].get(g, 0) + 1
    for k in range(order - 1, 0, -1):
        counts[k] = {}
        for g in counts[k + 1]:
            counts[k][g[1:]] = counts[k].get(g[1:], 0) + 1

    def p(c, h):
        k = len(h) + 1
        if k == 0:
            return 0
        once, twice = (sum(v == n for v in counts[k].values()) for n in (1, 2))
        d = min(0.95, max(0.05, once / (once + 2 * twice))) if once + twice else 0.5
        lower = p(c, h[1:]) if h else np.exp(langid.FLOOR)
        ctx = [v for g, v in counts[k].items() if g[:-1] == h]
        if not ctx:
            return lower
        return max(counts[k].get(h + c, 0) - d, 0) / sum(ctx) + d * len(ctx) / sum(ctx) * lower

    return p


def test_cross_entropy_equals_the_recursion():
    order = 3
    model = langid.LanguageModel.merged({n: langid.train(ts, order) for n, ts in TEXTS.items()}, order)
    tried = ["ab ba", "cd abz", "q", "bab  bab!"]
    got, letters = model.entropies(tried)
    assert letters.all()
    for j, n in enumerate(model.langs):
        p = plain_kn(TEXTS[n], order)
        for i, t in enumerate(tried):
            s = " " * (order - 1) + " ".join("".join(c if c.isalpha() else " " for c in t.lower()).split()) + " "
            want = [-np.log(p(s[k], s[k - order + 1 : k])) for k in range(order - 1, len(s))]
            assert abs(got[i, j] - np.mean(want)) < 1e-4
    assert [model.langs[k] for k in got.argmin(1)][:2] == ["aa", "bb"]


def test_held_out_accuracy(spark):
    got = langid.op6_language_id(spark, SF).join(table(spark, SF, "documents", "doc_id", "lang"), "doc_id").toPandas()
    held = got[got.held_out]
    assert len(held) > 100 and (held.lang_pred == held.lang).mean() > 0.98
    assert got.score.between(0, 1).all()
    assert (held.lang_or_rejected == held.lang).mean() > 0.95


def test_odd_rows(spark):
    rows = [(1, None, None), (2, "", "aa"), (None, "ba", "aa"), (3, "12 ?!", "bb"), (4, "x" * 50000, None), (4, "漢字かな", "zz"), (4, "漢字かな", "zz")]
    docs = spark.createDataFrame([(*r, "k") for r in rows], "doc_id long, text string, lang string, language string")
    model = langid.fit_languages(docs)
    out = langid.identify(docs, model).collect()
    assert [r.language.lang_best for r in out if r.doc_id != 4 and r.text != "ba"] == ["und"] * 3
    assert all(r.language.lang_best == "zz" for r in out if r.text == "漢字かな")
    assert langid.fit_languages(docs.limit(0)) is None
    assert langid.identify(docs, None).filter("language.lang_best != 'und'").count() == 0
