"""The pipeline's stages against plain versions of what each decides, on the small tables."""

import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline as cp
from epsgraph.llm import packing, quality, surrogates
from epsgraph.llm.common import table
from tests.conftest import TINY
from tests.llm.test_ops import exact_components


@pytest.fixture(scope="module")
def stages(spark, tmp_path_factory):
    folder, docs, out = tmp_path_factory.mktemp("stages"), table(spark, TINY, "documents"), []
    for name, f in cp.STAGES:
        f(spark, docs, TINY).write.parquet(f"{folder}/{name}")
        out.append((docs, docs := spark.read.parquet(f"{folder}/{name}")))
    return out


def test_stages_return_documents(stages):
    for _, after in stages[:-1]:
        assert after.columns == list(cp.COLUMNS)


def test_quality_stage_drops_what_the_rules_reject(spark, stages):
    before, after = stages[0]
    model = quality.fit_quality(before, table(spark, TINY, "labels"))
    kept = {r.doc_id for r in quality.score_quality(before, model).filter("quality.kept").collect()}
    assert {r.doc_id for r in after.collect()} == kept and 0 < len(kept) < before.count()


def test_near_duplicate_stage_keeps_one_of_each_component(stages):
    before, after = stages[1]
    rows = [(r.doc_id, r.text) for r in before.collect()]
    roots = {c for _, c in exact_components(rows, 5, 80).values()}
    assert sorted(r.doc_id for r in after.collect()) == sorted(roots)


def test_personal_data_stage(stages):
    before, after = stages[2]
    was = {r.doc_id: r for r in before.collect()}
    for r in after.collect():
        assert r.n_chars == len(r.text) and (r.lang, r.source) == (was[r.doc_id].lang, was[r.doc_id].source)
    hits = before.filter(F.size(surrogates.entities(F.col("text"))) > 0).count()
    assert hits == sum(r.text != was[r.doc_id].text for r in after.collect())


def test_mixing_stage_flattens_sources(stages):
    before, after = stages[3]
    words = lambda df: {r.source: r.n for r in df.withColumn("n", F.size(F.split(F.trim("text"), r"\s+"))).groupBy("source").agg(F.sum("n").alias("n")).collect()}
    a, b = words(before), words(after)
    assert set(b) <= set(a) and all(b[s] <= 1.26 * a[s] for s in b)
    assert max(Counter(r.doc_id for r in after.collect()).values()) <= 2
    assert np.std(list(b.values())) <= np.std(list(a.values()))


def test_packing_stage_holds_every_token(stages):
    before, after = stages[4]
    encode, want = packing.byte_bpe(), Counter()
    for r in before.collect():
        want[r.doc_id] += len(encode(r.text)) + 1
    got = Counter()
    for p in after.collect():
        got[p.doc_id] += p.length
        assert zlib.crc32(p.ids) == p.ids_crc32 and p.offset + p.length <= 2048
    assert got == want


def test_run_gives_what_the_stages_give(spark, stages):
    """Where windows cut documents depends on the order of rows; which tokens there are does not."""
    def tokens(df):
        got = Counter()
        for p in df.collect():
            got[p.doc_id] += p.length
        return got

    assert tokens(cp.run(spark, TINY)) == tokens(stages[-1][1])


GOOD = " ".join(f"word{i} and other" for i in range(40))
ODD = [
    (1, GOOD, "en", "a", 5),
    (1, GOOD, "en", "a", 5),
    (None, GOOD + " more", None, None, None),
    (3, GOOD, "en", "b", 5),
    (3, " ".join(f"thing{i} or else" for i in range(60)), "en", "b", 5),
    (3, " ".join(f"thing{i} or else" for i in range(60)) + " x", "en", "b", 5),
    (None, " ".join(f"long{i} text of" for i in range(30_000)), "fr", "c", 5),
    (7, None, "en", "a", None),
    (8, "", "en", "a", 0),
    (9, " \t\n", None, "a", 3),
]


@pytest.fixture(scope="module")
def odd(spark):
    df = spark.createDataFrame(ODD, "doc_id long, text string, lang string, source string, n_chars long")
    return df.withColumn("kept", F.lit(1)).withColumn("quality", F.lit("q")).withColumn("epoch", F.lit("e"))


def test_near_duplicate_stage_keeps_one_row_of_each_group(spark, odd):
    got = sorted((str(r.doc_id), len(r.text or "")) for r in cp.near_duplicate_removal(spark, odd, TINY).collect())
    sizes = [len(t or "") for _, t, *_ in ODD]
    short = min(sizes[4:6], key=lambda n: n)
    assert ("1", sizes[0]) in got and len([g for g in got if g[0] == "3"]) == 1 and [g for g in got if g[0] == "3"][0][1] in (short, short + 2)
    assert ("None", sizes[6]) in got and ("None", sizes[2]) not in got
    assert [g for g in got if g[0] in "789"] == [("7", 0), ("8", 0), ("9", 3)] and len(got) == 6


@pytest.mark.parametrize("name, stage", cp.STAGES)
def test_stages_take_odd_rows_and_empty_tables(spark, odd, name, stage):
    rows = stage(spark, odd, TINY).collect()
    assert stage(spark, odd.limit(0), TINY).count() == 0
    if name == "quality_rules":
        assert not {r.doc_id for r in rows} & {7, 8, 9}
    if name == "personal_data":
        assert sorted(map(str, rows)) == sorted(map(str, odd.select(*cp.COLUMNS).withColumn("n_chars", F.length("text").cast("long")).collect()))
    if name == "source_mixing":
        assert {r.source for r in rows} <= {"a", "b", "c", None} and all(r.text for r in rows if r.source != "a")
    if name == "packing":
        assert sum(r.length for r in rows) == sum(len(packing.byte_bpe()(t or "")) + 1 for _, t, *_ in ODD)
