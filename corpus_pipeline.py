"""The corpus pipeline: quality rules, near-duplicates, personal data, source mixing, packing.

Every stage takes empty tables, repeated rows, texts of any length, nulls in any column and columns beyond those of documents (which go).
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from epsgraph.llm.common import table
from epsgraph.llm.mixing import mix
from epsgraph.llm.neardup import near_duplicates
from epsgraph.llm.packing import pack
from epsgraph.llm.quality import fit_quality, score_quality
from epsgraph.llm.surrogates import replace_entities
from epsgraph.operators.components import checkpoint_dir

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")
#: Fixed value: what a word holds.
WORD = r"[^\x20\x09-\x0D]"


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the rules reject go: each row is judged by its own text, whatever its id; null and empty texts go. The
    model is fitted on this stage's input and the labels of its ids; labels without a document do not matter."""
    model = fit_quality(docs, table(spark, sf_dir, "labels", "doc_id", "quality"))
    return score_quality(docs.select(*COLUMNS), model).filter("quality.kept").select(*COLUMNS)


def near_duplicate_removal(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group stays: five words, similarity 0.8.

    It is the one of the smallest id, then of the smallest text hash; of equal rows of it, one. Null ids come last and are told
    apart by their texts. Texts without words belong to no group and all stay; columns beyond those of documents go."""
    rows = near_duplicates(docs, words=5, percent=80)
    named = F.struct(F.col("doc_id").isNull().alias("later"), "doc_id", "text_id")
    first = rows.filter("class_id is not null").groupBy("class_id").agg(F.min(named).alias("one")).select(F.col("one.doc_id").alias("_id"), F.col("one.text_id").alias("_text"))
    docs = docs.select(*COLUMNS).withColumn("_text", F.xxhash64("text")).withColumn("_words", F.coalesce(F.col("text").rlike(WORD), F.lit(False)))
    stay = docs.filter("_words").join(first.withColumnRenamed("_text", "_of"), F.col("doc_id").cast("long").eqNullSafe(F.col("_id")) & (F.col("_text") == F.col("_of")), "left_semi")
    return stay.dropDuplicates(["doc_id", "_text"]).unionByName(docs.filter("not _words")).select(*COLUMNS)


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Entities are replaced by surrogates; n_chars is counted anew (null for a null text). Every row stays."""
    return replace_entities(docs.select(*COLUMNS)).withColumn("n_chars", F.length("text").cast("long")).select(*COLUMNS)


def source_mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sources as flat as repeating none more than 1.25 times allows, in as many tokens as there are. A null source is one of
    its own, repeated rows are dealt like others, a source without any words gives no rows."""
    return mix(docs.select(*COLUMNS), max_repeats=1.25).select(*COLUMNS)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Windows of 2048 tokens, a row a piece, with its token ids. A null text is its end id alone; null and repeated ids are
    packed like any others."""
    return pack(docs)


STAGES = [
    ("quality_rules", quality_rules),
    ("near_duplicates", near_duplicate_removal),
    ("personal_data", personal_data),
    ("source_mixing", source_mixing),
    ("packing", packing),
]

#: No SQL: signatures, keyed surrogates and tokenisation have no SQL form. Tests hold run() against plain versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", *COLUMNS)
    folder = f"{checkpoint_dir(spark)}/pipeline-{uuid.uuid4().hex}"
    for name, stage in STAGES[:-1]:
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
