"""Mixing sources to target weights, with DataFrame functions only.

A source's weight is its token share to a power between 0 (uniform) and 1 (as found), normalised. The power is found by
bisection, inside one SQL expression over the array of sources: the largest that reaches a target entropy (as a part of the
logarithm of the number of sources), or the smallest that keeps every source's repetition within a limit (a budget that exceeds the limit for all is cut to it).

Weights become token budgets and budgets whole epochs and a rest. A source's documents are dealt into blocks by
hash, about ``block_tokens`` tokens each and at most 65,536 a source, and every epoch permutes the blocks by a keyed hash. The
rest takes whole blocks in the order of its epoch while they fit, and of the next block documents in keyed order while they
fit. So running sums go over the blocks of a source and the documents of single blocks, never over a source.

Result: the input's columns and epoch (from 0), block_order (from 1, within source and epoch), n_tokens (words, unless given).
A document repeated is a row an epoch.

Defined results: a null source is a source of its own; null and empty texts have no tokens, and documents without tokens come
along with their block; sources without any tokens get no weight and no rows; ties and repeated rows are dealt like
others; an empty table gives no rows; columns of the result's names are replaced.
"""

from __future__ import annotations

from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import table

MOST_BLOCKS = 1 << 16
STEPS = 50
#: Stands for a null source while grouping.
NO_SOURCE = "\x00"


def count_words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def _sums(shares: Column, a: Column) -> Column:
    """struct<z, l>: the sums of share**a and of share**a * log(share)."""
    zero = F.struct(F.lit(0.0).alias("z"), F.lit(0.0).alias("l"))
    return F.aggregate(shares, zero, lambda s, p: F.struct((s["z"] + F.pow(p, a)).alias("z"), (s["l"] + F.pow(p, a) * F.log(p)).alias("l")))


def entropy(shares: Column, a: Column) -> Column:
    s = _sums(shares, a)
    return F.log(s["z"]) - a * s["l"] / s["z"]


def repetition(shares: Column, a: Column, budget_share: Column) -> Column:
    """The most often any source is repeated: the smallest is, as powers are at most 1."""
    return budget_share * F.pow(F.array_min(shares), a - 1) / _sums(shares, a)["z"]


def weights(sizes: DataFrame, budget: int | None, target_entropy: float | None, max_repeats: float | None) -> DataFrame:
    """(src, tokens, exponent, weight, budget) from (src, tokens); one row holds all sources, whose number is bounded by nature."""
    whole = sizes.filter("tokens > 0").agg(F.array_sort(F.collect_list(F.struct("src", "tokens"))).alias("ss"), F.sum("tokens").alias("total"))
    whole = whole.filter("total > 0").withColumn("shares", F.transform("ss", lambda s: s["tokens"] / F.col("total")))
    whole = whole.withColumn("budget", F.lit(budget).cast("double") if budget else F.col("total").cast("double"))
    shares = F.col("shares")

    def flat_enough(a: Column) -> Column:
        """True where the exponent may not be lower (repetition), or need not be (entropy)."""
        if max_repeats is not None:
            return repetition(shares, a, F.col("budget") / F.col("total")) > max_repeats
        return entropy(shares, a) >= F.lit(target_entropy) * F.log(F.size(shares))

    start = F.struct(F.lit(0.0).alias("lo"), F.lit(1.0).alias("hi"))

    def halve(s: Column, _: Column) -> Column:
        mid = (s["lo"] + s["hi"]) / 2
        up = flat_enough(mid)
        return F.struct(F.when(up, mid).otherwise(s["lo"]).alias("lo"), F.when(up, s["hi"]).otherwise(mid).alias("hi"))

    found = F.aggregate(F.sequence(F.lit(1), F.lit(STEPS)), start, halve)
    side = "hi" if max_repeats is not None else "lo"
    ends = F.when(~flat_enough(F.lit(0.0)), F.lit(0.0)).when(flat_enough(F.lit(1.0)), F.lit(1.0)).otherwise(found[side])
    whole = whole.withColumn("exponent", ends).withColumn("z", _sums(shares, F.col("exponent"))["z"])
    return whole.select("exponent", "z", "total", F.col("budget").alias("all"), F.inline("ss")).select(
        "src", "tokens", "exponent", (F.pow(F.col("tokens") / F.col("total"), F.col("exponent")) / F.col("z")).alias("weight"), (F.pow(F.col("tokens") / F.col("total"), F.col("exponent")) / F.col("z") * F.col("all")).alias("budget")
    ).withColumn("budget", F.col("budget") if max_repeats is None else F.least("budget", max_repeats * F.col("tokens")))


def mix(docs: DataFrame, budget: int | None = None, target_entropy: float | None = None, max_repeats: float | None = None, block_tokens: int = 100_000, seed: int = 7, tokens: Column | None = None) -> DataFrame:
    if (target_entropy is None) == (max_repeats is None):
        raise ValueError("give a target entropy or a repetition limit")
    columns = [c for c in docs.columns if c not in ("epoch", "block_order", "n_tokens")]
    rows = docs.select(*columns, (count_words(F.col("text")) if tokens is None else tokens).alias("n_tokens"))
    rows = rows.withColumn("_src", F.coalesce("source", F.lit(NO_SOURCE))).withColumn("_h", F.xxhash64("doc_id", F.lit(seed)))
    small = rows.select("_src", "_h", "n_tokens").persist(StorageLevel.DISK_ONLY)
    sizes = small.groupBy("_src").agg(F.sum("n_tokens").alias("tokens")).withColumnRenamed("_src", "src")
    plan = weights(sizes, budget, target_entropy, max_repeats)
    n_blocks = F.least(F.lit(MOST_BLOCKS), F.greatest(F.lit(1), F.ceil(F.col("tokens") / block_tokens)))
    plan = plan.withColumn("n_blocks", n_blocks.cast("int")).withColumn("epochs", F.floor(F.col("budget") / F.col("tokens")).cast("int"))
    plan = plan.withColumn("rest", F.col("budget") - F.col("epochs") * F.col("tokens")).persist(StorageLevel.DISK_ONLY)
    by_source = plan.select(F.col("src").alias("_src"), "n_blocks")

    def blocked(df: DataFrame) -> DataFrame:
        return df.join(by_source, "_src").withColumn("_block", F.pmod(F.col("_h"), F.col("n_blocks")).cast("int")).drop("n_blocks")

    order = Window.partitionBy("_src", "epoch").orderBy("_key", "_block")
    filled = blocked(small).groupBy("_src", "_block").agg(F.sum("n_tokens").alias("tokens"))
    shares = plan.select(F.col("src").alias("_src"), "epochs", "rest")
    # a row for each block and epoch, the last one being that of the rest
    drawn = filled.join(shares, "_src").withColumn("epoch", F.explode(F.sequence(F.lit(0), F.col("epochs"))))
    drawn = drawn.withColumn("_key", F.xxhash64("_src", "_block", "epoch", F.lit(seed)))
    drawn = drawn.withColumn("block_order", F.row_number().over(order)).withColumn("end", F.sum("tokens").over(order.rowsBetween(Window.unboundedPreceding, 0)))
    room = F.when(F.col("epoch") < F.col("epochs"), F.col("tokens").cast("double")).otherwise(F.col("rest") - (F.col("end") - F.col("tokens")))
    drawn = drawn.withColumn("room", room).filter((F.col("room") > 0) | ((F.col("epoch") < F.col("epochs"))))
    drawn = drawn.withColumn("whole", F.col("room") >= F.col("tokens")).select("_src", "_block", "epoch", "block_order", "room", "whole")

    # blocks are cut by running sums of their documents, without their texts
    cut = drawn.filter("not whole").select("_src", "_block", "epoch", "room")
    inside = Window.partitionBy("_src", "_block").orderBy("_in", "_h").rowsBetween(Window.unboundedPreceding, 0)
    part = blocked(small).join(cut, ["_src", "_block"]).withColumn("_in", F.xxhash64("_h", "epoch", F.lit(seed)))
    part = part.withColumn("end", F.sum("n_tokens").over(inside)).filter("end <= room")
    # documents of one hash lie side by side, so the last of them in the block's order says how far it goes
    last = part.groupBy("_src", "_block").agg(F.max(F.struct("_in", "_h")).alias("last"))
    out = blocked(rows).join(drawn, ["_src", "_block"]).join(last, ["_src", "_block"], "left")
    here = F.struct(F.xxhash64("_h", "epoch", F.lit(seed)).alias("_in"), F.col("_h"))
    return out.filter(F.col("whole") | (here <= F.col("last"))).select(*columns, "epoch", "block_order", "n_tokens")


def op8_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "source", "text")
    return mix(docs, max_repeats=1.25).select("doc_id", "source", "epoch", "block_order", "n_tokens")
