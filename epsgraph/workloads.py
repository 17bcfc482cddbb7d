"""Point sets on the given tables: how to build them in Spark, the same in SQL, their metric and radii."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions.metrics import Metric, metric
from .operators.points import points


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


@dataclass(frozen=True)
class PointSet:
    build: Callable[[SparkSession, str], DataFrame]
    sql: str  # SELECT pid, vec
    distance: str  # of a.vec and b.vec
    metric: Callable[[], Metric]
    radii: tuple[float, ...]

    def edges_sql(self, eps: float) -> str:
        return f"WITH p AS ({self.sql}), e AS (SELECT a.pid AS src, b.pid AS dst, CAST({self.distance} AS DOUBLE) AS dist FROM p a JOIN p b ON a.pid < b.pid) SELECT src, dst, dist FROM e WHERE dist <= {eps}"


L2_SQL = "list_distance(a.vec, b.vec)"
BITS_SQL = "round(list_distance(a.vec, b.vec) * list_distance(a.vec, b.vec))"


def embeddings(k: int):
    return lambda spark, d: points(read(spark, d, "embeddings"), "vec_id", F.slice(F.col("embedding").cast("array<double>"), 1, k))


def embeddings_sql(k: int) -> str:
    return f"SELECT vec_id AS pid, CAST(embedding[1:{k}] AS DOUBLE[]) AS vec FROM embeddings"


def _word(bit: Callable) -> F.Column:
    """64 conditions in one long."""
    return F.aggregate(F.sequence(F.lit(0), F.lit(63)), F.lit(0).cast("long"), lambda w, i: w.bitwiseOR(F.when(bit(i), F.call_function("shiftleft", F.lit(1).cast("long"), i)).otherwise(F.lit(0).cast("long"))))


def bits256(spark: SparkSession, d: str) -> DataFrame:
    e = lambda i: F.element_at("embedding", i + 1)
    words = [_word(lambda i, k=k: e(i) > e(F.pmod(i + k, F.lit(64)))) for k in range(1, 5)]
    return points(read(spark, d, "embeddings"), "vec_id", F.array(*words))


def bits64(spark: SparkSession, d: str) -> DataFrame:
    return points(read(spark, d, "embeddings"), "vec_id", F.array(_word(lambda i: F.element_at("embedding", i + 1) > 0)))


def tokens800(spark: SparkSession, d: str) -> DataFrame:
    docs = read(spark, d, "documents").select("doc_id", F.explode(F.array_distinct(F.split(F.lower("text"), " "))).alias("t"))
    top = docs.groupBy("t").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "t").limit(800)
    place = top.withColumn("k", F.row_number().over(Window.orderBy(F.desc("n"), "t")) - 1).select("t", "k")
    bit = F.expr("shiftleft(1L, k % 64)")
    words = docs.join(F.broadcast(place), "t").groupBy("doc_id", F.floor(F.col("k") / 64).cast("int").alias("w")).agg(F.bit_or(bit).alias("bits"))
    found = words.groupBy("doc_id").agg(F.map_from_entries(F.collect_list(F.struct("w", "bits"))).alias("m"))
    every = read(spark, d, "documents").select("doc_id").join(found, "doc_id", "left")
    vec = F.transform(F.sequence(F.lit(0), F.lit(12)), lambda w: F.coalesce(F.element_at("m", w), F.lit(0).cast("long")))
    return points(every, "doc_id", vec)


TOKENS800_SQL = """
SELECT d.doc_id AS pid, list_transform(v.ts, lambda t: CASE WHEN list_contains(d.ts, t) THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END) AS vec
FROM (SELECT doc_id, list_distinct(string_split(lower(text), ' ')) AS ts FROM documents) d,
  (SELECT list(t) AS ts FROM (SELECT t FROM (SELECT DISTINCT doc_id, unnest(string_split(lower(text), ' ')) AS t FROM documents) GROUP BY t ORDER BY count(*) DESC, t LIMIT 800)) v
"""

LINE_KEY = ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice")
#: Ranges of the first key within which ``ranked`` sorts.
RANGES = 64
#: Payloads of lines, and their first orders, that are held on the driver and shared.
MOST_KINDS = 1_000_000


def _range(key: F.Column, cuts: list, lo: int, hi: int) -> F.Column:
    """How many of ``cuts[lo:hi]``, in order, lie below the key, added to ``lo``, by bisection; none below a null, the first in order."""
    if lo == hi:
        return F.lit(lo)
    at = (lo + hi) // 2
    return F.when(key > F.lit(cuts[at]), _range(key, cuts, at + 1, hi)).otherwise(_range(key, cuts, lo, at))


def ranked(df: DataFrame, *keys: str) -> DataFrame:
    """``df`` with ``pid``, the row's number in the order of ``keys``: rows are numbered within ranges of the first key, and the ranges'
    sizes (a bounded table) give the numbers before them. Rows that are equal in all keys are numbered in any order."""
    cuts = df.select(F.percentile_approx(keys[0], [k / RANGES for k in range(1, RANGES)], 10 * RANGES)).first()[0]
    cuts = sorted(set(cuts or []))
    at = _range(F.col(keys[0]), cuts, 0, len(cuts))
    size = dict(df.select(at.alias("_range")).groupBy("_range").count().collect())
    before = F.array(*[F.lit(sum(n for r, n in size.items() if r < k)).cast("long") for k in range(max(size, default=0) + 1)])
    of = Window.partitionBy("_range").orderBy(*keys)
    numbered = df.withColumn("_range", at).withColumn("pid", F.row_number().over(of) + F.element_at(before, F.col("_range") + 1))
    return numbered.drop("_range")


def line_grid(spark: SparkSession, d: str) -> DataFrame:
    """(pid, vec) of all lines; the pid is a rank among all."""
    li = read(spark, d, "lineitem")
    vec = F.array("l_quantity", F.round(100 * F.col("l_discount")), F.round(100 * F.col("l_tax"))).cast("array<double>")
    return points(ranked(li, *LINE_KEY), "pid", vec)


LINE_GRID_SQL = f"SELECT row_number() OVER (ORDER BY {', '.join(LINE_KEY)}) AS pid, [CAST(l_quantity AS DOUBLE), round(100 * l_discount), round(100 * l_tax)] AS vec FROM lineitem"
FLAGS = [("l_returnflag", v) for v in ("A", "N", "R")] + [("l_linestatus", v) for v in ("F", "O")]


def line_flags_all(spark: SparkSession, d: str) -> DataFrame:
    """As ``line_grid``, with the flags."""
    return _with_flags(read(spark, d, "lineitem"))


def line_kinds(spark: SparkSession, d: str) -> DataFrame:
    """The distinct payloads of all lines, each under the smallest rank of its copies.

    Only lines of a payload's first order can be its first copy: their ranks are the lines of smaller orders, counted by one pass over
    the order keys, and their places within the order. With more than ``MOST_KINDS`` payloads all lines are ranked."""
    li = read(spark, d, "lineitem").withColumn("_order", F.coalesce(F.col("l_orderkey").cast("long"), F.lit(-(1 << 63))))
    parts = [f"_x{k}" for k in range(3 + len(FLAGS))]
    lines = li.select("*", *[c.alias(n) for c, n in zip(_flag_parts(), parts)])
    kinds = lines.groupBy(*parts).agg(F.min("_order").alias("_order")).persist(StorageLevel.MEMORY_AND_DISK)
    if kinds.limit(MOST_KINDS + 1).count() > MOST_KINDS:
        kinds.unpersist()
        return line_flags_all(spark, d).groupBy("vec").agg(F.min("pid").alias("pid")).select("pid", "vec")
    firsts = np.array(sorted(r[0] for r in kinds.select("_order").distinct().collect()), np.int64)

    def between(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n = np.zeros(len(firsts) + 1, np.int64)
        for b in batches:
            n += np.bincount(np.searchsorted(firsts, b.column(0).to_numpy(), "right"), minlength=len(n))
        at = np.flatnonzero(n)
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(n[at])], ["at", "n"])

    counted = dict(li.select("_order").mapInArrow(between, "at long, n long").groupBy("at").agg(F.sum("n")).collect())
    below = np.cumsum([counted.get(k, 0) for k in range(len(firsts))])
    orders = spark.createDataFrame([(int(o), int(n)) for o, n in zip(firsts, below)], "_order long, _below long")
    place = F.row_number().over(Window.partitionBy("_order").orderBy(*LINE_KEY))
    placed = lines.join(F.broadcast(orders), "_order").withColumn("pid", place + F.col("_below"))
    found = placed.join(F.broadcast(kinds), [*parts, "_order"]).groupBy(*parts).agg(F.min("pid").alias("pid"))
    return points(found, "pid", F.array(*parts))


def line_flags(spark: SparkSession, d: str) -> DataFrame:
    """The LGF of FIXTURES.md, a twentieth of the orders: for the bench and the published tables only."""
    return _with_flags(read(spark, d, "lineitem").filter(F.col("l_orderkey") % 20 == 0))


def _flag_parts() -> list[F.Column]:
    hot = [F.when(F.col(c) == v, 10.0).otherwise(0.0) for c, v in FLAGS]
    return [F.col("l_quantity").cast("double"), F.round(100 * F.col("l_discount")).cast("double"), F.round(100 * F.col("l_tax")).cast("double"), *hot]


def _with_flags(li: DataFrame) -> DataFrame:
    return points(ranked(li, *LINE_KEY), "pid", F.array(*_flag_parts()))


LINE_FLAGS_SQL = (
    f"SELECT row_number() OVER (ORDER BY {', '.join(LINE_KEY)}) AS pid, [CAST(l_quantity AS DOUBLE), round(100 * l_discount), round(100 * l_tax), "
    + ", ".join(f"CASE WHEN {c} = '{v}' THEN 10.0::DOUBLE ELSE 0.0::DOUBLE END" for c, v in FLAGS)
    + "] AS vec FROM lineitem WHERE l_orderkey % 20 = 0"
)
LINE_FLAGS_ALL_SQL = LINE_FLAGS_SQL.removesuffix(" WHERE l_orderkey % 20 = 0")

TYPES_SQL = "(SELECT DISTINCT event_type FROM events ORDER BY event_type)"


def _counted(spark: SparkSession, d: str, n: int, key) -> DataFrame:
    """Per user an array of ``n`` counts; ``key`` is the position."""
    c = read(spark, d, "events").select("user_id", key.cast("int").alias("k")).groupBy("user_id", "k").agg(F.count("*").alias("n"))
    c = c.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("k", "n"))).alias("m"))
    return points(c, "user_id", F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda k: F.coalesce(F.element_at("m", k), F.lit(0)).cast("double")))


EVENT_TYPES = ("click", "error", "purchase", "signup", "view")


def _type_rank(spark: SparkSession, d: str) -> F.Column:
    kinds = [r[0] for r in read(spark, d, "events").select("event_type").distinct().orderBy("event_type").limit(64).collect()]
    return F.array_position(F.array(*map(F.lit, kinds)), F.col("event_type")) - 1


def user_types(spark: SparkSession, d: str) -> DataFrame:
    return _counted(spark, d, 5, _type_rank(spark, d))


def user_hours(spark: SparkSession, d: str) -> DataFrame:
    return _counted(spark, d, 120, _type_rank(spark, d) * 24 + F.hour("ts"))


def value_cdf(spark: SparkSession, d: str) -> DataFrame:
    h = _counted(spark, d, 20, F.least(F.floor(F.col("value") / 10), F.lit(19)))
    n = F.aggregate("vec", F.lit(0.0), lambda s, x: s + x)
    cum = F.transform(F.sequence(F.lit(1), F.lit(20)), lambda k: F.aggregate(F.slice("vec", F.lit(1), k), F.lit(0.0), lambda s, x: s + x) / n)
    return h.select("pid", cum.alias("vec"))


def _users_sql(n: int, key: str) -> str:
    return (
        f"SELECT u.user_id AS pid, list_transform(range({n}), lambda k: CAST(len(list_filter(u.ks, lambda x: x = k)) AS DOUBLE)) AS vec FROM "
        f"(SELECT user_id, list(CAST({key} AS BIGINT)) AS ks FROM events GROUP BY user_id) u"
    )


TYPE_RANK_SQL = "list_position((SELECT list(event_type ORDER BY event_type) FROM (SELECT DISTINCT event_type FROM events)), event_type) - 1"


def names(spark: SparkSession, d: str) -> DataFrame:
    n = read(spark, d, "part").select("p_name").distinct()
    return points(n.withColumn("pid", F.row_number().over(Window.orderBy("p_name"))), "pid", "p_name")


def token_sets(spark: SparkSession, d: str) -> DataFrame:
    return points(read(spark, d, "documents"), "doc_id", F.array_sort(F.array_distinct(F.split(F.lower("text"), " "))))


def orders(o: DataFrame) -> DataFrame:
    return points(o, "o_orderkey", F.array(F.col("o_totalprice") / 1000, F.datediff("o_orderdate", F.lit("1992-01-01")) / 10))


ORDERS_SQL = "SELECT o_orderkey AS pid, [o_totalprice / 1000, date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) / 10] AS vec FROM orders"


SETS: dict[str, PointSet] = {
    **{
        f"e{k}": PointSet(embeddings(k), embeddings_sql(k), L2_SQL, lambda: metric("l2"), r)
        for k, r in {2: (0.015, 0.05, 0.117), 4: (0.077, 0.141, 0.227), 8: (0.205, 0.289, 0.386), 20: (0.496, 0.59, 0.691), 32: (0.714, 0.808, 0.908), 40: (0.836, 0.933, 1.032), 64: (1.161, 1.249, 1.336)}.items()
    },
    "e64_angular": PointSet(embeddings(64), embeddings_sql(64), "acos(greatest(-1.0, least(1.0, list_cosine_similarity(a.vec, b.vec))))", lambda: metric("angular"), (1.24, 1.35, 1.46)),
    "h256": PointSet(bits256, "SELECT vec_id AS pid, flatten(list_transform([1, 2, 3, 4], lambda k: list_transform(range(64), lambda i: CASE WHEN embedding[i + 1] > embedding[(i + k) % 64 + 1] THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END))) AS vec FROM embeddings", BITS_SQL, lambda: metric("hamming"), (94, 106, 117)),
    "h64": PointSet(bits64, "SELECT vec_id AS pid, list_transform(embedding, lambda x: CASE WHEN x > 0 THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END) AS vec FROM embeddings", BITS_SQL, lambda: metric("hamming"), (21, 25, 29)),
    "h800": PointSet(tokens800, TOKENS800_SQL, BITS_SQL, lambda: metric("hamming"), (5, 10, 20)),
    "lg": PointSet(line_grid, LINE_GRID_SQL, L2_SQL, lambda: metric("l2"), (1.0, 1.5, 2.0)),
    "lgf": PointSet(line_flags, LINE_FLAGS_SQL, L2_SQL, lambda: metric("l2"), (1.5, 3.2, 6.1)),
    "lgf_all": PointSet(line_flags_all, LINE_FLAGS_ALL_SQL, L2_SQL, lambda: metric("l2"), (1.5, 3.2, 6.1)),
    "lgd": PointSet(line_kinds, f"SELECT min(pid) AS pid, vec FROM ({LINE_FLAGS_ALL_SQL}) GROUP BY vec", L2_SQL, lambda: metric("l2"), (1.5, 3.2, 6.1)),
    "uc": PointSet(user_hours, _users_sql(120, f"({TYPE_RANK_SQL}) * 24 + hour(ts)"), L2_SQL, lambda: metric("l2"), (9.49, 10.44, 11.79)),
    "ut": PointSet(user_types, _users_sql(5, TYPE_RANK_SQL), L2_SQL, lambda: metric("l2"), (2.9, 4.1, 5.9)),
    "w1": PointSet(
        value_cdf,
        f"SELECT pid, list_transform(range(1, 21), lambda k: list_sum(vec[1:k]) / list_sum(vec)) AS vec FROM ({_users_sql(20, 'least(floor(value / 10), 19)')})",
        "10 * list_sum(list_transform(range(1, 21), lambda k: abs(a.vec[k] - b.vec[k])))", lambda: metric("w1", 10.0), (2.9, 3.45, 4.5),
    ),
    "url": PointSet(lambda spark, d: points(read(spark, d, "pages"), "page_id", "url"), "SELECT page_id AS pid, url AS vec FROM pages", "levenshtein(a.vec, b.vec)", lambda: metric("edit"), (8, 12, 16)),
    "names": PointSet(names, "SELECT row_number() OVER (ORDER BY p_name) AS pid, p_name AS vec FROM (SELECT DISTINCT p_name FROM part)", "levenshtein(a.vec, b.vec)", lambda: metric("edit"), (2, 3, 5)),
    "ca": PointSet(lambda spark, d: points(read(spark, d, "customer"), "c_custkey", F.array("c_acctbal")), "SELECT c_custkey AS pid, [c_acctbal] AS vec FROM customer", "abs(a.vec[1] - b.vec[1])", lambda: metric("l1"), (1.005, 5.005, 50.005)),
    "p2": PointSet(lambda spark, d: points(read(spark, d, "part"), "p_partkey", F.array(F.col("p_size").cast("double"), "p_retailprice")), "SELECT p_partkey AS pid, [CAST(p_size AS DOUBLE), p_retailprice] AS vec FROM part", L2_SQL, lambda: metric("l2"), (1.005, 2.005, 5.005)),
    "o2": PointSet(lambda spark, d: orders(read(spark, d, "orders").filter(F.col("o_orderkey") % 5 == 0)), ORDERS_SQL + " WHERE o_orderkey % 5 = 0", L2_SQL, lambda: metric("l2"), (2.003, 5.003, 10.003)),
    "o2_all": PointSet(lambda spark, d: orders(read(spark, d, "orders")), ORDERS_SQL, L2_SQL, lambda: metric("l2"), (2.003, 5.003, 10.003)),
    "jaccard": PointSet(token_sets, "SELECT doc_id AS pid, list_distinct(string_split(lower(text), ' ')) AS vec FROM documents", "1 - len(list_intersect(a.vec, b.vec)) / (len(a.vec) + len(b.vec) - len(list_intersect(a.vec, b.vec)))", lambda: metric("jaccard"), (0.1, 0.2)),
}
