"""Relational operators around the graphs: one query each, in SQL that both engines read where the dialects meet."""

from __future__ import annotations

import re
import uuid
from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions import tables
from .functions.metrics import metric
from .operators.components import checkpoint_dir
from .operators.landmark import landmark_graph
from .sources.edges import register, write_edges
from .workloads import SETS, read

E8 = SETS["e8"]
TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "labels")


def sql(text: str, oracle: str | None = None) -> tuple[Callable, str]:
    """``text`` with tables in braces; the oracle is the same text unless the dialects differ."""
    used = sorted(set(re.findall(r"\{(\w+)\}", text)))
    run = lambda spark, d: spark.sql(text, **{t: _edges(spark, d, t) if t in EDGE_SETS else read(spark, d, t) for t in used})
    plain = re.sub(r"\{(\w+)\}", lambda m: f"({EDGE_SETS[m[1]][1]})" if m[1] in EDGE_SETS else m[1], oracle or text)
    return run, plain


#: Edges at two radii, and both directions of the larger.
EDGE_SETS = {
    "edges": (0.289, E8.edges_sql(0.289)),
    "fewer": (0.205, E8.edges_sql(0.205)),
    "both": (0.289, f"SELECT src, dst, dist FROM ({E8.edges_sql(0.289)}) UNION ALL SELECT dst, src, dist FROM ({E8.edges_sql(0.289)})"),
}


def _edges(spark: SparkSession, d: str, name: str) -> DataFrame:
    e = landmark_graph(E8.build(spark, d), EDGE_SETS[name][0], "l2", 16)
    return e.unionByName(e.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "dist")) if name == "both" else e


def _joined(hint: str) -> Callable:
    def run(spark: SparkSession, d: str) -> DataFrame:
        o, c = read(spark, d, "orders").select("o_custkey", "o_totalprice"), read(spark, d, "customer").select("c_custkey", "c_mktsegment")
        return o.join(c.hint(hint), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))

    return run


JOINED_SQL = "SELECT c_mktsegment, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment"


def _band(spark: SparkSession, d: str) -> DataFrame:
    """|a - b| <= 5.005 by bins of that width: each value meets its own and the next bin."""
    w = 5.005
    c = read(spark, d, "customer").select("c_custkey", "c_acctbal").withColumn("bin", F.floor(F.col("c_acctbal") / w))
    a, b = c.alias("a"), c.withColumn("at", F.explode(F.array(F.col("bin") - 1, "bin", F.col("bin") + 1))).alias("b")
    hit = a.join(b, (F.col("a.bin") == F.col("b.at")) & (F.col("a.c_custkey") < F.col("b.c_custkey"))).filter(F.abs(F.col("a.c_acctbal") - F.col("b.c_acctbal")) <= w)
    return hit.select(F.col("a.c_custkey").alias("src"), F.col("b.c_custkey").alias("dst"))


def _asof(spark: SparkSession, d: str) -> DataFrame:
    """The latest earlier event of the same user for every purchase, by one window over the union of both roles."""
    e = read(spark, d, "events").select("event_id", "user_id", "ts", "event_type")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return e.withColumn("prior_id", F.last("event_id").over(w)).filter((F.col("event_type") == "purchase") & F.col("prior_id").isNotNull()).select("event_id", "prior_id")


def _roundtrip(kind: str) -> Callable:
    def run(spark: SparkSession, d: str) -> DataFrame:
        both = read(spark, d, "nation").join(F.broadcast(read(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "n_name", "r_name")
        path = f"{checkpoint_dir(spark)}/trip-{uuid.uuid4().hex}"
        writer = both.write.format(kind)
        (writer.option("header", True) if kind == "csv" else writer).save(path)
        back = spark.read.format(kind).schema(both.schema)
        return (back.option("header", True) if kind == "csv" else back).load(path)

    return run


def _bucketed(spark: SparkSession, d: str) -> DataFrame:
    path = f"{checkpoint_dir(spark)}/edges-{uuid.uuid4().hex}"
    write_edges(_edges(spark, d, "edges"), path, 8)
    return spark.read.parquet(path).filter("part = 3").select("src", "dst")


def _source(spark: SparkSession, d: str) -> DataFrame:
    register(spark)
    small = _edges(spark, d, "fewer").select("src", "dst", "dist")
    path = f"{checkpoint_dir(spark)}/list-{uuid.uuid4().hex}"
    small.write.option("header", False).csv(path)
    lines = spark.read.schema("src long, dst long, dist double").csv(path)
    return lines.select("src", "dst", F.round("dist", 6).alias("dist"))


def _lattice(spark: SparkSession, d: str) -> DataFrame:
    """The parts on the least square lattice that holds all their keys, row by row: edges that the Python data source makes,
    as far as both ends are keys."""
    register(spark)
    ids = read(spark, d, "part").select(F.col("p_partkey").cast("long").alias("v")).distinct()
    side = ids.agg(F.coalesce(F.ceil(F.sqrt(F.max("v") + 1)), F.lit(1))).first()[0]
    edges = spark.read.format("lattice_edges").option("side", side).option("parts", min(side, 4 + side * side // 250_000)).load()
    ends = edges.join(ids.withColumnRenamed("v", "src"), "src", "left_semi").join(ids.withColumnRenamed("v", "dst"), "dst", "left_semi")
    return ends.select("src", "dst", "dist")


def _near_docs(how: str) -> Callable:
    """Documents (token bits) near, or not near, any of low labelled quality: a semi or anti join by distance."""
    from .operators.landmark import near_join

    def run(spark: SparkSession, d: str) -> DataFrame:
        p = SETS["h800"].build(spark, d)
        bad = p.join(read(spark, d, "labels").filter("quality = 0").select(F.col("doc_id").alias("pid")).distinct(), "pid", "left_semi")
        hit = near_join(p, bad, 10, metric("hamming")).select(F.col("left").alias("pid")).distinct()
        return p.select("pid").join(hit, "pid", how)

    return run


def _near_docs_sql(keep: str) -> str:
    return f"WITH p AS ({SETS['h800'].sql}), q AS (SELECT * FROM p WHERE pid IN (SELECT doc_id FROM labels WHERE quality = 0)), h AS (SELECT DISTINCT a.pid FROM p a, q b WHERE {SETS['h800'].distance} <= 10) SELECT pid FROM p WHERE pid {keep} (SELECT pid FROM h)"


def _map_suite(spark: SparkSession, d: str) -> DataFrame:
    ws = F.split(F.lower("text"), " ")
    counts = read(spark, d, "documents").select("doc_id", F.explode(ws).alias("w")).groupBy("doc_id", "w").agg(F.count("*").alias("n"))
    m = counts.groupBy("doc_id").agg(F.map_from_entries(F.collect_list(F.struct("w", "n"))).alias("m"))
    frequent = F.map_filter("m", lambda k, v: v >= 5)
    return m.select("doc_id", F.size("m").cast("long").alias("words"), F.size(frequent).cast("long").alias("frequent"), F.coalesce(F.element_at("m", "the"), F.lit(0)).alias("the"))


def _approx_percentile(spark: SparkSession, d: str) -> DataFrame:
    """Whether each approximate quartile's rank is within 1 and a thousandth of the rows of the exact one's."""
    e = read(spark, d, "events").filter("value IS NOT NULL")
    parts = F.array(*map(F.lit, (0.25, 0.5, 0.75)))
    q = e.groupBy("event_type").agg(F.percentile_approx("value", parts).alias("q")).select("event_type", F.explode(F.arrays_zip(parts.alias("part"), "q")).alias("z")).select("event_type", "z.part", "z.q")
    n = e.join(F.broadcast(q), "event_type").groupBy("event_type", "part").agg(F.count("*").alias("n"), F.count_if(F.col("value") < F.col("q")).alias("below"), F.count_if(F.col("value") <= F.col("q")).alias("upto"))
    at, slack = F.col("part") * F.col("n"), 1 + F.col("n") / 1000
    return n.select("event_type", "part", ((F.col("below") <= at + slack) & (F.col("upto") >= at - slack)).alias("near"))


def _medoid(spark: SparkSession, d: str) -> DataFrame:
    """The row of each label whose summed distance to a bounded hash sample of its label is least."""
    import pyarrow as pa

    m = metric("l2")

    def run(t: pa.Table) -> pa.Table:
        x, pid = m.decode(t.column("vec")), t.column("pid").to_numpy()
        s = m.table(x, x).sum(1).round(9)
        return pa.table({"label": t.column("label")[:1], "medoid": [int(pid[s == s.min()].min())]})

    e = read(spark, d, "embeddings").select("label", F.col("vec_id").alias("pid"), F.slice(F.col("embedding").cast("array<double>"), 1, 8).alias("vec"))
    return e.groupBy("label").applyInArrow(run, "label int, medoid long")


def _udf(spark: SparkSession, d: str) -> DataFrame:
    @F.pandas_udf("double")
    def norm(v: pd.Series) -> pd.Series:
        return v.map(lambda x: float((x.astype(float) ** 2).sum() ** 0.5))

    return read(spark, d, "embeddings").select("vec_id", F.round(norm("embedding"), 4).alias("norm"))


def _table_function(text: str) -> Callable:
    def run(spark: SparkSession, d: str) -> DataFrame:
        tables.register(spark)
        e = read(spark, d, "embeddings").select("label", F.col("vec_id").alias("pid"), F.slice(F.col("embedding").cast("array<double>"), 1, 8).alias("vec"))
        e.createOrReplaceTempView("labelled_points")
        return spark.sql(text)

    return run


def _sessions(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = read(spark, d, "events").select("user_id", "event_id", "ts")
    gap = F.col("ts").cast("timestamp").cast("long") - F.lag("ts").over(w).cast("timestamp").cast("long")
    e = e.withColumn("new", F.when(gap.isNull() | (gap > 86400), 1).otherwise(0)).withColumn("session", F.sum("new").over(w))
    return e.groupBy("user_id").agg(F.max("session").alias("sessions"))


def _components_by_recursion(spark: SparkSession, d: str) -> DataFrame:
    from .operators.downstream import components

    p = SETS["names"].build(spark, d)
    return components(landmark_graph(p, 2, metric("edit"), 4), p)


S = "sum(l_quantity) AS q, count(*) AS n"
RELATIONAL: dict[str, tuple[Callable, str | None]] = {
    "scan_lineitem_pruned": sql("SELECT l_orderkey, l_quantity, l_discount FROM {lineitem} WHERE l_shipdate >= TIMESTAMP '1994-01-01' AND l_shipdate < TIMESTAMP '1994-04-01'", "SELECT l_orderkey, l_quantity, l_discount FROM {lineitem} WHERE l_shipdate >= TIMESTAMP '1994-01-01' AND l_shipdate < TIMESTAMP '1994-04-01'"),
    **{f"scan_roundtrip_{k}": (_roundtrip(k), "SELECT n_nationkey, n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey") for k in ("csv", "json", "orc", "parquet")},
    "sink_edges_bucketed": (_bucketed, f"SELECT src, dst FROM ({E8.edges_sql(0.289)}) WHERE src % 8 = 3"),
    "ds_lattice_edges": (_lattice, "WITH v AS (SELECT DISTINCT p_partkey AS v FROM part), s AS (SELECT CAST(ceil(sqrt(max(v) + 1)) AS BIGINT) AS side FROM v) SELECT a.v AS src, b.v AS dst, CAST(1 AS DOUBLE) AS dist FROM v a JOIN v b ON b.v = a.v + 1 CROSS JOIN s WHERE a.v % s.side < s.side - 1 UNION ALL SELECT a.v, b.v, CAST(1 AS DOUBLE) FROM v a CROSS JOIN s JOIN v b ON b.v = a.v + s.side"),
    "ds_edges_list": (_source, f"SELECT src, dst, round(dist, 6) AS dist FROM ({E8.edges_sql(0.205)})"),
    "proj_vector_norm": sql("SELECT vec_id, round(sqrt(aggregate(embedding, 0D, (s, x) -> s + cast(x AS double) * x)), 4) AS norm FROM {embeddings}", "SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x))), 4) AS norm FROM {embeddings}"),
    "filter_complex": sql("SELECT event_id FROM {events} WHERE event_type IN ('click', 'view') AND value BETWEEN 10 AND 50 AND cast(get_json_object(props, '$.k') AS int) > 50 AND ts < TIMESTAMP '2024-01-08'", "SELECT event_id FROM {events} WHERE event_type IN ('click', 'view') AND value BETWEEN 10 AND 50 AND CAST(json_extract_string(props, '$.k') AS INTEGER) > 50 AND ts < TIMESTAMP '2024-01-08'"),
    **{f"join_inner_{n}": (_joined(h), JOINED_SQL) for n, h in {"bcast": "broadcast", "smj": "merge", "shj": "shuffle_hash"}.items()},
    "join_left": sql("SELECT c_custkey, count(o_orderkey) AS n FROM {customer} LEFT JOIN {orders} ON c_custkey = o_custkey GROUP BY c_custkey"),
    "join_right": sql("SELECT n_name, count(s_suppkey) AS n FROM {supplier} RIGHT JOIN {nation} ON s_nationkey = n_nationkey GROUP BY n_name"),
    "join_full": sql("SELECT count(*) AS n, count(o_orderkey) AS o, count(l_orderkey) AS l FROM {orders} FULL JOIN {lineitem} ON o_orderkey = l_orderkey"),
    "join_semi": sql("SELECT doc_id FROM {documents} LEFT SEMI JOIN {labels} USING (doc_id)", "SELECT doc_id FROM {documents} WHERE doc_id IN (SELECT doc_id FROM {labels})"),
    "join_anti": sql("SELECT vec_id FROM {embeddings} LEFT ANTI JOIN {both} ON vec_id = src", "SELECT vec_id FROM {embeddings} WHERE vec_id NOT IN (SELECT src FROM {both})"),
    "join_null_safe": sql("SELECT count(*) AS n FROM (SELECT nullif(n_regionkey, 2) AS k FROM {nation}) a JOIN (SELECT nullif(r_regionkey, 2) AS k FROM {region}) b ON a.k <=> b.k", "SELECT count(*) AS n FROM (SELECT nullif(n_regionkey, 2) AS k FROM {nation}) a JOIN (SELECT nullif(r_regionkey, 2) AS k FROM {region}) b ON a.k IS NOT DISTINCT FROM b.k"),
    "join_cross_small": sql("SELECT r_name, n_name FROM {region} CROSS JOIN {nation}"),
    "join_theta_nl": sql("SELECT a.s_suppkey AS src, b.s_suppkey AS dst FROM {supplier} a JOIN {supplier} b ON a.s_suppkey < b.s_suppkey AND abs(a.s_acctbal - b.s_acctbal) <= 50"),
    "band_join_ca": (_band, "SELECT a.c_custkey AS src, b.c_custkey AS dst FROM customer a JOIN customer b ON a.c_custkey < b.c_custkey AND abs(a.c_acctbal - b.c_acctbal) <= 5.005"),
    "interval_join_orders": sql("SELECT r.r_name, count(*) AS n FROM {events} e JOIN {region} r ON extract(day FROM e.ts) BETWEEN r.r_regionkey * 6 + 1 AND r.r_regionkey * 6 + 6 GROUP BY r.r_name"),
    "asof_events_orders": (_asof, "WITH w AS (SELECT event_id, event_type, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS prior_id FROM events) SELECT event_id, prior_id FROM w WHERE event_type = 'purchase' AND prior_id IS NOT NULL"),
    "near_semi": (_near_docs("left_semi"), _near_docs_sql("IN")),
    "near_anti": (_near_docs("left_anti"), _near_docs_sql("NOT IN")),
    "lateral_topk": sql("SELECT n_name, c_custkey, c_acctbal FROM {nation}, LATERAL (SELECT c_custkey, c_acctbal FROM {customer} WHERE c_nationkey = n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 3)", "SELECT n_name, c_custkey, c_acctbal FROM (SELECT *, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS k FROM {customer}) JOIN {nation} ON c_nationkey = n_nationkey WHERE k <= 3"),
    "agg_basic": sql("SELECT l_returnflag, count(*) AS n, sum(l_quantity) AS q, min(l_tax) AS lo, max(l_tax) AS hi, round(avg(l_quantity), 6) AS mean, round(stddev(l_quantity), 6) AS sd FROM {lineitem} GROUP BY l_returnflag"),
    "agg_distinct": sql("SELECT l_returnflag, count(DISTINCT l_suppkey) AS n FROM {lineitem} GROUP BY l_returnflag"),
    "agg_filter": sql("SELECT l_linestatus, count(*) FILTER (WHERE l_quantity > 25) AS n FROM {lineitem} GROUP BY l_linestatus"),
    "agg_rollup": sql(f"SELECT l_returnflag, l_linestatus, CAST(grouping_id() AS BIGINT) AS g, {S} FROM {{lineitem}} GROUP BY ROLLUP (l_returnflag, l_linestatus)", f"SELECT l_returnflag, l_linestatus, CAST(grouping_id(l_returnflag, l_linestatus) AS BIGINT) AS g, {S} FROM {{lineitem}} GROUP BY ROLLUP (l_returnflag, l_linestatus)"),
    "agg_cube": sql(f"SELECT l_returnflag, l_linestatus, {S} FROM {{lineitem}} GROUP BY CUBE (l_returnflag, l_linestatus)"),
    "agg_grouping_sets": sql(f"SELECT l_returnflag, l_linestatus, {S} FROM {{lineitem}} GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())"),
    "agg_pivot": (lambda s, d: read(s, d, "events").groupBy("user_id").pivot("event_type", ["click", "view"]).count().na.fill(0), "SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS click, count(*) FILTER (WHERE event_type = 'view') AS view FROM events GROUP BY user_id"),
    "agg_unpivot": (lambda s, d: read(s, d, "part").limit(0).unionByName(read(s, d, "part")).select("p_partkey", F.col("p_size").cast("double").alias("size"), F.col("p_retailprice").alias("price")).unpivot("p_partkey", ["size", "price"], "kind", "v"), "SELECT p_partkey, 'size' AS kind, CAST(p_size AS DOUBLE) AS v FROM part UNION ALL SELECT p_partkey, 'price', p_retailprice FROM part"),
    "agg_percentile": sql("SELECT event_type, round(percentile(value, 0.5), 6) AS med FROM {events} GROUP BY event_type", "SELECT event_type, round(median(value), 6) AS med FROM {events} GROUP BY event_type"),
    "agg_approx_distinct": sql("SELECT l_returnflag, abs(approx_count_distinct(l_partkey, 0.01) - count(DISTINCT l_partkey)) <= 0.05 * count(DISTINCT l_partkey) AS near FROM {lineitem} GROUP BY l_returnflag", "SELECT DISTINCT l_returnflag, true AS near FROM {lineitem}"),
    "agg_approx_percentile": (_approx_percentile, "SELECT event_type, unnest([0.25, 0.5, 0.75])::DOUBLE AS part, true AS near FROM events GROUP BY event_type"),
    "agg_maxby_minby": sql("SELECT src, min_by(dst, struct(dist, dst)) AS near, max_by(dst, struct(dist, dst)) AS far FROM {both} GROUP BY src", "SELECT DISTINCT src, first_value(dst) OVER (PARTITION BY src ORDER BY dist, dst) AS near, first_value(dst) OVER (PARTITION BY src ORDER BY dist DESC, dst DESC) AS far FROM {both}"),
    "agg_collect": sql("SELECT src, array_join(array_sort(collect_list(dst)), ',') AS near FROM {edges} GROUP BY src", "SELECT src, string_agg(CAST(dst AS VARCHAR), ',' ORDER BY dst) AS near FROM {edges} GROUP BY src"),
    "agg_udaf_medoid": (_medoid, f"WITH p AS (SELECT label, vec_id AS pid, CAST(embedding[1:8] AS DOUBLE[]) AS vec FROM embeddings), s AS (SELECT a.label, a.pid, round(sum(list_distance(a.vec, b.vec)), 9) AS t FROM p a JOIN p b ON a.label = b.label GROUP BY a.label, a.pid), r AS (SELECT *, row_number() OVER (PARTITION BY label ORDER BY t, pid) AS k FROM s) SELECT label, pid AS medoid FROM r WHERE k = 1"),
    "win_rank_all": sql("SELECT src, dst, CAST(row_number() OVER w AS BIGINT) AS rn, CAST(rank() OVER w AS BIGINT) AS rk, CAST(dense_rank() OVER w AS BIGINT) AS dr, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd, CAST(ntile(4) OVER w AS BIGINT) AS nt FROM {both} WINDOW w AS (PARTITION BY src ORDER BY dist, dst)"),
    "win_lag_lead": sql("SELECT event_id, lag(event_id) OVER w AS prior, lead(event_id) OVER w AS next FROM {events} WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)"),
    "win_rows_frame": sql("SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS s FROM {events}"),
    "win_range_frame": sql("SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY unix_timestamp(CAST(ts AS TIMESTAMP)) RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW), 4) AS s FROM {events}", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY CAST(floor(epoch(ts)) AS BIGINT) RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW), 4) AS s FROM {events}"),
    "win_first_last_nth": sql("SELECT DISTINCT user_id, first_value(event_id) OVER w AS a, last_value(event_id) OVER w AS z, nth_value(event_id, 2) OVER w AS b FROM {events} WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)"),
    "win_sessionize": (_sessions, "WITH g AS (SELECT user_id, CASE WHEN lag(ts) OVER w IS NULL OR floor(epoch(ts)) - floor(epoch(lag(ts) OVER w)) > 86400 THEN 1 ELSE 0 END AS n FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)) SELECT user_id, CAST(sum(n) AS BIGINT) AS sessions FROM g GROUP BY user_id"),
    "topk_global": sql("SELECT src, dst, round(dist, 6) AS dist FROM {edges} ORDER BY dist, src, dst LIMIT 20"),
    "topk_group": sql("SELECT src, dst FROM (SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY dist, dst) AS k FROM {both}) WHERE k <= 3"),
    "limit_offset": sql("SELECT o_orderkey FROM {orders} ORDER BY o_totalprice DESC, o_orderkey LIMIT 10 OFFSET 20"),
    "set_union": sql("SELECT src, dst FROM {edges} UNION SELECT src, dst FROM {fewer}"),
    "set_union_all": sql("SELECT src, dst FROM {edges} UNION ALL SELECT src, dst FROM {fewer}"),
    "set_intersect": sql("SELECT src, dst FROM {edges} INTERSECT SELECT src, dst FROM {fewer}"),
    "set_except": sql("SELECT src, dst FROM {edges} EXCEPT SELECT src, dst FROM {fewer}"),
    "set_except_all": sql("SELECT src FROM {edges} EXCEPT ALL SELECT src FROM {fewer}"),
    "str_suite": sql("SELECT page_id, lower(url) AS lo, upper(trim(url)) AS up, substring(url, 1, 8) AS head, length(url) AS n, replace(url, 'http', 'x') AS rep, regexp_extract(url, '//([^/]+)', 1) AS host FROM {pages}"),
    "str_levenshtein_names": sql("SELECT a.p_name AS x, b.p_name AS y, CAST(levenshtein(a.p_name, b.p_name) AS BIGINT) AS d FROM (SELECT DISTINCT p_name FROM {part}) a JOIN (SELECT DISTINCT p_name FROM {part}) b ON a.p_name < b.p_name AND levenshtein(a.p_name, b.p_name) <= 3"),
    "date_suite": sql("SELECT o_orderkey, CAST(date_trunc('month', o_orderdate) AS DATE) AS m, CAST(extract(year FROM o_orderdate) AS BIGINT) AS y, CAST(datediff(o_orderdate, DATE '1992-01-01') AS BIGINT) AS n FROM {orders}", "SELECT o_orderkey, CAST(date_trunc('month', o_orderdate) AS DATE) AS m, CAST(extract(year FROM o_orderdate) AS BIGINT) AS y, CAST(date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS BIGINT) AS n FROM {orders}"),
    "math_suite": sql("SELECT p_partkey, round(sqrt(p_retailprice), 6) AS r, round(ln(p_retailprice), 6) AS l, CAST(floor(p_retailprice) AS BIGINT) AS f, CAST(p_size % 7 AS BIGINT) AS m, CAST(bit_count(p_partkey ^ p_size) AS BIGINT) AS b FROM {part}", "SELECT p_partkey, round(sqrt(p_retailprice), 6) AS r, round(ln(p_retailprice), 6) AS l, CAST(floor(p_retailprice) AS BIGINT) AS f, CAST(p_size % 7 AS BIGINT) AS m, CAST(bit_count(xor(p_partkey, CAST(p_size AS BIGINT))) AS BIGINT) AS b FROM {part}"),
    "array_suite": sql("SELECT doc_id, CAST(size(split(text, ' ')) AS BIGINT) AS n, array_join(slice(split(text, ' '), 1, 3), '_') AS head, CAST(array_position(split(text, ' '), 'the') AS BIGINT) AS p FROM {documents}", "SELECT doc_id, CAST(len(string_split(text, ' ')) AS BIGINT) AS n, array_to_string(string_split(text, ' ')[1:3], '_') AS head, CAST(coalesce(list_position(string_split(text, ' '), 'the'), 0) AS BIGINT) AS p FROM {documents}"),
    "map_suite": (_map_suite, "WITH w AS (SELECT doc_id, unnest(string_split(lower(text), ' ')) AS w FROM documents), c AS (SELECT doc_id, w, count(*) AS n FROM w GROUP BY doc_id, w) SELECT doc_id, count(*) AS words, count(*) FILTER (WHERE n >= 5) AS frequent, CAST(coalesce(max(CASE WHEN w = 'the' THEN n END), 0) AS BIGINT) AS the FROM c GROUP BY doc_id"),
    "json_suite": sql("SELECT event_id, CAST(get_json_object(props, '$.k') AS BIGINT) AS k FROM {events}", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM {events}"),
    "cond_null_suite": sql("SELECT p_partkey, CASE WHEN p_size > 25 THEN 'big' ELSE 'small' END AS c, coalesce(nullif(p_size, 10), -1) AS n FROM {part}"),
    "sample_hash": sql("SELECT c_custkey FROM {customer} WHERE (c_custkey * 2654435761) % 100 < 10"),
    "cte_recursive_components": (_components_by_recursion, f"WITH RECURSIVE p AS ({SETS['names'].sql}), e AS ({SETS['names'].edges_sql(2)}), s AS (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e), w AS (SELECT pid, pid AS root FROM p UNION SELECT s.dst, w.root FROM w JOIN s ON s.src = w.pid) SELECT pid, min(root) AS component FROM w GROUP BY pid"),
    "subquery_suite": sql("SELECT c_custkey FROM {customer} WHERE c_acctbal > (SELECT avg(c_acctbal) FROM {customer}) AND EXISTS (SELECT 1 FROM {orders} WHERE o_custkey = c_custkey AND o_totalprice > 100000) AND c_nationkey IN (SELECT n_nationkey FROM {nation} WHERE n_regionkey = 1)"),
    "udf_pandas_norm": (_udf, "SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x))), 4) AS norm FROM embeddings"),
    "udtf_near_pairs": (_table_function("SELECT src, dst, round(dist, 6) AS dist FROM near_pairs(TABLE(SELECT * FROM labelled_points) PARTITION BY (label), 0.4D)"), "WITH p AS (SELECT label, vec_id AS pid, CAST(embedding[1:8] AS DOUBLE[]) AS vec FROM embeddings) SELECT a.pid AS src, b.pid AS dst, round(list_distance(a.vec, b.vec), 6) AS dist FROM p a JOIN p b ON a.label = b.label AND a.pid < b.pid WHERE list_distance(a.vec, b.vec) <= 0.4"),
    "udtf_tree_nodes": (_table_function("SELECT sum(size) AS points, count(*) AS trees FROM tree_nodes(TABLE(SELECT * FROM labelled_points) PARTITION BY label)"), "SELECT count(*) AS points, count(DISTINCT label) AS trees FROM embeddings"),
}
