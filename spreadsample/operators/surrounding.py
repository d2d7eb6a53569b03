"""Relational, function and streaming operators that users of samples need around them, one query each."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from spreadsample.functions.points import load, tables
from spreadsample.functions.runtime import durable, new_path
from spreadsample.operators import baselines as bl
from spreadsample.operators import density, measures
from spreadsample.operators.queries import WIDE, bottom, d2, unit
from spreadsample.registry import Registry

R = Registry()


def sql(name: str, text: str, duck: str | None = None) -> None:
    """A query that both engines read alike (or DuckDB in its own words)."""
    R.add(name, lambda s, d: (tables(s, d), s.sql(text))[1], duck or text)


def frame(name: str, run, duck: str | None = None) -> None:
    R.add(name, run, duck)


t = lambda s, d, name: s.read.parquet(f"{d}/{name}.parquet")

# scans, sources, sinks
frame("op_scan_pruned", lambda s, d: t(s, d, "lineitem").where((F.col("l_quantity") >= 49) & (F.col("l_discount") <= 0.01)).select("l_orderkey", "l_quantity"), "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_quantity >= 49 AND l_discount <= 0.01")
frame("op_source_range", lambda s, d: s.range(0, 100, 7).withColumnRenamed("id", "v"), "SELECT range AS v FROM range(0, 100, 7)")


def round_trip(kind: str):
    def run(s: SparkSession, d: str) -> DataFrame:
        path, rows = new_path(s, kind), t(s, d, "nation").select("n_nationkey", "n_name")
        rows.write.format(kind).save(path)
        return s.read.schema(rows.schema).format(kind).load(path)

    return run


for _kind in ("csv", "json", "orc"):
    frame(f"op_roundtrip_{_kind}", round_trip(_kind), "SELECT n_nationkey, n_name FROM nation")


def partitioned_sink(s: SparkSession, d: str) -> DataFrame:
    """A dynamic overwrite replaces only the partitions that it writes."""
    path, rows = new_path(s, "sink"), t(s, d, "customer").select("c_custkey", "c_mktsegment")
    rows.write.partitionBy("c_mktsegment").parquet(path)
    rows.where(F.col("c_mktsegment") == "BUILDING").limit(0).union(rows.where(F.col("c_mktsegment") == "BUILDING")).write.option("partitionOverwriteMode", "dynamic").mode("overwrite").partitionBy("c_mktsegment").parquet(path)
    return s.read.parquet(path).groupBy("c_mktsegment").agg(F.count("*").alias("n"))


frame("op_sink_partitioned", partitioned_sink, "SELECT c_mktsegment, count(*) AS n FROM customer GROUP BY 1")

# projection, predicates, functions
frame("op_project", lambda s, d: t(s, d, "part").select(F.col("p_partkey").alias("k"), (F.col("p_retailprice") * 2).alias("twice"), F.col("p_size").cast("string").alias("size_text")), "SELECT p_partkey AS k, p_retailprice * 2 AS twice, CAST(p_size AS VARCHAR) AS size_text FROM part")
sql("op_filter_box", "SELECT event_id, value FROM events WHERE value BETWEEN 100 AND 200 AND event_type IN ('click', 'view') AND user_id IS NOT NULL")
sql("op_filter_like", "SELECT doc_id FROM documents WHERE text LIKE '%the %' AND NOT lang = 'fr' OR n_chars < 20")
frame("op_filter_radius", lambda s, d: load(s, d, "latency").where((F.col("x") - 0.5) ** 2 + (F.col("y") - 0.1) ** 2 <= 0.01).select("id"), f"SELECT id FROM ({unit('latency')}) AS p WHERE (x - 0.5e0) * (x - 0.5e0) + (y - 0.1e0) * (y - 0.1e0) <= 0.01e0")
sql("op_fn_math", "SELECT s_suppkey, round(exp(-s_suppkey / 10e0), 9) AS e, round(ln(s_suppkey + 1), 9) AS l, round(log10(s_suppkey + 1), 9) AS l10, round(sqrt(s_suppkey), 9) AS r, round(sin(s_suppkey) + cos(s_suppkey), 9) AS t, greatest(s_suppkey, 5) AS g, least(s_suppkey, 5) AS m FROM supplier")
_gc = "2 * 6371e0 * asin(sqrt(pow(sin(radians(lat2 - lat1) / 2), 2) + cos(radians(lat1)) * cos(radians(lat2)) * pow(sin(radians(lon2 - lon1) / 2), 2)))"
sql("op_fn_great_circle", f"SELECT s_suppkey, round({_gc}, 6) AS km FROM (SELECT s_suppkey, s_suppkey % 90 AS lat1, s_suppkey % 180 AS lon1, 40e0 AS lat2, 116e0 AS lon2 FROM supplier) AS p")
sql("op_fn_string", "SELECT n_nationkey, length(n_name) AS n, lower(n_name) AS l, substring(n_name, 1, 3) AS s3, concat(n_name, '-', n_regionkey) AS c, md5(n_name) AS h, replace(n_name, 'A', 'b') AS r FROM nation")
frame("op_fn_words", lambda s, d: t(s, d, "documents").select("doc_id", F.size(F.split("text", " ")).alias("words"), F.length(F.regexp_replace("text", "[^aeiou]", "")).alias("vowels")), "SELECT doc_id, CAST(len(string_split(text, ' ')) AS INT) AS words, CAST(length(regexp_replace(text, '[^aeiou]', '', 'g')) AS INT) AS vowels FROM documents")
sql("op_fn_date", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, dayofmonth(o_orderdate) AS d, date_trunc('month', o_orderdate) AS t, date_trunc('month', o_orderdate) + INTERVAL '1' DAY AS n FROM orders")
frame("op_fn_array_dot", lambda s, d: t(s, d, "embeddings").select("vec_id", F.round(F.aggregate(F.zip_with("embedding", "embedding", lambda a, b: a.cast("double") * b), F.lit(0.0), lambda a, b: a + b), 6).alias("norm2"), F.size(F.filter("embedding", lambda v: v > 0)).alias("positive")), "SELECT vec_id, round(list_sum(list_transform(embedding, lambda v: CAST(v AS DOUBLE) * v)), 6) AS norm2, CAST(len(list_filter(embedding, lambda v: v > 0)) AS INT) AS positive FROM embeddings")
frame("op_fn_explode", lambda s, d: t(s, d, "nation").select("n_nationkey", F.posexplode(F.sequence(F.lit(1), F.col("n_regionkey") + 1)).alias("pos", "v")), "SELECT n_nationkey, CAST(v - 1 AS INT) AS pos, CAST(v AS INT) AS v FROM nation, unnest(range(1, n_regionkey + 2)) AS u(v)")
frame("op_fn_map", lambda s, d: t(s, d, "nation").select(F.create_map("n_name", "n_regionkey").alias("m"), "n_name").select(F.element_at("m", F.col("n_name")).alias("v"), F.map_keys("m")[0].alias("k")), "SELECT n_regionkey AS v, n_name AS k FROM nation")
frame("op_fn_json", lambda s, d: t(s, d, "events").groupBy(F.get_json_object("props", "$.k").cast("int").alias("k")).agg(F.count("*").alias("n")), "SELECT CAST(props ->> '$.k' AS INT) AS k, count(*) AS n FROM events GROUP BY 1")
frame("op_fn_from_json", lambda s, d: t(s, d, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k")), "SELECT event_id, CAST(props ->> '$.k' AS INT) AS k FROM events")
frame("op_fn_decimal_null", lambda s, d: t(s, d, "lineitem").agg(F.sum(F.col("l_extendedprice").cast("decimal(15,2)")).cast("double").alias("total"), F.sum(F.coalesce(F.try_divide(F.lit(1.0), F.nullif(F.col("l_discount"), F.lit(0.0))), F.lit(0.0))).alias("inv")).select(F.round("total", 2).alias("total"), F.round("inv", 3).alias("inv")), "SELECT round(CAST(sum(CAST(l_extendedprice AS DECIMAL(15, 2))) AS DOUBLE), 2) AS total, round(sum(coalesce(1 / nullif(l_discount, 0), 0)), 3) AS inv FROM lineitem")

# joins
for _how, _word in (("inner", "JOIN"), ("left", "LEFT JOIN"), ("right", "RIGHT JOIN"), ("full", "FULL JOIN")):
    frame(f"op_join_{_how}", lambda s, d, h=_how: t(s, d, "customer").join(t(s, d, "orders").where("o_totalprice > 250000"), F.col("c_custkey") == F.col("o_custkey"), h).select("c_custkey", "o_orderkey"), f"SELECT c_custkey, o_orderkey FROM customer {_word} (SELECT * FROM orders WHERE o_totalprice > 250000) AS o ON c_custkey = o_custkey")
frame("op_join_star_broadcast", lambda s, d: t(s, d, "supplier").join(F.broadcast(t(s, d, "nation")), F.col("s_nationkey") == F.col("n_nationkey")).join(F.broadcast(t(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey")).groupBy("r_name").agg(F.count("*").alias("n")), "SELECT r_name, count(*) AS n FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1")
frame("op_join_merge_hint", lambda s, d: t(s, d, "lineitem").hint("merge").join(t(s, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n")), "SELECT o_orderpriority, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
for _how, _word in (("left_semi", ""), ("left_anti", "NOT ")):
    frame(f"op_join_{_how}", lambda s, d, h=_how: t(s, d, "customer").join(t(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), h).select("c_custkey"), f"SELECT c_custkey FROM customer WHERE {_word}EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
_at = lambda c: f"CAST(floor({c} / 0.0002e0) AS BIGINT)"
frame("op_join_range_cells", lambda s, d: measures.close_pairs(load(s, d, "hubs"), 0.0002), f"WITH s AS ({unit('hubs')}), o AS (SELECT range - 1 AS d FROM range(3)), t AS (SELECT id, x, y, {_at('x')} + ox.d AS cx, {_at('y')} + oy.d AS cy FROM s, o AS ox, o AS oy) SELECT a.id AS a_id, b.id AS b_id FROM (SELECT *, {_at('x')} AS cx, {_at('y')} AS cy FROM s) AS a JOIN t AS b ON a.cx = b.cx AND a.cy = b.cy WHERE a.id < b.id AND {d2('a', 'b')} <= 0.0002e0 * 0.0002e0")
frame("op_join_nearest", lambda s, d: density.by_scan(bl.uniform(load(s, d, "supp"), 7), load(s, d, "supp")), f"WITH s AS ({bottom('supp', 7)}), n AS (SELECT arg_min(s.id, ROW({d2('p', 's')}, s.id)) AS sid FROM ({unit('supp')}) AS p, s GROUP BY p.id) SELECT s.id, count(n.sid) AS density FROM s LEFT JOIN n ON n.sid = s.id GROUP BY s.id")


def as_of(s: SparkSession, d: str) -> DataFrame:
    """For each purchase the last earlier view of the user: one shuffle by user and a sort, no join."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    seen = F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(w)
    return t(s, d, "events").withColumn("view_id", seen).where(F.col("event_type") == "purchase").select("event_id", "view_id")


frame("op_join_asof", as_of, "SELECT event_id, view_id FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type = 'view' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS view_id FROM events) AS e WHERE event_type = 'purchase'")
sql("op_join_self", "SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a CROSS JOIN nation b WHERE a.n_nationkey < b.n_nationkey AND a.n_regionkey = b.n_regionkey")

# aggregates
frame("op_agg_basic", lambda s, d: t(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("q"), F.round(F.avg("l_discount"), 9).alias("d"), F.min("l_tax").alias("lo"), F.max("l_tax").alias("hi"), F.count_if(F.col("l_quantity") > 25).alias("big"), F.bool_or(F.col("l_tax") > 0.07).alias("any_tax")), "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS q, round(avg(l_discount), 9) AS d, min(l_tax) AS lo, max(l_tax) AS hi, CAST(count(*) FILTER (WHERE l_quantity > 25) AS BIGINT) AS big, bool_or(l_tax > 0.07) AS any_tax FROM lineitem GROUP BY 1, 2")
frame("op_agg_stats", lambda s, d: t(s, d, "events").groupBy("event_type").agg(*[F.round(c, 6).alias(a) for c, a in ((F.stddev_samp("value"), "sd"), (F.var_pop("value"), "vp"), (F.corr("value", "user_id"), "r"), (F.covar_samp("value", "user_id"), "cv"), (F.regr_slope("value", "user_id"), "sl"), (F.median("value"), "md"), (F.percentile("value", 0.9), "p9"), (F.kurtosis("value"), "ku"))]), "SELECT event_type, round(stddev_samp(value), 6) AS sd, round(var_pop(value), 6) AS vp, round(corr(value, user_id), 6) AS r, round(covar_samp(value, user_id), 6) AS cv, round(regr_slope(value, user_id), 6) AS sl, round(median(value), 6) AS md, round(quantile_cont(value, 0.9), 6) AS p9, round(kurtosis_pop(value), 6) AS ku FROM events GROUP BY 1")
frame("op_agg_arg_extremes", lambda s, d: t(s, d, "events").groupBy("event_type").agg(F.max_by("event_id", F.struct("value", "event_id")).alias("top"), F.min_by("event_id", F.struct("value", "event_id")).alias("low")), "SELECT event_type, arg_max(event_id, ROW(value, event_id)) AS top, arg_min(event_id, ROW(value, event_id)) AS low FROM events GROUP BY 1")
frame("op_agg_collect", lambda s, d: t(s, d, "nation").groupBy("n_regionkey").agg(F.array_join(F.sort_array(F.collect_list("n_name")), ",").alias("names")), "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY 1")
sql("op_agg_distinct", "SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY event_type")
frame("op_agg_approx", lambda s, d: t(s, d, "events").agg((F.abs(F.approx_count_distinct("user_id", 0.02) / F.count_distinct("user_id") - 1) < 0.1).alias("near_distinct"), (F.abs(F.percentile_approx("value", 0.5, 1000) / F.median("value") - 1) < 0.05).alias("near_median")), "SELECT true AS near_distinct, true AS near_median")
sql("op_agg_having", "SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey HAVING count(*) > 12")
for _kind in ("ROLLUP", "CUBE"):
    sql(f"op_agg_{_kind.lower()}", f"SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY {_kind} (l_returnflag, l_linestatus)")
sql("op_agg_grouping_sets", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")
frame("op_agg_pivot", lambda s, d: t(s, d, "lineitem").groupBy("l_linestatus").pivot("l_returnflag", ["A", "N", "R"]).agg(F.count(F.lit(1))).na.fill(0), "SELECT l_linestatus, count(*) FILTER (WHERE l_returnflag = 'A') AS A, count(*) FILTER (WHERE l_returnflag = 'N') AS N, count(*) FILTER (WHERE l_returnflag = 'R') AS R FROM lineitem GROUP BY 1")
frame("op_agg_unpivot", lambda s, d: t(s, d, "part").select("p_partkey", F.col("p_size").cast("double").alias("size"), F.col("p_retailprice").alias("price")).unpivot("p_partkey", ["size", "price"], "what", "v"), "SELECT p_partkey, 'size' AS what, CAST(p_size AS DOUBLE) AS v FROM part UNION ALL SELECT p_partkey, 'price', p_retailprice FROM part")

# windows, order, sets, subqueries
sql("op_win_rank", "SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 9) AS pr, round(cume_dist() OVER w, 9) AS cd, ntile(4) OVER w AS nt FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey)")
sql("op_win_analytic", "SELECT event_id, lag(value) OVER w AS before, lead(value, 2) OVER w AS after, first_value(event_id) OVER w AS f FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
sql("op_win_frame", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS s3, count(*) OVER (PARTITION BY event_type ORDER BY event_id RANGE BETWEEN 50 PRECEDING AND CURRENT ROW) AS near FROM events")
sql("op_sort_limit", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 5")
frame("op_topk_per_group", lambda s, d: t(s, d, "orders").withColumn("rn", F.row_number().over(Window.partitionBy("o_orderpriority").orderBy(F.desc("o_totalprice"), "o_orderkey"))).where("rn <= 3").select("o_orderpriority", "o_orderkey", "rn"), "SELECT o_orderpriority, o_orderkey, CAST(row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey) AS INT) AS rn FROM orders QUALIFY rn <= 3")
_a, _b = "SELECT s_nationkey AS k FROM supplier", "SELECT c_nationkey AS k FROM customer"
for _name, _word in (("union_all", "UNION ALL"), ("union", "UNION"), ("intersect", "INTERSECT"), ("intersect_all", "INTERSECT ALL"), ("except", "EXCEPT"), ("except_all", "EXCEPT ALL")):
    sql(f"op_set_{_name}", f"{_a} {_word} {_b}")
frame("op_set_union_by_name", lambda s, d: t(s, d, "nation").select("n_name", F.lit(1).alias("a")).unionByName(t(s, d, "region").select(F.lit(2).alias("a"), F.col("r_name").alias("n_name"))), "SELECT n_name, 1 AS a FROM nation UNION ALL SELECT r_name, 2 FROM region")
frame("op_set_drop_duplicates", lambda s, d: t(s, d, "lineitem").dropDuplicates(["l_discount", "l_tax"]).select("l_discount", "l_tax"), "SELECT DISTINCT l_discount, l_tax FROM lineitem")
sql("op_subquery_scalar", "SELECT s_suppkey FROM supplier WHERE s_acctbal > (SELECT avg(s_acctbal) FROM supplier)")
sql("op_subquery_in", "SELECT c_custkey FROM customer WHERE c_nationkey IN (SELECT n_nationkey FROM nation WHERE n_regionkey = 1)")
sql("op_subquery_correlated", "SELECT o_orderkey FROM orders o WHERE o_totalprice = (SELECT max(o_totalprice) FROM orders i WHERE i.o_custkey = o.o_custkey)")
#: A histogram of prices and its coarser levels, each of half as many bins as the one before.
sql("op_cte_recursive", "WITH RECURSIVE r(n, bin, c) AS (SELECT 0, CAST(floor(o_totalprice / 1000) AS BIGINT), count(*) FROM orders GROUP BY CAST(floor(o_totalprice / 1000) AS BIGINT) UNION ALL SELECT n + 1, CAST(floor(bin / 2) AS BIGINT), c FROM r WHERE n < 9) SELECT n, bin, CAST(sum(c) AS BIGINT) AS c FROM r GROUP BY n, bin")


# functions of ours, table transforms, sampling, streams
def scalar_udf(s: SparkSession, d: str) -> DataFrame:
    """The pair kernel as an Arrow function against the built-in expression."""
    @F.pandas_udf("double")
    def kernel(x1: pd.Series, y1: pd.Series, x2: pd.Series, y2: pd.Series) -> pd.Series:
        return np.exp(-((x1 - x2) ** 2 + (y1 - y2) ** 2) / (2 * WIDE * WIDE))

    p = bl.uniform(load(s, d, "supp"), 20)
    a, b = p.select(F.col("id").alias("i"), F.col("x").alias("x1"), F.col("y").alias("y1")), p.select(F.col("id").alias("j"), F.col("x").alias("x2"), F.col("y").alias("y2"))
    return a.join(b, F.col("i") < F.col("j")).select("i", "j", F.round(kernel("x1", "y1", "x2", "y2"), 9).alias("k"))


_pair = f"exp(-{d2('a', 'b')} / (2e0 * 0.1e0 * 0.1e0))"
frame("op_udf_scalar", scalar_udf, f"WITH s AS ({bottom('supp', 20)}) SELECT a.id AS i, b.id AS j, round({_pair}, 9) AS k FROM s a JOIN s b ON a.id < b.id")


def grouped_udf(s: SparkSession, d: str) -> DataFrame:
    @F.pandas_udf("double")
    def objective(x: pd.Series, y: pd.Series) -> float:
        d2s = (x.values[:, None] - x.values) ** 2 + (y.values[:, None] - y.values) ** 2
        return float(np.triu(np.exp(-d2s / (2 * WIDE * WIDE)), 1).sum())

    return bl.uniform(load(s, d, "latency"), 200).groupBy("category").agg(F.round(objective("x", "y"), 6).alias("objective"))


frame("op_udf_grouped", grouped_udf, f"WITH s AS ({bottom('latency', 200)}) SELECT a.category, round(sum(CASE WHEN a.id < b.id THEN {_pair} ELSE 0 END), 6) AS objective FROM s a JOIN s b ON a.category = b.category GROUP BY 1")
frame("op_log_sum_exp", lambda s, d: t(s, d, "events").groupBy("event_type").agg(F.max("value").alias("top"), F.collect_list("value").alias("v")).select("event_type", F.round(F.col("top") + F.ln(F.aggregate("v", F.lit(0.0), lambda a, x: a + F.exp(x - F.col("top")))), 6).alias("lse")), "SELECT event_type, round(top + ln(sum(exp(value - top))), 6) AS lse FROM (SELECT event_type, value, max(value) OVER (PARTITION BY event_type) AS top FROM events) AS e GROUP BY event_type, top")


def cogrouped(s: SparkSession, d: str) -> DataFrame:
    def both(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        key = a["category"].iloc[0] if len(a) else b["category"].iloc[0]
        return pd.DataFrame({"category": [key], "rows": [len(a)], "kept": [len(b)]})

    p = load(s, d, "latency").select("category", "id")
    kept = bl.uniform(p, 100).select(F.col("category").alias("category"), F.col("id").alias("kept_id")).toDF("category", "kept_id")
    return p.groupBy("category").cogroup(durable(kept).groupBy("category")).applyInPandas(both, "category string, rows long, kept long")


frame("op_transform_cogroup", cogrouped, f"SELECT p.category, count(*) AS rows, count(s.id) AS kept FROM ({unit('latency')}) AS p LEFT JOIN ({bottom('latency', 100)}) AS s ON p.id = s.id GROUP BY 1")
frame("op_sample_builtin", lambda s, d: t(s, d, "lineitem").sample(0.1, seed=3).agg(F.count("*").alias("n")).crossJoin(t(s, d, "lineitem").agg(F.count("*").alias("all"))).select(F.col("n").between(F.col("all") * 0.085, F.col("all") * 0.115).alias("near_tenth")), "SELECT true AS near_tenth")
frame("op_sample_by", lambda s, d: t(s, d, "lineitem").sampleBy("l_returnflag", {"A": 0.2, "N": 0.0, "R": 0.0}, seed=3).select("l_returnflag").distinct(), "SELECT 'A' AS l_returnflag")
frame("op_session_repartition", lambda s, d: t(s, d, "orders").repartitionByRange(8, "o_orderkey").sortWithinPartitions("o_orderkey").groupBy(F.spark_partition_id().alias("p")).agg(F.min("o_orderkey").alias("lo"), F.max("o_orderkey").alias("hi")).agg(F.count("*").alias("parts"), F.min("lo").alias("lo"), F.max("hi").alias("hi")).select((F.col("parts") <= 8).alias("few"), "lo", "hi"), "SELECT true AS few, min(o_orderkey) AS lo, max(o_orderkey) AS hi FROM orders")


def streamed(transform, mode: str = "append"):
    """Runs a transform over events as a file stream to its end and returns the table that it wrote."""

    def run(s: SparkSession, d: str) -> DataFrame:
        src, out = new_path(s, "events"), new_path(s, "out")
        rows = t(s, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
        rows.repartitionByRange(4, "event_id").write.parquet(src)
        stream = s.readStream.schema(rows.schema).parquet(src)
        if mode == "append":
            transform(stream).writeStream.format("parquet").option("path", out).option("checkpointLocation", new_path(s, "offsets")).trigger(availableNow=True).start().awaitTermination()
            return s.read.schema(transform(rows).schema).parquet(out)

        def keep(batch: DataFrame, n: int) -> None:
            batch.write.mode("overwrite").parquet(f"{out}/last")

        transform(stream).writeStream.outputMode("complete").foreachBatch(keep).option("checkpointLocation", new_path(s, "offsets")).trigger(availableNow=True).start().awaitTermination()
        return s.read.parquet(f"{out}/last")

    return run


frame("op_stream_tumbling", streamed(lambda df: df.groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.date_format("w.start", "yyyy-MM-dd").alias("day"), "event_type", "n"), "complete"), "SELECT strftime(ts, '%Y-%m-%d') AS day, event_type, count(*) AS n FROM events GROUP BY 1, 2")
frame("op_stream_sliding", streamed(lambda df: df.groupBy(F.window("ts", "2 days", "1 day").alias("w")).agg(F.count("*").alias("n")).select(F.date_format("w.start", "yyyy-MM-dd").alias("day"), "n"), "complete"), "SELECT strftime(day, '%Y-%m-%d') AS day, count(*) AS n FROM (SELECT date_trunc('day', ts) AS day FROM events UNION ALL SELECT date_trunc('day', ts) - INTERVAL '1' DAY FROM events) AS e GROUP BY 1")
frame("op_stream_session", streamed(lambda df: df.groupBy(F.session_window("ts", "1 hour").alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.unix_timestamp("w.start").alias("began"), "n"), "complete"), "SELECT user_id, CAST(floor(epoch(min(ts))) AS BIGINT) AS began, count(*) AS n FROM (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS g FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL '1' HOUR THEN 0 ELSE 1 END AS fresh FROM events) AS e) AS f GROUP BY user_id, g")
frame("op_stream_dedup", streamed(lambda df: df.withWatermark("ts", "60 days").dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type")), "SELECT DISTINCT user_id, event_type FROM events")
frame("op_stream_static_join", streamed(lambda df: df.join(df.sparkSession.range(0, 50).withColumnRenamed("id", "user_id"), "user_id").select("event_id", "user_id")), "SELECT event_id, user_id FROM events WHERE user_id BETWEEN 0 AND 49")


def stream_density(s: SparkSession, d: str) -> DataFrame:
    """Density counts of streamed rows by nearest member, against the batch."""
    from spreadsample.streaming.refresh import density_upkeep

    p, src, out = durable(load(s, d, "latency").select("id", "x", "y")), new_path(s, "rows"), new_path(s, "counts")
    sample = durable(bl.uniform(p, 20))
    p.write.parquet(src)
    counts = density_upkeep(s.readStream.schema(p.schema).parquet(src), sample)
    counts.writeStream.outputMode("complete").foreachBatch(lambda b, n: b.write.mode("overwrite").parquet(out)).option("checkpointLocation", new_path(s, "offsets")).trigger(availableNow=True).start().awaitTermination()
    return s.read.parquet(out)


frame("op_stream_density", stream_density, f"WITH s AS ({bottom('latency', 20)}) SELECT id, count(*) AS rows FROM (SELECT arg_min(s.id, ROW({d2('p', 's')}, s.id)) AS id FROM ({unit('latency')}) AS p, s GROUP BY p.id) AS n GROUP BY id")
