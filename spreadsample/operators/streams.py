"""Further joins and windows, and stream operators with state: keyed samples, interval joins, late rows, the memory sink."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from spreadsample.functions.points import load, tables
from spreadsample.functions.runtime import durable, new_path
from spreadsample.operators import baselines as bl
from spreadsample.operators import measures
from spreadsample.operators.queries import WIDE, unit
from spreadsample.registry import Registry
from spreadsample.streaming import keyed, refresh

R = Registry()


def sql(name: str, text: str) -> None:
    R.add(name, lambda s, d: (tables(s, d), s.sql(text))[1], text)


# joins and windows
R.add("op_join_hash_hint", lambda s, d: s.read.parquet(f"{d}/orders.parquet").hint("shuffle_hash").join(s.read.parquet(f"{d}/customer.parquet"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n")), "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
sql("op_join_lateral_top", "SELECT s_suppkey, c_custkey FROM supplier, LATERAL (SELECT c_custkey FROM customer WHERE c_nationkey = s_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 2) AS n")
sql("op_join_interval", "SELECT a.event_id AS view_id, b.event_id AS purchase_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.ts >= b.ts - INTERVAL '6' HOUR AND a.ts <= b.ts WHERE a.event_type = 'view' AND b.event_type = 'purchase'")


def band_join(s: SparkSession, d: str, width: float = 50.0) -> DataFrame:
    """Customers within width of each supplier's balance: an equi-join on cells of that width, then the exact test."""
    cell = lambda c: F.floor(F.col(c) / width)
    suppliers = s.read.parquet(f"{d}/supplier.parquet").select("s_suppkey", "s_acctbal", F.explode(F.sequence(cell("s_acctbal") - 1, cell("s_acctbal") + 1)).alias("cell"))
    customers = s.read.parquet(f"{d}/customer.parquet").select("c_acctbal", cell("c_acctbal").alias("cell"))
    near = suppliers.join(customers, "cell").where(F.col("c_acctbal").between(F.col("s_acctbal") - width, F.col("s_acctbal") + width))
    return near.groupBy("s_suppkey").agg(F.count("*").alias("n"))


R.add("op_join_band", band_join, "SELECT s_suppkey, count(*) AS n FROM supplier JOIN customer ON c_acctbal BETWEEN s_acctbal - 50 AND s_acctbal + 50 GROUP BY 1")
sql("op_win_nth", "SELECT event_id, nth_value(event_id, 2) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second FROM events")
sql("op_win_range_interval", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL '1' DAY PRECEDING AND CURRENT ROW) AS in_a_day FROM events")


# streams
def drained(rows: DataFrame, path: str, mode: str, checkpoint: str) -> None:
    """Runs a streamed table into path/batch=n to its end; a batch that is tried again writes the same place."""
    keep = lambda b, n: b.write.mode("overwrite").parquet(f"{path}/batch={n}")
    rows.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()


def keyed_samples(s: SparkSession, d: str, k: int = 20) -> DataFrame:
    """Each event type's sample from a stream of four files: rows seen, size, members that are no rows, against a uniform one."""
    p, src, out = durable(load(s, d, "latency").select("id", "x", "y", "category")), new_path(s, "keyed"), new_path(s, "samples")
    p.repartition(4, "id").write.parquet(src)
    stream = s.readStream.schema(p.schema).option("maxFilesPerTrigger", 1).parquet(src)
    drained(keyed.samples_by_key(stream, k, WIDE, "category"), out, "update", new_path(s, "offsets"))
    last = durable(s.read.parquet(out).groupBy("key").agg(F.max_by(F.struct("rows", "id", "objective"), "batch").alias("s")).select("key", "s.*"))
    members = last.select("key", F.explode("id").alias("id"))
    strange = members.join(p.select("id", F.col("category").alias("key")), ["id", "key"], "left_anti").groupBy("key").agg(F.count("*").alias("strange"))
    place = F.row_number().over(Window.partitionBy("category").orderBy(F.md5("id"), "id"))  # limited before the shuffle
    drawn = p.withColumn("nth", place).where(F.col("nth") <= k).groupBy("category").agg(F.collect_list(F.struct("x", "y")).alias("u"))
    pair = F.transform("u", lambda a: F.aggregate(F.transform("u", lambda b: F.exp(-((a["x"] - b["x"]) ** 2 + (a["y"] - b["y"]) ** 2) / (2 * WIDE * WIDE))), F.lit(0.0), lambda t, v: t + v))
    uniform = drawn.select(F.col("category").alias("key"), ((F.aggregate(pair, F.lit(0.0), lambda t, v: t + v) - F.size("u")) / 2).alias("uniform"))
    return last.join(uniform, "key").join(strange, "key", "left").select("key", "rows", F.size("id").cast("long").alias("kept"), F.coalesce("strange", F.lit(0)).cast("long").alias("strange"), (F.col("objective") <= F.col("uniform")).alias("beats_uniform"))


R.add("op_stream_keyed_samples", keyed_samples, f"SELECT category AS key, count(*) AS rows, least(count(*), 20) AS kept, CAST(0 AS BIGINT) AS strange, true AS beats_uniform FROM ({unit('latency')}) AS p GROUP BY 1")


def timed_events(s: SparkSession, d: str) -> DataFrame:
    return s.read.parquet(f"{d}/events.parquet").select("event_id", "user_id", "event_type", F.col("ts").cast("timestamp").alias("ts"))


def stream_interval_join(s: SparkSession, d: str) -> DataFrame:
    """Views and later purchases of a user within six hours, both sides streams; watermarks let old rows leave the state."""
    rows, src, out = timed_events(s, d), new_path(s, "events"), new_path(s, "pairs")
    rows.repartitionByRange(4, "event_id").write.parquet(src)
    stream = lambda kind, ts, i: s.readStream.schema(rows.schema).parquet(src).where(F.col("event_type") == kind).withWatermark("ts", "1 day").select(F.col("user_id").alias(f"u_{i}"), F.col("ts").alias(ts), F.col("event_id").alias(i))
    views, purchases = stream("view", "seen", "view_id"), stream("purchase", "bought", "purchase_id")
    pairs = views.join(purchases, (F.col("u_view_id") == F.col("u_purchase_id")) & (F.col("seen") >= F.col("bought") - F.expr("INTERVAL 6 HOURS")) & (F.col("seen") <= F.col("bought")))
    drained(pairs.select("view_id", "purchase_id"), out, "append", new_path(s, "offsets"))
    return s.read.parquet(out).select("view_id", "purchase_id")


R.add("op_stream_interval_join", stream_interval_join, R.oracles["op_join_interval"])


def two_arrivals(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    """The first half of the events; then the second half, of which every 50th row is 20 days behind its time."""
    rows = timed_events(s, d)
    half = rows.agg(F.expr("max(event_id) div 2")).first()[0]
    behind = F.when(F.col("event_id") % 50 == 0, F.col("ts") - F.expr("INTERVAL 20 DAYS")).otherwise(F.col("ts"))
    return rows.where(F.col("event_id") <= half), rows.where(F.col("event_id") > half).withColumn("ts", behind)


def stream_late(s: SparkSession, d: str) -> DataFrame:
    """Counts by day that a watermark of one day closed; rows of days that were closed when they came are left out."""
    src, out, offsets = new_path(s, "arrivals"), new_path(s, "days"), new_path(s, "offsets")
    for n, part in enumerate(two_arrivals(s, d)):
        part.write.mode("append").parquet(src)
        counts = s.readStream.schema(part.schema).parquet(src).withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("n"))
        drained(counts.select(F.date_format("w.start", "yyyy-MM-dd").alias("day"), "n"), f"{out}/run={n}", "append", offsets)
    return s.read.parquet(out).select("day", "n")


R.add("op_stream_late_rows", stream_late, """
WITH e AS (SELECT event_id, event_id > (SELECT max(event_id) // 2 FROM events) AS second, ts FROM events),
a AS (SELECT second, CASE WHEN second AND event_id % 50 = 0 THEN ts - INTERVAL 20 DAY ELSE ts END AS ts FROM e),
m AS (SELECT max(ts) FILTER (WHERE NOT second) - INTERVAL 1 DAY AS before, max(ts) - INTERVAL 1 DAY AS after FROM a),
d AS (SELECT second, date_trunc('day', ts) AS day FROM a)
SELECT strftime(day, '%Y-%m-%d') AS day, count(*) AS n FROM d, m
WHERE day + INTERVAL 1 DAY <= after AND NOT (second AND day + INTERVAL 1 DAY <= before) GROUP BY 1
""")


def late_sample(s: SparkSession, d: str, k: int = 40) -> DataFrame:
    """Rows that come late are offered to the sample like all others, since any order of the scan is valid."""
    p = durable(load(s, d, "latency").select("id", "x", "y"))
    src, out, offsets = new_path(s, "late"), new_path(s, "sample"), new_path(s, "offsets")
    late = F.col("id").cast("long") % 50 == 0
    found = []
    for part in (p.where(~late), p.where(late)):
        part.write.mode("append").parquet(src)
        refresh.stream(s.readStream.schema(p.schema).parquet(src), k, WIDE, out, offsets).awaitTermination()
        found.append(measures.objective_by_cells(refresh.current(s, out), WIDE).first()[0])
    now = refresh.current(s, out)
    outside = now.join(p.select("id"), "id", "left_anti").count()
    return s.createDataFrame([(now.count(), outside, found[1] <= found[0] + 1e-9, found[1] <= measures.objective_by_cells(bl.uniform(p, k), WIDE).first()[0])], "n_rows long, n_outside long, never_rises boolean, beats_uniform boolean")


R.add("op_stream_late_sample", late_sample, "SELECT CAST(40 AS BIGINT) AS n_rows, CAST(0 AS BIGINT) AS n_outside, true AS never_rises, true AS beats_uniform")


def memory_sink(s: SparkSession, d: str) -> DataFrame:
    """Counts by type in a memory table, which the driver holds: for results of a few rows only."""
    rows, src, name = timed_events(s, d), new_path(s, "events"), f"counts_{uuid.uuid4().hex}"
    rows.write.parquet(src)
    s.readStream.schema(rows.schema).parquet(src).groupBy("event_type").agg(F.count("*").alias("n")).writeStream.format("memory").queryName(name).outputMode("complete").option("checkpointLocation", new_path(s, "offsets")).trigger(availableNow=True).start().awaitTermination()
    return s.table(name)


R.add("op_stream_memory_sink", memory_sink, "SELECT event_type, count(*) AS n FROM events GROUP BY 1")
