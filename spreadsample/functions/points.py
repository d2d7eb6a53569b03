"""Point sets: SQL that Spark and DuckDB both read, giving (id, x, y, value, category) for each plottable row."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
LINE_ID = "concat_ws('-', l_orderkey, l_linenumber, l_partkey, l_suppkey, CAST(CAST(floor(l_extendedprice * 100 + 0.5e0) AS BIGINT) AS VARCHAR(20)))"
FRAC = "({0} - CAST(floor({0}) AS DOUBLE))".format

#: Uniform and normal columns derived from lineitem, and the hub layout; fixed values of the derived sets.
NORMALS = f"""
  SELECT id, qty, price, w, sqrt(-2e0 * ln(u1)) * cos(2e0 * pi() * u2) AS g1, sqrt(-2e0 * ln(u1)) * sin(2e0 * pi() * u2) AS g2,
         sqrt(-2e0 * ln(u3)) * cos(2e0 * pi() * u4) AS g3, sqrt(-2e0 * ln(u3)) * sin(2e0 * pi() * u4) AS g4
  FROM (SELECT {LINE_ID} AS id, l_quantity AS qty, l_extendedprice AS price,
               (l_partkey + 0.5e0) / (mp + 1e0) AS u1, {FRAC("(l_extendedprice * 0.6180339887e0)")} AS u2,
               (l_suppkey + 0.5e0) / (ms + 1e0) AS u3, {FRAC("(l_orderkey * 0.6180339887e0)")} AS u4,
               {FRAC("((l_orderkey * 7 + l_linenumber) * 0.7548776662466927e0)")} AS w
        FROM lineitem CROSS JOIN (SELECT max(l_partkey) AS mp, max(l_suppkey) AS ms FROM lineitem) AS top) AS u"""
HUB_X, HUB_Y = FRAC("((h + 1) * 0.7548776662466927e0)"), FRAC("((h + 1) * 0.5698402909980532e0)")

POINTS = {
    "latency": "SELECT CAST(event_id AS VARCHAR(20)) AS id, CAST(hour(ts) * 3600 + minute(ts) * 60 + CAST(floor(second(ts)) AS INT) AS DOUBLE) AS x, value AS y, value, event_type AS category FROM events",
    "price": f"SELECT {LINE_ID} AS id, l_quantity AS x, l_extendedprice AS y, l_extendedprice / l_quantity AS value, l_returnflag AS category FROM lineitem",
    "discount": f"SELECT {LINE_ID} AS id, l_discount AS x, l_tax AS y, l_quantity AS value, l_returnflag AS category FROM lineitem",
    "docs": "SELECT CAST(doc_id AS VARCHAR(20)) AS id, CAST(n_chars AS DOUBLE) AS x, CAST(length(text) - length(replace(text, ' ', '')) + 1 AS DOUBLE) AS y, CAST(n_chars AS DOUBLE) AS value, lang AS category FROM documents",
    "supp": "SELECT CAST(s_suppkey AS VARCHAR(20)) AS id, CAST(s_suppkey AS DOUBLE) AS x, s_acctbal AS y, s_acctbal AS value, CAST(s_nationkey AS VARCHAR(20)) AS category FROM supplier",
    "cust": "SELECT CAST(c_custkey AS VARCHAR(20)) AS id, CAST(c_custkey AS DOUBLE) AS x, c_acctbal AS y, c_acctbal AS value, c_mktsegment AS category FROM customer",
    "part": "SELECT CAST(p_partkey AS VARCHAR(20)) AS id, CAST(p_size AS DOUBLE) AS x, p_retailprice AS y, p_retailprice AS value, p_brand AS category FROM part",
    "orders": "SELECT CAST(o_orderkey AS VARCHAR(20)) AS id, CAST(year(o_orderdate) * 372 + month(o_orderdate) * 31 + day(o_orderdate) AS DOUBLE) AS x, o_totalprice AS y, o_totalprice AS value, o_orderpriority AS category FROM orders",
    "conv": "SELECT concat_ws('-', conv_id, turn) AS id, CAST(turn AS DOUBLE) AS x, CAST(length(text) AS DOUBLE) AS y, CAST(length(text) AS DOUBLE) AS value, role AS category FROM conversations",
    "pages": "SELECT CAST(page_id AS VARCHAR(20)) AS id, CAST(length(html) AS DOUBLE) AS x, CAST(length(html) - length(replace(html, '<', '')) AS DOUBLE) AS y, CAST(length(url) AS DOUBLE) AS value, 'page' AS category FROM pages",
    "embed": "SELECT CAST(vec_id AS VARCHAR(20)) AS id, CAST({first} AS DOUBLE) AS x, CAST({second} AS DOUBLE) AS y, CAST(label AS DOUBLE) AS value, CAST(label AS VARCHAR(20)) AS category FROM embeddings",
    "hubs": f"SELECT id, x, y, 50e0 + 30e0 * sin(3e0 * x) * cos(2e0 * y) AS value, CAST(h AS VARCHAR(20)) AS category FROM (SELECT id, h, {HUB_X} + (0.008e0 + 0.002e0 * (h % 5)) * g1 AS x, {HUB_Y} + (0.008e0 + 0.002e0 * (h % 5)) * g2 AS y FROM (SELECT *, CAST(floor(25e0 * w * w * w) AS BIGINT) AS h FROM ({NORMALS}) AS n) AS k) AS p",
    "gauss5": f"SELECT id, g1 AS x, 0.6e0 * g1 + 0.8e0 * g3 AS y, 0.5e0 * g2 + 0.5e0 * g4 AS value, 'all' AS category FROM ({NORMALS}) AS n",
    "mix1a": f"SELECT id, g1 AS x, g2 AS y, 1e0 AS value, '1' AS category FROM ({NORMALS}) AS n",
    "mix1b": f"SELECT id, g1 AS x, 0.7e0 * g1 + 0.714142842854285e0 * g2 AS y, 1e0 AS value, '1' AS category FROM ({NORMALS}) AS n",
    "mix2a": f"SELECT id, g1 + CASE WHEN w < 0.5e0 THEN 0e0 ELSE 6e0 END AS x, g2 AS y, 2e0 AS value, '2' AS category FROM ({NORMALS}) AS n",
    "mix2b": f"SELECT id, CASE WHEN w < 0.3e0 THEN 0.5e0 * g1 ELSE g1 + 4e0 END AS x, CASE WHEN w < 0.3e0 THEN g2 ELSE 0.5e0 * g2 + 2e0 END AS y, 2e0 AS value, '2' AS category FROM ({NORMALS}) AS n",
}


def raw_sql(name: str, duck: bool = False) -> str:
    first, second = ("embedding[1]", "embedding[2]") if duck else ("embedding[0]", "embedding[1]")
    text = POINTS[name].replace("{first}", first).replace("{second}", second)
    return f"SELECT id, x, y, value, category FROM ({text}) AS raw WHERE abs(x) < 1e300 AND abs(y) < 1e300"


def unit_sql(name: str, duck: bool = False) -> str:
    """The set in the unit box (an axis without extent stays at 0); the box is one aggregate joined to the rows."""
    raw = raw_sql(name, duck)
    return f"""SELECT id, CASE WHEN x1 > x0 THEN (x - x0) / (x1 - x0) ELSE 0e0 END AS x,
       CASE WHEN y1 > y0 THEN (y - y0) / (y1 - y0) ELSE 0e0 END AS y, value, category
FROM ({raw}) AS p CROSS JOIN (SELECT min(x) AS x0, max(x) AS x1, min(y) AS y0, max(y) AS y1 FROM ({raw}) AS q) AS box"""


def tables(spark: SparkSession, sf_dir: str, *names: str) -> None:
    """Makes the given tables (all by default) visible to SQL."""
    for name in names or TABLES:
        spark.read.parquet(f"{sf_dir}/{name}.parquet").createOrReplaceTempView(name)


def source_of(name: str) -> str:
    return next(t for t in TABLES if f"FROM {t}" in POINTS[name])


def load(spark: SparkSession, sf_dir: str, name: str, unit: bool = True) -> DataFrame:
    tables(spark, sf_dir, source_of(name))
    if NORMALS not in POINTS[name]:
        return spark.sql(unit_sql(name) if unit else raw_sql(name))
    rows = placed(spark, name)
    if not unit:
        return rows
    box = spark.sql(raw_sql(name)).agg(*[f(c).alias(f"{c}{n}") for c in "xy" for n, f in ((0, F.min), (1, F.max))])
    scaled = lambda c: F.when(F.col(f"{c}1") > F.col(f"{c}0"), (F.col(c) - F.col(f"{c}0")) / (F.col(f"{c}1") - F.col(f"{c}0"))).otherwise(F.lit(0.0)).alias(c)
    return rows.crossJoin(F.broadcast(box)).select("id", scaled("x"), scaled("y"), "value", "category")


def placed(spark: SparkSession, name: str) -> DataFrame:
    """The rows of raw_sql. The filter on places does not pass the struct: pushed through all projections of a derived set, it would grow
    to a condition that is too long to be compiled."""
    made = spark.sql(f"SELECT id, x, y, value, category FROM ({POINTS[name]}) AS raw")
    return made.select(F.inline(F.array(F.struct(*made.columns)))).where("abs(x) < 1e300 AND abs(y) < 1e300")


def from_frame(df: DataFrame, id_col: str, x: str, y: str, value: str | None = None, category: str | None = None) -> DataFrame:
    """A point set from any table: times become seconds, booleans 0 and 1; rows whose place is null or not finite are left out."""

    def number(c: str):
        kind = dict(df.dtypes)[c]
        if kind in ("timestamp", "timestamp_ntz", "date"):
            return F.unix_micros(F.col(c).cast("timestamp")) / 1e6
        if kind.startswith("interval"):
            return F.col(c).cast("interval second").cast("double")
        return F.col(c).cast("double")

    out = df.select(F.col(id_col).cast("string").alias("id"), number(x).alias("x"), number(y).alias("y"), (number(value) if value else F.lit(None).cast("double")).alias("value"), (F.col(category).cast("string") if category else F.lit(None).cast("string")).alias("category"))
    finite = lambda c: F.col(c).isNotNull() & ~F.isnan(c) & (F.abs(F.col(c)) < float("inf"))
    return out.where(finite("x") & finite("y"))
