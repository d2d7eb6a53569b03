"""Time budgets, error/time curves, column-pair advice and weighted aggregates: small relational plans around stored samples."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def fit_latency(timings: DataFrame) -> DataFrame:
    """(series, slope, intercept, r2) of seconds over rows, by series."""
    return timings.groupBy("series").agg(F.regr_slope("seconds", "n").alias("slope"), F.regr_intercept("seconds", "n").alias("intercept"), F.regr_r2("seconds", "n").alias("r2"))


def pick(catalog: DataFrame, seconds: float, slope: float, intercept: float = 0.0) -> DataFrame:
    """(k, fits): the largest stored size whose predicted time is within the bound, else the smallest, flagged."""
    time = F.lit(intercept) + F.lit(slope) * F.col("k")
    return catalog.agg(F.max(F.when(time <= seconds, F.col("k"))).alias("best"), F.min("k").alias("least")).select(F.coalesce("best", "least").alias("k"), F.col("best").isNotNull().alias("fits"))


def time_for_error(curves: DataFrame, error: float) -> DataFrame:
    """(method, seconds): the first time at which a method's error is no larger than error."""
    return curves.where(F.col("error") <= error).groupBy("method").agg(F.min("seconds").alias("seconds"))


def best_error_by_time(curves: DataFrame) -> DataFrame:
    """(method, seconds, error, best): the least error reached so far."""
    w = Window.partitionBy("method").orderBy("seconds").rowsBetween(Window.unboundedPreceding, 0)
    return curves.withColumn("best", F.min("error").over(w))


def speedup(curves: DataFrame, ours: str) -> DataFrame:
    """(ours_seconds, method, factor): for each point of one method, how much longer each other method takes to its error."""
    one = curves.where(F.col("method") == ours).select(F.col("seconds").alias("ours_seconds"), F.col("error").alias("reached"))
    other = curves.where(F.col("method") != ours)
    first = other.join(F.broadcast(one), F.col("error") <= F.col("reached")).groupBy("ours_seconds", "method").agg(F.min("seconds").alias("needs"))
    return first.select("ours_seconds", "method", (F.col("needs") / F.col("ours_seconds")).alias("factor"))


def advise_by_frequency(log: DataFrame) -> DataFrame:
    """(xcol, ycol, n, share): how often column pairs are plotted, and the share of queries that the most plotted ones cover."""
    counted = log.groupBy("xcol", "ycol").agg(F.count("*").alias("n"))
    w = Window.orderBy(F.desc("n"), "xcol", "ycol").rowsBetween(Window.unboundedPreceding, 0)
    return counted.withColumn("share", F.sum("n").over(w) / F.sum("n").over(Window.partitionBy()))


def advise_by_stats(df: DataFrame, columns: list[str]) -> DataFrame:
    """(xcol, ycol, score, skew, tails, distinct): pairs of numeric columns by how much their plot has to show: 1 - |correlation|, then how lopsided
    and heavy-tailed the two columns are together, and the smaller number of distinct values (a pair of few values is better shown as a
    table). One aggregate over the table."""
    pairs = [(a, b) for i, a in enumerate(columns) for b in columns[i + 1 :]]
    each = [f(c).alias(f"{n}_{c}") for c in columns for n, f in (("s", F.skewness), ("k", F.kurtosis), ("d", lambda c: F.approx_count_distinct(c, 0.02)))]
    one = df.agg(*[F.corr(a, b).alias(f"c_{a}_{b}") for a, b in pairs], *each)
    both = lambda n, a, b: F.abs(F.col(f"{n}_{a}")) + F.abs(F.col(f"{n}_{b}"))
    rows = F.array(*[F.struct(F.lit(a).alias("xcol"), F.lit(b).alias("ycol"), (1 - F.abs(F.coalesce(F.col(f"c_{a}_{b}"), F.lit(1.0)))).alias("score"), both("s", a, b).alias("skew"), both("k", a, b).alias("tails"), F.least(f"d_{a}", f"d_{b}").alias("distinct")) for a, b in pairs])
    return one.select(F.inline(rows))


def advise_manually(df: DataFrame, pairs: list[tuple[str, str]]) -> DataFrame:
    """(xcol, ycol): the pairs that someone named, after a check that both columns are there and hold numbers or times."""
    kinds = dict(df.dtypes)
    for c in {c for pair in pairs for c in pair}:
        if c not in kinds or kinds[c].split("(")[0] not in ("tinyint", "smallint", "int", "bigint", "float", "double", "decimal", "date", "timestamp", "timestamp_ntz", "boolean"):
            raise ValueError(f"{c} is no column that a plot has an axis for")
    return df.sparkSession.createDataFrame(pairs, "xcol string, ycol string")


def weighted_average(sample: DataFrame, by: str, value: str = "value") -> DataFrame:
    """(by, estimate, rows): a group's mean and size from a sample whose members carry density weights."""
    return sample.groupBy(by).agg((F.sum(F.col("density") * F.col(value)) / F.sum("density")).alias("estimate"), F.sum("density").alias("rows"))
