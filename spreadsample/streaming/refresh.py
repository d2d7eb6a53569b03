"""Samples kept up to date from a stream: the exchange goes on with arriving rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from spreadsample.operators.density import nearest_counts
from spreadsample.operators.exchange import rescan


def refresh(sample: DataFrame, new_rows: DataFrame, k: int, eps: float, **options) -> DataFrame:
    """The sample after new rows were offered. Any order is valid, so late rows need no care."""
    return rescan(sample.select("id", "x", "y").union(new_rows.select("id", "x", "y")), sample.select("id", "x", "y"), k, eps, **options)


def stream(points: DataFrame, k: int, eps: float, path: str, checkpoint: str, **options):
    """Starts a query that offers every micro-batch of points (id, x, y) to the sample under path/version=n. A version is a
    batch: a batch that is tried again writes the same version from the one before, so restarts repeat nothing."""
    spark = points.sparkSession

    def offer(batch: DataFrame, n: int) -> None:
        before = current(spark, path, upto=n - 1)
        after = refresh(before, batch, k, eps, **options) if before is not None else rescan(batch, batch.limit(0), k, eps, **options)
        after.select("id", "x", "y", "burden").write.mode("overwrite").parquet(f"{path}/version={n}")

    return points.writeStream.foreachBatch(offer).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def current(spark: SparkSession, path: str, upto: int | None = None) -> DataFrame | None:
    """The sample of the last version (not above upto), or None."""
    hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    fs = hadoop.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    found = [int(f.getPath().getName().split("=")[1]) for f in fs.listStatus(hadoop) if f.getPath().getName().startswith("version=")] if fs.exists(hadoop) else []
    found = [v for v in found if upto is None or v <= upto]
    return spark.read.parquet(f"{path}/version={max(found)}") if found else None


def density_upkeep(points: DataFrame, sample: DataFrame) -> DataFrame:
    """(id, rows) running counts of streamed rows by nearest member: a stream joined to a static sample."""
    return nearest_counts(sample, points, "rows")
