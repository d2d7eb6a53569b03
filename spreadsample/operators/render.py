"""What is drawn: marker sizes, jittered copies, rasters, bins, zoom and progressive views."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spreadsample.operators.baselines import hashed


def marker_size(sample: DataFrame, lo: float = 2.0, hi: float = 20.0, scale: str = "sqrt") -> DataFrame:
    """sample (with density) and marker_size between lo and hi, by the root, logarithm or value of the weight."""
    f = {"sqrt": F.sqrt, "log": lambda c: F.ln(c + 1), "linear": lambda c: c}[scale]
    top = sample.agg(f(F.max("density").cast("double")).alias("top"))
    share = F.coalesce(F.try_divide(f(F.col("density").cast("double")), F.col("top")), F.lit(0.0))
    return sample.crossJoin(F.broadcast(top)).withColumn("marker_size", lo + (hi - lo) * share).drop("top")


def jitter(sample: DataFrame, per: int = 10, most: int = 20, radius: float = 0.005) -> DataFrame:
    """(id, copy, x, y): a member once for every `per` rows that it stands for (at least once, at most `most`), moved by its hash."""
    copies = F.greatest(F.lit(1), F.least(F.lit(most), F.floor(F.col("density") / per).cast("int")))
    many = sample.withColumn("copy", F.explode(F.sequence(F.lit(1), copies)))
    draw = lambda axis: F.conv(F.substring(F.md5(F.concat(F.lit(axis), F.col("id"), F.lit(":"), F.col("copy").cast("string"))), 1, 8), 16, 10).cast("double") / 4294967296.0 - 0.5
    moved = lambda c, axis: F.when(F.col("copy") == 1, F.col(c)).otherwise(F.col(c) + 2 * radius * draw(axis))
    return many.select("id", "copy", moved("x", "x").alias("x"), moved("y", "y").alias("y"))


def raster(points: DataFrame, w: int = 200, h: int = 200, box: tuple[float, float, float, float] = (0.0, 1.0, 0.0, 1.0)) -> DataFrame:
    """(px, py, n, colour): rows and mean value of each pixel of a box; a partial aggregate of at most w * h groups."""
    x0, x1, y0, y1 = box
    pixel = lambda c, lo, hi, size: F.least(F.lit(size - 1), F.floor((F.col(c) - lo) / (hi - lo) * size).cast("int"))
    return zoom(points, box).groupBy(pixel("x", x0, x1, w).alias("px"), pixel("y", y0, y1, h).alias("py")).agg(F.count("*").alias("n"), F.avg("value").alias("colour"))


def bin2d(points: DataFrame, nx: int, ny: int) -> DataFrame:
    """(bx, by, n): a two-dimensional histogram of the unit box."""
    return raster(points, nx, ny).select(F.col("px").alias("bx"), F.col("py").alias("by"), "n")


def zoom(points: DataFrame, box: tuple[float, float, float, float]) -> DataFrame:
    """The rows of a box; on stored samples the ranges reach the Parquet scan."""
    x0, x1, y0, y1 = box
    return points.where((F.col("x") >= x0) & (F.col("x") <= x1) & (F.col("y") >= y0) & (F.col("y") <= y1))


def progressive(sample: DataFrame, upto: int, seed: int = 7) -> DataFrame:
    """The first `upto` members in drawing order, with their sample_rank."""
    from pyspark.sql import Window

    return sample.withColumn("sample_rank", F.row_number().over(Window.orderBy(hashed(seed), "id"))).where(F.col("sample_rank") <= upto)
