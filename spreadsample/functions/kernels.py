"""Proximity kernels as Spark columns and as numpy, and the radii beyond which they vanish."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: name: (column of squared distance, numpy of squared distance, SQL of squared distance with {d2} and {e})
KERNELS = {
    "gaussian": (lambda d2, e: F.exp(-d2 / (e * e)), lambda d2, e: np.exp(-d2 / (e * e)), "exp(-({d2}) / ({e} * {e}))"),
    "pair": (lambda d2, e: F.exp(-d2 / (2 * e * e)), lambda d2, e: np.exp(-d2 / (2 * e * e)), "exp(-({d2}) / (2e0 * {e} * {e}))"),
    "laplacian": (lambda d2, e: F.exp(-F.sqrt(d2) / e), lambda d2, e: np.exp(-np.sqrt(d2) / e), "exp(-sqrt({d2}) / {e})"),
    "cauchy": (lambda d2, e: 1 / (1 + d2 / (e * e)), lambda d2, e: 1 / (1 + d2 / (e * e)), "1e0 / (1e0 + ({d2}) / ({e} * {e}))"),
    "epanechnikov": (lambda d2, e: F.greatest(F.lit(0.0), 1 - d2 / (e * e)), lambda d2, e: np.maximum(0, 1 - d2 / (e * e)), "greatest(0e0, 1e0 - ({d2}) / ({e} * {e}))"),
}
DEFAULT_TOL = math.exp(-16)


def squared(ax: str, ay: str, bx: str, by: str) -> Column:
    dx, dy = F.col(ax) - F.col(bx), F.col(ay) - F.col(by)
    return dx * dx + dy * dy


def column(name: str, d2: Column, eps: float) -> Column:
    return KERNELS[name][0](d2, eps)


def values(name: str, d2: np.ndarray, eps: float) -> np.ndarray:
    return KERNELS[name][1](d2, eps)


def sql(name: str, d2: str, eps: float | str) -> str:
    return KERNELS[name][2].format(d2=d2, e=f"{eps!r}e0" if isinstance(eps, float) else eps)


def cutoff(name: str, eps: float | Column, tol: float = DEFAULT_TOL) -> float | Column:
    """The distance from which the kernel is below tol: 4 eps for the Gaussian at the default, 5.657 eps for its pair kernel."""
    far = -math.log(tol)
    return {"gaussian": eps * math.sqrt(far), "pair": eps * math.sqrt(2 * far), "laplacian": eps * far, "cauchy": eps * math.sqrt(1 / tol - 1), "epanechnikov": eps}[name]


def pair_by_quadrature(distances: DataFrame, eps: float, name: str = "gaussian", reach: float = 6.0, steps: int = 120) -> DataFrame:
    """(d, value): the plane integral of the product of two kernels d apart, over its value at d = 0, by a midpoint grid: the pair
    kernel of any kernel. distances (d) are distinct; each meets the whole grid."""
    spark = distances.sparkSession
    cell = 2 * reach * eps / steps
    grid = spark.range(steps * steps).select((-reach * eps + (F.floor(F.col("id") / steps) + 0.5) * cell).alias("gx"), (-reach * eps + (F.col("id") % steps + 0.5) * cell).alias("gy"))
    k = lambda half: column(name, (F.col("gx") - half) * (F.col("gx") - half) + F.col("gy") * F.col("gy"), eps)
    product = k(F.col("d") / 2) * k(-F.col("d") / 2)
    sums = distances.crossJoin(F.broadcast(grid)).groupBy("d").agg(F.sum(product).alias("s"), F.sum(k(F.lit(0.0)) * k(F.lit(0.0))).alias("s0"))
    return sums.select("d", (F.col("s") / F.col("s0")).alias("value"))
