"""Bandwidth rules: a share of the largest pair distance, and a normal-reference rule."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def bbox(points: DataFrame, ratio: float = 100.0) -> DataFrame:
    """(eps): the diagonal of the bounding box over ratio; at most sqrt(2) times the diameter rule. One aggregate."""
    dx, dy = F.max("x") - F.min("x"), F.max("y") - F.min("y")
    return points.agg((F.sqrt(dx * dx + dy * dy) / ratio).alias("eps"))


def hull(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Indices of the convex hull (monotone chain)."""
    order = np.lexsort((y, x))
    turn = lambda a, b, c: (x[b] - x[a]) * (y[c] - y[a]) - (y[b] - y[a]) * (x[c] - x[a])
    sides = []
    for way in (order, order[::-1]):
        side: list[int] = []
        for i in way:
            while len(side) > 1 and turn(side[-2], side[-1], i) <= 0:
                side.pop()
            side.append(int(i))
        sides += side[:-1]
    return np.array(sorted(set(sides)) or order[:1].tolist(), np.int64)


def diameter(points: DataFrame) -> float:
    """The largest pair distance: partitions give the corners of their hulls, whose hull is taken on the driver. Corners are few
    (they grow with the logarithm of the rows for smooth shapes); a partition gives at most the corners of its batches."""

    def corners(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept = np.zeros((0, 2))
        for b in batches:
            both = np.vstack((kept, np.column_stack((b.column(0).to_numpy(), b.column(1).to_numpy()))))
            both = np.unique(both, axis=0)
            kept = both[hull(both[:, 0], both[:, 1])] if len(both) > 2 else both
        yield pa.RecordBatch.from_arrays([pa.array(kept[:, 0]), pa.array(kept[:, 1])], ["x", "y"])

    found = np.array([tuple(r) for r in points.select("x", "y").mapInArrow(corners, "x double, y double").collect()]).reshape(-1, 2)
    found = np.unique(found, axis=0)
    if len(found) < 2:
        return 0.0
    found = found[hull(found[:, 0], found[:, 1])] if len(found) > 2 else found
    return math.sqrt(max(((found - p) ** 2).sum(axis=1).max() for p in found))


def by_diameter(points: DataFrame, ratio: float = 100.0) -> DataFrame:
    return points.sparkSession.createDataFrame([(diameter(points) / ratio,)], "eps double")


def normal_reference(points: DataFrame, *by: str) -> DataFrame:
    """(eps): n^(-1/6) times the root of the mean variance of both axes; with columns, (by, eps) for each of their values."""
    return points.groupBy(*by).agg((F.sqrt((F.var_samp("x") + F.var_samp("y")) / 2) * F.pow(F.count("*").cast("double"), F.lit(-1 / 6))).alias("eps"))
