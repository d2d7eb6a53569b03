"""Checks of a sample: improving swaps left, bookkeeping, and the bound of a stable sample."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spreadsample.functions import kernels
from spreadsample.functions.runtime import bounded
from spreadsample.operators.exchange import MemberGrid, WorkingSet
from spreadsample.operators.measures import burdens_by_cells

#: Members that may travel to every task.
MOST_MEMBERS = 1_000_000


def improving_swaps(points: DataFrame, sample: DataFrame, eps: float, slack: float = 1e-12, kernel: str = "pair", tol: float = 1e-36) -> DataFrame:
    """(swaps): pairs of a member and a row outside whose exchange would lower the objective by more than slack.

    Members travel with the tasks, and a row counts its swaps where it is read: against members beyond the radius at which the kernel
    falls below tol by a search in the sorted burdens, against those within it one by one. tol is so small that what it leaves out cannot
    move a sum past slack: burdens of lonely members are themselves about as large as slack. A task returns one number."""
    rows = sorted(tuple(r) for r in sample.select("id", "x", "y").limit(MOST_MEMBERS + 1).collect())
    if len(rows) > MOST_MEMBERS:
        raise ValueError(f"swaps are counted for at most {MOST_MEMBERS} members")
    if not rows:
        return points.sparkSession.createDataFrame([(0,)], "swaps long")
    work = WorkingSet(len(rows), eps, kernel, "local", tol)
    work.fill(np.array([r[0] for r in rows], object), *(np.array([r[c] for r in rows], float) for c in (1, 2)))
    mx, my, radius, burden = work.x, work.y, work.radius, np.zeros(len(rows))
    for at, row, slot in MemberGrid(mx, my, radius).pairs(mx, my):
        other = at + row != slot  # a member's own 1 would round a small burden
        np.add.at(burden, at + row[other], work.near(mx[at + row[other]], my[at + row[other]], mx[slot[other]], my[slot[other]]))
    inside = {r[0] for r in rows}

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        grid, ordered, found = MemberGrid(mx, my, radius), np.sort(burden), 0
        for b in batches:
            outside = np.array([i not in inside for i in b.column(0).to_pylist()], bool)
            x, y = (b.column(c).to_numpy()[outside] for c in (1, 2))
            for at, row, slot in grid.pairs(x, y):
                near = kernels.values(kernel, (x[at + row] - mx[slot]) ** 2 + (y[at + row] - my[slot]) ** 2, eps)
                potential = np.bincount(row, near, min(grid.step, len(x) - at))
                found += int((len(ordered) - np.searchsorted(ordered, potential + slack, "right")).sum())
                found += int((potential[row] - near < burden[slot] - slack).sum()) - int((potential[row] < burden[slot] - slack).sum())
        yield pa.RecordBatch.from_arrays([pa.array([found])], ["n"])

    return points.select("id", "x", "y").mapInArrow(count, "n long").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("swaps"))


def consistency(points: DataFrame, sample: DataFrame, k: int, eps: float, slack: float = 1e-8) -> DataFrame:
    """(n_rows, n_ids, n_outside, burdens_match): the sample has min(k, N) rows, distinct, all from points, with true burdens. Pairs too
    far apart to move k burdens by slack are not looked at."""
    true = burdens_by_cells(sample.select("id", "x", "y"), eps, tol=slack / (10 * max(1, k))).withColumnRenamed("burden", "true_burden")
    size = sample.join(true, "id").agg(F.count("*").alias("n_rows"), F.count_distinct("id").alias("n_ids"), F.coalesce(F.bool_and(F.abs(F.col("burden") - F.col("true_burden")) < slack), F.lit(True)).alias("burdens_match"))
    outside = sample.select("id").distinct().withColumnRenamed("id", "s_id")
    met = points.join(bounded(outside, k), F.col("id") == F.col("s_id"), "left_semi").agg(F.count_distinct("id").alias("inside"))
    return size.crossJoin(met).select("n_rows", "n_ids", "burdens_match", (F.col("n_ids") - F.col("inside")).alias("n_outside"))


def quality_bound(average: float, optimum: float) -> bool:
    """A swap-stable sample's averaged objective is within a quarter of the optimum's."""
    return average <= optimum + 0.25 + 1e-12
