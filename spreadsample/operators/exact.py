"""Optimal samples for small sets, the greedy builder, a model for integer programming, and the reduction from edge subgraphs."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from spreadsample.functions import kernels
from spreadsample.operators.exchange import WorkingSet
from spreadsample.operators.measures import pair_values

#: Rows that an exact search accepts: it is exponential in them.
MOST_EXACT = 200


def exact_2(points: DataFrame, eps: float) -> DataFrame:
    """(a, b, objective): the best pair."""
    return pair_values(points, eps).select(F.col("i").alias("a"), F.col("j").alias("b"), F.col("k").alias("objective")).orderBy("objective", "a", "b").limit(1)


def exact_3(points: DataFrame, eps: float) -> DataFrame:
    """(a, b, c, objective): the best triple, from joins of the pair table; cubic, for tiny sets."""
    p = pair_values(points, eps)
    ab, ac, bc = (p.select(F.col("i").alias(u), F.col("j").alias(v), F.col("k").alias(f"k_{u}{v}")) for u, v in ("ab", "ac", "bc"))
    return ab.join(ac, "a").join(bc, ["b", "c"]).select("a", "b", "c", (F.col("k_ab") + F.col("k_ac") + F.col("k_bc")).alias("objective")).orderBy("objective", "a", "b", "c").limit(1)


def _search(prefix: list[int], matrix: np.ndarray, k: int, best: float) -> tuple[float, list[int]]:
    """Depth-first branch and bound below a prefix of ascending positions: potentials of later rows bound what they must add."""
    n, found = len(matrix), []
    bound = [best]

    def below(chosen: list[int], value: float, potential: np.ndarray, start: int) -> None:
        nonlocal found
        need = k - len(chosen)
        if not need:
            if value < bound[0] - 1e-15:
                bound[0], found = value, chosen
            return
        for t in range(start, n - need + 1):
            rest = potential[t + 1 :]
            more = np.partition(rest, need - 2)[: need - 1].sum() if need > 1 else 0.0
            now = value + potential[t]
            if now + more < bound[0]:
                below([*chosen, t], now, potential + matrix[t], t + 1)

    potential = matrix[prefix].sum(axis=0)
    value = sum(matrix[a, b] for i, a in enumerate(prefix) for b in prefix[i + 1 :])
    below(prefix, value, potential, prefix[-1] + 1)
    return bound[0], found


def exact(points: DataFrame, k: int, eps: float, kernel: str = "pair") -> DataFrame:
    """(id, objective): the k rows of least objective, by branch and bound. Every first row is a task's prefix, the exchange's sample the
    first bound. The set is small by nature (MOST_EXACT rows at most), so it travels with the tasks."""
    rows = sorted((r["id"], r["x"], r["y"]) for r in points.select("id", "x", "y").limit(MOST_EXACT + 1).collect())
    if len(rows) > MOST_EXACT:
        raise ValueError(f"an exact search takes at most {MOST_EXACT} rows")
    spark, k = points.sparkSession, min(k, len(rows))
    ids = np.array([r[0] for r in rows], object)
    x, y = (np.array([r[c] for r in rows], float) for c in (1, 2))
    work = WorkingSet(k, eps, kernel)
    for _ in range(5):
        work.offer(*(v[np.array([i not in set(work.id[: work.n]) for i in ids])] for v in (ids, x, y)))
    matrix = kernels.values(kernel, (x[:, None] - x) ** 2 + (y[:, None] - y) ** 2, eps)
    np.fill_diagonal(matrix, 0)
    order = np.argsort(-matrix.sum(1), kind="stable")
    matrix, ids, start = matrix[np.ix_(order, order)], ids[order], sorted(work.id.astype(str).tolist())
    bound = work.objective()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best = bound
        for b in batches:
            for first in b.column(0).to_pylist():
                value, found = _search([first], matrix, k, best)
                if found:
                    best = value
                    yield pa.RecordBatch.from_arrays([pa.array([value]), pa.array([sorted(ids[found].astype(str).tolist())])], ["objective", "ids"])

    spread = spark.range(len(rows) - k + 1).repartition(min(32, len(rows)), "id").mapInArrow(run, "objective double, ids array<string>")
    base = spark.createDataFrame([(bound, start)], "objective double, ids array<string>")
    return spread.union(base).orderBy("objective", "ids").limit(1).select(F.explode("ids").alias("id"), "objective")


def exact_model(points: DataFrame, k: int, eps: float) -> DataFrame:
    """(part, line): an integer program in LP text: z_ij is at least x_i + x_j - 1, the x sum to k, the weighted z are least."""
    pairs = pair_values(points, eps)
    z = F.concat_ws("_", F.lit("z"), "i", "j")
    cost = pairs.select(F.lit("minimize").alias("part"), F.concat(F.format_string("%+.12f", F.col("k")), F.lit(" "), z).alias("line"))
    link = pairs.select(F.lit("subject"), F.concat(z, F.lit(" - x_"), F.col("i"), F.lit(" - x_"), F.col("j"), F.lit(" >= -1")))
    one = points.select(F.lit("sum"), F.concat(F.lit("+ x_"), F.col("id"), F.lit(f" = {k} in total")))
    kind = points.select(F.lit("binary"), F.concat(F.lit("x_"), F.col("id")))
    low = pairs.select(F.lit("bounds"), F.concat(F.lit("0 <= "), z))
    return cost.union(link).union(one).union(kind).union(low)


def greedy(points: DataFrame, k: int, eps: float, checkpoint_every: int = 8, durable=None) -> DataFrame:
    """(id, nth, added): from the smallest id on, the row that adds least proximity (ties to the smaller id), with running potentials: each
    round is one pass over the rows and one row to the driver; lineage is cut every few rounds."""
    keep = durable or (lambda df: df.checkpoint())
    spark = points.sparkSession
    left = points.select("id", "x", "y", F.lit(0.0).alias("p"))
    out: list[tuple[str, int, float]] = []
    for nth in range(1, k + 1):
        best = left.agg(F.min(F.struct("p", "id", "x", "y")).alias("b")).first()["b"]
        if best is None:
            break
        out.append((best["id"], nth, best["p"]))
        dx, dy = F.col("x") - best["x"], F.col("y") - best["y"]
        left = left.where(F.col("id") != best["id"]).withColumn("p", F.col("p") + kernels.column("pair", dx * dx + dy * dy, eps))
        left = keep(left) if nth % checkpoint_every == 0 else left
    return spark.createDataFrame(out, "id string, nth int, added double")


def to_pairs(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """(i, j, k) over all vertex pairs with k = heaviest weight - weight (0 without an edge): the lightest k rows of the pair table are the
    heaviest k-vertex subgraph. edges: (u, v, w) with u < v; vertices: (id)."""
    top = edges.agg(F.max("w").alias("top"))
    a, b = vertices.select(F.col("id").alias("i")), vertices.select(F.col("id").alias("j"))
    every = a.join(b, F.col("i") < F.col("j")).join(edges, (F.col("i") == F.col("u")) & (F.col("j") == F.col("v")), "left")
    return every.crossJoin(F.broadcast(top)).select("i", "j", (F.col("top") - F.coalesce("w", F.lit(0.0))).alias("k"))


def to_edges(pairs: DataFrame) -> DataFrame:
    """Back from pairs (i, j, k) to weights: the largest k becomes 0."""
    return pairs.select(F.col("i").alias("u"), F.col("j").alias("v"), (F.max("k").over(Window.partitionBy()) - F.col("k")).alias("w"))
