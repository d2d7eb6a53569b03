"""Accuracy measures of a sample: objective, burdens, point loss and its averages, the log loss ratio; rank correlation."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from spreadsample.functions import kernels

LN10 = float(np.log(10))


def pair_values(sample: DataFrame, eps: float, kernel: str = "pair") -> DataFrame:
    """(i, j, k) for i < j: all unordered pairs of a sample and their proximity. Quadratic by nature, for samples of some thousands; larger ones
    go by cells."""
    a, b = (sample.select(F.col("id").alias(i), F.col("x").alias(f"{i}x"), F.col("y").alias(f"{i}y")) for i in "ij")
    return a.join(b, F.col("i") < F.col("j")).select("i", "j", kernels.column(kernel, kernels.squared("ix", "iy", "jx", "jy"), eps).alias("k"))


def near_pairs(a: DataFrame, b: DataFrame, radius: float, id_a: str = "id", id_b: str = "id") -> DataFrame:
    """(a_id, ax, ay, b_id, bx, by, d2) for rows within radius: an equi-join on grid cells of that width; every row of b goes to its nine
    neighbouring cells. Nothing is compared across the plane."""
    cell = lambda c: F.floor(F.col(c) / radius).cast("long")
    near = F.array(*[F.lit(d) for d in (-1, 0, 1)])
    left = a.select(F.col(id_a).alias("a_id"), F.col("x").alias("ax"), F.col("y").alias("ay"), cell("x").alias("cx"), cell("y").alias("cy"))
    right = b.select(F.col(id_b).alias("b_id"), F.col("x").alias("bx"), F.col("y").alias("by"), cell("x").alias("mx"), cell("y").alias("my"))
    right = right.withColumn("dx", F.explode(near)).withColumn("dy", F.explode(near))
    right = right.select("b_id", "bx", "by", (F.col("mx") + F.col("dx")).alias("cx"), (F.col("my") + F.col("dy")).alias("cy"))
    return left.join(right, ["cx", "cy"]).withColumn("d2", kernels.squared("ax", "ay", "bx", "by")).where(F.col("d2") <= radius * radius).drop("cx", "cy")


#: Strips of a distance join are this many radii wide; candidates that one step of it expands.
STRIP, CANDIDATES = 8, 1 << 18


def close_pairs(points: DataFrame, radius: float) -> DataFrame:
    """(a_id, b_id) with a_id < b_id, rows within radius of each other: what near_pairs gives for a set and itself, for sets whose ninefold
    copy is too much. Rows are dealt to strips of x once; only those within radius of the lower border go to the strip before too. A task
    sweeps its strips by bands of y and holds two bands of one strip."""
    wide = radius * (1 + 1e-6)
    strip = lambda x: F.floor(x / (STRIP * radius)).cast("long")
    placed = points.where(F.col("id").isNotNull() & ~F.isnan("x") & ~F.isnan("y") & F.col("x").isNotNull() & F.col("y").isNotNull())  # others are near nothing
    both = placed.select(F.col("id").cast("string").alias("id"), "x", "y", F.floor(F.col("y") / wide).cast("long").alias("band"), F.array_distinct(F.array(strip(F.col("x")), strip(F.col("x") - wide))).alias("to"))
    dealt = both.select("id", "x", "y", "band", F.posexplode("to").alias("guest", "strip"))
    swept = dealt.repartition("strip").sortWithinPartitions("strip", "band", "x")
    return swept.mapInArrow(_swept(radius, wide), "a_id string, b_id string")


def _swept(radius: float, wide: float):
    """Pairs of rows (id, x, y, band, guest, strip) that come ordered by strip, band and x. A row looks back: in its band to x - wide, in
    the band before to both sides. Two guests meet where they are at home."""

    def pairs(ids: pa.Array, x, y, band, guest, first: int) -> Iterator[pa.RecordBatch]:
        # bands by number, a gap counts as one empty band; places of a band lie in [0, 1/2) of its number
        at = np.concatenate(([0], np.cumsum(np.minimum(np.diff(band), 2))))
        place = lambda b, v: b + 0.25 + (v - x[0]) / (8 * STRIP * radius)
        key, new = place(at, x), np.arange(first, len(x))
        rank = pc.rank(ids, tiebreaker="dense").to_numpy()
        low = np.stack((key.searchsorted(place(at[new] - 1, x[new] - wide)), key.searchsorted(place(at[new], x[new] - wide))), 1)
        high = np.stack((key.searchsorted(place(at[new] - 1, x[new] + wide), "right"), new), 1)
        low, high, row = low.ravel(), high.ravel(), np.repeat(new, 2)
        some = high > low
        low, high, row = low[some], high[some], row[some]
        ends = np.concatenate(([0], np.cumsum(high - low)))
        for lo in range(0, int(ends[-1]), CANDIDATES):  # a run of candidates may end in the middle of a row's
            nth = np.arange(lo, min(lo + CANDIDATES, int(ends[-1])))
            run = np.repeat(np.arange(len(row)), np.diff(np.clip(ends, nth[0], nth[-1] + 1)))
            i, j = row[run], nth - ends[run] + low[run]
            dx, dy = x[i] - x[j], y[i] - y[j]
            met = (dx * dx + dy * dy <= radius * radius) & (rank[i] != rank[j]) & ~(guest[i] & guest[j])
            i, j = i[met], j[met]
            less = rank[i] < rank[j]
            if len(i):
                yield pa.RecordBatch.from_arrays([ids.take(pa.array(np.where(less, i, j))), ids.take(pa.array(np.where(less, j, i)))], ["a_id", "b_id"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None
        for b in batches:
            strips = b.column(5).to_numpy()
            cuts = [0, *(np.flatnonzero(strips[1:] != strips[:-1]) + 1).tolist(), len(strips)]
            for lo, hi in zip(cuts, cuts[1:]):
                if lo == hi:
                    continue
                rows, strip = pa.Table.from_batches([b.slice(lo, hi - lo)]), strips[lo]
                first = 0
                if held is not None and held[0] == strip:
                    first, rows = len(held[1]), pa.concat_tables([held[1], rows]).combine_chunks()
                x, y, band, guest = (rows.column(c).to_numpy() for c in (1, 2, 3, 4))
                yield from pairs(rows.column(0).combine_chunks(), x, y, band, guest > 0, first)
                held = strip, rows.slice(int(np.searchsorted(band, band[-1] - 1)))

    return run


def objective(sample: DataFrame, eps: float, kernel: str = "pair") -> DataFrame:
    """(objective): total proximity of all unordered pairs."""
    return pair_values(sample, eps, kernel).agg(F.coalesce(F.sum("k"), F.lit(0.0)).alias("objective"))


def objective_by_cells(sample: DataFrame, eps: float, kernel: str = "pair", tol: float = kernels.DEFAULT_TOL) -> DataFrame:
    """The objective without pairs whose proximity is below tol, for samples too large to meet each other whole."""
    pairs = near_pairs(sample, sample, kernels.cutoff(kernel, eps, tol)).where("a_id < b_id")
    return pairs.agg(F.coalesce(F.sum(kernels.column(kernel, F.col("d2"), eps)), F.lit(0.0)).alias("objective"))


def average_objective(sample: DataFrame, eps: float, kernel: str = "pair") -> DataFrame:
    """(avg_objective): the objective over k (k - 1), between 0 and 1/2."""
    k = sample.agg(F.count("*").alias("k"))
    return objective(sample, eps, kernel).crossJoin(k).select((F.col("objective") / (F.col("k") * (F.col("k") - 1))).alias("avg_objective"))


def burdens(sample: DataFrame, eps: float, kernel: str = "pair") -> DataFrame:
    """(id, burden): each member's total proximity to the others, without the half; they sum to twice the objective."""
    pairs = pair_values(sample, eps, kernel)
    sides = pairs.select(F.col("i").alias("id"), "k").union(pairs.select("j", "k"))
    return sample.select("id").join(sides.groupBy("id").agg(F.sum("k").alias("b")), "id", "left").select("id", F.coalesce("b", F.lit(0.0)).alias("burden"))


def burdens_by_cells(sample: DataFrame, eps: float, kernel: str = "pair", tol: float = kernels.DEFAULT_TOL) -> DataFrame:
    """Burdens without pairs whose proximity is below tol: members meet by cells, so there are as many rows as near pairs."""
    pairs = near_pairs(sample, sample, kernels.cutoff(kernel, eps, tol)).where("a_id != b_id")
    near = pairs.groupBy(F.col("a_id").alias("id")).agg(F.sum(kernels.column(kernel, F.col("d2"), eps)).alias("b"))
    return sample.select("id").join(near, "id", "left").select("id", F.coalesce("b", F.lit(0.0)).alias("burden"))


def probes(spark: SparkSession, m: int, oversample: int = 8) -> DataFrame:
    """(probe_id, px, py): m * oversample places of a two-dimensional low-discrepancy sequence in the unit box."""
    frac = lambda c: c - F.floor(c)
    return spark.range(1, m * oversample + 1).select(F.col("id").alias("probe_id"), frac(0.5 + F.col("id") * 0.7548776662466927).alias("px"), frac(0.5 + F.col("id") * 0.5698402909980532).alias("py"))


def domain_probes(points: DataFrame, m: int, radius: float = 0.1, oversample: int = 8) -> DataFrame:
    """The first m probes that have a data row within radius. One scan of the rows: the m * oversample probes travel with the tasks, and each
    task returns the probes that it found a row for, at most one row per probe. Pairs of rows and probes are never made."""
    at = probes(points.sparkSession, m, oversample)
    fixed = np.array([tuple(r) for r in at.orderBy("probe_id").collect()], np.float64).reshape(-1, 3)  # their number is a parameter
    near = points.where(F.col("x").between(-radius, 1 + radius) & F.col("y").between(-radius, 1 + radius)).select("x", "y")
    found = near.mapInArrow(_probes_met(fixed[:, 1:], radius), "nth long").distinct()
    kept = at.join(F.broadcast(found.select((F.col("nth") + int(fixed[0, 0] if len(fixed) else 0)).alias("probe_id"))), "probe_id", "left_semi")
    return kept.orderBy("probe_id").limit(m)


def _probes_met(at: np.ndarray, radius: float):
    """Positions of the probes that have a row within radius. Rows are taken by cells as wide as the radius and only compared with
    probes of neighbouring cells that have met none so far."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        waiting, home = np.ones(len(at), bool), np.floor(at / radius).astype(np.int64)
        for b in batches:
            xy = np.column_stack((b.column(0).to_numpy(), b.column(1).to_numpy()))
            if not len(xy):
                continue
            cells, inside = np.unique(np.floor(xy / radius).astype(np.int64), axis=0, return_inverse=True)
            order = np.argsort(inside, kind="stable")
            for cell, rows in zip(cells, np.split(order, np.cumsum(np.bincount(inside.ravel()))[:-1])):
                for low in range(0, len(rows), 1024):
                    who = np.flatnonzero(waiting & (np.abs(home - cell).max(axis=1) <= 1))
                    if not len(who):
                        break
                    d = at[who, None, :] - xy[None, rows[low : low + 1024], :]
                    waiting[who[(d[..., 0] * d[..., 0] + d[..., 1] * d[..., 1] <= radius * radius).any(axis=1)]] = False
        yield pa.RecordBatch.from_arrays([pa.array(np.flatnonzero(~waiting))], ["nth"])

    return run


#: Kernels that are exponentials of a distance: the exponent, by squared distance.
EXPONENTS = {"gaussian": lambda d2, e: -d2 / (e * e), "pair": lambda d2, e: -d2 / (2 * e * e), "laplacian": lambda d2, e: -np.sqrt(d2) / e}


def fixed_places(at: DataFrame) -> tuple[np.ndarray, DataFrame]:
    """Places (probe_id, px, py) as an array, and (probe, probe_id): their number is a parameter, so they may come to the driver."""
    rows = at.orderBy("probe_id").collect()
    names = at.sparkSession.createDataFrame([(n, r["probe_id"]) for n, r in enumerate(rows)], "probe long, probe_id long")
    return np.array([(r["px"], r["py"]) for r in rows], float).reshape(-1, 2), names


def point_loss(at: DataFrame, rows: DataFrame, eps: float, kernel: str = "gaussian") -> DataFrame:
    """(probe_id, log10_loss): the inverse of the kernel mass that rows, a sample or all of them, put at each probe, as a logarithm: masses
    are added in log space, since far places have masses below the smallest double."""
    places, names = fixed_places(at)
    return log_mass(places, rows, eps, kernel).join(F.broadcast(names), "probe").select("probe_id", (-(F.col("top") + F.ln("s")) / LN10).alias("log10_loss"))


def log_mass(at: np.ndarray, rows: DataFrame, eps: float, kernel: str = "gaussian") -> DataFrame:
    """(probe, top, s): kernel mass of any number of rows at a bounded set of probes, as exp(top) * s. One pass over rows; each
    task returns one row per probe, and pairs of rows and probes are never made."""
    if kernel not in EXPONENTS:
        raise ValueError("the log form needs an exponential kernel")
    exponent = EXPONENTS[kernel]

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        top, s = np.full(len(at), -np.inf), np.zeros(len(at))
        step = max(16, (1 << 16) // max(1, len(at)))
        for b in batches:
            x, y = b.column(0).to_numpy(), b.column(1).to_numpy()
            for low in range(0, len(x), step):
                dx, dy = at[:, :1] - x[low : low + step], at[:, 1:] - y[low : low + step]
                a = exponent(dx * dx + dy * dy, eps)
                new = np.maximum(top, a.max(axis=1))
                s = s * np.exp(np.where(np.isinf(top), -np.inf, top - new)) + np.exp(a - new[:, None]).sum(axis=1)
                top = new
        seen = np.flatnonzero(s > 0)
        yield pa.RecordBatch.from_arrays([pa.array(seen), pa.array(top[seen]), pa.array(s[seen])], ["probe", "top", "s"])

    parts = rows.select("x", "y").mapInArrow(scan, "probe long, top double, s double")
    best = Window.partitionBy("probe")
    return parts.withColumn("best", F.max("top").over(best)).groupBy("probe", "best").agg(F.sum(F.col("s") * F.exp(F.col("top") - F.col("best"))).alias("s")).select("probe", F.col("best").alias("top"), "s")


def mass(at: DataFrame, rows: DataFrame, eps: float, kernel: str = "gaussian") -> DataFrame:
    """(probe, u, own): kernel mass at each place of a bounded set, and the sum of its squared parts; one pass over rows, and a task returns
    one row per place."""
    places, _ = fixed_places(at)

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        u, own, step = np.zeros(len(places)), np.zeros(len(places)), max(16, (1 << 16) // max(1, len(places)))
        for b in batches:
            x, y = b.column(0).to_numpy(), b.column(1).to_numpy()
            for low in range(0, len(x), step):
                dx, dy = places[:, :1] - x[low : low + step], places[:, 1:] - y[low : low + step]
                k = kernels.values(kernel, dx * dx + dy * dy, eps)
                u, own = u + k.sum(axis=1), own + (k * k).sum(axis=1)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(places))), pa.array(u), pa.array(own)], ["probe", "u", "own"])

    return rows.select("x", "y").mapInArrow(scan, "probe long, u double, own double").groupBy("probe").agg(F.sum("u").alias("u"), F.sum("own").alias("own"))


def average_loss(losses: DataFrame, stat: str = "median") -> DataFrame:
    """(log10_loss): the median of point losses, or their mean, added in log space."""
    if stat == "median":
        return losses.agg(F.median("log10_loss").alias("log10_loss"))
    top = losses.agg(F.max("log10_loss").alias("top"))
    return losses.crossJoin(F.broadcast(top)).groupBy("top").agg(F.avg(F.pow(F.lit(10.0), F.col("log10_loss") - F.col("top"))).alias("m")).select((F.col("top") + F.log10("m")).alias("log10_loss"))


def log_ratio(points: DataFrame, sample: DataFrame, at: DataFrame, eps: float, stat: str = "median") -> DataFrame:
    """(log_ratio): log10 of the sample's loss over the loss of all rows at the same probes; 0 is best."""
    one, all_rows = average_loss(point_loss(at, sample, eps), stat), average_loss(point_loss(at, points, eps), stat).withColumnRenamed("log10_loss", "base")
    return one.crossJoin(all_rows).select((F.col("log10_loss") - F.col("base")).alias("log_ratio"))


def grid(spark: SparkSession, g: int) -> DataFrame:
    """(probe_id, px, py): the centres of a g x g grid over the unit box."""
    return spark.range(g * g).select(F.col("id").alias("probe_id"), ((F.floor(F.col("id") / g) + 0.5) / g).alias("px"), ((F.col("id") % g + 0.5) / g).alias("py"))


def integral_loss(at: DataFrame, sample: DataFrame, eps: float, floor: float = 1e-12) -> DataFrame:
    """(loss): the mean over a grid of 1 / max(mass, floor), the integral over the unit box."""
    return mass(at, sample, eps).agg(F.avg(1 / F.greatest("u", F.lit(floor))).alias("loss"))


def surrogate(at: DataFrame, sample: DataFrame, eps: float) -> DataFrame:
    """(second_order, reduced, pair_sum): means over the grid of the expansion about mass 1 and of its rewritten forms; the last is what the
    squares of the mass add up to in pairs."""
    u = F.col("u")
    return mass(at, sample, eps).agg(F.avg((u - 1) * (u - 1) - (u - 1) + 1).alias("second_order"), F.avg(u * u - 3 * u).alias("reduced"), F.avg((u * u - F.col("own")) / 2).alias("pair_sum"))


def average_ranks(df: DataFrame, column: str, durable=None) -> DataFrame:
    """(value, n, rank): each distinct value of a column, how often it occurs, and the average rank of its rows. Values are counted, then
    numbered range by range, and a range starts after the counts of the ranges below: no task sorts the whole column."""
    keep = durable or (lambda x: x.checkpoint())
    counted = df.groupBy(F.col(column).alias("value")).agg(F.count("*").alias("n"))
    ranged = keep(counted.repartitionByRange("value").withColumn("range", F.spark_partition_id()))
    sizes = ranged.groupBy("range").agg(F.sum("n").alias("size"))
    below = sizes.select("range", (F.sum("size").over(Window.orderBy("range")) - F.col("size")).alias("below"))  # a row per range
    upto = F.sum("n").over(Window.partitionBy("range").orderBy("value"))
    return ranged.join(F.broadcast(below), "range").select("value", "n", (F.col("below") + upto - (F.col("n") - 1) / 2).alias("rank"))


def spearman(df: DataFrame, a: str, b: str, durable=None) -> DataFrame:
    """(rho, t, n): rank correlation with average ranks at ties, and the t statistic with n - 2 degrees of freedom. Equal pairs of values are
    one row with a count, which meets the ranks of its two values."""
    pairs = df.groupBy(F.col(a).alias("a"), F.col(b).alias("b")).agg(F.count("*").alias("c"))
    rank = lambda c: average_ranks(df, c, durable).select("value", "rank")
    met = pairs.join(rank(a).toDF("a", "x"), "a").join(rank(b).toDF("b", "y"), "b")
    w = lambda e: F.sum(F.col("c") * e)
    n, sxx, syy, sxy = (F.col(c) for c in ("n", "sxx", "syy", "sxy"))
    mid = df.agg(((F.count("*") + 1) / 2).alias("mid"))  # ranks are taken from their mean, which they all share
    x, y = F.col("x") - F.col("mid"), F.col("y") - F.col("mid")
    sums = met.join(F.broadcast(mid)).agg(F.sum("c").alias("n"), w(x * x).alias("sxx"), w(y * y).alias("syy"), w(x * y).alias("sxy"))
    out = sums.select((sxy / F.sqrt(sxx * syy)).alias("rho"), "n")
    return out.select("rho", (F.col("rho") * F.sqrt((n - 2) / (1 - F.col("rho") * F.col("rho")))).alias("t"), "n")


def t_tail(t: float, dof: int, steps: int = 20_000) -> float:
    """Two-sided p-value of Student's t by quadrature of its density."""
    from math import lgamma, pi

    x = (np.arange(steps) + 0.5) * abs(t) / steps
    c = np.exp(lgamma((dof + 1) / 2) - lgamma(dof / 2)) / np.sqrt(dof * pi)
    return float(max(0.0, 1 - 2 * (c * (1 + x * x / dof) ** (-(dof + 1) / 2)).sum() * abs(t) / steps))
