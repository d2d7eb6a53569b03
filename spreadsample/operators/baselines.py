"""Baseline samplers: uniform, balanced over a grid, all rows; quotas; thinning before a build."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def hashed(seed: int, id_col: str = "id") -> Column:
    return F.md5(F.concat(F.lit(f"{seed}:"), F.col(id_col).cast("string")))


def uniform(points: DataFrame, k: int, seed: int = 7) -> DataFrame:
    """The k rows of smallest hash: equal in law to a reservoir, mergeable, and the same on every run. Each task keeps k rows."""
    return points.withColumn("h", hashed(seed)).orderBy("h", "id").limit(k).drop("h")


def reservoir(points: DataFrame, k: int, seed: int = 7) -> DataFrame:
    """One reservoir per partition: every row draws a key, the k smallest stay; partitions merge by keys."""

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rng, held, keys = None, None, np.zeros(0)
        for b in batches:
            if rng is None:
                rng = np.random.default_rng([seed, b.num_rows, abs(hash(str(b.column(0)[0]))) % 2**31 if b.num_rows else 0])
            draw = rng.random(b.num_rows)
            table = pa.Table.from_batches([b])
            both = table if held is None else pa.concat_tables([held, table])
            keys = np.concatenate((keys, draw))
            best = np.sort(np.argpartition(keys, k - 1)[:k]) if len(keys) > k else np.arange(len(keys))
            held, keys = both.take(pa.array(best)), keys[best]
        if held is not None:
            yield from held.append_column("key", pa.array(keys)).combine_chunks().to_batches()

    fields = ", ".join(f"{c} {t}" for c, t in points.dtypes)
    return points.mapInArrow(keep, f"{fields}, key double").orderBy("key").limit(k).drop("key")


def bernoulli(points: DataFrame, k: int, n: int, seed: int = 7) -> DataFrame:
    """About k of n rows, each kept by its own draw: no shuffle, size only near k."""
    return points.sample(min(1.0, k / max(1, n)), seed)


def cells(points: DataFrame, g: int) -> DataFrame:
    """points with the bin (bx, by) of a g x g grid over the unit box."""
    at = lambda c: F.least(F.lit(g - 1), F.greatest(F.lit(0), F.floor(F.col(c) * g))).cast("int")
    return points.withColumns({"bx": at("x"), "by": at("y")})


def balanced_grid(points: DataFrame, k: int, g: int = 10, seed: int = 7) -> DataFrame:
    """k rows spread evenly over the non-empty bins, uniform inside a bin; what a small bin lacks the others give.

    Round-robin over the bins is the balanced allocation: rows are ranked in their bin by hash, and the k lowest (rank, bin) stay. A bin
    never gives more than k rows, so the rank window is limited before the shuffle."""
    binned = cells(points, g).withColumns({"h": hashed(seed), "bin": F.col("bx") * g + F.col("by")})
    ranked = binned.withColumn("nth", F.row_number().over(Window.partitionBy("bin").orderBy("h", "id"))).where(F.col("nth") <= k)
    return ranked.orderBy("nth", F.md5(F.col("bin").cast("string")), "bin").limit(k).drop("h", "bx", "by", "bin", "nth")


def balanced_quota(counts: DataFrame, k: int) -> DataFrame:
    """(bin, n, quota) for (bin, n): equal quotas, shortfall handed to the others (water filling over sorted counts). Quotas sum to k unless
    all rows are fewer; a remainder goes to the first bins by name."""
    by_size = Window.orderBy("n", "bin")
    every = Window.partitionBy()
    filled = counts.withColumns({"below": F.coalesce(F.sum("n").over(by_size.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)), "left": F.count("*").over(by_size.rowsBetween(0, Window.unboundedFollowing))})
    level = F.floor((F.lit(k) - F.col("below")) / F.col("left"))
    open_bin = F.col("n") > level
    filled = filled.withColumn("level", F.max(F.when(open_bin, level)).over(every))
    filled = filled.withColumn("base", F.when(F.col("level").isNull(), F.col("n")).otherwise(F.least("n", "level")))
    spare = F.lit(k) - F.sum("base").over(every)
    more = (F.col("n") > F.col("base")).cast("int")
    return filled.withColumn("extra", F.when(more == 1, (F.sum(more).over(Window.orderBy("bin")) <= spare).cast("int")).otherwise(0)).select("bin", "n", (F.col("base") + F.col("extra")).cast("long").alias("quota"))


def every_row(points: DataFrame) -> DataFrame:
    return points


def prethin(points: DataFrame, eps: float, q: int = 4, seed: int = 7) -> DataFrame:
    """(cx, cy, id, x, y, n): the row of smallest hash in each cell of width eps / q, and the cell's rows. A partial aggregate: what
    is shuffled is bounded by the cells, whatever the rows."""
    cell = lambda c: F.floor(F.col(c) / (eps / q)).cast("long")
    best = F.min(F.struct(hashed(seed).alias("h"), "id", "x", "y")).alias("best")
    return points.groupBy(cell("x").alias("cx"), cell("y").alias("cy")).agg(best, F.count("*").alias("n")).select("cx", "cy", "best.id", "best.x", "best.y", "n")
