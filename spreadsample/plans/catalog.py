"""Stored samples: a Parquet table by (dataset, method, k) and its manifest, and SQL routed to it within a time bound."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spreadsample.functions.runtime import bounded, together
from spreadsample.operators import baselines as bl
from spreadsample.operators import density, measures
from spreadsample.operators import exchange as ex

#: Rows above which a build goes through tiles, and rows times members; rows that a tile keeps, at most, when there are enough tiles for it.
BLOCK_ROWS, BLOCK_WORK, TILE_MEMBERS = 2_000_000, 1_000_000_000, 128


def in_block(k: int, rows: int) -> bool:
    """Whether one task reads all rows in reasonable time."""
    return rows <= BLOCK_ROWS and rows * k <= BLOCK_WORK


def tiles_for(k: int, rows: int) -> int:
    return max(16, rows // BLOCK_ROWS, 2 * k // TILE_MEMBERS)


def variant_for(k: int, eps: float) -> str:
    return ex.choose_variant(k, k * 100 * eps * eps)  # members within the radius, were they even over the unit box


def spread_sample(points: DataFrame, k: int, eps: float, rows: int, durable=lambda df: df) -> DataFrame:
    """The build for any size: one exact block while a task can read it in reasonable time, else tiled. Every row is offered
    at any size, so a sample has min(k, rows) rows. Tiles read points four times; durable stores them, if they are not.

    A row of a tile meets the members of the tile alone, so more tiles are less work; most of them lie within the radius of each other, so
    no tile looks for the near ones."""
    variant = variant_for(k, eps)
    if in_block(k, rows):
        return ex.exchange(points, k, eps, variant=variant)
    return ex.exchange_tiles(durable(points.select("id", "x", "y")), k, eps, n_tiles=tiles_for(k, rows), tile_variant="add_drop", variant=variant)


def spread_samples(points: DataFrame, ks: list[int], eps: float, rows: int, durable) -> DataFrame:
    """(size, and the columns of points): the spread samples of several sizes. Sizes that go through tiles share one dealing and one reading of
    the rows; the last tasks of all sizes, and the blocks of the others, run side by side."""
    tiled = [k for k in ks if not in_block(k, rows)]
    pools = durable(ex.tile_pools(points, {k: tiles_for(k, rows) for k in tiled}, eps, side=max(4, round((rows / BLOCK_ROWS) ** 0.5)), variant="add_drop")) if tiled else None
    last = lambda k: ex.exchange(pools.where(F.col("k") == k) if k in tiled else points, k, eps, variant=variant_for(k, eps))
    made = together(*[lambda k=k: durable(last(k).select(F.lit(k).alias("size"), "id")) for k in sorted(ks, reverse=True)])
    return points.join(bounded(reduce(DataFrame.union, made).distinct(), sum(ks)), "id")


def build(spark: SparkSession, points: dict[str, DataFrame], ks: list[int], path: str, eps: float, durable, methods: tuple[str, ...] = ("uniform", "grid", "spread")) -> DataFrame:
    """Writes every (dataset, method, k) to path and returns the manifest (dataset, method, k, rows_seen, objective)."""
    manifest = []
    for dataset, p in points.items():
        rows, widest = p.count(), max(ks)
        # the first rows of a uniform or grid sample are the smaller ones
        wide = {m: durable(f(p, widest)) for m, f in {"uniform": bl.uniform, "grid": bl.balanced_grid}.items() if m in methods}
        spreads = durable(spread_samples(p, ks, eps, rows, durable)) if "spread" in methods else None
        makers = {"uniform": lambda k, w=wide: bl.uniform(w["uniform"], k), "grid": lambda k, w=wide: bl.balanced_grid(w["grid"], k), "spread": lambda k, s=spreads: s.where(F.col("size") == k)}
        keys = [(k, m) for k in ks for m in methods]
        kept = together(*[lambda k=k, m=m: durable(makers[m](k).select("id", "x", "y", "value", "category")) for k, m in keys])
        weights = density.by_indexes(kept, p, durable=durable)
        cols = [{"dataset": F.lit(dataset), "method": F.lit(m), "k": F.lit(k)} for k, m in keys]
        reduce(DataFrame.union, [s.join(w, "id").withColumns(c) for s, w, c in zip(kept, weights, cols)]).write.mode("append").partitionBy("dataset", "method", "k").parquet(path)
        objectives = together(*[lambda s=s: measures.objective_by_cells(s, eps).first()[0] for s in kept])
        manifest += [(dataset, m, k, rows, j) for (k, m), j in zip(keys, objectives)]
    return spark.createDataFrame(manifest, "dataset string, method string, k int, rows_seen long, objective double")


def routed(spark: SparkSession, text: str, view: str, path: str, dataset: str, seconds: float, slope: float, method: str = "spread") -> DataFrame:
    """Runs SQL that names `view` over the stored sample that the time bound allows; partition pruning reads only its folder."""
    stored = spark.read.parquet(path).where((F.col("dataset") == dataset) & (F.col("method") == method))
    ks = sorted(r[0] for r in stored.select("k").distinct().collect())
    fit = [k for k in ks if slope * k <= seconds] or ks[:1]
    stored.where(F.col("k") == fit[-1]).createOrReplaceTempView(view)
    return spark.sql(text)
