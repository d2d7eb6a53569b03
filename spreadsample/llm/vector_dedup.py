"""Near-duplicate vectors by exact cosine: tiled comparison in the order of principal components.

Equal vectors are one class with a multiplicity. Unit vectors are turned into principal axes (a rotation, so dot products stay), and
a tile's leading components are multiplied first with the norm of the rest as one more component: by Cauchy and
Schwarz that product bounds the cosine, so pairs below the threshold go before the other dimensions are read. Survivors gain
further components and tighter bounds; the last value is the cosine itself. Blocks of classes meet pairwise, unless
the extents of their leading components already rule a link out; each pair of blocks returns link counts and a spanning
forest, at most one row per class, never the pairs.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spreadsample.llm.common import components, durable
from spreadsample.llm.simhash import merge_labels
from spreadsample.llm.vectors import by_share, matrix, usable

#: Blocks are as large as BLOCK, or larger where there would be more than MOST_BLOCKS: their pairs are laid out on the driver.
THRESHOLD, BLOCK, MOST_BLOCKS, TILE, FIT_SAMPLE, LEAD = 0.9, 8192, 4096, 1024, 4096, 16
#: Lengths of vectors that a table may mix.
LENGTHS = 4096


def principal_axes(sample: np.ndarray) -> np.ndarray:
    """Orthonormal axes as columns, by falling second moment."""
    return np.linalg.eigh(sample.T @ sample)[1][:, ::-1]


def bounded_links(a: np.ndarray, b: np.ndarray, threshold: float, lead: int = LEAD) -> tuple[np.ndarray, np.ndarray]:
    """Index pairs of unit rows of a and b, in principal order, whose product reaches the threshold."""
    d = a.shape[1]
    stages = sorted({min(lead, d), min(2 * lead, d), d})
    rest = lambda x, m: np.sqrt(np.maximum(0, 1 - (x[:, :m] ** 2).sum(1)))
    m = stages[0]
    bound = np.column_stack((a[:, :m], rest(a, m))).astype(np.float32) @ np.column_stack((b[:, :m], rest(b, m))).astype(np.float32).T
    i, j = np.nonzero(bound >= np.float32(threshold - 1e-4))
    done = np.einsum("ij,ij->i", a[i, :m], b[j, :m]) if len(i) <= a.shape[0] * 64 else None
    if done is None:  # a dense tile: all of it at once
        return tuple(x.astype(np.int64) for x in np.nonzero(a @ b.T >= threshold))
    for m, upto in zip(stages, stages[1:]):
        done += np.einsum("ij,ij->i", a[i, m:upto], b[j, m:upto])
        keep = done + rest(a, upto)[i] * rest(b, upto)[j] >= threshold - 1e-9
        i, j, done = i[keep], j[keep], done[keep]
    return i, j


def exact_links(x: np.ndarray, y: np.ndarray, i: np.ndarray, j: np.ndarray, threshold: float, step: int = 100_000) -> np.ndarray:
    """Which of the pairs reach the threshold by the cosine of the original vectors, in double precision."""
    nx, ny = np.sqrt((x * x).sum(1)), np.sqrt((y * y).sum(1))
    return np.concatenate([np.einsum("ij,ij->i", x[i[s : s + step]], y[j[s : s + step]]) / (nx[i[s : s + step]] * ny[j[s : s + step]]) >= threshold for s in range(0, len(i), step)] or [np.zeros(0, bool)])


def scaled(x: np.ndarray) -> np.ndarray:
    """Rows as they are, but for those whose squares would leave the range of doubles: these are divided by their largest component."""
    most = np.abs(x).max(axis=1, keepdims=True)
    return np.where((most > 1e140) | (most < 1e-140), x / most, x)


def _compared(threshold: float, axes: np.ndarray, tile: int):
    def run(group: pa.Table) -> pa.Table:
        one = group.column("own").to_numpy(zero_copy_only=False) == group.column("p").to_numpy(zero_copy_only=False)
        order = np.argsort(~one, kind="stable")
        cid, mult = (group.column(c).to_numpy()[order] for c in ("cid", "mult"))
        x = matrix(group.column("embedding"))[order]
        x = scaled(x)
        unit = x / np.sqrt((x * x).sum(1))[:, None]
        unit = unit @ axes if x.shape[1] == len(axes) else unit  # axes are those of the commonest length
        n_one, same = int(one.sum()), group.column("p")[0] == group.column("q")[0]
        labels, links = np.arange(len(cid)), np.zeros(len(cid), np.int64)
        for s in range(0, n_one, tile):
            for t in range(s if same else n_one, len(cid), tile):
                a, b = slice(s, min(s + tile, n_one)), slice(t, t + tile)
                i, j = bounded_links(unit[a], unit[b], threshold - 1e-9)
                if same and s == t:
                    i, j = i[i < j], j[i < j]
                if len(i):
                    keep = exact_links(x[a], x[b], i, j, threshold)
                    i, j = i[keep] + s, j[keep] + t
                    np.add.at(links, i, mult[j])
                    np.add.at(links, j, mult[i])
                    labels = merge_labels(labels, i, j)
        some = np.flatnonzero(links)
        return pa.table({"cid": cid[some], "links": links[some], "root": cid[labels[some]]})

    return run


def near_duplicates(vectors: DataFrame, threshold: float = THRESHOLD, block: int = BLOCK, tile: int = TILE) -> DataFrame:
    """(vec_id, n_links, component_id, kept) for every row of vectors (vec_id, embedding; other columns are not read).

    Two rows are linked if they have one length and the cosine of their vectors, in double precision, is at least threshold; equal rows are
    linked like any others. component_id is the smallest non-null vec_id reachable, kept tells that the row has it itself. Vectors
    that are null, zero or hold null or non-finite components link with nothing and stay alone. Vectors of several lengths are
    compared within each; principal axes are those of the commonest. An empty table gives no rows."""
    spark = vectors.sparkSession
    rows = vectors.select(F.col("vec_id").cast("long"), "embedding", usable(F.col("embedding")).alias("ok"))
    keyed = rows.where("ok").select("vec_id", "embedding", F.xxhash64("embedding").alias("h1"), F.xxhash64(F.lit(1), "embedding").alias("h2"))
    alone = rows.where("NOT ok").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    classes = durable(keyed.groupBy("embedding").agg(F.min("vec_id").alias("first_id"), F.count("*").alias("mult"), F.first("h1").alias("h1"), F.first("h2").alias("h2")).withColumns({"cid": F.monotonically_increasing_id(), "d": F.size("embedding")}))
    lengths = {r["d"]: r["count"] for r in classes.groupBy("d").count().orderBy(F.desc("count"), "d").limit(LENGTHS + 1).collect()}
    if not lengths:
        return alone.withColumn("kept", F.col("vec_id").isNotNull())
    if len(lengths) > LENGTHS:
        raise ValueError(f"vectors of over {LENGTHS} lengths")
    d, n = next(iter(lengths.items()))
    sample = scaled(np.array([r[0] for r in by_share(classes.where(F.col("d") == d), F.col("embedding"), FIT_SAMPLE, n).select("embedding").collect()] or [classes.where(F.col("d") == d).first()["embedding"]], np.float64))
    sample /= np.sqrt((sample * sample).sum(1))[:, None]
    axes = principal_axes(sample)
    size = max(min(block, max(512, -(-n // 8))), -(-n // MOST_BLOCKS))
    cuts = np.quantile(sample @ axes[:, 0], np.linspace(0, 1, -(-n // size) + 1)[1:-1]) if n > size else np.zeros(0)
    lead = min(LEAD, d)

    def turned(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            at = b.column(3).to_numpy()
            cell, ends = np.zeros(len(at), np.int64), np.zeros((len(at), lead + 1))
            if (at == d).any():
                x = scaled(matrix(b.column(1).filter(pa.array(at == d))))
                u = (x / np.sqrt((x * x).sum(1))[:, None]) @ axes[:, :lead]
                ends[at == d] = np.column_stack((u, np.sqrt(np.maximum(0, 1 - (u * u).sum(1)))))
                cell[at == d] = np.searchsorted(cuts, u[:, 0])
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(cell), pa.array(list(ends), pa.list_(pa.float64()))], ["cid", "embedding", "mult", "d", "cell", "lead"])

    kind = dict(vectors.dtypes)["embedding"]
    placed = durable(classes.select("cid", "embedding", "mult", "d").mapInArrow(turned, f"cid long, embedding {kind}, mult long, d int, cell long, lead array<double>"))
    cells = {(r[0], r[1]): r[2] for r in placed.groupBy("d", "cell").count().collect()}  # at most n / size + LENGTHS rows
    layout, base = [], 0
    for (length, cell), k in sorted(cells.items()):
        layout.append((length, cell, base, -(-k // (2 * size))))
        base += layout[-1][-1]
    layout = spark.createDataFrame(layout, "d int, cell long, base int, parts int")
    placed = placed.join(F.broadcast(layout), ["d", "cell"]).withColumn("own", (F.col("base") + F.pmod(F.xxhash64("cid"), F.col("parts").cast("long"))).cast("int"))
    extents = placed.groupBy("own").agg(F.first("d").alias("d"), *[f(F.col("lead")[i]).alias(f"{f.__name__}{i}") for i in range(lead + 1) for f in (F.min, F.max)]).collect()
    mates = spark.createDataFrame(_possible(extents, d, lead, threshold))
    dealt = placed.select("cid", "embedding", "mult", "own").join(F.broadcast(mates), "own")
    found = durable(dealt.groupBy("p", "q").applyInArrow(_compared(threshold, axes, tile), "cid long, links long, root long"))
    roots = components(found.select(F.col("cid").alias("a"), F.col("root").alias("b")))
    links = found.groupBy("cid").agg(F.sum("links").alias("links"))
    rooted = classes.drop("embedding").join(links, "cid", "left").join(roots.withColumnRenamed("node", "cid"), "cid", "left").withColumn("root", F.coalesce("root", "cid"))
    least = rooted.groupBy("root").agg(F.min("first_id").alias("component_id"))
    known = rooted.join(least, "root").select("h1", "h2", (F.coalesce("links", F.lit(0)) + F.col("mult") - 1).alias("n_links"), "component_id")
    return keyed.select("vec_id", "h1", "h2").join(known, ["h1", "h2"]).select("vec_id", "n_links", "component_id").union(alone).withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(False)))


def _possible(extents: list, d: int, lead: int, threshold: float) -> pa.Table:
    """(own, p, q) for the pairs p <= q of blocks of one length whose extents allow a link, once for either block. Extents are known for length d."""
    order = sorted(extents, key=lambda r: r["own"])
    ids, length = np.array([r["own"] for r in order], np.int32), np.array([r["d"] for r in order])
    lo, hi = (np.array([[r[f"{f}{i}"] for i in range(lead + 1)] for r in order]) for f in ("min", "max"))
    out = [np.zeros((0, 3), np.int32)]
    for k in range(len(ids)):
        bound = np.maximum.reduce([lo[k] * lo[k:], lo[k] * hi[k:], hi[k] * lo[k:], hi[k] * hi[k:]]).sum(axis=1)
        q = ids[k:][(length[k:] == length[k]) & ((length[k] != d) | (bound >= threshold - 1e-6) | (ids[k:] == ids[k]))]
        pair = np.column_stack((np.full(len(q), ids[k], np.int32), q))
        out += [np.column_stack((pair[:, 0], pair)), np.column_stack((q, pair))[q != ids[k]]]
    every = np.concatenate(out)
    return pa.table({c: every[:, i] for i, c in enumerate(("own", "p", "q"))})
