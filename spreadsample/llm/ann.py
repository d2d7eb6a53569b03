"""Approximate nearest neighbours: hierarchical k-means tree, best-bin-first, calibrated leaf visits.

The tree is fitted on a bounded sample and every row is put into a leaf. A query walks the tree through a
priority queue of node centres and visits the leaves it pops. How many leaves each query visits is widened
until the recall of bounded calibration queries, whose true neighbours come from an exact scan of all
rows, reaches the target. Leaves larger than LEAF_BLOCK rows are split by id, so one full leaf is many tasks;
small leaves that neighbour in the tree are compared in one task, which returns k rows a query.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from spreadsample.llm.common import durable
from spreadsample.llm.vectors import by_share, dimension, matrix, usable

FIT_SAMPLE, CALIBRATION, TARGET = 20_000, 96, 0.97
#: ASKED: questions that a bundle's rows meet in one task, about.
BRANCHES, LEAF_ROWS, LEAF_BLOCK, BUNDLE, ASKED = 8, 256, 4096, 16384, 32768


@dataclass
class Tree:
    """Node 0 is the root; children[v] is empty for a leaf, and leaf_of[v] numbers the leaves."""

    centres: list[np.ndarray] = field(default_factory=list)
    children: list[list[int]] = field(default_factory=list)
    leaf_of: dict[int, int] = field(default_factory=dict)

    def grow(self, points: np.ndarray, leaf_points: int, branches: int, rng: np.random.Generator) -> int:
        node = len(self.centres)
        self.centres.append(points.mean(axis=0))
        self.children.append([])
        parts = split(points, branches, rng) if len(points) > leaf_points else []
        if len(parts) < 2:
            self.leaf_of[node] = len(self.leaf_of)
        else:
            self.children[node] = [self.grow(p, leaf_points, branches, rng) for p in parts]
        return node

    def assign(self, points: np.ndarray) -> np.ndarray:
        """The leaf of each point, by the nearest centre at every level."""
        out, todo = np.zeros(len(points), np.int32), [(0, np.arange(len(points)))]
        while todo:
            node, rows = todo.pop()
            if node in self.leaf_of:
                out[rows] = self.leaf_of[node]
            elif len(rows):
                kids = self.children[node]
                nearest = squared(points[rows], np.stack([self.centres[k] for k in kids])).argmin(axis=1)
                todo += [(k, rows[nearest == i]) for i, k in enumerate(kids)]
        return out

    def visits(self, point: np.ndarray) -> Iterator[int]:
        """Leaves in the order in which best-bin-first reaches them."""
        queue = [(0.0, 0)]
        while queue:
            _, node = heapq.heappop(queue)
            if node in self.leaf_of:
                yield self.leaf_of[node]
            else:
                kids = self.children[node]
                for d, k in zip(squared(point[None, :], np.stack([self.centres[k] for k in kids]))[0], kids):
                    heapq.heappush(queue, (float(d), k))


def squared(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return (a * a).sum(1)[:, None] + (b * b).sum(1)[None, :] - 2 * a @ b.T


def split(points: np.ndarray, k: int, rng: np.random.Generator, rounds: int = 8) -> list[np.ndarray]:
    """k-means parts of points, empty ones left out."""
    centres = points[rng.choice(len(points), min(k, len(points)), replace=False)]
    for _ in range(rounds):
        of = squared(points, centres).argmin(axis=1)
        centres = np.stack([points[of == i].mean(axis=0) for i in np.unique(of)])
    of = squared(points, centres).argmin(axis=1)
    return [points[of == i] for i in np.unique(of)]


def nearest_in_block(queries: np.ndarray, query_ids: np.ndarray, rows: np.ndarray, ids: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query index, id, distance) of each query's k nearest rows other than its own id, ties to smaller
    ids. A product bounds the distances; those near the k-th are computed from differences in double precision."""
    out: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    by_id = np.argsort(ids, kind="stable")
    rows, ids = rows[by_id], ids[by_id]
    for low in range(0, len(queries), 64):
        q, own = queries[low : low + 64], query_ids[low : low + 64]
        rough = squared(q, rows)
        rough[own[:, None] == ids[None, :]] = np.inf
        near = np.partition(rough, min(k, len(ids)) - 1, axis=1)[:, min(k, len(ids)) - 1]
        slack = 1e-9 * ((q * q).sum(1) + (rows * rows).sum(1).max())
        for i in range(len(q)):
            some = np.flatnonzero((rough[i] <= near[i] + slack[i]) & np.isfinite(rough[i]))
            exact = np.sqrt(((rows[some] - q[i]) ** 2).sum(axis=1))
            best = np.argsort(exact, kind="stable")[:k]
            out.append((np.full(len(best), low + i), ids[some][best], exact[best]))
    return tuple(np.concatenate(x) for x in zip(*out)) if out else (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))


def _top(scored: DataFrame, k: int) -> DataFrame:
    order = Window.partitionBy("query_id").orderBy("score", "vec_id")
    return scored.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


def search(vectors: DataFrame, is_query: Column, k: int = 10, target: float = TARGET, fit_sample: int = FIT_SAMPLE, calibration: int = CALIBRATION, leaf_rows: int = LEAF_ROWS, leaf_block: int = LEAF_BLOCK, bundle_rows: int = BUNDLE, seed: int = 7) -> DataFrame:
    """(query_id, rank, vec_id, score): for each row of vectors (vec_id, embedding) with is_query, the k
    nearest other ids found, by Euclidean distance in double precision, ties to the smaller id.

    Null ids, null or zero vectors and null or non-finite components take no part, as query or candidate. Distances are between vectors of
    one length: those of the commonest go through the tree, the others, of each length, are compared in blocks. Rows that repeat a query's id are its own and no candidates for it; other repeated rows are kept. With
    fewer than k candidates all are returned; with none, or no queries, no rows.

    The fit sample, the calibration queries and the number of leaves (at most fit_sample) are bounded, so the tree and its
    leaf counts are small whatever the table holds."""
    schema = "query_id long, rank int, vec_id long, score double"
    spark = vectors.sparkSession
    rows = vectors.select(F.col("vec_id").cast("long"), "embedding", F.coalesce(is_query, F.lit(False)).alias("asked")).where(F.col("vec_id").isNotNull() & usable(F.col("embedding")))
    d = dimension(rows, "embedding")
    rest = _in_blocks(rows.where(F.size("embedding") != d), k, leaf_block).select("query_id", F.col("rank").cast("int"), "vec_id", "score")
    rows = rows.where(F.size("embedding") == d)
    total, asked = rows.agg(F.count("*"), F.count_if("asked")).first()
    if not asked:
        return rest if total else spark.createDataFrame([], schema)
    sample = np.array([r[0] for r in by_share(rows, F.col("vec_id"), fit_sample, total).orderBy(F.xxhash64("vec_id", F.lit(seed)), "vec_id").select("embedding").collect()] or [rows.first()["embedding"]], np.float64)
    tree = Tree()
    tree.grow(sample, max(BRANCHES, round(leaf_rows * len(sample) / total)), BRANCHES, np.random.default_rng(seed))

    def put(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                yield pa.RecordBatch.from_arrays([*b.columns, pa.array(tree.assign(matrix(b.column(1))))], ["vec_id", "embedding", "asked", "leaf"])

    kind = dict(rows.dtypes)["embedding"]
    placed = durable(rows.mapInArrow(put, f"vec_id long, embedding {kind}, asked boolean, leaf int"))
    counts = np.zeros(len(tree.leaf_of), np.int64)
    for leaf, n in placed.groupBy("leaf").count().collect():  # at most as many rows as the tree has leaves
        counts[leaf] = n
    visits = _calibrated(placed, tree, counts, k, target, calibration, asked)
    blocks = np.maximum(1, -(-counts // leaf_block))
    # units (a leaf's blocks, leaf by leaf) are gathered into bundles of about BUNDLE rows: neighbours in the tree share a task
    first_unit = np.cumsum(blocks) - blocks
    unit_rows = np.repeat(counts / blocks, blocks)
    bundle_of = ((np.cumsum(unit_rows) - unit_rows) // bundle_rows).astype(np.int64)

    def ask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            at, bundles, leaves = [], [], []
            for i, q in enumerate(matrix(b.column(1))):
                seen = held = 0
                wanted: dict[int, list[int]] = {}
                for leaf in tree.visits(q):
                    if seen >= visits and held > k:
                        break
                    seen, held = seen + 1, held + counts[leaf]
                    for bundle in set(bundle_of[first_unit[leaf] : first_unit[leaf] + blocks[leaf]].tolist()):
                        wanted.setdefault(bundle, []).append(leaf)
                for bundle, some in wanted.items():
                    at.append(i)
                    bundles.append(bundle)
                    leaves.append(some)
            for low in range(0, len(at), 20_000):
                part = slice(low, low + 20_000)
                picked = b.take(pa.array(at[part], pa.int64()))
                yield pa.RecordBatch.from_arrays([picked.column(0), picked.column(1), pa.array(bundles[part], pa.int64()), pa.array(leaves[part], pa.list_(pa.int32()))], ["query_id", "q", "bundle", "leaves"])

    def compare(asked: pa.Table, held: pa.Table) -> pa.Table:
        """Each query's k best in the bundle, from the leaves that it visits there."""
        found: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = [(np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))]
        if asked.num_rows and held.num_rows:
            ids, q = asked.column("query_id").to_numpy(), matrix(asked.column("q"))
            rows, row_ids, leaf = matrix(held.column("embedding")), held.column("vec_id").to_numpy(), held.column("leaf").to_numpy()
            lists = asked.column("leaves").combine_chunks()
            asker, asked_leaf = np.repeat(np.arange(len(ids)), np.diff(lists.offsets.to_numpy())), lists.flatten().to_numpy()
            for v in np.unique(leaf):
                who, some = asker[asked_leaf == v], leaf == v
                if len(who):
                    i, near, score = nearest_in_block(q[who], ids[who], rows[some], row_ids[some], k)
                    found.append((ids[who[i]], near, score))
        query, near, score = (np.concatenate(x) for x in zip(*found))
        order = np.lexsort((near, score, query))
        query, near, score = query[order], near[order], score[order]
        starts = np.flatnonzero(np.diff(query, prepend=-1 if not len(query) else query[0] - 1))
        nth = np.arange(len(query)) - np.repeat(starts, np.diff(starts, append=len(query)))
        best = nth < k
        return pa.table({"query_id": query[best], "vec_id": near[best], "score": score[best]})

    layout = spark.createDataFrame([(int(leaf), int(u - first_unit[leaf]), int(bundle_of[u])) for leaf in range(len(blocks)) for u in range(first_unit[leaf], first_unit[leaf] + blocks[leaf])], "leaf int, block long, bundle long")
    parts = spark.createDataFrame([(i, int(x)) for i, x in enumerate(blocks)], "leaf int, blocks long")
    # questions of a bundle are many tasks where they are many; its rows go to each of them
    salts = max(1, round(asked * visits / max(1, bundle_of.max() + 1) / ASKED))
    held = placed.join(F.broadcast(parts), "leaf").withColumn("block", F.pmod(F.xxhash64("vec_id", F.lit(1)), F.col("blocks"))).join(layout, ["leaf", "block"]).select("vec_id", "embedding", "leaf", "bundle", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))).alias("salt"))
    queries = placed.where("asked").select("vec_id", "embedding").mapInArrow(ask, f"query_id long, q {kind}, bundle long, leaves array<int>").withColumn("salt", F.pmod(F.xxhash64("query_id", F.lit(2)), F.lit(salts)).cast("int"))
    scored = queries.groupBy("bundle", "salt").cogroup(held.groupBy("bundle", "salt")).applyInArrow(compare, "query_id long, vec_id long, score double")
    return _top(scored, k).select("query_id", F.col("rank").cast("int"), "vec_id", "score").union(rest)


def _in_blocks(rows: DataFrame, k: int, block: int) -> DataFrame:
    """The k nearest of each query among rows of its own length, by blocks of rows that every query of that length visits. For the lengths beside
    the commonest one."""
    sized = rows.withColumn("d", F.size("embedding"))
    parts = sized.groupBy("d").agg(F.ceil(F.count("*") / block).cast("long").alias("parts"))
    held = sized.join(parts, "d").withColumn("part", F.pmod(F.xxhash64("vec_id", F.lit(1)), F.col("parts"))).select("vec_id", "embedding", "d", "part")
    queries = sized.where("asked").join(parts, "d").select(F.col("vec_id").alias("query_id"), F.col("embedding").alias("q"), F.col("d").alias("of_length"), F.explode(F.sequence(F.lit(0).cast("long"), F.col("parts") - 1)).alias("block"))

    def compare(asked: pa.Table, held: pa.Table) -> pa.Table:
        if not asked.num_rows or not held.num_rows:
            return pa.table({"query_id": pa.array([], pa.int64()), "vec_id": pa.array([], pa.int64()), "score": pa.array([], pa.float64())})
        ids = asked.column("query_id").to_numpy()
        i, near, score = nearest_in_block(matrix(asked.column("q")), ids, matrix(held.column("embedding")), held.column("vec_id").to_numpy(), k)
        return pa.table({"query_id": ids[i], "vec_id": near, "score": score})

    return _top(queries.groupBy("of_length", "block").cogroup(held.groupBy("d", "part")).applyInArrow(compare, "query_id long, vec_id long, score double"), k)


def exact_neighbours(rows: DataFrame, queries: np.ndarray, ids: np.ndarray, k: int) -> DataFrame:
    """The k nearest rows of a bounded set of queries, by a scan of all rows (vec_id, embedding, leaf)."""
    shared = rows.sparkSession.sparkContext.broadcast((queries, ids))

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        q, own = shared.value
        for b in batches:
            for low in range(0, b.num_rows, 4096):
                part = b.slice(low, 4096)
                held = part.column(0).to_numpy()
                i, found, score = nearest_in_block(q, own, matrix(part.column(1)), held, k)
                leaf = dict(zip(held.tolist(), part.column(2).to_pylist()))
                yield pa.RecordBatch.from_arrays([pa.array(own[i]), pa.array(found), pa.array(score), pa.array([leaf[x] for x in found.tolist()], pa.int32())], ["query_id", "vec_id", "score", "leaf"])

    return _top(rows.select("vec_id", "embedding", "leaf").mapInArrow(scan, "query_id long, vec_id long, score double, leaf int"), k)


def _calibrated(placed: DataFrame, tree: Tree, counts: np.ndarray, k: int, target: float, calibration: int, asked: int) -> int:
    """Leaves to visit: widened until the calibration queries' mean recall reaches the target."""
    some = by_share(placed.where("asked"), F.col("vec_id"), calibration, asked).select("vec_id", "embedding").collect() or placed.where("asked").select("vec_id", "embedding").limit(1).collect()
    queries, ids = np.array([r[1] for r in some], np.float64), np.array([r[0] for r in some], np.int64)
    wanted: dict[int, list[int]] = {}
    for query_id, leaf in exact_neighbours(placed, queries, ids, k).select("query_id", "leaf").collect():  # calibration * k rows
        wanted.setdefault(query_id, []).append(leaf)
    position = [{leaf: n for n, leaf in enumerate(tree.visits(q))} for q in queries]
    depths = [np.array([position[i][leaf] for leaf in wanted[ids[i]]]) for i in range(len(ids)) if ids[i] in wanted]
    visits = 1
    while visits < len(counts) and depths and np.mean([(x < visits).mean() for x in depths]) < target:
        visits = min(len(counts), max(visits + 1, visits * 5 // 4))
    return visits
