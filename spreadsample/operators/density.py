"""Density weights: how many rows each member of a sample stands for (those that have it as the nearest member)."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spreadsample.functions import kernels

#: Members that travel to every task (24 bytes each); beyond, members and rows meet by cell.
MOST_BROADCAST = 1_000_000
#: Rows that a task looks up at once; members that the cells of a level of its quadtree hold at most as they are quartered, and those quartered at once.
LOOKED_UP, LEVEL_MEMBERS, QUARTERED = 1 << 17, 1 << 21, 1 << 17


def by_scan(sample: DataFrame, points: DataFrame) -> DataFrame:
    """(id, density) by comparing every row with every member; ties to the smallest id. The members are one array in every task, so
    a row gives its nearest member where it is read, and only counts are shuffled. For samples of a few thousand members."""
    return _attach(sample, nearest_counts(sample, points, "density"))


def nearest_counts(sample: DataFrame, points: DataFrame, name: str) -> DataFrame:
    """(id, <name>): rows of points, a table or a stream, by nearest member; members without rows are left out."""
    s = sample.select(F.col("id").alias("s_id"), F.col("x").alias("sx"), F.col("y").alias("sy"))
    members = s.agg(F.collect_list(F.struct("sx", "sy", "s_id")).alias("members")).where(F.size("members") > 0)
    far = lambda m: (F.col("x") - m["sx"]) * (F.col("x") - m["sx"]) + (F.col("y") - m["sy"]) * (F.col("y") - m["sy"])
    nearest = F.array_min(F.transform("members", lambda m: F.struct(far(m).alias("d2"), m["s_id"].alias("s_id"))))
    return points.select("x", "y").crossJoin(F.broadcast(members)).groupBy(nearest["s_id"].alias("id")).agg(F.count("*").alias(name))


def _attach(sample: DataFrame, counts: DataFrame) -> DataFrame:
    return sample.select("id").join(counts, "id", "left").select("id", F.coalesce("density", F.lit(0)).cast("long").alias("density"))


class GridIndex:
    """Nearest member by rings of grid cells around a row, for all rows of a batch at once, until no nearer member can follow."""

    def __init__(self, x: np.ndarray, y: np.ndarray):
        self.x, self.y = x, y
        self.low = x.min(), y.min()
        extent = max(x.max() - x.min(), y.max() - y.min(), 1e-300)
        self.side = max(1, int(np.sqrt(len(x))))
        self.width = extent / self.side
        keys = self._key(*self._cell(x, y))
        self.order = np.argsort(keys, kind="stable")
        self.keys = keys[self.order]

    def _cell(self, x, y):
        return tuple(np.clip(np.floor((v - low) / self.width), -1, self.side + 1).astype(np.int64) for v, low in zip((x, y), self.low))

    def _key(self, cx, cy):
        return (cx + 2 * self.side + 4) * (8 * self.side + 16) + cy + 2 * self.side + 4

    def nearest(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        best, at = np.full(len(x), np.inf), np.full(len(x), len(self.x), np.int64)
        cx, cy = self._cell(x, y)
        todo = np.arange(len(x))
        for ring in range(self.side + 3):  # rings reach every cell from any place
            for a, b in [(a, b) for a in range(-ring, ring + 1) for b in (range(-ring, ring + 1) if abs(a) == ring else sorted({-ring, ring}))]:
                key = self._key(cx[todo] + a, cy[todo] + b)
                lo, hi = self.keys.searchsorted(key), self.keys.searchsorted(key, "right")
                for some in np.array_split(np.arange(len(todo)), -(-int((hi - lo).sum()) // (1 << 20)) or 1):
                    size = hi[some] - lo[some]
                    row = np.repeat(todo[some], size)
                    who = self.order[np.repeat(lo[some] - np.cumsum(size) + size, size) + np.arange(size.sum())]
                    d2 = (x[row] - self.x[who]) ** 2 + (y[row] - self.y[who]) ** 2
                    before = best[row]
                    np.minimum.at(best, row, d2)
                    at[row[best[row] < before]] = len(self.x)
                    win = d2 == best[row]
                    np.minimum.at(at, row[win], who[win])
            todo = todo[best[todo] >= (ring * self.width) ** 2]
            if not len(todo):
                break
        return at


class TreeIndex:
    """Nearest member by a k-d tree, built once: alternate halves down to small leaves, descended for many rows at once."""

    def __init__(self, x: np.ndarray, y: np.ndarray, leaf: int = 32):
        self.p, self.leaf = np.column_stack((x, y)), leaf
        self.nodes: list[tuple] = []
        self._grow(np.arange(len(self.p)), 0)

    def _grow(self, members: np.ndarray, axis: int) -> int:
        """Adds the node of some members: (members,) for a leaf, else (axis, cut, left, right)."""
        node = len(self.nodes)
        self.nodes.append((members,))
        if len(members) > self.leaf:
            half = len(members) // 2
            order = members[np.argpartition(self.p[members, axis], half)]
            cut = self.p[order[half], axis]
            self.nodes[node] = axis, cut, self._grow(order[:half], 1 - axis), self._grow(order[half:], 1 - axis)
        return node

    def nearest(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        q = np.column_stack((x, y))
        best, at = np.full(len(q), np.inf), np.full(len(q), len(self.p), np.int64)
        self._down(0, np.arange(len(q)), q, best, at)
        return at

    def _down(self, node, rows, q, best, at) -> None:
        if not len(rows):
            return
        if len(self.nodes[node]) == 1:
            (members,) = self.nodes[node]
            for lo in range(0, len(rows), 4096):
                r = rows[lo : lo + 4096]
                d2 = ((q[r, None, :] - self.p[None, members, :]) ** 2).sum(2)
                least = d2.min(axis=1)
                who = np.where(d2 == least[:, None], members[None, :], len(self.p)).min(axis=1)
                win = (least < best[r]) | (least == best[r]) & (who < at[r])
                best[r[win]], at[r[win]] = least[win], who[win]
            return
        axis, cut, low, high = self.nodes[node]
        left = q[rows, axis] < cut
        for first, near, far in ((left, low, high), (~left, high, low)):
            mine = rows[first]
            self._down(near, mine, q, best, at)
            self._down(far, mine[(q[mine, axis] - cut) ** 2 <= best[mine]], q, best, at)


class QuadIndex:
    """Nearest member by cells that know theirs: a cell holds the members that are nearest to some place in it, and is quartered while they are
    many. A row is compared with those of its cell only. Of members at one place the first stands for all; rows far outside go by a tree.

    A level quarters cells up to LEVEL_MEMBERS, those nearest to a member first, since rows are many where members are: the index stays
    small in any task, and a cell that is not quartered only holds more members to compare."""

    def __init__(self, x: np.ndarray, y: np.ndarray, most: int = 8, deepest: int = 12):
        order = np.lexsort((np.arange(len(x)), y, x))
        new = np.concatenate(([True], (np.diff(x[order]) != 0) | (np.diff(y[order]) != 0)))
        self.first = np.sort(order[new])
        self.x, self.y = x[self.first], y[self.first]
        self.far = None
        half = max(np.ptp(self.x), np.ptp(self.y), 1e-150)
        self.middle, self.half = (float((self.x.min() + self.x.max()) / 2), float((self.y.min() + self.y.max()) / 2)), half
        cx, cy = (np.array([v]) for v in self.middle)
        # cells of one level: centres, and their members as runs of who; cell numbers go on from level to level
        start, who, near = np.array([0, len(self.x)]), np.arange(len(self.x), dtype=np.int32), np.zeros(1)
        centres, child, runs, n_cells, held = [(cx, cy)], [], [], 1, []
        for depth in range(deepest + 1):
            size = np.diff(start)
            split = (size > most) & (depth < deepest)
            if 4 * size[split].sum() > LEVEL_MEMBERS:
                first = np.argsort(near, kind="stable")
                first = first[split[first]]
                split[first[4 * np.cumsum(size[first]) > LEVEL_MEMBERS]] = False
            kids = np.full((len(size), 4), -1, np.int32)
            kids[split] = n_cells + np.arange(4 * split.sum()).reshape(-1, 4)
            child.append(kids)
            runs.append(np.where(split, 0, size))
            held.append(who[np.repeat(~split, size)])
            if not split.any():
                break
            half /= 2
            side = np.array([-half, half])
            cx, cy = (centres[-1][0][split][:, None] + side[[0, 0, 1, 1]]).ravel(), (centres[-1][1][split][:, None] + side[[0, 1, 0, 1]]).ravel()
            begin, size = np.repeat(start[:-1][split], 4), np.repeat(size[split], 4)
            kept, sizes, ends, near = [], np.zeros(len(size), np.int64), np.cumsum(size), np.zeros(len(size))
            cuts = np.unique(np.append(4 * np.flatnonzero(np.diff(ends[3::4] // QUARTERED, prepend=0)), [0, len(size)]))
            for part in (slice(lo, hi) for lo, hi in zip(cuts, cuts[1:])):
                ran, many = np.cumsum(size[part]), size[part]
                some = who[np.repeat(begin[part] - ran + many, many) + np.arange(ran[-1])]
                cell = np.repeat(np.arange(len(many)), many)
                dx, dy, wide = np.abs(self.x[some] - cx[part][cell]), np.abs(self.y[some] - cy[part][cell]), half * (1 + 1e-9)
                bound = np.minimum.reduceat((dx + wide) ** 2 + (dy + wide) ** 2, ran - many)
                near[part] = bound
                stay = np.maximum(dx - wide, 0) ** 2 + np.maximum(dy - wide, 0) ** 2 <= bound[cell] * (1 + 1e-9)
                kept.append(some[stay])
                sizes[part] = np.bincount(cell[stay], minlength=len(many))
            who, start = np.concatenate(kept), np.concatenate(([0], np.cumsum(sizes)))
            centres.append((cx, cy))
            n_cells += len(cx)
        self.cx, self.cy = (np.concatenate([c[i] for c in centres]) for i in (0, 1))
        self.child, self.size, self.who = np.concatenate(child), np.concatenate(runs), np.concatenate(held)
        self.start = np.cumsum(self.size) - self.size

    def nearest(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        at = np.zeros(len(x), np.int64)
        inside = (np.abs(x - self.middle[0]) <= self.half) & (np.abs(y - self.middle[1]) <= self.half)
        if not inside.all():
            self.far = self.far or TreeIndex(self.x, self.y)
            at[~inside] = self.far.nearest(x[~inside], y[~inside])
        rows, cell = np.flatnonzero(inside), np.zeros(int(inside.sum()), np.int64)
        todo = np.arange(len(rows))
        while len(todo := todo[self.child[cell[todo], 0] >= 0]):
            c, r = cell[todo], rows[todo]
            cell[todo] = self.child[c, 2 * (x[r] >= self.cx[c]) + (y[r] >= self.cy[c])]
        # from here on, rows whose cell has an n-th member
        best, who, todo, nth = np.full(len(rows), np.inf), np.zeros(len(rows), np.int64), np.arange(len(rows)), 0
        while len(todo):
            m = self.who[self.start[cell[todo]] + nth]
            d2 = (x[rows[todo]] - self.x[m]) ** 2 + (y[rows[todo]] - self.y[m]) ** 2
            less = d2 < best[todo]
            best[todo[less]], who[todo[less]] = d2[less], m[less]
            nth += 1
            todo = todo[self.size[cell[todo]] > nth]
        at[rows] = who
        return self.first[at]


INDEXES = {"grid": GridIndex, "kdtree": TreeIndex, "quadtree": QuadIndex}


def by_index(sample: DataFrame, points: DataFrame, how: str = "kdtree") -> DataFrame:
    """(id, density): one scan of points; members, by ascending id, travel with the tasks, which return a count per member."""
    return by_indexes([sample], points, how)[0]


def by_indexes(samples: list[DataFrame], points: DataFrame, how: str = "quadtree", durable=lambda df: df) -> list[DataFrame]:
    """(id, density) for each of several samples, from one scan of points for all."""
    held = [sorted(tuple(r) for r in s.select("id", "x", "y").limit(MOST_BROADCAST + 1).collect()) for s in samples]
    if sum(len(rows) for rows in held) > MOST_BROADCAST:
        return [by_cells(s, points) for s in samples] if len(samples) == 1 else [by_indexes([s], points, how, durable)[0] for s in samples]
    members = [(n, [r[0] for r in rows], np.array([r[1] for r in rows]), np.array([r[2] for r in rows])) for n, rows in enumerate(held) if rows]

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found = [(INDEXES[how](x, y), np.zeros(len(ids), np.int64)) for _, ids, x, y in members]
        for x, y in _gathered(batches):
            for index, n in found:
                n += np.bincount(index.nearest(x, y), minlength=len(n))
        for (nth, ids, _, _), (_, n) in zip(members, found):
            seen = np.flatnonzero(n)
            yield pa.RecordBatch.from_arrays([pa.array([nth] * len(seen), pa.int32()), pa.array([ids[i] for i in seen], pa.string()), pa.array(n[seen])], ["nth", "id", "n"])

    parts = durable(points.select("x", "y").mapInArrow(count, "nth int, id string, n long").groupBy("nth", "id").agg(F.sum("n").alias("density")))
    return [_attach(s, parts.where(F.col("nth") == n).drop("nth")) for n, s in enumerate(samples)]


def _gathered(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Places of batches (x, y), LOOKED_UP rows together or more: an index is descended once for them."""
    some, n = [], 0
    for b in batches:
        some.append([b.column(c).to_numpy() for c in (0, 1)])
        n += b.num_rows
        if n >= LOOKED_UP:
            yield tuple(np.concatenate(c) for c in zip(*some))
            some, n = [], 0
    if n:
        yield tuple(np.concatenate(c) for c in zip(*some))


def by_cells(sample: DataFrame, points: DataFrame, width: float = 0.02, durable=None) -> DataFrame:
    """(id, density) without a broadcast: distinct places meet members in growing rings of cells; a place whose nearest member found is
    nearer than the ring reaches is done, the others go on with cells of twice the width."""
    keep = durable or (lambda df: df.checkpoint())
    left = points.groupBy("x", "y").agg(F.count("*").alias("n"))
    done, s = None, sample.select(F.col("id").alias("s_id"), F.col("x").alias("sx"), F.col("y").alias("sy"))
    if s.isEmpty():
        return _attach(sample, points.sparkSession.createDataFrame([], "id string, density long"))
    while True:
        cell = lambda c, w=width: F.floor(F.col(c) / w).cast("long")
        near = F.array(*[F.lit(d) for d in (-1, 0, 1)])
        around = s.withColumn("dx", F.explode(near)).withColumn("dy", F.explode(near)).select("s_id", "sx", "sy", (cell("sx") + F.col("dx")).alias("cx"), (cell("sy") + F.col("dy")).alias("cy"))
        met = left.withColumns({"cx": cell("x"), "cy": cell("y")}).join(around, ["cx", "cy"], "left")
        best = keep(met.groupBy("x", "y", "n").agg(F.min(F.when(F.col("s_id").isNotNull(), F.struct(kernels.squared("x", "y", "sx", "sy").alias("d2"), "s_id"))).alias("m")))
        sure = best.where(F.col("m.d2") <= width * width).select(F.col("m.s_id").alias("id"), "n")
        done = sure if done is None else done.union(sure)
        left = best.where(F.col("m").isNull() | (F.col("m.d2") > width * width)).select("x", "y", "n")
        if left.isEmpty():
            return _attach(sample, done.groupBy("id").agg(F.sum("n").alias("density")))
        width *= 2
