"""SimHash near-duplicates at a wide radius: bit-sliced comparison of five-word fingerprints, then exact Jaccard similarity of 4/5 or more.

Two sets of shingles of similarity 4/5 have fingerprints that differ in about 10 of 64 bits, too many for blocks of equal bits. What
meets in a tile is chosen without loss instead: the sets share at least 4/5 of the larger one, so if both are put into one order, they
have a common member among the first n - ceil(4n/5) + 1 of each, and m common members among m - 1 more. That holds for any order. A first
pass orders by hash, takes m as a tenth of the set, and keeps the texts of which so many leading members are those of other texts
too. Over those, members are ordered by how many texts have them, so that a passage common to many texts stands last and makes no
candidates of texts that differ elsewhere. Texts with a common member are compared with the first and the last of that member's
texts; what these links have not joined meets in tiles, where the bit planes of op1 leave few pairs, which are compared set by set, and a
spanning forest leaves the tile. Nothing is sampled or capped; pairs are never rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from spreadsample.llm.common import components, durable
from spreadsample.llm.simhash import FLUSH, bit_sliced_links, majority, merge_labels, shingle_hashes

WORDS = 5
#: Members of the sets held by a task before it passes them on.
HELD = FLUSH << 2
#: Bits of the filter that spares most texts a shuffle; what it lets through by chance is joined away.
BITS = 1 << 23
#: Bits in which fingerprints may differ, about six standard deviations above what similarity 4/5 gives. Sets of fewer than SMALL members, whose
#: votes are close, may differ in more: 12 of 64 are expected of four members in five.
RADIUS, SMALL, SMALL_RADIUS = 28, 32, 34
#: Texts compared together at least; texts, and members of their sets, of a part of a large bucket.
TILE, PART_TEXTS, PART_MEMBERS = 1024, 4096, 1 << 20


def _sets(width: int, leading: bool):
    """Batches (did, th, text) to (did, th, node, n, fp, hs): the set's own hash, its size and fingerprint, and its members or the leading
    ones (the fingerprint is then left out)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            low, held, nodes, sizes, lists, fps = 0, 0, [], [], [], []
            texts = batch.column(2).cast(pa.binary())
            for at in range(batch.num_rows):
                h = np.unique(np.array(shingle_hashes(texts[at].as_py() or b"", width), np.uint64))
                n = len(h)
                nodes.append(xxhash.xxh64_intdigest(h.tobytes()))
                sizes.append(n)
                fps.append(0 if leading else int(majority(h, np.array([n]))[0]))
                lists.append(h[: n - (4 * n + 4) // 5 + 1 + n // 10].copy() if leading else h)
                held += len(lists[-1])
                if held >= HELD or at == batch.num_rows - 1:
                    ends = np.concatenate(([0], np.cumsum([len(x) for x in lists]))).astype(np.int32)
                    hs = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(lists).view(np.int64)))
                    part = batch.slice(low, at + 1 - low)
                    yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(np.array(nodes, np.uint64).view(np.int64)), pa.array(sizes, pa.int64()), pa.array(np.array(fps, np.uint64).view(np.int64)), hs], ["did", "th", "node", "n", "fp", "hs"])
                    low, held, nodes, sizes, lists, fps = at + 1, 0, [], [], [], []

    return run


def _with_sets(placed: DataFrame, width: int, leading: bool) -> DataFrame:
    return placed.select("did", "th", F.col("text").cast("string")).mapInArrow(_sets(width, leading), "did long, th long, node long, n long, fp long, hs array<long>")


def _place(doc_id: str, text: str) -> list[Column]:
    """did, th: the order of rows, null ids last, rows of one id by their text."""
    return [F.coalesce(F.col(doc_id).cast("long"), F.lit(2**63 - 1)).alias("did"), F.xxhash64(F.col(text).cast("string")).alias("th")]


def _passing(one: DataFrame):
    """A filter of batches (did, th, text) that keeps every row with the th of a row of one, and few others."""
    bits = np.zeros(BITS, bool)
    at = one.select(F.pmod("th", F.lit(BITS)).cast("int").alias("at")).distinct().toArrow().column(0).to_numpy()
    bits[at] = True
    packed = np.packbits(bits)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = batch.column(1).to_numpy() & (len(packed) * 8 - 1)
            yield batch.filter(pa.array((packed[at >> 3] >> (7 - (at & 7)).astype(np.uint8) & 1).astype(bool)))

    return run


def tile_links(nodes: np.ndarray, labels: np.ndarray, fps: np.ndarray, sets: list[np.ndarray], buckets: np.ndarray | None = None, centres: np.ndarray | None = None) -> list[tuple[int, int]]:
    """Links (a node, a node) that join all texts of a tile with similarity 4/5 or more, as far as their labels do not say so already. With
    buckets and centres, only the pairs of a bucket's centre and another text of that bucket."""
    sizes = np.array([len(x) for x in sets])
    order = np.argsort(sizes, kind="stable")
    if buckets is not None:
        buckets, centres = buckets[order], centres[order]
    nodes, fps, sizes, sets = nodes[order], fps[order], sizes[order], [sets[i] for i in order]
    _, labels = np.unique(labels[order], return_inverse=True)
    known, codes = np.unique(np.concatenate(sets), return_inverse=True)  # members that one text alone has stay, they count in no pair
    starts, mark = np.concatenate(([0], np.cumsum(sizes))), np.zeros(len(known), bool)
    first = np.full(labels.max() + 1, len(nodes))
    np.minimum.at(first, labels, np.arange(len(nodes)))
    roots, out = first[labels], []

    def verify(i: int, js: np.ndarray) -> None:
        nonlocal roots
        if buckets is not None:
            js = js[(buckets[js] == buckets[i]) & (centres[js] | centres[i])]
        js = js[(roots[js] != roots[i]) & (5 * np.minimum(sizes[js], sizes[i]) >= 4 * np.maximum(sizes[js], sizes[i])) & (sizes[js] > 0)]
        if not len(js) or not sizes[i]:
            return
        mark[codes[starts[i] : starts[i + 1]]] = True
        flat = np.repeat(starts[js] - np.cumsum(sizes[js]) + sizes[js], sizes[js]) + np.arange(sizes[js].sum())
        common = np.add.reduceat(mark[codes[flat]].astype(np.int64), np.cumsum(sizes[js]) - sizes[js])
        mark[codes[starts[i] : starts[i + 1]]] = False
        near = js[9 * common >= 4 * (sizes[js] + sizes[i])]
        if len(near):
            _, at = np.unique(roots[near], return_index=True)
            out.extend((int(nodes[i]), int(nodes[j])) for j in near[at])
            roots = merge_labels(roots, np.full(len(near), i), near)

    for low, high, radius in ((0, int(np.searchsorted(sizes, SMALL * 5 // 4 + 1)), SMALL_RADIUS), (int(np.searchsorted(sizes, SMALL)), len(nodes), RADIUS)):
        for i, j in bit_sliced_links(fps[low:high], radius) if low < high else ():
            for x, js in zip(np.unique(i), np.split(j, np.flatnonzero(np.diff(i)) + 1)):
                verify(low + int(x), low + js)
    return out


def _forests(stars: bool):
    """Buckets (h, p, q, node, label, centre, fp, hs), in order, to links; small buckets share a tile. Stars: only a bucket's centre is compared
    with its texts; else all texts of a tile are."""

    def linked(held: list[pa.RecordBatch]) -> pa.RecordBatch:
        table = pa.Table.from_batches(held)
        only = {}
        if stars:
            keys = np.column_stack([table.column(c).to_numpy() for c in ("h", "p", "q")])
            only = {"buckets": np.concatenate(([0], np.cumsum((keys[1:] != keys[:-1]).any(axis=1)))), "centres": table.column("centre").to_numpy().astype(bool)}
        else:
            table = table.take(pa.array(np.unique(table.column("node").to_numpy(), return_index=True)[1]))
        hs = table.column("hs").combine_chunks()
        sets = np.split(hs.flatten().to_numpy(), hs.offsets.to_numpy()[1:-1] - hs.offsets.to_numpy()[0])
        found = tile_links(table.column("node").to_numpy(), table.column("label").to_numpy(), table.column("fp").to_numpy().view(np.uint64), sets, **only)
        return pa.RecordBatch.from_arrays([pa.array([x[i] for x in found], pa.int64()) for i in (0, 1)], ["a", "b"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        rows = members = 0
        last = None
        for batch in batches:
            keys = np.column_stack([batch.column(c).to_numpy() for c in ("h", "p", "q")])
            sizes = np.diff(batch.column("hs").offsets.to_numpy())
            cuts = [0, *(np.flatnonzero((keys[1:] != keys[:-1]).any(axis=1)) + 1).tolist(), batch.num_rows]
            for low, high in zip(cuts, cuts[1:]):
                if low == high:
                    continue
                if (rows >= TILE or members >= PART_MEMBERS) and tuple(keys[low]) != last:
                    yield linked(held)
                    held, rows, members = [], 0, 0
                held.append(batch.slice(low, high - low))
                rows, members, last = rows + high - low, members + int(sizes[low:high].sum()), tuple(keys[low])
        if held:
            yield linked(held)

    return run


def _tiled(texts: DataFrame, sets: DataFrame, stars: bool) -> DataFrame:
    """Links of buckets of texts (h, p, q, node, label, centre)."""
    tiles = texts.join(sets.select("node", "fp", "hs"), "node").select("h", "p", "q", "node", "label", "centre", "fp", "hs")
    return tiles.repartition("h", "p", "q").sortWithinPartitions("h", "p", "q").mapInArrow(_forests(stars), "a long, b long")


def _parts(texts: str, members: str) -> Column:
    """Parts of a bucket, by its texts and the members of their sets."""
    return F.greatest(F.ceil(F.col(texts) / PART_TEXTS), F.ceil(F.col(members) / PART_MEMBERS)).cast("int")


def links(sets: DataFrame) -> DataFrame:
    """Edges (a, b) that connect exactly the nodes of sets (node, n, fp, hs) with similarity 4/5 or more."""
    members = sets.select("node", F.explode("hs").alias("h"))
    common = durable(members.groupBy("h").agg(F.count("*").alias("c")).where("c > 1"))
    shared = members.join(common, "h").groupBy("node").agg(F.array_sort(F.collect_list(F.struct("c", "h"))).alias("found"))
    alone = F.col("n") - F.size("found")  # members of no other text come first in the order
    room = F.col("n") - F.ceil(4 * F.col("n") / 5) + 1 - alone
    leading = shared.join(sets.select("node", "n"), "node").withColumns({"alone": alone, "room": room.cast("int")}).where("room > 0")
    posted = leading.select("node", "n", "alone", F.posexplode(F.slice("found", 1, F.col("room"))).alias("i", "x")).select(F.col("x.h").alias("h"), "node", "n", (F.col("alone") + F.col("i")).alias("at"))
    posted = durable(posted)
    ends = posted.groupBy("h").agg(F.min("node").alias("lo"), F.max("node").alias("hi")).where("lo != hi")
    first = posted.join(ends, "h").select("node", "n", "lo", F.explode(F.array("lo", "hi")).alias("end"))
    first = durable(first.where("node != end AND NOT (node = lo AND end > lo)").select("node", "n", "end").distinct())
    rays = first.join(first.groupBy("end").agg(F.count("*").alias("m"), F.sum("n").alias("members")), "end")
    rays = rays.select(F.col("end").alias("h"), F.pmod(F.xxhash64("node"), _parts("m", "members").cast("long")).cast("int").alias("p"), "node", F.lit(False).alias("centre"))
    stars = rays.union(rays.select("h", "p", F.col("h").alias("node"), F.lit(True).alias("centre")).distinct())
    linked = durable(_tiled(stars.select("h", "p", F.col("p").alias("q"), "node", F.col("node").alias("label"), "centre"), sets, True))
    labels = components(linked)
    labelled = durable(posted.join(labels, "node", "left").withColumn("label", F.coalesce("root", "node")).drop("root"))
    several = labelled.groupBy("h").agg(F.min("label").alias("lo"), F.max("label").alias("hi"), F.count("*").alias("m"), F.sum("n").alias("members")).where("lo != hi")
    open_ = labelled.join(several.select("h", _parts("m", "members").alias("parts")), "h").withColumn("part", F.pmod(F.xxhash64("node"), F.col("parts").cast("long")).cast("int"))
    met = open_.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).select("h", F.least("part", "other").alias("p"), F.greatest("part", "other").alias("q"), "node", "label", F.lit(False).alias("centre"))
    return linked.union(_tiled(met, sets, False))


def deduplicate(docs: DataFrame, width: int = WORDS) -> DataFrame:
    """One row of docs (doc_id, text and any others, kept) for each component of texts linked by similarity 4/5: that of the smallest
    id, null ids last. Rows are told apart by id and text, so rows that share an id and nothing else both stay. Texts without a
    word are equal; a text of fewer words than a shingle is one shingle."""
    names = [f"in_{i}" for i in range(len(docs.columns))]
    doc_id, text = (names[docs.columns.index(c)] for c in ("doc_id", "text"))
    placed = docs.toDF(*names).withColumns(dict(zip(("did", "th"), _place(doc_id, text))))
    texts = placed.select("did", "th", F.col(text).cast("string").alias("text"))
    leading = _with_sets(texts, width, True)
    rows = durable(leading.drop("hs", "fp"))
    same = Window.partitionBy("h")
    posted = leading.select("node", "n", F.explode("hs").alias("h")).withColumns({"lo": F.min("node").over(same), "hi": F.max("node").over(same)}).where("lo != hi")
    least = 1 + F.floor(F.ceil(4 * F.col("n") / 5) / 10)  # of the smallest text that can be similar
    near = posted.groupBy("node", "n").agg(F.count("*").alias("c")).where(F.col("c") >= least).select("node")
    first = durable(rows.groupBy("node").agg(F.min(F.struct("did", "th")).alias("x")))  # exact copies meet before any join
    one = durable(first.join(near, "node", "left_semi").select("x.did", "x.th"))
    some = texts.mapInArrow(_passing(one), texts.schema).join(one, ["did", "th"], "left_semi").dropDuplicates(["did", "th"])
    sets = durable(_with_sets(some, width, False).select("node", "n", "fp", "hs"))
    roots = components(links(sets))
    kept = first.join(roots, "node", "left").groupBy(F.coalesce("root", "node").alias("root")).agg(F.min("x").alias("x"))
    stay = placed.join(durable(kept.select("x.did", "x.th")), ["did", "th"], "left_semi")
    nth = F.row_number().over(Window.partitionBy("did", "th").orderBy("did"))  # rows that repeat id and text
    return stay.withColumn("nth", nth).where("nth = 1").select(*names).toDF(*docs.columns)
