"""SimHash near-duplicates: 64-bit fingerprints of word shingles, compared bit-sliced.

Fingerprints are compared in tiles: bit planes lie vertically (one machine word holds one bit of 64
fingerprints), carry-save counters add up the differing bits of 64 candidates at once, and blocks in
which every lane is beyond the radius are abandoned. Which fingerprints meet in a tile follows the pigeonhole
principle, so no pair within the radius is lost: the 64 bits are cut into blocks, and two fingerprints
that differ in at most `radius` bits agree on all but `radius` blocks, hence share one of the block choices.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations, repeat

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from spreadsample.llm.common import components, durable

SHINGLE, SEED, RADIUS, BLOCKS = 3, 42, 2, 5
#: Fingerprints compared together at least, and the largest bucket that is compared tile by tile.
TILE, BUCKET = 1024, 32768
FLUSH = 1 << 18
ALL = np.uint64(0xFFFFFFFFFFFFFFFF)


def shingle_hashes(text: bytes, width: int = SHINGLE, seed: int = SEED) -> list[int]:
    """XXH64 of every shingle of one text: words are cut at ASCII white space, A-Z count as a-z."""
    words = text.lower().split()
    if len(words) < width:
        return [xxhash.xxh64_intdigest(b" ".join(words), seed)] if words else []
    return list(map(xxhash.xxh64_intdigest, map(b" ".join, zip(*(words[i:] for i in range(width)))), repeat(seed)))


def majority(hashes: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """One fingerprint for each run of hashes: a bit is set if over half of the run's hashes have it."""
    out = np.zeros(len(counts), np.uint64)
    some = np.flatnonzero(counts)
    if len(some):
        starts = np.concatenate(([0], np.cumsum(counts[some])[:-1]))
        ones = np.add.reduceat(np.unpackbits(hashes.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little"), starts, axis=0, dtype=np.int32)
        out[some] = np.packbits(2 * ones > counts[some][:, None], axis=1, bitorder="little").view(np.uint64).ravel()
    return out


def _fingerprint_batches(width: int, seed: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found, hashes, counts = [], [], []
            for text in batch.column(batch.num_columns - 1).cast(pa.binary()).to_pylist():
                h = shingle_hashes(text or b"", width, seed)
                hashes += h
                counts.append(len(h))
                if len(hashes) >= FLUSH:
                    found.append(majority(np.array(hashes, np.uint64), np.array(counts)))
                    hashes, counts = [], []
            found.append(majority(np.array(hashes, np.uint64), np.array(counts, np.int64)))
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(np.concatenate(found).view(np.int64))], [*batch.schema.names[:-1], "fp"])

    return run


def fingerprints(docs: DataFrame, width: int = SHINGLE, seed: int = SEED) -> DataFrame:
    """(doc_id, fp) for every row of docs; fp is the fingerprint as a signed long. Null, empty and blank
    texts have fingerprint 0; a text of fewer words than a shingle is one shingle."""
    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(_fingerprint_batches(width, seed), "doc_id long, fp long")


def hex16(fp: Column) -> Column:
    return F.lpad(F.lower(F.hex(fp)), 16, "0")


def bit_sliced_links(values: np.ndarray, radius: int, queries: int = 256, check_every: int = 8) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Index pairs (i, j), i < j, of values that differ in at most radius bits, for one block of i at a time."""
    n = len(values)
    words = -(-n // 64)
    bits = np.zeros((words * 64, 64), np.uint8)
    bits[:n] = np.unpackbits(np.ascontiguousarray(values).view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
    planes = np.ascontiguousarray(np.packbits(np.ascontiguousarray(bits.T), axis=1, bitorder="little")).view(np.uint64)
    masks = np.where(bits[:n].astype(bool), ALL, np.uint64(0))
    lanes = np.arange(words * 64)
    levels = max(1, radius.bit_length())
    for low in range(0, n, queries):
        rows = np.arange(low, min(n, low + queries))
        live = np.arange(low // 64, words)  # only later fingerprints are compared
        later = lanes[None, low // 64 * 64 :]
        beyond = np.packbits((later <= rows[:, None]) | (later >= n), axis=1, bitorder="little").view(np.uint64)
        counter = [np.zeros_like(beyond) for _ in range(levels)]

        def exceeded(counter=counter):
            above, same = np.zeros_like(counter[0]), np.full_like(counter[0], ALL)
            for level in reversed(range(levels)):
                if radius >> level & 1:
                    same = same & counter[level]
                else:
                    above |= same & counter[level]
                    same = same & ~counter[level]
            return above

        for bit in range(64):
            carry = planes[bit][live][None, :] ^ masks[rows, bit][:, None]
            for level in range(levels):
                counter[level], carry = counter[level] ^ carry, counter[level] & carry
            beyond |= carry
            if bit % check_every == check_every - 1:
                beyond |= exceeded(counter)
                keep = (beyond != ALL).any(axis=0)
                if not keep.all():
                    live, beyond, counter = live[keep], beyond[:, keep], [c[:, keep] for c in counter]
                if not len(live):
                    break
        if len(live):
            near = np.unpackbits(np.ascontiguousarray(~beyond).view(np.uint8), axis=1, bitorder="little").astype(bool)
            i, j = np.nonzero(near)
            if len(i):
                yield rows[i], live[j // 64] * 64 + j % 64


def merge_labels(labels: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """labels (each node's smallest known index in its component) after the links i-j."""
    while True:
        a, b = labels[i], labels[j]
        least = np.minimum(a, b)
        if (a == b).all():
            return labels
        for side in (i, j, a, b):
            np.minimum.at(labels, side, least)
        while (labels[labels] != labels).any():
            labels = labels[labels]


def _forests(radius: int):
    """Per tile of whole buckets, edges from each linked fingerprint to the first of its component there."""

    def forest(values: np.ndarray) -> pa.RecordBatch:
        values = np.unique(values)
        labels = np.arange(len(values))
        for i, j in bit_sliced_links(values, radius):
            labels = merge_labels(labels, i, j)
        linked = np.flatnonzero(labels != np.arange(len(values)))
        return pa.RecordBatch.from_arrays([pa.array(values[linked].view(np.int64)), pa.array(values[labels[linked]].view(np.int64))], ["a", "b"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept = [np.zeros(0, np.int64)] * 3
        for batch in batches:
            blocks, keys, values = (np.concatenate((k, batch.column(c).to_numpy(zero_copy_only=False))) for c, k in enumerate(kept))
            cuts = np.flatnonzero((np.diff(keys) != 0) | (np.diff(blocks) != 0)) + 1
            at = 0
            for cut in cuts:
                if cut - at >= TILE:
                    yield forest(values[at:cut].view(np.uint64))
                    at = cut
            kept = [blocks[at:], keys[at:], values[at:]]
        if len(kept[2]):
            yield forest(kept[2].view(np.uint64))

    return run


def block_masks(radius: int, blocks: int = BLOCKS) -> list[int]:
    """Masks of all choices of blocks - radius out of the blocks of the 64 bits."""
    edges = [64 * i // blocks for i in range(blocks + 1)]
    spans = [((1 << (hi - lo)) - 1) << lo for lo, hi in zip(edges, edges[1:])]
    return [sum(chosen) for chosen in combinations(spans, blocks - radius)]


def _signed(mask: int) -> int:
    return mask - (1 << 64) if mask >> 63 else mask


def fingerprint_links(distinct: DataFrame, radius: int = RADIUS, blocks: int = BLOCKS, bucket: int = BUCKET) -> DataFrame:
    """Edges (a, b) that connect exactly the fingerprints (column fp, distinct) within radius bits of each
    other: a spanning forest for each tile, so that a group of m near copies gives no m * m pairs.

    A bucket beyond `bucket` fingerprints never meets in one task: there, fingerprints within two bits are found by
    the values one bit away that they share (radius 2 or less), by a partially aggregated minimum."""
    if radius > 2:
        raise ValueError("buckets beyond the bound are resolved for a radius of at most 2")
    keys = F.array(*[F.col("fp").bitwiseAND(F.lit(_signed(m))) for m in block_masks(radius, blocks)])
    dealt = distinct.select("fp", F.posexplode(keys).alias("block", "key"))
    shared = dealt.groupBy("block", "key").agg(F.count("*").alias("n")).where("n > 1")
    members = dealt.join(shared, ["block", "key"])
    cold = members.where(F.col("n") <= bucket).select("block", "key", "fp").repartition("block", "key").sortWithinPartitions("block", "key")
    edges = cold.mapInArrow(_forests(radius), "a long, b long")
    hot = members.where(F.col("n") > bucket).select("fp").distinct()
    ball = hot.select("fp", F.explode(F.array(F.col("fp"), *[F.col("fp").bitwiseXOR(F.lit(_signed(1 << b))) for b in range(64 * (radius > 0))])).alias("near"))
    if radius == 1:
        ball = ball.join(hot.select(F.col("fp").alias("near")), "near", "left_semi")
    first = ball.groupBy("near").agg(F.min("fp").alias("b"), F.count("*").alias("n")).where("n > 1").select("near", "b")
    return edges.union(ball.join(first, "near").where("fp != b").select(F.col("fp").alias("a"), "b"))


def fingerprint_roots(distinct: DataFrame, radius: int = RADIUS, bucket: int = BUCKET) -> DataFrame:
    """distinct (fp and other columns) with root, the fingerprint that names its component."""
    roots = components(fingerprint_links(distinct, radius, bucket=bucket))
    return distinct.join(roots.withColumnRenamed("node", "fp"), "fp", "left").withColumn("root", F.coalesce("root", "fp"))


def near_duplicates(docs: DataFrame, width: int = SHINGLE, radius: int = RADIUS, bucket: int = BUCKET) -> DataFrame:
    """(doc_id, fingerprint, component_id) for every row of docs (columns doc_id, text; others are not read).

    component_id is the smallest non-null doc_id of the rows reachable over links; null only if none of them has an id.
    Repeated rows and equal ids are kept as they come; an empty table gives no rows."""
    fps = durable(fingerprints(docs, width))
    distinct = durable(fps.groupBy("fp").agg(F.min("doc_id").alias("first_id")))
    rooted = fingerprint_roots(distinct, radius, bucket)
    least = rooted.groupBy("root").agg(F.min("first_id").alias("component_id"))
    found = durable(rooted.join(least, "root").select("fp", "component_id"))
    return fps.join(found, "fp").select("doc_id", hex16(F.col("fp")).alias("fingerprint"), "component_id")


def deduplicate(docs: DataFrame, width: int = SHINGLE, radius: int = RADIUS, bucket: int = BUCKET) -> DataFrame:
    """One row of docs (doc_id, text and any others, kept) for each component of near duplicates: that of the smallest id, null ids
    last, rows of one id in the order of a hash of their text. Rows are told apart by id and text, so unlike texts of one id both stay; of
    rows that repeat both, one stays. An empty table gives no rows."""
    names = [f"in_{i}" for i in range(len(docs.columns))]
    doc_id, text = (F.col(names[docs.columns.index(c)]) for c in ("doc_id", "text"))
    placed = docs.toDF(*names).withColumns({"did": F.coalesce(doc_id.cast("long"), F.lit(2**63 - 1)), "th": F.xxhash64(text.cast("string"))})
    fps = placed.select("did", "th", text.cast("string").alias("text")).mapInArrow(_fingerprint_batches(width, SEED), "did long, th long, fp long")
    distinct = durable(fps.groupBy("fp").agg(F.min(F.struct("did", "th")).alias("first")))
    kept = durable(fingerprint_roots(distinct, radius, bucket).groupBy("root").agg(F.min("first").alias("x")).select("x.did", "x.th"))
    nth = F.row_number().over(Window.partitionBy("did", "th").orderBy("did"))
    return placed.join(kept, ["did", "th"], "left_semi").withColumn("nth", nth).where("nth = 1").select(*names).toDF(*docs.columns)
