"""Quality classifier: histogram gradient-boosted trees over document statistics.

Statistics come from the bytes of many texts at once, by table look-ups, counts and word hashes in numpy. Trees are grown on the driver
from a bounded sample of labelled rows; all trees together are four flat arrays, and a batch of documents goes
down all of them at once.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spreadsample.llm.common import durable
from spreadsample.llm.langid import held_out

CHUNK_BYTES, LABELLED = 1 << 22, 20_000
TREES, DEPTH, BINS, RATE, LEAST, RIDGE = 80, 4, 64, 0.15, 8, 1.0
#: Classes of bytes; each symbol of the second string is a class of its own. Bytes of several-byte characters are the last two.
GROUPS = ("abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789", "\t\r\v\f ", "\n", "'\"`", "()[]{}")
SYMBOLS = ".,!?:;|*#$%&@_-/\\<>=+~^"
MULTIPLIER = np.uint64(0x9E3779B97F4A7C15)


def byte_classes() -> np.ndarray:
    table = np.full(256, len(GROUPS) + len(SYMBOLS), np.uint8)
    for k, group in enumerate((*GROUPS, *SYMBOLS)):
        table[list(group.encode())] = k
    table[0x80:0xC0] = len(GROUPS) + len(SYMBOLS) + 1
    table[0xC0:] = len(GROUPS) + len(SYMBOLS) + 2
    return table


N_CLASSES = len(GROUPS) + len(SYMBOLS) + 3
NAMES = ["log_bytes", *(f"share_{k}" for k in range(N_CLASSES)), "words_per_byte", "word_length", "word_length_sd", "words_end_in_symbol", "words_upper", "lines_per_word", "line_length_sd", "doubled_bytes", "distinct_words", "distinct_triples", "distinct_lines", "mean_word_repeats"]


def _segment_hash(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each span of data, from one running polynomial."""
    power = np.cumprod(np.full(len(data) + 1, MULTIPLIER, np.uint64), dtype=np.uint64)
    running = np.concatenate((np.zeros(1, np.uint64), np.cumsum((data.astype(np.uint64) + np.uint64(1)) * power[:-1], dtype=np.uint64)))
    back = np.cumprod(np.full(len(data) + 1, np.uint64(pow(int(MULTIPLIER), -1, 1 << 64)), np.uint64), dtype=np.uint64)
    value = (running[ends] - running[starts]) * back[starts]
    return value ^ (value >> np.uint64(29))


def _distinct(of: np.ndarray, values: np.ndarray, n: int) -> np.ndarray:
    """How many distinct values each document has."""
    mixed = values * np.uint64(0xD6E8FEB86659FD93) ^ of.astype(np.uint64) * MULTIPLIER
    _, first = np.unique(mixed, return_index=True)
    return np.bincount(of[first], minlength=n)


def statistics(texts: list[bytes]) -> np.ndarray:
    """A row of NAMES for each text; an empty text has zeros."""
    n = len(texts)
    out = np.zeros((n, len(NAMES)))
    size = np.array([len(t) for t in texts], np.int64)
    data = np.frombuffer(b"".join(texts), np.uint8)
    if not len(data):
        return out
    doc = np.repeat(np.arange(n), size)
    kind = byte_classes()[data]
    counts = np.bincount(doc * N_CLASSES + kind, minlength=n * N_CLASSES).reshape(n, N_CLASSES)
    some = np.maximum(size, 1)
    ratio = lambda a, b: a / np.maximum(b, 1)
    first_byte = np.zeros(len(data), bool)
    first_byte[(np.cumsum(size) - size)[size > 0]] = True
    blank = (kind == 3) | (kind == 4)
    begins = ~blank & (np.append(True, blank[:-1]) | first_byte)
    starts = np.flatnonzero(begins)
    closes = ~blank & (np.append(blank[1:], True) | np.append(first_byte[1:], True))
    ends = np.flatnonzero(closes) + 1
    of = doc[starts]
    words = np.bincount(of, minlength=n)
    length = ends - starts
    mean = ratio(np.bincount(of, length, n), words)
    spread = np.sqrt(np.maximum(0, ratio(np.bincount(of, length.astype(float) ** 2, n), words) - mean**2))
    last = kind[ends - 1]
    symbol = (last >= len(GROUPS)) & (last < N_CLASSES - 3) & (data[ends - 1] != ord(".")) & (data[ends - 1] != ord(","))
    upper = np.concatenate(([0], np.cumsum(kind == 1)))
    shouted = (upper[ends] - upper[starts]) * 2 > length
    line_starts = np.flatnonzero(first_byte | np.append(False, kind[:-1] == 4))
    line_ends = np.append(line_starts[1:], len(data))
    line_of, line_size = doc[line_starts], (line_ends - line_starts).astype(float)
    lines = np.bincount(line_of, minlength=n)
    line_mean = ratio(np.bincount(line_of, line_size, n), lines)
    line_spread = np.sqrt(np.maximum(0, ratio(np.bincount(line_of, line_size**2, n), lines) - line_mean**2))
    doubled = np.append(False, (data[1:] == data[:-1]) & ~first_byte[1:])
    hashes = _segment_hash(data, starts, ends)
    distinct = _distinct(of, hashes, n)
    triple = np.flatnonzero(of[2:] == of[:-2]) if len(of) > 2 else np.zeros(0, np.int64)
    triples = hashes[triple] * np.uint64(3) + hashes[triple + 1] * np.uint64(5) + hashes[triple + 2 if len(triple) else triple]
    out[:, 0] = np.log1p(size)
    out[:, 1 : 1 + N_CLASSES] = counts / some[:, None]
    out[:, 1 + N_CLASSES :] = np.column_stack((
        words / some, mean, spread, ratio(np.bincount(of, symbol, n), words), ratio(np.bincount(of, shouted, n), words),
        ratio(lines, words), line_spread, np.bincount(doc, doubled, n) / some, ratio(distinct, words),
        ratio(_distinct(of[triple], triples, n), np.bincount(of[triple], minlength=n)),
        ratio(_distinct(line_of, _segment_hash(data, line_starts, line_ends), n), lines), ratio(words, distinct),
    ))
    return out


@dataclass
class Forest:
    """Trees of equal depth: node v's children are 2v+1 and 2v+2; a row goes right where its feature is above the limit."""

    feature: np.ndarray  # trees x inner nodes
    limit: np.ndarray
    value: np.ndarray  # trees x leaves
    start: float

    def score(self, x: np.ndarray) -> np.ndarray:
        total = np.full(len(x), self.start)
        if len(self.value):
            trees, rows = np.arange(len(self.value)), np.arange(len(x))[:, None]
            node = np.zeros((len(x), len(trees)), np.int64)
            for _ in range(int(np.log2(self.value.shape[1]))):
                node = 2 * node + 1 + (x[rows, self.feature[trees, node]] > self.limit[trees, node])
            total += self.value[trees, node - self.feature.shape[1]].sum(axis=1)
        return 1 / (1 + np.exp(-total))


def grow(x: np.ndarray, y: np.ndarray, trees: int = TREES, depth: int = DEPTH, bins: int = BINS, rate: float = RATE, least: int = LEAST, ridge: float = RIDGE) -> Forest:
    """Boosted trees for labels 0 and 1 by logistic loss; one class alone, or none, gives its share as constant score."""
    share = (y.sum() + 1) / (len(y) + 2)
    start = float(np.log(share / (1 - share)))
    inner, empty = 2**depth - 1, np.zeros((0, 2**depth - 1))
    if len(np.unique(y)) < 2:
        return Forest(empty.astype(np.int64), empty, np.zeros((0, 2**depth)), start)
    n, f = x.shape
    edges = [np.unique(np.quantile(x[:, k], np.linspace(0, 1, bins + 1)[1:-1])) for k in range(f)]
    binned = np.column_stack([np.searchsorted(edges[k], x[:, k], "left") for k in range(f)])
    flat = binned + np.arange(f) * bins
    margin = np.full(n, start)
    all_features, all_limits, all_values = [], [], []
    for _ in range(trees):
        p = 1 / (1 + np.exp(-margin))
        g, h = p - y, p * (1 - p)
        node, feature, limit = np.zeros(n, np.int64), np.zeros(inner, np.int64), np.full(inner, np.inf)
        for level in range(depth):
            base, width = 2**level - 1, 2**level
            at = ((node - base)[:, None] * (f * bins) + flat).ravel()
            sums = [np.bincount(at, np.repeat(v, f), width * f * bins).reshape(width, f, bins).cumsum(2) for v in (g, h, np.ones(n))]
            (gl, hl, nl), (gt, ht, nt) = sums, [s[:, :, -1:] for s in sums]
            gain = gl**2 / (hl + ridge) + (gt - gl) ** 2 / (ht - hl + ridge) - gt**2 / (ht + ridge)
            gain[(nl < least) | (nt - nl < least)] = 0
            best = gain.reshape(width, -1).argmax(1)
            for v in range(width):
                k, b = divmod(int(best[v]), bins)
                if gain[v, k, b] > 1e-9 and b < len(edges[k]):
                    feature[base + v], limit[base + v] = k, edges[k][b]
            node = 2 * node + 1 + (x[np.arange(n), feature[node]] > limit[node])
        leaf = node - inner
        value = -rate * np.bincount(leaf, g, 2**depth) / (np.bincount(leaf, h, 2**depth) + ridge)
        margin += value[leaf]
        all_features.append(feature)
        all_limits.append(limit)
        all_values.append(value)
    return Forest(np.stack(all_features), np.stack(all_limits), np.stack(all_values), start)


def described(docs: DataFrame) -> DataFrame:
    """(doc_id, held_out, f array<float>): the statistics of every row of docs (doc_id, text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows, part, size = [], [], 0
            for t in b.column(2).cast(pa.binary()):
                part.append(t.as_py() or b"")
                size += len(part[-1])
                if size >= CHUNK_BYTES:
                    rows.append(statistics(part))
                    part, size = [], 0
            rows.append(statistics(part))
            flat = np.concatenate(rows).astype(np.float32)
            found = pa.ListArray.from_arrays(pa.array(np.arange(len(flat) + 1, dtype=np.int32) * len(NAMES)), pa.array(flat.ravel()))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), found], ["doc_id", "held_out", "f"])

    docs = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    return docs.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "text").mapInArrow(run, "doc_id long, held_out boolean, f array<float>")


def score(docs: DataFrame, labels: DataFrame, labelled: int = LABELLED) -> DataFrame:
    """(doc_id, held_out, score, predicted) for every row of docs. Labels (doc_id, quality 0 or 1) teach only by rows that are not
    held out: those of smallest hash, at most `labelled`. Null ids, labels and other label values teach nothing; null texts are
    scored as empty; repeated rows count as often as they come."""
    known = durable(described(docs))
    taught = labels.select(F.col("doc_id").cast("long"), F.col("quality").cast("int")).where(F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id")) & F.col("quality").isin(0, 1))
    some = taught.orderBy(F.xxhash64("doc_id"), "doc_id", "quality").limit(labelled)
    rows = known.join(F.broadcast(some), "doc_id").orderBy("doc_id", "quality").select("f", "quality").limit(2 * labelled).toArrow()
    n = rows.num_rows
    x = rows.column("f").combine_chunks().flatten().to_numpy().reshape(n, len(NAMES)) if n else np.zeros((0, len(NAMES)))
    forest = grow(x.astype(np.float32), rows.column("quality").to_numpy().astype(float))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = b.column(2).flatten().to_numpy().reshape(b.num_rows, len(NAMES))
            found = np.concatenate([forest.score(x[s : s + 4096]) for s in range(0, len(x), 4096)] or [np.zeros(0)])
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(found), pa.array((found >= 0.5).astype(np.int32))], ["doc_id", "held_out", "score", "predicted"])

    return known.mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int")
