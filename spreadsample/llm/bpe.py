"""Byte-level BPE encoding and decoding of whole texts, with batched numpy merge rounds.

Symbols of many distinct words lie in one flat array. A round looks all neighbouring pairs up by binary search over the sorted
pair keys, finds every word's lowest rank, and merges that pair wherever it stands in the word; words without a
known pair are done. Few very long words would need many rounds, so words beyond LONG bytes merge from a heap instead.
"""

from __future__ import annotations

import heapq
import json
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

LONG, CHUNK_CHARS, CACHED_WORDS = 1024, 1 << 21, 200_000
NONE = np.int64(1 << 40)
#: How byte-level vocabularies cut text (their white space is the Unicode property), and the bytes that stand for themselves.
PIECES = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\p{White_Space}\p{L}\p{N}]+|\p{White_Space}+(?!\P{White_Space})|\p{White_Space}+"
PRINTABLE = [*range(ord("!"), ord("~") + 1), *range(ord("¡"), ord("¬") + 1), *range(ord("®"), ord("ÿ") + 1)]


def byte_letters() -> list[str]:
    """The letter that stands for each byte in a byte-level vocabulary."""
    letters, spare = [""] * 256, iter(range(256, 512))
    for b in range(256):
        letters[b] = chr(b) if b in PRINTABLE else chr(next(spare))
    return letters


class Codec:
    """Encoder and decoder of one tokenizer file (JSON of the tokenizers library, byte-level BPE)."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model, pre = spec["model"], spec["pre_tokenizer"]
        odd = [x for x in ("continuing_subword_prefix", "end_of_word_suffix", "dropout", "ignore_merges", "byte_fallback") if model.get(x)]
        if spec["normalizer"] or pre["type"] != "ByteLevel" or pre["add_prefix_space"] or not pre.get("use_regex", True) or odd:
            raise ValueError("only plain byte-level BPE files are read here")
        if any(t[x] for t in spec["added_tokens"] for x in ("single_word", "lstrip", "rstrip", "normalized")):
            raise ValueError("added tokens that change their surroundings are not read here")
        letters, vocab = byte_letters(), model["vocab"]
        value = {c: b for b, c in enumerate(letters)}
        self.size = max(*vocab.values(), *(t["id"] for t in spec["added_tokens"])) + 1
        self.first = np.array([vocab[c] for c in letters], np.int64)
        pairs = [m.split(" ") if isinstance(m, str) else m for m in model["merges"]]
        keys = np.array([vocab[a] * self.size + vocab[b] for a, b in pairs], np.int64)
        order = np.argsort(keys, kind="stable")
        self.keys, self.ranks = keys[order], np.arange(len(keys), dtype=np.int64)[order]
        self.merged = np.array([vocab[a + b] for a, b in pairs], np.int64)[order]
        self.bytes_of = [b""] * self.size
        for token, i in vocab.items():
            self.bytes_of[i] = bytes(value[c] for c in token)
        self.added = {t["content"]: t["id"] for t in spec["added_tokens"]}
        for token, i in self.added.items():
            self.bytes_of[i] = token.encode()
        self.reset()

    def reset(self) -> None:
        self.known: dict[str, int] = {}
        self.flat, self.begin, self.count = np.zeros(0, np.int32), np.zeros(0, np.int64), np.zeros(0, np.int64)

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if k not in ("known", "flat", "begin", "count", "cut", "split_added")}

    def __setstate__(self, state):
        self.__dict__.update(state)
        self.reset()

    def lookup(self, left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Rank (NONE if unknown) and merged symbol of each pair."""
        key = left * self.size + right
        at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
        return np.where(self.keys[at] == key, self.ranks[at], NONE), self.merged[at]

    def merge_words(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Flat ids of all words, in order, and their counts."""
        sizes = np.array([len(w) for w in words], np.int64)
        symbols = self.first[np.frombuffer(b"".join(words), np.uint8)]
        word = np.repeat(np.arange(len(words)), sizes)
        done_symbols, done_words = [], []
        while len(symbols):
            rank, into = self.lookup(symbols[:-1], symbols[1:])
            rank[word[:-1] != word[1:]] = NONE
            rank, into = np.append(rank, NONE), np.append(into, 0)
            starts = np.flatnonzero(np.diff(word, prepend=-1))
            least = np.minimum.reduceat(rank, starts)
            least = np.repeat(least, np.diff(starts, append=len(word)))
            busy = least < NONE
            done_symbols.append(symbols[~busy])
            done_words.append(word[~busy])
            hit = (rank == least) & busy
            at = np.arange(len(hit))
            run = np.maximum.accumulate(np.where(hit & ~np.append(False, hit[:-1]), at, 0))
            hit &= (at - run) % 2 == 0  # in a run of one symbol, every second pair
            symbols = np.where(hit, into, symbols)
            keep = busy & ~np.append(False, hit[:-1])
            symbols, word = symbols[keep], word[keep]
        if not done_symbols:
            return np.zeros(0, np.int32), sizes
        symbols, word = np.concatenate(done_symbols), np.concatenate(done_words)
        return symbols[np.argsort(word, kind="stable")].astype(np.int32), np.bincount(word, minlength=len(words))

    def merge_long(self, word: bytes) -> np.ndarray:
        """Ids of one long word: pairs leave a heap by rank and place, neighbours are linked."""
        symbols = self.first[np.frombuffer(word, np.uint8)].tolist()
        n = len(symbols)
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        rank, into = self.lookup(self.first[np.frombuffer(word, np.uint8)][:-1], self.first[np.frombuffer(word, np.uint8)][1:])
        heap = [(r, i, symbols[i], symbols[i + 1], m) for i, (r, m) in enumerate(zip(rank.tolist(), into.tolist())) if r < NONE]
        heapq.heapify(heap)
        table: dict[tuple[int, int], tuple[int, int]] = {}
        while heap:
            _, i, left, right, new = heapq.heappop(heap)
            j = after[i]
            if j >= n or symbols[i] != left or symbols[j] != right:
                continue
            symbols[i], symbols[j] = new, -1
            after[i] = after[j]
            if after[j] < n:
                before[after[j]] = i
            for a, b in ((before[i], i), (i, after[i])):
                if a >= 0 and b < n:
                    pair = symbols[a], symbols[b]
                    if pair not in table:
                        r, m = self.lookup(np.array(pair[:1]), np.array(pair[1:]))
                        table[pair] = int(r[0]), int(m[0])
                    r, m = table[pair]
                    if r < NONE:
                        heapq.heappush(heap, (r, a, *pair, m))
        return np.array([s for s in symbols if s >= 0], np.int32)

    def learn(self, words: list[str]) -> None:
        """Encodes words that are not known yet."""
        raw = [w.encode() for w in words]
        short = [i for i, w in enumerate(raw) if len(w) <= LONG]
        flat, count = self.merge_words([raw[i] for i in short])
        parts, counts = [flat], list(count)
        order = [words[i] for i in short]
        for i, w in enumerate(raw):
            if len(w) > LONG:
                order.append(words[i])
                parts.append(self.merge_long(w))
                counts.append(len(parts[-1]))
        base, n = len(self.flat), len(self.known)
        self.known.update(zip(order, range(n, n + len(order))))
        counts = np.array(counts, np.int64)
        self.begin = np.concatenate((self.begin, base + np.cumsum(counts) - counts))
        self.count = np.concatenate((self.count, counts))
        self.flat = np.concatenate((self.flat, *parts))

    def words(self, text: str) -> list[str]:
        if not hasattr(self, "cut"):
            self.cut = regex.compile(PIECES)
            self.split_added = regex.compile("(" + "|".join(map(regex.escape, sorted(self.added, key=len, reverse=True))) + ")") if self.added else None
        if self.split_added is None or not any(t in text for t in self.added):
            return self.cut.findall(text)
        return [w for part in self.split_added.split(text) for w in ([part] if part in self.added else self.cut.findall(part))]

    def encode(self, texts: list[str]) -> list[np.ndarray]:
        """The ids of each text."""
        words = [self.words(t) for t in texts]
        sizes = np.array([len(w) for w in words], np.int64)
        flat = [w for ws in words for w in ws]
        if len(self.known) > CACHED_WORDS:
            self.reset()
        if new := list({w for w in flat if w not in self.known}):
            own = [w for w in new if w in self.added]
            self.learn([w for w in new if w not in self.added])
            for w in own:
                self.known[w] = len(self.known)
                self.begin, self.count, self.flat = np.append(self.begin, len(self.flat)), np.append(self.count, 1), np.append(self.flat, np.int32(self.added[w]))
        at = np.fromiter(map(self.known.__getitem__, flat), np.int64, len(flat))
        count = self.count[at]
        ends = np.cumsum(count)
        ids = self.flat[np.repeat(self.begin[at] - ends + count, count) + np.arange(ends[-1] if len(ends) else 0)]
        bounds = np.concatenate(([0], ends))[np.cumsum(sizes)]
        return np.split(ids, bounds[:-1]) if len(texts) else []

    def decode(self, ids: np.ndarray) -> str:
        """The text of ids; bytes that are no UTF-8 become replacement characters."""
        return b"".join(map(self.bytes_of.__getitem__, ids.tolist())).decode("utf-8", "replace")


def chunks(column: pa.Array, most: int = CHUNK_CHARS) -> Iterator[list[str]]:
    """The texts of a column (null: empty), in lists of about most code points."""
    part, size = [], 0
    for x in column:
        text = x.as_py() or ""
        part.append(text)
        size += len(text)
        if size >= most:
            yield part
            part, size = [], 0
    yield part


def encode(docs: DataFrame, path: str) -> DataFrame:
    """(doc_id, ids array<int>) for every row of docs (doc_id, text); a null text is an empty one and has no ids."""
    codec = Codec(path)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            at = 0
            for texts in chunks(b.column(1)):
                ids = codec.encode(texts)
                offsets = np.concatenate(([0], np.cumsum([len(x) for x in ids]))).astype(np.int32)
                flat = np.concatenate(ids) if ids else np.zeros(0, np.int32)
                yield pa.RecordBatch.from_arrays([b.column(0).slice(at, len(texts)), pa.ListArray.from_arrays(pa.array(offsets), pa.array(flat, pa.int32()))], ["doc_id", "ids"])
                at += len(texts)

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, ids array<int>")


def encode_and_decode(docs: DataFrame, path: str) -> DataFrame:
    """(doc_id, n_tokens, ids, text) for every row of docs: the ids of each text and what they decode to."""
    codec = Codec(path)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            at = 0
            for texts in chunks(b.column(1)):
                ids = codec.encode(texts)
                sizes = np.array([len(x) for x in ids], np.int64)
                listed = pa.ListArray.from_arrays(pa.array(np.concatenate(([0], np.cumsum(sizes))).astype(np.int32)), pa.array(np.concatenate(ids) if ids else np.zeros(0, np.int32), pa.int32()))
                yield pa.RecordBatch.from_arrays([b.column(0).slice(at, len(texts)), pa.array(sizes), listed, pa.array([codec.decode(x) for x in ids], pa.string())], ["doc_id", "n_tokens", "ids", "text"])
                at += len(texts)

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, n_tokens long, ids array<int>, text string")


def decode(encoded: DataFrame, path: str) -> DataFrame:
    """(doc_id, text) from (doc_id, ids)."""
    codec = Codec(path)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([codec.decode(np.array(x.as_py() or [], np.int64)) for x in b.column(1)], pa.string())], ["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(run, "doc_id long, text string")


def digests(docs: DataFrame, path: str) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256): every text encoded, its ids decoded, both hashed where they arise, so neither leaves its task."""
    import hashlib

    codec = Codec(path)
    names = [str(i) for i in range(codec.size)]
    sha = lambda x: hashlib.sha256(x).hexdigest()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            n, ids_sha, text_sha = [], [], []
            for texts in chunks(b.column(1)):
                for ids in codec.encode(texts):
                    n.append(len(ids))
                    ids_sha.append(sha(",".join(map(names.__getitem__, ids.tolist())).encode()))
                    text_sha.append(sha(codec.decode(ids).encode()))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), pa.array(ids_sha), pa.array(text_sha)], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
