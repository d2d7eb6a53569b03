"""Language ID by unigram pieces, marginalised over all segmentations.

Pieces come from a fixed public vocabulary. Each language has a probability for every piece, learned by
expectation maximisation on the language's words; a word's likelihood is the sum over all its segmentations, by a
forward pass that runs over many words at once through a trie held as an array.
"""

from __future__ import annotations

import re
import unicodedata
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from spreadsample.llm.bpe import chunks

MARK, LONGEST, LUT = "▁", 24, 0x110000
#: Letters in no piece share one for each 256 code points, so that scripts stay apart.
OTHER = LUT >> 8
DOCS_PER_LANG, WORDS_PER_LANG, ROUNDS, SMOOTH = 2000, 20_000, 4, 0.1
CACHED_WORDS, NEW_WORDS, LANGUAGES = 150_000, 8_000, 4096
#: Code points of the texts that are split into words at once.
TEXT_CHARS = 1 << 18
UNKNOWN = "und"
#: A text of at least so many words has no language if no language is likelier than the others together, or if each letter costs more bits
#: than one drawn at random from 64 signs. Shorter texts say too little to be turned away.
JUDGED_WORDS, LEAST_SCORE, RANDOM_BITS = 20, 0.5, 6.0


def vocabulary(path: str) -> list[str]:
    """The pieces of lower-case letters (and their marks) in a sentencepiece model, a leading mark for word begin, and the mark itself.
    Texts are lower-cased, so pieces with capitals could never be used."""
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    pieces = {model.id_to_piece(i) for i in range(model.get_piece_size())}
    return sorted(p for p in pieces if p == MARK or (body := p.removeprefix(MARK)) and body == body.lower() and all(c.isalpha() or unicodedata.category(c)[0] == "M" for c in body))


class Segmenter:
    """Likelihoods of words under unigram pieces. Letters of longer pieces walk a trie, a table of nodes and letters; letters that
    are pieces by themselves alone, and those in none, are looked up by code point."""

    def __init__(self, pieces: list[str]):
        common = sorted({c for p in pieces if len(p.removeprefix(MARK)) > 1 for c in p} | {MARK})
        self.code = np.zeros(LUT, np.uint16)
        for i, c in enumerate(common):
            self.code[ord(c)] = i + 1
        singles = sorted({c for p in pieces for c in p} - set(common))
        pieces = sorted({p for p in pieces if all(self.code[ord(c)] for c in p)} | set(common))
        self.n_pieces = len(pieces) + len(singles) + OTHER
        self.single = self._blocks()  # the piece of a letter outside the trie
        for i, c in enumerate(singles):
            self.single[ord(c)] = len(pieces) + i
        rows, ends = [dict()], [-1]
        for k, p in enumerate(pieces):
            node = 0
            for c in p:
                node = rows[node].setdefault(int(self.code[ord(c)]), len(rows))
                if node == len(rows):
                    rows.append({})
                    ends.append(-1)
            ends[node] = k
        dead = len(rows)
        self.arms = np.array([(v, c, to) for v, row in enumerate(rows) for c, to in row.items()], np.int32)
        self.letters = len(common) + 1
        self.piece = np.array([*ends, -1], np.int32)
        self.piece[self.piece < 0] = self.n_pieces  # a piece of probability zero
        self.depth = max(map(len, pieces))
        self.dead = dead
        self._grow()

    def _grow(self) -> None:
        """The table of nodes and letters, from its arms: nearly all of it is dead ends."""
        self.child = np.full((self.dead + 1, self.letters), self.dead, np.uint16 if self.dead < 1 << 16 else np.int32)
        self.child[self.arms[:, 0], self.arms[:, 1]] = self.arms[:, 2]

    def __getstate__(self) -> dict:
        """What travels to tasks: the arms in place of the table, and the letters that differ from the rule in place of all code points."""
        state = {k: v for k, v in self.__dict__.items() if k not in ("child", "code", "single")}
        coded, alone = np.flatnonzero(self.code), np.flatnonzero(self.single != self._blocks())
        return state | {"coded": (coded, self.code[coded]), "alone": (alone, self.single[alone])}

    def __setstate__(self, state: dict) -> None:
        (coded, codes), (alone, singles) = state.pop("coded"), state.pop("alone")
        self.__dict__.update(state)
        self.code, self.single = np.zeros(LUT, np.uint16), self._blocks()
        self.code[coded], self.single[alone] = codes, singles
        self._grow()

    def _blocks(self) -> np.ndarray:
        """The piece of each code point that is in none: one for 256 of them."""
        return self.n_pieces - OTHER + (np.arange(LUT, dtype=np.int32) >> 8)

    def codes(self, words: list[str]) -> tuple[np.ndarray, np.ndarray, tuple[np.ndarray, np.ndarray]]:
        """Order of falling length, lengths in that order, and as columns the letters' codes and the pieces of those without a code."""
        marked = [MARK + w for w in words]
        sizes = np.array([len(w) for w in marked])
        points = np.frombuffer("".join(marked).encode("utf-32-le"), np.uint32)
        flat, alone = self.code[points], self.single[points]
        grid, lone = np.zeros((sizes.max(), len(words)), np.intp), np.zeros((sizes.max(), len(words)), np.int32)
        order = np.argsort(-sizes, kind="stable")
        starts = np.cumsum(sizes) - sizes
        for p in range(len(grid)):
            n = np.count_nonzero(sizes > p)
            at = starts[order[:n]] + p
            grid[p, :n], lone[p, :n] = flat[at], alone[at]
        return order, sizes[order], (grid, lone)

    def arcs(self, sizes: np.ndarray, letters: tuple[np.ndarray, np.ndarray]) -> Iterator[tuple[int, int, int, np.ndarray]]:
        """(from, to, words, piece) for all letters spans that may be pieces; only the first `words` are so long."""
        grid, lone = letters
        for p in range(len(grid)):
            node = np.zeros(np.count_nonzero(sizes > p), np.int32)
            for q in range(p, min(len(grid), p + self.depth)):
                n = np.count_nonzero(sizes > q)
                node = self.child[node[:n], grid[q, :n]]
                piece = self.piece[node]
                yield p, q + 1, n, np.where(grid[p, :n] == 0, lone[p, :n], piece) if q == p else piece
                if not (node != self.dead).any():
                    break

    def forward(self, words: list[str], probability: np.ndarray) -> np.ndarray:
        """Log-likelihood (words x languages): the sum over all segmentations. probability: pieces x languages."""
        order, sizes, grid = self.codes(words)
        table = np.vstack((probability, np.zeros(probability.shape[1])))
        alpha = np.zeros((len(grid[0]) + 1, len(words), probability.shape[1]))
        alpha[0] = 1
        for p, q, n, piece in self.arcs(sizes, grid):
            alpha[q, :n] += alpha[p, :n] * table[piece]
        out = np.empty(alpha.shape[1:])
        out[order] = np.log(alpha[sizes, np.arange(len(words))])
        return out

    def expected(self, words: list[str], counts: np.ndarray, probability: np.ndarray) -> np.ndarray:
        """Expected uses of each piece in words, under one language's probabilities."""
        order, sizes, grid = self.codes(words)
        table = np.append(probability, 0.0)
        arcs = list(self.arcs(sizes, grid))
        alpha, beta = np.zeros((2, len(grid[0]) + 1, len(words)))
        alpha[0] = 1
        for p, q, n, piece in arcs:
            alpha[q, :n] += alpha[p, :n] * table[piece]
        beta[sizes, np.arange(len(words))] = 1
        for p, q, n, piece in reversed(arcs):
            beta[p, :n] += beta[q, :n] * table[piece]
        share = counts[order] / beta[0]
        uses = np.zeros(self.n_pieces + 1)
        for p, q, n, piece in arcs:
            np.add.at(uses, piece, alpha[p, :n] * table[piece] * beta[q, :n] * share[:n])
        return uses[:-1]

    def learn(self, words: list[str], counts: np.ndarray, rounds: int = ROUNDS) -> np.ndarray:
        probability = np.full(self.n_pieces, 1 / self.n_pieces)
        for _ in range(rounds):
            uses = sum(self.expected(words[s : s + 5000], counts[s : s + 5000], probability) for s in range(0, len(words), 5000)) + SMOOTH
            probability = uses / uses.sum()
        return probability


def held_out(doc_id):
    return F.coalesce(F.pmod(F.crc32(F.encode(doc_id.cast("string"), "UTF-8")), F.lit(3)) == 1, F.lit(False))


def learned(docs: DataFrame, path: str, per_lang: int = DOCS_PER_LANG, words_per_lang: int = WORDS_PER_LANG) -> tuple[Segmenter, list[str], np.ndarray]:
    """Pieces, languages and probabilities, from about per_lang documents of each language (chosen by a hash of the id among those not
    held out) and their words_per_lang commonest words."""
    usable = docs.where(~held_out(F.col("doc_id")) & F.col("doc_id").isNotNull() & F.col("lang").isNotNull() & F.col("text").isNotNull())
    counted = usable.groupBy("lang").count().orderBy(F.desc("count"), "lang")
    sizes = counted.limit(LANGUAGES + 1).collect()
    if len(sizes) > LANGUAGES:
        raise ValueError(f"lang has over {LANGUAGES} values: no table of languages")
    segmenter = Segmenter(vocabulary(path))
    if not sizes:
        return segmenter, [], np.zeros((segmenter.n_pieces, 0))
    share = F.create_map(*[x for r in sizes for x in (F.lit(r["lang"]), F.lit(per_lang / r["count"]))])
    sample = usable.where(F.pmod(F.xxhash64("doc_id", F.lit(3)), F.lit(1_000_000)) < F.element_at(share, F.col("lang")) * 1_000_000)
    words = sample.select("lang", F.explode(F.regexp_extract_all(F.lower("text"), F.lit(rf"[\p{{L}}\p{{M}}]{{1,{LONGEST}}}"), F.lit(0))).alias("word")).where(F.col("word").rlike(r"\p{L}")).groupBy("lang", "word").count()
    best = words.withColumn("r", F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("count"), "word"))).where(F.col("r") <= words_per_lang)
    found: dict[str, list] = {}
    for r in best.orderBy("lang", "r").collect():
        found.setdefault(r["lang"], []).append((r["word"].lower()[:LONGEST], r["count"]))
    langs = sorted(found)
    return segmenter, langs, np.column_stack([segmenter.learn([w for w, _ in found[x]], np.array([n for _, n in found[x]], float)) for x in langs]) if langs else np.zeros((segmenter.n_pieces, 0))


def predictor(segmenter: Segmenter, langs: list[str], probability: np.ndarray):
    """A function from lists of texts to (languages, scores, whether the text has a language); words that it has met are kept, up to a bound."""
    letters, scripts = re.compile(r"[^\W\d_]{1,%d}" % LONGEST), re.compile("[\u0300-\u1dff\u20d0-\u20ff\u2c00-\U0010ffff]")
    with_marks = regex.compile(r"[\p{L}\p{M}]{1,%d}" % LONGEST)  # slower, for texts that may have combining marks
    in_text = lambda t: (with_marks if scripts.search(t) else letters).findall(t)
    known: dict[str, int] = {}
    table = np.zeros((0, len(langs)))

    def predict(texts: list[str]) -> tuple[list[str], list[float], list[bool]]:
        nonlocal known, table
        words = [in_text(t.lower()) for t in texts]
        counts = np.array([len(w) for w in words], np.int64)
        flat = [w for ws in words for w in ws]
        if len(known) > CACHED_WORDS:
            known, table = {}, table[:0]
        new = [w for w in dict.fromkeys(flat) if w not in known]
        for s in range(0, len(new), NEW_WORDS) if langs else ():
            part = new[s : s + NEW_WORDS]
            known.update(zip(part, range(len(known), len(known) + len(part))))
            spelt = ["".join(c for c in w if not c.isnumeric() or c.isalpha()) if any(map(str.isalpha, w)) else "" for w in part]  # \w has some numerals too
            found = segmenter.forward([w or "a" for w in spelt], probability)
            found[[i for i, w in enumerate(spelt) if not w]] = 0
            table = np.vstack((table, found))
        total = np.zeros((len(texts), len(langs)))
        some = np.flatnonzero(counts)
        if langs and len(some):
            at = np.fromiter(map(known.__getitem__, flat), np.int64, len(flat))
            total[some] = np.add.reduceat(table[at], (np.cumsum(counts) - counts)[some])
        if not langs:
            return [UNKNOWN] * len(texts), [0.0] * len(texts), [False] * len(texts)
        best = total.argmax(axis=1)
        score = 1 / np.exp(total - total[np.arange(len(texts)), best][:, None]).sum(axis=1)
        none = ~total.any(axis=1)
        signs = np.array([sum(map(len, ws)) + len(ws) for ws in words])  # letters, and the beginnings of words
        random = total.max(axis=1) < -signs * np.log(2) * RANDOM_BITS
        spoken = ~none & ((counts < JUDGED_WORDS) | (score >= LEAST_SCORE) & ~random)
        return [UNKNOWN if n else langs[b] for n, b in zip(none, best)], np.where(none, 0.0, score).tolist(), spoken.tolist()

    return predict


def identify(docs: DataFrame, path: str, **options) -> DataFrame:
    """(doc_id, held_out, lang_pred, score) for every row of docs (doc_id, text, lang). Only texts are read to predict.

    score is the predicted language's posterior under equal priors. A text that is null or has no letter, and any text if nothing could be
    learned, is `und` with score 0; ties go to the first language by name. Words beyond 24 letters are read as words of 24 letters and the rest.
    Repeated rows are predicted alike; an empty table gives no rows."""
    docs = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"), F.col("lang").cast("string"))
    model = learned(docs, path, **options)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        predict = predictor(*model)
        for b in batches:
            pred, score = [], []
            for texts in chunks(b.column(2), TEXT_CHARS):
                found = predict(texts)
                pred += found[0]
                score += found[1]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(pred, pa.string()), pa.array(score, pa.float64())], ["doc_id", "held_out", "lang_pred", "score"])

    return docs.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "text").mapInArrow(run, "doc_id long, held_out boolean, lang_pred string, score double")


def with_language(docs: DataFrame, path: str, **options) -> DataFrame:
    """The rows of docs (doc_id, text, lang and any others, kept) whose text has a language. Texts that are null or have no letter go, and
    of those with JUDGED_WORDS words or more the ones that fit no language: no language is likelier than the others together, or their
    letters would be likelier if drawn at random. If nothing could be learned, all go; repeated rows are judged alike, an empty table
    gives no rows."""
    model = learned(docs, path, **options)
    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        predict = predictor(*model)
        for b in batches:
            done = 0
            for texts in chunks(b.column(at), TEXT_CHARS):  # a part at a time goes out, so that no second copy of the batch is made
                yield b.slice(done, len(texts)).filter(pa.array(predict(texts)[2], pa.bool_()))
                done += len(texts)

    return docs.mapInArrow(run, docs.schema)
