"""Near duplicates of five-word shingles against all pairs."""

import random

import numpy as np
import pytest

import corpus_pipeline
from spreadsample.llm import jaccard

DOC = "doc_id long, text string, lang string, source string, n_chars long"


def plain(rows):
    """The rows that stay: of texts linked by similarity 4/5, the one of the smallest (id, place)."""

    def shingles(text):
        w = (text or "").lower().split()
        return {" ".join(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()

    sets, root = [shingles(t) for _, t in rows], list(range(len(rows)))

    def find(a):
        return a if root[a] == a else find(root[a])

    for a in range(len(rows)):
        for b in range(a):
            both = len(sets[a] & sets[b])
            if sets[a] == sets[b] or both and 9 * both >= 4 * (len(sets[a]) + len(sets[b])):
                x, y = sorted((find(a), find(b)))
                root[y] = x
    groups = {}
    for at, r in enumerate(rows):
        groups.setdefault(find(at), []).append(r)
    return sorted((min(g, key=lambda r: (r[0] is None, r[0] or 0)) for g in groups.values()), key=repr)


def near_copies(seed):
    """Texts of which later ones differ from earlier ones in a few words, so that pairs lie on both sides of 4/5; a common passage."""
    rng = random.Random(seed)
    words = [f"w{i}" for i in range(500)]
    passage = " ".join(rng.choice(words) for _ in range(30))
    texts = [" ".join(rng.choice(words) for _ in range(n)) for n in (8, 20, 60, 60, 120, 300)] + [f"{passage} {' '.join(rng.choice(words) for _ in range(6))}" for _ in range(12)]
    for _ in range(150):
        w = rng.choice(texts[:60]).split()
        for _ in range(rng.randrange(1, 4)):
            w[rng.randrange(len(w))] = rng.choice(words)
        texts.append(" ".join(w))
    return texts + [t.upper() for t in texts[:3]] + ["", " ", "A b", "a B", "c d"]


@pytest.mark.parametrize("seed", range(3))
def test_every_pair_of_four_fifths_is_linked(spark, seed):
    rows = list(enumerate(near_copies(seed)))
    got = corpus_pipeline.remove_near_duplicates(spark, spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in rows], DOC), "").collect()
    assert sorted(((r["doc_id"], r["text"]) for r in got), key=repr) == plain(rows)


def test_rows_of_one_id_with_unlike_texts_stay(spark):
    rows = [(1, "one two three four five six"), (1, "seven eight nine ten eleven twelve"), (1, "one two three four five six"), (None, "ONE two three four five six"), (None, "a b c d e f"), (2, None)]
    got = jaccard.deduplicate(spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in rows], DOC)).collect()
    assert sorted(((r["doc_id"], r["text"]) for r in got), key=repr) == sorted([rows[0], rows[1], rows[4], rows[5]], key=repr)
    assert jaccard.deduplicate(spark.createDataFrame([], DOC)).count() == 0


def test_no_pair_is_compared_before_its_fingerprints(monkeypatch):
    """Sets of any size, and of stars too, are only compared set by set where the bit planes let a pair through."""
    seen = []

    def none(fps, radius):
        seen.append((len(fps), radius))
        return iter(())

    rng = np.random.default_rng(1)
    big, small = np.unique(rng.integers(0, 1 << 60, 100)), np.unique(rng.integers(0, 1 << 60, 5))
    nodes, sets = np.arange(4), [small, small[:4], big, big[:95]]
    fps = np.array([jaccard.majority(s.view(np.uint64), np.array([len(s)]))[0] for s in sets])
    star = {"buckets": np.array([0, 0, 1, 1]), "centres": np.array([True, False, True, False])}
    for only in ({}, star):
        assert sorted(tuple(sorted(x)) for x in jaccard.tile_links(nodes, nodes, fps, sets, **only)) == [(0, 1), (2, 3)]
    assert jaccard.tile_links(nodes, nodes, fps, sets, np.zeros(4, int), np.zeros(4, bool)) == []
    monkeypatch.setattr(jaccard, "bit_sliced_links", none)
    for only in ({}, star):
        assert jaccard.tile_links(nodes, nodes, fps, sets, **only) == []
    assert seen == [(2, jaccard.SMALL_RADIUS), (2, jaccard.RADIUS)] * 2
    assert not hasattr(jaccard, "_similar")
