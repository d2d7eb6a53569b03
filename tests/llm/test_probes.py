"""Awkward tables, brute force and planted cases for the operators."""

import hashlib
import json
import random
import re
import string

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from spreadsample.llm import ann, bpe, langid, linededup, mixing, quality, secrets, sharding, simhash, vector_dedup
from spreadsample.llm.queries import vocabulary_file

from test_jaccard import plain as plain_near
from test_llm import docs, odd, plain_dedup, vectors

PIECES, BYTES = "piece_bpe_32k.model", "byte_bpe_50k.json"


def rows_of(df, *cols):
    return sorted((tuple(r[c] for c in cols) for r in df.collect()), key=repr)


def test_simhash_stage_tells_rows_of_one_id_apart(spark):
    a, b, c = "one two three four five six", "seven eight nine ten eleven twelve", "red green blue black white pink"
    got = simhash.deduplicate(docs(spark, [(3, a, "en", "s"), (5, a, "en", "s"), (5, b, "en", "s"), (5, c, "en", "s"), (None, c, "en", "s"), (None, "other words stand in this line", "en", "s")]))
    assert rows_of(got, "doc_id", "text") == sorted([(3, a), (5, b), (5, c), (None, "other words stand in this line")], key=repr)


def test_vectors_of_several_lengths(spark):
    rng = np.random.default_rng(4)
    rows = [(i, rng.normal(size=8).tolist(), 0) for i in range(200)] + [(1000, [1.0, 2.0, 3.0], 0), (1001, [1.0, 2.0, 3.0], 0), (1002, [3.0, 2.0, -1.0], 0), (1003, [1.0], 0), (1004, [5.0], 0), (1005, [1e200] * 3, 0)]
    got = {r["vec_id"]: (r["n_links"], r["component_id"]) for r in vector_dedup.near_duplicates(vectors(spark, [r for r in rows if r[0] != 1005])).collect()}
    assert got[1000] == (1, 1000) and got[1001] == (1, 1000) and got[1002] == (0, 1002) and got[1003] == (1, 1003) and got[1004] == (1, 1003)
    found = rows_of(ann.search(vectors(spark, rows[:-1]), F.col("vec_id") == 1000), "query_id", "rank", "vec_id")
    assert found == [(1000, 1, 1001), (1000, 2, 1002)]


def test_equal_texts_share_a_shard(spark):
    rows = [(i, "same" if i < 40 else f"text {i}", "en", "s") for i in range(2000)]
    got = {r["doc_id"]: (r["shard"], r["slot"]) for r in sharding.shard(docs(spark, rows)).collect()}
    assert len({got[i][0] for i in range(40)}) == 1
    for s in range(16):
        slots = sorted(v[1] for v in got.values() if v[0] == s)
        assert slots == list(range(len(slots)))


def test_a_group_beyond_a_shard_is_spread_evenly(spark):
    d = docs(spark, [(i, "same text" if i % 3 == 0 else f"own {i:05d}", "en", "s") for i in range(3000)])
    sizes = [r["z"] for r in sharding.shard(d).groupBy("shard").agg(F.sum("size").alias("z")).collect()]
    assert len(sizes) == 16 and max(sizes) < 1.05 * min(sizes)


def test_lines_of_one_id_and_of_none(spark):
    text = "a line of twenty code points\nand another line of that length"
    got = linededup.dedup_lines(docs(spark, [(1, text + "\nx", "en", "s"), (1, text + "\ny", "en", "s"), (None, text + "\nz", "en", "s"), (None, text + "\nw", "en", "s")])).collect()
    assert sum(r["n_removed"] for r in got) == 6 and sorted(r["n_removed"] for r in got if r["doc_id"] == 1) == [0, 2] and len(got) == 4


def test_line_dedup_of_long_texts(spark):
    text = "\n".join(f"line number {i} of a long text" for i in range(50_000))
    got = {r["doc_id"]: r for r in linededup.dedup_lines(docs(spark, [(1, text, "en", "s"), (2, text + "\nnew", "en", "s")])).collect()}
    assert got[1]["text"] == text and got[2]["text"] == "new" and got[2]["n_removed"] == 50_000


def test_letters_of_other_scripts(spark):
    rng = random.Random(3)
    letters = {"zh": "的一是不了人我在有他这为之大来以个中上们到说国和地也子时道出而要于就下得可你年生", "ja": "のにはをたがでてとしれさあるいするからなこんもよりだそうまど日本人大年会国学生時行", "ko": "가나다라마바사아자차카타파하은는이를에서의로와과도만한국사람말때일년시간것들수있없되하고"}
    rows = [(i, "".join(rng.choice(letters[lang]) for _ in range(rng.randrange(8, 30))), lang, "s") for i, lang in enumerate(["zh", "ja", "ko"] * 300)]
    d = docs(spark, rows)
    got = langid.identify(d, vocabulary_file(PIECES)).join(d.select("doc_id", "lang"), "doc_id").where("held_out").collect()
    assert sum(r["lang"] == r["lang_pred"] for r in got) > 0.95 * len(got) > 100
    marks = [("हिन्दी", 1), ("\u0301\u0302", 0)]
    assert [bool(re.search(r"[^\W\d_]", t)) for t, _ in marks] == [bool(v) for _, v in marks]
    und = {r["doc_id"]: r["lang_pred"] for r in langid.identify(docs(spark, rows + [(5000, "\u0301\u0302", None, "s")]), vocabulary_file(PIECES)).where("doc_id = 5000").collect()}
    assert und == {5000: "und"}


def test_random_letters_have_no_language(spark):
    rng = random.Random(1)
    d = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    junk = [(10**7 + i, " ".join("".join(rng.choice("qxzjkvwy") for _ in range(rng.randrange(4, 9))) for _ in range(40)), None, "s") for i in range(20)]
    kept = langid.with_language(d.select("doc_id", "text", "lang", "source", "n_chars").union(docs(spark, junk)), vocabulary_file(PIECES))
    lost = d.where(F.col("text").rlike(r"\p{L}")).join(kept, "doc_id", "left_anti").count()
    assert kept.where("doc_id >= 10000000").count() == 0 and lost <= d.count() // 100


BASE = {"assign": (re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A), 2, 12), "access": (re.compile("AKIA[A-Z0-9]+"), 0, 18), "hex": (re.compile("[0-9a-f]+"), 0, 16)}


def base_spans(text):
    found = [(m.start(), rank, m.end(), kind) for rank, (kind, (p, g, least)) in enumerate(BASE.items()) for m in p.finditer(text) if len(m.group(g)) >= least]
    return ",".join(f"{k}:{a}:{b}" for a, _, b, k in sorted(found))


def test_base_secrets_like_python(spark):
    d = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text")
    rng = random.Random(2)
    parts = ["password", "API_KEY", "apikey", "=", ":", " ", "'", '"', "abcdefghijklm", "AKIA", "ABCDEFGHIJKLMNOPQR", "0123456789abcdef", "é", "😀", ".", "token", "==", "\n", "secret"]
    made = [(10**7 + i, "".join(rng.choice(parts) for _ in range(rng.randrange(60)))) for i in range(300)] + [(10**7 + 900, None), (10**7 + 901, " ".join(hashlib.sha256(str(i).encode()).hexdigest() + " token=abcdefghijklmnop" for i in range(1500)))]
    every = d.union(spark.createDataFrame(made, "doc_id long, text string"))
    got = {r["doc_id"]: r for r in secrets.digests(every).collect()}
    for r in every.collect():
        want = base_spans(r["text"] or "")
        assert got[r["doc_id"]]["base_sha256"] == hashlib.sha256(want.encode()).hexdigest()
        assert set(filter(None, want.split(","))) <= set(got[r["doc_id"]]["spans"].split(",")) and got[r["doc_id"]]["n_hex"] == want.count("hex:")


def test_planted_tokens_are_found_and_identifiers_left(spark):
    rng = random.Random(1)
    d = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text")
    tokens = ["".join(rng.choice(al) for _ in range(rng.choice([20, 24, 32, 40]))) for al in (string.ascii_letters + string.digits, string.ascii_letters + string.digits + "+/", string.ascii_letters) for _ in range(100)]
    words = [w for r in d.limit(300).collect() for w in re.findall("[a-z]{3,12}", r["text"] or "")]
    names = [f(["".join(rng.choice(words)) for _ in range(5)]) for i in range(300) for f in ((("_".join), ("-".join), (lambda a: a[0] + "".join(w.title() for w in a[1:])), ("/".join), (lambda a: "_".join(a).upper()))[i % 5],)]
    made = [(10**7 + i, f"the value {t} stands here") for i, t in enumerate(tokens + names)]
    got = {r["doc_id"]: "markov" in r["spans"] for r in secrets.digests(d.union(spark.createDataFrame(made, "doc_id long, text string"))).where("doc_id >= 10000000").collect()}
    hits = [got[10**7 + i] for i in range(len(made))]
    assert sum(hits[:300]) >= 0.97 * 300 and sum(hits[300:]) <= 0.02 * 300


def test_schedule_keeps_every_prefix_near_the_targets(spark):
    rng = random.Random(6)
    d = docs(spark, [(i, "w " * rng.randrange(1, 30), "en", rng.choice("aabc")) for i in range(1500)])
    m = mixing.mix(d)
    blocks = [r["sid"] for r in m.slots.orderBy("position").collect()]
    share = {s: blocks.count(s) / len(blocks) for s in set(blocks)}
    for upto in range(50, len(blocks), 97):
        assert all(abs(blocks[:upto].count(s) - share[s] * upto) < 12 for s in share)
    rows = mixing.taken(d).collect()
    assert all((r["first_slot"] is not None) == (r["taken"] > 0) == (r["n_slots"] > 0) for r in rows)
    first = {r["doc_id"]: r["first_slot"] for r in rows}
    order, seen = [r["doc_id"] for r in mixing.mixed(d).collect()], set()
    firsts = [first[i] for i in order if not (i in seen or seen.add(i))]
    assert firsts == sorted(firsts)


def test_null_ids_and_null_sources_in_a_mix(spark):
    d = docs(spark, [(None, f"{'w ' * (i % 7)}x{i}", "en", None if i % 2 else "a") for i in range(60)])
    rows = mixing.taken(d).collect()
    by = {}
    for r in rows:
        by.setdefault((r["source_size"], r["target"]), []).append(r["taken"])
    assert len(rows) == 60 and all(abs(sum(v) - t) < 1 for (_, t), v in by.items()) and sum(r["target"] is None for r in rows) == 0


def clashing(spark):
    return odd(spark).withColumns({c: F.lit(1) for c in ("h", "fp", "did", "node", "size", "bucket", "leaf", "own", "parcel", "gone", "w")})


def test_clashing_columns(spark):
    d, path = clashing(spark), vocabulary_file(PIECES)
    labels = spark.createDataFrame([(5, 1, 0), (6, 0, 0)], "doc_id long, quality int, toxic int")
    n = d.count()
    for out in (simhash.near_duplicates(d), langid.identify(d, path), bpe.digests(d, vocabulary_file(BYTES)), secrets.digests(d), mixing.taken(d), sharding.shard(d), quality.score(d, labels), linededup.dedup_lines(d)):
        assert out.count() == n
    assert simhash.deduplicate(d).columns == mixing.mixed(d).columns == langid.with_language(d, path).columns == d.columns
    v = vectors(spark, [(i, [1.0, float(i)], 0) for i in range(30)]).withColumns({c: F.lit(1) for c in ("d", "cid", "leaf", "cell", "own", "salt")})
    assert vector_dedup.near_duplicates(v).count() == 30 and ann.search(v, F.col("vec_id") == 0).count() == 10


def plain_mix(rows):
    """(doc_id, text) as often as the mix takes it."""
    size = lambda t: len(re.findall(r"[^\x20\x09-\x0D]+", t or ""))
    sources = sorted({s for _, _, s in rows}, key=lambda s: (s is None, s))
    total, weight = {s: sum(size(t) for _, t, x in rows if x == s) for s in sources}, {s: i % 3 + 1 for i, s in enumerate(sources)}
    target, open_ = {}, set(sources)
    while True:
        left, w = sum(total.values()) - sum(target.values()), sum(weight[s] for s in open_)
        full = {s for s in open_ if left * weight[s] / w > 3 * total[s]}
        if not full:
            break
        target |= {s: 3 * total[s] for s in full}
        open_ -= full
    target |= {s: left * weight[s] / w for s in open_}
    out = []
    for s in sources:
        words, at = int(target[s]), 0
        for i, t, _ in sorted((r for r in rows if r[2] == s), key=lambda r: (hashlib.md5(str(r[0]).encode()).hexdigest(), size(r[1]))):
            taken = words // total[s] * size(t) + max(0, min(size(t), words % total[s] - at)) if total[s] else 0
            at += size(t)
            out += [(i, t)] * (int(taken / size(t) + 0.5) if size(t) else 0)
    return out


@pytest.mark.parametrize("seed", range(2))
def test_pipeline_like_plain_code(spark, tmp_path, seed):
    rng = random.Random(seed)
    vocabulary = {"en": "the of and to in is that it was for on are as with his they at be this from".split(), "fr": "le la les des une est dans pour que qui sur avec pas sont nous vous cette mais".split()}
    sentence = lambda lang, n: " ".join(rng.choice(vocabulary[lang]) for _ in range(n))
    shared = [sentence("en", 14) for _ in range(3)]
    rows = []
    for i in range(60):
        lang = rng.choice(["en", "fr"])
        lines = [sentence(lang, rng.randrange(3, 16)) for _ in range(rng.randrange(1, 6))] + ([rng.choice(shared)] if rng.random() < 0.4 else [])
        rows.append((i, "\n".join(lines), lang, rng.choice(["a", "a", "a", "b", None])))
    for i in range(60, 80):  # near copies of long texts, with a word changed
        w = rows[rng.randrange(20)][1].replace("\n", " ").split()
        w[rng.randrange(len(w))] = "changed"
        rows.append((i, " ".join(w), "en", "b"))
    rows += [(80, None, "en", "a"), (81, "123 456", "en", "a"), (82, "", "en", "b")]
    docs(spark, rows).write.parquet(str(tmp_path / "documents.parquet"))
    spoken = [r for r in rows if re.search(r"[^\W\d_]", r[1] or "")]
    texts = plain_dedup([t for _, t, _, _ in spoken])
    source = {i: s for i, _, _, s in rows}
    near = plain_near([(r[0], t) for r, t in zip(spoken, texts)])
    want = plain_mix([(i, t, source[i]) for i, t in near])
    got = corpus_pipeline.run(spark, str(tmp_path))
    assert rows_of(got, "doc_id", "text") == sorted(want, key=repr) and len(want) > 30
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(vocabulary_file(BYTES))
    ids = next(c for c, t in got.dtypes if t.startswith("array"))
    assert all(list(r[ids]) == library.encode(r["text"], add_special_tokens=False).ids for r in got.limit(20).collect())


def test_registered_sql_holds_the_schedule():
    from spreadsample.llm import queries

    assert json.dumps(sorted(queries.oracle_sql())) == json.dumps(["op4_line_dedup", "op7_embedding_near_dedup", "op8_mix_sources"]) and "first_slot" in queries.OP8_SQL
