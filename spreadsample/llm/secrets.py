"""Secret scans: patterns of known forms, and Markov models that tell random strings from ordinary identifiers.

Two character Markov models are trained from labelled samples: random strings (known forms found in the corpus, and strings
drawn from a hash) and ordinary identifiers (words of the corpus, alone and joined). A token whose log-likelihood ratio per transition is
high is an added span. Spans come from whole texts, in code points, by DataFrame functions alone: a match is
extracted together with the gap before it, and gaps and matches add up to places.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Kinds in their order, patterns (Java syntax, no capturing group but the value of the first) and least lengths.
ASSIGN = r"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS, HEX = r"AKIA[A-Z0-9]+", r"[0-9a-f]+"
LEAST = {"assign": 12, "access": 18, "hex": 16, "markov": 20}
KINDS = ("assign", "access", "hex", "markov")
ALPHABET = "abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789+/_=-"
#: A whole token; the ratio that it must reach, higher where it has no digit, as most identifiers have none.
CANDIDATE = r"(?<![A-Za-z0-9+/_=-])[A-Za-z0-9+/_=-]{20,}"
RANDOM_SAMPLE, ORDINARY_DOCS, PER_STEP, PER_STEP_LETTERS = 2048, 2000, 0.9, 1.1
#: Elements of an array that a nested function goes over at once.
CHUNK = 128
SPAN, TOKENS = "array<struct<start:int,rank:int,end:int>>", "array<struct<start:int,rank:int,end:int,token:string>>"


def chunked(items: Column) -> Column:
    """An array in pieces of CHUNK elements."""
    return F.when(F.size(items) > 0, F.transform(F.sequence(F.lit(0), F.floor((F.size(items) - 1) / CHUNK).cast("int")), lambda c: F.slice(items, c * CHUNK + 1, F.lit(CHUNK)))).otherwise(F.array())


def matches(text: Column, pattern: str, rank: int, group: int | None = None, least: int = 0, kind: str = SPAN) -> Column:
    """Spans of the leftmost non-overlapping matches whose group (or whole) has at least `least` code points; of kind TOKENS with what they hold.

    One pass extracts each match with the gap before it; the match itself, and its value, are found again in that short
    string. Places are sums of lengths: of the chunks before, then of the elements before in the chunk, so the work does not grow with
    the square of the matches."""
    lazy = F.lit(rf"(?s)\G(.*?)(?:{pattern})")  # \G: after the last match, one pass to the end and no new starts
    extract = lambda z, g: F.call_function("regexp_extract", z, F.lit(pattern), F.lit(g))
    found = F.transform(F.regexp_extract_all(text, lazy, F.lit(0)), lambda z: F.struct(F.length(z).alias("all"), extract(z, 0).alias("z")))
    value = lambda x: F.length(extract(x["z"], group)) if group else F.length(x["z"])
    sized = F.transform(found, lambda x: F.struct((x["all"] - F.length(x["z"])).alias("gap"), F.length(x["z"]).alias("hit"), value(x).alias("value"), x["z"].alias("z")))
    length = lambda items: F.aggregate(items, F.lit(0), lambda s, x: s + x["gap"] + x["hit"])

    def placed(chunks: Column) -> Column:
        """chunks with the place at which each begins."""
        totals = F.transform(chunks, length)
        return F.transform(F.array(F.struct(chunks.alias("chunks"), totals.alias("totals"))), lambda h: F.transform(h["chunks"], lambda c, i: F.struct(c.alias("items"), F.aggregate(F.slice(h["totals"], F.lit(1), i), F.lit(0), lambda s, x: s + x).alias("at"))))

    def spans(chunk: Column) -> Column:
        start = lambda x, i: chunk["at"] + length(F.slice(chunk["items"], F.lit(1), i)) + x["gap"]
        both = F.transform(chunk["items"], lambda x, i: F.struct(start(x, i).alias("start"), x["hit"].alias("hit"), x["value"].alias("value"), *([x["z"].alias("token")] if kind == TOKENS else [])))
        return F.transform(F.filter(both, lambda x: x["value"] >= least), lambda x: F.struct(x["start"].alias("start"), F.lit(rank).alias("rank"), (x["start"] + x["hit"]).alias("end"), *([x["token"].alias("token")] if kind == TOKENS else [])))

    held = F.transform(F.array(sized), chunked)  # an array of one, so that what it holds is evaluated once
    all_spans = F.flatten(F.transform(F.flatten(F.transform(held, placed)), lambda ones: F.flatten(F.transform(ones, spans))))
    return F.when(text.rlike(pattern), all_spans).otherwise(F.array()).cast(kind)


def base_pattern(kind: str) -> str:
    """A run of hexadecimal digits, and all after AKIA, is one match: a least length in the pattern drops what a filter would."""
    return {"assign": ASSIGN, "access": ACCESS[:-1] + "{%d,}" % (LEAST["access"] - 4), "hex": HEX[:-1] + "{%d,}" % LEAST["hex"]}[kind]


def base_spans(text: Column) -> list[Column]:
    return [matches(text, ASSIGN, 0, 1, LEAST["assign"]), matches(text, base_pattern("access"), 1), matches(text, base_pattern("hex"), 2)]


def transitions(samples: DataFrame) -> DataFrame:
    """(label, a, b, n): how often a character of the alphabet follows another in the labelled samples (label, token)."""
    n = F.length("token") - 1
    pairs = samples.where(n > 0).select("label", "token", F.explode(F.sequence(F.lit(1), n)).alias("i"))
    code = lambda i: F.expr(f"locate(substring(token, {i}, 1), '{ALPHABET}')")
    return pairs.select("label", code("i").alias("a"), code("i + 1").alias("b")).where("a > 0 AND b > 0").groupBy("label", "a", "b").agg(F.count("*").alias("n"))


def labelled_samples(docs: DataFrame, random: int = RANDOM_SAMPLE, ordinary: int = ORDINARY_DOCS) -> DataFrame:
    """(label, token): 1 for random strings, 0 for ordinary identifiers; bounded by the two parameters.

    Random: base64 and alphanumeric strings of a hash, and the values of known forms in the sampled documents. Ordinary: words of
    about `ordinary` documents (chosen by a hash of the id) in the shapes of identifiers."""
    spark = docs.sparkSession
    raw = spark.range(random).select(F.sha2(F.concat(F.lit("sample"), F.col("id").cast("string")), 256).alias("x"))
    strings = raw.select(F.explode(F.array(F.base64(F.unhex("x")), F.substring(F.regexp_replace(F.base64(F.unhex("x")), "[+/=]", ""), 1, 32), F.upper(F.substring(F.conv(F.substring("x", 1, 15), 16, 36), 1, 12)))).alias("token"))
    share = F.lit(1_000_000 * ordinary / max(1, docs.count()))
    some = docs.where(F.col("doc_id").isNotNull() & F.col("text").isNotNull()).where(F.pmod(F.xxhash64("doc_id", F.lit(5)), F.lit(1_000_000)) < share).select("text")
    values = some.select(F.explode(F.regexp_extract_all("text", F.lit(ASSIGN), F.lit(1))).alias("token")).where(F.length("token") >= LEAST["assign"])
    words = F.filter(F.split(F.lower("text"), "[^a-z]+"), lambda w: F.length(w).between(2, 24))
    joined = some.select(F.posexplode(words).alias("i", "w")).select("w", F.lead("w").over(Window.partitionBy("i").orderBy("w")).alias("w2")).where("w2 IS NOT NULL")
    ordinary_tokens = joined.select(F.explode(F.array(F.concat_ws("_", "w", "w2"), F.concat("w", F.initcap("w2")), F.concat_ws("-", "w", "w2"), F.upper(F.concat_ws("_", "w", "w2")), F.initcap("w"), F.concat("w", F.lit("="), "w2"), F.concat_ws("/", "w", "w2"), F.concat("w", F.length("w2").cast("string")))).alias("token"))
    return strings.union(values).select(F.lit(1).alias("label"), "token").union(ordinary_tokens.select(F.lit(0), "token"))


def trained(docs: DataFrame, **options) -> list[float]:
    """Log-likelihood ratios of all pairs of alphabet characters, row by row: half a count is added to every pair."""
    size = len(ALPHABET)
    counts = {0: [[0.5] * size for _ in range(size)], 1: [[0.5] * size for _ in range(size)]}
    for label, a, b, n in transitions(labelled_samples(docs, **options)).collect():  # at most 2 * size * size rows
        counts[label][a - 1][b - 1] += n
    return [round(math.log(counts[1][a][b] / sum(counts[1][a])) - math.log(counts[0][a][b] / sum(counts[0][a])), 4) for a in range(size) for b in range(size)]


def ratio_per_step(token: Column, ratios: list[float]) -> Column:
    """The mean log-likelihood ratio over the token's transitions."""
    table = F.split(F.lit(",".join(map(str, ratios))), ",").cast("array<double>")
    codes = F.transform(F.split(token, ""), lambda c: F.call_function("instr", F.lit(ALPHABET), c))
    codes = F.filter(codes, lambda c: c > 0)
    end = F.aggregate(codes, F.struct(F.lit(0).alias("last"), F.lit(0.0).alias("sum")), lambda s, c: F.struct(c.alias("last"), (s["sum"] + F.when(s["last"] == 0, 0.0).otherwise(F.element_at(table, (s["last"] - 1) * len(ALPHABET) + c))).alias("sum")))
    return end["sum"] / F.greatest(F.lit(1), F.length(token) - 1)


def joined_spans(spans: Column) -> Column:
    """kind:start:end of spans in the order of start, then kind, comma-joined."""
    kind = lambda x: F.element_at(F.array(*[F.lit(k) for k in KINDS]), x["rank"] + 1)
    return F.array_join(F.transform(F.array_sort(spans), lambda x: F.concat_ws(":", kind(x), x["start"].cast("string"), x["end"].cast("string"))), ",")


def scan(docs: DataFrame, per_step: float = PER_STEP, per_letters: float = PER_STEP_LETTERS, **options) -> DataFrame:
    """(doc_id, assign, access, hex, markov): the spans of each kind (start, rank, end) in every row of docs (doc_id, text).

    A null text is an empty one and has no spans. Markov spans are runs of at least 20 characters of base64 and identifiers that meet
    no other span and reach per_step, or per_letters if they hold no digit; repeated rows are scanned as they come, an empty table gives no
    rows."""
    ratios = trained(docs, **options)
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    found = docs.select("doc_id", text.alias("text")).select("doc_id", "text", *[c.alias(k) for k, c in zip(KINDS, base_spans(F.col("text")))], matches(F.col("text"), CANDIDATE, 3, kind=TOKENS).alias("likely")).drop("text")
    found = found.withColumn("near", F.transform(chunked(F.col("assign")), lambda c: F.struct(c.alias("items"), c[0]["start"].alias("start"), F.element_at(c, -1)["end"].alias("end"))))
    token = lambda x: x["token"]
    meets = lambda a, b: (a["start"] < b["end"]) & (b["start"] < a["end"])
    # access and hex spans lie inside a token, assignments may begin before it: those are looked for chunk by chunk
    clash = lambda x, t: t.rlike(base_pattern("access")) | t.rlike(base_pattern("hex")) | F.exists("near", lambda c: meets(c, x) & F.exists(c["items"], lambda b: meets(b, x)))
    random = lambda x: ~clash(x, token(x)) & (ratio_per_step(token(x), ratios) >= F.when(token(x).rlike("[0-9]"), per_step).otherwise(per_letters))
    return found.select("doc_id", "assign", "access", "hex", F.transform(F.filter("likely", random), lambda x: F.struct(x["start"].alias("start"), x["rank"].alias("rank"), x["end"].alias("end"))).cast(SPAN).alias("markov"))


def digests(docs: DataFrame, **options) -> DataFrame:
    """(doc_id, n_assign, n_access, n_hex, base_sha256, spans) from scan."""
    base = F.concat("assign", "access", "hex")
    return scan(docs, **options).select("doc_id", *[F.size(k).cast("long").alias(f"n_{k}") for k in KINDS[:3]], F.sha2(joined_spans(base), 256).alias("base_sha256"), joined_spans(F.concat(base, "markov")).alias("spans"))
