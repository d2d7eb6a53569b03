"""Line dedup: repeated runs of lines, found by prefix doubling over line ids; later copies are deleted.

The corpus is read as sequences of line ids, one per document, that end at the document's end. Ranks of blocks of 1, 2,
4, ... lines come from sorting pairs of ranks of half the length, as in a suffix array: equal blocks have equal ranks, ranks follow the
order of the sorted blocks, and only repeated blocks go on to the next round. Two overlapping blocks name a window of
any length, so suffixes that share a window's name are one longest-common-prefix interval of at least that depth.

A repeated run counts if its lines, each with its line break, hold at least min_chars code points. It is the
union of the shortest windows of that weight that start or end at one of its lines, and a window of weight min_chars has at most
min_chars lines, so the doubling is bounded although runs are not. Everything is DataFrame operations.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from spreadsample.llm.common import durable

MIN_CHARS = 20
PLACE = ["did", "th"]


def _with_place(docs: DataFrame) -> DataFrame:
    """did orders documents (null ids last), th tells rows of one id apart."""
    return docs.withColumns({"did": F.coalesce(F.col("doc_id").cast("long"), F.lit(2**63 - 1)), "th": F.xxhash64("text")})


def line_rows(docs: DataFrame) -> DataFrame:
    """(did, th, n, w, h1, h2): every line of docs by its place, weight and 128-bit hash."""
    cut = _with_place(docs.select("doc_id", F.col("text").cast("string"))).select("did", "th", F.posexplode(F.split("text", "\n", -1)).alias("n", "line"))
    return cut.select("did", "th", "n", (F.length("line") + 1).alias("w"), F.xxhash64("line").alias("h1"), F.xxhash64(F.lit(1), "line").alias("h2"))


def _ranked(pairs: DataFrame, a: str, b: str) -> DataFrame:
    """pairs with a column r that grows with (a, b): range partitions in sorted order, numbered in that order."""
    return durable(pairs.repartitionByRange(a, b).sortWithinPartitions(a, b).withColumn("r", F.monotonically_increasing_id()))


def repeated_lines(lines: DataFrame) -> DataFrame:
    """The lines that occur more than once, with their rank r and the place of their first occurrence."""
    groups = lines.groupBy("h1", "h2").agg(F.count("*").alias("c"), F.min(F.struct("did", "th", "n")).alias("first")).where("c > 1").drop("c")
    return durable(lines.join(_ranked(groups, "h1", "h2"), ["h1", "h2"]).select("did", "th", "n", "w", "r", "first"))


def doubled(ranks: DataFrame, step: int) -> DataFrame:
    """Ranks (did, th, n, r) of repeated blocks of 2 * step lines, from those of step lines."""
    ahead = ranks.select("did", "th", (F.col("n") - step).alias("n"), F.col("r").alias("b"))
    pairs = durable(ranks.select("did", "th", "n", F.col("r").alias("a")).join(ahead, ["did", "th", "n"]))
    groups = pairs.groupBy("a", "b").agg(F.count("*").alias("c")).where("c > 1").select("a", "b")
    found = pairs.join(_ranked(groups, "a", "b"), ["a", "b"])
    return durable(found.select("did", "th", "n", "r"))


def _shortest(weights: Column, least: int) -> Column:
    """The length of the shortest prefix of an array of weights that sums to least, or null."""
    start = F.struct(F.lit(0).cast("long").alias("sum"), F.lit(0).alias("n"))
    end = F.aggregate(weights, start, lambda s, w: F.struct((s["sum"] + F.when(s["sum"] < least, w).otherwise(0)).alias("sum"), (s["n"] + F.when(s["sum"] < least, 1).otherwise(0)).alias("n")))
    return F.when(end["sum"] >= least, end["n"])


def short_windows(active: DataFrame, least: int) -> DataFrame:
    """(did, th, s, len): shortest windows of several repeated lines that start or end at a line lighter than least."""
    run = Window.partitionBy(*PLACE).orderBy("n")
    runs = active.select("did", "th", "n", "w").withColumn("run", F.col("n") - F.row_number().over(run))
    near = Window.partitionBy(*PLACE, "run").orderBy("n")
    sides = runs.withColumns({"after": F.collect_list("w").over(near.rowsBetween(0, least - 1)), "before": F.reverse(F.collect_list("w").over(near.rowsBetween(1 - least, 0)))}).where(F.col("w") < least)
    lengths = sides.select("did", "th", "n", _shortest(F.col("after"), least).alias("f"), _shortest(F.col("before"), least).alias("b"))
    both = lengths.select("did", "th", F.explode(F.array(F.struct(F.col("n").alias("s"), F.col("f").alias("len")), F.struct((F.col("n") - F.col("b") + 1).alias("s"), F.col("b").alias("len")))).alias("x"))
    return both.select("did", "th", "x.s", "x.len").where("len IS NOT NULL").distinct()


def later_lines(docs: DataFrame, min_chars: int = MIN_CHARS) -> DataFrame:
    """(did, th, n), distinct: the lines inside later copies of repeated runs of at least min_chars."""
    active = repeated_lines(line_rows(docs))
    place = lambda s: F.struct("did", "th", F.col(s).alias("n"))
    found = active.where((F.col("w") >= min_chars) & (place("n") > F.col("first"))).select("did", "th", "n")
    once = active.dropDuplicates(["did", "th", "n"])  # rows that repeat both id and text stand at one place
    windows = durable(short_windows(once, min_chars))
    longest = windows.agg(F.max("len")).first()[0] or 0
    ranks, step = once.select("did", "th", "n", "r"), 1
    while 2 * step <= longest:
        ranks, step = doubled(ranks, step), 2 * step
        here = windows.where((F.col("len") >= step) & (F.col("len") < 2 * step))
        head = ranks.select("did", "th", F.col("n").alias("s"), F.col("r").alias("head"))
        tail = ranks.select("did", "th", F.col("n").alias("t"), F.col("r").alias("tail"))
        named = here.withColumn("t", F.col("s") + F.col("len") - step).join(head, [*PLACE, "s"]).join(tail, [*PLACE, "t"])
        first = named.groupBy("len", "head", "tail").agg(F.count("*").alias("c"), F.min(place("s")).alias("first")).where("c > 1").drop("c")
        late = named.join(first, ["len", "head", "tail"]).where(place("s") > F.col("first"))
        found = found.union(late.select("did", "th", F.explode(F.sequence("s", F.col("s") + F.col("len") - 1)).alias("n")))
    return found.distinct()


def _without(lines: Column, gone: Column) -> Column:
    """An array without the elements at distinct positions (from 0): the slices between one removed element and the next, so the work grows
    with the array, not with its product with the removals."""

    def between(x: Column) -> Column:
        cuts, all_ = x["cuts"], x["lines"]
        return F.flatten(F.transform(F.sequence(F.lit(1), F.size(cuts) - 1), lambda k: F.slice(all_, F.get(cuts, k - 1) + 2, F.get(cuts, k) - F.get(cuts, k - 1) - 1)))

    ends = lambda x: F.concat(F.array(F.lit(-1)), F.array_sort(x["gone"]), F.array(F.size(x["lines"])))
    held = F.transform(F.array(F.struct(lines.alias("lines"), gone.alias("gone"))), lambda x: F.struct(x["lines"].alias("lines"), ends(x).alias("cuts")))
    return F.flatten(F.transform(held, between))


def dedup_lines(docs: DataFrame, min_chars: int = MIN_CHARS) -> DataFrame:
    """docs (doc_id, text and any others, kept) with later copies of repeated line runs deleted from text, and n_lines and n_removed.

    Documents are in the order of doc_id, null ids last, rows of one id (or of none) in the order of a hash of their text, lines in
    their own order; the first copy of every line stays. Only rows that repeat both id and text stand at one place: none of them is a later
    copy of another. Blank lines go only as part of a run. A null text stays null with 0 lines; a text whose lines all go is
    left empty. No rows are dropped; an empty table gives none."""
    own = {c: f"in_{i}_{c}" for i, c in enumerate(docs.columns) if c not in ("doc_id", "text")}
    placed = _with_place(docs.withColumnsRenamed(own).withColumn("text", F.col("text").cast("string")))
    gone = later_lines(docs, min_chars).groupBy(*PLACE).agg(F.collect_list("n").alias("gone"))
    lines = F.split("text", "\n", -1)
    out = placed.join(gone, PLACE, "left").withColumns({"n_lines": F.when(F.col("text").isNull(), 0).otherwise(F.size(lines)), "n_removed": F.coalesce(F.size("gone"), F.lit(0)), "text": F.when(F.col("gone").isNull(), F.col("text")).otherwise(F.array_join(_without(lines, F.col("gone")), "\n"))})
    count = lambda c: F.greatest(F.lit(0), F.col(c)).cast("long").alias(c)
    return out.select(*[F.col(own[c]).alias(c) if c in own else c for c in docs.columns if c not in ("n_lines", "n_removed")], count("n_lines"), count("n_removed"))
