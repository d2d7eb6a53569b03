"""Mixing sources to target weights by a low-discrepancy schedule of equal-token blocks.

Multiples of the golden ratio, taken modulo one, go through the cumulated targets and give every slot a source; a source's
slots are ranked, and its k-th slot takes the k-th block of its stream: its documents in the order of a hash, end to end, again
from the start when it is used up. The schedule gives every document its place in the mix; any prefix of the mix holds the sources
near their targets. A source takes exactly its target in whole words: the last block is cut there, and
blocks that the sequence left without a slot follow at the end. Prefix sums and ranks go in two steps
(buckets of the hash, chunks of slots), so a source that holds most rows is still many tasks. DataFrame operations only.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from spreadsample.llm.common import WORD, durable

MOST_REPEATS, PERIOD_BITS, STEP, CHUNK_BITS, CELL_BITS = 3, 31, 1327217885, 16, 10
SLOTS, LARGEST_BLOCK, BUCKET_ROWS = 1 << 16, 4096, 100_000


def words_in(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def sized(docs: DataFrame) -> DataFrame:
    """(doc_id, source, size, h): words of every text, and the hash that orders documents: that of the id, where it is null that of the text."""
    key = F.coalesce(F.col("doc_id").cast("string"), F.concat(F.lit("null:"), F.md5(F.coalesce(F.col("text").cast("string"), F.lit("")))))
    return docs.select("doc_id", F.col("source").cast("string"), words_in(F.col("text")).alias("size"), F.md5(key).alias("h"))


def targets(sizes: DataFrame, weights: tuple[int, ...] = (1, 2, 3), repeats: int = MOST_REPEATS) -> DataFrame:
    """(source, sid, source_size, target), a row per source: weights repeat over the sources by code point, null last, and
    share all words; no target is above repeats times its source's words, the excess is shared out again by weight. Sources of equal
    words and weight are told apart by their order; an empty table has no rows, and sources without words have target 0."""
    per = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    per = per.withColumn("sid", F.row_number().over(by_name) - 1)
    per = per.withColumn("w", F.element_at(F.array(*[F.lit(w) for w in weights]), F.col("sid") % len(weights) + 1))
    per = per.withColumn("cap", F.col("source_size") * repeats)
    filled = Window.orderBy(F.col("cap") / F.col("w"), "sid")
    every = Window.partitionBy()
    per = per.withColumns({"before": F.sum("cap").over(filled.rowsBetween(Window.unboundedPreceding, 0)) - F.col("cap"), "left": F.sum("w").over(filled.rowsBetween(0, Window.unboundedFollowing)), "total": F.sum("source_size").over(every)})
    level = (F.col("total") - F.col("before")) / F.col("left")
    per = per.withColumn("level", F.when(level <= F.col("cap") / F.col("w"), level))
    per = per.withColumn("level", F.min_by("level", F.when(F.col("level").isNotNull(), F.struct(F.col("cap") / F.col("w"), "sid"))).over(every))
    return per.select("source", "sid", "source_size", F.least(F.col("cap").cast("double"), F.col("w") * F.col("level")).alias("target"))


@dataclass
class Mix:
    docs: DataFrame  # doc_id, source, size, sid, source_size, target, start: every document with its place in its source's stream
    pieces: DataFrame  # sid, block, round, start, doc_id, size, from_word, words: what each block takes of each document
    slots: DataFrame  # sid, block, position: the schedule; the mix is the pieces by position


def schedule(plan: DataFrame, n_slots: int, block: int) -> DataFrame:
    """(sid, block, position): every block that a source needs, at the slot that the sequence gives it. Borders of the sources are
    whole numbers of the cumulated words, so there are no ties: each slot falls to one source. An empty plan, or one without
    words, has no blocks."""
    whole = 1 << PERIOD_BITS
    cum = Window.orderBy("sid")
    reach = plan.select("sid", "words", F.sum("words").over(cum).alias("upto"), F.sum("words").over(Window.partitionBy()).alias("every")).where("words > 0")
    edge = lambda c: F.expr(f"CAST({c} AS DECIMAL(27, 0)) * {whole} div CAST(every AS DECIMAL(27, 0))")
    reach = reach.select("sid", edge("(upto - words)").alias("lo"), edge("upto").alias("hi")).where("hi > lo")
    cell = PERIOD_BITS - CELL_BITS
    reach = reach.withColumn("cell", F.explode(F.sequence(F.shiftright("lo", cell), F.shiftright(F.col("hi") - 1, cell))))
    spark = plan.sparkSession
    slots = spark.range(n_slots).withColumn("u", F.pmod(F.pmod("id", F.lit(whole)) * STEP, F.lit(whole))).withColumn("cell", F.shiftright("u", cell))
    drawn = slots.join(reach, "cell").where("u >= lo AND u < hi").select("sid", "id", F.shiftright("id", CHUNK_BITS).alias("chunk"))
    per_chunk = drawn.groupBy("sid", "chunk").agg(F.count("*").alias("n"))
    earlier = per_chunk.select("sid", "chunk", (F.sum("n").over(Window.partitionBy("sid").orderBy("chunk")) - F.col("n")).alias("earlier"))
    ranked = drawn.join(earlier, ["sid", "chunk"]).select("sid", "id", (F.col("earlier") + F.row_number().over(Window.partitionBy("sid", "chunk").orderBy("id")) - 1).alias("block"))
    needed = plan.where("words > 0").select("sid", F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("words") - 1) / block).cast("long"))).alias("block"))
    return needed.join(ranked, ["sid", "block"], "left").select("sid", "block", F.coalesce("id", F.lit(n_slots) + F.col("block")).alias("position"))


def mix(docs: DataFrame, weights: tuple[int, ...] = (1, 2, 3), repeats: int = MOST_REPEATS, slots: int = SLOTS, largest_block: int = LARGEST_BLOCK) -> Mix:
    """The mix of docs (doc_id, text, source). Null texts have no words; a null source is a source of its own. Documents
    without words stay in docs and have no pieces. Repeated rows are documents of their own."""
    sizes = durable(sized(docs))
    n, total = sizes.agg(F.count("*"), F.coalesce(F.sum("size"), F.lit(0))).first()
    block = max(1, min(largest_block, total // slots))
    plan = durable(targets(sizes, weights, repeats).withColumn("words", F.floor("target").cast("long")))
    digits = max(2, min(8, len(f"{n // BUCKET_ROWS:x}") + 1))  # so that a bucket of the hash stays small; the order does not depend on it
    known = sizes.join(plan.withColumnRenamed("source", "s2"), F.col("source").eqNullSafe(F.col("s2"))).drop("s2").withColumn("bucket", F.substring("h", 1, digits))
    buckets = known.groupBy("sid", "bucket").agg(F.sum("size").alias("n"))
    before = buckets.select("sid", "bucket", (F.sum("n").over(Window.partitionBy("sid").orderBy("bucket")) - F.col("n")).alias("before"))
    order = Window.partitionBy("sid", "bucket").orderBy("h", "size").rowsBetween(Window.unboundedPreceding, 0)
    placed = durable(known.join(before, ["sid", "bucket"]).withColumn("start", F.col("before") + F.sum("size").over(order) - F.col("size")).select("doc_id", "source", "size", "sid", "source_size", "target", "words", "start"))
    rounds = F.sequence(F.lit(0).cast("long"), F.floor((F.col("words") - 1) / F.col("source_size")).cast("long"))
    uses = placed.where("size > 0 AND words > 0").withColumn("round", F.explode(rounds)).withColumn("at", F.col("round") * F.col("source_size") + F.col("start")).withColumn("end", F.least(F.col("at") + F.col("size"), "words")).where("end > at")
    cut = uses.withColumn("block", F.explode(F.sequence(F.floor(F.col("at") / block).cast("long"), F.floor((F.col("end") - 1) / block).cast("long"))))
    first, last = F.greatest("at", F.col("block") * block), F.least("end", (F.col("block") + 1) * block)
    pieces = cut.select("sid", "block", "round", "start", "doc_id", "source", "size", "source_size", "target", (first - F.col("at")).alias("from_word"), (last - first).alias("words"))
    return Mix(placed, pieces, schedule(plan, total // block + 1, block))


def mixed_blocks(m: Mix) -> DataFrame:
    """(position, sid, block, doc_id, from_word, words): the mix itself, to be read by position."""
    return m.pieces.join(m.slots, ["sid", "block"]).select("position", "sid", "block", "start", "doc_id", "from_word", "words")


def taken(docs: DataFrame, **options) -> DataFrame:
    """(doc_id, size, source_size, target, taken, first_slot, n_slots) for every row of docs: the words that the mix takes of it, repeats
    counted, the slot of the schedule at which it comes first (null if it is not taken), and the slots that it has words in."""
    m = mix(docs, **options)
    used = m.pieces.join(m.slots, ["sid", "block"]).groupBy("sid", "start", "doc_id").agg(F.sum("words").alias("taken"), F.min("position").alias("first_slot"), F.count("*").alias("n_slots"))
    some = m.docs.where("size > 0").join(used.drop("doc_id"), ["sid", "start"], "left")
    none = m.docs.where("size = 0").withColumns({"taken": F.lit(0), "first_slot": F.lit(None).cast("long"), "n_slots": F.lit(0)})
    cols = ["doc_id", "size", "source_size", "target", F.coalesce("taken", F.lit(0)).cast("long").alias("taken"), "first_slot", F.coalesce("n_slots", F.lit(0)).cast("long").alias("n_slots")]
    return some.select(*cols).union(none.select(*cols))


def mixed(docs: DataFrame, **options) -> DataFrame:
    """Rows of docs (doc_id, text, source and any others, kept), each as often as the mix takes it, to the nearest whole time, in the
    order of the schedule: a row's first use stands at its first slot, its second at that of the second round, and so on; ties
    (documents of one block) go by the hash of the id. Only a source's last document is taken in part. Documents without words are never
    taken. Rows that repeat an id and size share evenly what the mix takes of them, at the first of their slots."""
    m = mix(docs, **options)
    key = [F.col("doc_id").alias("mix_id"), F.col("size").alias("mix_size")]
    rounds = m.pieces.join(m.slots, ["sid", "block"]).groupBy(*key, "round").agg(F.sum("words").alias("w"), F.min("position").alias("position"))
    rows = m.docs.groupBy(*key).agg(F.count("*").alias("mix_rows"))
    places = rounds.groupBy("mix_id", "mix_size").agg(F.sum("w").alias("mix_taken"), F.array_sort(F.collect_list(F.struct("round", "position"))).alias("mix_places"))  # at most a round for each repeat
    per_id = places.join(rows.withColumnsRenamed({"mix_id": "i2", "mix_size": "s2"}), F.col("mix_id").eqNullSafe(F.col("i2")) & (F.col("mix_size") == F.col("s2"))).drop("i2", "s2")
    names = [f"in_{i}" for i in range(len(docs.columns))]
    place = {c: names[i] for i, c in enumerate(docs.columns)}
    known = docs.toDF(*names).withColumn("own_size", words_in(F.col(place["text"])))
    times = F.floor(F.col("mix_taken") / (F.col("own_size") * F.col("mix_rows")) + 0.5).cast("int")
    out = known.join(per_id, F.col(place["doc_id"]).eqNullSafe(F.col("mix_id")) & (F.col("own_size") == F.col("mix_size"))).withColumn("times", times).where("times > 0")
    each = out.withColumn("time", F.explode(F.sequence(F.lit(1), F.col("times"))))
    at = F.col("mix_places")[F.least(F.col("time"), F.size("mix_places")) - 1]["position"]
    return each.withColumn("at", at).orderBy("at", F.xxhash64("mix_id")).select(*names).toDF(*docs.columns)
