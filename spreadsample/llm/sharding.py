"""Sharding by vector bin packing: bytes, tokens and rows are balanced together.

Equal texts are a group and share a shard, but for groups that exceed a shard's share of the corpus and so fit in none: those go in
parts. Groups that hold a noticeable share are parcels of their own, all others are gathered into a fixed number of
parcels by their hash. Only parcels, whose number is bounded by the parameters, come to the driver; each goes, largest first, to the
shard where the dot product of its shares with the shard's residual capacity is highest.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from spreadsample.llm.common import durable
from spreadsample.llm.mixing import words_in

#: PIECES: parts in which the rows of one large group are numbered; with the bound on such groups, at most 3 * HEAVY * PIECES rows.
SHARDS, PARCELS, HEAVY, PARTS, PIECES = 16, 4096, 1024, 256, 32


def pack(loads: np.ndarray, shards: int) -> np.ndarray:
    """The shard of each row of loads (shares of the whole in each dimension)."""
    residual = np.full((shards, loads.shape[1]), 1.0 / shards)
    out = np.zeros(len(loads), np.int64)
    for i in np.argsort(-loads.max(axis=1), kind="stable"):
        out[i] = (residual @ loads[i]).argmax()
        residual[out[i]] -= loads[i]
    return out


def levelled(to: np.ndarray, size: np.ndarray, shards: int, close: float = 0.005) -> np.ndarray:
    """The packing `to` with sizes near equal, as the law says: the residuals of three measures leave the bytes uneven where texts differ much in
    bytes a word. The fullest and the emptiest shard exchange the two parcels (or move the one) that halve their gap best, until it is below
    `close` of a shard or no exchange makes it less."""
    to, held = to.copy(), np.bincount(to, size, shards)
    for _ in range(4 * len(to)):
        hi, lo = int(held.argmax()), int(held.argmin())
        gap = held[hi] - held[lo]
        if gap <= close * held.sum() / shards:
            break
        ours, theirs = np.flatnonzero(to == hi), np.flatnonzero(to == lo)
        moved = size[ours][:, None] - np.append(size[theirs], 0.0)
        a, b = np.unravel_index(np.abs(moved - gap / 2).argmin(), moved.shape)
        if not 0 < moved[a, b] < gap:
            break
        to[ours[a]] = lo
        if b < len(theirs):
            to[theirs[b]] = hi
        held[hi] -= moved[a, b]
        held[lo] += moved[a, b]
    return to


def shard(docs: DataFrame, shards: int = SHARDS, parcels: int = PARCELS, heavy: int = HEAVY, parts: int = PARTS) -> DataFrame:
    """(doc_id, size, text_crc32, law, shard, slot, grown_shard) for every row of docs (doc_id, text).

    size is the UTF-8 bytes of the text plus 1; a null text counts as an empty one, and equal texts are a group, whatever their ids. Slots of
    a shard run from 0 without gaps, by parcel, then a hash of the id (parcels of one group only), then doc_id (nulls first).
    Repeated rows have slots of their own; ties go to the first shard. An empty table gives no rows. Groups with over 1/heavy of the bytes,
    words or rows are placed by themselves, those with over 1/shards in parts of about 1/parts, by doc_id; so at most
    parcels + 3 * (heavy + parts + shards) rows are collected."""
    spark = docs.sparkSession
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    rows = durable(docs.select(F.col("doc_id").cast("long"), (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), words_in(text).alias("words"), F.xxhash64(text).alias("h1"), F.xxhash64(F.lit(1), text).alias("h2")))
    measures = [F.sum("size").alias("size"), F.sum("words").alias("words"), F.count("*").alias("n")]
    total = rows.agg(*measures).first()
    whole = np.array([max(1, total[0] or 0), max(1, total[1] or 0), max(1, total[2])], float)
    share = F.greatest(*[F.col(c) / float(t) for c, t in zip(("size", "words", "n"), whole)])
    large = rows.groupBy("h1", "h2").agg(*measures).withColumn("share", share).where(F.col("share") > 1 / heavy).orderBy("h1", "h2").collect()
    own, at = [], parcels
    for g in large:
        n = -int(-g["share"] * parts // 1) if g["share"] > 1 / shards else 1
        own.append((g["h1"], g["h2"], at, n))
        at += n
    heavies = F.broadcast(spark.createDataFrame(own, "h1 long, h2 long, base int, parts int"))
    named = rows.join(heavies, ["h1", "h2"], "left").withColumn("parcel", F.when(F.col("base").isNull(), F.pmod("h1", F.lit(parcels))).otherwise(F.col("base") + F.pmod(F.xxhash64("doc_id"), F.col("parts").cast("long"))).cast("int"))
    held = sorted(named.groupBy("parcel").agg(*measures).collect())
    loads = np.array([r[1:] for r in held], float).reshape(-1, 3)
    to = levelled(pack(loads / whole, shards), loads[:, 0], shards)
    starts, layout = [0] * shards, []
    for r, s in zip(held, to):
        layout.append((r["parcel"], int(s), starts[s]))
        starts[s] += r["n"]
    where = F.broadcast(spark.createDataFrame(layout, "parcel int, shard int, first long"))
    # a parcel of one group may hold a shard's share of all rows: its slots are counted in pieces by a hash of the id
    named = named.withColumn("piece", F.when(F.col("base").isNull(), 0).otherwise(F.pmod(F.xxhash64("doc_id", F.lit(9)), F.lit(PIECES))).cast("int"))
    per = named.where("piece IS NOT NULL AND base IS NOT NULL").groupBy("parcel", "piece").agg(F.count("*").alias("n"))
    earlier = F.broadcast(per.select("parcel", "piece", (F.sum("n").over(Window.partitionBy("parcel").orderBy("piece")) - F.col("n")).alias("earlier")))
    slot = F.coalesce("earlier", F.lit(0)) + F.row_number().over(Window.partitionBy("parcel", "piece").orderBy("doc_id", "h1", "h2", "size")) - 1
    return named.join(where, "parcel").join(earlier, ["parcel", "piece"], "left").select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", (F.col("first") + slot).alias("slot"), F.lit(None).cast("int").alias("grown_shard"))
