"""What the operators share: table access, durable intermediate results, connected components."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: ASCII white space, the separator of words in every operator that counts or joins words.
WORD = "[^\\x20\\x09-\\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The session's spark.checkpoint.dir; only where that is unset (tests, one machine) a temporary folder is made."""
    context = spark.sparkContext
    if context._jsc.sc().getCheckpointDir().isEmpty():
        context.setCheckpointDir(spark.conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp(prefix="checkpoint-"))
    return context._jsc.sc().getCheckpointDir().get()


def durable(df: DataFrame) -> DataFrame:
    """df, written once to the shared checkpoint folder and read from there: its lineage is cut, and no
    executor holds the only copy."""
    shared_folder(df.sparkSession)
    return df.checkpoint()


def parked(df: DataFrame) -> DataFrame:
    """df as a Parquet table in the shared folder."""
    path = f"{shared_folder(df.sparkSession)}/table-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.parquet(path)


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """Connected components of an edge list (columns a, b; long, in any direction, loops and repeats
    allowed) as rows (node, root): root is the smallest node reachable. Nodes without an edge to another
    node do not appear.

    Alternating large-star and small-star rounds: every round is two partially aggregated minima and two
    joins over at most the given edges, the number of rounds is logarithmic in practice, and nothing is
    collected but three sums that tell whether a round changed anything."""
    stars = durable(edges.where(F.col("a") != F.col("b")).select(F.greatest("a", "b").alias("hi"), F.least("a", "b").alias("lo")).distinct())
    before = None
    for _ in range(max_rounds):
        found = stars.agg(F.count("*"), F.sum(F.col("hi").cast("decimal(38,0)")), F.sum(F.col("lo").cast("decimal(38,0)"))).first()
        if tuple(found) == before or not found[0]:
            return stars.select(F.col("hi").alias("node"), F.col("lo").alias("root")).union(stars.select(F.col("lo"), F.col("lo")).distinct())
        before = tuple(found)
        both = stars.select(F.col("hi").alias("u"), F.col("lo").alias("v")).union(stars.select("lo", "hi"))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("hi"), F.col("m").alias("lo")).distinct()
        roots = large.groupBy("hi").agg(F.min("lo").alias("m"))
        small = large.join(roots, "hi").where("lo != m").select(F.col("lo").alias("hi"), F.col("m").alias("lo"))
        stars = durable(small.union(roots.select("hi", "m")).where("hi != lo").distinct())
    raise RuntimeError(f"components did not settle within {max_rounds} rounds")
