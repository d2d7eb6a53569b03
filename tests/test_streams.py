"""Keyed samples of a stream on awkward rows."""

from pyspark.sql import functions as F

from spreadsample.functions.runtime import new_path
from spreadsample.operators.streams import drained
from spreadsample.streaming import keyed


def test_keyed_samples_leave_out_rows_without_place_and_keep_null_keys(spark):
    rows = [(str(i), float(i), 0.0, "a", 1) for i in range(9)] + [("n", None, 1.0, "a", 2), ("i", float("inf"), 1.0, "a", 3), ("q", float("nan"), 1.0, "b", 4), ("z", 5.0, 5.0, None, 5)]
    p = spark.createDataFrame(rows, "id string, x double, y double, kind string, key int")
    src, out, offsets = new_path(spark, "rows"), new_path(spark, "out"), new_path(spark, "offsets")
    for _ in range(2):  # the same rows again: the state goes on
        p.write.mode("append").parquet(src)
        drained(keyed.samples_by_key(spark.readStream.schema(p.schema).parquet(src), 3, 1.0, "kind"), out, "update", offsets)
    last = {r["key"]: r["s"] for r in spark.read.parquet(out).groupBy("key").agg(F.max_by(F.struct("rows", "id", "objective"), "batch").alias("s")).collect()}
    assert set(last) == {"a", ""}
    assert last["a"]["rows"] == 18 and len(last["a"]["id"]) == 3 and len(set(last["a"]["id"])) == 3
    assert last[""]["rows"] == 2 and last[""]["id"] == ["z", "z"] and last[""]["objective"] == 1.0
