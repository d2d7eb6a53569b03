"""The distance join of a set with itself, by strips."""

import numpy as np
import pytest

from spreadsample.operators import measures, surrounding

SF = "/root/testdata/sf0.001"


def crowded(seed: int) -> list[tuple]:
    """Even rows, a crowd, equal places, equal ids, places on the borders of strips and bands."""
    rng = np.random.default_rng(seed)
    xy = np.concatenate((rng.random((300, 2)) - 0.5, rng.normal(0.3, 0.003, (150, 2)), np.full((20, 2), 0.25), rng.integers(-20, 20, (120, 2)) * 0.01, rng.integers(-3, 3, (60, 2)) * 0.08))
    return [(str(n % 600), float(x), float(y)) for n, (x, y) in enumerate(xy)] + [("n", None, 0.3), (None, 0.3, 0.3), ("m", float("nan"), 0.3)]


@pytest.mark.parametrize("candidates, rows", [(1 << 18, 10_000), (7, 5)])
def test_close_pairs(spark, monkeypatch, candidates, rows):
    monkeypatch.setattr(measures, "CANDIDATES", candidates)
    made, radius = crowded(5), 0.01
    whole = [(i, x, y) for i, x, y in made if i is not None and x is not None and x == x]
    want = sorted((i, j) for i, x, y in whole for j, u, v in whole if i < j and (x - u) * (x - u) + (y - v) * (y - v) <= radius * radius)
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(rows))
    try:
        found = measures.close_pairs(spark.createDataFrame(made, "id string, x double, y double"), radius).collect()
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    assert len(want) > 5000 and sorted((r["a_id"], r["b_id"]) for r in found) == want


def test_range_join_copies_no_row_ninefold(spark):
    df = surrounding.R.queries["op_join_range_cells"](spark, SF)
    plan = df._jdf.queryExecution().toString()
    assert "cx" not in plan and "RepartitionByExpression [strip" in plan
