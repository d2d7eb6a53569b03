"""A spread sample for every key of a stream, kept as keyed state."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from spreadsample.operators.exchange import WorkingSet

STATE = "rows long, id array<string>, x array<double>, y array<double>"
OUT = "key string, rows long, id array<string>, x array<double>, y array<double>, objective double"


def samples_by_key(points: DataFrame, k: int, eps: float, by: str, **options) -> DataFrame:
    """(key, rows, id, x, y, objective), in update mode: the k members of each key after every micro-batch that has rows of it.

    points: a stream (id, x, y and the key). The state of a key is its members, whatever it has seen; a key's
    rows of one batch are streamed to its task. Rows with a null, NaN or infinite coordinate are left out; rows without a key share one."""

    def offer(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        work = WorkingSet(k, eps, **options)
        rows = 0
        if state.exists:
            rows, ids, x, y = state.get
            work.offer(np.array(ids, object), np.array(x, float), np.array(y, float))
        for f in frames:
            work.offer(f["id"].to_numpy(object), f["x"].to_numpy(float), f["y"].to_numpy(float))
            rows += len(f)
        members = [work.id[: work.n].tolist(), work.x[: work.n].tolist(), work.y[: work.n].tolist()]
        state.update((rows, *members))
        yield pd.DataFrame({"key": [key[0]], "rows": [rows], **{c: [m] for c, m in zip(("id", "x", "y"), members)}, "objective": [work.objective()]})

    finite = lambda c: F.col(c).isNotNull() & ~F.isnan(c) & (F.abs(c) != float("inf"))
    dealt = points.where(finite("x") & finite("y")).select(F.coalesce(F.col(by).cast("string"), F.lit("")).alias("key"), F.col("id").cast("string").alias("id"), "x", "y")
    return dealt.groupBy("key").applyInPandasWithState(offer, OUT, STATE, "update", GroupStateTimeout.NoTimeout)
