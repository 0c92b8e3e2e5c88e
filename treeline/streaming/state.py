"""Custom state: the recent mean of each user's values, with state that expires."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

OUT = "user_id bigint, n bigint, mean double"


def _update(key, parts, state: GroupState):
    if state.hasTimedOut:
        state.remove()
        return
    n, total = state.get if state.exists else (0, 0.0)
    last = 0
    for part in parts:
        n, total = n + len(part), total + float(part["value"].sum())
        last = max(last, int(part["ts"].max().value // 1_000_000))
    state.update((n, total))
    state.setTimeoutTimestamp(max(last, state.getCurrentWatermarkMs()) + 3_600_000)
    yield pd.DataFrame({"user_id": [key[0]], "n": [n], "mean": [total / n if n else 0.0]})


def running_means(events: DataFrame) -> DataFrame:
    """user_id, n, mean after each batch; a user's state goes once the watermark is an hour past their last event."""
    return events.withWatermark("ts", "1 hour").groupBy("user_id").applyInPandasWithState(_update, OUT, "n bigint, total double", "update", GroupStateTimeout.EventTimeTimeout)
