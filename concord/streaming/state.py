"""A stateful stream operator: interest in a coordination value as users arrive.

State is kept per value: the users who want it and when they came. A row is emitted whenever a value gains a user while at
least ``need`` users want it; users whose request is older than ``ttl_seconds`` of event time leave. This is the cheap
filter in front of full coordination: a value with fewer users than any ask needs cannot coordinate.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout


def live_interest(stream: DataFrame, time: str, user: str, value: list[str], need: int = 2, ttl_seconds: int = 3600, late: str = "1 hour") -> DataFrame:
    """(value columns, users, at) of a streaming DataFrame, in update mode."""
    kinds = dict(stream.dtypes)
    out = ", ".join([*(f"{v} {kinds[v]}" for v in value), "users long", "at double"])

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        users: dict = dict(zip(*state.get, strict=True)) if state.exists else {}
        if state.hasTimedOut:
            state.remove()
            return
        before, newest = len(users), max(users.values(), default=0.0)
        for pdf in frames:
            for who, at in zip(pdf["__user"].tolist(), pdf["__seconds"].tolist(), strict=True):
                users[who] = max(at, users.get(who, at))
                newest = max(newest, at)
        users = {u: t for u, t in users.items() if t > newest - ttl_seconds}
        state.update((list(users), list(users.values())))
        state.setTimeoutTimestamp(max(int((newest + ttl_seconds) * 1000), state.getCurrentWatermarkMs() + 1))
        if len(users) >= need and len(users) != before:
            yield pd.DataFrame([(*key, len(users), newest)], columns=[*value, "users", "at"])

    at = F.col(time).cast("timestamp")
    rows = stream.withColumn("__at", at).withWatermark("__at", late).select(*value, F.col(user).cast("long").alias("__user"), "__at", F.col("__at").cast("double").alias("__seconds"))
    return rows.groupBy(*value).applyInPandasWithState(step, out, "users array<long>, times array<double>", "update", GroupStateTimeout.EventTimeTimeout)
