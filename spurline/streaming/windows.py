"""Windowed event features as streams, and assignment of arriving points to stored groups."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from spurline.operators.neighbors import squared


def event_windows(events: DataFrame, length: str = "1 day", slide: str | None = None, late: str = "1 day") -> DataFrame:
    """Counts and sums by type in event-time windows; the same plan for a stream (later rows than ``late`` are dropped) and a batch."""
    rows = events.withColumn("ts", F.col("ts").cast("timestamp"))
    if events.isStreaming:
        rows = rows.withWatermark("ts", late)
    return rows.groupBy(F.window("ts", length, slide or length).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total")).select(F.col("w.start").alias("start"), "event_type", "n", "total")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 day") -> DataFrame:
    rows = events.withColumn("ts", F.col("ts").cast("timestamp"))
    if events.isStreaming:
        rows = rows.withWatermark("ts", late)
    return rows.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def assign(points: DataFrame, centres: DataFrame, cutoff: float) -> DataFrame:
    """Arriving points (``id, x``) with the label of the nearest of the stored ``centres`` (``label, c``; at most 10000), or -1 beyond ``cutoff``. Stateless."""
    if centres.count() > 10_000:
        raise ValueError("over 10000 centres are not sent to every task")
    rows = F.broadcast(centres.agg(F.collect_list(F.struct("label", "c")).alias("cs")))
    near = F.array_min(F.transform("cs", lambda s: F.struct(F.sqrt(squared(F.col("x"), s["c"])).alias("d"), s["label"].alias("label"))))
    return points.join(rows).select("id", "x", near.alias("m")).select("id", "x", F.when(F.col("m.d") <= cutoff, F.col("m.label")).otherwise(-1).alias("label"))


def walk_positions(events: DataFrame, steps: int = 50) -> DataFrame:
    """``(user_id, step, p0, p1)`` of a stream of ``events``: each user's position after every event, up to ``steps``, in whole units.

    A user's count and position are the state, three numbers. Within a batch events go by time and id; an event that comes
    in a later batch than a younger one takes the next step. Null users are left out.
    """
    from spurline.sources.workloads import walk_step

    rows = events.where("user_id is not null").select("user_id", "ts", "event_id", F.pmod("event_id", F.lit(2)).alias("axis"), walk_step().alias("size"))

    def run(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, p0, p1 = state.get if state.exists else (0, 0, 0)
        batch = pd.concat(list(parts)).sort_values(["ts", "event_id"]).head(steps - n)
        if len(batch):
            even = batch["axis"].to_numpy() == 0
            size = batch["size"].to_numpy()
            at = [p0 + np.cumsum(np.where(even, size, 0)), p1 + np.cumsum(np.where(even, 0, size))]
            state.update((n + len(batch), int(at[0][-1]), int(at[1][-1])))
            yield pd.DataFrame({"user_id": key[0], "step": np.arange(n + 1, n + 1 + len(batch)), "p0": at[0], "p1": at[1]})

    return rows.groupBy("user_id").applyInPandasWithState(run, "user_id long, step long, p0 long, p1 long", "n long, p0 long, p1 long", "append", GroupStateTimeout.NoTimeout)
