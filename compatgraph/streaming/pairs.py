"""The one-hop statistic on streams: X'AX is a sum over edges, so windows of it add up.  Multi-hop counts need a snapshot."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.compat import nearest_compat, normalize_counts

STEP = "ts timestamp, user_id long, a string, b string"


def class_steps(events: DataFrame) -> DataFrame:
    """ts, user_id, a, b: event types of consecutive events of a user; works on batches and streams (state: the last event).

    A stream's events are put in order within each micro-batch; later ones than the watermark are dropped by the caller.
    """
    def follow(key, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        before = state.get[0] if state.exists else None
        types = rows["event_type"].tolist()
        state.update((types[-1],))
        out = pd.DataFrame({"ts": rows["ts"], "user_id": key[0], "a": [before, *types[:-1]], "b": types})
        yield out[out["a"].notna()]

    if events.isStreaming:
        return events.groupBy("user_id").applyInPandasWithState(follow, STEP, "last string", "append", "NoTimeout")
    from pyspark.sql import Window as W

    before = F.lag("event_type").over(W.partitionBy("user_id").orderBy("ts", "event_id"))
    return events.select("ts", "user_id", before.alias("a"), F.col("event_type").alias("b")).filter("a is not null")


def windowed(steps: DataFrame, width: str = "1 day", slide: str | None = None, late: str = "1 day") -> DataFrame:
    """start, a, b, n per tumbling or sliding window."""
    if steps.isStreaming:
        steps = steps.withWatermark("ts", late)
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return steps.groupBy(w.alias("w"), "a", "b").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "a", "b", "n")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 day") -> DataFrame:
    """user_id, start, n per session."""
    if events.isStreaming:
        events = events.withWatermark("ts", late)
    return events.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def deduplicated(events: DataFrame, within: str = "1 day") -> DataFrame:
    """Events without repeats of an event_id; a stream forgets ids that are older than ``within``."""
    if events.isStreaming:
        return events.withWatermark("ts", within).dropDuplicatesWithinWatermark(["event_id"])
    return events.dropDuplicates(["event_id"])


def with_classes(events: DataFrame, classes: DataFrame) -> DataFrame:
    """Events with the class number of their type: a stream (or batch) joined with a static table (name, cls)."""
    return events.join(F.broadcast(classes.withColumnRenamed("name", "event_type")), "event_type")


def dropped_late(query) -> int:
    """Rows that a streaming query has dropped as later than its watermark, over the progress it still remembers."""
    return sum(int(op["numRowsDroppedByWatermark"]) for p in query.recentProgress for op in p["stateOperators"])


class RunningCompat:
    """``foreachBatch`` sink: adds a micro-batch's pair counts, re-estimates K one-hop and keeps its drift.

    A micro-batch that is played again after a failure has the number of one seen before and is left out.
    """

    def __init__(self, classes: list[str], variant: int = 1):
        self.at = {c: i for i, c in enumerate(classes)}
        self.M, self.K, self.variant, self.drift, self.last = np.zeros((len(classes),) * 2), None, variant, [], -1

    def __call__(self, steps: DataFrame, epoch: int) -> None:
        if epoch <= self.last:
            return
        self.last = epoch
        for r in steps.groupBy("a", "b").count().collect():  # k x k rows
            i, j = self.at[r.a], self.at[r.b]
            self.M[i, j] += r["count"]
            self.M[j, i] += r["count"]
        K = nearest_compat(normalize_counts(self.M, self.variant))
        self.drift.append(float("nan") if self.K is None else float(np.linalg.norm(K - self.K)))
        self.K = K
