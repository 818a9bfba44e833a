"""Graphs that grow by streams of edges or events."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from ..algorithms import connected_components
from ..graph import Graph
from ..plans.checkpoints import cut


class IncrementalComponents:
    """Labels kept right while edges are only added.

    A batch of edges is mapped to the labels of its ends; components of that
    small graph of labels tell which labels fall.  Old edges are never read.
    """

    def __init__(self, spark):
        self.labels = spark.createDataFrame([], "id long, component long")

    def add(self, edges: DataFrame) -> None:
        ends = edges.select(F.col("src").alias("id")).unionByName(edges.select(F.col("dst").alias("id"))).distinct()
        fresh = ends.join(self.labels, "id", "left_anti").select("id", F.col("id").alias("component"))
        known = cut(self.labels.unionByName(fresh))
        a, b = known.toDF("src", "x"), known.toDF("dst", "y")
        joined = edges.select("src", "dst").join(a, "src").join(b, "dst").where("x <> y").select(F.col("x").alias("src"), F.col("y").alias("dst"))
        if joined.isEmpty():
            self.labels = known
            return
        moved = connected_components(Graph.from_edges(joined)).toDF("component", "lower")
        self.labels = cut(known.join(moved, "component", "left").select("id", F.coalesce("lower", "component").alias("component")))

    def batch(self) -> Callable[[DataFrame, int], None]:
        """The function for ``foreachBatch``."""
        return lambda edges, _number: self.add(edges)


#: How late an event may come, and after how long without events a user's state goes.
LATE = "1 hour"
IDLE_DAYS = 30

_HELD = "ids array<long>, times array<long>, last long, last_time long"


def chain_stream(events: DataFrame, late: str = LATE) -> DataFrame:
    """The edge from each user's event to the next in time, from a stream of
    (event_id, user_id, ts).

    Events are held until the watermark, ``late`` behind the newest, has passed
    them, so events that come out of order are chained in order; one that comes
    after a later event was chained is dropped.  The state of a user is the last event chained and those held.
    """

    def step(key, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        ids, times, last, last_time = state.get if state.exists else ((), (), None, None)
        held = list(zip(times, ids))
        if not state.hasTimedOut:
            for rows in frames:
                held += zip(rows["micros"].tolist(), rows["event_id"].tolist())
        mark = state.getCurrentWatermarkMs() * 1000
        held.sort()
        ready = [e for e in held if e[0] <= mark and (last_time is None or e >= (last_time, last))]
        rest = [e for e in held if e[0] > mark]
        chained = ([] if last is None else [last]) + [i for _, i in ready]
        if ready:
            last_time, last = ready[-1]
        if state.hasTimedOut and not ready and not rest:
            state.remove()
        else:
            state.update(([i for _, i in rest], [t for t, _ in rest], last, last_time))
            wake = rest[0][0] if rest else last_time + IDLE_DAYS * 86_400_000_000 if last_time is not None else mark
            state.setTimeoutTimestamp(max(wake, mark) // 1000 + 1)
        yield pd.DataFrame({"src": chained[:-1], "dst": chained[1:]}, dtype="int64")

    rows = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late).withColumn("micros", F.unix_micros("ts"))
    return rows.groupBy("user_id").applyInPandasWithState(step, "src long, dst long", _HELD, "append", GroupStateTimeout.EventTimeTimeout)
