"""Union-find grouping of links that are spread over the cluster."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import BROADCAST_ROWS, counted, map_batches, small_cut


def connected(links: DataFrame, few: int = BROADCAST_ROWS) -> DataFrame:
    """(node, component) of links (a, b): component is the least node reachable.

    Links that were counted to be at most ``few`` are united by one task.  More are
    turned into stars round by round: each node hands its larger
    neighbours to its least one, then its smaller ones, until nothing moves.
    The number of rounds grows with the logarithm of the longest path.  Minima
    are partially aggregated; minima are written first, so the
    join with them is a broadcast if they are few, else one whose hot nodes split.
    """
    edges, before = _marked(links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct())
    if before["rows"] <= few:
        return map_batches(edges.coalesce(1), _unite, "node long, component long")
    while True:
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = small_cut(both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m")))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        large, _ = counted(large)
        stars = large.join(small_cut(large.groupBy("u").agg(F.min("v").alias("m"))), "u")
        edges, now = _marked(
            stars.select("u", F.col("m").alias("v"))
            .unionByName(stars.select(F.col("v").alias("u"), F.col("m").alias("v")))
            .where("u <> v")
            .distinct()
        )
        if now == before:
            break
        before = now
    return edges.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(
        edges.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    )


def _unite(batches: Iterator[pa.RecordBatch]) -> Iterator[dict]:
    """The classes of links (u, v) that lie in one partition."""
    above: dict[int, int] = {}

    def top(node: int) -> int:
        while (over := above.setdefault(node, node)) != node:
            above[node] = node = above[over]
        return node

    for batch in batches:
        for u, v in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
            a, b = top(u), top(v)
            above[max(a, b)] = min(a, b)
    yield {"node": list(above), "component": [top(node) for node in list(above)]}


def _marked(edges: DataFrame) -> tuple[DataFrame, dict]:
    """Edges cut, with their number and a sum of their hashes, to see whether they moved."""
    return counted(edges, F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("mark"))
