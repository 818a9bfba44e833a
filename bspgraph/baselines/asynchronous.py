"""Asynchronous execution: updates are visible within the pass.

``blocks``: the range of identifiers is cut into ordered blocks; a pass runs them
one after another, each reading the newest values.  One block is synchronous
execution, very many are sequential.  A block is one job with one shuffle.

``partition_local``: each partition is solved to its own fixpoint in memory of
one task and only labels of border vertices move.  For programs whose values
only fall the fixpoint is the same, in far fewer rounds on long paths.
"""

from __future__ import annotations

import contextlib
import copy
import itertools
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F

from ..algorithms.paths import UNREACHED
from ..graph import Graph
from ..plans.checkpoints import cut, drop, held, loop_settings
from ..plans.layout import place
from ..shipping import ship

#: Bytes that edges and vertices may take in memory, unless a run says else.
MEMORY_BUDGET = 1 << 30


@dataclass(frozen=True)
class Scheduler:
    """Whether vertices run only when scheduled; switched by the user."""

    enabled: bool = True


def storage_for(num_vertices: int, num_edges: int, memory_budget: int, storage: str = "auto") -> StorageLevel:
    """In memory if vertices and edges fit the budget, partly so up to eight
    times of it, else out of core."""
    need = num_vertices * 40 + num_edges * 24
    if storage == "memory" or storage == "auto" and need <= memory_budget:
        return StorageLevel.MEMORY_ONLY
    return StorageLevel.MEMORY_AND_DISK if storage == "auto" and need <= 8 * memory_budget else StorageLevel.DISK_ONLY


@contextlib.contextmanager
def _stored(graph: Graph, storage: str, memory_budget: int) -> Iterator[Graph]:
    """The graph with its edges in the storage that the budget allows, within the
    loop's settings."""
    with loop_settings(graph.spark), held(graph.light, storage_for(graph.num_vertices, graph.num_edges, memory_budget, storage)) as light:
        kept = copy.copy(graph)
        kept.light = light
        yield kept


def block_of(graph: Graph, blocks: int) -> Callable[[str], Column]:
    """The number of an identifier's block: equal ranges in their order."""
    lowest, highest = graph.vertices.agg(F.min("id"), F.max("id")).first()
    if lowest is None:
        return lambda c: F.lit(0)
    width = -(-(highest - lowest + 1) // blocks)
    return lambda c: F.floor((F.col(c) - lowest) / F.lit(float(width))).cast("int") if blocks > 1 else F.lit(0)


def async_pagerank(
    graph: Graph,
    passes: int = 10,
    damping: float = 0.85,
    blocks: int = 2,
    tolerance: float | None = None,
    seed_share: str = "scaled",
    storage: str = "auto",
    memory_budget: int = MEMORY_BUDGET,
) -> DataFrame:
    """(id, rank).  The shared table holds shares, rank over out-degree; ranks
    come out at the end.  It starts with 1/N, divided by the degree or raw.
    With a tolerance, passes go on until no rank changes by more."""
    n, block = float(max(1, graph.num_vertices)), block_of(graph, blocks)
    first = F.lit(1.0 / n) if seed_share == "raw" else F.try_divide(F.lit(1.0 / n), F.col("out_degree"))
    state, made = graph.vertices.select("pid", "id", "out_degree", F.lit(1.0 / n).alias("rank"), first.alias("share")), None
    with _stored(graph, storage, memory_budget) as kept:
        for _ in range(passes):
            change = 0.0
            for b in range(blocks):
                got = kept.mail(state.select("pid", F.col("id").alias("src"), "share"), F.col("share"), F.sum, into=block("dst") == b)
                new = (1 - damping) / n + damping * F.coalesce("msg", F.lit(0.0))
                mine = block("id") == b
                moved = F.when(mine, F.abs(new - F.col("rank"))).alias("moved")
                nxt = state.join(got, ["id", "pid"], "left").select("pid", "id", "out_degree", F.when(mine, new).otherwise(F.col("rank")).alias("rank"), "share", moved)
                share = F.when(mine, F.try_divide("rank", "out_degree")).otherwise(F.col("share"))
                seen = Observation()
                before, made = made, cut(nxt.withColumn("share", share).observe(seen, F.coalesce(F.max("moved"), F.lit(0.0)).alias("change")))
                state = made.drop("moved")
                drop(before)
                change = max(change, seen.get["change"])
            if tolerance is not None and change <= tolerance:
                break
    return state.select("id", "rank")


def _monotone(graph: Graph, offered: Column, step: int, blocks: int, scheduler: Scheduler, storage: str, memory_budget: int, work: list[int] | None) -> DataFrame:
    """(id, value): values fall to what their neighbours offer, block by block.

    ``offered`` is a first offer, or null.  A vertex with an offer is scheduled;
    when its block's turn comes it takes the offer and offers its value plus
    ``step`` to its out-neighbours, where only an offer below their newest value
    stands.  So only those are scheduled that would improve.  Without a scheduler
    every vertex of the block runs and offers each time.  ``work`` gets the number
    of vertices run in each turn.
    """
    block = block_of(graph, blocks)
    state, made = graph.vertices.select("pid", "id", F.lit(UNREACHED).cast("long").alias("value"), offered.cast("long").alias("offer")), None
    with _stored(graph, storage, memory_budget) as kept:
        for turn in itertools.count():
            mine = block("id") == turn % blocks
            scheduled = mine & F.col("offer").isNotNull()
            ran = scheduled if scheduler.enabled else mine
            taken = state.select(
                "pid", "id", F.when(scheduled, F.least("value", "offer")).otherwise(F.col("value")).alias("value"), F.when(~mine, F.col("offer")).alias("offer"), ran.alias("ran")
            )
            told = taken.where(F.col("ran") & (F.col("value") < UNREACHED)).select("pid", F.col("id").alias("src"), "value")
            mail = kept.mail(told, F.col("value") + step, F.min)
            stands = F.when(F.col("msg") < F.col("value"), F.col("msg"))
            nxt = taken.join(mail, ["id", "pid"], "left").select("pid", "id", "value", F.least("offer", stands).alias("offer"), "ran")
            seen = Observation()
            before, made = made, cut(nxt.observe(seen, F.count_if(F.col("offer").isNotNull()).alias("waiting"), F.count_if("ran").alias("ran")))
            state = made.drop("ran")
            drop(before)
            if work is not None:
                work.append(int(seen.get["ran"]))
            if not seen.get["waiting"]:
                return state.select("id", "value")


def async_components(
    graph: Graph, blocks: int = 2, scheduler: Scheduler = Scheduler(), storage: str = "auto", memory_budget: int = MEMORY_BUDGET, work: list[int] | None = None
) -> DataFrame:
    return _monotone(graph, F.col("id"), 0, blocks, scheduler, storage, memory_budget, work).withColumnRenamed("value", "component")


def async_sssp(
    graph: Graph, source: int, blocks: int = 2, scheduler: Scheduler = Scheduler(), storage: str = "auto", memory_budget: int = MEMORY_BUDGET, work: list[int] | None = None
) -> DataFrame:
    done = _monotone(graph, F.when(F.col("id") == source, F.lit(0)), 1, blocks, scheduler, storage, memory_budget, work)
    return done.select("id", F.when(F.col("value") < UNREACHED, F.col("value")).alias("distance"))


def least_labels(src: np.ndarray, dst: np.ndarray, known: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Identifiers of a set of edges and the least label that each can reach
    within it, by halving paths over arrays; ``known`` are the sources' labels."""
    ids, at = np.unique(np.concatenate([src, dst]), return_inverse=True)
    a, b = at[: len(src)], at[len(src) :]
    label = ids.copy()
    np.minimum.at(label, a, known)
    order = np.argsort(label, kind="stable")  # roots are the vertices of least labels
    rank = np.empty(len(ids), dtype=np.int64)
    rank[order] = np.arange(len(ids))
    root = rank.copy()
    while True:
        low = np.minimum(root[a], root[b])
        nxt = root.copy()
        np.minimum.at(nxt, a, low)
        np.minimum.at(nxt, b, low)
        np.minimum.at(nxt, order[root[a]], low)  # their roots hook on as well
        np.minimum.at(nxt, order[root[b]], low)
        nxt = np.minimum(nxt, nxt[order[nxt]])
        if (nxt == root).all():
            return ids, label[order[root]]
        root = nxt


def local_components(graph: Graph) -> DataFrame:
    """Components with partitions solved on their own and the labels of targets
    exchanged in between.  A task holds its partition's edges as arrays."""
    ship(graph.spark)

    def solve(batches):
        parts = [[b.column(i).to_numpy() for i in range(3)] for b in batches if b.num_rows]
        if not parts:
            return
        ids, label = least_labels(*(np.concatenate(x) for x in zip(*parts)))
        for at in range(0, len(ids), 100_000):
            yield pa.RecordBatch.from_arrays([pa.array(ids[at : at + 100_000]), pa.array(label[at : at + 100_000])], names=["id", "label"])

    with loop_settings(graph.spark):
        state, made = graph.vertices.select("pid", "id").withColumn("label", F.col("id") + 0), None
        while True:
            near, far = graph.sent(state.select("pid", F.col("id").alias("src"), "label"))
            found = [x.select("src", "dst", "label").mapInArrow(solve, "id long, label long") for x in (near, far) if x is not None]
            found = found[0] if len(found) == 1 else found[0].unionByName(found[1])
            best = found.select(place("id", graph.partitions).alias("pid"), "id", "label").repartition(graph.partitions, "pid").groupBy("pid", "id").agg(F.min("label").alias("new"))
            joined = state.join(best, ["id", "pid"], "left")
            seen = Observation()
            lower = (F.coalesce("new", "label") < F.col("label")).alias("fell")
            before, made = made, cut(joined.select("pid", "id", F.least("label", "new").alias("label"), lower).observe(seen, F.count_if("fell").alias("fell")))
            state = made.drop("fell")
            drop(before)
            if not seen.get["fell"]:
                return state.select("id", F.col("label").alias("component"))
