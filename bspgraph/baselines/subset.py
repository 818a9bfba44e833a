"""A vertex-subset engine: the caller owns loop, buffers and stopping rule.

``edge_map`` sends along the edges of a subset and returns what reaches the
targets; ``vertex_map`` updates the vertices of a subset.  A subset is sparse (a
table of its vertices) or dense (all vertices with a flag).  A small subset is
kept sparse and pushes: its rows meet their out-edges.  A large one is dense and is
pulled: targets that may still change read their in-edges.  Both read the graph's
own layout and have one shuffle; a round is one job, whose counters size the
next subset.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F

from ..algorithms.paths import UNREACHED
from ..graph import Graph
from ..plans.checkpoints import cut, drop, loop_settings


@dataclass
class VertexSubset:
    """Vertices (pid, id, and what they carry), their number and out-edges."""

    rows: DataFrame
    size: int
    out_edges: int
    is_dense: bool = False

    @classmethod
    def everyone(cls, graph: Graph, rows: DataFrame) -> VertexSubset:
        return cls(rows.withColumn("inside", F.lit(True)), graph.num_vertices, graph.num_edges, True)

    def sparse(self) -> DataFrame:
        return self.rows.where("inside").drop("inside") if self.is_dense else self.rows

    def dense(self, graph: Graph) -> DataFrame:
        """All vertices of the graph with the flag ``inside``."""
        if self.is_dense:
            return self.rows
        flags = self.rows.select("pid", "id", F.lit(True).alias("inside"))
        return graph.vertices.select("pid", "id").join(flags, ["id", "pid"], "left").withColumn("inside", F.coalesce("inside", F.lit(False)))


@dataclass(frozen=True)
class EdgeUpdate:
    """The same update twice: plain, for a target that reads and so writes alone,
    and atomic, for sources that write to a shared target.  Here both are
    aggregates; the atomic one is applied twice, at the sources and at the target."""

    plain: Callable[[Column], Column]
    atomic: Callable[[Column], Column]


MINIMUM = EdgeUpdate(F.min, F.min)
ADDITION = EdgeUpdate(F.sum, F.sum)


def edge_map(
    graph: Graph, subset: VertexSubset, value: Column, update: EdgeUpdate, targets: DataFrame | None = None, threshold: float = 0.05
) -> tuple[DataFrame, str]:
    """(pid, id, got): ``value`` of the subset's vertices combined over their
    out-edges, for ``targets`` (pid, id) or all; and the direction taken."""
    told = subset.sparse().select("pid", F.col("id").alias("src"), value.alias("v"))
    if subset.size + subset.out_edges <= threshold * graph.num_edges:
        got = graph.mail(told, F.col("v"), update.atomic)
        if targets is not None:
            got = got.join(targets.select("pid", "id"), ["id", "pid"], "left_semi")
        return got.withColumnRenamed("msg", "got"), "push"
    outboxes = told.join(graph.routes, ["src", "pid"]).select("tpid", "src", "v").repartition(graph.partitions, "tpid")
    edges = graph.edges_in
    if targets is not None:
        edges = edges.join(targets.select(F.col("pid").alias("tpid"), F.col("id").alias("dst")), ["dst", "tpid"], "left_semi")
    got = edges.join(outboxes, ["src", "tpid"]).groupBy("dst", "tpid").agg(update.plain(F.col("v")).alias("got"))
    return got.select(F.col("tpid").alias("pid"), F.col("dst").alias("id"), "got"), "pull"


def vertex_map(subset: VertexSubset, **columns: Column) -> VertexSubset:
    """New columns for every vertex of the subset."""
    return VertexSubset(subset.rows.withColumns(columns), subset.size, subset.out_edges, subset.is_dense)


def subset_pagerank(graph: Graph, iterations: int = 10, damping: float = 0.85, threshold: float = 0.05) -> DataFrame:
    """Two rank buffers are swapped; the subset is always full."""
    n = float(max(1, graph.num_vertices))
    rows, made = graph.vertices.select("pid", "id", "out_degree").withColumn("rank", F.lit(1.0 / n)), None
    with loop_settings(graph.spark):
        for _ in range(iterations):
            full = VertexSubset.everyone(graph, rows)
            sums, _way = edge_map(graph, full, F.try_divide("rank", "out_degree"), ADDITION, threshold=threshold)
            nxt = VertexSubset(full.rows.drop("rank").join(sums, ["id", "pid"], "left"), full.size, full.out_edges, True)
            nxt = vertex_map(nxt, rank=(1 - damping) / n + damping * F.coalesce("got", F.lit(0.0)))
            before, made = made, cut(nxt.rows.drop("got", "inside"))
            rows = made
            drop(before)
    return rows.select("id", "rank")


def _fall(graph: Graph, start: DataFrame, step: int, threshold: float, once: bool, ways: list[str] | None = None) -> DataFrame:
    """(id, value) falls to the least of its neighbours' plus ``step``; the
    subset holds what fell in the last round.  With ``once`` a value falls only
    once, so vertices that have one are no targets any more."""
    with loop_settings(graph.spark):
        state, made = start, None
        seen = Observation()
        inside = F.col("value") < UNREACHED
        counted = lambda flag: (F.count_if(flag).alias("size"), F.coalesce(F.sum(F.when(flag, F.col("out_degree"))), F.lit(0)).alias("out_edges"))
        made = state = cut(state.withColumn("fell", inside).observe(seen, *counted(inside)))
        while True:
            facts = seen.get
            front = VertexSubset(state.where("fell"), int(facts["size"]), int(facts["out_edges"]))
            targets = state.where(F.col("value") >= UNREACHED) if once else None
            got, way = edge_map(graph, front, F.col("value") + step, MINIMUM, targets, threshold)
            if ways is not None:
                ways.append(way)
            better = F.coalesce(F.col("got") < F.col("value"), F.lit(False))
            fallen = F.when(better, F.col("got")).otherwise(F.col("value"))
            nxt = state.drop("fell").join(got, ["id", "pid"], "left").select("pid", "id", "out_degree", fallen.alias("value"), better.alias("fell"))
            seen = Observation()
            before, made = made, cut(nxt.observe(seen, *counted(F.col("fell"))))
            state = made
            drop(before)
            if not seen.get["size"]:
                return state.select("id", "value")


def subset_components(graph: Graph, threshold: float = 0.05, ways: list[str] | None = None) -> DataFrame:
    start = graph.vertices.select("pid", "id", "out_degree", (F.col("id") + 0).alias("value"))
    return _fall(graph, start, 0, threshold, False, ways).withColumnRenamed("value", "component")


def subset_sssp(graph: Graph, source: int, threshold: float = 0.05, ways: list[str] | None = None) -> DataFrame:
    value = F.when(F.col("id") == source, F.lit(0)).otherwise(F.lit(UNREACHED)).cast("long")
    done = _fall(graph, graph.vertices.select("pid", "id", "out_degree", value.alias("value")), 1, threshold, True, ways)
    return done.select("id", F.when(F.col("value") < UNREACHED, F.col("value")).alias("distance"))
