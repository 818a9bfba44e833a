"""PageRank over supersteps."""

from __future__ import annotations

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from ..engine import Run, run
from ..functions.combiners import Combiner
from ..graph import Graph
from ..options import EngineError, Options
from ..plans.checkpoints import cut, drop, loop_settings
from ..program import StepView, Turn, VertexProgram, VertexView


class PageRank(VertexProgram):
    """A fixed number of rank updates; a rank is shared out over the out-edges.
    Vertices stay awake to the end, mail or not, so none may be skipped."""

    combiner = Combiner.sum()

    def __init__(self, iterations: int = 10, damping: float = 0.85):
        self.iterations, self.damping = iterations, damping

    def compute(self, me: VertexView, step: StepView) -> Turn:
        n = float(max(1, step.num_vertices))
        if step.is_first:
            rank = F.lit(1.0 / n)
        else:
            rank = (1.0 - self.damping) / n + self.damping * F.coalesce(me.message, F.lit(0.0))
        if step.number >= self.iterations:
            return Turn(value=rank, halt=True)
        return Turn(value=rank, broadcast=F.try_divide(rank, me.out_degree), when=me.out_degree > 0, halt=False)


def pagerank(
    graph: Graph, iterations: int = 10, damping: float = 0.85, options: Options | None = None, dangling: str = "leak"
) -> DataFrame:
    """(id, rank).  Vertices without out-edges let their rank leak, or spread it
    over all vertices."""
    if dangling == "spread":
        return _spread(graph, iterations, damping)
    if dangling != "leak":
        raise EngineError(f"unknown rule {dangling!r} for vertices without out-edges")
    return ranks(run(graph, PageRank(iterations, damping), options))


def ranks(done: Run) -> DataFrame:
    return done.values.withColumnRenamed("value", "rank")


def _step(graph: Graph, state: DataFrame, damping: float, lost: float = 0.0) -> DataFrame:
    """One update of (pid, id, out_degree, value) by a push of shares."""
    told = state.select("pid", F.col("id").alias("src"), F.try_divide("value", "out_degree").alias("share"))
    mail = graph.mail(told, F.col("share"), F.sum)
    n = float(max(1, graph.num_vertices))
    rank = (1 - damping) / n + damping * (F.coalesce("msg", F.lit(0.0)) + lost / n)
    return state.join(mail, ["id", "pid"], "left").select("pid", "id", "out_degree", rank.alias("value"), F.col("value").alias("old"))


def _start(graph: Graph) -> DataFrame:
    return graph.vertices.select("pid", "id", "out_degree").withColumn("value", F.lit(1.0 / max(1, graph.num_vertices)))


def _spread(graph: Graph, iterations: int, damping: float) -> DataFrame:
    state, made = _start(graph), None
    with loop_settings(graph.spark):
        for _ in range(iterations):
            lost = state.where("out_degree = 0").agg(F.coalesce(F.sum("value"), F.lit(0.0))).first()[0]
            before, made = made, cut(_step(graph, state, damping, lost))
            state = made.drop("old")
            drop(before)
    return state.select("id", F.col("value").alias("rank"))


def pagerank_converged(graph: Graph, tolerance: float = 1e-6, max_iterations: int = 300, damping: float = 0.85) -> tuple[DataFrame, int]:
    """(id, rank) once the ranks' total change is below ``tolerance``, and the
    number of updates.  The change is observed in the update's own job."""
    state, made, done = _start(graph), None, 0
    with loop_settings(graph.spark):
        while done < max_iterations:
            seen = Observation()
            moved = F.sum(F.abs(F.col("value") - F.col("old")))
            before, made = made, cut(_step(graph, state, damping).observe(seen, F.coalesce(moved, F.lit(0.0)).alias("change")))
            state = made.drop("old")
            drop(before)
            done += 1
            if seen.get["change"] < tolerance:
                break
    return state.select("id", F.col("value").alias("rank")), done


def top_ranked(ranked: DataFrame, k: int) -> DataFrame:
    """The k best, by rank and then id."""
    return ranked.orderBy(F.desc("rank"), "id").limit(k)
