"""Single-source shortest paths."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..engine import Run, run
from ..functions.combiners import Combiner
from ..graph import Graph
from ..options import Options
from ..program import StepView, Turn, VertexProgram, VertexView

#: Above any distance; null in results.
UNREACHED = 1 << 62


class ShortestPaths(VertexProgram):
    """The distance falls when mail beats it, and is then told with the edge's
    length added (1 without weights)."""

    value_type = message_type = "long"
    combiner = Combiner.min()

    def __init__(self, source: int):
        self.source = source

    def compute(self, me: VertexView, step: StepView) -> Turn:
        if step.is_first:
            here = me.id == self.source
            return Turn(value=F.when(here, 0).otherwise(UNREACHED), broadcast=F.lit(0), when=here)
        return Turn(value=F.least(me.value, me.message), broadcast=me.message, when=me.message < me.value)

    def on_edge(self, payload: Column, weight: Column | None) -> Column:
        return payload + (F.lit(1) if weight is None else weight.cast("long"))


def distances(done: Run) -> DataFrame:
    distance = F.when(F.col("value") < UNREACHED, F.col("value"))
    return done.values.select("id", distance.alias("distance"))


def sssp(graph: Graph, source: int, options: Options | None = None) -> DataFrame:
    """(id, distance); null where the source does not reach."""
    return distances(run(graph, ShortestPaths(source), options))
