"""Connected components by spreading least identifiers."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..engine import run
from ..functions.combiners import Combiner
from ..graph import Graph
from ..options import EngineError, Options
from ..program import StepView, Turn, VertexProgram, VertexView


class ConnectedComponents(VertexProgram):
    """The label is the least identifier heard of; it is told when it falls."""

    value_type = message_type = "long"
    combiner = Combiner.min()

    def compute(self, me: VertexView, step: StepView) -> Turn:
        if step.is_first:
            return Turn(value=me.id, broadcast=me.id)
        return Turn(value=F.least(me.value, me.message), broadcast=me.message, when=me.message < me.value)


def connected_components(graph: Graph, options: Options | None = None) -> DataFrame:
    """(id, component) of an undirected graph."""
    if graph.directed:
        raise EngineError("components are of undirected graphs; see min_reaching_id")
    return min_reaching_id(graph, options)


def min_reaching_id(graph: Graph, options: Options | None = None) -> DataFrame:
    """(id, component): the least identifier with a path to the vertex."""
    return run(graph, ConnectedComponents(), options).values.withColumnRenamed("value", "component")


def component_sizes(components: DataFrame) -> DataFrame:
    return components.groupBy("component").agg(F.count(F.lit(1)).alias("n"))
