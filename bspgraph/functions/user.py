"""User functions: whole-vertex Python programs, a table function, SQL views."""

from __future__ import annotations

from abc import ABC, abstractmethod
from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from ..engine import run
from ..graph import Graph
from ..options import Options
from ..program import StepView, Turn, VertexProgram, VertexView
from ..shipping import ship
from .combiners import Combiner


@udtf(returnType="src: bigint, dst: bigint")
class AdjacencyEdges:
    """``adjacency_edges(id, neighbours)``: an edge for each neighbour."""

    def eval(self, id: int, neighbours: list):
        for other in neighbours or ():
            yield id, other


class ArrowVertexProgram(ABC):
    """A program in Python over batches of vertices.

    ``compute(batch, step)`` gets a pandas frame with ``id, out_degree, value,
    message`` (NaN without mail) of the vertices to run and returns ``value``
    and ``payload`` (NaN: sends nothing) for each; vertices always halt.
    Messages are combined by ``combine``: "sum", "min" or "max".
    """

    combine = "min"

    @abstractmethod
    def compute(self, batch: pd.DataFrame, step: int) -> pd.DataFrame:
        """New values and payloads of a batch, in its order."""


class _Batched(VertexProgram):
    """Such a program for the engine: one Arrow function per superstep, inside
    the plan, so the layout and all options stay as they are."""

    def __init__(self, program: ArrowVertexProgram):
        self._program, self.combiner = program, getattr(Combiner, program.combine)()

    def compute(self, me: VertexView, step: StepView) -> Turn:
        program, number = self._program, step.number

        def turn(runs: pd.Series, id: pd.Series, out_degree: pd.Series, value: pd.Series, message: pd.Series) -> pd.DataFrame:
            rows = runs.to_numpy(dtype=bool)
            batch = pd.DataFrame({"id": id, "out_degree": out_degree, "value": value.astype(float), "message": message.astype(float)})
            out = pd.DataFrame({"value": batch["value"], "payload": float("nan")})
            if rows.any():
                found = program.compute(batch.loc[rows], number)
                out.loc[rows, ["value", "payload"]] = found[["value", "payload"]].to_numpy(dtype=float)
            return out

        # annotated afterwards, as names in annotations are not resolved in workers
        turn.__annotations__ = {}
        found = F.pandas_udf(turn, "value double, payload double")(F.col("run"), me.id, me.out_degree, me.value, me.message)
        payload = found["payload"]
        return Turn(value=found["value"], broadcast=payload, when=payload.isNotNull() & ~F.isnan(payload))


def run_arrow(graph: Graph, program: ArrowVertexProgram, options: Options | None = None) -> DataFrame:
    """(id, value) at the end of a Python program, under any options."""
    ship(graph.spark)
    return run(graph, _Batched(program), options).values


def register(spark: SparkSession) -> dict[str, Callable[..., str]]:
    """The table function in SQL, and helpers that run an application on a table
    of edges (src, dst) and leave the result as a view, whose name they return."""
    from ..algorithms import ConnectedComponents, PageRank, ShortestPaths
    from ..algorithms.pagerank import ranks
    from ..algorithms.paths import distances

    spark.udtf.register("adjacency_edges", AdjacencyEdges)

    def view(name, shape):
        def call(table: str, *args, options: Options | None = None) -> str:
            shape(Graph.from_edges(spark.table(table)), args, options).createOrReplaceTempView(name)
            return name

        return call

    return {
        "pagerank": view("bsp_pagerank", lambda g, a, o: ranks(run(g, PageRank(*a), o))),
        "components": view("bsp_components", lambda g, a, o: run(g, ConnectedComponents(), o).values.withColumnRenamed("value", "component")),
        "sssp": view("bsp_sssp", lambda g, a, o: distances(run(g, ShortestPaths(*a), o))),
    }


def recursive_components_sql(table: str, rounds: int = 64) -> str:
    """Components as recursive SQL, for very small graphs only: it lists every
    reachable (vertex, label) pair up to a number of rounds."""
    return f"""
WITH RECURSIVE reach(id, label, n) MAX RECURSION LEVEL {rounds + 2} AS (
  SELECT DISTINCT src, src, 0 FROM {table}
  UNION ALL
  SELECT e.dst, r.label, r.n + 1 FROM reach r JOIN {table} e ON e.src = r.id WHERE r.n < {rounds} AND r.label < e.dst
)
SELECT id, min(label) AS component FROM reach GROUP BY id"""
