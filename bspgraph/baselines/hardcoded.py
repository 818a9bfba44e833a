"""A synchronous engine fixed to PageRank: all vertices run in every superstep,
mailboxes are queues of bounded length and what does not fit is lost."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..algorithms.pagerank import PageRank
from ..engine import Run, run
from ..graph import Graph
from ..options import NotSupported, Options
from ..program import VertexProgram

SLOTS = 100


def run_hardcoded(graph: Graph, program: VertexProgram, mailbox_limit: int = SLOTS) -> Run:
    if not isinstance(program, PageRank):
        raise NotSupported("without selection of vertices only PageRank can be run")
    return run(graph, program, Options(selection="none", combine=False, mailbox_limit=mailbox_limit))


def hardcoded_pagerank(graph: Graph, iterations: int = 10, damping: float = 0.85, mailbox_limit: int = SLOTS) -> DataFrame:
    return run_hardcoded(graph, PageRank(iterations, damping), mailbox_limit).values.withColumnRenamed("value", "rank")


def lost_messages(graph: Graph, mailbox_limit: int = SLOTS) -> DataFrame:
    """(id, lost): what each mailbox loses when every vertex sends."""
    degrees = graph.in_degrees().where(F.col("degree") > mailbox_limit)
    return degrees.select("id", (F.col("degree") - mailbox_limit).alias("lost"))
