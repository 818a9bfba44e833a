"""A graph as tables laid out for supersteps.

Every vertex belongs to one of P partitions by the hash of its identifier, and
carries that partition's label (see ``plans.layout``).  Vertices, edges by source
and edges by target are each written once, clustered by label and sorted, so
joins between them in the loop need no shuffle and each of the P partitions has
its own task.

The out-edges of a hub would make its partition a large one, so they lie with
their targets instead.  A hub has more than a 1 / (``HUBS`` * P) share of the edges;
so there are at most ``HUBS`` * P of them, and what hubs send may be broadcast.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable
from functools import cached_property

from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F

from .options import EngineError
from .plans.checkpoints import cut, loop_settings, pack, shared_folder
from .plans.layout import place
from .plans.lookup import Lookup

#: Directed edges of a partition: 16 bytes each, sorted and streamed.
EDGES_PER_PARTITION = 4_000_000
LEAST_PARTITIONS = 2

#: Hubs a partition at most, and out-edges that never make a hub.
HUBS = 32
NO_HUB = 16

#: Columns of the layout, which attributes cannot be called.
OWN = ("pid", "out_degree", "src", "dst", "tpid")


class Graph:
    """Vertices ``(pid, id, out_degree, attributes)`` and directed edges
    ``(pid, src, tpid, dst[, weight])``; undirected edges are stored both ways.

    ``light`` are the edges that lie with their source, ``heavy`` those of hubs.
    """

    def __init__(self, light: DataFrame, heavy: DataFrame | None, vertices: DataFrame, partitions: int, num_edges: int, num_vertices: int, directed: bool, hub_degree: int):
        self.light, self.heavy, self.vertices, self.hub_degree = light, heavy, vertices, hub_degree
        self.partitions, self.num_edges, self.num_vertices, self.directed = partitions, num_edges, num_vertices, directed
        self.spark = light.sparkSession
        self.weighted = "weight" in light.columns

    @classmethod
    def from_edges(
        cls,
        edges: DataFrame,
        src: str = "src",
        dst: str = "dst",
        *,
        vertices: DataFrame | None = None,
        directed: bool = False,
        weight: str | None = None,
        parallel: str = "merge",
        self_loops: str = "drop",
        partitions: int | None = None,
    ) -> Graph:
        """Parallel edges are merged (the least weight stays) or kept, self-loops
        dropped or kept, edges without two ends left out.  ``vertices`` adds
        isolated vertices and attributes; rows without an id are left out, and of
        rows with one id any one gives the attributes."""
        columns = [F.col(src).cast("long").alias("src"), F.col(dst).cast("long").alias("dst")]
        columns += [F.col(weight).alias("weight")] if weight else []
        e = edges.select(*columns).where("src is not null and dst is not null")
        if self_loops == "drop":
            e = e.where("src <> dst")
        if not directed:
            e = e.unionByName(e.select(F.col("dst").alias("src"), F.col("src").alias("dst"), *(["weight"] if weight else [])))
        if parallel == "merge":
            e = e.groupBy("src", "dst").agg(F.min("weight").alias("weight")) if weight else e.distinct()
        seen = Observation()
        e = cut(e.observe(seen, F.count(F.lit(1)).alias("n")))
        num_edges, spark = int(seen.get["n"]), e.sparkSession
        return cls._laid_out(e, num_edges, vertices, directed, partitions or max(LEAST_PARTITIONS, spark.sparkContext.defaultParallelism, -(-num_edges // EDGES_PER_PARTITION)))

    @classmethod
    def _laid_out(cls, e: DataFrame, num_edges: int, vertices: DataFrame | None, directed: bool, p: int) -> Graph:
        extra: list[str] = []
        with loop_settings(e.sparkSession):
            ends = e.select(F.col("src").alias("id"), F.lit(1).alias("one")).unionByName(e.select(F.col("dst").alias("id"), F.lit(0).alias("one")))
            if vertices is not None:
                extra = [c for c in vertices.columns if c != "id"]
                if clash := [c for c in extra if c in OWN]:
                    raise EngineError(f"attributes cannot be called {', '.join(clash)}")
                vertices = vertices.withColumn("id", F.col("id").cast("long")).where("id is not null").dropDuplicates(["id"])
                ends = ends.unionByName(vertices.select("id", F.lit(0).alias("one")))
            v = ends.groupBy("id").agg(F.sum("one").cast("long").alias("out_degree"))
            if extra:
                v = v.join(vertices, "id", "left")
            limit = max(NO_HUB, num_edges // (HUBS * p))
            v = v.select(place("id", p).alias("pid"), "id", "out_degree", *extra)
            v = v.repartition(p, "pid").sortWithinPartitions("id", "pid")
            v, seen = pack(v.observe("vertices", F.count(F.lit(1)).alias("n"), F.count_if(F.col("out_degree") > limit).alias("hubs")))
            hubs = v.where(F.col("out_degree") > limit).select(F.col("id").alias("src"))
            out = e.select(place("src", p).alias("pid"), "src", place("dst", p).alias("tpid"), "dst", *e.columns[2:])
            heavy = None
            if seen["hubs"]:  # at most HUBS a partition
                heavy, _ = pack(out.join(F.broadcast(hubs), "src", "left_semi").repartition(p, "tpid").sortWithinPartitions("src", "tpid"))
                out = out.join(F.broadcast(hubs), "src", "left_anti")
            out, _ = pack(out.repartition(p, "pid").sortWithinPartitions("src", "pid"))
        return cls(out, heavy, v, p, num_edges, int(seen["n"]), directed, limit)

    @property
    def edges(self) -> DataFrame:
        """All edges, in no order."""
        return self.light if self.heavy is None else self.light.unionByName(self.heavy)

    @cached_property
    def edges_in(self) -> DataFrame:
        """The edges clustered by target and sorted by source, for pulling."""
        with loop_settings(self.spark):
            e = self.edges.select("tpid", "src", "dst", *(["weight"] if self.weighted else []))
            return pack(e.repartition(self.partitions, "tpid").sortWithinPartitions("src", "tpid", "dst"))[0]

    @cached_property
    def routes(self) -> DataFrame:
        """To which partitions a broadcast of each vertex has to go."""
        with loop_settings(self.spark):
            e = self.edges.select("pid", "src", "tpid").distinct()
            return pack(e.repartition(self.partitions, "pid").sortWithinPartitions("src", "pid"))[0]

    @cached_property
    def out_lookup(self) -> Lookup:
        """The edges as a table from which those of a few sources can be read."""
        with loop_settings(self.spark):
            e = self.edges if self.heavy is None else self.edges.repartition(self.partitions, "pid")
            return Lookup(e, "src", f"{shared_folder(self.spark)}/edges-{uuid.uuid4().hex}")

    def sent(self, senders: DataFrame) -> tuple[DataFrame, DataFrame | None]:
        """``senders`` (pid, src, and more) with their out-edges where these lie:
        of light ones in the senders' partitions, of hubs in the targets'."""
        near = senders.join(self.light, ["src", "pid"])
        if self.heavy is None:
            return near, None
        hubs = self.vertices.where(F.col("out_degree") > self.hub_degree).select(F.col("id").alias("src"))
        few = senders.drop("pid").join(F.broadcast(hubs), "src", "left_semi")  # HUBS a partition at most
        return near, self.heavy.join(F.broadcast(few), "src")

    def mail(
        self, senders: DataFrame, message: Column, partial: Callable[[Column], Column], final: Callable[[Column], Column] | None = None, into: Column | None = None
    ) -> DataFrame:
        """(pid, id, msg): ``message`` (over the senders' columns, and ``weight``)
        along all out-edges, or those whose ``dst`` is ``into``, combined before
        and after the one shuffle."""
        near, far = self.sent(senders)
        if into is not None:
            near, far = near.where(into), far if far is None else far.where(into)
        final = final or partial
        m = F.col("m")
        first = partial(m).alias("m")
        local = near.withColumn("m", message).groupBy("pid", "tpid", "dst").agg(first).select("tpid", "dst", "m")
        if far is not None:
            local = local.unionByName(far.withColumn("m", message).groupBy("dst", "tpid").agg(first))
        boxes = local.repartition(self.partitions, "tpid").groupBy("dst", "tpid").agg(final(m).alias("msg"))
        return boxes.selectExpr("tpid AS pid", "dst AS id", "msg")

    def reverse(self) -> Graph:
        """The graph with its edges turned around."""
        e = self.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), *(["weight"] if self.weighted else []))
        return Graph.from_edges(
            e, vertices=self.vertices.drop("pid", "out_degree"), directed=True, weight="weight" if self.weighted else None, partitions=self.partitions, self_loops="keep", parallel="keep"
        )

    def subgraph(self, predicate: Column) -> Graph:
        """The graph induced by the vertices that ``predicate`` holds for."""
        kept = self.vertices.where(predicate).drop("pid", "out_degree")
        ids = kept.select("id")
        e = self.edges.join(ids.withColumnRenamed("id", "src"), "src", "left_semi").join(ids.withColumnRenamed("id", "dst"), "dst", "left_semi")
        part = Graph.from_edges(e, vertices=kept, directed=True, weight="weight" if self.weighted else None, self_loops="keep", parallel="keep")
        part.directed = self.directed
        return part

    def out_degrees(self) -> DataFrame:
        return self.vertices.select("id", F.col("out_degree").alias("degree"))

    def in_degrees(self) -> DataFrame:
        return self.edges.groupBy(F.col("dst").alias("id")).agg(F.count(F.lit(1)).alias("degree"))

    def to_adjacency(self, direction: str = "out") -> DataFrame:
        """(id, neighbours): sorted arrays of out- or in-neighbours."""
        here, there = ("src", "dst") if direction == "out" else ("dst", "src")
        return self.edges.groupBy(F.col(here).alias("id")).agg(F.array_sort(F.collect_list(there)).alias("neighbours"))

    def save(self, table: str) -> None:
        """Vertices and edges as tables ``<table>_vertices`` and ``_edges``, laid
        out by partition label in buckets, with what else the graph knows."""
        n = self.partitions
        facts = {"bsp.partitions": n, "bsp.edges": self.num_edges, "bsp.directed": self.directed}
        self.edges.write.bucketBy(n, "pid").sortBy("pid", "src").mode("overwrite").saveAsTable(f"{table}_edges")
        self.vertices.write.bucketBy(n, "pid").sortBy("pid", "id").mode("overwrite").saveAsTable(f"{table}_vertices")
        listed = ", ".join(f"'{k}'='{v}'" for k, v in facts.items())
        self.spark.sql(f"ALTER TABLE {table}_vertices SET TBLPROPERTIES ({listed})")

    @classmethod
    def load(cls, spark, table: str) -> Graph:
        """A saved graph.  Its buckets are its partitions: nothing is counted,
        hashed or merged again, and bucketed scans need no shuffle."""
        facts = {r["key"]: r["value"] for r in spark.sql(f"SHOW TBLPROPERTIES {table}_vertices").collect()}
        p, num_edges, directed = int(facts["bsp.partitions"]), int(facts["bsp.edges"]), facts["bsp.directed"] == "True"
        limit = max(NO_HUB, num_edges // (HUBS * p))
        with loop_settings(spark):
            v = spark.table(f"{table}_vertices").sortWithinPartitions("id", "pid")
            v, seen = pack(v.observe("vertices", F.count(F.lit(1)).alias("n"), F.count_if(F.col("out_degree") > limit).alias("hubs")))
            e, heavy = spark.table(f"{table}_edges"), None
            if seen["hubs"]:
                hubs = v.where(F.col("out_degree") > limit).select(F.col("id").alias("src"))
                heavy, _ = pack(e.join(F.broadcast(hubs), "src", "left_semi").repartition(p, "tpid").sortWithinPartitions("src", "tpid"))
                e = e.join(F.broadcast(hubs), "src", "left_anti")
            light, _ = pack(e.sortWithinPartitions("src", "pid"))
        return cls(light, heavy, v, p, num_edges, int(seen["n"]), directed, limit)
