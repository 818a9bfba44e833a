"""Supersteps of a few vertices, at a cost of a few vertices.

When less than ``Options.lookup_most`` messages are in flight, the step no longer
joins tables of the graph's size.  The senders' edges and the receivers' state are
looked up by key, and the few rows that ran are kept beside the tables until
the frontier widens again or the program ends.  The number of rows that come to
the driver here is counted before and bounded by the option.
"""

from __future__ import annotations

import contextlib
import math
import uuid
from collections.abc import Iterator

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from ..graph import Graph
from ..program import VertexProgram
from .checkpoints import pack, remove, shared_folder
from .lookup import Lookup, rows_scanned

#: Rows that are kept beside the tables before they are written as a delta.
MOST_KEPT = 20_000

#: Types whose values can be written into a plan, and how.
PLAIN = {"tinyint": "Y", "smallint": "S", "int": "", "bigint": "L", "float": "F", "double": "D", "boolean": ""}


@contextlib.contextmanager
def uncompiled(spark: SparkSession) -> Iterator[None]:
    """A few rows are read before a plan of their own would be compiled."""
    names = {"spark.sql.codegen.wholeStage": "false", "spark.sql.codegen.factoryMode": "NO_CODEGEN"}
    before = {k: spark.conf.get(k, None) for k in names}
    try:
        for k, v in names.items():
            spark.conf.set(k, v)
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def literal(value, kind: str) -> str:
    """A plain value as SQL."""
    if value is None:
        return f"CAST(NULL AS {kind})"
    if isinstance(value, float) and not math.isfinite(value):
        return f"CAST('{value}' AS {kind})"
    return f"{str(value).lower()}{PLAIN[kind]}" if not isinstance(value, int) or value >= 0 else f"CAST('{value}' AS {kind})"


class Frontier:
    def __init__(self, graph: Graph, program: VertexProgram, base: DataFrame):
        self._graph, self._program, self._spark = graph, program, graph.spark
        self._schema = base.schema
        self._state = Lookup(base, "id", f"{shared_folder(graph.spark)}/state-{uuid.uuid4().hex}")
        self._ran: dict[int, dict] = {}

    def _table(self, rows: list[dict], schema: StructType) -> DataFrame:
        """A few rows as a table; plain values stand in the plan itself."""
        kinds = [f.dataType.simpleString() for f in schema]
        if len(rows) > 1000 or any(k not in PLAIN for k in kinds):
            return self._spark.createDataFrame([tuple(r[n] for n in schema.names) for r in rows], schema, verifySchema=False)
        values = ", ".join("(" + ", ".join(literal(r[n], k) for n, k in zip(schema.names, kinds)) + ")" for r in rows)
        return self._spark.sql(f"SELECT * FROM VALUES {values} AS t(`{'`, `'.join(schema.names)}`)")

    def _joined(self, table: DataFrame, key: str, rows: list[dict], name: str, kind: str) -> DataFrame:
        """``table`` with the column ``name`` of the row that has its key."""
        schema = StructType().add(key, "long").add(name, kind)
        if (simple := schema[1].dataType.simpleString()) in PLAIN:
            pairs = ", ".join(f"{literal(r['id'], 'bigint')}, {literal(r[name], simple)}" for r in rows)
            found = F.expr(f"try_element_at(map({pairs}), `{key}`)")
            return table.withColumn(name, found)
        return table.join(F.broadcast(self._table([r | {key: r["id"]} for r in rows], schema)), key)

    def mail(self, senders: list[dict]) -> tuple[list[dict], int]:
        """(pid, id, msg) for the receivers of these senders (pid, id, payload),
        and the edges read."""
        program, kind = self._program, self._program.message_type
        edges = self._graph.out_lookup.rows([r["pid"] for r in senders], [r["id"] for r in senders])
        message: Column = program.on_edge(F.col("payload"), F.col("weight") if self._graph.weighted else None)
        near = self._joined(edges.coalesce(1), "src", senders, "payload", kind)
        local = near.select("tpid", "dst", message.alias("m")).groupBy("dst", "tpid").agg(program.combiner.partial(F.col("m")).alias("m"))
        boxes = local.groupBy("dst", "tpid").agg(program.combiner.final(F.col("m")).cast(kind).alias("msg"))
        found = boxes.collect()
        return [{"pid": r.tpid, "id": r.dst, "msg": r.msg} for r in found], rows_scanned(boxes)

    def chosen(self, inbox: list[dict]) -> tuple[DataFrame, DataFrame | None]:
        """State and mail of the receivers, and the part of it that is looked up."""
        kind = self._program.message_type
        old = [r for r in inbox if r["id"] not in self._ran]
        parts, looked = [], None
        if old:
            looked = self._state.rows([r["pid"] for r in old], [r["id"] for r in old])
            parts.append(self._joined(looked.coalesce(1), "id", old, "msg", kind))
        if new := [self._ran[r["id"]] | {"msg": r["msg"]} for r in inbox if r["id"] in self._ran]:
            fields = StructType([*self._schema.fields]).add("msg", kind)
            parts.append(self._table(new, fields).coalesce(1))
        out = parts[0] if len(parts) == 1 else parts[0].unionByName(parts[1]).coalesce(1)
        return out.withColumn("run", F.lit(True)), looked

    def keep(self, rows: list[dict]) -> None:
        self._ran.update((r["id"], {n: r[n] for n in self._schema.names}) for r in rows)

    @property
    def full(self) -> bool:
        return len(self._ran) > MOST_KEPT

    def close(self) -> tuple[DataFrame | None, int]:
        """What ran, in the graph's layout, and its rows; the tables go."""
        remove(self._spark, self._state.path)
        if not self._ran:
            return None, 0
        rows = self._table(list(self._ran.values()), self._schema)
        return pack(rows.repartition(self._graph.partitions, "pid").sortWithinPartitions("id", "pid"))[0], len(self._ran)
