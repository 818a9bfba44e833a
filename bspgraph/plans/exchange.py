"""How payloads become mailboxes: one shuffle in every form.

A mailbox table is ``(pid, id, msg)``, clustered by ``pid`` like the state.
``senders`` is the last state where a payload is set.  Pulling forms observe the
outboxes that their join reads, and those found empty, under the name ``probe``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..graph import Graph
from ..options import Options
from ..program import VertexProgram
from .layout import place


def _message(graph: Graph, program: VertexProgram) -> Column:
    return program.on_edge(F.col("payload"), F.col("weight") if graph.weighted else None)


def push(senders: DataFrame, graph: Graph, program: VertexProgram, options: Options, probe: str | None = None) -> DataFrame:
    """Senders write to their out-neighbours' mailboxes."""
    told = senders.selectExpr("pid", "id AS src", "payload")
    if options.combine:
        return graph.mail(told, _message(graph, program), program.combiner.partial, program.combiner.final)
    near, far = graph.sent(told)
    mail = [x.select("tpid", "dst", "src", _message(graph, program).alias("m")) for x in (near, far) if x is not None]
    return _boxed(mail[0] if len(mail) == 1 else mail[0].unionByName(mail[1]), graph, program, options)


def push_single(senders: DataFrame, graph: Graph, program: VertexProgram, options: Options, probe: str | None = None) -> DataFrame:
    """Payloads for single neighbours; those to unknown ids are dropped by the
    join with the state."""
    one = senders.select("pid", F.col("id").alias("src"), F.explode("sends").alias("s"))
    to = F.col("s.to").cast("long")
    mail = one.select("pid", place(to, graph.partitions).alias("tpid"), "src", to.alias("dst"), F.col("s.msg").alias("m"))
    return _boxed(mail, graph, program, options)


def _boxed(mail: DataFrame, graph: Graph, program: VertexProgram, options: Options) -> DataFrame:
    """Mail (tpid, src, dst, m) where it is made, to mailboxes at the receivers."""
    if options.combine:
        local = mail.groupBy("pid", "tpid", "dst").agg(program.combiner.partial(F.col("m")).alias("m"))
        boxes = local.repartition(graph.partitions, "tpid").groupBy("dst", "tpid").agg(program.combiner.final(F.col("m")).alias("msg"))
        return boxes.select(F.col("tpid").alias("pid"), F.col("dst").alias("id"), "msg")
    return _queued(mail.select("tpid", "dst", "src", "m").repartition(graph.partitions, "tpid"), options)


def _queued(mail: DataFrame, options: Options) -> DataFrame:
    """Queues in the order of senders.  A bounded mailbox numbers its mail as it
    comes by sender and keeps the first; the rest is only counted, so a receiver
    of very much mail is never one long array."""
    one = F.struct("src", F.col("m").alias("msg"))
    names = (F.col("tpid").alias("pid"), F.col("dst").alias("id"))
    if options.mailbox_limit is None:
        boxes = mail.groupBy("dst", "tpid").agg(F.sort_array(F.collect_list(one)).alias("msg"))
        return boxes.select(*names, "msg")
    place_in_box = F.row_number().over(Window.partitionBy("dst", "tpid").orderBy("src"))
    kept = F.when(F.col("place_in_box") <= options.mailbox_limit, one)
    boxes = mail.withColumn("place_in_box", place_in_box).groupBy("dst", "tpid").agg(F.sort_array(F.collect_list(kept)).alias("msg"), F.count(F.lit(1)).alias("n"))
    return boxes.select(*names, "msg", F.greatest(F.col("n") - options.mailbox_limit, F.lit(0)).alias("lost"))


def pull(senders: DataFrame, graph: Graph, program: VertexProgram, options: Options, probe: str | None = None) -> DataFrame:
    """Receivers read the one stored payload of each in-neighbour: a payload
    goes once to every partition that holds a neighbour, and is read there."""
    routed = senders.selectExpr("pid", "id AS src", "payload").join(graph.routes, ["src", "pid"])
    outboxes = routed.select("tpid", "src", "payload").repartition(graph.partitions, "tpid")
    return _read(graph.edges_in.join(outboxes, ["src", "tpid"], "left"), graph, program, options, probe)


def pull_addressed(senders: DataFrame, graph: Graph, program: VertexProgram, options: Options, probe: str | None = None) -> DataFrame:
    """Outboxes with one entry per receiver: general, and as large as the mail."""
    near, far = graph.sent(senders.select("pid", F.col("id").alias("src"), "payload"))
    parts = [x.select("tpid", "src", "dst", "payload") for x in (near, far) if x is not None]
    outbox = (parts[0] if len(parts) == 1 else parts[0].unionByName(parts[1])).repartition(graph.partitions, "tpid")
    return _read(graph.edges_in.join(outbox, ["src", "tpid", "dst"], "left"), graph, program, options, probe)


def _read(read: DataFrame, graph: Graph, program: VertexProgram, options: Options, probe: str | None) -> DataFrame:
    """Mailboxes from every in-edge and the payload found for it, or none."""
    if probe is not None:
        read = read.observe(probe, F.expr("count(1) AS probes"), F.expr("count_if(payload IS NULL) AS wasted_probes"))
    mail = read.where("payload is not null").select("tpid", "src", "dst", _message(graph, program).alias("m"))
    if not options.combine:
        return _queued(mail, options)
    partial, final = program.combiner.partial, program.combiner.final
    if partial is not final:  # all mail of a receiver lies here: else one pass does
        mail = mail.groupBy("dst", "tpid").agg(partial(F.col("m")).alias("m"))
    boxes = mail.groupBy("dst", "tpid").agg(final(F.col("m")).alias("msg"))
    return boxes.selectExpr("tpid AS pid", "dst AS id", "msg")


FORMS = {"push": push, "pull": pull, "pull_addressed": pull_addressed}


def choose(options: Options, messages: int, num_edges: int) -> str:
    """The form of this step: ``auto`` pulls when much of the graph sends."""
    if options.exchange != "auto":
        return options.exchange
    return "pull" if messages > options.switch_threshold * num_edges else "push"
