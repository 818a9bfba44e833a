"""The superstep loop.

A superstep is one Spark job: mailboxes of the last payloads, selection, the
program's expressions, and the rows that ran written to the shared folder.  What
ends the loop, and the ledger, are counters observed in that same job.

With bypass only receivers are joined to the state and only their rows are
written, as a delta; when nearly all vertices have mail the state is rewritten in
one go, and when a few have, their edges and states are looked up by key.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .graph import Graph
from .options import Options, PullNotApplicable, SystematicHaltError
from .plans import exchange, select
from .plans.checkpoints import drop, loop_settings, pack
from .plans.frontier import Frontier, uncompiled
from .plans.lookup import rows_scanned
from .plans.store import Store
from .program import ATTRIBUTE, StepView, Turn, VertexProgram, VertexView, broadcasts_only, halts_every_step

LEDGER = (
    "superstep int, ran long, checked long, wasted_checks long, state_read long, state_written long, senders long, messages long, probes long, "
    "wasted_probes long, edges_read long, lost long, awake long, form string, partitions long, largest long, seconds double"
)


@dataclass
class Run:
    """The end of a run: ``state`` and what each superstep did.

    Of a superstep the ledger holds vertices that ran and that were tested, rows
    of state read and written, messages, outboxes probed, edges looked up, and,
    if asked for, partitions that had vertices to run and the most in one.
    """

    state: DataFrame
    rows: list[dict] = field(default_factory=list)

    @property
    def values(self) -> DataFrame:
        return self.state.select("id", "value")

    @property
    def supersteps(self) -> int:
        return len(self.rows)

    @property
    def processing_seconds(self) -> float:
        """Time of the supersteps alone; loading and dumping are not in it."""
        return sum(r["seconds"] for r in self.rows)

    def total(self, counter: str) -> int:
        return sum(r[counter] for r in self.rows)

    @property
    def ledger(self) -> DataFrame:
        names = [x.split()[0] for x in LEDGER.split(", ")]
        return self.state.sparkSession.createDataFrame([[r[n] for n in names] for r in self.rows], LEDGER)

    def write(self, path: str, format: str = "parquet") -> None:
        self.values.write.format(format).save(path)


def check(graph: Graph, program: VertexProgram, options: Options) -> None:
    """Refuse options that would change the program's result."""
    if options.selection == "bypass" and not options.force_bypass and not halts_every_step(program, graph.num_vertices):
        raise SystematicHaltError("vertices without mail would be skipped though they are awake")
    if options.exchange != "push" and not broadcasts_only(program, graph.num_vertices):
        raise PullNotApplicable("only one payload for all neighbours can be pulled")


SELECTION = {"scan": select.scan, "bypass": select.bypass, "none": select.everyone, "receivers": select.receivers}


def choose_vertices(state: DataFrame, inbox: DataFrame | None, program: VertexProgram, options: Options, selection: str | None = None) -> DataFrame:
    """The plan of the vertices that may run, with their mail."""
    if inbox is None:
        chosen = select.first(state, program.message_type if options.combine else f"array<struct<src:long,msg:{program.message_type}>>")
    else:
        chosen = SELECTION[selection or options.selection](state, inbox)
    return chosen if "lost" in chosen.columns else chosen.selectExpr("*", "0 AS lost")


def take_turns(chosen: DataFrame, graph: Graph, program: VertexProgram, options: Options, number: int) -> DataFrame:
    """The plan of their new values, status and payloads."""
    turn: Turn = program.compute(VertexView(not options.combine, program.combiner), StepView(number, graph.num_vertices))
    # the program's columns by name; the engine's own part is text, which costs the
    # driver one call and not one for every operator
    given = {"turn_value": turn.value}
    sends = "run"
    if turn.broadcast is not None:
        given["turn_payload"] = turn.broadcast
        if turn.when is not None:
            given["turn_sends"] = turn.when
            sends = "run AND coalesce(turn_sends, false)"
    if not isinstance(turn.halt, bool):
        given["turn_halts"] = turn.halt
    if turn.sends is not None:
        given["turn_letters"] = turn.sends
    payload = f"CASE WHEN {sends} THEN CAST(turn_payload AS {program.message_type}) END" if turn.broadcast is not None else f"CAST(NULL AS {program.message_type})"
    halted = "turn_halts" if "turn_halts" in given else str(turn.halt).lower()
    columns = [
        "pid",
        "id",
        "out_degree",
        *[f"`{c}`" for c in chosen.columns if c.startswith(ATTRIBUTE)],
        f"CASE WHEN run THEN CAST(turn_value AS {program.value_type}) ELSE value END AS value",
        f"CASE WHEN run THEN {halted} ELSE halted END AS halted",
        f"{payload} AS payload",
        "run AS ran",
        "coalesce(lost, 0) AS lost",
        *(["CASE WHEN run THEN turn_letters END AS sends"] if turn.sends is not None else []),
    ]
    return chosen.withColumns(given).selectExpr(*columns)


def superstep(state: DataFrame, inbox: DataFrame | None, graph: Graph, program: VertexProgram, options: Options, number: int) -> DataFrame:
    """The plan of one superstep: the next state with its payloads."""
    return take_turns(choose_vertices(state, inbox, program, options), graph, program, options, number)


def initial(graph: Graph, program: VertexProgram) -> DataFrame:
    """The state before the first superstep; attributes are set apart by name."""
    extra = [F.col(c).alias(ATTRIBUTE + c) for c in graph.vertices.columns if c not in ("pid", "id", "out_degree")]
    return graph.vertices.select("pid", "id", "out_degree", *extra, F.lit(None).cast(program.value_type).alias("value"), F.lit(False).alias("halted"))


class _Loop:
    """One run: the state, the mail in flight and the ledger."""

    def __init__(self, graph: Graph, program: VertexProgram, options: Options):
        self.graph, self.program, self.options = graph, program, options
        self.store = Store(initial(graph, program), graph.num_vertices, owned=False)
        self.rows: list[dict] = []
        self.made: DataFrame | None = None  # the last rows that were cut
        self.few: list[dict] | None = None  # the last senders, if they are few
        self.frontier: Frontier | None = None

    def sent(self, frame: DataFrame) -> tuple[bool, str, str]:
        """Whether mail is for single neighbours, who sends, and how many."""
        if "sends" in frame.columns:
            return True, "size(coalesce(sends, array())) > 0", "size(sends)"
        return False, "payload IS NOT NULL", "out_degree"

    def wide(self, number: int) -> dict:
        """A superstep over tables."""
        graph, program, options = self.graph, self.program, self.options
        inbox, form = None, "none"
        if number:
            single, sent, _ = self.sent(self.made)
            form = exchange.choose(options, self.rows[-1]["messages"], graph.num_edges)
            probe = "probe" if form.startswith("pull") else None
            move = exchange.push_single if single else exchange.FORMS[form]
            inbox = move(self.made.where(sent), graph, program, options, probe)
        narrow = options.selection == "bypass" and number > 0 and (options.rebalance_active or 2 * self.rows[-1]["messages"] <= graph.num_vertices)
        if narrow:
            base = self.store.base.observe("reading", F.expr("count(1) AS state_read"))
            chosen = self.store.over(choose_vertices(base, inbox, program, options))
            if options.rebalance_active:
                chosen = select.rebalanced(chosen, graph.partitions)
        else:
            chosen = choose_vertices(self.store.current, inbox, program, options, "receivers" if options.selection == "bypass" else None)
        planned = take_turns(chosen, graph, program, options, number)
        _, sent, mails = self.sent(planned)
        planned, seen = pack(
            planned.observe(
                "seen",
                *map(
                    F.expr,
                    (
                        "count(1) AS checked",
                        "count_if(ran) AS ran",
                        f"count_if({sent}) AS senders",
                        f"coalesce(sum(CASE WHEN {sent} THEN {mails} END), 0) AS messages",
                        "count_if(NOT halted) AS awake",
                        "coalesce(sum(lost), 0) AS lost",
                    ),
                ),
            )
        )
        row = {k: int(v) for k, v in seen.items() if k not in ("probes", "wasted_probes", "state_read")}
        if options.selection == "none":
            row["checked"] = row["ran"]
        row |= {"probes": 0, "wasted_probes": 0, "edges_read": 0, "partitions": 0, "largest": 0, "state_read": row["checked"], "form": form}
        row["state_written"] = row["ran"] if narrow else row["checked"]
        row |= {k: int(v) for k, v in seen.items() if k in ("probes", "wasted_probes", "state_read")}
        if options.measure_balance:
            sizes = planned.where("ran").groupBy(F.spark_partition_id()).agg(F.count(F.lit(1)).alias("n"))
            found = sizes.agg(F.count(F.lit(1)), F.coalesce(F.max("n"), F.lit(0))).first()
            row |= {"partitions": found[0], "largest": found[1]}
        if narrow:
            if options.rebalance_active:  # back to the layout, the rows that ran alone
                even, (planned, _) = planned, pack(planned.repartition(graph.partitions, "pid").sortWithinPartitions("id", "pid"))
                drop(even)
            self.store.add(planned, row["ran"])
        else:
            self.store.replace(planned.drop("payload", "ran", "lost", "sends"), planned)
        self.made = planned
        return row

    def lookup(self, number: int) -> dict:
        """A superstep of a few vertices."""
        inbox, edges_read = self.frontier.mail(self.few)
        row = {"probes": 0, "wasted_probes": 0, "lost": 0, "form": "lookup", "partitions": 1, "edges_read": edges_read, "state_read": 0}
        rows: list[dict] = []
        if inbox:
            chosen, looked = self.frontier.chosen(inbox)
            planned = take_turns(chosen.withColumn("lost", F.lit(0)), self.graph, self.program, self.options, number)
            rows = [r.asDict() for r in planned.collect()]
            row["state_read"] = rows_scanned(planned) if looked is not None else 0
        self.frontier.keep(rows)
        self.few = [r for r in rows if r["payload"] is not None]
        return row | {
            "ran": len(rows), "checked": len(rows), "largest": len(rows), "state_written": len(rows), "senders": len(self.few),
            "messages": sum(r["out_degree"] for r in self.few), "awake": sum(not r["halted"] for r in rows),
        }

    def turn_narrow(self) -> None:
        """Go over to lookups, with the senders that wait."""
        self.few = [r.asDict() for r in self.made.where("payload is not null").select("pid", "id", "payload").collect()]
        self.store.fold()
        self.frontier = Frontier(self.graph, self.program, self.store.base)

    def turn_wide(self) -> None:
        """Go back to tables."""
        delta, count = self.frontier.close()
        if delta is not None:
            self.store.add(delta, count)
            kind = self.program.message_type
            told = self.graph.spark.createDataFrame([(r["id"], r["payload"]) for r in self.few], f"id long, payload {kind}")
            self.made = delta.join(F.broadcast(told), "id", "left").select("pid", "id", "out_degree", "payload")
        self.frontier = self.few = None

    def step(self, number: int) -> dict:
        began = time.perf_counter()
        options = self.options
        fits = number > 0 and options.selection == "bypass" and options.combine and options.exchange in ("push", "auto") and not options.rebalance_active
        fits = fits and self.rows[-1]["messages"] <= options.lookup_most and not (self.made is not None and "sends" in self.made.columns)
        if self.frontier is not None and (not fits or self.frontier.full):
            self.turn_wide()
        # a second narrow step in a row: the state is written for lookups once, not at each passing dip
        if self.frontier is None and fits and (number == 1 or self.rows[-2]["messages"] <= options.lookup_most):
            self.turn_narrow()
        if self.frontier is None:
            row = self.wide(number)
        else:
            with uncompiled(self.graph.spark):
                row = self.lookup(number)
        row |= {"superstep": number, "wasted_checks": row["checked"] - row["ran"], "seconds": time.perf_counter() - began}
        self.rows.append(row)
        return row

    def end(self) -> DataFrame:
        if self.frontier is not None:
            self.turn_wide()
        return self.store.current


def run(graph: Graph, program: VertexProgram, options: Options | None = None) -> Run:
    """Run a program until every vertex halts and nothing is in flight."""
    options = options or Options()
    check(graph, program, options)
    with loop_settings(graph.spark):
        loop = _Loop(graph, program, options)
        for number in range(options.max_supersteps):
            if is_finished(loop.step(number), options.selection):
                break
        return Run(loop.end(), loop.rows)


def is_finished(counters: dict, selection: str = "scan") -> bool:
    """All halted and no message in flight; bypass runs receivers alone, so
    without messages it is at its end whoever is awake."""
    return counters["messages"] == 0 and (selection == "bypass" or counters["awake"] == 0)
