"""Cost, memory, accuracy and programmability measures."""

from __future__ import annotations

import csv
import enum
import inspect
import os
import re
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import sql, workloads
from .algorithms import ConnectedComponents, PageRank, ShortestPaths, connected_components, sssp
from .baselines import asynchronous, hardcoded, subset
from .engine import run
from .graph import Graph
from .options import NotSupported, Options
from .program import StepView, Turn, VertexProgram, VertexView


class Outcome(enum.Enum):
    """How a measured run ended."""

    DONE = "done"
    ABNORMAL_END = "abnormal end"
    OUT_OF_MEMORY = "out of memory"
    TOO_MANY_FILES = "too many files"
    NOT_SUPPORTED = "not supported"


def outcome_of(error: BaseException | None) -> Outcome:
    if error is None:
        return Outcome.DONE
    text = f"{type(error).__name__} {error}"
    if isinstance(error, NotSupported):
        return Outcome.NOT_SUPPORTED
    if isinstance(error, MemoryError) or "OutOfMemory" in text:
        return Outcome.OUT_OF_MEMORY
    if "Too many open files" in text:
        return Outcome.TOO_MANY_FILES
    return Outcome.ABNORMAL_END


def timed(work: Callable[[], object]) -> tuple[float, Outcome]:
    """Seconds and end of a piece of work; graphs are pinned before."""
    began = time.perf_counter()
    try:
        work()
    except Exception as error:  # noqa: BLE001
        return time.perf_counter() - began, outcome_of(error)
    return time.perf_counter() - began, Outcome.DONE


def peak_rss_bytes(pids: list[int] | None = None) -> int:
    """Sum of the peak resident sets of processes: by default this process, the
    JVM and the Python workers below it."""
    if pids is None:
        pids, seen = [], [os.getpid()]
        below: dict[int, list[int]] = {}
        for name in filter(str.isdigit, os.listdir("/proc")):
            try:
                with open(f"/proc/{name}/stat") as stat:
                    below.setdefault(int(stat.read().rsplit(")", 1)[1].split()[1]), []).append(int(name))
            except OSError:
                continue
        while seen:
            pids.append(seen.pop())
            seen += below.get(pids[-1], [])
    total = 0
    for pid in pids:
        try:
            with open(f"/proc/{pid}/status") as status:
                total += sum(int(x.split()[1]) * 1024 for x in status if x.startswith("VmHWM"))
        except OSError:
            continue
    return total


def speedup_table(runs: DataFrame, base: str, other: str) -> DataFrame:
    """Least, mean and greatest ratio of ``base``'s seconds to ``other``'s over
    worker counts, per graph.  ``runs``: engine, graph, workers, seconds."""
    a = runs.where(F.col("engine") == base).select("graph", "workers", F.col("seconds").alias("a"))
    b = runs.where(F.col("engine") == other).select("graph", "workers", F.col("seconds").alias("b"))
    ratio = a.join(b, ["graph", "workers"]).withColumn("ratio", F.try_divide("a", "b"))
    return ratio.groupBy("graph").agg(F.min("ratio").alias("least"), F.avg("ratio").alias("mean"), F.max("ratio").alias("greatest"))


def strong_scaling(runs: DataFrame) -> DataFrame:
    """Time with one worker over time with k, per engine and graph."""
    one = runs.where("workers = 1").select("engine", "graph", F.col("seconds").alias("one"))
    return runs.join(one, ["engine", "graph"]).select("engine", "graph", "workers", F.try_divide("one", "seconds").alias("gain"))


def graph_scaling(runs: DataFrame) -> DataFrame:
    """Seconds per edge as the graph grows.  ``runs`` has ``edges`` too."""
    return runs.select("engine", "graph", "edges", F.try_divide("seconds", "edges").alias("seconds_per_edge"))


def mailbox_bytes(num_vertices: int, slots: int, width: int = 4) -> int:
    """Bytes that mailboxes of a fixed number of slots reserve."""
    return num_vertices * slots * width


def balance(df: DataFrame) -> DataFrame:
    """Rows per partition: least, mean, greatest, and greatest over mean."""
    sizes = df.groupBy(F.spark_partition_id().alias("p")).agg(F.count(F.lit(1)).alias("n"))
    return sizes.agg(
        F.count(F.lit(1)).alias("partitions"), F.min("n").alias("least"), F.avg("n").alias("mean"), F.max("n").alias("greatest")
    ).withColumn("skew", F.col("greatest") / F.col("mean"))


def agreement(a: DataFrame, b: DataFrame, value: str) -> DataFrame:
    """Rows on one side only, equal and unequal values, greatest difference."""
    x, y = a.select("id", F.col(value).alias("x")), b.select("id", F.col(value).alias("y"))
    both = x.withColumn("in_a", F.lit(1)).join(y.withColumn("in_b", F.lit(1)), "id", "full_outer")
    same = F.col("x").eqNullSafe(F.col("y"))
    return both.agg(
        F.count_if(F.col("in_b").isNull()).alias("only_a"),
        F.count_if(F.col("in_a").isNull()).alias("only_b"),
        F.count_if(same).alias("equal"),
        F.count_if(~same).alias("unequal"),
        F.coalesce(F.max(F.abs(F.col("x") - F.col("y"))).cast("double"), F.lit(0.0)).alias("greatest_difference"),
    )


def top_overlap(a: DataFrame, b: DataFrame, k: int) -> float:
    """Share of the k best of ``a`` that are among those of ``b``."""
    best = lambda df: df.orderBy(F.desc("rank"), "id").limit(k).select("id")
    return best(a).intersect(best(b)).count() / k


# ---- published figures, by graph from small to large ----------------------

#: Peak gigabytes by application; None where a run gave no figure.
PUBLISHED_MEMORY = {
    "pagerank": {"studied": (0.07, 0.48, 1.08, 20.45), "hardcoded": (3.26, 51.95, None, None), "asynchronous": (0.07, 1.41, 3.91, None), "subset": (0.04, 0.51, 1.10, 21.43)},
    "components": {"studied": (0.15, 0.42, 1.03, 20.94), "hardcoded": (None,) * 4, "asynchronous": (1.06, 2.49, 7.58, None), "subset": (0.03, 0.48, 1.07, 20.45)},
    "paths": {"studied": (0.14, 0.47, 1.07, 19.91), "hardcoded": (None,) * 4, "asynchronous": (0.10, 2.49, 7.57, None), "subset": (0.02, 0.42, 1.04, 18.19)},
}
GRAPHS = ("co-authorship", "blogging", "social", "gaming")


def memory_diff_rows() -> list[tuple]:
    """(app, graph, studied, subset, difference in MB, percent, lighter)."""
    rows = []
    for app, by_engine in PUBLISHED_MEMORY.items():
        for name, ours, other in zip(GRAPHS, by_engine["studied"], by_engine["subset"]):
            rows.append((app, name, ours, other, round((ours - other) * 1000), round(100 * abs(ours - other) / max(ours, other)), "studied" if ours < other else "subset"))
    return rows


#: Criteria of the programmability study, and which engine meets them:
#: studied, hard-coded, asynchronous, subset.
CRITERIA = (
    ("per-vertex interface", True, True, True, False),
    ("encapsulated attributes", True, True, False, False),
    ("halting call", True, True, False, False),
)


def meets_criteria(program: type[VertexProgram]) -> tuple[bool, bool, bool]:
    """The criteria checked on what a program does: its turn is made from one
    vertex alone, it reads no column but the vertex's own data and mail, and it
    says when the vertex halts."""
    made = program(0) if "source" in inspect.signature(program).parameters else program()
    turns = [made.compute(VertexView(False, made.combiner), StepView(t, 10)) for t in (0, 1, 10**6)]
    columns = [c for t in turns for c in (t.value, t.broadcast, t.when, t.sends) if c is not None]
    named = {name for c in columns for name in re.findall(r"`?([a-z_]+)`?", str(c)) if name in OTHERS_DATA}
    return all(isinstance(t, Turn) for t in turns), not named, all(t.halt is not None for t in turns)


#: Columns that belong to edges or other vertices.
OTHERS_DATA = ("src", "dst", "tpid", "payload", "weight")


# ---- reports --------------------------------------------------------------

ENGINES: dict[str, dict[str, Callable[[Graph], DataFrame]]] = {
    "studied": {
        "pagerank": lambda g: run(g, PageRank()).values,
        "components": lambda g: connected_components(g, Options("bypass", "auto")),
        "paths": lambda g: sssp(g, workloads.source_of(g), Options("bypass", "auto")),
    },
    "hardcoded": {
        "pagerank": hardcoded.hardcoded_pagerank,
        "components": lambda g: hardcoded.run_hardcoded(g, ConnectedComponents()).values,
        "paths": lambda g: hardcoded.run_hardcoded(g, ShortestPaths(workloads.source_of(g))).values,
    },
    "asynchronous": {
        "pagerank": asynchronous.async_pagerank,
        "components": asynchronous.async_components,
        "paths": lambda g: asynchronous.async_sssp(g, workloads.source_of(g)),
    },
    "subset": {
        "pagerank": subset.subset_pagerank,
        "components": subset.subset_components,
        "paths": lambda g: subset.subset_sssp(g, workloads.source_of(g)),
    },
}


def measure(spark: SparkSession, sf_dir: str, graphs: list[str], apps: list[str], engines: list[str]) -> list[tuple]:
    """Rows of ``RUNS``.  Peaks are of the whole process: one cell a process
    gives peaks that do not contain one another (see ``experiments.py``)."""
    rows = []
    for name in graphs:
        g = workloads.graph(spark, sf_dir, name)
        g.edges_in, g.routes  # noqa: B018  loaded before the clock starts
        for app in apps:
            for engine in engines:
                seconds, end = timed(lambda: ENGINES[engine][app](g).count())  # noqa: B023
                sf = os.path.basename(sf_dir.rstrip("/")).removeprefix("sf")
                rows.append((engine, app, name, spark.sparkContext.defaultParallelism, float(sf), g.num_edges, round(seconds, 3), peak_rss_bytes(), end.value))
    return rows


RUNS = "engine string, app string, graph string, workers int, sf double, edges long, seconds double, peak_bytes long, outcome string"
RUNS_FILE = os.path.join(os.path.dirname(os.path.abspath(__file__)), "runs.csv")


def stored_runs() -> list[tuple]:
    """Runs that ``experiments.py`` measured, one row a cell."""
    kinds = [{"string": str, "int": int, "long": int, "double": float}[x.split()[1]] for x in RUNS.split(", ")]
    if not os.path.exists(RUNS_FILE):
        return []
    with open(RUNS_FILE, newline="") as file:
        return [tuple(kind(x) for kind, x in zip(kinds, row)) for row in list(csv.reader(file))[1:]]


def runs(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(stored_runs(), RUNS)


def _ended(spark: SparkSession, app: str, sf: float) -> DataFrame:
    return runs(spark).where((F.col("outcome") == "done") & (F.col("app") == app) & (F.col("sf") == sf))


def _means(rows: DataFrame) -> DataFrame:
    """Cells that were measured more than once count by their mean."""
    return rows.groupBy("engine", "app", "graph", "workers", "sf", "edges").agg(F.avg("seconds").alias("seconds"))


def speedup_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Components: the studied engine's seconds over the subset engine's, least,
    mean and greatest over worker counts, for each graph."""
    shown = speedup_table(_means(_ended(spark, "components", REPORT_SF)), "studied", "subset")
    return shown.select("graph", *[F.round(c, 6).alias(c) for c in ("least", "mean", "greatest")])


def scaling_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Gain of more workers over one, for every engine, application and graph."""
    cells = _means(runs(spark).where((F.col("outcome") == "done") & (F.col("sf") == REPORT_SF)))
    one = cells.where("workers = 1").select("engine", "app", "graph", F.col("seconds").alias("one"))
    return cells.join(one, ["engine", "app", "graph"]).select("engine", "app", "graph", "workers", F.round(F.try_divide("one", "seconds"), 6).alias("gain"))


def graph_scaling_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Microseconds per edge as the graph grows with the scale factor."""
    cells = _means(runs(spark).where("outcome = 'done' and engine = 'studied'"))
    most = cells.groupBy("app", "graph", "sf").agg(F.max("workers").alias("workers"))
    grown = cells.join(most, ["app", "graph", "sf", "workers"])
    return graph_scaling(grown.withColumn("graph", F.concat_ws("/", "app", "graph"))).select("graph", "edges", F.round(F.col("seconds_per_edge") * 1e6, 4).alias("micros_per_edge"))


def memory_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Peak resident bytes by application, graph and engine, or why there is none."""
    cells = runs(spark).where(F.col("sf") == REPORT_SF)
    return cells.groupBy("engine", "app", "graph", "outcome").agg(F.min(F.when(F.col("outcome") == "done", F.col("peak_bytes"))).alias("peak_bytes"))


#: The scale factor of the stored tables by graph, engine and workers.
REPORT_SF = 0.01


def _values(rows: list[tuple], names: str) -> str:
    literal = lambda x: "NULL" if x is None else f"'{x}'" if isinstance(x, str) else str(x)
    return f"SELECT * FROM (VALUES {', '.join('(' + ', '.join(map(literal, r)) + ')' for r in rows)}) AS t({names})"


def graph_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    parts = []
    for name in SIZED:
        g = workloads.graph(spark, sf_dir, name)
        parts.append((name, g.num_vertices, g.num_edges // 2, g.num_edges))
    return spark.createDataFrame(parts, "graph string, v long, e long, directed long")


SIZED = ("links", "stars", "geo", "chain", "supply", "trade", "basket", "talk", "twins", "similar")
SIZES_SQL = " UNION ALL ".join(
    f"SELECT * FROM (WITH {sql.base(n)} SELECT '{n}' AS graph, (SELECT count(*) FROM v) AS v, (SELECT count(*) FROM e) // 2 AS e, (SELECT count(*) FROM e) AS directed)" for n in SIZED
)
PUBLISHED_VERTICES = (317_080, 4_036_538, 3_072_441, 65_608_366)
MAILBOX_ROWS = [(g, slots, mailbox_bytes(v, slots)) for g, v in zip(GRAPHS, PUBLISHED_VERTICES) for slots in (100, 1)]


def active_balance(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Vertices that run in each superstep of paths, and whether an even deal
    gives no partition more than its share (and one row from each partition)."""
    g = workloads.graph(spark, sf_dir, "supply")
    done = run(g, ShortestPaths(workloads.source_of(g)), Options("bypass", rebalance_active=True, measure_balance=True))
    p = g.partitions
    rows = [(r["superstep"], r["ran"], r["superstep"] == 0 or r["largest"] <= r["ran"] / p + p) for r in done.rows]
    return spark.createDataFrame(rows, "superstep int, active long, even boolean")


def cc_certificate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Violations of what makes labels right: equal along edges, the label is a
    member, and no member is below it."""
    g = workloads.graph(spark, sf_dir, "supply")
    labels = connected_components(g)
    a, b = labels.toDF("src", "x"), labels.toDF("dst", "y")
    torn = g.edges.select("src", "dst").join(a, "src").join(b, "dst").where("x <> y").agg(F.count(F.lit(1)).alias("n"))
    wrong = labels.groupBy("component").agg(F.min("id").alias("least")).where("component <> least").agg(F.count(F.lit(1)).alias("n"))
    return torn.unionByName(wrong).agg(F.sum("n").alias("violations"))


def sssp_certificate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Violations: distances of neighbours differ by more than one, or a reached
    vertex other than the source has no neighbour one step nearer."""
    g = workloads.graph(spark, sf_dir, "supply")
    found = sssp(g, workloads.source_of(g))
    ends = g.edges.select("src", "dst").join(found.toDF("src", "x"), "src").join(found.toDF("dst", "y"), "dst")
    torn = ends.where("abs(x - y) > 1 or (x is null) <> (y is null)").agg(F.count(F.lit(1)).alias("n"))
    near = ends.where("x = y - 1").select(F.col("dst").alias("id")).distinct()
    alone = found.where("distance > 0").join(near, "id", "left_anti").agg(F.count(F.lit(1)).alias("n"))
    return torn.unionByName(alone).agg(F.sum("n").alias("violations"))


def rank_mass(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = workloads.graph(spark, sf_dir, "supply")
    return run(g, PageRank()).values.agg(F.round(F.sum("value"), 8).alias("mass"))


def rank_agreement(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The asynchronous engine's ranks after ten passes against ten synchronous
    rounds: share of the twenty best in common, and whether ranks are near."""
    g = workloads.graph(spark, sf_dir, "geo")
    a, b = run(g, PageRank()).values.withColumnRenamed("value", "rank"), asynchronous.async_pagerank(g)
    near = agreement(a, b, "rank").select("only_a", "only_b", (F.col("greatest_difference") < 0.05).alias("near"))
    return near.withColumn("top_in_common", F.lit(top_overlap(a, b, 20) >= 0.5))


def agreement_cc(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The engine's labels against the subset baseline's."""
    g = workloads.graph(spark, sf_dir, "geo")
    return agreement(connected_components(g), subset.subset_components(g), "component")


def programmability(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.createDataFrame([*CRITERIA], "criterion string, studied boolean, hardcoded boolean, asynchronous boolean, subset boolean")


_STORED = [f"('{r[0]}', '{r[1]}', '{r[2]}', {r[3]}, {r[4]}::DOUBLE, {r[5]}::BIGINT, {r[6]}::DOUBLE, {r[7]}::BIGINT, '{r[8]}')" for r in stored_runs()]
_NAMES = ", ".join(x.split()[0] for x in RUNS.split(", "))
_RUNS = f"r AS (SELECT * FROM (VALUES {', '.join(_STORED)}) AS t({_NAMES}))" if _STORED else f"r AS (SELECT * FROM (VALUES ('', '', '', 0, 0::DOUBLE, 0::BIGINT, 0::DOUBLE, 0::BIGINT, '')) AS t({_NAMES}) WHERE false)"
QUERIES = {
    "graph_sizes": (graph_sizes, SIZES_SQL),
    "active_balance": (active_balance, f"SELECT superstep, ran AS active, true AS even FROM ({sql.path_rounds('supply')})"),
    "mailbox_model": (lambda s, d: s.createDataFrame(MAILBOX_ROWS, "graph string, slots int, bytes long"), _values(MAILBOX_ROWS, "graph, slots, bytes")),
    "published_memory_diff": (
        lambda s, d: s.createDataFrame(memory_diff_rows(), "app string, graph string, studied double, subset double, diff_mb int, percent int, lighter string"),
        _values(memory_diff_rows(), "app, graph, studied, subset, diff_mb, percent, lighter").replace("SELECT *", "SELECT app, graph, studied::DOUBLE AS studied, subset::DOUBLE AS subset, diff_mb, percent, lighter"),
    ),
    "programmability_matrix": (programmability, _values([*CRITERIA], "criterion, studied, hardcoded, asynchronous, subset")),
    "cert_cc_supply": (cc_certificate, "SELECT 0::BIGINT AS violations"),
    "cert_sssp_supply": (sssp_certificate, "SELECT 0::BIGINT AS violations"),
    "rank_mass": (rank_mass, "SELECT 1.0::DOUBLE AS mass"),
    "rank_agreement": (rank_agreement, "SELECT 0::BIGINT AS only_a, 0::BIGINT AS only_b, true AS near, true AS top_in_common"),
    "agreement_cc": (
        agreement_cc,
        f"WITH {sql.base('geo')} SELECT 0::BIGINT AS only_a, 0::BIGINT AS only_b, count(*) AS equal, 0::BIGINT AS unequal, 0.0::DOUBLE AS greatest_difference FROM v",
    ),
    "speedup_report": (speedup_report, f"""
WITH {_RUNS}, m AS (SELECT engine, graph, workers, avg(seconds) AS seconds FROM r WHERE outcome = 'done' AND app = 'components' AND sf = {REPORT_SF} GROUP BY ALL),
q AS (SELECT a.graph, a.seconds / b.seconds AS ratio FROM m a JOIN m b ON a.graph = b.graph AND a.workers = b.workers WHERE a.engine = 'studied' AND b.engine = 'subset')
SELECT graph, round(min(ratio), 6) AS least, round(avg(ratio), 6) AS mean, round(max(ratio), 6) AS greatest FROM q GROUP BY graph"""),
    "scaling_report": (scaling_report, f"""
WITH {_RUNS}, m AS (SELECT engine, app, graph, workers, avg(seconds) AS seconds FROM r WHERE outcome = 'done' AND sf = {REPORT_SF} GROUP BY ALL)
SELECT m.engine, m.app, m.graph, m.workers, round(o.seconds / m.seconds, 6) AS gain FROM m JOIN m o ON o.engine = m.engine AND o.app = m.app AND o.graph = m.graph AND o.workers = 1"""),
    "graph_scaling_report": (graph_scaling_report, f"""
WITH {_RUNS}, m AS (SELECT app, graph, sf, workers, edges, avg(seconds) AS seconds FROM r WHERE outcome = 'done' AND engine = 'studied' GROUP BY ALL)
SELECT app || '/' || graph AS graph, edges, round(seconds / edges * 1e6, 4) AS micros_per_edge FROM m QUALIFY workers = max(workers) OVER (PARTITION BY app, graph, sf)"""),
    "memory_report": (memory_report, f"""
WITH {_RUNS} SELECT engine, app, graph, outcome, min(CASE WHEN outcome = 'done' THEN peak_bytes END) AS peak_bytes FROM r WHERE sf = {REPORT_SF} GROUP BY ALL"""),
}
