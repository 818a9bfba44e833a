"""Times the headline queries and prints one line of JSON.

``BENCH_SF_DIR`` names the tables (default sf0.1), ``BENCH_CPUS`` the threads.
Graphs are built and pinned before the clock starts, as loading is not part of
the processing time; the programs run once on a small graph before, untimed.
PageRank on ``supply`` is timed once more in a session of one thread.
"""

from __future__ import annotations

import json
import os
import subprocess
import sys
import time

from pyspark.sql import SparkSession

from bspgraph import measures, workloads
from bspgraph.algorithms import ConnectedComponents, PageRank, ShortestPaths
from bspgraph.engine import run
from bspgraph.options import Options

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
GRAPHS = ("stars", "supply")


def session(cpus: str) -> SparkSession:
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.driver.memory", "8g")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def pagerank_alone(cpus: str) -> float:
    """Seconds of the second of two runs."""
    g = workloads.graph(session(cpus), SF_DIR, "supply")
    return [run(g, PageRank(), Options()).processing_seconds for _ in range(2)][1]


def main() -> None:
    spark = session(CPUS)
    queries: dict[str, float] = {}
    ratios: dict[str, float] = {}
    bypass = Options("bypass", "auto")
    warm = workloads.graph(spark, SF_DIR, GRAPHS[0])
    for program, options in ((PageRank(), Options()), (ConnectedComponents(), bypass), (ConnectedComponents(), Options("bypass", "pull"))):
        run(warm, program, options)
    for name in GRAPHS:
        g = workloads.graph(spark, SF_DIR, name)
        g.edges_in, g.routes  # noqa: B018  pinned before the clock starts
        source = workloads.source_of(g)
        for app, program, options in (("pr", PageRank(), Options()), ("cc", ConnectedComponents(), bypass), ("sssp", ShortestPaths(source), bypass)):
            queries[f"{app}_{name}"] = round(run(g, program, options).processing_seconds, 3)
        for app in ("pagerank", "components"):
            seconds, _ = measures.timed(lambda: measures.ENGINES["subset"][app](g).count())  # noqa: B023
            queries[f"subset_{app}_{name}"] = round(seconds, 3)
            ours = queries[f"{'pr' if app == 'pagerank' else 'cc'}_{name}"]
            ratios[f"{app}_{name}_studied_over_subset"] = round(ours / seconds, 2)
    g = workloads.graph(spark, SF_DIR, "supply")
    seconds, _ = measures.timed(lambda: measures.ENGINES["hardcoded"]["pagerank"](g).count())
    queries["hardcoded_pagerank_supply"] = round(seconds, 3)
    ratios["pagerank_supply_hardcoded_over_studied"] = round(seconds / queries["pr_supply"], 2)
    seconds, _ = measures.timed(lambda: measures.ENGINES["asynchronous"]["components"](g).count())
    queries["async_components_supply"] = round(seconds, 3)

    # a frontier of a few vertices: what bypass is for
    g = workloads.graph(spark, SF_DIR, "chain")
    g.out_lookup  # noqa: B018
    source, work = workloads.source_of(g), {}
    for selection in ("scan", "bypass"):
        done = run(g, ShortestPaths(source), Options(selection, max_supersteps=12))
        queries[f"sssp_chain_{selection}"] = round(done.processing_seconds, 3)
        work[f"chain_state_rows_read_{selection}"] = done.total("state_read")
    ratios["sssp_chain_scan_over_bypass"] = round(queries["sssp_chain_scan"] / queries["sssp_chain_bypass"], 2)
    try:
        from bspgraph.llm import queries as llm
    except ModuleNotFoundError:
        llm = None
    if llm is not None:
        for name in llm.QUERIES:
            began = time.perf_counter()
            llm.QUERIES[name](spark, SF_DIR).write.format("noop").mode("overwrite").save()
            queries[name] = round(time.perf_counter() - began, 3)
    peak = measures.peak_rss_bytes()
    spark.stop()
    alone = {cpus: float(subprocess.run([sys.executable, __file__, cpus], capture_output=True, text=True, check=True).stdout.split()[-1]) for cpus in ("1", CPUS)}
    ratios[f"pagerank_supply_1_over_{CPUS}_threads"] = round(alone["1"] / alone[CPUS], 2)
    out = {"metric": "total_seconds", "value": round(sum(queries.values()), 3), "unit": "sec", "queries": queries, "sf": SF_DIR.rsplit("sf", 1)[-1], "ratios": ratios, "work": work, "peak_rss_gb": round(peak / 1e9, 2)}
    print(json.dumps(out))


if __name__ == "__main__":
    if len(sys.argv) > 1:
        print(pagerank_alone(sys.argv[1]))
    else:
        main()
