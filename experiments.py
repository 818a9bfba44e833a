"""Runs the experiments: applications x graphs x engines x workers.

Each cell is a process of its own, so its peak memory contains no other cell's,
and its session has as many threads as the cell has workers.  Rows are added to
``bspgraph/runs.csv``, which the report queries read.

    python experiments.py --sf 0.01 --workers 1 2 4 --seconds 600
"""

from __future__ import annotations

import argparse
import csv
import os
import subprocess
import sys
import time

from bspgraph import measures, workloads

GRAPHS = list(workloads.STAND_INS.values())
APPS = ["pagerank", "components", "paths"]


def cell(sf_dir: str, graph: str, apps: list[str], engine: str, workers: int) -> None:
    """Measure in this process and print the rows."""
    from pyspark.sql import SparkSession

    spark = (
        SparkSession.builder.master(f"local[{workers}]")
        .config("spark.sql.shuffle.partitions", workers)
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.driver.memory", "4g")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    for row in measures.measure(spark, sf_dir, [graph], apps, [engine]):
        print("row", *row, sep="\t", flush=True)
    spark.stop()


def main() -> None:
    ask = argparse.ArgumentParser()
    ask.add_argument("--data", default="/root/testdata")
    ask.add_argument("--sf", nargs="+", default=["0.01"])
    ask.add_argument("--workers", nargs="+", type=int, default=[1, 2, 4])
    ask.add_argument("--graphs", nargs="+", default=GRAPHS)
    ask.add_argument("--apps", nargs="+", default=APPS)
    ask.add_argument("--engines", nargs="+", default=list(measures.ENGINES))
    ask.add_argument("--seconds", type=float, default=3600, help="start no cell after so long")
    ask.add_argument("--together", action="store_true", help="the applications of a cell in one process: faster, but peaks add up")
    ask.add_argument("--cell", nargs=5)
    args = ask.parse_args()
    if args.cell:
        folder, graph, apps, engine, workers = args.cell
        return cell(folder, graph, apps.split(","), engine, int(workers))
    began, have = time.monotonic(), {r[:5] for r in measures.stored_runs()}
    apps = [",".join(args.apps)] if args.together else args.apps
    todo = [(sf, k, g, a, e) for sf in args.sf for k in args.workers for g in args.graphs for a in apps for e in args.engines]
    for sf, k, g, a, e in todo:
        if time.monotonic() - began > args.seconds:
            break
        if all((e, x, g, k, float(sf)) in have for x in a.split(",")):
            continue
        out = subprocess.run([sys.executable, __file__, "--cell", f"{args.data}/sf{sf}", g, a, e, str(k)], capture_output=True, text=True, timeout=900)
        rows = [x.split("\t")[1:] for x in out.stdout.splitlines() if x.startswith("row\t")]
        if not rows:
            rows = [[e, x, g, str(k), sf, "0", "0.0", "0", measures.Outcome.ABNORMAL_END.value] for x in a.split(",")]
        fresh = not os.path.exists(measures.RUNS_FILE)
        with open(measures.RUNS_FILE, "a", newline="") as file:
            writer = csv.writer(file)
            if fresh:
                writer.writerow([x.split()[0] for x in measures.RUNS.split(", ")])
            writer.writerows(rows)
        print(*rows, sep="\n", flush=True)


if __name__ == "__main__":
    main()
