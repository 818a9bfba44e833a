"""Sources, user functions, streams, measures and SQL answers."""

import pandas as pd
import pytest
from helpers import assert_same
from pyspark.sql import functions as F

from bspgraph import measures, registry, workloads
from bspgraph.algorithms import connected_components
from bspgraph.functions import user
from bspgraph.graph import Graph
from bspgraph.options import Options
from bspgraph.sources import edgelist, files
from bspgraph.streaming import incremental, windows

FAST = ["pr_async_ten_geo", "pr_reference_form_geo", "cc_subset_push_stars", "cc_subset_pull_stars", "sssp_subset_push_links", "sssp_subset_pull_links", "pr_subset_links", "pr_links", "pr_links_directed", "pr_links_spread", "cc_geo", "cc_twins", "sssp_geo", "pr_hardcoded_supply", "sssp_weighted_trade", "cc_sizes_stars"]


@pytest.mark.parametrize("name", FAST + [n for t in (measures.QUERIES, windows.QUERIES) for n, (_, q) in t.items() if q])
def test_answers_of_sql(spark, sf, duck, name):
    assert_same(registry.QUERIES[name](spark, sf).toPandas(), duck.sql(registry.ORACLES[name]).df())


def test_relational_answers_of_sql(spark, sf, duck):
    from bspgraph.operators import relational

    for name, (query, oracle) in relational.QUERIES.items():
        try:
            assert_same(query(spark, sf).toPandas(), duck.sql(oracle).df())
        except AssertionError as error:
            raise AssertionError(name) from error


def test_edge_files(spark, tmp_path):
    text = tmp_path / "edges.txt"
    text.write_text("# a comment\n1 2\n2\t3\n\n30 4\nx y\n")
    want = [(1, 2), (2, 3), (30, 4)]
    assert sorted(map(tuple, files.read_edge_list(spark, str(text)).collect())) == want
    text.write_text("# a comment\n1 2\n2\t3\n30 4\n")
    edgelist.register(spark)
    for n in (1, 3, 7):
        got = spark.read.format("edgelist").option("path", str(text)).option("partitions", n).load()
        assert sorted(map(tuple, got.collect())) == want
    g = Graph.from_edges(spark.createDataFrame(want, files.EDGE_SCHEMA))
    files.write_adjacency(g.to_adjacency(), str(tmp_path / "adj"))
    back = files.read_adjacency(spark, str(tmp_path / "adj"))
    assert sorted(map(tuple, back.collect())) == sorted([*want, *((b, a) for a, b in want)])
    for form in ("parquet", "json", "orc", "csv"):
        spark.createDataFrame(want, files.EDGE_SCHEMA).write.option("header", True).format(form).save(str(tmp_path / form))
        assert sorted(map(tuple, files.read_edges(spark, str(tmp_path / form), form).collect())) == want


class LeastId(user.ArrowVertexProgram):
    def compute(self, batch, step):
        if step == 0:
            return pd.DataFrame({"value": batch["id"].astype(float), "payload": batch["id"].astype(float)})
        low = batch[["value", "message"]].min(axis=1)
        return pd.DataFrame({"value": low, "payload": low.where(low < batch["value"])})


def test_python_programs_table_function_and_sql(spark, sf):
    from pyspark import cloudpickle
    import sys

    cloudpickle.register_pickle_by_value(sys.modules[__name__])
    g = workloads.graph(spark, sf, "geo")
    want = {r.id: r.component for r in connected_components(g).collect()}
    for options in (None, Options("bypass", "pull"), Options("bypass", combine=False)):
        assert {r.id: int(r.value) for r in user.run_arrow(g, LeastId(), options).collect()} == want
    calls = user.register(spark)
    g.edges.select("src", "dst").createOrReplaceTempView("geo_edges")
    assert {r.id: r.component for r in spark.table(calls["components"]("geo_edges")).collect()} == want
    assert spark.table(calls["pagerank"]("geo_edges")).count() == len(want)
    assert spark.sql("SELECT * FROM adjacency_edges(1, array(2L, 3L))").count() == 2
    spark.createDataFrame([(1, 2), (2, 1), (2, 3), (3, 2), (7, 8), (8, 7)], "src long, dst long").createOrReplaceTempView("tiny")
    rows = spark.sql(user.recursive_components_sql("tiny", 5)).collect()
    assert {r.id: r.component for r in rows} == {1: 1, 2: 1, 3: 1, 7: 7, 8: 7}


def test_streams(spark, sf, tmp_path):
    edges = workloads.supply(spark, sf).distinct().repartition(3)
    edges.write.parquet(str(tmp_path / "edges"))
    grown = incremental.IncrementalComponents(spark)
    stream = files.stream_edges(spark, str(tmp_path / "edges"))
    stream.writeStream.foreachBatch(grown.batch()).option("checkpointLocation", str(tmp_path / "c1")).trigger(availableNow=True).start().awaitTermination()
    want = {r.id: r.component for r in connected_components(workloads.graph(spark, sf, "supply")).collect()}
    assert {r.id: r.component for r in grown.labels.collect()} == want



def _ran(stream, name, folder, mode="append"):
    stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", str(folder)).trigger(availableNow=True).start().awaitTermination()


def _files(spark, folder, batches, schema):
    """One file a batch, in their order."""
    import os
    import time

    for n, rows in enumerate(batches):
        frame = rows if not isinstance(rows, list) else spark.createDataFrame(rows, schema)
        frame.coalesce(1).write.mode("append").parquet(str(folder))
        newest = max((os.path.join(folder, f) for f in os.listdir(folder) if f.endswith(".parquet")), key=os.path.getmtime)
        os.utime(newest, (time.time() - 1000 + n,) * 2)


EVENT = "event_id long, user_id long, ts timestamp"


def test_events_are_chained_in_order_of_time(spark, sf, tmp_path):
    from datetime import datetime, timedelta

    at = lambda h, m=0, d=1: datetime(2024, 1, d, h, m)
    batches = [[(1, 7, at(10)), (3, 7, at(10, 20)), (9, 8, at(9, 50))], [(2, 7, at(10, 10)), (8, 8, at(9, 40))], [(0, -1, at(0, 0, 3))], [(4, 7, at(10, 15)), (5, 7, at(1, 0, 3))], [(0, -1, at(0, 0, 9))]]
    batches += [[(6, 7, at(10, 16)), (0, -1, at(0, 0, 10))], [(0, -1, at(0, 0, 12))]]
    _files(spark, tmp_path / "a", batches, EVENT)
    _ran(incremental.chain_stream(files.stream_edges(spark, str(tmp_path / "a"), schema=EVENT)), "ordered", tmp_path / "c")
    got = sorted(map(tuple, spark.table("ordered").where("src > 0").collect()))
    # event 4 came before those around it were chained, event 6 after
    assert got == [(1, 2), (2, 4), (3, 5), (4, 3), (8, 9)]

    events = workloads.table(spark, sf, "events").select("event_id", "user_id", F.col("ts").cast("timestamp").alias("ts"))
    end = events.agg(F.max("ts")).first()[0] + timedelta(days=2)
    _files(spark, tmp_path / "b", [events, [(-5, -1, end)], [(-6, -1, end + timedelta(days=2))]], EVENT)
    _ran(incremental.chain_stream(files.stream_edges(spark, str(tmp_path / "b"), schema=EVENT)), "chained", tmp_path / "d")
    assert sorted(map(tuple, spark.table("chained").where("src >= 0").collect())) == sorted(map(tuple, workloads.chain(spark, sf).collect()))


def test_late_rows_are_dropped_from_windows(spark, tmp_path):
    from datetime import datetime

    day = lambda d: datetime(2024, 1, d, 10)
    _files(spark, tmp_path / "a", [[(1, 7, day(1))], [(2, 7, day(3))], [(4, 7, day(9))], [(3, 7, day(1))], [(5, 7, day(20))]], EVENT)
    stream = windows.with_watermark(files.stream_edges(spark, str(tmp_path / "a"), schema=EVENT))
    _ran(windows.windowed(stream, "tumbling"), "counted", tmp_path / "c")
    assert {r.opens.day: r.degree for r in spark.table("counted").collect()} == {1: 1, 3: 1, 9: 1}


def test_measures(spark):
    runs = spark.createDataFrame([("a", "g", 1, 4.0), ("b", "g", 1, 2.0), ("a", "g", 2, 3.0), ("b", "g", 2, 1.0)], "engine string, graph string, workers int, seconds double")
    assert tuple(measures.speedup_table(runs, "a", "b").first()) == ("g", 2.0, 2.5, 3.0)
    assert {r.gain for r in measures.strong_scaling(runs).where("workers = 2").collect()} == {4 / 3, 2.0}
    assert measures.mailbox_bytes(65_608_366, 100) == 26_243_346_400
    assert [r[-1] for r in measures.memory_diff_rows()].count("subset") == 7
    assert max(r[4] for r in measures.memory_diff_rows()) == 1720
    assert measures.outcome_of(None) is measures.Outcome.DONE
    assert measures.outcome_of(MemoryError()) is measures.Outcome.OUT_OF_MEMORY
    assert measures.outcome_of(OSError("Too many open files")) is measures.Outcome.TOO_MANY_FILES
    assert measures.peak_rss_bytes() > 50_000_000
    from bspgraph.algorithms import PageRank

    assert measures.meets_criteria(PageRank) == (True, True, True)
    text = measures.sql.EDGES["geo"]
    assert text and measures.top_overlap(*[spark.createDataFrame([(1, 0.5), (2, 0.4), (3, x)], "id long, rank double") for x in (0.1, 0.9)], 2) == 0.5
    scaled = spark.createDataFrame([("a", "g", 10, 2.0)], "engine string, graph string, edges long, seconds double")
    assert measures.graph_scaling(scaled).first().seconds_per_edge == 0.2
