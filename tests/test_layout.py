"""Layout, bypass, storage and hard inputs of the engine."""

import os
import random
import time
from dataclasses import replace

import pytest
from pyspark import StorageLevel
from pyspark.sql import functions as F

from bspgraph import engine, registry, workloads
from bspgraph.algorithms import ConnectedComponents, PageRank, ShortestPaths, connected_components, pagerank, sssp
from bspgraph.algorithms.pagerank import pagerank_converged
from bspgraph.baselines import asynchronous, subset
from bspgraph.engine import run
from bspgraph.functions.combiners import Combiner
from bspgraph.graph import Graph
from bspgraph.options import EngineError, Options
from bspgraph.plans import checkpoints, exchange, inspect
from bspgraph.plans.checkpoints import cut, loop_settings
from bspgraph.plans.layout import place
from bspgraph.program import Turn, VertexProgram

SF = "/root/testdata/sf0.01"


def make(spark, pairs, ids=None, **kw):
    vertices = spark.createDataFrame([(i,) for i in ids], "id long") if ids else None
    return Graph.from_edges(spark.createDataFrame(pairs, "src long, dst long"), vertices=vertices, **kw)


def values(df):
    return {r[0]: r[1] for r in df.collect()}


def sizes(df):
    return [r[1] for r in df.groupBy(F.spark_partition_id()).agg(F.count(F.lit(1))).collect()]


@pytest.mark.parametrize("partitions", [2, 7, 64, 1000])
def test_every_partition_has_its_own_label(spark, partitions):
    rows = spark.range(20_000).select(place("id", partitions).alias("p"), F.pmod(F.hash("id"), F.lit(partitions)).alias("n"))
    assert rows.where(F.pmod(F.hash("p"), F.lit(partitions)) != F.col("n")).isEmpty()
    assert rows.select("p").distinct().count() == partitions


@pytest.mark.parametrize("name", ["supply", "basket"])
def test_edges_are_spread_evenly(spark, name):
    g = Graph.from_edges(workloads.BUILDERS[name](spark, SF), partitions=8)
    used = sizes(g.light)
    if g.heavy is not None:
        by_place = dict.fromkeys(range(8), 0)
        for part in (g.light, g.heavy):
            for r in part.groupBy(F.spark_partition_id().alias("p")).count().collect():
                by_place[r.p] += r["count"]
        used = list(by_place.values())
        assert g.vertices.where(F.col("out_degree") > g.hub_degree).count() <= 32 * 8
    assert len(used) == 8 and max(used) <= 1.3 * sum(used) / 8
    assert len(sizes(g.vertices)) == 8 and sum(used) == g.num_edges


def test_hubs_lie_with_their_targets(spark):
    hub = make(spark, [(0, i) for i in range(1, 3001)] + [(i, i + 1) for i in range(1, 3000)], partitions=4)
    assert hub.heavy.select("src").distinct().count() == 1 and hub.heavy.count() == 3000
    assert max(sizes(hub.heavy)) < 1.2 * 750
    plain = {i: min(i, 1) for i in range(3001)}
    for options in (Options(), Options("bypass", "pull"), Options("bypass", "pull_addressed"), Options("bypass", combine=False), Options("bypass", lookup_most=0)):
        assert values(sssp(hub, 0, options)) == plain
    assert values(subset.subset_sssp(hub, 0)) == plain == values(asynchronous.async_sssp(hub, 0))
    assert set(values(asynchronous.local_components(hub)).values()) == {0}
    assert sum(values(pagerank(hub)).values()) == pytest.approx(1)
    with loop_settings(spark):
        told = hub.vertices.select("pid", F.col("id").alias("src"), F.col("id").alias("m0"))
        assert inspect.exchanges(hub.mail(told, F.col("m0"), F.min)) == 1


def test_bypass_reads_and_writes_little(spark):
    chain = make(spark, [(i, i + 1) for i in range(6000)])
    want = {i: i for i in range(6001)}
    looked = run(chain, ShortestPaths(0), Options("bypass", max_supersteps=6))
    assert {r["form"] for r in looked.rows[1:]} == {"lookup"}
    assert all(0 < r["state_read"] <= 256 * r["ran"] and r["edges_read"] <= 256 * 2 for r in looked.rows[1:])
    narrow = run(chain, ShortestPaths(0), Options("bypass", lookup_most=0, max_supersteps=6))
    assert all(r["state_written"] == r["ran"] <= 2 and r["state_read"] < 6001 for r in narrow.rows[1:])
    scan = run(chain, ShortestPaths(0), Options("scan", max_supersteps=6))
    assert all(r["state_read"] == r["state_written"] == r["checked"] == 6001 for r in scan.rows)
    near = lambda done: {i: d for i, d in values(done.values).items() if d < 1 << 62}
    assert near(looked) == near(narrow) == near(scan) == {i: want[i] for i in range(6)}


def test_a_frontier_that_widens_and_narrows(spark):
    random.seed(4)
    pairs = [(i, i + 1) for i in range(4)] + [(4, 100 + i) for i in range(400)] + [(100 + i, 600) for i in range(400)] + [(600 + i, 601 + i) for i in range(4)]
    g = make(spark, pairs)
    want = values(sssp(g, 0))
    for most in (0, 50, 10_000):
        done = run(g, ShortestPaths(0), Options("bypass", "auto", lookup_most=most))
        assert {i: d for i, d in values(done.values).items()} == want
        forms = [r["form"] for r in done.rows]
        assert ("lookup" in forms) == (most > 0) and (most != 50 or len(set(forms)) > 2)
    labels = values(connected_components(g))
    assert values(connected_components(g, Options("bypass", lookup_most=64))) == labels
    messages = [r["messages"] for r in run(g, ShortestPaths(0), Options("bypass")).rows]
    assert messages == [r["messages"] for r in run(g, ShortestPaths(0), Options("scan")).rows]


def test_rebalancing_deals_the_vertices_that_run(spark):
    random.seed(2)
    ids = [i for i in range(40_000) if True]
    one = values(spark.createDataFrame([(i,) for i in ids], "id long").select("id", F.pmod(F.hash("id"), F.lit(4))))
    same = [i for i in ids if one[i] == 1][:2000]  # all in one partition
    g = make(spark, [(-1, i) for i in same], partitions=4)
    lying, dealt = (run(g, ShortestPaths(-1), Options("bypass", rebalance_active=x, measure_balance=True, lookup_most=0)).rows[1] for x in (False, True))
    assert lying["ran"] == dealt["ran"] == 2000
    assert lying["largest"] == 2000 and dealt["largest"] <= 2000 / 4 + 4 and dealt["partitions"] == 4
    want = values(sssp(g, -1))
    assert values(sssp(g, -1, Options("bypass", rebalance_active=True))) == want


class Named(VertexProgram):
    """Adds an attribute to what is heard, through a Python function."""

    combiner = Combiner.sum()

    def compute(self, me, step):
        if step.number == 0:
            return Turn(value=me.attr("value"), broadcast=me.attr("payload"))
        plus = me.apply(lambda a, b: a + b.fillna(0), "double", me.attr("halted"), me.message)
        return Turn(value=plus + me.attr("msg"))


def test_attributes_may_have_any_name(spark):
    rows = [(1, 1.0, 2.0, 3.0, 4.0, "x"), (2, 10.0, 20.0, 30.0, 40.0, "y"), (None, 0.0, 0.0, 0.0, 0.0, "z"), (2, 10.0, 20.0, 30.0, 40.0, "y")]
    names = "id long, value double, payload double, halted double, msg double, run string"
    g = Graph.from_edges(spark.createDataFrame([(1, 2)], "src long, dst long"), vertices=spark.createDataFrame(rows, names))
    assert values(run(g, Named()).values) == {1: 3.0 + 20.0 + 4.0, 2: 30.0 + 2.0 + 40.0}
    assert values(run(g, Named(), Options("bypass")).values) == {1: 27.0, 2: 72.0}
    with pytest.raises(EngineError):
        Graph.from_edges(g.edges.select("src", "dst"), vertices=g.vertices.select("id", F.lit(1).alias("pid")))


def test_empty_and_odd_graphs(spark):
    none = make(spark, [])
    assert none.num_vertices == none.num_edges == 0
    for df in (pagerank(none), connected_components(none, Options("bypass", "pull")), sssp(none, 1, Options("bypass")), pagerank_converged(none)[0], pagerank(none, dangling="spread")):
        assert df.count() == 0
    for df in (asynchronous.async_pagerank(none), subset.subset_pagerank(none), subset.subset_components(none), asynchronous.async_components(none), asynchronous.local_components(none)):
        assert df.count() == 0
    alone = make(spark, [(1, 1)], ids=[3, 3, 1])
    assert values(connected_components(alone)) == {1: 1, 3: 3}


def test_superseded_checkpoints_go(spark):
    g = make(spark, [(i, i + 1) for i in range(14)])
    folder = checkpoints.shared_folder(spark).removeprefix("file:")
    count = lambda: len([d for d in os.listdir(folder) if d.startswith("rdd-")])
    before = count()
    for options in (Options(), Options("bypass", lookup_most=0)):
        done = run(g, ConnectedComponents(), options)
        assert done.supersteps > 12 and values(done.values) == dict.fromkeys(range(15), 0)
    assert count() - before <= 2 * 9
    run(g, ShortestPaths(0), Options("bypass"))
    assert not [d for d in os.listdir(os.path.dirname(folder)) if d.startswith("state-")] and not [d for d in os.listdir(folder) if d.startswith("state-")]


def test_saved_graphs_are_read_by_their_buckets(spark, tmp_path):
    g = make(spark, [(0, i) for i in range(1, 500)] + [(7, 8)], partitions=3)
    spark.sql(f"CREATE DATABASE IF NOT EXISTS kept LOCATION '{tmp_path}'")
    g.save("kept.g")
    back = Graph.load(spark, "kept.g")
    assert (back.partitions, back.num_edges, back.num_vertices, back.directed) == (g.partitions, g.num_edges, g.num_vertices, g.directed)
    assert values(connected_components(back, Options("bypass", "pull"))) == values(connected_components(g))
    with loop_settings(spark):
        assert inspect.exchanges(back.light.groupBy("pid", "src").count()) == 0 == inspect.exchanges(back.vertices.groupBy("pid", "id").count())
    spark.sql("DROP DATABASE kept CASCADE")


def test_storage_is_chosen_by_the_budget(spark, monkeypatch):
    g, levels = make(spark, [(i, i + 1) for i in range(9)]), []
    plain = checkpoints.held
    monkeypatch.setattr(asynchronous, "held", lambda df, level: levels.append(level) or plain(df, level))
    for budget in (1 << 30, 200, 1):
        assert set(values(asynchronous.async_components(g, memory_budget=budget)).values()) == {0}
    asynchronous.async_sssp(g, 0, storage="memory", memory_budget=1)
    assert levels == [StorageLevel.MEMORY_ONLY, StorageLevel.MEMORY_AND_DISK, StorageLevel.DISK_ONLY, StorageLevel.MEMORY_ONLY]
    assert not spark.sparkContext._jsc.getPersistentRDDs()


def test_scheduled_vertices_alone_run(spark):
    g, on, off = make(spark, [(i, i + 1) for i in range(8)]), [], []
    want = values(sssp(g, 0))
    assert values(asynchronous.async_sssp(g, 0, blocks=3, work=on)) == want
    assert values(asynchronous.async_sssp(g, 0, blocks=3, scheduler=asynchronous.Scheduler(False), work=off)) == want
    assert sum(on) == 9 and sum(off) == 3 * len(off)  # each runs once, or its block each turn
    pair = make(spark, [(1, 2), (2, 3)])
    raw, scaled = (values(asynchronous.async_pagerank(pair, passes=12, blocks=1, seed_share=x)) for x in ("raw", "scaled"))
    assert raw == pytest.approx(scaled, abs=0.1) and raw != scaled


def test_subsets_push_and_pull(spark):
    g = make(spark, [(i, i + 1) for i in range(4)] + [(0, 20 + i) for i in range(10)])
    want, ways = values(sssp(g, 0)), {}
    for share in (10.0, -1.0, 0.3):
        ways[share] = []
        assert values(subset.subset_sssp(g, 0, share, ways[share])) == want
        assert values(subset.subset_components(g, share)) == values(connected_components(g))
    assert set(ways[10.0]) == {"push"} and set(ways[-1.0]) == {"pull"} and set(ways[0.3]) == {"push", "pull"}
    front = subset.VertexSubset(g.vertices.where("id < 3"), 3, 15)
    assert sorted(r.id for r in front.dense(g).where("inside").collect()) == [0, 1, 2] and front.dense(g).count() == g.num_vertices
    full = subset.VertexSubset.everyone(g, g.vertices)
    assert full.sparse().count() == g.num_vertices
    some = g.vertices.where("id in (1, 21, 4)")
    for update in (subset.MINIMUM, subset.ADDITION, subset.EdgeUpdate(plain=F.max, atomic=F.max)):
        got = [subset.edge_map(g, front, F.col("id"), update, some, share) for share in (10.0, -1.0)]
        assert [way for _, way in got] == ["push", "pull"]
        assert values(got[0][0].select("id", "got")) == values(got[1][0].select("id", "got"))


def test_generated_code_gives_the_same(spark, sf):
    g = workloads.graph(spark, sf, "links")
    cells = [lambda: pagerank(g), lambda: connected_components(g, Options("bypass", "auto")), lambda: sssp(g, workloads.source_of(g), Options("bypass", "pull", combine=False))]
    plain = [values(cell()) for cell in cells]
    spark.conf.set("spark.sql.codegen.wholeStage", "true")
    try:
        assert [values(cell()) == pytest.approx(want) for cell, want in zip(cells, plain)] == [True] * 3
    finally:
        spark.conf.set("spark.sql.codegen.wholeStage", "false")


def test_a_cluster_needs_a_shared_folder(spark, monkeypatch):
    class Context:
        master = "spark://somewhere:7077"

        def getCheckpointDir(self):
            return None

    class Session:
        sparkContext = Context()
        conf = type("Conf", (), {"get": lambda self, k, d=None: d})()

    with pytest.raises(RuntimeError):
        checkpoints.shared_folder(Session())


def test_runs_are_written(spark, tmp_path):
    done = run(make(spark, [(1, 2)]), PageRank())
    done.write(str(tmp_path / "ranks"))
    assert values(spark.read.parquet(str(tmp_path / "ranks"))) == values(done.values)
    assert cut(done.values).count() == 2


def test_cuts_forget_the_estimates_of_the_plans_that_made_them(spark):
    """Joined to itself from cut to cut, a table keeps its size, and so must the
    number that Spark plans with."""
    df = spark.range(8).withColumn("v", F.col("id"))
    for _ in range(8):
        df = checkpoints.cut(df.join(df.select("id", F.col("v").alias("w")), "id").select("id", F.least("v", "w").alias("v")))
    assert df.count() == 8
    assert df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes() < 2**64


def test_queries_read_their_tables_every_time(spark, sf, monkeypatch):
    read, plain = [], workloads.table
    monkeypatch.setattr(workloads, "table", lambda s, d, name: read.append(name) or plain(s, d, name))
    for name, tables in (("cc_supply", {"lineitem"}), ("cc_supply", {"lineitem"}), ("combine_avg", {"lineitem"}), ("agreement_cc", {"customer", "supplier", "nation"})):
        read.clear()
        registry.QUERIES[name](spark, sf)
        assert set(read) == tables, name


def test_files_of_frames_that_nobody_holds_are_deleted(spark):
    df = cut(spark.range(5))
    held = df.where("id > 2")
    path = df._jdf.queryExecution().analyzed().rdd().getCheckpointFile().get().removeprefix("file:")
    del df
    checkpoints.release(spark)
    assert os.path.exists(path) and held.count() == 2
    del held
    for _ in range(50):
        checkpoints.release(spark)
        if not os.path.exists(path):
            break
        time.sleep(0.2)
    assert not os.path.exists(path)


def test_packed_tables_are_whole_and_keep_their_layout(spark):
    rows = [(i, None if i % 3 else i * 0.5, f"ä{i}", [(i, i + 1)] if i % 2 else None) for i in range(3000)]
    df = spark.createDataFrame(rows, "id long, v double, s string, sends array<struct<to:long,msg:long>>")
    with loop_settings(spark):
        packed, seen = checkpoints.pack(df.repartition(3, "id").sortWithinPartitions("id").observe("seen", F.count("v").alias("n"), F.max("id").alias("m")))
        assert seen == {"n": 1000, "m": 2999} and packed.rdd.getNumPartitions() == 3
        assert sorted((r.id, r.v, r.s, r.sends) for r in packed.collect()) == rows
        found = packed.join(packed.select("id", F.col("v").alias("w")), "id")
        assert found.count() == 3000 and inspect.operators(found)["Sort"] == inspect.exchanges(found) == 0
    assert packed._jdf.queryExecution().optimizedPlan().stats().sizeInBytes() >= 2**60  # no estimate is handed on
    path = packed._jdf.queryExecution().analyzed().rdd().dependencies().head().rdd().getCheckpointFile().get().removeprefix("file:")
    assert os.path.exists(path)
    checkpoints.drop(packed)
    assert not os.path.exists(path)


def test_no_sort_of_a_superstep_compares_labels_first(spark, sf):
    """All rows of a partition share its label; sorted by it first, every comparison
    reads both rows."""
    g, program = workloads.graph(spark, sf, "chain"), ConnectedComponents()
    for combine, name in ((True, "push"), (True, "pull"), (True, "pull_addressed"), (False, "push"), (False, "pull"), (False, "pull_addressed")):
        options = Options("bypass", name, combine, lookup_most=0)
        with loop_settings(spark):
            state = run(g, program, replace(options, max_supersteps=1)).state
            senders = state.withColumn("payload", F.col("id"))
            text = inspect.plan_text(engine.superstep(state, exchange.FORMS[name](senders, g, program, options), g, program, options, 1))
        assert "Sort [" in text
        assert "Sort [pid" not in text and "Sort [tpid" not in text, name
