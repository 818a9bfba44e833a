"""Hand graphs, option invariance, ledgers and plans of the engine."""

from itertools import product

import pytest
from pyspark.sql import functions as F

from bspgraph import workloads
from bspgraph.algorithms import ConnectedComponents, PageRank, ShortestPaths, connected_components, pagerank, sssp
from bspgraph.engine import run, superstep
from bspgraph.functions.combiners import Combiner, combine_arrow
from bspgraph.graph import Graph
from bspgraph.options import EngineError, NotSupported, Options, PullNotApplicable, SystematicHaltError
from bspgraph.plans import exchange, inspect
from bspgraph.plans.checkpoints import LOOP, cut, loop_settings
from bspgraph.program import Turn, VertexProgram, halts_every_step

CELLS = [(s, x, c) for s, x, c in product(("scan", "bypass"), ("push", "pull", "auto", "pull_addressed"), (True, False))]


def make(spark, pairs, ids=None, **kw):
    vertices = spark.createDataFrame([(i,) for i in ids], "id long") if ids else None
    return Graph.from_edges(spark.createDataFrame(pairs, "src long, dst long"), vertices=vertices, **kw)


@pytest.fixture(scope="module")
def h1(spark):
    return make(spark, [(1, 2), (2, 3), (3, 4), (5, 6)], ids=[7])


@pytest.fixture(scope="module")
def h3(spark):
    return make(spark, [(1, 2), (2, 3), (3, 1), (3, 4), (5, 1)], directed=True)


def values(df):
    return {r[0]: r[1] for r in df.collect()}


@pytest.mark.parametrize("selection,form,combine", CELLS)
def test_components_in_every_cell(h1, selection, form, combine):
    options = Options(selection, form, combine)
    assert values(connected_components(h1, options)) == {1: 1, 2: 1, 3: 1, 4: 1, 5: 5, 6: 5, 7: 7}


@pytest.mark.parametrize("selection,form,combine", [CELLS[i] for i in (0, 3, 5, 8, 10, 13)])
def test_paths_in_some_cells(h1, selection, form, combine):
    options = Options(selection, form, combine)
    assert values(sssp(h1, 1, options)) == {1: 0, 2: 1, 3: 2, 4: 3, 5: None, 6: None, 7: None}


@pytest.mark.parametrize("form,combine", [(x, c) for x in ("push", "pull", "auto") for c in (True, False)])
def test_pagerank_in_every_cell(spark, form, combine):
    star = make(spark, [(1, 2), (1, 3), (1, 4)])
    got = values(pagerank(star, options=Options("scan", form, combine)))
    assert got[1] == pytest.approx(0.4345018260, abs=1e-10)
    assert [got[i] for i in (2, 3, 4)] == pytest.approx([0.1884993913] * 3, abs=1e-10)


def test_directed_pagerank_leaks_and_spreads(h3):
    got = values(pagerank(h3))
    assert [got[i] for i in range(1, 6)] == pytest.approx([0.1190806123, 0.1291267299, 0.1397577204, 0.0935806123, 0.03], abs=1e-10)
    assert sum(values(pagerank(h3, dangling="spread")).values()) == pytest.approx(1.0)


def test_bypass_is_refused_where_it_would_change_ranks(h3):
    with pytest.raises(SystematicHaltError):
        run(h3, PageRank(), Options("bypass"))
    forced = values(run(h3, PageRank(), Options("bypass", force_bypass=True)).values)
    assert [forced[i] for i in range(1, 6)] == pytest.approx([0.0833461903, 0.0987524713, 0.1139396006, 0.0833461903, 0.2], abs=1e-10)
    assert halts_every_step(ConnectedComponents()) and not halts_every_step(PageRank())


def test_ledger_of_the_hand_graph(h1):
    done = run(h1, ConnectedComponents(), Options("bypass"))
    assert [r["ran"] for r in done.rows] == [7, 6, 5, 3, 1]
    assert [r["senders"] for r in done.rows] == [7, 4, 2, 1, 0]
    done = run(h1, ShortestPaths(1), Options("scan"))
    assert [r["ran"] for r in done.rows] == [7, 1, 2, 2, 1]
    assert [r["checked"] for r in done.rows] == [7] * 5
    assert done.ledger.count() == done.supersteps == 5


def test_golden_counts_of_supply(spark, sf):
    g = workloads.graph(spark, sf, "supply")
    assert (g.num_vertices, g.num_edges) == (210, 2 * 1905)
    done = run(g, ConnectedComponents(), Options("bypass", "pull"))
    assert (done.supersteps, done.total("ran"), done.total("messages"), done.total("probes")) == (4, 640, 9505, 11430)


def test_one_shuffle_per_superstep_and_settings_are_put_back(spark, sf):
    g = workloads.graph(spark, sf, "supply")
    before = {k: spark.conf.get(k, None) for k in LOOP}
    program = ConnectedComponents()
    with loop_settings(spark):
        start = g.vertices.withColumn("value", F.lit(None).cast("long")).withColumn("halted", F.lit(False))
        state = cut(superstep(start, None, g, program, Options(), 0))
        for move in exchange.FORMS.values():
            inbox = move(state.where("payload is not null"), g, program, Options())
            assert inspect.exchanges(superstep(state.drop("payload", "ran", "lost"), inbox, g, program, Options(), 1)) == 1
    assert {k: spark.conf.get(k, None) for k in LOOP} == before
    with pytest.raises(RuntimeError), loop_settings(spark):
        raise RuntimeError
    assert {k: spark.conf.get(k, None) for k in LOOP} == before


class Whisper(VertexProgram):
    """Each vertex sends its id to the vertex after it, known or not."""

    value_type = message_type = "long"
    combiner = Combiner.max()

    def compute(self, me, step):
        if step.is_first:
            return Turn(value=F.lit(-1), sends=F.array(F.struct((me.id + 1).alias("to"), me.id.alias("msg"))))
        return Turn(value=me.message)


def test_messages_to_single_vertices(h1):
    assert values(run(h1, Whisper()).values) == {1: -1, 2: 1, 3: 2, 4: 3, 5: 4, 6: 5, 7: 6}
    with pytest.raises(PullNotApplicable):
        run(h1, Whisper(), Options(exchange="pull"))


def test_combiners_agree_with_plain_folds(spark):
    rows = spark.createDataFrame([(k, k * 7 % 5 + i) for k in range(3) for i in range(4)], "k long, m long").repartition(3)
    for kind, plain in (("sum", sum), ("min", min), ("max", max), ("avg", lambda x: sum(x) / len(x))):
        c = getattr(Combiner, kind)()
        got = values(rows.groupBy("k", F.spark_partition_id().alias("p")).agg(c.partial(F.col("m")).alias("m")).groupBy("k").agg(c.final(F.col("m"))))
        assert got == {k: plain([k * 7 % 5 + i for i in range(4)]) for k in range(3)}
        queue = values(rows.groupBy("k").agg(c.fold(F.collect_list("m"))))
        assert queue == got
    c = Combiner.custom(lambda a, b: F.greatest(a, b))
    assert values(rows.groupBy("k").agg(c.final(F.col("m")))) == {k: k * 7 % 5 + 3 for k in range(3)}
    assert values(combine_arrow(rows, "k", "m", max, 2)) == {k: k * 7 % 5 + 3 for k in range(3)}


def test_bad_options_are_refused(h3):
    with pytest.raises(EngineError):
        Options("unknown")
    with pytest.raises(EngineError):
        Options(mailbox_limit=5)
    with pytest.raises(EngineError):
        connected_components(h3)


def test_graph_operators(spark, h1, h3, tmp_path):
    assert values(h3.reverse().out_degrees())[1] == 2
    assert values(h3.in_degrees()) == {1: 2, 2: 1, 3: 1, 4: 1}
    assert values(h1.to_adjacency())[2] == [1, 3]
    part = h1.subgraph(F.col("id") != 2)
    assert part.num_edges == 4 and part.num_vertices == 6
    loops = spark.createDataFrame([(1, 1), (1, 2), (1, 2), (None, 3)], "src long, dst long")
    assert Graph.from_edges(loops, directed=True).num_edges == 1
    assert Graph.from_edges(loops, directed=True, parallel="keep", self_loops="keep").num_edges == 3
    spark.sql(f"CREATE DATABASE IF NOT EXISTS saved LOCATION '{tmp_path}'")
    h1.save("saved.h1")
    assert values(connected_components(Graph.load(spark, "saved.h1"))) == values(connected_components(h1))
    spark.sql("DROP DATABASE saved CASCADE")


def test_hardcoded_engine_refuses_other_programs(h1):
    from bspgraph.baselines.hardcoded import run_hardcoded

    with pytest.raises(NotSupported):
        run_hardcoded(h1, ConnectedComponents())
    lossless = run_hardcoded(h1, PageRank())
    assert lossless.total("lost") == 0
    lossy = run_hardcoded(h1, PageRank(), mailbox_limit=1)
    assert lossy.total("lost") == 10 * 2


def test_baselines_agree_with_the_engine(h1):
    from bspgraph.baselines import asynchronous, subset

    want_c, want_p = values(connected_components(h1)), values(sssp(h1, 1))
    assert values(asynchronous.local_components(h1)) == want_c == values(subset.subset_components(h1))
    assert values(subset.subset_sssp(h1, 1)) == want_p
    for blocks, on in ((3, True), (2, False)):
        scheduler = asynchronous.Scheduler(on)
        assert values(asynchronous.async_components(h1, blocks, scheduler)) == want_c
        assert values(asynchronous.async_sssp(h1, 1, blocks, scheduler)) == want_p
    ranks = values(pagerank(h1))
    assert values(asynchronous.async_pagerank(h1, blocks=1)) == pytest.approx(ranks)
    assert values(subset.subset_pagerank(h1)) == pytest.approx(ranks)
