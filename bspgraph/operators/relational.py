"""Projections, filters, joins, aggregates, windows and set operations on graph
tables, each as a query with its SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .. import sql, workloads
from ..engine import run
from ..functions.combiners import Combiner
from ..graph import Graph
from ..workloads import table

def _n(name: str):
    return F.count(F.lit(1)).alias(name)


def _g(s, d, name="supply", **kw) -> Graph:
    return workloads.graph(s, d, name, **kw)


def _edges(g: Graph) -> DataFrame:
    return g.edges.select("src", "dst")


def edges_filtered_quantity(s, d):
    """Edges of large lineitems: the filter reaches the scan."""
    rows = table(s, d, "lineitem").where("l_quantity >= 45")
    return rows.select(workloads.tagged("l_partkey", workloads.PART).alias("src"), workloads.tagged("l_suppkey", workloads.SUPPLIER).alias("dst")).distinct()


def induced_subgraph_quality(s, d):
    """The copy graph among documents that are rated good."""
    good = table(s, d, "labels").where("quality = 1").select(F.col("doc_id").alias("id"))
    e = workloads.twins(s, d)
    return e.join(good.withColumnRenamed("id", "src"), "src", "left_semi").join(good.withColumnRenamed("id", "dst"), "dst", "left_semi").select("src", "dst")


def degree_at_least(s, d):
    return _edges(_g(s, d)).groupBy(F.col("src").alias("id")).agg(_n("degree")).where("degree >= 100")


def first_step_values(s, d):
    """Values after the first superstep of a shortest-path run: one branch."""
    g = _g(s, d, "geo")
    return g.vertices.select("id", F.when(F.col("id") == workloads.source_of(g), 0).otherwise(None).cast("long").alias("value"))


def join_senders_edges(s, d):
    """What a push makes: every sender's share on every out-edge, counted."""
    g = _g(s, d)
    senders = g.vertices.select("pid", F.col("id").alias("src"), "out_degree")
    return g.edges.join(senders, ["src", "pid"]).groupBy(F.col("dst").alias("id")).agg(F.round(F.sum(F.try_divide(F.lit(1.0), "out_degree")), 9).alias("got"))


def join_broadcast_frontier(s, d):
    """A frontier of few rows is broadcast and the edges stay where they are."""
    g = _g(s, d)
    front = g.vertices.orderBy(F.desc("out_degree"), "id").limit(10).select(F.col("id").alias("src"))
    return g.edges.join(F.broadcast(front), "src").groupBy(F.col("dst").alias("id")).agg(_n("n"))


def _mail(g: Graph) -> DataFrame:
    return _edges(g).groupBy(F.col("dst").alias("id")).agg(F.min("src").alias("msg"))


def join_state_messages(s, d):
    g = _g(s, d)
    return g.vertices.select("id", "out_degree").join(_mail(g).hint("shuffle_hash"), "id")


def join_state_inbox(s, d):
    g = _g(s, d)
    return g.vertices.select("id", "out_degree").join(_mail(g), "id", "left").select("id", "out_degree", F.coalesce("msg", F.lit(-1)).alias("msg"))


def vertices_with_edges(s, d):
    orders = table(s, d, "orders").select(F.col("o_custkey").alias("c_custkey"))
    return table(s, d, "customer").join(orders, "c_custkey", "left_semi").select(F.col("c_custkey").alias("id"))


def vertices_isolated(s, d):
    items = table(s, d, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"))
    return table(s, d, "orders").join(items, "o_orderkey", "left_anti").select(F.col("o_orderkey").alias("id"))


def edges_of(name):
    def query(s, d):
        e = workloads.BUILDERS[name](s, d)
        return e.select("src", "dst").distinct()

    query.__doc__ = f"The undirected edges of ``{name}``, once each."
    return query


def edges_events_within_hour(s, d):
    """Two events of one user within an hour: equality on the user and a range.
    Hour buckets keep a user's join linear in the pairs found."""
    e = table(s, d, "events").select("event_id", "user_id", "ts", (F.datediff("ts", F.lit("1970-01-01")) * 24 + F.hour("ts")).alias("hour"))
    a = e.toDF("src", "user_id", "ta", "ha").withColumn("hour", F.explode(F.array(F.col("ha"), F.col("ha") + 1)))
    b = e.toDF("dst", "user_id", "tb", "hour")
    later = (F.col("tb") > F.col("ta")) | (F.col("tb") == F.col("ta")) & (F.col("dst") > F.col("src"))
    return a.join(b, ["user_id", "hour"]).where(later & (F.col("tb") <= F.col("ta") + F.expr("INTERVAL 1 HOUR"))).select("src", "dst")


def combine(kind):
    """Messages combined per receiver, partially before the shuffle."""

    def query(s, d):
        c = getattr(Combiner, kind)()
        g = _g(s, d)
        local = g.edges.groupBy("pid", "dst").agg(c.partial(F.col("src")).alias("m"))
        out = local.groupBy(F.col("dst").alias("id")).agg(c.final(F.col("m")).alias("msg"))
        return out if kind != "avg" else out.select("id", F.round("msg", 6).alias("msg"))

    return query


def mailbox_queue(s, d):
    g = _g(s, d, "geo")
    return _edges(g).groupBy(F.col("dst").alias("id")).agg(F.concat_ws(",", F.transform(F.array_sort(F.collect_list("src")), lambda x: x.cast("string"))).alias("senders"))


def mailbox_fold(s, d):
    """A queue folded by an array expression."""
    g = _g(s, d, "geo")
    q = _edges(g).groupBy(F.col("dst").alias("id")).agg(F.collect_list("src").alias("q"))
    return q.select("id", F.aggregate("q", F.lit(0).cast("long"), lambda a, x: a + x).alias("total"), F.size("q").cast("long").alias("n"))


def adjacency_arrays(s, d):
    g = _g(s, d, "geo")
    return g.to_adjacency().select("id", F.size("neighbours").cast("long").alias("n"), F.get("neighbours", F.lit(0)).alias("first_one"))


def attr_map(s, d):
    """A bag of attributes as a map, read back by key."""
    bag = F.create_map(F.lit("segment"), F.col("c_mktsegment"), F.lit("name"), F.col("c_name"))
    return table(s, d, "customer").select(F.col("c_custkey").alias("id"), bag.alias("m")).select("id", F.element_at("m", "segment").alias("segment"))


def degree_distinct(s, d):
    """Exact distinct targets; ``approx_count_distinct`` where that is enough."""
    e = _edges(_g(s, d))
    return e.agg(F.countDistinct("src").alias("n"), (F.abs(F.approx_count_distinct("src", 0.02) - F.countDistinct("src")) < 0.1 * F.countDistinct("src")).alias("near"))


def degree(end):
    return lambda s, d: _edges(_g(s, d, "links", directed=True)).groupBy(F.col(end).alias("id")).agg(_n("degree"))


def _kinds(s, d):
    g = _g(s, d, "geo")
    return g.vertices.select((F.col("id") % 8).alias("kind"), (F.col("out_degree") > 1).alias("inner"), "out_degree")


def _totals():
    return _n("n"), F.sum("out_degree").alias("degrees")


def degree_rollup(s, d):
    return _kinds(s, d).rollup("kind", "inner").agg(*_totals())


def degree_cube(s, d):
    return _kinds(s, d).cube("kind", "inner").agg(*_totals())


def degree_sets(s, d):
    k = _kinds(s, d)
    return k.groupingSets([[F.col("kind")], [F.col("inner")]], "kind", "inner").agg(*_totals())


def degree_percentiles(s, d):
    """Exact percentiles over counted degrees: one task gets distinct degrees only."""
    counted = _g(s, d).vertices.groupBy("out_degree").agg(_n("times"))
    return counted.agg(*[F.percentile("out_degree", F.lit(p / 100), F.col("times")).alias(f"p{p}") for p in (50, 90, 99, 100)])


def top_rank_per_component(s, d):
    from ..algorithms import PageRank, connected_components

    g = _g(s, d, "links")
    ranks = run(g, PageRank()).values.select("id", F.round("value", 8).alias("rank"))
    best = F.row_number().over(Window.partitionBy("component").orderBy(F.desc("rank"), "id"))
    return connected_components(g).join(ranks, "id").withColumn("place", best).where("place = 1").select("component", "id", "rank")


def ledger_running(s, d):
    """Vertices run so far, over the supersteps of a run."""
    from ..algorithms import PageRank

    rows = run(_g(s, d, "geo"), PageRank()).ledger
    so_far = Window.orderBy("superstep").rowsBetween(Window.unboundedPreceding, 0)
    return rows.select("superstep", F.sum("ran").over(so_far).alias("ran_so_far"))


def edges_symmetric(s, d):
    e = workloads.geo(s, d)
    return e.unionByName(e.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()


def _returned(s, d, flag):
    rows = table(s, d, "lineitem").where(F.col("l_returnflag") == flag)
    return rows.select(F.col("l_partkey").alias("src"), F.col("l_suppkey").alias("dst"))


def edges_common(s, d):
    return _returned(s, d, "A").intersect(_returned(s, d, "R"))


def edges_only_a(s, d):
    return _returned(s, d, "A").distinct().exceptAll(_returned(s, d, "R").distinct())


def page_links(s, d):
    return workloads.page_links(s, d)


def host_edges(s, d):
    """Links between hosts, counted."""
    host = lambda c: F.regexp_extract(c, "^[a-z]+://([^/?#]+)", 1)
    pages = table(s, d, "pages").select("page_id", host(F.col("url")).alias("src"))
    links = workloads.page_links(s, d).select("page_id", host(F.col("href")).alias("dst"))
    return pages.join(links, "page_id").where("dst <> ''").groupBy("src", "dst").agg(_n("n"))


def events_json_weight(s, d):
    k = F.get_json_object("props", "$.k").cast("long")
    return table(s, d, "events").groupBy("user_id").agg(F.sum(k).alias("weight"))


_KINDS_SQL = f"WITH {sql.base('geo')}, k AS (SELECT id % 8 AS kind, count(*) > 1 AS inner_, count(*) AS out_degree FROM v JOIN e ON e.src = v.id GROUP BY id)"
_TOTALS_SQL = 'SELECT kind, inner_ AS "inner", count(*) AS n, CAST(sum(out_degree) AS BIGINT) AS degrees FROM k'
_SUPPLY = f"WITH {sql.base('supply')}"
_GEO = f"WITH {sql.base('geo')}"
_DEG = f"{_SUPPLY}, deg AS (SELECT src AS id, count(*) AS out_degree FROM e GROUP BY src)"
_HOST = "regexp_extract({}, '^[a-z]+://([^/?#]+)', 1)"
_RETURNED = "SELECT l_partkey AS src, l_suppkey AS dst FROM lineitem WHERE l_returnflag = '{}'"
_COMBINED = {"min": "min(src)", "sum": "CAST(sum(src) AS BIGINT)", "max": "max(src)", "avg": "round(avg(src), 6)"}
_MAIL = "mail AS (SELECT dst AS id, min(src) AS msg FROM e GROUP BY dst)"

QUERIES = {
    "edges_filtered_quantity": (edges_filtered_quantity, "SELECT DISTINCT l_partkey * 8 AS src, l_suppkey * 8 + 1 AS dst FROM lineitem WHERE l_quantity >= 45"),
    "induced_subgraph_quality": (
        induced_subgraph_quality,
        f"SELECT src, dst FROM ({sql.EDGES['twins']}) WHERE src IN (SELECT doc_id FROM labels WHERE quality = 1) AND dst IN (SELECT doc_id FROM labels WHERE quality = 1)",
    ),
    "degree_at_least": (degree_at_least, f"{_SUPPLY} SELECT src AS id, count(*) AS degree FROM e GROUP BY src HAVING count(*) >= 100"),
    "first_step_values": (first_step_values, f"{_GEO} SELECT id, CASE WHEN id = (SELECT min(id) FROM v) THEN 0::BIGINT END AS value FROM v"),
    "join_senders_edges": (join_senders_edges, f"{_DEG} SELECT e.dst AS id, round(sum(1.0::DOUBLE / out_degree), 9) AS got FROM e JOIN deg ON deg.id = e.src GROUP BY e.dst"),
    "join_broadcast_frontier": (join_broadcast_frontier, f"{_DEG}, f AS (SELECT id FROM deg ORDER BY out_degree DESC, id LIMIT 10) SELECT e.dst AS id, count(*) AS n FROM e JOIN f ON f.id = e.src GROUP BY e.dst"),
    "join_state_messages": (join_state_messages, f"{_DEG}, {_MAIL} SELECT id, out_degree, msg FROM deg JOIN mail USING (id)"),
    "join_state_inbox": (join_state_inbox, f"{_DEG}, {_MAIL} SELECT id, out_degree, coalesce(msg, -1) AS msg FROM deg LEFT JOIN mail USING (id)"),
    "vertices_with_edges": (vertices_with_edges, "SELECT c_custkey AS id FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)"),
    "vertices_isolated": (vertices_isolated, "SELECT o_orderkey AS id FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)"),
    **{f"edges_{n}": (edges_of(n), f"SELECT DISTINCT src, dst FROM ({sql.EDGES[n]})") for n in ("basket", "similar", "chain", "supply")},
    "edges_events_within_hour": (
        edges_events_within_hour,
        "SELECT a.event_id AS src, b.event_id AS dst FROM events a JOIN events b ON a.user_id = b.user_id AND (b.ts > a.ts OR b.ts = a.ts AND b.event_id > a.event_id) AND b.ts <= a.ts + INTERVAL 1 HOUR",
    ),
    **{f"combine_{k}": (combine(k), f"{_SUPPLY} SELECT dst AS id, {x} AS msg FROM e GROUP BY dst") for k, x in _COMBINED.items()},
    "mailbox_queue": (mailbox_queue, f"{_GEO} SELECT dst AS id, string_agg(src::VARCHAR, ',' ORDER BY src) AS senders FROM e GROUP BY dst"),
    "mailbox_fold": (mailbox_fold, f"{_GEO} SELECT dst AS id, CAST(sum(src) AS BIGINT) AS total, count(*) AS n FROM e GROUP BY dst"),
    "adjacency_arrays": (adjacency_arrays, f"{_GEO} SELECT src AS id, count(*) AS n, min(dst) AS first_one FROM e GROUP BY src"),
    "attr_map": (attr_map, "SELECT c_custkey AS id, c_mktsegment AS segment FROM customer"),
    "degree_distinct": (degree_distinct, f"{_SUPPLY} SELECT count(DISTINCT src) AS n, true AS near FROM e"),
    "degree_out": (degree("src"), f"WITH {sql.base('links', True)} SELECT src AS id, count(*) AS degree FROM e GROUP BY src"),
    "degree_in": (degree("dst"), f"WITH {sql.base('links', True)} SELECT dst AS id, count(*) AS degree FROM e GROUP BY dst"),
    "degree_rollup": (degree_rollup, f"{_KINDS_SQL} {_TOTALS_SQL} GROUP BY ROLLUP (kind, inner_)"),
    "degree_cube": (degree_cube, f"{_KINDS_SQL} {_TOTALS_SQL} GROUP BY CUBE (kind, inner_)"),
    "degree_sets": (degree_sets, f"{_KINDS_SQL} {_TOTALS_SQL} GROUP BY GROUPING SETS ((kind), (inner_))"),
    "degree_percentiles": (degree_percentiles, f"{_DEG} SELECT " + ", ".join(f"quantile_cont(out_degree, {p / 100})::DOUBLE AS p{p}" for p in (50, 90, 99, 100)) + " FROM deg"),
    "top_rank_per_component": (
        top_rank_per_component,
        f"WITH c AS ({sql.components('links')}), r AS ({sql.pagerank('links', digits=8)}) SELECT component, id, rank FROM c JOIN r USING (id) QUALIFY row_number() OVER (PARTITION BY component ORDER BY rank DESC, id) = 1",
    ),
    "ledger_running": (ledger_running, f"{_GEO} SELECT CAST(t AS INT) AS superstep, (t + 1) * (SELECT count(*) FROM v) AS ran_so_far FROM (SELECT unnest(generate_series(0, 10)) AS t)"),
    "edges_symmetric": (edges_symmetric, f"{_GEO} SELECT src, dst FROM e"),
    "edges_common": (edges_common, f"{_RETURNED.format('A')} INTERSECT {_RETURNED.format('R')}"),
    "edges_only_a": (edges_only_a, f"{_RETURNED.format('A')} EXCEPT {_RETURNED.format('R')}"),
    "page_links": (page_links, """SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS href FROM pages"""),
    "host_edges": (
        host_edges,
        f"""SELECT {_HOST.format('url')} AS src, {_HOST.format('href')} AS dst, count(*) AS n
        FROM pages JOIN (SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS href FROM pages) USING (page_id)
        WHERE {_HOST.format('href')} <> '' GROUP BY ALL""",
    ),
    "events_json_weight": (events_json_weight, "SELECT user_id, CAST(sum(CAST(json_extract_string(props, '$.k') AS BIGINT)) AS BIGINT) AS weight FROM events GROUP BY user_id"),
}
