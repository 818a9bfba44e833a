"""Every query of the graph engine by name, and its SQL where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable
from itertools import product

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import measures, sql, workloads
from .algorithms import PageRank, component_sizes, min_reaching_id, pagerank, pagerank_converged, sssp, top_ranked
from .algorithms.components import ConnectedComponents
from .algorithms.pagerank import ranks
from .algorithms.paths import ShortestPaths, distances
from .baselines import asynchronous, hardcoded, subset
from .engine import run
from .operators import relational
from .options import Options
from .plans.lookup import PAGE_ROWS
from .programs.reference_form import ObjectPageRank
from .streaming import windows

QUERIES: dict[str, Callable] = {}
ORACLES: dict[str, str] = {}

CHOICES = {"comb": True, "queue": False}


def add(name: str, query: Callable, oracle: str | None = None) -> None:
    QUERIES[name] = query
    if oracle is not None:
        ORACLES[name] = oracle


def _rounded(ranked: DataFrame, digits: int = 10) -> DataFrame:
    return ranked.select("id", F.round("rank", digits).alias("rank"))


def _pr(name, options=None, directed=False, dangling="leak"):
    return lambda s, d: _rounded(pagerank(workloads.graph(s, d, name, directed), options=options, dangling=dangling))


def _cc(name, options=None, directed=False):
    return lambda s, d: min_reaching_id(workloads.graph(s, d, name, directed), options)


def _sp(name, options=None, weighted=False):
    def query(s, d):
        g = workloads.graph(s, d, name, weighted=weighted)
        return sssp(g, workloads.source_of(g), options)

    return query


def _on(name, method, *args, source=False, digits=None, **kwargs):
    """A baseline's method on a graph."""

    def query(s, d):
        g = workloads.graph(s, d, name)
        out = method(g, workloads.source_of(g), *args, **kwargs) if source else method(g, *args, **kwargs)
        return _rounded(out, digits) if digits else out

    return query


for _g in ("links", "stars", "geo", "chain", "supply", "trade", "basket"):
    add(f"pr_{_g}", _pr(_g), sql.pagerank(_g))
    add(f"sssp_{_g}", _sp(_g), sql.paths(_g))
for _g in ("links", "stars", "geo", "chain", "supply", "trade", "basket", "talk", "twins", "similar"):
    add(f"cc_{_g}", _cc(_g), sql.components(_g))
add("pr_links_directed", _pr("links", directed=True), sql.pagerank("links", directed=True))
add("pr_links_spread", _pr("links", directed=True, dangling="spread"), sql.pagerank("links", directed=True, spread=True))
add("pr_converged_geo", lambda s, d: _rounded(pagerank_converged(workloads.graph(s, d, "geo"), 1e-10)[0], 6), sql.pagerank("geo", rounds=200, digits=6))
add("cc_reaching_links", _cc("links", directed=True), sql.components("links", directed=True))
add("cc_sizes_stars", lambda s, d: component_sizes(_cc("stars")(s, d)), f"SELECT component, count(*) AS n FROM ({sql.components('stars')}) GROUP BY component")
add("sssp_weighted_trade", _sp("trade", weighted=True), sql.weighted_paths())
add("top_ranked", lambda s, d: top_ranked(_pr("supply")(s, d), 20), f"SELECT id, rank FROM ({sql.pagerank('supply')}) ORDER BY rank DESC, id LIMIT 20")

# the flag matrix: one answer whatever the options
for _x, _c in product(("push", "pull", "auto"), CHOICES):
    add(f"pr_scan_{_x}_{_c}_supply", _pr("supply", Options("scan", _x, CHOICES[_c])), sql.pagerank("supply"))
    for _s in ("scan", "bypass"):
        add(f"cc_{_s}_{_x}_{_c}_chain", _cc("chain", Options(_s, _x, CHOICES[_c])), sql.components("chain"))
        add(f"sssp_{_s}_{_x}_{_c}_chain", _sp("chain", Options(_s, _x, CHOICES[_c])), sql.paths("chain"))
add("cc_addressed_chain", _cc("chain", Options("bypass", "pull_addressed")), sql.components("chain"))
add("sssp_addressed_chain", _sp("chain", Options("bypass", "pull_addressed")), sql.paths("chain"))

add("pr_hardcoded_stars", _on("stars", hardcoded.hardcoded_pagerank, digits=10), sql.pagerank("stars"))
add("pr_hardcoded_supply", _on("supply", hardcoded.hardcoded_pagerank, digits=10), sql.pagerank("supply", keep=hardcoded.SLOTS))
add("lost_messages_supply", _on("supply", hardcoded.lost_messages), f"WITH {sql.base('supply')} SELECT dst AS id, count(*) - 100 AS lost FROM e GROUP BY dst HAVING count(*) > 100")
add("pr_async_geo", _on("geo", asynchronous.async_pagerank, passes=200, tolerance=1e-10, digits=6), sql.pagerank("geo", rounds=200, digits=6))
add("pr_async_ten_geo", _on("geo", asynchronous.async_pagerank, digits=10), sql.async_pagerank("geo"))
add("cc_async_chain", _on("chain", asynchronous.async_components), sql.components("chain"))
add("sssp_async_chain", _on("chain", asynchronous.async_sssp, source=True), sql.paths("chain"))
add("cc_local_chain", _on("chain", asynchronous.local_components), sql.components("chain"))
for _g in ("links", "stars", "supply", "basket"):
    add(f"pr_subset_{_g}", _on(_g, subset.subset_pagerank, digits=10), sql.pagerank(_g))
    add(f"cc_subset_{_g}", _on(_g, subset.subset_components), sql.components(_g))
    add(f"sssp_subset_{_g}", _on(_g, subset.subset_sssp, source=True), sql.paths(_g))
for _way, _share in (("push", 10.0), ("pull", -1.0)):
    add(f"cc_subset_{_way}_stars", _on("stars", subset.subset_components, threshold=_share), sql.components("stars"))
    add(f"sssp_subset_{_way}_links", _on("links", subset.subset_sssp, source=True, threshold=_share), sql.paths("links"))
add("pr_reference_form_geo", lambda s, d: _rounded(ranks(run(workloads.graph(s, d, "geo"), ObjectPageRank()))), sql.pagerank("geo"))


def _ledger(name, program, options=None, columns=("superstep", "ran", "checked", "messages", "probes")):
    def query(s, d):
        g = workloads.graph(s, d, name)
        return run(g, program(g), options).ledger.select(*columns)

    return query


add("ledger_sssp_chain", _ledger("chain", lambda g: ShortestPaths(workloads.source_of(g)), Options("bypass")), sql.path_rounds("chain"))
add(
    "ledger_cc_chain",
    _ledger("chain", lambda g: ConnectedComponents(), Options("bypass", "pull"), ("superstep", "ran", "messages", "probes", "wasted_probes")),
    sql.component_rounds("chain"),
)


def bypass_work(s, d):
    """State rows that each selection reads on a small frontier, as multiples: the
    scan reads every vertex in every superstep, bypass no more than two pages for
    every vertex that runs, after the first superstep."""
    g = workloads.graph(s, d, "chain")
    scan, bypass = (run(g, ShortestPaths(workloads.source_of(g)), Options(x)).rows for x in ("scan", "bypass"))
    few = all(b["state_read"] <= 2 * PAGE_ROWS * b["ran"] for b in bypass[1:])
    facts = [(len(scan), sum(r["state_read"] for r in scan), sum(r["ran"] for r in bypass), few)]
    return s.createDataFrame(facts, "supersteps long, scan_read long, bypass_ran long, bypass_reads_few boolean")


add(
    "bypass_work",
    bypass_work,
    f"WITH r AS ({sql.path_rounds('chain')}) SELECT count(*) AS supersteps, CAST(count(*) * max(ran) AS BIGINT) AS scan_read, CAST(sum(ran) AS BIGINT) AS bypass_ran, true AS bypass_reads_few FROM r",
)
add(
    "ledger_pr_supply",
    _ledger("supply", lambda g: PageRank()),
    f"WITH {sql.base('supply')} SELECT CAST(t AS INT) AS superstep, (SELECT count(*) FROM v) AS ran, (SELECT count(*) FROM v) AS checked, "
    "CASE WHEN t < 10 THEN (SELECT count(*) FROM e) ELSE 0 END AS messages, 0::BIGINT AS probes FROM (SELECT unnest(generate_series(0, 10)) AS t)",
)
for _name, (_query, _oracle) in (measures.QUERIES | relational.QUERIES | windows.QUERIES).items():
    add(_name, _query, _oracle)

# long paths take a job per step: last
for _name in [n for n in QUERIES if n.endswith("_chain") and n[:2] in ("cc", "ss", "le", "pr")]:
    QUERIES[_name] = QUERIES.pop(_name)

__all__ = ["ORACLES", "QUERIES", "distances"]
