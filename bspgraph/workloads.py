"""The graphs on the given tables and the experiments that run on them.

Identifiers of different tables are told apart by arithmetic: key * 8 + kind.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .graph import Graph
from .plans.checkpoints import release
from .shipping import ship

PART, SUPPLIER, CUSTOMER, ORDER, NATION, REGION, PAGE, LINK = range(8)

#: Stand-ins for the four graphs of the experiments, small to large.
STAND_INS = {"co-authorship": "links", "blogging": "stars", "social": "supply", "gaming": "basket"}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tagged(key: str, kind: int):
    return F.col(key).cast("long") * 8 + kind


def page_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(page_id, href) of the distinct links of every page."""
    pages = table(spark, sf_dir, "pages").select("page_id", "html")
    found = F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))
    return pages.select("page_id", F.explode(F.array_distinct(found)).alias("href"))


def href_number(href: str = "href"):
    """A link's number: the first 56 bits of its digest, below 2^56 so that it can
    be tagged.  Two links of 10^8 share one with a chance of about 7 %, of 10^7
    below 0.1 %; ``number_clashes`` counts them."""
    return F.conv(F.substring(F.md5(F.col(href).cast("binary")), 1, 14), 16, 10).cast("long")


def number_clashes(rows: DataFrame) -> DataFrame:
    """Numbers of more than one link, in a table with ``href``."""
    same = rows.groupBy(href_number().alias("place")).agg(F.min("href").alias("a"), F.max("href").alias("b"))
    return same.where("a <> b")


def links(spark, sf_dir):
    """Pages and the links on them."""
    rows = page_links(spark, sf_dir)
    return rows.select(tagged("page_id", PAGE).alias("src"), (href_number() * 8 + LINK).alias("dst"))


def stars(spark, sf_dir):
    return table(spark, sf_dir, "orders").select(tagged("o_orderkey", ORDER).alias("src"), tagged("o_custkey", CUSTOMER).alias("dst"))


def geo(spark, sf_dir):
    place = lambda t, key, kind, of, above: table(spark, sf_dir, t).select(tagged(key, kind).alias("src"), tagged(of, above).alias("dst"))
    return (
        place("customer", "c_custkey", CUSTOMER, "c_nationkey", NATION)
        .unionByName(place("supplier", "s_suppkey", SUPPLIER, "s_nationkey", NATION))
        .unionByName(place("nation", "n_nationkey", NATION, "n_regionkey", REGION))
    )


def chain(spark, sf_dir):
    nxt = F.lead("event_id").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
    return table(spark, sf_dir, "events").select(F.col("event_id").alias("src"), nxt.alias("dst")).where("dst is not null")


def supply(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").select(tagged("l_partkey", PART).alias("src"), tagged("l_suppkey", SUPPLIER).alias("dst"))


def _sales(spark, sf_dir):
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    items = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"), "l_partkey")
    return orders.join(items, "o_orderkey").select(tagged("o_custkey", CUSTOMER).alias("src"), tagged("l_partkey", PART).alias("dst"))


def trade(spark, sf_dir):
    return _sales(spark, sf_dir)


def trade_weighted(spark, sf_dir):
    """Customers and parts; the weight is the number of lineitems."""
    return _sales(spark, sf_dir).groupBy("src", "dst").agg(F.count(F.lit(1)).alias("weight"))


def basket(spark, sf_dir):
    """Parts bought in one order."""
    items = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").distinct()
    a = items.select("l_orderkey", tagged("l_partkey", PART).alias("src"))
    b = items.select("l_orderkey", tagged("l_partkey", PART).alias("dst"))
    return a.join(b, "l_orderkey").where("src < dst").select("src", "dst").distinct()


def talk(spark, sf_dir):
    here = F.col("conv_id") * 1000 + F.col("turn")
    nxt = F.lead(here).over(Window.partitionBy("conv_id").orderBy("turn"))
    return table(spark, sf_dir, "conversations").select(here.alias("src"), nxt.alias("dst")).where("dst is not null")


def twins(spark, sf_dir):
    """Documents and the first one with the same text."""
    docs = table(spark, sf_dir, "documents").select("doc_id", F.md5(F.col("text").cast("binary")).alias("h"))
    first = docs.groupBy("h").agg(F.min("doc_id").alias("dst"))
    return docs.join(first, "h").where("doc_id <> dst").select(F.col("doc_id").alias("src"), "dst")


#: Embeddings that are compared in one task with as many others.
BLOCK = 2000


def similar(spark, sf_dir, least: float = 0.3):
    """Pairs of embeddings with a cosine above ``least``.

    The exact answer looks at every pair; it does so in blocks: the vectors are
    dealt to blocks, every two blocks meet in one task and are multiplied as
    matrices, so only found pairs become rows.  It grows with the square of the
    table all the same.
    """
    rows = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    blocks = max(1, -(-rows.count() // BLOCK))
    mine = F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int")
    rows = rows.withColumn("mine", mine).withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    rows = rows.select("vec_id", "embedding", "mine", F.least("mine", "other").alias("low"), F.greatest("mine", "other").alias("high"))

    def meet(frame: pd.DataFrame) -> pd.DataFrame:
        ids, matrix = frame["vec_id"].to_numpy(), np.stack(frame["embedding"].to_numpy()).astype(float)
        matrix /= np.maximum(np.sqrt((matrix * matrix).sum(axis=1, keepdims=True)), 1e-300)
        low, high = (np.flatnonzero(frame["mine"] == frame[side]) for side in ("low", "high"))
        a, b = np.nonzero(matrix[low] @ matrix[high].T > least)
        a, b = ids[low[a]], ids[high[b]]
        apart = a < b if (frame["low"] == frame["high"]).all() else a != b
        return pd.DataFrame({"src": np.minimum(a, b)[apart], "dst": np.maximum(a, b)[apart]})

    ship(spark)
    return rows.groupBy("low", "high").applyInPandas(meet, "src long, dst long")


BUILDERS = {f.__name__: f for f in (links, stars, geo, chain, supply, trade, basket, talk, twins, similar)}


def graph(spark: SparkSession, sf_dir: str, name: str, directed: bool = False, weighted: bool = False) -> Graph:
    """A graph by name, made from its tables each time it is asked for.  The files of
    graphs that nobody holds any more go first."""
    release(spark)
    edges = trade_weighted(spark, sf_dir) if weighted else BUILDERS[name](spark, sf_dir)
    return Graph.from_edges(edges, directed=directed, weight="weight" if weighted else None)


def source_of(g: Graph) -> int:
    """The smallest identifier."""
    return g.vertices.agg(F.min("id")).first()[0]
