"""Mixing sources to target weights by exponential-key sampling.

A document's key is ``-ln(u) / quality``: ``u`` is a uniform number from a hash
of its identifier and a seed, so reruns agree; better documents tend to smaller
keys.  Within a source, complete epochs come first and the rest of the target
is filled in key order by running sums of sizes.

The running sum is never taken over a whole source in one task.  Keys fall into
``BUCKETS`` ranges; sums per (source, range) tell in which range the target is
reached, ranges before it are taken whole, and only that range is sorted.

Null text has size 0; a null source is one source of its own, last in order.
Repeated rows count and are taken each on their own (a repeated row has equal
keys and is ordered by doc_id, then size).  A source without words has target
0.  An empty table gives an empty result.  Columns other than doc_id, text and
source are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD, cut, fresh, small

BUCKETS = 4096
WEIGHTS = (5.0, 2.0, 1.0)
MOST_EPOCHS = 3
SEED = "mix-1"


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def quality(text: Column) -> Column:
    """1 for plain prose, less with the share of mark-up and symbol characters."""
    symbols = F.length(text) - F.length(F.translate(text, "#$%&*|<>{}[]=_~^\\", ""))
    return F.greatest(F.lit(0.05), F.coalesce(1 - 4 * F.try_divide(symbols, F.length(text)), F.lit(1.0)))


def uniform(doc_id: Column, seed: str = SEED) -> Column:
    """A number in (0, 1) from the first 48 bits of an md5."""
    word = F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(seed), doc_id.cast("string")).cast("binary")), 1, 12), 16, 10)
    return (word.cast("double") + 0.5) / float(1 << 48)


def targets(sizes: DataFrame, weights: tuple[float, ...] = WEIGHTS, most: int = MOST_EPOCHS) -> DataFrame:
    """(source, source_size, target) from (source, source_size).

    Sources take ``weights`` in turn by code point, null last, and share the
    whole size.  A target stops at ``most`` times its source's size and the
    excess goes to the others by weight; in the order of size over weight the
    stopped sources come first, so one running sum finds them.
    """
    place = F.row_number().over(Window.orderBy(F.col("source").isNull(), F.col("source"))) - 1
    weight = F.element_at(F.array(*map(F.lit, weights)), (place % len(weights) + 1).cast("int"))
    df = sizes.withColumn("weight", weight).withColumn("most", F.col("source_size") * float(most))
    order = Window.orderBy(F.col("most") / F.col("weight"), F.col("source").isNull(), F.col("source"))
    whole = Window.partitionBy()
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    df = (
        df.withColumn("total", F.sum("source_size").over(whole).cast("double"))
        .withColumn("spent", F.coalesce(F.sum("most").over(before), F.lit(0.0)))
        .withColumn("still", F.sum("weight").over(order.rowsBetween(0, Window.unboundedFollowing)))
    )
    df = df.withColumn("level", (F.col("total") - F.col("spent")) / F.col("still"))
    df = df.withColumn("stops", F.col("most") <= F.col("level") * F.col("weight"))
    first = F.first(F.when(~F.col("stops"), F.col("level")), ignorenulls=True).over(order.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    goal = F.when(F.col("stops"), F.col("most")).otherwise(first * F.col("weight"))
    return df.select("source", "source_size", F.round(goal, 6).alias("target"))


def mix(docs: DataFrame, weights: tuple[float, ...] = WEIGHTS, most: int = MOST_EPOCHS, seed: str = SEED) -> DataFrame:
    """doc_id, size, source_size, target, taken and copies, one row per document."""
    key = -F.log(uniform(F.col("doc_id"), seed)) / F.col("quality")
    rows = docs.select("doc_id", "source", word_count(F.col("text")).alias("size"), quality(F.col("text")).alias("quality"))
    rows = rows.withColumn("key", F.coalesce(key, F.lit(0.0)))
    rows = cut(rows.select("doc_id", "source", "size", "key", F.floor((1 - F.exp(-F.col("key"))) * BUCKETS).cast("int").alias("bucket")))

    ranges = rows.groupBy("source", "bucket").agg(F.sum("size").alias("bucket_size"), F.count(F.lit(1)).alias("n"))
    ranges = cut(ranges)
    sources = ranges.groupBy("source").agg(F.sum("bucket_size").alias("source_size"))
    goals = targets(sources, weights, most)
    epochs = F.when(F.col("source_size") > 0, F.least(F.lit(most), F.floor(F.try_divide(F.col("target"), F.col("source_size")))))
    goals = goals.withColumn("epochs", F.coalesce(epochs, F.lit(0)).cast("long"))
    goals = goals.withColumn("rest", F.when(F.col("epochs") < most, F.col("target") - F.col("epochs") * F.col("source_size")).otherwise(0.0))

    by = Window.partitionBy("source").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    same = F.col("r.source").eqNullSafe(F.col("g.source"))
    sums = ranges.withColumn("before", F.coalesce(F.sum("bucket_size").over(by), F.lit(0)))
    edge = (
        sums.alias("r")
        .join(goals.alias("g"), same)
        .where(F.col("before") <= F.col("rest"))
        .groupBy("g.source", "source_size", "target", "epochs", "rest")
        .agg(F.max(F.struct("bucket", "before")).alias("edge"))
    )
    edge = cut(edge.select("source", "source_size", "target", "epochs", "rest", F.col("edge.bucket").alias("edge"), F.col("edge.before").alias("before")))
    plan = rows.alias("r").join(small(edge, edge.count()).alias("g"), same).select(
        "r.doc_id", "r.source", "r.size", "r.key", "r.bucket", "g.source_size", "g.target", "g.epochs", "g.rest", "g.edge", "g.before"
    )
    inside = Window.partitionBy("source", "bucket").orderBy("key", "doc_id", "size").rowsBetween(Window.unboundedPreceding, -1)
    last = (
        plan.where(F.col("bucket") == F.col("edge"))
        .withColumn("run", F.col("before") + F.coalesce(F.sum("size").over(inside), F.lit(0)))
        .withColumn("more", ((F.col("run") + F.col("size") / 2 <= F.col("rest")) & (F.col("epochs") < most)).cast("long"))
        .drop("run")
    )
    others = plan.where(F.col("bucket") != F.col("edge")).withColumn("more", (F.col("bucket") < F.col("edge")).cast("long"))
    return last.unionByName(others).select(
        "doc_id", "source", "size", "source_size", "target", (F.col("epochs") + F.col("more")).alias("copies")
    ).withColumn("taken", F.col("size") * F.col("copies"))


def take(docs: DataFrame, weights: tuple[float, ...] = WEIGHTS, most: int = MOST_EPOCHS, seed: str = SEED) -> DataFrame:
    """The rows of ``docs`` as often as the mix takes them; untaken rows go.
    Rows that share a doc_id are taken alike, as often as any of them is."""
    at, copies, turn = fresh(docs, "row_at", "row_copies", "row_turn")
    plan = mix(docs, weights, most, seed).groupBy(F.col("doc_id").alias(at)).agg(F.max("copies").alias(copies))
    plan = cut(plan.where(F.col(copies) > 0))
    joined = docs.join(small(plan, plan.count()), docs["doc_id"].eqNullSafe(F.col(at)))
    again = joined.withColumn(turn, F.explode(F.sequence(F.lit(1), F.col(copies).cast("int"))))
    return again.select(docs.columns)
