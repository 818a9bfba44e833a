"""Near duplicates: SuperMinHash, banding, exact verification, union-find.

1. Each whole text gives its set of word shingles, a 128-bit fingerprint of the
   set, a SuperMinHash signature and its band keys.  Only these small rows are
   kept.  Equal sets are folded into one representative (the least doc_id).
2. Representatives that share a band key form a bucket.  Every member is
   compared exactly with the least one, its pivot.  A pivot's set travels with
   each few hundred of its members, so a huge bucket is many small tasks that
   hold one set and stream the others.  Union-find gives the classes so far.
3. Buckets whose other members are still of several classes are compared once
   more: members outside the bucket's largest class, in groups, against all
   members, in chunks; each group and chunk meet in a task of their own.  Members
   of one class need no comparison, so no link between classes is lost and a
   group of copies never makes all of its pairs.
4. The verified links are grouped by union-find over the cluster.

With 32 bands of 4 rows a pair of similarity 0.75 shares no band with a chance
below 1e-5.  Sets are of 64-bit shingle hashes: two different shingles of a pair
of texts that hash alike (chance below 1e-9 for texts of 10^5 words) would count
as one, and equal sets are known by a 128-bit fingerprint.

Null, empty and wordless texts have no shingles and are linked with nothing.  A
null doc_id is linked with nothing and is its own class (null, kept).  Repeated
rows have equal sets and one class; rows that share a doc_id are one document
with several texts.  Very long texts are one set each, whatever their length.
Ties of similarity are links at exactly the threshold.  Extra columns are
ignored, whatever their names; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import counted, cut, map_batches, map_rows, small, small_cut
from .components import connected
from .superminhash import band_keys, shingles, signatures, similar

PERCENT = 75

#: Shingles and documents of a chunk; a task holds two chunks at most.
CHUNK_SHINGLES = 1_000_000
CHUNK_DOCS = 256

#: Shingles whose signatures are computed side by side.
TOGETHER = 500_000


def _features(batch: pa.RecordBatch) -> dict:
    sizes, high, low, keys = [], [], [], []
    waiting: list[np.ndarray] = []

    def sign() -> None:
        if waiting:
            keys.extend(band_keys(signatures(waiting)).view(np.int64).tolist())
            waiting.clear()

    total = 0
    for text in batch.column(1):
        found = shingles(text.as_py())
        print_ = xxhash.xxh3_128_intdigest(found.tobytes())
        sizes.append(len(found))
        high.append((print_ >> 64) - (1 << 63))
        low.append((print_ & (1 << 64) - 1) - (1 << 63))
        waiting.append(found)
        total += len(found)
        if total >= TOGETHER:
            sign()
            total = 0
    sign()
    return {"doc_id": batch.column(0), "n": sizes, "high": high, "low": low, "bands": [k if n else [] for k, n in zip(keys, sizes)]}


def _sets(batch: pa.RecordBatch) -> dict:
    columns = {name: batch.column(i) for i, name in enumerate(batch.schema.names)}
    found, last, raw = [], None, b""
    for text in columns.pop("text").to_pylist():  # rows of one document follow one another
        if text != last:
            last, raw = text, shingles(text).tobytes()
        found.append(raw)
    columns["found"] = found
    return columns


def links_within(ids: list[int], sets: list[np.ndarray], percent: int = PERCENT) -> list[tuple[int, int]]:
    """Links that join all classes of these documents, by exact comparison."""
    count = len(ids)
    sizes = np.fromiter(map(len, sets), dtype=np.int64, count=count)
    owner = np.repeat(np.arange(count), sizes)
    _, token, seen = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    common = seen[token] > 1  # a token of one document adds to no overlap
    owner, token = owner[common], token[common]
    shared = np.bincount(owner, minlength=count)
    order = np.argsort(token, kind="stable")
    holders = owner[order]
    ends = np.cumsum(np.bincount(token, minlength=len(seen)))
    starts = np.concatenate([[0], np.cumsum(shared)])
    label = np.arange(count)
    members = np.ones(count, dtype=np.int64)
    done = 100 * shared < percent * sizes  # too little in common with anything
    out: list[tuple[int, int]] = []

    def compare(q: int) -> None:
        mine = token[starts[q] : starts[q + 1]]
        stop = ends[mine]
        width = seen[mine]
        first = np.repeat(stop - width - np.concatenate([[0], np.cumsum(width)[:-1]]), width)
        overlap = np.bincount(holders[first + np.arange(int(width.sum()))], minlength=count)
        hit = 100 * overlap >= percent * (sizes[q] + sizes - overlap)
        for other in np.unique(label[hit]):
            partner = np.flatnonzero(hit & (label == other))
            if other != label[q] and len(partner):  # none left: merged just now
                out.append((ids[q], ids[int(partner[0])]))
                into, gone = (label[q], other) if members[label[q]] >= members[other] else (other, label[q])
                members[into] += members[gone]
                members[gone] = 0
                label[label == gone] = into

    while True:
        largest = int(np.argmax(members))
        open_ = np.flatnonzero(~done & ((label != largest) | (members[largest] == 1)))
        if not len(open_):
            return out
        for q in open_.tolist():
            if label[q] == np.argmax(members) and members[label[q]] > 1:
                continue
            compare(q)
            done[q] = True


def _meet_pivot(percent: int):
    """Links of members to their unit's pivot, whose rows come first."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[dict]:
        unit, pivots = None, {}
        for batch in batches:
            a, b = [], []
            keys, roles, docs = zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()), batch.column(2).to_pylist(), batch.column(3).to_pylist()
            for now, member, doc, raw in zip(keys, roles, docs, batch.column(4)):
                if now != unit:
                    unit, pivots = now, {}
                if not member:
                    one = raw.as_py()
                    pivots[one] = np.frombuffer(one, dtype=np.uint64)
                elif any(similar(np.frombuffer(raw.as_py(), dtype=np.uint64), p, percent) for p in pivots.values()):
                    a.append(doc)
                    b.append(now[0])
            yield {"a": a, "b": b}

    return kernel


def _meet_chunk(percent: int):
    """Links among the rows of each unit."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[dict]:
        key, held = None, {}

        def flush() -> dict:
            ids, sets = [i for i, _ in held], [np.frombuffer(raw, dtype=np.uint64) for _, raw in held]
            found = links_within(ids, sets, percent) if len(ids) > 1 else []
            return {"a": [a for a, _ in found], "b": [b for _, b in found]} if found else {}

        for batch in batches:
            parts = [batch.column(i).to_pylist() for i in range(4)]
            for *now, doc, raw in zip(*parts, batch.column(4)):
                if now != key:
                    yield flush()
                    key, held = now, {}
                held[doc, raw.as_py()] = None  # of the group and of the chunk: once
        yield flush()

    return kernel


def _star_links(rows: DataFrame, shared: DataFrame, percent: int, chunk_docs: int) -> DataFrame:
    """Exact links (a, b) of bucket members to their pivots."""
    pairs = cut(shared.where("node <> pivot").select("node", "pivot").distinct())
    wide = pairs.groupBy("pivot").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > chunk_docs)
    wide = small_cut(wide.select("pivot", F.ceil(F.col("n") / chunk_docs).alias("chunks")))
    salt = F.pmod(F.xxhash64("node"), F.coalesce("chunks", F.lit(1))).cast("int")
    members = pairs.join(wide, "pivot", "left").select("pivot", salt.alias("salt"), F.lit(1).alias("member"), "node")
    units = members.select("pivot", "salt", F.lit(0).alias("member"), F.col("pivot").alias("node")).distinct()
    tasks = small_cut(members.unionByName(units).withColumnRenamed("node", "doc_id"))
    chosen = rows.join(tasks, "doc_id").select("pivot", "salt", "member", "doc_id", "text")
    sets = map_rows(chosen, _sets, "pivot long, salt int, member int, doc_id long, found binary")
    dealt = sets.repartition("pivot", "salt").sortWithinPartitions("pivot", "salt", "member", "doc_id")
    return cut(map_batches(dealt, _meet_pivot(percent), "a long, b long"))


def _rest_links(rows: DataFrame, shared: DataFrame, classes: DataFrame, percent: int, chunk_docs: int, chunk_shingles: int) -> DataFrame | None:
    """Links of members that neither are a pivot nor share a class; None if
    there are none."""
    others = shared.where("node <> pivot").select("key", "node", "n")
    label = F.coalesce("component", "node").alias("label")
    others = others.join(classes, "node", "left").select("key", "node", "n", label)
    sized = others.groupBy("key", "label").agg(F.count(F.lit(1)).alias("docs"), F.sum("n").alias("n"), F.bit_xor(F.xxhash64("node")).alias("mark"))
    torn = sized.groupBy("key").agg(
        F.max(F.struct("docs", "label", "n")).alias("top"), F.sum("docs").alias("docs"), F.sum("n").alias("n"), F.bit_xor("mark").alias("mark"), F.count(F.lit(1)).alias("labels")
    ).where("labels > 1")
    # the same members under several keys meet once
    torn = torn.groupBy("docs", "n", "mark").agg(F.min(F.struct("key", "top")).alias("one"))
    parts = lambda docs, n: F.greatest(F.ceil(docs / chunk_docs), F.ceil(n / chunk_shingles), F.lit(1)).cast("int")
    torn = torn.select(
        F.col("one.key").alias("key"),
        F.col("one.top.label").alias("largest"),
        parts(F.col("docs"), F.col("n")).alias("chunks"),
        parts(F.col("docs") - F.col("one.top.docs"), F.col("n") - F.col("one.top.n")).alias("groups"),
    )
    torn, seen = counted(torn)
    if not seen["rows"]:
        return None
    inside = others.join(small(torn, seen["rows"]), "key")
    every = lambda k: F.explode(F.sequence(F.lit(0), F.col(k) - 1))
    in_group, in_chunk = F.pmod(F.xxhash64("node", F.lit(1)), F.col("groups")).cast("int"), F.pmod(F.xxhash64("node"), F.col("chunks")).cast("int")
    opened = inside.where("label <> largest").select("key", in_group.alias("g"), every("chunks").alias("c"), F.col("node").alias("doc_id"))
    faced = inside.select("key", every("groups").alias("g"), in_chunk.alias("c"), F.col("node").alias("doc_id"))
    tasks = small_cut(opened.unionByName(faced).distinct())
    chosen = rows.join(tasks, "doc_id").select("key", "g", "c", "doc_id", "text")
    sets = map_rows(chosen, _sets, "key long, g int, c int, doc_id long, found binary")
    units = ("key", "g", "c")
    dealt = sets.repartition(*units).sortWithinPartitions(*units, "doc_id")
    more, seen = counted(map_batches(dealt, _meet_chunk(percent), "a long, b long"))
    return more if seen["rows"] else None


def near_duplicates(
    docs: DataFrame, percent: int = PERCENT, chunk_shingles: int = CHUNK_SHINGLES, chunk_docs: int = CHUNK_DOCS
) -> DataFrame:
    """doc_id, n_shingles, component_id and kept of every row."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    features = cut(map_rows(rows, _features, "doc_id long, n long, high long, low long, bands array<long>"))
    real = features.where("n > 0 and doc_id is not null")
    folded = real.groupBy("n", "high", "low").agg(F.min(F.struct("doc_id", "bands")).alias("one"), F.count(F.lit(1)).alias("copies"))
    folded = cut(folded.select("n", "high", "low", "copies", F.col("one.doc_id").alias("node"), F.col("one.bands").alias("bands")))

    members = folded.select("node", "n", F.explode("bands").alias("key"))
    buckets = members.groupBy("key").agg(F.min("node").alias("pivot"), F.max("node").alias("last")).where("pivot < last").drop("last")
    shared = cut(members.join(buckets, "key"))
    links = _star_links(rows, shared, percent, chunk_docs)
    classes = small_cut(connected(links))
    more = _rest_links(rows, shared, classes, percent, chunk_docs, chunk_shingles)
    if more is not None:
        classes = connected(links.unionByName(more))

    known = folded.join(classes, "node", "left").where("copies > 1 or component is not null")
    known = small_cut(known.select("n", "high", "low", F.coalesce("component", "node").alias("component")))
    out = features.join(known, ["n", "high", "low"], "left")
    component = F.when(F.col("doc_id").isNotNull(), F.coalesce("component", "doc_id"))
    return out.select(
        "doc_id", F.col("n").alias("n_shingles"), component.alias("component_id"), component.eqNullSafe(F.col("doc_id")).alias("kept")
    )


def keep_one(docs: DataFrame, percent: int = PERCENT) -> DataFrame:
    """The rows of ``docs`` without those that near-copy a lesser doc_id."""
    gone = small_cut(near_duplicates(docs, percent).where("not kept").select("doc_id").distinct())
    return docs.join(gone, "doc_id", "left_anti").select(docs.columns)
