"""Repeated lines: two Bloom filters pick suspects, an exact count decides.

A line's key is the line stripped of ASCII white space with A-Z lowered.  Keys
of at least ``MIN_CHARS`` code points that occur in at least ``MIN_DOCS``
documents lose all their lines except those of the largest doc_id that holds
the key.

Key hashes are dealt to owners, each with its share of two filters: a hash new
to the once-filter is put there, one already there is put into the
twice-filter.  Filters and owners are sized by the counted bytes of all texts,
up to ``MOST_BITS``, because the twice-filters go to every worker; too small a
filter only makes more suspects, never another result.  Only suspect keys are
shuffled whole and counted exactly per key, with partial counts first.
Confirmed keys, if counted to be few, go to the workers, which drop lines where
the texts are, so no text is shuffled; if they are many, the numbers of the
lines to drop are joined to their texts.

Null and empty texts are one empty line; very long texts are read whole.  Rows
with equal doc_id are the same document for the counts; a null doc_id counts as
one more document and is below all others.  A row loses only lines of its own
text, whoever shares its doc_id.  Keys tie only by doc_id.  Extra columns are
ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Shared, cut, fresh, map_batches, map_rows, small

MIN_CHARS = 40
MIN_DOCS = 5
SPACE = b"\x20\t\n\x0b\x0c\r"

#: Bits of the twice-filters of all owners together: a few per possible key,
#: between these bounds; bits of one owner's share; probes of a hash.
LEAST_BITS, MOST_BITS = 1 << 22, 1 << 29
OWNER_BITS = 1 << 20
PROBES = 3

#: Most bytes of confirmed keys that are sent to every worker.
KEYS_SENT = 16 << 20

#: Characters of keys that count as one row of a broadcast.
KEY_BYTES = 200

#: What a null doc_id counts as.
NO_ID = -(1 << 63)


def key_of(line: bytes) -> bytes:
    """The key of a line in UTF-8, empty if it is shorter than ``MIN_CHARS``."""
    key = line.strip(SPACE)
    if len(key) < MIN_CHARS or not key.isascii() and len(key.decode()) < MIN_CHARS:
        return b""
    return key.lower()  # on bytes, only A-Z are lowered


def keys_of(text: str | None) -> list[bytes]:
    """The key of every line."""
    return [key_of(x) if len(x) >= MIN_CHARS else b"" for x in (text or "").encode().split(b"\n")]


class Filter:
    """A Bloom filter over 64-bit hashes, many at a time."""

    def __init__(self, bits: int, data: bytes | None = None):
        self.bits = bits
        self._cells = np.zeros(bits // 8, dtype=np.uint8) if data is None else np.frombuffer(data, dtype=np.uint8)

    def _places(self, hashes: np.ndarray) -> np.ndarray:
        low, high = hashes & np.uint64(0xFFFFFFFF), (hashes >> np.uint64(32)) | np.uint64(1)
        return np.array([(low + np.uint64(i) * high) % np.uint64(self.bits) for i in range(PROBES)])

    def add(self, hashes: np.ndarray) -> None:
        at = self._places(hashes).ravel()
        np.bitwise_or.at(self._cells, (at >> np.uint64(3)).astype(np.int64), (np.uint8(1) << (at & np.uint64(7)).astype(np.uint8)))

    def holds(self, hashes: np.ndarray) -> np.ndarray:
        at = self._places(hashes)
        return ((self._cells[(at >> np.uint64(3)).astype(np.int64)] >> (at & np.uint64(7)).astype(np.uint8)) & 1).all(axis=0)

    def data(self) -> bytes:
        return self._cells.tobytes()


def _owner(hashes: np.ndarray, owners: int) -> np.ndarray:
    return ((hashes >> np.uint64(40)) % np.uint64(owners)).astype(np.int64)


def _hash_all(keys: list[bytes]) -> np.ndarray:
    return np.fromiter(map(xxhash.xxh3_64_intdigest, keys), dtype=np.uint64, count=len(keys))


class Suspects:
    """The twice-filters of all owners, for look-ups in the workers."""

    def __init__(self, model: tuple[int, int, dict[int, bytes]]):
        self._owners, bits, parts = model
        self._filters = {o: Filter(bits, data) for o, data in parts.items()}

    def among(self, hashes: np.ndarray) -> np.ndarray:
        out = np.zeros(len(hashes), dtype=bool)
        owner = _owner(hashes, self._owners)
        for o in np.unique(owner):
            if o in self._filters:
                mine = owner == o
                out[mine] = self._filters[o].holds(hashes[mine])
        return out


def filter_bits(docs: DataFrame) -> int:
    """A power of two: four bits for every key that the texts could hold."""
    size = docs.agg(F.coalesce(F.sum(F.octet_length("text").cast("long")), F.lit(0))).first()[0]
    return min(MOST_BITS, max(LEAST_BITS, 1 << (4 * size // (MIN_CHARS + 1)).bit_length()))


def twice_filters(docs: DataFrame, bits: int | None = None) -> tuple[int, int, dict[int, bytes]]:
    """The bounded model of keys seen in more than one row."""
    bits = bits or filter_bits(docs)
    owners = max(64, bits // OWNER_BITS)
    each = bits // owners

    def pack(batch: pa.RecordBatch) -> dict:
        per_doc = [_hash_all(list(keys)) for t in batch.column(0) if (keys := {k for k in keys_of(t.as_py()) if k})]
        if not per_doc:
            return {"owner": [], "hashes": []}
        hashes, seen = np.unique(np.concatenate(per_doc), return_counts=True)
        # twice is as good as many times
        hashes = np.concatenate([hashes, hashes[seen > 1]])
        owner = _owner(hashes, owners)
        order = np.argsort(owner, kind="stable")
        present, first = np.unique(owner[order], return_index=True)
        return {"owner": present, "hashes": [x.tobytes() for x in np.split(hashes[order], first[1:])]}

    def own(batches: Iterator[pa.RecordBatch]) -> Iterator[dict]:
        mine: dict[int, tuple[Filter, Filter]] = {}
        for batch in batches:
            for o, packed in zip(batch.column(0).to_pylist(), batch.column(1)):
                once, twice = mine.setdefault(o, (Filter(each * 4), Filter(each)))
                hashes = np.frombuffer(packed.as_py(), dtype=np.uint64)
                distinct, seen = np.unique(hashes, return_counts=True)
                again = once.holds(distinct) | (seen > 1)
                twice.add(distinct[again])
                once.add(distinct[~again])
        for o, (_, twice) in mine.items():
            yield {"owner": [o], "twice": [twice.data()]}

    packed = map_rows(docs.select("text"), pack, "owner int, hashes binary")
    found = map_batches(packed.repartition(owners, "owner"), own, "owner int, twice binary").collect()
    return owners, each, {r.owner: bytes(r.twice) for r in found}


def _at() -> Column:
    return F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID))


def _digest() -> Column:
    return F.unhex(F.sha2(F.coalesce("text", F.lit("")).cast("binary"), 256))


def _suspects(docs: DataFrame, bits: int | None) -> DataFrame:
    """(doc_id, digest, key, lines): lines whose key passes the twice-filters,
    as numbers from 0 per row and key."""
    shared = Shared(docs.sparkSession, twice_filters(docs, bits), Suspects)

    def suspect(batch: pa.RecordBatch) -> dict:
        ids, digests, keys, lines = [], [], [], []
        suspects = shared.get()
        for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1)):
            where: dict[bytes, list[int]] = {}
            raw = (text.as_py() or "").encode()
            for n, line in enumerate(raw.split(b"\n")):
                if len(line) >= MIN_CHARS and (key := key_of(line)):
                    where.setdefault(key, []).append(n)
            names, digest = list(where), None
            for key, hit in zip(names, suspects.among(_hash_all(names))):
                if hit:
                    digest = digest or hashlib.sha256(raw).digest()
                    ids.append(doc_id)
                    digests.append(digest)
                    keys.append(key.decode())
                    lines.append(where[key])
        return {"doc_id": ids, "digest": digests, "key": keys, "lines": lines}

    return cut(map_rows(docs.select(_at().alias("doc_id"), "text"), suspect, "doc_id long, digest binary, key string, lines array<int>"))


def _confirmed(suspects: DataFrame, min_docs: int) -> tuple[DataFrame, int, int]:
    """(key, keep_id) of the keys of enough documents, how many, their bytes."""
    # rows of one document with the same key count once
    per_doc = suspects.select("key", "doc_id").distinct()
    found = per_doc.groupBy("key").agg(F.count(F.lit(1)).alias("n"), F.max("doc_id").alias("keep_id")).where(F.col("n") >= min_docs)
    found = cut(found.select("key", "keep_id"))
    return found, *found.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.octet_length("key").cast("long")), F.lit(0))).first()


def repeated_lines(suspects: DataFrame, found: DataFrame, rows: int) -> DataFrame:
    """(doc_id, digest, lines) of the lines to drop: numbers from 0, one row per
    doc_id and text as an array ``lines``."""
    # broadcast only if counted small; else both sides shuffle and hot keys can be split
    drops = suspects.join(small(found, rows), "key").where(F.col("doc_id") != F.col("keep_id"))
    # equal rows have equal arrays, so a set holds no more than the lines of one text
    return drops.groupBy("doc_id", "digest").agg(F.flatten(F.collect_set("lines")).alias("lines"))


def _without(text: str | None, gone: list[int] | None) -> tuple[str | None, int, int]:
    """The text without its lines ``gone``, its lines and how many went."""
    parts = (text or "").split("\n")
    if not gone:
        return text, len(parts), 0
    numbers = set(gone)
    return "\n".join(x for n, x in enumerate(parts) if n not in numbers), len(parts), len(numbers)


def _dropping(docs: DataFrame, make: Callable, schema, bits: int | None, min_docs: int, keys_sent: int) -> DataFrame:
    """Apply ``make`` (columns of a batch, and of each row the text that stays,
    its lines and how many go) to all rows of ``docs``."""
    suspects = _suspects(docs, bits)
    found, count, size = _confirmed(suspects, min_docs)
    at, digest, drop = fresh(docs, "row_at", "row_digest", "row_drop")
    if size + 100 * count <= keys_sent:
        kept = {key.encode(): keep for key, keep in found.toArrow().to_pandas().itertuples(index=False)}
        shared = Shared(docs.sparkSession, kept)

        def kernel(batch: pa.RecordBatch) -> dict:
            keep = shared.get()
            columns = {name: batch.column(i) for i, name in enumerate(batch.schema.names)}
            results = []
            for here, text in zip(columns.pop(at).to_pylist(), columns["text"].to_pylist()):
                gone = []
                if keep and text and len(text) >= MIN_CHARS:
                    for n, key in enumerate(keys_of(text)):
                        if key and keep.get(key, here) != here:
                            gone.append(n)
                results.append(_without(text, gone))
            return make(columns, results)

        return map_rows(docs.withColumn(at, _at()), kernel, schema)
    drops = repeated_lines(suspects, found, max(count, size // KEY_BYTES))
    drops = drops.select(F.col("doc_id").alias(at), F.col("digest").alias(digest), F.col("lines").alias(drop))
    joined = docs.withColumn(at, _at()).withColumn(digest, _digest()).join(drops, [at, digest], "left").drop(at, digest)

    def kernel(batch: pa.RecordBatch) -> dict:
        columns = {name: batch.column(i) for i, name in enumerate(batch.schema.names)}
        gone = columns.pop(drop).to_pylist()
        return make(columns, [_without(t, g) for t, g in zip(columns["text"].to_pylist(), gone)])

    return map_rows(joined, kernel, schema)


def dedup_lines(docs: DataFrame, bits: int | None = None, min_docs: int = MIN_DOCS, keys_sent: int = KEYS_SENT) -> DataFrame:
    """The rows and columns of ``docs`` with repeated lines dropped from ``text``."""
    make = lambda columns, results: columns | {"text": [text for text, _, _ in results]}
    return _dropping(docs, make, docs.schema, bits, min_docs, keys_sent)


def line_report(docs: DataFrame, bits: int | None = None, keys_sent: int = KEYS_SENT) -> DataFrame:
    """Counts and the hash of what stays of each document."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")

    def make(columns: dict, results: list) -> dict:
        hashes = [hashlib.sha256((x or "").encode()).hexdigest() for x, _, _ in results]
        return {"doc_id": columns["doc_id"], "n_lines": [n for _, n, _ in results], "n_dropped": [n for _, _, n in results], "kept_sha256": hashes}

    return _dropping(rows, make, "doc_id long, n_lines long, n_dropped long, kept_sha256 string", bits, MIN_DOCS, keys_sent)
