"""Exact duplicates with Patricia tries over whole byte strings.

Texts are equal when their bytes are, after lowering A-Z.  Rows go to owners by
length and content hash; an owner inserts the full byte strings, headed by their
length, into one compressed radix trie, whose terminal nodes hold the identifier
that stays and the number of rows.  Equality is decided by the trie alone, so a
collision of the routing hash cannot merge two texts.

Copies within a partition are folded before the shuffle (within every
``FOLDED`` bytes of different texts), so a text that fills a third of the table
arrives about once per partition.  Very long texts are inserted whole.  A trie that outgrows its budget
writes subtrees, small ones together, to unnamed files until half the budget is
free; later strings that lead there are appended, and each file is finished on
its own at the end.  Only labels of one string may take more than the budget.  Documents get their
group by a join on the 256-bit digest (or on whole texts, if the caller routes
by a weaker hash).

Null text counts as empty, and all empty texts are one group.  Rows with equal
doc_id count each; a null doc_id stays only in a group of nulls.  Extra columns
are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import pickle
import tempfile
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_batches, map_rows

#: Bytes of labels a trie holds in memory before it spills subtrees.
BUDGET = 256 << 20


#: Bytes of different texts that are held to fold copies before the shuffle.
FOLDED = 32 << 20


def common_prefix(a: bytes, b: bytes) -> int:
    """Length of the common prefix, by halving."""
    n = min(len(a), len(b))
    if a[:n] == b[:n]:
        return n
    low = 0
    while n - low > 1:
        middle = (low + n) // 2
        if a[low:middle] == b[low:middle]:
            low = middle
        else:
            n = middle
    return low


class _Node:
    __slots__ = ("label", "children", "held", "file", "base", "size")

    def __init__(self, label: bytes):
        self.label, self.children, self.held, self.file, self.base, self.size = label, {}, None, None, 0, len(label)


def _records(file) -> Iterator[tuple[bytes, object]]:
    file.seek(0)
    while True:
        try:
            yield pickle.load(file)
        except EOFError:
            return


class Patricia:
    """Byte strings to values; equal strings fold their values with ``fold``."""

    def __init__(self, fold: Callable, budget: int = BUDGET):
        self._root, self._fold, self._fixed, self._budget, self.spilled = _Node(b""), fold, budget, budget, 0

    def insert(self, key: bytes, value) -> None:
        node, at, path = self._root, 0, []
        while True:
            path.append(node)
            if node.file is not None:
                pickle.dump((key[node.base :], value), node.file)
                return
            if at == len(key):
                node.held = value if node.held is None else self._fold(node.held, value)
                return
            child = node.children.get(key[at])
            if child is None:
                child = node.children[key[at]] = _Node(key[at:])
                child.held = value
                grown = len(child.label) + 64
                break
            rest = key[at : at + len(child.label)]
            same = len(rest) if rest == child.label else common_prefix(rest, child.label)
            if same < len(child.label):
                fork = _Node(child.label[:same])
                child.label = child.label[same:]
                fork.children[child.label[0]] = child
                fork.size = child.size + 64
                node.children[key[at]] = fork
                child.size -= same
                child = fork
            node, at = child, at + same
        for x in path:
            x.size += grown
        if self._root.size > self._budget:
            self._spill()

    def _spill(self) -> None:
        """Write subtrees to files until half the budget is free."""
        while self._root.size > self._fixed // 2 and self._spill_children():
            pass
        # what is left above it are the labels of one string: they need their memory
        self._budget = max(self._fixed, self._root.size + self._fixed // 2)

    def _spill_children(self) -> bool:
        """Write children of the lowest node that holds over half of all, the
        largest first; children under a quarter of the budget share files."""
        path = [self._root]
        while True:
            inside = [c for c in path[-1].children.values() if c.file is None]
            largest = max(inside, key=lambda c: c.size, default=None)
            if largest is None or largest.size <= self._root.size // 2:
                break
            path.append(largest)
        while not inside and len(path) > 1:  # one long label: what stands beside it goes
            long = path.pop()
            inside = [c for c in path[-1].children.values() if c.file is None and c is not long]
        if not inside:
            return False
        head = b"".join(x.label for x in path)
        file, size = None, 0
        for child in sorted(inside, key=lambda c: -c.size):
            if self._root.size <= self._fixed // 2:
                break
            if file is None or size >= self._fixed // 4:
                file, size = tempfile.TemporaryFile(), 0
                self.spilled += 1
            inner: dict = {}
            for key, value in self._held(child, head + child.label, inner):
                pickle.dump((key[len(head) :], value), file)
            for start, old in inner.values():
                for tail, value in _records(old):
                    pickle.dump(((start + tail)[len(head) :], value), file)
                old.close()
            freed = child.size - 1
            size += child.size
            # all strings that go on with this byte are in the file
            child.label, child.children, child.held, child.size = child.label[:1], {}, None, 1
            child.file, child.base = file, len(head)
            for x in path:
                x.size -= freed
        return True

    def _held(self, top: _Node, key: bytes, files: dict) -> Iterator[tuple[bytes, object]]:
        """Strings in memory from ``top`` on, which ends ``key``; ``files`` gets
        the files met and the string they go on from."""
        todo = [(top, key)]
        while todo:
            node, key = todo.pop()
            if node.held is not None:
                yield key, node.held
            if node.file is not None:
                files[id(node.file)] = (key[: node.base], node.file)
            todo += [(c, key + c.label) for c in node.children.values()]

    def __iter__(self) -> Iterator[tuple[bytes, object]]:
        """Every string once; the trie is empty after its strings in memory, so
        that each file has the memory to itself."""
        files: dict = {}
        yield from self._held(self._root, b"", files)
        self._root = _Node(b"")
        for start, file in files.values():
            inner = Patricia(self._fold, self._fixed)
            for tail, value in _records(file):
                inner.insert(tail, value)
            file.close()
            for tail, value in inner:
                yield start + tail, value


def normalised(text: str | None) -> bytes:
    return (text or "").encode().lower()  # on bytes, only A-Z are lowered


def fold_max(a: tuple, b: tuple) -> tuple:
    """The larger identifier (null last) and the sum of the counts."""
    ids = [x for x in (a[0], b[0]) if x is not None]
    return (max(ids) if ids else None, a[1] + b[1])


def fold_min(a: tuple, b: tuple) -> tuple:
    ids = [x for x in (a[0], b[0]) if x is not None]
    return (min(ids) if ids else None, a[1] + b[1])


def _digests(batch: pa.RecordBatch) -> dict:
    found = [hashlib.sha256(normalised(t.as_py())).digest() for t in batch.column(1)]
    return {"doc_id": batch.column(0), "digest": found}


def _parts(local: dict[bytes, tuple], route: Callable[[bytes], bytes]) -> Iterator[dict]:
    """Folded texts, some at a time."""
    items = list(local.items())
    for at in range(0, len(items), 1000):
        part = items[at : at + 1000]
        yield {
            "length": [len(raw) for raw, _ in part],
            "digest": [route(raw) for raw, _ in part],
            "raw": [raw for raw, _ in part],
            "best": [v[0] for _, v in part],
            "n": [v[1] for _, v in part],
        }


def exact_groups(docs: DataFrame, keep: str = "max", budget: int = BUDGET, hashed: Callable[[bytes], bytes] | None = None) -> DataFrame:
    """doc_id, keep_id, group_size, kept and text_sha256 of every row.

    ``hashed`` replaces the digest that routes texts (a weak one, in tests).
    """
    fold = {"max": fold_max, "min": fold_min}[keep]
    route = hashed or (lambda raw: hashlib.sha256(raw).digest())

    def fold_copies(batches: Iterator[pa.RecordBatch]) -> Iterator[dict]:
        local: dict[bytes, tuple] = {}
        size = 0
        for batch in batches:
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                raw = normalised(text.as_py())
                one = (doc_id, 1)
                if raw in local:
                    local[raw] = fold(local[raw], one)
                    continue
                local[raw] = one
                size += len(raw) + 100
                if size >= FOLDED:
                    yield from _parts(local, route)
                    local, size = {}, 0
        yield from _parts(local, route)

    def own(batches: Iterator[pa.RecordBatch]) -> Iterator[dict]:
        trie = Patricia(fold, budget)
        for batch in batches:
            for length, raw, best, n in zip(batch.column(0).to_pylist(), batch.column(2), batch.column(3).to_pylist(), batch.column(4).to_pylist()):
                trie.insert(length.to_bytes(4, "big") + raw.as_py(), (best, n))
        part: list[tuple] = []
        for key, (best, n) in trie:
            if n > 1:
                part.append((route(key[4:]), key[4:] if hashed else None, best, n))
            if len(part) == 1000:
                yield dict(zip(("digest", "raw", "keep_id", "n"), map(list, zip(*part))))
                part = []
        if part:
            yield dict(zip(("digest", "raw", "keep_id", "n"), map(list, zip(*part))))

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    folded = map_batches(rows, fold_copies, "length int, digest binary, raw binary, best long, n long")
    owned = folded.repartition("length", "digest")
    groups = map_batches(owned, own, "digest binary, raw binary, keep_id long, n long")
    if hashed is None:
        found = map_rows(rows, _digests, "doc_id long, digest binary")
        joined = found.join(groups.drop("raw"), "digest", "left")
        digest = F.lower(F.hex("digest"))
    else:
        found = rows.withColumn("raw", _lowered(F.col("text"))).drop("text")
        joined = found.join(groups.select("raw", "keep_id", "n"), "raw", "left")
        digest = F.sha2("raw", 256)
    alone = F.col("n").isNull()
    keep_id = F.when(alone, F.col("doc_id")).otherwise(F.col("keep_id"))
    return joined.select(
        "doc_id",
        keep_id.alias("keep_id"),
        F.coalesce("n", F.lit(1)).cast("long").alias("group_size"),
        keep_id.eqNullSafe(F.col("doc_id")).alias("kept"),
        digest.alias("text_sha256"),
    )


def _lowered(text):
    capitals = "".join(map(chr, range(65, 91)))
    return F.translate(F.coalesce(text, F.lit("")), capitals, capitals.lower()).cast("binary")
