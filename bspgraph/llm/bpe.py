"""Byte-level BPE with a minimal acyclic transducer as its lexicon.

Words are counted over the whole corpus in the JVM, the distinct ones are cut
into pieces, and the ``LEXICON_PIECES`` most frequent pieces are merged once.
These and the vocabulary's own entries are compiled into a minimal acyclic
automaton (equal suffixes share their states).  Each edge carries an additive
output; the outputs on a piece's path sum to its place in the table of id
sequences.  The automaton is one flat file that Spark puts on every executor
once; all workers there map the same file, so they share its pages.  Pieces
outside of it are merged exactly by rank, so the choice of the lexicon never
changes a result.

Text is split as byte-level BPE files prescribe; added tokens of the file are
cut out first.  Null text counts as empty: no ids, and empty text back.  Very
long texts are encoded whole, and very long pieces merged with a heap.  Rows are
mapped one by one: repeated rows, ties and clashing column names have no effect,
and an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import heapq
import json
import mmap
import os
import struct
import tempfile

import numpy as np
import pyarrow as pa
import regex
from pyspark import SparkFiles
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Shared, map_rows

VOCABULARY = "byte_bpe_50k.json"

#: Pieces in the lexicon: bounds its file, not what is encoded.
LEXICON_PIECES = 100_000

#: Words longer than this are not counted, pieces longer not looked up.
LONGEST_WORD = 64

#: First bytes of a word whose way is remembered, and how many ways at most.
HEAD, MOST_HEADS = 5, 50_000

_SPACE = r"\t\n\x0b\x0c\r\x20\x85\xa0" + "".join(map(chr, [0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000]))
PIECES = regex.compile(
    rf"'s|'t|'re|'ve|'m|'ll|'d| ?\p{{L}}+| ?\p{{N}}+| ?[^{_SPACE}\p{{L}}\p{{N}}]+|[{_SPACE}]+(?![^{_SPACE}])|[{_SPACE}]+"
)


def byte_letters() -> dict[int, str]:
    """The printable letter that stands for each byte in vocabulary files."""
    plain = [*range(ord("!"), ord("~") + 1), *range(ord("¡"), ord("¬") + 1), *range(ord("®"), ord("ÿ") + 1)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(rest)}


_ID = (1 << 20) - 1
_NO_PAIR = 1 << 60


class Merges:
    """Vocabulary and merge ranks of a file, and exact merging by rank."""

    def __init__(self, source: str):
        model = json.loads(source)
        back = {c: b for b, c in byte_letters().items()}
        self.added = {t["content"]: t["id"] for t in model["added_tokens"]}
        raw = {}
        for token, i in model["model"]["vocab"].items():
            if token not in self.added:
                raw[i] = bytes(back[c] for c in token)
        self.bytes_of = raw | {i: t.encode() for t, i in self.added.items()}
        ids = {b: i for i, b in raw.items()}
        self.single = [ids[bytes([b])] for b in range(256)]
        self.pairs = {}
        for rank, pair in enumerate(model["model"]["merges"]):
            left, right = pair if isinstance(pair, list) else pair.split(" ")
            left, right = (bytes(back[c] for c in x) for x in (left, right))
            self.pairs[ids[left] << 20 | ids[right]] = rank << 20 | ids[left + right]
        self.words = ids

    def merge(self, piece: bytes) -> list[int]:
        """Ids of one piece; the lowest rank goes first, the leftmost of equals.

        ``pairs`` holds rank and new id in one number, so the least of the
        waiting pairs is the next merge, and only its two neighbours change.
        """
        ids = [*map(self.single.__getitem__, piece)]
        if len(ids) > 48:
            return self._merge_long(ids)
        get, none = self.pairs.get, _NO_PAIR
        waiting = [get(a << 20 | b, none) for a, b in zip(ids, ids[1:])]
        while waiting:
            best = min(waiting)
            if best == none:
                break
            i, new = waiting.index(best), best & _ID
            ids[i : i + 2] = [new]
            del waiting[i]
            if i:
                waiting[i - 1] = get(ids[i - 1] << 20 | new, none)
            if i < len(waiting):
                waiting[i] = get(new << 20 | ids[i + 1], none)
        return ids

    def _merge_long(self, ids: list[int]) -> list[int]:
        """The same with a heap over a linked list, for pieces of any length."""
        n = len(ids)
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        heap = []

        def offer(i: int) -> None:
            j = after[i]
            if j < n and (found := self.pairs.get(ids[i] << 20 | ids[j])):
                heapq.heappush(heap, (found >> 20, i, ids[i], ids[j], found & _ID))

        for i in range(n - 1):
            offer(i)
        while heap:
            _, i, left, right, new = heapq.heappop(heap)
            j = after[i]
            if ids[i] != left or j >= n or ids[j] != right:
                continue
            ids[i], ids[j] = new, -1
            after[i] = after[j]
            if after[j] < n:
                before[after[j]] = i
            offer(i)
            if before[i] >= 0:
                offer(before[i])
        return [x for x in ids if x >= 0]


def compile_lexicon(entries: dict[bytes, tuple[int, ...]]) -> bytes:
    """A minimal acyclic transducer from words to id sequences, as flat bytes.

    Words are added in order; a state that no later word can change is replaced
    by an equal one if there is one.
    """
    register: dict[tuple, int] = {}
    states: list[tuple[bool, tuple]] = []

    def settle(node: list) -> int:
        key = (node[0], tuple(node[1]))
        if key not in register:
            register[key] = len(states)
            states.append(key)
        return register[key]

    path: list[list] = [[False, []]]
    word = b""
    words = sorted(entries)
    for nxt in [*words, None]:
        same = 0
        if nxt is not None:
            most = min(len(word), len(nxt))
            while same < most and word[same] == nxt[same]:
                same += 1
        while len(path) > same + 1:
            node = path.pop()
            path[-1][1].append((word[len(path) - 1], settle(node)))
        if nxt is None:
            break
        for _ in nxt[same:]:
            path.append([False, []])
        path[-1][0] = True
        word = nxt
    root = settle(path[0])

    below = [0] * len(states)
    for s, (final, edges) in enumerate(states):  # children settle first
        below[s] = final + sum(below[t] for _, t in edges)
    starts, labels, targets, outputs = [0], bytearray(), [], []
    for final, edges in states:
        passed = int(final)
        for label, t in edges:
            labels.append(label)
            targets.append(t)
            outputs.append(passed)
            passed += below[t]
        starts.append(len(labels))
    ends = np.cumsum([0, *(len(entries[w]) for w in words)]).tolist()
    ids = [i for w in words for i in entries[w]]
    ints = [*starts, *targets, *outputs, *ends, *ids]
    head = struct.pack("<5i", root, len(states), len(targets), len(words), len(ids))
    return head + struct.pack(f"<{len(ints)}i", *ints) + bytes(final for final, _ in states) + bytes(labels)


class Lexicon:
    """A compiled transducer in a memory-mapped file."""

    def __init__(self, path: str):
        with open(path, "rb") as file:
            self._map = mmap.mmap(file.fileno(), 0, access=mmap.ACCESS_READ)
        self._root, states, edges, words, ids = struct.unpack_from("<5i", self._map)
        count = (states + 1) + 2 * edges + (words + 1) + ids
        ints, at = memoryview(self._map)[20 : 20 + 4 * count].cast("i"), 0
        parts = []
        for size in (states + 1, edges, edges, words + 1, ids):
            parts.append(ints[at : at + size])
            at += size
        self._starts, self._targets, self._outputs, self._ends, self._ids = parts
        self._finals = 20 + 4 * count
        self._labels = self._finals + states
        self.states = states
        self._heads: dict[bytes, tuple[int, int] | None] = {}

    def _walk(self, word: bytes, begin: int, state: int, place: int) -> tuple[int, int] | None:
        """State and place after the bytes from ``begin`` on, or None without a path."""
        find, labels, starts, outputs, targets = self._map.find, self._labels, self._starts, self._outputs, self._targets
        for i in range(begin, len(word)):
            edge = find(word[i : i + 1], labels + starts[state], labels + starts[state + 1]) - labels
            if edge < 0:
                return None
            place += outputs[edge]
            state = targets[edge]
        return state, place

    def get(self, word: bytes) -> list[int] | None:
        """The ids of a word, or None if the lexicon lacks it.  Where the first bytes
        lead is remembered, most words begin alike."""
        head = word[:HEAD]
        if head in self._heads:
            found = self._heads[head]
        else:
            found = self._walk(head, 0, self._root, 0)
            if len(self._heads) < MOST_HEADS:
                self._heads[head] = found
        if found is not None and len(word) > HEAD:
            found = self._walk(word, HEAD, *found)
        if found is None:
            return None
        state, place = found
        return self._ids[self._ends[place] : self._ends[place + 1]].tolist() if self._map[self._finals + state] else None


class Pieces(dict):
    """Piece -> its ids as decimal text.  What the lexicon answers is remembered,
    no more than its pieces; the rest is merged each time it is met."""

    def __init__(self, lexicon: Lexicon | None, merges: Merges):
        super().__init__()
        self._lexicon, self._merges = lexicon, merges

    def __missing__(self, piece: str) -> str:
        raw = piece.encode()
        ids = self._lexicon.get(raw) if self._lexicon and len(raw) <= LONGEST_WORD else None
        if ids is None:  # rare: not worth the memory
            return ",".join(map(str, self._merges.merge(raw)))
        text = self[piece] = ",".join(map(str, ids))
        return text


class Codec:
    """Encoding and decoding of whole texts."""

    def __init__(self, source: str, lexicon: str | None = None):
        self.merges = Merges(source)
        self.lexicon = Lexicon(lexicon) if lexicon else None
        self._pieces = Pieces(self.lexicon, self.merges)
        self._cut = regex.compile("(" + "|".join(map(regex.escape, sorted(self.merges.added, key=len, reverse=True))) + ")") if self.merges.added else None
        self._bytes = {str(i): b for i, b in self.merges.bytes_of.items()}

    def encode_text(self, text: str) -> str:
        """The ids as decimal text joined by commas."""
        get, added = self._pieces.__getitem__, self.merges.added
        if self._cut is None or not any(t in text for t in added):
            return ",".join(map(get, PIECES.findall(text)))
        out = []
        for part in self._cut.split(text):
            if part in added:
                out.append(str(added[part]))
            else:
                out += map(get, PIECES.findall(part))
        return ",".join(out)

    def encode(self, text: str | None) -> list[int]:
        return [int(x) for x in self.encode_text(text or "").split(",") if x]

    def decode_text(self, ids: str) -> str:
        return b"".join(map(self._bytes.__getitem__, ids.split(","))).decode("utf-8", "replace") if ids else ""

    def decode(self, ids: list[int]) -> str:
        return self.decode_text(",".join(map(str, ids)))


def _source(path: str) -> str:
    with open(path, encoding="utf-8") as file:
        return file.read()


def _build(model: tuple[str, str | None]) -> Codec:
    source, name = model
    return Codec(source, SparkFiles.get(name) if name else None)


def frequent_pieces(docs: DataFrame, most: int = LEXICON_PIECES) -> DataFrame:
    """(piece, c): the most frequent pieces of all texts, by count and piece.

    Only distinct words are shuffled, counted where they are first.
    """
    words = docs.select(F.explode(F.split("text", " ")).alias("word")).where(F.length("word").between(1, LONGEST_WORD))
    words = words.groupBy("word").agg(F.count(F.lit(1)).alias("c"))

    def kernel(batch: pa.RecordBatch) -> dict:
        found: dict[str, int] = {}
        for word, c in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
            for piece in PIECES.findall(" " + word):
                found[piece] = found.get(piece, 0) + c
        return {"piece": list(found), "c": list(found.values())}

    pieces = map_rows(words, kernel, "piece string, c long", 10_000).groupBy("piece").agg(F.sum("c").alias("c"))
    return pieces.orderBy(F.desc("c"), "piece").limit(most)


def build_lexicon(docs: DataFrame, source: str, most: int = LEXICON_PIECES) -> bytes:
    """The transducer of the vocabulary's entries and the frequent pieces.  The
    driver gets ``most`` pieces and their ids at most."""
    shared = Shared(docs.sparkSession, (source, None), _build)

    def kernel(batch: pa.RecordBatch) -> dict:
        merge = shared.get().merges.merge
        pieces = [x.encode() for x in batch.column(0).to_pylist()]
        return {"piece": pieces, "ids": [merge(x) for x in pieces]}

    found = map_rows(frequent_pieces(docs, most).select("piece"), kernel, "piece binary, ids array<int>").toArrow()
    merges = Merges(source)
    entries = {w: (i,) for w, i in merges.words.items() if merges.merge(w) == [i]}
    entries |= {w: tuple(ids) for w, ids in zip(found.column("piece").to_pylist(), found.column("ids").to_pylist())}
    return compile_lexicon(entries)


_sent: set[tuple[str, str]] = set()


def shared_codec(docs: DataFrame, path: str, lexicon: bool = True) -> Shared:
    """The codec of a vocabulary file for all workers, with a lexicon of the
    documents' frequent pieces in a file on every executor."""
    spark, source, name = docs.sparkSession, _source(path), None
    if lexicon:
        flat = build_lexicon(docs, source)
        name = f"lexicon-{hashlib.sha256(flat).hexdigest()[:20]}.bin"
        sent = (spark.sparkContext.applicationId, name)
        if sent not in _sent:  # the name says what is in it
            local = os.path.join(tempfile.mkdtemp(prefix="lexicon-"), name)
            with open(local, "wb") as file:
                file.write(flat)
            spark.sparkContext.addFile(local)  # the driver serves it to every executor, also to later ones
            _sent.add(sent)
    return Shared(spark, (source, name), _build)


def encode_documents(docs: DataFrame, path: str) -> DataFrame:
    """doc_id and ``ids`` (array of int) of every whole text."""
    shared = shared_codec(docs, path)

    def kernel(batch: pa.RecordBatch) -> dict:
        codec = shared.get()
        return {"doc_id": batch.column(0), "ids": [codec.encode(t) for t in batch.column(1).to_pylist()]}

    return map_rows(docs.select("doc_id", "text"), kernel, "doc_id long, ids array<int>")


def decode_documents(encoded: DataFrame, path: str) -> DataFrame:
    """doc_id and the text of every row of ids."""
    shared = shared_codec(encoded, path, lexicon=False)

    def kernel(batch: pa.RecordBatch) -> dict:
        codec = shared.get()
        return {"doc_id": batch.column(0), "text": [codec.decode(x or []) for x in batch.column(1).to_pylist()]}

    return map_rows(encoded.select("doc_id", "ids"), kernel, "doc_id long, text string")


def codec_report(docs: DataFrame, path: str) -> DataFrame:
    """Each text encoded and decoded again in one pass: counts and hashes."""
    shared = shared_codec(docs, path)
    hashed = lambda s: hashlib.sha256(s.encode()).hexdigest()

    def kernel(batch: pa.RecordBatch) -> dict:
        codec = shared.get()
        counts, ids, texts = [], [], []
        for value in batch.column(1):
            encoded = codec.encode_text(value.as_py() or "")
            counts.append(encoded.count(",") + 1 if encoded else 0)
            ids.append(hashed(encoded))
            texts.append(hashed(codec.decode_text(encoded)))
        return {"doc_id": batch.column(0), "n_tokens": counts, "ids_sha256": ids, "decoded_sha256": texts}

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return map_rows(rows, kernel, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def tokenise(docs: DataFrame, path: str) -> DataFrame:
    """doc_id, n_tokens, ``ids`` and the hash of the text decoded from them."""
    shared = shared_codec(docs, path)

    def kernel(batch: pa.RecordBatch) -> dict:
        codec = shared.get()
        ids, texts = [], []
        for value in batch.column(1):
            encoded = codec.encode_text(value.as_py() or "")
            ids.append(np.array(encoded.split(",") if encoded else [], dtype=np.int32))
            texts.append(hashlib.sha256(codec.decode_text(encoded).encode()).hexdigest())
        return {"doc_id": batch.column(0), "n_tokens": list(map(len, ids)), "ids": ids, "decoded_sha256": texts}

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return map_rows(rows, kernel, "doc_id long, n_tokens long, ids array<int>, decoded_sha256 string")
