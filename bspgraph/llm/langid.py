"""Language identification: known words first, then shorter character n-grams.

Learning counts words per language over labelled documents; a known word scores
by its log frequency in each language.  A word no language knows falls back to
its character n-grams, from the longest length that has a known one down to
single letters.  A document adds up its words; the score is the normalised
likelihood of the best language.

Null texts and texts without letters are ``und`` with score 0, as is all else
if nothing could be learned.  Equal likelihoods go to the first language by
code point.  Null labels are not learned from; lang, source and doc_id never
enter a prediction.  Repeated rows count each; extra columns are ignored; an
empty table gives an empty result.

At most ``MOST_DOCS`` labelled documents per language are learned from, one row
for each doc_id (a documented bound of the classifier).  Their whole texts are
counted, however long, and every word and n-gram of them is kept.
"""

from __future__ import annotations

import re
from collections import Counter

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Shared, bounded_sample, cut, held_out, map_rows, sampled_texts

UNKNOWN = "und"
MOST_DOCS = 3000
LONGEST = 5
SMOOTHING = 0.2
WORDS = re.compile(r"[^\W\d_]+")

#: Counted words that are cut up at once.
WORDS_AT_ONCE = 4_000

#: Unseen words whose scores a worker remembers.
REMEMBERED = 20_000


def grams(word: str, n: int) -> list[str]:
    """Character n-grams of a word with its ends marked; single letters have no marks."""
    if n == 1:
        return list(word)
    marked = f"<{word}>"
    return [marked[i : i + n] for i in range(len(marked) - n + 1)]


def _count_words(batch: pa.RecordBatch) -> dict:
    """Rows (lang, word, count) of a batch."""
    by: dict[str, Counter] = {}
    for text, lang in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
        by.setdefault(lang, Counter()).update(WORDS.findall(text.lower()))
    return {
        "lang": [lang for lang, words in by.items() for _ in words],
        "gram": [word for words in by.values() for word in words],
        "c": [c for words in by.values() for c in words.values()],
    }


def _count_grams(batch: pa.RecordBatch) -> dict:
    """Rows (lang, n, gram, count) of counted words: every word is cut up once."""
    by: dict[tuple, Counter] = {}
    for lang, word, c in zip(*(batch.column(i).to_pylist() for i in range(3))):
        for n in range(1, LONGEST + 1):
            counter = by.setdefault((lang, n), Counter())
            for g in grams(word, n):
                counter[g] += c
    return {
        "lang": [k[0] for k, found in by.items() for _ in found],
        "n": [k[1] for k, found in by.items() for _ in found],
        "gram": [g for found in by.values() for g in found],
        "c": [c for found in by.values() for c in found.values()],
    }


def _table(rows: pa.Table, langs: list[str]) -> tuple[pa.Array, np.ndarray]:
    """The grams of (lang, gram, c) and their log frequencies in each language."""
    coded = pc.dictionary_encode(rows.column("gram").combine_chunks())
    keys = coded.dictionary
    counts = np.full((len(keys), len(langs)), SMOOTHING)
    at = pc.index_in(rows.column("lang").combine_chunks(), pa.array(langs, pa.string())).to_numpy(zero_copy_only=False)
    counts[coded.indices.to_numpy(zero_copy_only=False), at] += rows.column("c").to_numpy()
    return keys, np.log(counts / counts.sum(axis=0, keepdims=True)).astype(np.float32) if len(keys) else counts


def learn(labelled: DataFrame) -> dict:
    """A model from (doc_id, text, lang): languages and their score tables.

    The driver gets the counts of a bounded number of documents, as Arrow.
    """
    chosen = bounded_sample(labelled.select("doc_id", "lang"), ["lang"], MOST_DOCS)
    sample = sampled_texts(labelled.select("doc_id", "lang", "text"), chosen, ["doc_id", "lang"]).where("text is not null")
    words = map_rows(sample.select("text", "lang"), _count_words, "lang string, gram string, c long")
    words = cut(words.groupBy("lang", "gram").agg(F.sum("c").alias("c")))
    parts = map_rows(words, _count_grams, "lang string, n int, gram string, c long", WORDS_AT_ONCE)
    shorter = parts.groupBy("lang", "n", "gram").agg(F.sum("c").alias("c")).toArrow()
    whole = words.toArrow()
    langs = sorted(set(whole.column("lang").unique().to_pylist()))
    tables = [whole] + [shorter.filter(pc.equal(shorter.column("n"), n)) for n in range(1, LONGEST + 1)]
    return {"langs": langs, "tables": [_table(t, langs) for t in tables]}


class Scorer:
    def __init__(self, model: dict):
        self.langs = model["langs"]
        (words, scores), *shorter = model["tables"]
        self._scores = scores
        self._words = {w: i for i, w in enumerate(words.to_pylist())}
        self._shorter = [({g: i for i, g in enumerate(keys.to_pylist())}, values) for keys, values in shorter]
        self._unseen: dict[str, np.ndarray] = {}

    def _fall_back(self, word: str) -> np.ndarray:
        found = self._unseen.get(word)
        if found is None:
            found = np.zeros(len(self.langs), dtype=np.float32)
            for n in range(LONGEST, 0, -1):
                index, values = self._shorter[n - 1]
                hits = [index[g] for g in grams(word, n) if g in index]
                if hits:
                    found = values[hits].mean(axis=0)
                    break
            if len(self._unseen) >= REMEMBERED:
                self._unseen.clear()
            self._unseen[word] = found
        return found

    def predict(self, text: str | None) -> tuple[str, float]:
        words = Counter(WORDS.findall((text or "").lower()))
        if not self.langs or not any(c.isalpha() for w in words for c in w):
            return UNKNOWN, 0.0
        known = self._words
        rows, times, total = [], [], np.zeros(len(self.langs))
        for word, c in words.items():
            i = known.get(word)
            if i is None:
                total += c * self._fall_back(word)
            else:
                rows.append(i)
                times.append(c)
        if rows:
            total += np.asarray(times, dtype=np.float64) @ self._scores[rows]
        best = int(np.argmax(total))
        share = np.exp(np.clip(total - total[best], -700, 0))
        return self.langs[best], float(1 / share.sum())


def predict(docs: DataFrame, model: dict) -> DataFrame:
    """doc_id, lang_pred and score of every whole text."""
    shared = Shared(docs.sparkSession, model, Scorer)

    def kernel(batch: pa.RecordBatch) -> dict:
        scorer = shared.get()
        found = [scorer.predict(t.as_py()) for t in batch.column(1)]
        return {"doc_id": batch.column(0), "lang_pred": [x for x, _ in found], "score": [x for _, x in found]}

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return map_rows(rows, kernel, "doc_id long, lang_pred string, score double")


def identify(docs: DataFrame) -> DataFrame:
    """Learn from the labelled rows outside the held-out fold, predict all rows."""
    out = held_out(F.col("doc_id"), 4, 2)
    labelled = docs.where(F.col("lang").isNotNull() & F.col("doc_id").isNotNull() & ~out)
    found = predict(docs, learn(labelled))
    return found.select("doc_id", held_out(F.col("doc_id"), 4, 2).alias("held_out"), "lang_pred", "score")


def keep_identified(docs: DataFrame, least: float = 0.4) -> DataFrame:
    """The rows of ``docs`` whose language is found; ``und`` and rows with a
    score below ``least`` go.  All columns stay as they are, whatever their names;
    repeated rows stay or go together."""
    labelled = docs.where(F.col("lang").isNotNull() & F.col("doc_id").isNotNull())
    shared = Shared(docs.sparkSession, learn(labelled), Scorer)

    def kernel(batch: pa.RecordBatch) -> dict:
        scorer = shared.get()
        found = [scorer.predict(t.as_py()) for t in batch.column(batch.schema.get_field_index("text"))]
        kept = batch.filter(pa.array([lang != UNKNOWN and score >= least for lang, score in found], type=pa.bool_()))
        return {name: kept.column(i) for i, name in enumerate(kept.schema.names)}

    return map_rows(docs, kernel, docs.schema)
