"""Quality grades by ordinal cumulative-link regression.

Every whole text gives hashed word counts and a few shape marks.  One weight
vector is shared by all grades: ``P(grade <= k) = logistic(theta_k - w.x)`` with
ordered thresholds, so a document has an expected grade and the tail
probability of reaching any grade, by which it is selected.

Grades are integers from 0 in the column ``grade``; any number of them works.
Null and empty texts have the shape mark of emptiness only.  Labels are joined
on doc_id; of several the least grade counts.  Repeated rows are scored one by
one, ties score alike, extra columns are ignored, an empty table gives an empty
result, and without labels every document has the tail probability 1/2 and is
kept.  Very long texts are hashed whole; their features are no more than
``1 << BITS``.  At most ``MOST_DOCS`` labelled documents per grade are learned
from, one row for each doc_id.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Shared, bounded_sample, held_out, map_rows, sampled_texts

BITS = 15
SHAPES = 64
MOST_DOCS = 2000
ROUNDS = 150
RIDGE = 1e-4
SYMBOLS = b"#$%&*|<>{}[]=_~^\\!"


def features(text: str | None) -> tuple[np.ndarray, np.ndarray]:
    """Sorted feature numbers and values of a text; the length of the values is 1
    for the words and about 1 for the shape marks."""
    raw = (text or "").encode()
    words = raw.split()
    marks = [0 if not words else 1]
    where, values = np.empty(0, dtype=np.int64), np.empty(0)
    if words:
        n = len(words)
        hashed = np.fromiter(map(xxhash.xxh3_64_intdigest, words), dtype=np.uint64, count=n)
        where, counts = np.unique((hashed >> np.uint64(64 - BITS)).astype(np.int64), return_counts=True)
        values = np.log1p(counts)
        values /= np.sqrt(values @ values)
        step = lambda share: int(min(7, share * 8))
        symbols = len(raw) - len(raw.translate(None, SYMBOLS))
        capitals = len(raw) - len(raw.translate(None, b"ABCDEFGHIJKLMNOPQRSTUVWXYZ"))
        marks.append(2 + step(4 * symbols / len(raw)))
        marks.append(10 + step(2 * capitals / len(raw)))
        marks.append(18 + step(float((hashed[1:] == hashed[:-1]).mean()) if n > 1 else 0))
        marks.append(26 + step(len(np.unique(hashed)) / n))
        marks.append(34 + min(7, int(np.log2(n))))
        marks.append(42 + min(7, len(raw) // n // 2))
    return np.concatenate([where, (1 << BITS) + np.array(marks)]), np.concatenate([values, np.full(len(marks), 0.5)])


def fit(rows: list, grades: np.ndarray, top: int) -> dict:
    """Shared weights and ordered thresholds by full-batch adaptive steps.

    Grades weigh alike, however many rows they have.
    """
    size = (1 << BITS) + SHAPES
    owner = np.repeat(np.arange(len(rows)), [len(r[0]) for r in rows])
    where, values = np.concatenate([r[0] for r in rows]), np.concatenate([r[1] for r in rows])
    share = np.bincount(grades, minlength=top + 1).astype(float)
    weight = 1 / share[grades]
    weight /= weight.sum()
    # parameters: weights, first threshold, logarithms of the gaps
    p = np.zeros(size + top)
    p[size] = -0.5
    m, v = np.zeros_like(p), np.zeros_like(p)
    logistic = lambda z: 1 / (1 + np.exp(-np.clip(z, -40, 40)))
    for t in range(1, ROUNDS + 1):
        theta = thresholds(p[size:])
        z = np.bincount(owner, values * p[where], minlength=len(rows))
        edges = np.concatenate([[-np.inf], theta, [np.inf]])
        high = np.where(grades == top, 1.0, logistic(edges[grades + 1] - z))
        low = np.where(grades == 0, 0.0, logistic(edges[grades] - z))
        chance = np.maximum(high - low, 1e-12)
        up, down = high * (1 - high) / chance * weight, low * (1 - low) / chance * weight
        slope = np.zeros_like(p)
        slope[:size] = np.bincount(where, values * (up - down)[owner], minlength=size) + RIDGE * p[:size]
        by_edge = np.zeros(top)
        np.add.at(by_edge, grades[grades < top], -up[grades < top])
        np.add.at(by_edge, grades[grades > 0] - 1, down[grades > 0])
        tails = np.cumsum(by_edge[::-1])[::-1]
        slope[size] = tails[0]
        slope[size + 1 :] = tails[1:] * np.exp(p[size + 1 :])
        m, v = 0.9 * m + 0.1 * slope, 0.99 * v + 0.01 * slope**2
        p -= 0.1 * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.99**t)) + 1e-8)
    return {"weights": p[:size], "thresholds": thresholds(p[size:])}


def thresholds(raw: np.ndarray) -> np.ndarray:
    return raw[0] + np.concatenate([[0.0], np.cumsum(np.exp(raw[1:]))])


def learn(docs: DataFrame, grades: DataFrame) -> dict | None:
    """A model from texts and (doc_id, grade), or None without two grades."""
    rated = grades.where(F.col("doc_id").isNotNull() & F.col("grade").isNotNull() & ~held_out(F.col("doc_id"), 5, 0))
    rated = rated.groupBy("doc_id").agg(F.min("grade").cast("int").alias("grade"))
    sample = sampled_texts(docs, bounded_sample(rated, ["grade"], MOST_DOCS), ["doc_id"]).select("text", "grade")

    def kernel(batch: pa.RecordBatch) -> dict:
        found = [features(t.as_py()) for t in batch.column(0)]
        return {"i": [w.astype(np.int32) for w, _ in found], "x": [v.astype(np.float32) for _, v in found], "grade": batch.column(1)}

    table = map_rows(sample, kernel, "i array<int>, x array<float>, grade int").toArrow()
    y = table.column("grade").to_numpy().astype(np.int64)
    if len(np.unique(y)) < 2:
        return None
    rows = [(i.values.to_numpy().astype(np.int64), x.values.to_numpy().astype(float)) for i, x in zip(table.column("i"), table.column("x"))]
    return fit(rows, y, int(y.max()))


def score(docs: DataFrame, model: dict | None, tail: int = 1) -> DataFrame:
    """doc_id, expected_grade and tail_prob = P(grade >= tail) of every text."""
    if model is None:
        return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.lit(0.5).alias("expected_grade"), F.lit(0.5).alias("tail_prob"))
    shared = Shared(docs.sparkSession, model)

    def kernel(batch: pa.RecordBatch) -> dict:
        model = shared.get()
        w, theta = model["weights"], model["thresholds"]
        z = np.zeros(batch.num_rows)
        for n, text in enumerate(batch.column(1)):
            where, values = features(text.as_py())
            z[n] = values @ w[where]
        tails = 1 / (1 + np.exp(np.clip(theta[None, :] - z[:, None], -40, 40)))
        return {"doc_id": batch.column(0), "expected_grade": tails.sum(axis=1), "tail_prob": tails[:, min(tail, len(theta)) - 1]}

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return map_rows(rows, kernel, "doc_id long, expected_grade double, tail_prob double")


def quality_report(docs: DataFrame, grades: DataFrame, tail: int = 1, least: float = 0.5) -> DataFrame:
    """Scores of all documents and whether the tail probability selects them."""
    found = score(docs, learn(docs, grades), tail)
    return found.select(
        "doc_id", held_out(F.col("doc_id"), 5, 0).alias("held_out"), "expected_grade", "tail_prob", (F.col("tail_prob") >= least).alias("kept")
    )
