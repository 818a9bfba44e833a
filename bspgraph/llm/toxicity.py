"""Toxicity from a weighted finite-state grammar over clauses.

Two layers of transducers read a text.  The lexical one reads the letters of a
word and ends in a class: insult, weak insult, threat verb, intent, target,
negation, reported speech, other.  The clause grammar is the composition of one
small transducer each for negation, reported speech, intent and target; it
rewrites the classes of a clause and holds an insult or threat back for
``AHEAD`` words, so a target after it counts like one before it.  A threat verb
without a target is no finding ("kill the process").  Arcs that emit a finding
carry its weight; a clause weighs what its path adds up to, and the text is
scored by the sum over its clauses and by that sum per words, both dampened and
calibrated.  So matched clauses
are scored and not words.

Insults are fixed lists plus words and word beginnings induced from labelled
documents in which they are dense: again and again the candidate that explains
most toxic documents not yet explained, less its harm among the others, is taken,
so chance companions of real insults are not.  Labels do not tell threats from insults, so threat verbs
are the fixed lists alone.  Arc weights and calibration are logistic fits.

Null and empty texts have no clauses and the score of a text without findings.
Very long texts are read whole.  Labels are joined on doc_id; several labels of
one doc_id count as toxic if any is, and of rows that share a doc_id one text is
learned from.  Repeated rows are scored one by one; ties score alike; extra
columns are ignored; an empty table gives an empty result; without labels, prior
weights hold.  At most ``MOST_DOCS`` labelled documents per class are learned
from; nothing else is bounded.
"""

from __future__ import annotations

import heapq
import re
from collections import Counter
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Shared, bounded_sample, cut, held_out, map_rows, sampled_texts

MOST_DOCS = 5000

#: A lexeme explains at least so many labelled toxic documents, is so many times
#: likelier in toxic documents than in others, and costs so much per other one.
MIN_SUPPORT = 3
MIN_RATIO = 8
HARM = 3
#: Toxic documents per other one from which a lexeme is a full insult.
STRONG = 20
PREFIXES = range(3, 10)
#: A lexeme is dense in a document with so many of it, and one per so many words.
LEAST_TIMES = 2
PER_WORDS = 200

#: Fixed word lists of the grammar; * stands for any ending.
LISTS = {
    "insult": "idiot moron scum loser clown trash stupid worthless pathetic disgusting idioten dummkopf abschaum versager connard salaud ordure imbécile idiota imbécil escoria estúpido",
    "threat": "kill hurt destroy smash burn stab shoot beat töten umbringen verletzen erschießen erstechen vernichten tuer frapper poignarder détruire matar mataré golpear apuñalar destruir",
    "intent": "will gonna going shall must werde werden wirst wird vais va allons voy vamos vas",
    "target": "you your he she they them him her these those u du dich dir ihr euch sie ihn tu te toi vous il elle ils usted ustedes eres tú ti os él ella ellos",
    "negation": "not no never isn aren wasn won nicht kein keine nie pas jamais nunca jamás",
    "report": "said says say called calls wrote claimed quoted alleged sagte sagt dit disait dijo dice",
}

TOKENS = re.compile(r"[^\W\d_]+|[.;:!?\n|]+")
WORDS = re.compile(r"[^\W\d_]+")
REACH, AHEAD = 3, 2
END = "end"

#: Findings and their weights before any are learned; then the calibration.
PRIOR = {"insult": 2.0, "targeted": 2.5, "weak": 1.0, "weak_targeted": 1.5, "negated": 0.2, "reported": 0.2, "threat": 3.0, "act": 1.0}
OUTPUTS = tuple(PRIOR)
CALIBRATION = (-2.5, 1.5, 1.2)
HOT = frozenset(("insult", "weak", "threat"))

#: Words a worker remembers before it starts anew.
REMEMBERED = 300_000


class Transducer(dict):
    """(state, symbol) -> (next state, symbols out), filled as states are met."""

    def __init__(self, start, step: Callable):
        super().__init__()
        self.start, self._step = start, step

    def __missing__(self, key):
        found = self[key] = self._step(*key)
        return found


def after(trigger: str, changes: dict[str, str], reach: int | None) -> Transducer:
    """Rewrites symbols seen within ``reach`` words after a trigger, or up to
    the end of the clause.  States count the reach down."""

    def step(state, c):
        if c == END:
            return 0, (END,)
        out = changes.get(c, c) if state else c
        return (reach or 1) if c == trigger else state if reach is None else max(0, state - 1), (out,)

    return Transducer(0, step)


def beside(trigger: str, changes: dict[str, str], alone: dict[str, str | None], reach: int, ahead: int) -> Transducer:
    """Rewrites symbols with a trigger up to ``reach`` words before or ``ahead``
    words after them.  A symbol without one before is held back until a trigger
    comes or ``ahead`` words have passed, then leaves as ``alone`` says."""

    def leave(c):
        return () if c is None or alone.get(c) is None else (alone[c],)

    def step(state, c):
        left, held = state
        if c == END:
            return (0, (None,) * ahead), (*(x for h in held for x in leave(h)), END)
        if c == trigger:
            out = tuple(changes[h] for h in held if h is not None)
            return (reach, (None,) * ahead), out
        out, held = leave(held[0]), held[1:]
        if c not in changes:
            return (max(0, left - 1), (*held, None)), (*out, *(() if c == "other" else (c,)))
        if left:
            return (left - 1, (*held, None)), (*out, changes[c])
        return (0, (*held, c)), out

    return Transducer((0, (None,) * ahead), step)


def compose(*machines: Transducer) -> Transducer:
    """The transducer that applies the machines one after another."""

    def step(state, c):
        symbols, states = (c,), list(state)
        for i, machine in enumerate(machines):
            out = []
            for symbol in symbols:
                states[i], more = machine[states[i], symbol]
                out += more
            symbols = tuple(out)
        return tuple(states), symbols

    return Transducer(tuple(m.start for m in machines), step)


def grammar() -> Transducer:
    """Negation, then reported speech, then intent, then target."""
    quiet = {"insult": "negated", "weak": "negated", "threat": "other"}
    told = {"insult": "reported", "weak": "reported", "threat": "other"}
    near = {"insult": "targeted", "weak": "weak_targeted", "threat": "act", "meant": "threat"}
    return compose(
        after("negation", quiet, REACH),
        after("report", told, None),
        after("intent", {"threat": "meant"}, REACH + 1),
        beside("target", near, {"insult": "insult", "weak": "weak"}, REACH, AHEAD),
    )


class Lexicon(dict):
    """The lexical transducer: a word's class, read letter by letter.

    States are a trie of the lexemes; a state may end a whole word or, for a
    beginning (ends in *), any longer word.  Words read before are remembered.
    """

    def __init__(self, lexemes: dict[str, str]):
        super().__init__()
        self._arcs: list[dict[str, int]] = [{}]
        self._whole: dict[int, str] = {}
        self._longer: dict[int, str] = {}
        for lexeme, kind in lexemes.items():
            state = 0
            for letter in lexeme.rstrip("*"):
                if letter not in self._arcs[state]:
                    self._arcs[state][letter] = len(self._arcs)
                    self._arcs.append({})
                state = self._arcs[state][letter]
            (self._longer if lexeme.endswith("*") else self._whole)[state] = kind

    def read(self, word: str) -> str:
        state, passed = 0, "other"
        for letter in word:
            passed = self._longer.get(state, passed)
            state = self._arcs[state].get(letter)
            if state is None:
                return passed
        return self._whole.get(state, passed)

    def __missing__(self, token: str) -> str:
        kind = END if token[0] in ".;:!?\n|" else self.read(token)
        if len(self) >= REMEMBERED:
            self.clear()
        if len(token) <= 64:
            self[token] = kind
        return kind


class Reader:
    """Findings and clause weights of texts, from (lexemes, weights)."""

    def __init__(self, model: tuple[dict[str, str], dict[str, float]]):
        self._lexicon, self._weights = Lexicon(model[0]), model[1]
        self._grammar = grammar()

    def read(self, text: str | None) -> tuple[Counter, float, float, int]:
        """How often each finding occurs, the weight of all clauses and of the
        heaviest one, and the number of words and breaks."""
        classes = list(map(self._lexicon.__getitem__, TOKENS.findall((text or "").lower())))
        found: Counter = Counter()
        if HOT.isdisjoint(classes):
            return found, 0.0, 0.0, len(classes)
        state, table, weights = self._grammar.start, self._grammar, self._weights
        total = worst = path = 0.0
        for c in (*classes, END):
            state, out = table[state, c]
            for x in out:
                if x in weights:
                    found[x] += 1
                    path += weights[x]
            if c == END:
                total, worst, path = total + path, max(worst, path), 0.0
        return found, total, worst, len(classes)


def evidence(total: np.ndarray, words: np.ndarray) -> np.ndarray:
    """What is calibrated: the weight of all clauses, and that per words."""
    return np.stack([np.log1p(total), np.log1p(100 * total / (words + 20))], axis=1)


def candidates(text: str) -> set[str]:
    """Words and word beginnings that are dense in a text, as lexemes."""
    words = Counter(WORDS.findall(text.lower()))
    times, least = Counter(words), max(LEAST_TIMES, words.total() / PER_WORDS)
    for w, c in words.items():
        for n in PREFIXES:
            if len(w) <= n:
                break
            times[w[:n] + "*"] += c
    return {x for x, c in times.items() if c >= least}


def _tally(batch: pa.RecordBatch) -> dict:
    both = (Counter(), Counter())
    for text, toxic in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
        both[toxic].update(candidates(text))
    return {
        "lexeme": [x for y in (0, 1) for x in both[y]],
        "good": [*both[0].values(), *[0] * len(both[1])],
        "bad": [*[0] * len(both[0]), *both[1].values()],
    }


def induce(sample: DataFrame, sizes: dict[int, int], given: set[str]) -> dict[str, str]:
    """Lexemes and their classes from (text, toxic): greedy cover of the toxic
    documents that the ``given`` insults leave."""
    if not sizes.get(1):
        return {}
    tally = map_rows(sample, _tally, "lexeme string, good long, bad long").groupBy("lexeme").agg(F.sum("bad").alias("bad"), F.sum("good").alias("good"))
    ratio = (F.col("bad") / sizes[1]) / ((F.col("good") + 0.5) / max(1, sizes.get(0, 0)))
    # the sample is bounded, and with it what comes to the driver
    rows = tally.where((F.col("bad") >= MIN_SUPPORT) & (ratio >= MIN_RATIO)).orderBy("lexeme").collect()
    names, harm = [r.lexeme for r in rows], [HARM * r.good for r in rows]
    shared = Shared(sample.sparkSession, {x: i for i, x in enumerate(names)})

    def present(batch: pa.RecordBatch) -> dict:
        known = shared.get()
        dense = [candidates(t) for t in batch.column(0).to_pylist()]
        return {"found": [[] if given & d else sorted(known[x] for x in d if x in known) for d in dense]}

    documents = [set(r.found) for r in map_rows(sample.where("toxic = 1"), present, "found array<int>").collect()]
    gain = Counter(i for d in documents for i in d)
    holders: dict[int, list] = {}
    for n, d in enumerate(documents):
        for i in d:
            holders.setdefault(i, []).append(n)
    # gains only fall, so a candidate whose place is still right is the best;
    # of equals the shorter beginning is taken: it also covers unseen endings
    place = lambda i: (harm[i] - gain[i], not names[i].endswith("*"), len(names[i]), names[i], i)
    queue = [place(i) for i in gain]
    heapq.heapify(queue)
    explained, chosen = set(), {}
    while queue:
        now = heapq.heappop(queue)
        i = now[-1]
        if place(i) != now:
            heapq.heappush(queue, place(i))
            continue
        if gain[i] - harm[i] < MIN_SUPPORT:
            break
        chosen[names[i]] = "insult" if rows[i].bad >= STRONG * rows[i].good else "weak"
        for n in holders[i]:
            if n not in explained:
                explained.add(n)
                for j in documents[n]:
                    gain[j] -= 1
    return chosen


def fit(x: np.ndarray, y: np.ndarray, weight: np.ndarray, prior: np.ndarray, pull: float = 0.002) -> np.ndarray:
    """Weights of a logistic model by Newton steps, drawn towards ``prior``."""
    x = np.hstack([np.ones((len(x), 1)), x])
    w = prior.copy()
    for _ in range(40):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        slope = x.T @ (weight * (p - y)) + pull * len(y) * (w - prior)
        bend = (x * (weight * p * (1 - p))[:, None]).T @ x + pull * len(y) * np.eye(len(w))
        move = np.linalg.solve(bend, slope)
        w = w - np.clip(move, -2, 2)
        if np.abs(move).max() < 1e-8:
            break
    return w


def learn(docs: DataFrame, labels: DataFrame) -> dict:
    """Lexemes, arc weights and calibration from labelled documents outside the
    held-out fold."""
    rated = labels.where(F.col("doc_id").isNotNull() & F.col("toxic").isin(0, 1) & ~held_out(F.col("doc_id"), 5, 0))
    rated = rated.groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    chosen = bounded_sample(rated, ["toxic"], MOST_DOCS)
    sample = cut(sampled_texts(docs, chosen, ["doc_id"]).where("text is not null").select("text", "toxic"))
    sizes = {r.toxic: r.n for r in sample.groupBy("toxic").agg(F.count(F.lit(1)).alias("n")).collect()}
    lexemes = induce(sample, sizes, set(LISTS["insult"].split())) | {w: kind for kind, words in LISTS.items() for w in words.split()}
    model = {"lexemes": lexemes, "weights": dict(PRIOR), "calibration": CALIBRATION}
    if not sizes.get(0) or not sizes.get(1):
        return model
    shared = Shared(sample.sparkSession, (lexemes, PRIOR), Reader)

    def kernel(batch: pa.RecordBatch) -> dict:
        found = [shared.get().read(t) for t in batch.column(0).to_pylist()]
        return {"x": [[float(f[0][o]) for o in OUTPUTS] for f in found], "words": [f[3] for f in found], "y": batch.column(1)}

    rows = map_rows(sample, kernel, "x array<double>, words int, y int").collect()
    x, y = np.array([r.x for r in rows]), np.array([r.y for r in rows], dtype=float)
    whole = {r.toxic: r.n for r in rated.groupBy("toxic").agg(F.count(F.lit(1)).alias("n")).collect()}
    ratio = np.where(y == 1, whole.get(1, 1) / sizes[1], whole.get(0, 1) / sizes[0])
    ratio /= ratio.mean()
    arcs = np.maximum(0.05, fit(np.minimum(x, 3), y, ratio, np.array([-4.0, *PRIOR.values()]))[1:])
    model["weights"] = dict(zip(OUTPUTS, arcs.tolist()))
    model["calibration"] = tuple(fit(evidence(x @ arcs, np.array([r.words for r in rows])), y, ratio, np.array(CALIBRATION)).tolist())
    return model


def score(docs: DataFrame, model: dict) -> DataFrame:
    """doc_id, score and the weight of the heaviest clause of every whole text."""
    shared = Shared(docs.sparkSession, (model["lexemes"], model["weights"]), Reader)
    base, *slopes = model["calibration"]

    def kernel(batch: pa.RecordBatch) -> dict:
        reader = shared.get()
        found = [reader.read(t) for t in batch.column(1).to_pylist()]
        z = base + evidence(np.array([f[1] for f in found]), np.array([f[3] for f in found])) @ slopes
        return {"doc_id": batch.column(0), "score": 1 / (1 + np.exp(-np.clip(z, -30, 30))), "worst_clause": [f[2] for f in found]}

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return map_rows(rows, kernel, "doc_id long, score double, worst_clause double")


def toxicity_report(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """Scores of all documents, and whether they are predicted to be toxic."""
    found = score(docs, learn(docs, labels))
    return found.select(
        "doc_id",
        held_out(F.col("doc_id"), 5, 0).alias("held_out"),
        "score",
        (F.col("score") >= 0.5).cast("int").alias("predicted"),
        "worst_clause",
    )
