"""Rows on which an operator once did less than the whole job."""

import hashlib
import os
import random
import sys
import zlib
from collections import Counter

sys.path.insert(0, os.path.dirname(__file__))
import reference  # noqa: E402

from bspgraph.llm import bpe, exactdup, linededup, pii, telephony  # noqa: E402


def test_account_numbers_in_prose_and_long_secrets(spark):
    number, spaced = "DE89370400440532013000", "GB82 WEST 1234 5698 7654 32"
    tails = [" Please pay", " EUR 300", " BIC COBADEFF", " 2024-01-02", ", thanks", "\nnext", " to you", "", f" {spaced}", " AND THEN SOME MORE CAPITALS THAT GO ON AND ON 1234"]
    texts = [f"é {x}{tail}" for x in (number, spaced) for tail in tails]
    texts += [f"{number}X", "DE8937040044053201300", "QQ92 1234 5678 901 EUR 300", "token = '" + "k" * 5000 + "'"]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r.doc_id: [(s.kind, texts[r.doc_id][s.start : s.end]) for s in r.spans if s.kind in ("iban", "secret")] for r in pii.pii_spans(df).collect()}
    for i in range(20):
        first = number if i < 10 else spaced
        assert got[i] == [("iban", x) for x in ([first, spaced] if tails[i % 10] == f" {spaced}" else [first])], texts[i]
    assert got[20] == got[21] == []
    assert got[22] == [("iban", QQ)]
    assert got[23] == [("secret", texts[23])]


#: A country without a registered length.
QQ = "QQ92 1234 5678 901"


def test_rows_that_share_an_id_lose_only_their_own_lines(spark):
    line = "this long line is repeated in very many of the documents"
    rows = [(i, f"a{i}\n{line}") for i in range(6)]
    rows += [(None, f"x\n{line}"), (None, "y\nthis one is clean"), (None, "z\n\n" + line), (None, None), (None, f"x\n{line}")]
    rows += [(2, f"{line}\n{line}\nnot the same text"), (2, "clean one\nclean two\nclean three")]
    want = Counter((i, n, n - len(kept), reference.sha("\n".join(kept))) for i, n, kept in reference.kept_lines(rows))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    assert Counter(map(tuple, linededup.line_report(docs).collect())) == want
    texts = Counter((i, "\n".join(kept)) for i, _, kept in reference.kept_lines(rows))
    assert Counter((r.doc_id, r.text or "") for r in linededup.dedup_lines(docs).collect()) == texts


def test_trie_of_many_lengths_stays_within_its_budget():
    random.seed(7)
    budget, want, largest = 400_000, Counter(), 0
    trie = exactdup.Patricia(lambda a, b: a + b, budget)
    for _ in range(1500):
        text = random.choice(list(want)[:200])[4:] if want and random.random() < 0.2 else random.randbytes(random.randint(1000, 30_000))
        key = len(text).to_bytes(4, "big") + text
        want[key] += 1
        trie.insert(key, 1)
        largest = max(largest, trie._root.size)
    assert largest <= budget and 0 < trie.spilled < 300
    assert dict(trie) == want
    # one string above the budget gets its memory; what stands beside it is written
    trie = exactdup.Patricia(lambda a, b: a + b, 10_000)
    keys = [b"a" * 50_000, *[b"a" * 50_000 + bytes([i]) for i in range(100)], *[bytes([i % 97]) * (i + 1) for i in range(500)]] * 2
    for k in keys:
        trie.insert(k, 1)
    assert trie.spilled and dict(trie) == Counter(keys)


def test_telephony_digest_is_of_the_stored_columns(spark, monkeypatch):
    docs = spark.createDataFrame([(1, "abc"), (2, None), (None, "é" * 500)], "doc_id long, text string")
    plain = telephony.store_audio
    stored = {r.doc_id: r for r in plain(docs, up=3).collect()}
    monkeypatch.setattr(telephony, "store_audio", lambda d: plain(d, up=3))
    for r in telephony.audio_report(docs).collect():
        media, pcm = bytes(stored[r.doc_id].media), bytes(stored[r.doc_id].pcm)
        assert (r.media_bytes, r.media_sha256) == (len(media), hashlib.sha256(media).hexdigest())
        assert int(r.feature.split(",")[-1]) == zlib.crc32(telephony.read_wave(pcm)[2])


def test_telephony_needs_one_worker_a_task(spark):
    docs = spark.createDataFrame([(1, "a" * 500), (2, None)], "doc_id long, text string")
    plan = telephony.audio_report(docs)._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("MapInArrow") == 1


def test_lexicon_remembers_where_words_begin(tmp_path, monkeypatch):
    """Words that begin alike share the way; beyond the bound nothing is remembered."""
    entries = {w: (i, i + 1) for i, w in enumerate(sorted([b"a", b"abcde", b"abcdefg", b"abcdehi", b"xyzuvw", b"xyz"]))}
    (tmp_path / "lexicon.bin").write_bytes(bpe.compile_lexicon(entries))
    for most, kept in ((0, 0), (1, 1), (100, 6)):
        monkeypatch.setattr(bpe, "MOST_HEADS", most)
        lexicon = bpe.Lexicon(str(tmp_path / "lexicon.bin"))
        for _ in range(2):
            for w in [*entries, b"", b"ab", b"abcdef", b"abcdx", b"xyzuvwx"]:
                assert lexicon.get(w) == (list(entries[w]) if w in entries else None), w
        assert len(lexicon._heads) == (most if kept <= 1 else len({w[: bpe.HEAD] for w in [*entries, b"", b"ab", b"abcdef", b"abcdx", b"xyzuvwx"]}))
