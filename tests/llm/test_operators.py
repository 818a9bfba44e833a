"""The ten operators against plain Python, on small tables and hard rows."""

import os
import random
import sys
import zlib
from collections import Counter

import pytest
from pyspark.sql import functions as F

sys.path.insert(0, os.path.dirname(__file__))
import reference  # noqa: E402

from bspgraph.llm import bpe, common, components, exactdup, langid, linededup, mixing, neardup, pii, quality, queries, telephony, toxicity  # noqa: E402

LINE = "  This LINE is long enough and is repeated in many of them \t"
HARD = [
    (-1, None),
    (-2, ""),
    (-3, "\n\n"),
    (-4, "aBc"),
    (-5, "AbC"),
    (None, "abc"),
    (None, None),
    (-6, "1 " * 30_000),
    (-7, "a." * 20_000 + "@x.y" + ".z" * 10_000),
    (-8, "9" * 50_000),
    (-9, "é😀 a@b.c%x@d.e 1.2.3.4.5.6.7.8 000255.1.1.01 +1 (487) 555-7209; 4111 1111-1111 1111"),
    (-10, "one two"),
    (-11, "One\tTWO"),
    (-12, "one two"),
    (-12, "one two"),
    *[(10_000 + i, f"{LINE}\n{LINE.upper()}\n{i}\nend") for i in range(6)],
]


@pytest.fixture(scope="module")
def docs(spark, sf):
    given = common.documents(spark, sf)
    hard = spark.createDataFrame(HARD, "doc_id long, text string").select("doc_id", "text", F.lit(None).cast("string").alias("lang"), F.lit("x").alias("source"), F.lit(0).cast("long").alias("n_chars"))
    clash = ("key", "n", "lines", "component", "digest", "bucket", "copies", "score")
    df = given.select("doc_id", "text", "lang", "source", "n_chars").unionByName(hard)
    return df.select("*", *[F.lit("clash").alias(c) for c in clash]).repartition(5).cache()


@pytest.fixture(scope="module")
def rows(docs):
    return [(r.doc_id, r.text) for r in docs.select("doc_id", "text").collect()]


def bag(df):
    return Counter(map(tuple, df.collect()))


def test_pii_spans(docs, rows):
    want = Counter()
    for i, text in rows:
        spans = reference.base_spans(text)
        digest = reference.sha(",".join(f"{reference.KINDS[k]}:{a}:{b}" for a, k, b in spans))
        want[(i, *[sum(s[1] == k for s in spans) for k in range(4)], digest)] += 1
    assert bag(pii.pii_report(docs).select("doc_id", "n_email", "n_ip", "n_card", "n_phone", "base_sha256")) == want


def test_pii_checksums_and_context(spark):
    texts = ["GB82 WEST 1234 5698 7654 32", "GB82 WEST 1234 5698 7654 33", "my ssn is 123-45-6789", "part 123-45-6789", 'token = "24be64439e3e49cf46b2"']
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    found = {r.doc_id: [s.kind for s in r.spans] for r in pii.pii_spans(df).collect()}
    assert found == {0: ["iban"], 1: [], 2: ["ssn"], 3: [], 4: ["secret"]}


def test_exact_groups(docs, rows):
    want = reference.exact_groups(rows)
    assert bag(exactdup.exact_groups(docs)) == want
    assert bag(exactdup.exact_groups(docs, hashed=lambda raw: bytes([len(raw) % 3]), budget=20_000)) == want
    assert {r.keep_id for r in exactdup.exact_groups(docs, keep="min").where("doc_id in (-4, -5)").collect()} == {-5}


def test_patricia_spills_and_folds():
    random.seed(3)
    keys = [bytes(random.choice(b"ab") for _ in range(random.randint(0, 12))) * random.randint(1, 9) for _ in range(3000)]
    for budget in (1 << 30, 2_000):
        trie = exactdup.Patricia(lambda a, b: a + b, budget)
        for k in keys:
            trie.insert(k, 1)
        assert dict(trie) == Counter(keys)
        assert (trie.spilled > 0) == (budget == 2_000)


def test_line_dedup(docs, rows):
    want = Counter((i, n, n - len(kept), reference.sha("\n".join(kept))) for i, n, kept in reference.kept_lines(rows))
    assert bag(linededup.line_report(docs)) == want
    # many confirmed keys take the way by a join
    assert bag(linededup.line_report(docs, keys_sent=0)) == want
    texts = Counter((i, "\n".join(kept)) for i, _, kept in reference.kept_lines(rows))
    # filters that say yes to nearly everything change nothing
    for out in (linededup.dedup_lines(docs, bits=64 * 64), linededup.dedup_lines(docs, keys_sent=0)):
        assert out.columns == docs.columns
        assert Counter((r.doc_id, r.text or "") for r in out.collect()) == texts


def test_filters_grow_with_the_texts(spark):
    df = spark.range(3000).select(F.repeat(F.lit("x"), 100_000).alias("text"))
    assert linededup.filter_bits(df) == 1 << (4 * 300_000_000 // 41).bit_length() > linededup.LEAST_BITS


@pytest.mark.parametrize("chunk", [256, 3])
def test_near_duplicates(docs, rows, chunk):
    sets = {i: reference.shingle_set(t) for i, t in rows if i is not None}
    label = reference.components(sets)
    got = neardup.near_duplicates(docs, chunk_docs=chunk)
    want = Counter((i, len(sets[i]), label[i], label[i] == i) for i, _ in rows if i is not None)
    assert bag(got.where("doc_id is not null")) == want
    assert got.where("doc_id is null and component_id is null and kept").count() == 2
    kept = neardup.keep_one(docs)
    assert kept.columns == docs.columns
    assert {r.doc_id for r in kept.select("doc_id").collect()} == {i for i in label if label[i] == i} | {None}


def test_blocks_lose_no_link():
    import numpy as np

    random.seed(5)
    base = list(range(60))
    sets = []
    for _ in range(80):
        gone = set(random.sample(base, random.randint(0, 14)))
        sets.append(np.unique(np.array([x if x not in gone else random.randrange(10**6) for x in base], dtype=np.uint64)))
    want = reference.components({i: frozenset(s.tolist()) for i, s in enumerate(sets)})
    label = {i: i for i in range(len(sets))}
    for a, b in neardup.links_within(list(range(len(sets))), sets):
        x, y = sorted((label[a], label[b]))
        label = {i: x if v == y else v for i, v in label.items()}
    assert label == want


def jobs_of(spark, name, made):
    """The rows of a frame that is made and collected, and the jobs it took."""
    spark.sparkContext.setJobGroup(name, name)
    rows = made().collect()
    spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    return rows, len(spark.sparkContext.statusTracker().getJobIdsForGroup(name))


def test_links_are_united_in_few_jobs(spark):
    pairs = [(i, i + 1) for i in range(100, 160)] + [(7, i) for i in range(200, 260)] + [(3, 3), (259, 9), (161, 300), (300, 160)]
    links = spark.createDataFrame(pairs, "a long, b long")
    want = {i: 100 for i in [*range(100, 162), 300]} | {i: 7 for i in [7, 9, *range(200, 260)]}
    for few, most in ((len(pairs), 6), (0, 10_000)):
        rows, jobs = jobs_of(spark, f"united-{few}", lambda: components.connected(links, few))
        assert len(rows) == len(want) and {r.node: r.component for r in rows} == want
        assert jobs <= most
    assert components.connected(links.limit(0)).collect() == []
    assert components.connected(links.limit(0), few=-1).collect() == []


def test_near_copies_are_found_in_few_jobs(spark, sf):
    """The driver keeps the plan and the tasks of every job."""
    docs = common.documents(spark, sf)
    rows, jobs = jobs_of(spark, "near-copies", lambda: neardup.keep_one(docs))
    assert rows and jobs <= 45


def test_superminhash_estimates_similarity():
    import numpy as np

    from bspgraph.llm.superminhash import mix64, signatures

    words = mix64(np.arange(1, 1201, dtype=np.uint64))
    a, b = np.sort(words[:1000]), np.sort(words[200:])
    x, y = signatures([a, b], slots=1024)
    assert abs((x == y).mean() - 800 / 1200) < 0.06
    small = signatures([a[:3], a[:0]])
    assert len(set(small[0].tolist())) == 128 and (small[1] == np.uint64(2**64 - 1)).all()


def test_codec_equals_the_library(docs, rows):
    import public_tokenizers
    from tokenizers import Tokenizer

    path = public_tokenizers.path(bpe.VOCABULARY)
    plain = Tokenizer.from_file(path)
    odd = ["a<|endoftext|>b", "   x \x1c y　", "it's we'll", "ab" * 5000, "½² १२", "​᠎"]
    want = {}
    for i, text in rows + list(enumerate(odd, 50_000)):
        ids = plain.encode(text or "", add_special_tokens=False).ids
        want[text] = (len(ids), reference.sha(",".join(map(str, ids))), reference.sha(plain.decode(ids, skip_special_tokens=False)))
    more = docs.select("doc_id", "text").unionByName(docs.sparkSession.createDataFrame(list(enumerate(odd, 50_000)), "doc_id long, text string"))
    got = bpe.codec_report(more, path).collect()
    texts = dict(enumerate(odd, 50_000)) | dict(rows)
    for r in got:
        if r.doc_id is not None:
            assert (r.n_tokens, r.ids_sha256, r.decoded_sha256) == want[texts[r.doc_id]]
    some = more.where("doc_id is not null").dropDuplicates(["doc_id"])
    back = bpe.decode_documents(bpe.encode_documents(some, path), path)
    assert {r.doc_id: r.text for r in back.collect()} == {i: texts[i] or "" for i in {r.doc_id for r in some.collect()}}


def test_lexicon_is_minimal_and_exact(tmp_path):
    words = {b"walking": (5,), b"talking": (7, 8), b"walk": (9, 1, 2), b"talk": (11,), b"": ()}
    (tmp_path / "flat").write_bytes(bpe.compile_lexicon(words))
    lexicon = bpe.Lexicon(str(tmp_path / "flat"))
    assert {w: tuple(lexicon.get(w)) for w in words} == words
    assert lexicon.get(b"walki") is None and lexicon.get(b"x") is None
    assert lexicon.states == 8  # the root, and one state after each letter of either verb


def test_lexicon_answers_most_pieces(spark, tmp_path):
    import public_tokenizers

    given = common.documents(spark, "/root/testdata/sf0.01")
    source = bpe._source(public_tokenizers.path(bpe.VOCABULARY))
    (tmp_path / "flat").write_bytes(bpe.build_lexicon(given, source))
    codec = bpe.Codec(source, str(tmp_path / "flat"))
    pieces = Counter(p for r in given.select("text").limit(300).collect() for p in bpe.PIECES.findall(r.text or ""))
    known = {p: codec.lexicon.get(p.encode()) for p in pieces}
    assert sum(c for p, c in pieces.items() if known[p] is not None) >= 0.9 * pieces.total()
    assert all(ids == codec.merges.merge(p.encode()) for p, ids in known.items() if ids is not None)


def test_telephony(docs, rows):
    import hashlib
    import zlib

    import numpy as np

    got = telephony.audio_report(docs).collect()
    assert len(got) == len(rows)
    features = {}
    for r in got:
        assert features.setdefault(r.media_sha256, r.feature) == r.feature
    for i, text in dict((i, t) for i, t in rows if i is not None).items():
        raw = (text or "").encode()
        payload = raw + b" " * (-len(raw) % 192) or b" " * 192
        r = next(x for x in got if x.doc_id == i)
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(raw), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-16:]))
    stored = telephony.store_audio(docs.where("doc_id > 10000"))
    assert all(r.payload.rstrip(b" ").startswith(b"  This") for r in telephony.load_payload(stored).collect())
    # fixed points of the two companding laws, and lossy but close ADPCM
    assert telephony.MULAW[[0, 127, 128, 255]].tolist() == [-32124, 0, 32124, 0]
    assert telephony.ALAW[[0x55, 0xD5, 0x2A, 0xAA]].tolist() == [-8, 8, -32256, 32256]
    wave = (8000 * np.sin(np.arange(377 * 3) / 9)).astype(np.int16).reshape(3, 377)
    again = telephony.decode_adpcm(telephony.encode_adpcm(wave))
    assert np.abs(again[:, 50:].astype(int) - wave[:, 50:]).max() < 400
    alone = telephony.decode_adpcm(telephony.encode_adpcm(wave[1:2]))
    assert (alone[0] == again[1]).all()
    for table in (telephony.MULAW, telephony.ALAW):
        codes = np.frombuffer(telephony.nearest_codes(table, table), dtype=np.uint8)
        assert (table[codes] == table).all()
    rate, pcm = telephony.to_pcm(telephony.write_wave(b"abc", telephony.ALAW_TAG))
    assert rate == 8000 and pcm.tolist() == telephony.ALAW[list(b"abc")].tolist()
    assert telephony.resample(np.array([0, 10, 20], dtype=np.int16)).tolist() == [0, 5, 10, 15, 20, 20]


def plain_feature(payload):
    """The audio feature sample by sample."""
    from bspgraph.llm.telephony import INDEX_MOVES, STEPS

    def mu(b):
        b = ~b & 0xFF
        size = (((b & 15) * 8 + 132) << (b >> 4 & 7)) - 132
        return -size if b & 128 else size

    def a(b):
        b ^= 0x55
        segment, size = b >> 4 & 7, (b & 15) * 16 + 8
        size = size if segment == 0 else (size + 256) << (segment - 1)
        return size if b & 128 else -size

    one, two = [mu(b) for b in payload], [a(b) for b in payload]
    crossings = sum((x < 0) != (y < 0) for x, y in zip(one, one[1:]))
    squares = count = 0
    for at in range(0, len(payload), 192):
        block = payload[at : at + 192]
        value, index = int.from_bytes(block[:2], "little", signed=True), min(88, block[2])
        squares, count = squares + value * value, count + 1
        for code in (c for b in block[4:] for c in (b & 15, b >> 4)):
            step = int(STEPS[index])
            move = (step >> 3) + (step if code & 4 else 0) + (step >> 1 if code & 2 else 0) + (step >> 2 if code & 1 else 0)
            value = max(-32768, min(32767, value - move if code & 8 else value + move))
            index = max(0, min(88, index + int(INDEX_MOVES[code])))
            squares, count = squares + value * value, count + 1
    wide = []
    for k, x in enumerate(one):
        wide += [x, (x + one[min(k + 1, len(one) - 1)]) // 2]
    stored = b"".join(x.to_bytes(2, "little", signed=True) for x in wide)
    return f"{sum(x * x for x in one) // len(one)},{sum(x * x for x in two) // len(two)},{crossings},{squares // count},{zlib.crc32(stored)}"


def test_telephony_feature_by_brute_force(spark):
    rng = random.Random(2)
    texts = ["", None, "abc", "é" * 97, *["".join(chr(rng.randrange(1, 0x2FFF)) for _ in range(n)) for n in (5, 300, 2000)]]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    for r in telephony.audio_report(df).collect():
        raw = (texts[r.doc_id] or "").encode()
        assert r.feature == plain_feature(raw.ljust(max(1, -(-len(raw) // 192)) * 192, b" "))


def test_long_samples_are_resampled_in_parts(monkeypatch):
    import numpy as np

    samples = np.random.default_rng(1).integers(-32768, 32767, 5000).astype(np.int16)
    whole = {(u, d): telephony.resample(samples, u, d) for u, d in ((2, 1), (3, 2), (1, 3))}
    monkeypatch.setattr(telephony, "SAMPLES", 64)
    for (u, d), want in whole.items():
        assert (telephony.resample(samples, u, d) == want).all()
    assert telephony.square_sum(samples) == int((samples.astype(object) ** 2).sum())


def test_mixing(docs, rows):
    got = mixing.mix(docs).collect()
    assert len(got) == len(rows)
    by, total = {}, sum(r.size for r in got)
    for r in got:
        s = by.setdefault(r.source, [0, 0, r.target, r.source_size, 0])
        s[0] += r.size
        s[1] += r.taken
        s[4] = max(s[4], r.size)
        assert r.taken <= 3 * r.size and r.taken == r.size * r.copies
    assert total == sum(len(t.encode().split()) for _, t in rows if t)
    level = water(by)
    for name, (size, taken, target, source_size, longest) in by.items():
        assert size == source_size and target == pytest.approx(level[name], abs=1e-3)
        assert abs(taken - target) <= longest / 2 + 1
    assert bag(mixing.mix(docs).drop("target")) == Counter((r.doc_id, r.source, r.size, r.source_size, r.copies, r.taken) for r in got)
    assert mixing.take(docs).columns == docs.columns


def water(by):
    """Targets by giving the excess away again and again."""
    names = sorted(by, key=lambda s: (s is None, s))
    weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(names)}
    total, target = sum(by[s][0] for s in names), {}
    while True:
        open_ = [s for s in names if s not in target]
        left = total - sum(target.values())
        share = {s: left * weight[s] / sum(weight[x] for x in open_) for s in open_}
        above = [s for s in open_ if share[s] > 3 * by[s][0]]
        if not above:
            return target | share
        target |= {s: 3 * by[s][0] for s in above}


def test_language(spark, sf, docs):
    truth = {r.doc_id: r.lang for r in common.documents(spark, sf).select("doc_id", "lang").collect()}
    got = langid.identify(docs).collect()
    by_id = {r.doc_id: r for r in got}
    assert all(by_id[i].lang_pred == langid.UNKNOWN and by_id[i].score == 0 for i in (-1, -2, -3, -6, -8))
    tested = [r for r in got if r.held_out and r.doc_id in truth]
    assert sum(r.lang_pred == truth[r.doc_id] for r in tested) >= 0.95 * len(tested) > 0
    assert all(0 <= r.score <= 1 for r in got)
    kept = langid.keep_identified(docs)
    assert kept.columns == docs.columns and {-1, -2, -3, -6, -8}.isdisjoint({r.doc_id for r in kept.select("doc_id").collect()})
    unlabelled = docs.withColumn("lang", F.lit(None).cast("string"))
    assert {r.lang_pred for r in langid.identify(unlabelled).collect()} == {langid.UNKNOWN}


def findings(classes):
    """The grammar as plain windows over one clause."""
    near = lambda c, i, before, ahead: c in classes[max(0, i - before) : i] + classes[i + 1 : i + 1 + ahead]
    out = Counter()
    for i, c in enumerate(classes):
        if c not in toxicity.HOT:
            continue
        if near("negation", i, toxicity.REACH, 0):
            out["negated"] += c != "threat"
        elif "report" in classes[:i]:
            out["reported"] += c != "threat"
        elif near("target", i, toxicity.REACH, toxicity.AHEAD):
            out[{"insult": "targeted", "weak": "weak_targeted"}.get(c) or ("threat" if near("intent", i, toxicity.REACH + 1, 0) else "act")] += 1
        elif c != "threat":
            out[c] += 1
    return +out


def test_toxicity_grammar():
    random.seed(11)
    machine, kinds = toxicity.grammar(), [*toxicity.LISTS, "weak", "other", "other"]
    for _ in range(400):
        clause = [random.choice(kinds) for _ in range(random.randint(0, 9))]
        state, got = machine.start, Counter()
        for c in [*clause, toxicity.END]:
            state, out = machine[state, c]
            got.update(x for x in out if x in toxicity.OUTPUTS)
        assert got == findings(clause) and state == machine.start
    fixed = {w: kind for kind, words in toxicity.LISTS.items() for w in words.split()}
    reader = toxicity.Reader((fixed, toxicity.PRIOR))
    read = lambda text: dict(reader.read(text)[0])
    assert read("You are an idiot") == read("idiot you!") == {"targeted": 1}
    assert read("this is not stupid") == {"negated": 1} and read("the paper said that some moron came") == {"reported": 1}
    assert read("Ich werde dich töten.") == read("je vais te tuer") == read("we will kill them") == {"threat": 1}
    assert read("kill the process") == read("will kill the process") == {} and read("they beat us; what a clown") == {"act": 1, "insult": 1}
    lexicon = toxicity.Lexicon({"abc": "insult", "ab*": "weak", "abcd*": "insult"})
    assert [lexicon[w] for w in ("ab", "abc", "abx", "abcd", "abcde", "b")] == ["other", "insult", "weak", "weak", "insult", "other"]


def test_toxicity_scores_by_brute_force(spark, docs, rows):
    sf = "/root/testdata/sf0.01"
    model = toxicity.learn(common.documents(spark, sf), common.labels(spark, sf))
    whole = {x: k for x, k in model["lexemes"].items() if not x.endswith("*")}
    starts = {x[:-1]: k for x, k in model["lexemes"].items() if x.endswith("*")}

    def kind(word):
        fits = [word[:n] for n in range(1, len(word)) if word[:n] in starts]
        return whole.get(word) or (starts[fits[-1]] if fits else "other")

    import math
    import re

    def plain(text):
        tokens = re.findall(r"[^\W\d_]+|[.;:!?\n|]+", (text or "").lower())
        total, clause = 0.0, []
        for t in [*tokens, "."]:
            if t[0] in ".;:!?\n|":
                total += sum(model["weights"][x] * c for x, c in findings(clause).items())
                clause = []
            else:
                clause.append(kind(t))
        base, one, two = model["calibration"]
        return 1 / (1 + math.exp(-(base + one * math.log1p(total) + two * math.log1p(100 * total / (len(tokens) + 20)))))

    want = Counter((i, round(plain(t), 6)) for i, t in rows)
    assert Counter((r.doc_id, round(r.score, 6)) for r in toxicity.score(docs, model).collect()) == want


def test_language_by_brute_force(spark, docs):
    import math
    import re

    given = [(r.doc_id, r.text, r.lang) for r in docs.select("doc_id", "text", "lang").collect()]
    texts, seen = {}, set()
    for i, text, lang in given:
        if i is not None and lang is not None and text is not None and zlib.crc32(str(i).encode()) % 4 != 2:
            texts.setdefault((i, lang), text)
    counts = [Counter() for _ in range(6)]
    for (_, lang), text in texts.items():
        for word in re.findall(r"[^\W\d_]+", text.lower()):
            counts[0][word, lang] += 1
            for n in range(1, 6):
                marked = word if n == 1 else f"<{word}>"
                counts[n].update((marked[k : k + n], lang) for k in range(len(marked) - n + 1))
    langs = sorted({lang for _, lang in texts})
    tables = []
    for table in counts:
        keys = {g for g, _ in table}
        totals = {x: sum(table[g, x] + 0.2 for g in keys) for x in langs}
        tables.append({g: [math.log((table[g, x] + 0.2) / totals[x]) for x in langs] for g in keys})

    def plain(text):
        words = Counter(re.findall(r"[^\W\d_]+", (text or "").lower()))
        if not any(c.isalpha() for w in words for c in w):
            return "und", 0.0
        total = [0.0] * len(langs)
        for word, c in words.items():
            found = tables[0].get(word)
            for n in range(5, 0, -1):
                if found:
                    break
                marked = word if n == 1 else f"<{word}>"
                hits = [tables[n][g] for k in range(len(marked) - n + 1) if (g := marked[k : k + n]) in tables[n]]
                found = [sum(h) / len(hits) for h in zip(*hits)] if hits else None
            total = [a + c * b for a, b in zip(total, found or [0.0] * len(langs))]
        best = max(range(len(langs)), key=lambda k: (total[k], -k))
        return langs[best], 1 / sum(math.exp(max(-700, x - total[best])) for x in total)

    for r in langid.identify(docs).collect():
        seen.add(r.doc_id)
        for i, text, _ in given:
            if i is not None and i == r.doc_id:
                lang, score = plain(text)
                assert r.lang_pred == lang and abs(r.score - score) < 1e-2
    assert len(seen) > 200


def test_quality_by_brute_force(spark, docs):
    import numpy as np

    sf = "/root/testdata/sf0.01"
    given, rated = common.documents(spark, sf), common.labels(spark, sf).select("doc_id", F.col("quality").alias("grade"))
    texts = {r.doc_id: r.text for r in given.collect()}
    train = sorted((r.doc_id, r.grade) for r in rated.collect() if zlib.crc32(str(r.doc_id).encode()) % 5)
    model = quality.fit([quality.features(texts[i]) for i, _ in train], np.array([g for _, g in train]), 1)
    for r in quality.quality_report(given, rated).collect():
        where, values = quality.features(texts[r.doc_id])
        tail = 1 / (1 + np.exp(model["thresholds"][0] - values @ model["weights"][where]))
        assert abs(r.tail_prob - tail) < 0.02 and abs(r.expected_grade - tail) < 0.02


def test_samples_are_bounded_by_rows(spark):
    rated = spark.range(100).select(F.col("id").alias("doc_id"), (F.col("id") % 2).alias("y"))
    rated = rated.unionByName(spark.range(5000).select(F.lit(7).cast("long").alias("doc_id"), F.lit(1).cast("long").alias("y")))
    chosen = common.bounded_sample(rated, ["y"], 10)
    got = Counter(r.y for r in chosen.collect())
    assert max(got.values()) <= 10 and chosen.count() == chosen.select("doc_id").distinct().count()
    texts = rated.select("doc_id", F.concat(F.lit("t"), F.rand(1).cast("string")).alias("text"))
    assert common.sampled_texts(texts, chosen, ["doc_id"]).count() == chosen.count()


def test_toxicity_and_quality(spark, docs):
    sf = "/root/testdata/sf0.01"
    given, rated = common.documents(spark, sf), common.labels(spark, sf)
    truth = {r.doc_id: r for r in rated.collect()}
    got = [r for r in queries.op4_toxicity(spark, sf).collect() if r.doc_id in truth]
    assert sum(r.predicted == truth[r.doc_id].toxic for r in got) >= 0.95 * len(got)
    assert all(0 <= r.score <= 1 for r in got)
    got = [r for r in queries.op1_quality(spark, sf).collect() if r.doc_id in truth and r.held_out]
    assert sum(r.kept == (truth[r.doc_id].quality == 1) for r in got) >= 0.95 * len(got)
    none = rated.limit(0)
    assert {r.predicted for r in toxicity.toxicity_report(given.limit(5), none).collect()} == {0}
    assert all(r.kept for r in quality.quality_report(given.limit(5), none.select("doc_id", F.col("quality").alias("grade"))).collect())
    # the hard rows have scores as well, and none is lost
    assert toxicity.toxicity_report(docs, rated).count() == docs.count()
    assert quality.quality_report(docs, rated.select("doc_id", F.col("quality").alias("grade"))).count() == docs.count()


def test_ordinal_fit_orders_many_grades():
    import numpy as np

    random.seed(1)
    pools = [["bad", "poor"], ["so", "fair"], ["good", "fine"], ["best", "great"]]
    texts = [(g, " ".join(random.choice(pools[g]) for _ in range(12))) for g in range(4) for _ in range(40)]
    model = quality.fit([quality.features(t) for _, t in texts], np.array([g for g, _ in texts]), 3)
    assert (np.diff(model["thresholds"]) > 0).all()
    means = []
    for pool in pools:
        where, values = quality.features(" ".join(pool * 6))
        z = values @ model["weights"][where]
        means.append(float((1 / (1 + np.exp(model["thresholds"] - z))).sum()))
    assert means == sorted(means)


def test_empty_tables(docs, spark, sf):
    import public_tokenizers

    none, rated = docs.limit(0), common.labels(spark, sf).limit(0)
    path = public_tokenizers.path(bpe.VOCABULARY)
    found = [
        pii.pii_report(none), exactdup.exact_groups(none), linededup.line_report(none), neardup.near_duplicates(none), bpe.codec_report(none, path),
        telephony.audio_report(none), mixing.mix(none), langid.identify(none), toxicity.toxicity_report(none, rated),
        quality.quality_report(none, rated.select("doc_id", F.col("quality").alias("grade"))),
    ]
    assert [df.count() for df in found] == [0] * 10
