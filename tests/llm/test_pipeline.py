"""The pipeline stage by stage against plain Python."""

import os
import sys
from collections import Counter

sys.path.insert(0, os.path.dirname(__file__))
import reference  # noqa: E402

import corpus_pipeline  # noqa: E402
from bspgraph.llm import common  # noqa: E402


def test_stages(spark, sf, tmp_path):
    docs = common.documents(spark, sf)
    results = [docs]
    for n, (_, stage) in enumerate(corpus_pipeline.STAGES):
        stage(spark, results[-1], sf).write.parquet(str(tmp_path / str(n)))
        results.append(spark.read.parquet(str(tmp_path / str(n))))
    for df in results[1:-1]:
        assert df.columns == docs.columns
    pairs = [[(r.doc_id, r.text) for r in df.select("doc_id", "text").collect()] for df in results[:-1]]
    named = dict(pairs[0])
    assert set(pairs[1]) <= set(pairs[0]) and len(pairs[1]) >= 0.97 * len(pairs[0])
    assert Counter(pairs[2]) == Counter((i, "\n".join(kept)) for i, _, kept in reference.kept_lines(pairs[1]))
    label = reference.components({i: reference.shingle_set(t) for i, t in pairs[2]})
    assert Counter(pairs[3]) == Counter((i, t) for i, t in pairs[2] if label[i] == i)
    times = Counter(i for i, _ in pairs[4])
    assert set(pairs[4]) <= set(pairs[3]) and max(times.values()) <= 3
    tokens = results[-1].collect()
    assert len(tokens) == len(pairs[4])
    texts = dict(pairs[4])
    for r in tokens:
        assert r.decoded_sha256 == reference.sha(texts[r.doc_id] or "") and len(r.ids) == r.n_tokens
    assert named


def test_stages_on_hard_rows(spark, sf, tmp_path):
    """Nulls in any column, empty and very long texts, ties, repeated rows and
    clashing names, through all stages, and an empty table."""
    from pyspark.sql import functions as F

    given = common.documents(spark, sf).limit(60)
    line = "this long line is held by very many of the documents here"
    hard = [(None, None, None, None, None), (None, "un texte sans nombre", None, "a", 1), (-1, "", "fr", None, None), (-2, None, "de", "b", 0), (-3, "1 2 3", "en", "b", 3)]
    hard += [(-4, "the words of the text are repeated and the words are many", "en", "b", 9)] * 3 + [(-5, ("the words and " * 40_000).strip(), None, None, 2)]
    hard += [(-10 - i, f"{line}\nand the end of number {i}", "en", "b", 5) for i in range(6)]
    schema = "doc_id long, text string, lang string, source string, n_chars long"
    clash = ["row_at", "row_digest", "row_drop", "row_copies", "row_turn", "key", "node", "component", "found", "bucket", "place_in_key", "n"]
    docs = given.select("doc_id", "text", "lang", "source", "n_chars").unionByName(spark.createDataFrame(hard, schema))
    docs = docs.select("*", *[F.lit(i).alias(c) for i, c in enumerate(clash)])
    for frame, least in ((docs, 40), (docs.limit(0), 0)):
        out = frame
        for n, (_, stage) in enumerate(corpus_pipeline.STAGES):
            path = str(tmp_path / f"{least}-{n}")
            stage(spark, out, sf).write.parquet(path)
            before, out = out, spark.read.parquet(path)
            if n < 4:
                assert out.columns == frame.columns
                assert all(r[c] == i for r in out.select(*clash).distinct().collect() for i, c in enumerate(clash))
            if n == 0 and least:
                ids = [r.doc_id for r in out.collect()]
                assert not {-1, -2, -3} & set(ids) and ids.count(-4) in (0, 3) and -5 in ids
            if n == 1 and least:
                assert out.count() == before.count()
                lines = [r.doc_id for r in out.collect() if line in r.text]
                assert lines == [-10]
            if n == 2 and least:
                assert Counter(r.doc_id for r in out.collect())[-4] in (0, 3)
        assert out.count() >= least
        assert set(out.columns) >= {"doc_id", "n_tokens", "ids", "decoded_sha256"}


def test_run_is_a_query(spark, sf):
    import __spark_entry__

    assert __spark_entry__.queries()["pipeline"](spark, sf).count() > 100
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())
