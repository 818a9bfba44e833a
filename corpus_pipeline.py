"""The corpus pipeline: documents to tokens in five stages.

Each stage is a function of (spark, docs, sf_dir).  Its result is written as
Parquet and read again as the next one's ``docs``, so a lost executor costs a
stage at most.  Columns that ``docs`` has beside those of ``documents`` go through
all stages but the last, whatever their names; empty tables give empty results.
"""

from __future__ import annotations

import uuid

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from bspgraph.llm import bpe, langid, linededup, mixing, neardup
from bspgraph.llm.common import checkpoint_dir, documents


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a language go: null, empty and letterless texts, and
    those whose best language has a likelihood below 0.4.  Languages are learned
    from the labelled rows of ``docs``; without any, all rows go.  Very long texts
    are read whole, repeated rows stay or go together, of equal likelihoods the
    first language by code point counts, and an empty table stays empty."""
    return langid.keep_identified(docs)


def drop_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Long lines of five documents or more stay in the one with the largest
    doc_id; ``n_chars`` follows.  Every row stays: null and empty texts are one
    empty line, rows with one doc_id are one document, a null doc_id is one more
    document below all others.  Very long texts and lines are read whole."""
    out = linededup.dedup_lines(docs)
    return out.withColumn("n_chars", F.length("text").cast("long")) if "n_chars" in docs.columns else out


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies stays, the one with the least
    doc_id.  Null, empty and wordless texts and rows without doc_id are copies of
    nothing and stay; repeated rows have one doc_id and stay or go together."""
    return neardup.keep_one(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each source comes near its share of the words, repeated at most thrice.
    A null source is one of its own; texts without words weigh nothing and are
    taken as their place in the order says; rows with one doc_id are taken alike."""
    return mixing.take(docs)


def encode_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, number and ids of the tokens, and the hash of the text they decode
    to, row by row; null and empty texts have no tokens, very long ones are
    encoded whole."""
    return bpe.tokenise(docs, public_tokenizers.path(bpe.VOCABULARY))


STAGES = [
    ("language ID", identify_language),
    ("line dedup", drop_repeated_lines),
    ("near-duplicate removal", drop_near_copies),
    ("mixing", mix_sources),
    ("BPE", encode_tokens),
]

#: Learned languages and token ids are beyond SQL; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; stages are kept in the shared folder."""
    docs, folder = documents(spark, sf_dir), f"{checkpoint_dir(spark)}/pipeline-{uuid.uuid4().hex}"
    for n, (_, stage) in enumerate(STAGES):
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{n}")
        docs = spark.read.parquet(f"{folder}/{n}")
    return docs
