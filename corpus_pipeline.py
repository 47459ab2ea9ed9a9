"""Five stages from raw documents to token ids; each works on everything its predecessor kept.

Defined results: a null text counts as an empty one, and like any text it stays or goes by its score; line dedup turns a null text that stays
into an empty one.  Rows with a null doc_id learn from no label, count for no line, are copies of nothing and are mixed by their text.  Rows
that share a doc_id keep a row each, and stay or go together as near copies.  Equal texts have equal scores; of equal texts under different
ids the least id stays.  Columns beyond doc_id, text and source pass through untouched, but for n_chars, which follows the text.  An empty
table gives an empty one.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sparsetri.llm import bpe, line_dedup, minhash, mixing, quality
from sparsetri.llm.common import stored, table
from sparsetri.llm.queries import BYTE_BPE


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier does not reject.  It learns from the labels of the table folder, without the held-out ones."""
    labels = table(spark, sf_dir, "labels").where(~quality.held_out())
    return quality.score(docs, quality.fit(docs, labels), "__score").where(F.col("__score") >= 0.7).select(*docs.columns)


def drop_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without lines that many documents share; n_chars follows."""
    return line_dedup.dedup_lines(docs).withColumn("n_chars", F.char_length("text").cast("long")).select(*docs.columns)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group: five words, similarity 0.8."""
    return minhash.keep_one(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes them."""
    return mixing.take(docs)


def encode_bytes(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256)."""
    return bpe.round_trip_documents(docs, BYTE_BPE, public_tokenizers.PATTERN)


STAGES = [
    ("quality_classifier", keep_quality),
    ("line_dedup", drop_lines),
    ("minhash_near_dedup", drop_near_copies),
    ("mix_sources", mix_sources),
    ("byte_bpe", encode_bytes),
]

#: A trained classifier, MinHash and a tokenizer are beyond SQL; tests/llm holds the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = stored(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
