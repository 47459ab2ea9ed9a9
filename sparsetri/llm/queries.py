"""The operators' registered queries, each over a whole table with production parameters, and their SQL where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, line_dedup, minhash, mixing, nn_descent, quality, telephony, token_counts, token_store, warc
from .common import stored, table

BYTE_BPE = public_tokenizers.path("byte_bpe_50k.tiktoken")
WORD_BPE = public_tokenizers.path("word_bpe_49k.json")
END_OF_DOCUMENT = 49407


def op1_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, n_tokens, ended): ids before each end-of-document id, found by scanning flat files."""
    files = token_counts.write_flat_files(table(spark, sf_dir, "documents"), WORD_BPE, END_OF_DOCUMENT)
    counted = token_counts.token_counts(files.select("file", "bytes"), END_OF_DOCUMENT)
    written = files.select("file", F.posexplode("doc_ids").alias("place", "doc_id")).select("file", F.col("place").cast("long").alias("place"), "doc_id")
    return written.join(counted, ["file", "place"], "left").select("doc_id", "n_tokens", "ended")


def op2_telephony_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Media in three codecs by content, at 8 kHz; the stored PCM has the operator's 16 kHz, every sample and one between each two."""
    return telephony.media_digest(telephony.store_media(table(spark, sf_dir, "documents")))


def op3_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    out = line_dedup.dedup_lines(docs)
    return out.select("doc_id", "line_dedup.n_lines", "line_dedup.n_dropped", F.sha2("text", 256).alias("kept_sha256"))


def op4_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    labels = table(spark, sf_dir, "labels").where(~quality.held_out())
    scored = quality.score(docs, quality.fit(docs, labels))
    return scored.select("doc_id", quality.held_out().alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"))


def op5_warc_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    index = warc.write_archives(table(spark, sf_dir, "pages"))
    records = stored(warc.read_records(index).withColumn("own_bytes", F.octet_length("payload").cast("long")).drop("payload"), "warc-records")
    done = warc.resolve_revisits(records)
    return done.select("page_id", "payload_bytes", F.col("digest").alias("payload_digest"), "record_type", "refers_to")


def op6_nn_descent(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nn_descent.near_vectors(table(spark, sf_dir, "embeddings"))


def op7_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    ids = bpe.encode_documents(table(spark, sf_dir, "documents"), BYTE_BPE, public_tokenizers.PATTERN)
    return bpe.decode_documents(ids, BYTE_BPE, public_tokenizers.PATTERN)


def op8_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    mixed = mixing.mix(table(spark, sf_dir, "documents"))
    return mixed.select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).alias("taken"))


def op9_token_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_store.read_shards(token_store.write_shards(table(spark, sf_dir, "documents"), WORD_BPE))


def op10_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash.near_duplicates(table(spark, sf_dir, "documents"), width=4)


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    own = (op1_token_counts, op2_telephony_media, op3_line_dedup, op4_quality_classifier, op5_warc_index, op6_nn_descent, op7_byte_bpe, op8_mix_sources, op9_token_store, op10_minhash, pipeline)
    return {f.__name__: f for f in own}


_BLANKS = "chr(32) || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)"
_UPPER, _LOWER = "'ABCDEFGHIJKLMNOPQRSTUVWXYZ'", "'abcdefghijklmnopqrstuvwxyz'"

LINE_DEDUP_SQL = f"""
WITH lines AS (
  SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line,
         generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS pos
  FROM documents),
keyed AS (SELECT *, translate(trim(line, {_BLANKS}), {_UPPER}, {_LOWER}) AS key FROM lines),
common AS (
  SELECT key, max(doc_id) AS keeper FROM keyed WHERE length(key) >= 40
  GROUP BY key HAVING count(DISTINCT doc_id) >= 5),
flagged AS (
  SELECT k.doc_id, k.pos, k.line, (c.key IS NOT NULL AND k.doc_id <> c.keeper) AS gone
  FROM keyed k LEFT JOIN common c ON k.key = c.key)
SELECT doc_id, count(*) AS n_lines, count(*) FILTER (gone) AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (NOT gone), '')) AS kept_sha256
FROM flagged GROUP BY doc_id
"""

WARC_SQL = """
WITH p AS (
  SELECT page_id, octet_length(encode(coalesce(html, ''))) AS payload_bytes, sha1(coalesce(html, '')) AS payload_digest FROM pages),
k AS (SELECT payload_digest AS d, max(page_id) AS keeper FROM p WHERE payload_bytes >= 1000 GROUP BY 1)
SELECT page_id, payload_bytes, payload_digest,
       CASE WHEN keeper IS NOT NULL AND page_id <> keeper THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN keeper IS NOT NULL AND page_id <> keeper THEN keeper END AS refers_to
FROM p LEFT JOIN k ON payload_bytes >= 1000 AND payload_digest = d
"""

MIX_SQL = """
WITH sized AS (
  SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+'))::BIGINT AS size,
         substr(md5('mix|' || doc_id), 1, 9) AS h
  FROM documents),
per AS (SELECT source, sum(size)::BIGINT AS source_size FROM sized GROUP BY source),
ranked AS (
  SELECT *, (ARRAY[5.0, 2.0, 1.0])[((row_number() OVER (ORDER BY source IS NULL, encode(source)) - 1) % 3)::INT + 1]::DOUBLE AS weight,
         row_number() OVER (ORDER BY source IS NULL, encode(source)) AS place
  FROM per),
leveled AS (
  SELECT *, source_size / weight AS ratio,
         ((sum(source_size) OVER ())::DOUBLE * 1.5::DOUBLE
           - coalesce(sum(2 * source_size) OVER (ORDER BY source_size / weight, place ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::DOUBLE)
         / sum(weight) OVER (ORDER BY source_size / weight, place ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level
  FROM ranked),
fixed AS (SELECT level AS fixed FROM leveled WHERE level * weight <= 2 * source_size ORDER BY ratio, place LIMIT 1),
targets AS (
  SELECT source, source_size, least(2.0::DOUBLE * source_size, fixed * weight) AS target FROM leveled, fixed),
lefts AS (
  SELECT *, CASE WHEN source_size > 0 THEN floor(target / source_size) ELSE 0 END AS whole,
         target - CASE WHEN source_size > 0 THEN floor(target / source_size) ELSE 0 END * source_size AS budget
  FROM targets),
slices AS (
  SELECT s.source, s.h, sum(size) AS words, sum(sum(size)) OVER (PARTITION BY s.source ORDER BY s.h) AS upto
  FROM sized s GROUP BY s.source, s.h),
cut AS (
  SELECT sl.source, sl.h, sl.words, sl.upto, l.whole, l.budget, l.target, l.source_size
  FROM slices sl JOIN lefts l ON sl.source IS NOT DISTINCT FROM l.source),
edge AS (SELECT source, min(h) AS edge FROM cut WHERE upto > budget GROUP BY source),
decided AS (
  SELECT c.source, c.h, c.target, c.source_size, c.whole
         + CASE WHEN e.edge IS NULL THEN (c.budget > 0)::INT
                WHEN c.h < e.edge THEN 1
                WHEN c.h = e.edge THEN ((c.budget - c.upto + c.words) * 2 > c.words)::INT
                ELSE 0 END AS copies
  FROM cut c LEFT JOIN edge e ON c.source IS NOT DISTINCT FROM e.source)
SELECT s.doc_id, s.size, d.source_size, d.target, (s.size * d.copies)::BIGINT AS taken
FROM sized s JOIN decided d ON s.source IS NOT DISTINCT FROM d.source AND s.h = d.h
"""


def oracle_sql() -> dict[str, str]:
    """Telephony digests, classifier, tokenizers and MinHash have no SQL; their tests hold them against brute force."""
    return {"op3_line_dedup": LINE_DEDUP_SQL, "op5_warc_index": WARC_SQL, "op8_mix_sources": MIX_SQL}
