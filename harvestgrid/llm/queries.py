"""The dealt queries opN_<name> and their DuckDB counterparts."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table


def op4_simhash_components(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .simhash import near_duplicates

    found = near_duplicates(table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


QUERIES = {
    "op4_simhash_components": op4_simhash_components,
}

ORACLE_SQL: dict[str, str] = {}


def op1_entropy_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .mixing import mixed

    found = mixed(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "size", "source_size", F.round("target", 6).alias("target"), (F.col("copies") * F.col("size")).alias("taken"), F.round("rate", 6).alias("rate"))


QUERIES["op1_entropy_mix"] = op1_entropy_mix

def op10_word_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .bpe import round_trip

    return round_trip(table(spark, sf_dir, "documents"))


QUERIES["op10_word_bpe"] = op10_word_bpe


def op8_transport_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .mpegts import stored_and_read

    return stored_and_read(table(spark, sf_dir, "documents")).drop("units")


QUERIES["op8_transport_stream"] = op8_transport_stream


def op3_warc_bundles(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .warc import read, write

    folder, index = write(table(spark, sf_dir, "pages"))
    return read(folder, index).drop("url")


QUERIES["op3_warc_bundles"] = op3_warc_bundles


def op5_pivot_top5(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .pivot_search import top_k

    vectors = table(spark, sf_dir, "embeddings")
    return top_k(vectors, vectors.where("vec_id % 50 = 0"), k=5)


QUERIES["op5_pivot_top5"] = op5_pivot_top5

ORACLE_SQL["op5_pivot_top5"] = """
WITH good AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)) AS v FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
scored AS (
  SELECT q.vec_id AS query_id, c.vec_id, list_inner_product(q.v, c.v)::BIGINT AS score
  FROM good q JOIN good c ON q.vec_id <> c.vec_id AND len(q.v) = len(c.v) WHERE q.vec_id % 50 = 0),
ranked AS (SELECT *, (row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id))::INTEGER AS rank FROM scored)
SELECT query_id, rank, vec_id, score FROM ranked WHERE rank <= 5
"""


def op6_crf_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .common import fold
    from .langid_crf import fit, predict

    docs = table(spark, sf_dir, "documents")
    found = predict(docs, fit(docs))
    return found.select("doc_id", (fold(F.col("doc_id"), 4) == 2).alias("held_out"), "lang_pred", "score")


QUERIES["op6_crf_language"] = op6_crf_language


def op2_compression_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .common import fold
    from .compress_quality import fit, score

    docs = table(spark, sf_dir, "documents")
    found = score(docs, fit(docs, table(spark, sf_dir, "labels")))
    return found.select("doc_id", (fold(F.col("doc_id"), 3) == 1).alias("held_out"), "score", "predicted")


QUERIES["op2_compression_quality"] = op2_compression_quality


def op7_boosted_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .html_gbt import main_text

    return main_text(table(spark, sf_dir, "pages"))


QUERIES["op7_boosted_main_text"] = op7_boosted_main_text


def op9_disclosure_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .pii import detect

    return detect(table(spark, sf_dir, "documents"))


QUERIES["op9_disclosure_pii"] = op9_disclosure_pii

ORACLE_SQL["op3_warc_bundles"] = """
WITH p AS (SELECT page_id, encode(coalesce(html, '')) AS b FROM pages),
h AS (SELECT page_id, octet_length(b)::BIGINT AS payload_bytes, sha1(b) AS hex FROM p),
f AS (SELECT hex, min(page_id) AS first FROM h GROUP BY hex),
bits AS (SELECT h.*, first, list_aggregate(list_transform(range(1, 41), lambda i: substr('0000000100100011010001010110011110001001101010111100110111101111', strpos('0123456789abcdef', substr(h.hex, i, 1))::BIGINT * 4 - 3, 4)), 'string_agg', '') AS s
         FROM h JOIN f USING (hex))
SELECT page_id, payload_bytes,
  list_aggregate(list_transform(range(0, 32), lambda k: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567',
    1 + 16 * substr(s, 5 * k + 1, 1)::BIGINT + 8 * substr(s, 5 * k + 2, 1)::BIGINT + 4 * substr(s, 5 * k + 3, 1)::BIGINT + 2 * substr(s, 5 * k + 4, 1)::BIGINT + substr(s, 5 * k + 5, 1)::BIGINT, 1)), 'string_agg', '') AS payload_digest,
  CASE WHEN page_id = first OR first IS NULL THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN page_id = first OR first IS NULL THEN NULL ELSE first END AS refers_to
FROM bits
"""
