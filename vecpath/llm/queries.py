"""Queries of the ten operators over the given tables, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, html, lm, quality, warc
from .common import cut
from .exact_dedup import digest, mark_copies
from .jaccard import jaccard_join
from .mixing import mix
from .substring import substring_dedup
from .topk import topk_inner


def _docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def quality_model(spark: SparkSession, docs: DataFrame, sf_dir: str) -> quality.Additive:
    """Model of ``labels.quality``, from rows outside the fold that is held out."""
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").where(quality.fold("doc_id", 4) != 2)
    return quality.train(docs, labels)


def op1_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _docs(spark, sf_dir).select("doc_id", "text")
    scored = quality.score(docs, quality_model(spark, docs, sf_dir))
    held_out = F.coalesce(quality.fold("doc_id", 4) == 2, F.lit(False))
    return scored.select("doc_id", held_out.alias("held_out"), "score", "predicted")


def op2_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    narrow = cut(_docs(spark, sf_dir).select("doc_id", digest("text").alias("text_sha256")))
    return mark_copies(narrow, "text_sha256", "doc_id").select(
        "doc_id", "keep_id", "group_size", "kept", "text_sha256"
    )


def op3_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    scored = lm.score(_docs(spark, sf_dir).select("doc_id", "text"), quality.fold("doc_id", 7) != 2)
    held_out = F.coalesce(quality.fold("doc_id", 7) == 2, F.lit(False))
    return scored.select(
        "doc_id", held_out.alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score"
    )


def op4_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    mixed = mix(_docs(spark, sf_dir).select("doc_id", "source", "text"))
    return mixed.select(
        "doc_id", "size", "source_size", "target", (F.col("copies") * F.col("size")).cast("long").alias("taken")
    )


def op5_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup(_docs(spark, sf_dir).select("doc_id", "text"))


def op6_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = warc.new_folder(spark, "warc")
    written = warc.write_pages(spark.read.parquet(f"{sf_dir}/pages.parquet"), folder)
    return warc.page_records(warc.read_archives(written, folder), strict=True)


def op7_topk_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    return topk_inner(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))


def op8_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html.extract(spark.read.parquet(f"{sf_dir}/pages.parquet"))


def tokenizer_path(name: str = "byte_bpe_50k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op9_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_decode(_docs(spark, sf_dir).select("doc_id", "text"), tokenizer_path()).drop("text")


def op10_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_join(_docs(spark, sf_dir).select("doc_id", "text"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_quality_classifier": op1_quality_classifier,
    "op2_exact_dedup": op2_exact_dedup,
    "op3_lm_scoring": op3_lm_scoring,
    "op4_mix_sources": op4_mix_sources,
    "op5_substring_dedup": op5_substring_dedup,
    "op6_warc": op6_warc,
    "op7_topk_search": op7_topk_search,
    "op8_html_extraction": op8_html_extraction,
    "op9_bpe": op9_bpe,
    "op10_jaccard_join": op10_jaccard_join,
}

SQL_OP2 = """
WITH d AS (
  SELECT doc_id, sha256(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')) AS text_sha256
  FROM documents)
SELECT doc_id, max(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size,
       doc_id = max(doc_id) OVER w AS kept, text_sha256
FROM d WINDOW w AS (PARTITION BY text_sha256)
"""

SQL_OP6 = """
WITH p AS (SELECT page_id, coalesce(html, '') AS html FROM pages),
d AS (SELECT page_id, octet_length(encode(html)) AS payload_bytes, sha256(html) AS payload_digest FROM p),
f AS (SELECT *, min(page_id) OVER (PARTITION BY payload_digest) AS first FROM d)
SELECT page_id, payload_bytes, payload_digest,
       CASE WHEN payload_bytes >= 100 AND page_id <> first THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN payload_bytes >= 100 AND page_id <> first THEN first END AS refers_to
FROM f
"""

SQL_OP7 = """
WITH e AS (
  SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(256 * CAST(x AS DOUBLE)) AS DOUBLE)) AS q
  FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (
  SELECT a.vec_id AS query_id, b.vec_id, CAST(list_dot_product(a.q, b.q) AS BIGINT) AS score
  FROM e a JOIN e b ON a.vec_id % 50 = 0 AND a.vec_id <> b.vec_id),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s)
SELECT query_id, CAST(rank AS INTEGER) AS rank, vec_id, score FROM r WHERE rank <= 5
"""

ORACLES: dict[str, str] = {"op2_exact_dedup": SQL_OP2, "op6_warc": SQL_OP6, "op7_topk_search": SQL_OP7}
