"""The queries op1 to op10 over whole tables, and the SQL of those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coverdp.llm import bpe, decontaminate, langid, linechunks, neardup, paragraphs, quality, substrings, toxicity, warc
from coverdp.runtime import table


def _remainder(by: int):
    return F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(by))


def op1_minhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.near_duplicates(table(spark, sf_dir, "documents"))


def op2_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    prototypes = langid.train(docs.where(_remainder(4) != 2))
    return langid.identify(docs, prototypes).select("doc_id", (_remainder(4) == 2).alias("held_out"), "lang_pred", "score")


def op3_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.find_leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    model = toxicity.train(docs, labels.where(_remainder(5) != 0))
    return toxicity.score(docs, model).select("doc_id", (_remainder(5) == 0).alias("held_out"), "score", "predicted")


def op5_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.archive_pages(table(spark, sf_dir, "pages"))


def codec() -> bpe.Codec:
    import public_tokenizers

    return bpe.Codec.load(public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)


def op6_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.round_trip(table(spark, sf_dir, "documents"), codec())


def op7_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = substrings.remove_repeats(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_bytes", "n_removed", F.size("removed").cast("long").alias("n_spans"), F.sha2("kept", 256).alias("kept_sha256"))


def op8_paragraph_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return paragraphs.removals(table(spark, sf_dir, "documents"))


def op9_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.quality_rules(table(spark, sf_dir, "documents"))


def op10_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = linechunks.drop_repeated_chunks(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_chunks", "n_removed_lines", F.octet_length("text").cast("long").alias("n_kept_bytes"), F.sha2(F.coalesce("text", F.lit("")), 256).alias("kept_sha256"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    every = op1_minhash_near_dedup, op2_language_id, op3_decontamination, op4_toxicity, op5_warc, op6_byte_bpe, op7_substring_dedup, op8_paragraph_dedup, op9_quality_rules, op10_line_dedup
    return {f.__name__: f for f in every}


def oracle_sql() -> dict[str, str]:
    return {
        "op5_warc": """
            WITH p AS (SELECT page_id, coalesce(html, '') AS html FROM pages),
            d AS (SELECT page_id, octet_length(encode(html)) AS n, sha256(html) AS h FROM p),
            f AS (SELECT h, min(page_id) AS first FROM d WHERE n >= 100 GROUP BY h)
            SELECT d.page_id, CAST(d.n AS BIGINT) AS payload_bytes, d.h AS payload_digest,
                   CASE WHEN d.n >= 100 AND f.first <> d.page_id THEN 'revisit' ELSE 'response' END AS record_type,
                   CASE WHEN d.n >= 100 AND f.first <> d.page_id THEN f.first END AS refers_to
            FROM d LEFT JOIN f ON d.h = f.h""",
    }
