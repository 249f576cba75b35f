"""The corpus queries: each applies one operator, with production parameters, to its whole table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .block_repeats import word_repeats
from .common import load
from .decontaminate import contamination
from .line_dedup import line_decisions
from .media import media_features, media_table
from .packing import pack
from .quality import classify_quality
from .simhash import near_duplicates
from .suffix_repeats import byte_repeats
from .toxicity import classify_toxicity
from .warc import archive_round_trip


def op1_suffix_repeats(spark: SparkSession, sf_dir: str) -> DataFrame:
    return byte_repeats(load(spark, sf_dir, "documents")).drop("spans")


def op2_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(load(spark, sf_dir, "documents"))


def op3_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return classify_toxicity(load(spark, sf_dir, "documents"), load(spark, sf_dir, "labels"))


def op4_block_repeats(spark: SparkSession, sf_dir: str) -> DataFrame:
    return word_repeats(load(spark, sf_dir, "documents")).drop("spans")


def op5_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contamination(load(spark, sf_dir, "documents"), load(spark, sf_dir, "benchmark"))


def op6_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(load(spark, sf_dir, "documents"))


def op7_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media_features(media_table(load(spark, sf_dir, "documents"))).drop("tile_npy")


def op8_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return classify_quality(load(spark, sf_dir, "documents"), load(spark, sf_dir, "labels"))


def op9_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_decisions(load(spark, sf_dir, "documents"))


def op10_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = archive_round_trip(load(spark, sf_dir, "pages"), segment_bytes=4096)
    refers = F.when(F.col("record_type") == "revisit", F.col("refers_to"))
    return got.select("page_id", "payload_bytes", "payload_digest", "record_type", refers.alias("refers_to"))


QUERIES = {
    "op1_suffix_repeats": op1_suffix_repeats,
    "op2_packing": op2_packing,
    "op3_toxicity": op3_toxicity,
    "op4_block_repeats": op4_block_repeats,
    "op5_decontamination": op5_decontamination,
    "op6_simhash": op6_simhash,
    "op7_media": op7_media,
    "op8_quality": op8_quality,
    "op9_lines": op9_lines,
    "op10_warc": op10_warc,
}
ORACLE_SQL: dict[str, str] = {
    "op10_warc": """
        WITH own AS (SELECT page_id, coalesce(html, '') AS html, octet_length(encode(coalesce(html, ''))) AS n FROM pages),
        hashed AS (SELECT *, sha1(html) AS sha, max(page_id) OVER (PARTITION BY sha1(html)) AS keeper FROM own)
        SELECT page_id, CAST(n AS BIGINT) AS payload_bytes,
            list_aggregate(list_transform(range(32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567',
                CAST(((CAST(('0x' || substr(sha, CAST((i // 4) * 5 + 1 AS BIGINT), 5)) AS BIGINT) >> CAST((3 - i % 4) * 5 AS BIGINT)) & 31) + 1 AS BIGINT), 1)),
                'string_agg', '') AS payload_digest,
            CASE WHEN page_id = keeper THEN 'response' ELSE 'revisit' END AS record_type,
            CASE WHEN page_id <> keeper THEN keeper END AS refers_to
        FROM hashed
    """,
}
