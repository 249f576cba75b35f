"""A five-stage corpus pipeline over `documents`: from raw documents to packed training sequences.

Each stage takes and, but for the last, returns the columns of `documents`; the caller writes each result
as Parquet and hands the reread table to the next stage. Rows without doc_id pass the near-duplicate stage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from cubefactor.llm.common import load, ship_package, written
from cubefactor.llm.decontaminate import drop_contaminated
from cubefactor.llm.document_dedup import keep_one
from cubefactor.llm.line_dedup import dedup_lines
from cubefactor.llm.packing import pack
from cubefactor.llm.quality import keep_quality


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier rejects go."""
    return keep_quality(docs, load(spark, sf_dir, "labels"))


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each component of similar lines the first stays; documents keep their other lines."""
    ship_package(spark)
    return dedup_lines(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document stays of each group linked by a Jaccard similarity of 0.8 or more over five-word shingles."""
    ship_package(spark)
    return keep_one(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark item go."""
    return drop_contaminated(docs, load(spark, sf_dir, "benchmark"))


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the remaining documents, each with its sequence and offset."""
    ship_package(spark)
    return pack(docs)


STAGES = [
    ("quality", quality),
    ("line dedup", line_dedup),
    ("near duplicates", near_duplicates),
    ("decontamination", decontamination),
    ("packing", packing),
]

#: No stage but the joins around them can be said in SQL: trained trees, MinHash and tokens.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over `documents`; each result is written to the shared folder and read again."""
    docs = load(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), f"stage-{name.replace(' ', '-')}")
    return STAGES[-1][1](spark, docs, sf_dir)
