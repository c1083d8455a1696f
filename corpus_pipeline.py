"""A corpus in five stages: quality rules, line dedup, near-dedup, substring dedup, packing.

STAGES lists (name, function); each function takes (spark, docs, sf_dir) and returns a DataFrame, which is written and
read again as the next one's docs.  All but the last return the columns of documents.  Every stage works on all rows
that its predecessor kept, and decides on whole texts.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from truekeys.llm import line_dedup, minhash, packing, quality_rules, substring_dedup
from truekeys.llm.exchange import passed_on, staged


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the rules reject go."""
    return quality_rules.kept_documents(docs)


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines found in three documents or more stay in one of them."""
    return passed_on(docs, line_dedup.line_dedup(docs, keep=True), F.col("kept_text"))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group stays: five-word shingles, similarity 0.8 or more."""
    gone = minhash.near_duplicates(docs, minhash.MinHash(shingle=5)).where("not kept").select(F.col("doc_id").alias("_gone"))
    return docs.join(gone, F.col("doc_id") == F.col("_gone"), "left_anti").select(docs.columns)


def passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Words of repeated passages go, and documents of which nothing is left."""
    out = substring_dedup.substring_dedup(docs, keep=True).where("n_removed = 0 or n_removed < n_words")
    return passed_on(docs, out, F.col("kept_text"))


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token pieces with their places in sequences."""
    return packing.pack(docs)


STAGES = [("quality rules", quality), ("line dedup", lines), ("near-dedup", near_duplicates), ("substring dedup", passages), ("packing", packed)]

#: SQL has no compression ratios, signatures or tokenizers; tests/llm holds a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for _, stage in STAGES[:-1]:
        docs = staged(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
