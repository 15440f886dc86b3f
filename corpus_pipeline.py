"""From raw documents to packed training sequences: quality rules, line dedup, near duplicates, decontamination, packing.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; run() writes what a stage returns to the shared folder
and reads it again as the next one's docs. All stages but the last return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from unicat.llm import decontam, jaccard_join, line_dedup, packing, quality_rules
from unicat.llm.common import materialise, prepare, read_table
from unicat.llm.queries import tokenizer_path


#: Chunks of text whose ids a worker remembers in the last stage: fewer than by itself, as the stages before have left less room.
REMEMBERED = 120_000


def by_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality rules reject go."""
    prepare(spark)
    return quality_rules.drop_rejected(docs)


def by_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines that many documents share go, with n_chars following the text."""
    prepare(spark)
    cleaned = line_dedup.dedup_lines(docs).withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))
    return cleaned.select(*docs.columns)


def by_similarity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates stays."""
    prepare(spark)
    return jaccard_join.keep_one(docs)


def by_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with passages of a benchmark go."""
    return decontam.drop_contaminated(docs, read_table(spark, sf_dir, "benchmark"))


def into_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of sequences, as op2 returns them."""
    prepare(spark)
    return packing.pack(docs, tokenizer_path(), with_ids=False, bound=REMEMBERED).withColumnRenamed("id", "doc_id")


STAGES = [
    ("quality_rules", by_quality),
    ("line_dedup", by_lines),
    ("jaccard_join", by_similarity),
    ("decontamination", by_benchmark),
    ("packing", into_sequences),
]

#: Compression and tokenization are beyond SQL; tests/llm/test_pipeline.py has a brute-force version instead.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
