"""From raw documents to packed training sequences: language ID, exact dedup, near-dedup by shingle sets, decontamination, packing.

Every stage takes (spark, docs, sf_dir), works on all rows its predecessor kept and returns the columns of documents; the last
returns the pieces of packed sequences. Stages are written as Parquet to the shared folder and read again, so a lost executor
costs the stage it was in. Language ID fits its model on the labelled rows of the documents it is given.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from predmap.llm import decontaminate, exact_dedup, langid, packing, pieces, simhash
from predmap.llm.common import scratch, table


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in a language the model knows; those it rejects go."""
    return langid.accept(docs, langid.train(docs))


def exact_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the one with the smallest id."""
    return exact_dedup.dedup(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of documents that share 0.8 or more of their five-word shingles the one with the smallest id."""
    return simhash.dedup_similar(docs)


def benchmark_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark passage."""
    return decontaminate.clean(docs, table(spark, sf_dir, "benchmark"))


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of packed sequences."""
    return packing.pack(docs, pieces.path(packing.VOCABULARY))


STAGES = [
    ("language ID", language_id),
    ("exact dedup", exact_duplicates),
    ("near dedup", near_duplicates),
    ("decontamination", benchmark_leaks),
    ("packing", packed),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents, each written and reread."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        path = scratch(spark, name.replace(" ", "-"))
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return STAGES[-1][1](spark, docs, sf_dir)


#: Fingerprints, the trained model and the tokenizer are no SQL; tests follow the stages by brute force.
ORACLE_SQL = None
