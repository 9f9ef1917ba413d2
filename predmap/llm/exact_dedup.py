"""Exact dedup: group by a 128-bit content hash, keep the smallest id, compare bytes inside the groups.

Only DataFrame functions. One shuffle carries each distinct text of a map task once, as ``(hash, text)`` is the key of a
hash aggregate: the aggregate compares whole texts, so two texts whose hashes collide stay apart, and copies inside a map
task are merged before anything moves. A second, narrow join gives each row its class; a hot class is an ordinary skewed
join there, which adaptive execution splits.

Defined results: null text counts as empty; texts of white space only are equal to each other (one space) but not to the
empty text; a null id is ignored for the smallest id unless the whole class has none (then keep_id is null); rows that repeat
both id and text are each returned, and are kept or dropped together; an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from predmap.llm.common import SPACES, table

NAME = "op10_exact_dedup"


def normalised(text: Column) -> Column:
    """Each run of white space as one space; null as empty."""
    return F.regexp_replace(F.coalesce(text, F.lit("")), SPACES, " ")


def classes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per distinct text: _h (128-bit hash), _sha, keep_id, group_size."""
    keyed = docs.select(docs[id_col].alias("_id"), normalised(docs[text_col]).alias("_t"))
    return (
        keyed.select("_id", "_t", F.unhex(F.md5("_t")).alias("_h"))
        .groupBy("_h", "_t")
        .agg(F.min("_id").alias("keep_id"), F.count(F.lit(1)).alias("group_size"))
        .select("_h", F.sha2("_t", 256).alias("_sha"), "keep_id", "group_size")
    )


def label(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of docs: its id, keep_id, group_size, kept and text_sha256."""
    t = normalised(docs[text_col])
    rows = docs.select(docs[id_col].alias("_id"), F.unhex(F.md5(t)).alias("_h"), F.sha2(t, 256).alias("_sha"))
    return rows.join(classes(docs, id_col, text_col), ["_h", "_sha"]).select(
        F.col("_id").alias(id_col), "keep_id", "group_size", F.col("_id").eqNullSafe(F.col("keep_id")).alias("kept"), F.col("_sha").alias("text_sha256")
    )


def dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of docs that stay, all columns."""
    keep = classes(docs, id_col, text_col).select(F.col("_h").alias("_keep_h"), F.col("keep_id").alias("_keep_id"))
    h = F.unhex(F.md5(normalised(docs[text_col])))
    return docs.join(keep, docs[id_col].eqNullSafe(keep["_keep_id"]) & (h == keep["_keep_h"]), "left_semi")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return label(table(spark, sf_dir, "documents"))


SQL = r"""
WITH t AS (SELECT doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') AS norm FROM documents)
SELECT doc_id, min(doc_id) OVER (PARTITION BY norm) AS keep_id, count(*) OVER (PARTITION BY norm) AS group_size,
       doc_id = min(doc_id) OVER (PARTITION BY norm) AS kept, sha256(norm) AS text_sha256
FROM t
"""
