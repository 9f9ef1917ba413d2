"""Token counts by a finite-state transducer whose arcs carry emitted-token counts.

The merge table is compiled to a deterministic transducer (see ``transducer``). Every text runs through it: texts are laid in one
stream of symbols, the stream is cut into chunks, all chunks move in lock step, and their state maps are composed by a
prefix scan. What a text emits is the sum of its arcs' annotations. Workers compile states when a text first needs them, and
forget them when there are too many, so memory is bounded.

A tokenizer file whose normaliser, splitting rule or model is of another kind is counted by its own library, text by text.

Defined results: null and empty texts have 0 bytes and 0 tokens; a very long text is one row, read in parts cut at spaces; repeated
rows are counted each; rows with null ids are counted too; an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from predmap.llm import pieces
from predmap.llm.common import batch_of, small, table, texts
from predmap.llm.transducer import Counter

NAME = "op8_token_counts"
SQL = None  # a tokenizer's merges are not an SQL expression; tests compare with the library
VOCABULARY = "word_bpe_49k.json"
SCHEMA = "doc_id long, n_bytes long, n_tokens long, over_limit boolean"

_counters: dict[str, Counter] = {}


def counter(file: str) -> Counter:
    """One counter per worker process and file."""
    if file not in _counters:
        _counters[file] = Counter(file)
    return _counters[file]


def count_tokens(docs: DataFrame, vocabulary: str, limit: int = 2048, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit for every row, with no shuffle."""
    schema = pa.schema([("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("n_tokens", pa.int64()), ("over_limit", pa.bool_())])

    def run(batches):
        fst = counter(vocabulary)
        for b in small(batches):
            n = fst.counts(texts(b))
            yield batch_of(schema, b.column("doc_id"), b.column("n_bytes"), n, [x > limit for x in n])

    text = F.coalesce(docs[text_col], F.lit(""))
    return docs.select(docs[id_col].cast("long").alias("doc_id"), F.octet_length(text).cast("long").alias("n_bytes"), text.alias("text")).mapInArrow(run, SCHEMA)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return count_tokens(table(spark, sf_dir, "documents"), pieces.path(VOCABULARY))
