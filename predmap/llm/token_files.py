"""Token files: ids in a Simple-8b word format, in ascending document order, and their reader.

A 64-bit word holds a 4-bit selector in its top bits and as many equally wide ids as fit the other 60. Selector 0 is the escape:
the next word is one id of 64 bits, whatever its value. Words form blocks of whole documents; a block carries its documents'
lengths, so any document is found without decoding others, and a block is decoded by numpy, selector by selector.

Files are Parquet tables of blocks written by Spark, one range of document ids per file, so commits are atomic, retried tasks
leave nothing behind and any store that Spark reaches will do. The start of each document among all ids is the running sum over
the ranges (as many rows as files) plus the place within its range.

Defined results: a null or empty text is the one end id; a very long text is one block of its own; rows that repeat an id follow
each other, in the order of their texts' hashes; rows with a null id come first; an empty table gives an empty file set; other columns are not read.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from predmap.llm import pieces
from predmap.llm.common import batch_of, scratch, small, table, texts

NAME = "op4_token_files"
SQL = None  # tests check round trips and hold ids against the library
VOCABULARY = "word_bpe_49k.json"
END = 1
BLOCK_IDS, FILE_BYTES = 1 << 16, 10 << 20
#: Ids per word by selector, 0 the escape.
COUNTS = (0, 60, 30, 20, 15, 12, 10, 8, 7, 6, 5, 4, 3, 2, 1)
WIDTHS = tuple(60 // c if c else 64 for c in COUNTS)
BLOCKS = "shard int, block long, doc_ids array<long>, lengths array<long>, words binary"
OUT = "shard int, doc_id long, local_start long, n_tokens long, ids_crc32 long"


def _longest(small: np.ndarray) -> int:
    """Length of the longest run of True."""
    edge = np.flatnonzero(np.diff(small, prepend=False, append=False))
    return int((edge[1::2] - edge[::2]).max(initial=0))


def encode(ids: np.ndarray) -> bytes:
    """Little-endian 64-bit words of ids (unsigned integers up to 64 bits)."""
    v = np.asarray(ids, np.uint64)
    n = len(v)
    if not n:
        return b""
    step, sel = np.ones(n, np.uint8), np.zeros(n, np.uint8)
    top = int(v.max())
    narrow = np.uint32 if top < 1 << 32 else np.uint64  # what is compared: half as wide where ids allow
    x = v.astype(narrow)
    # long runs of small ids are rare: selectors that no run is long enough for are not tried
    first = 8
    while first > 1 and _longest(x < (1 << WIDTHS[first - 1])) >= COUNTS[first - 1]:
        first -= 1
    most = COUNTS[first]
    best = np.zeros(n, bool)
    ors = {1: np.concatenate([x, np.zeros(64, narrow)])}  # ors[k][i]: or of v[i : i + k], whose highest bit is that of the largest
    reach = 1
    while reach * 2 <= most:
        wide = ors[reach].copy()
        wide[:-reach] |= ors[reach][reach:]
        reach *= 2
        ors[reach] = wide
    left = n - np.arange(n)
    for s in range(first, len(COUNTS)):
        c, w = COUNTS[s], WIDTHS[s]
        k = 1 << (c.bit_length() - 1)
        if top >> w == 0:  # any ids fit
            ok = ~best & (left >= c)
            step[ok], sel[ok] = c, s
            best |= ok
            continue
        over = ors[k][:n] | (ors[k][c - k : c - k + n] if c > k else 0)
        ok = ~best & (left >= c) & ((over >> narrow(w)) == 0)
        step[ok], sel[ok] = c, s
        best |= ok
    at, starts, steps = 0, [], step.tobytes()
    add = starts.append
    while at < n:
        add(at)
        at += steps[at]
    starts = np.array(starts)
    chosen = sel[starts]
    size = 1 + (chosen == 0)
    place = np.cumsum(size) - size
    out = np.zeros(int(size.sum()), np.uint64)
    for s in np.unique(chosen):
        rows = np.flatnonzero(chosen == s)
        if s == 0:
            out[place[rows] + 1] = v[starts[rows]]
            continue
        c, w = COUNTS[s], WIDTHS[s]
        word = np.full(len(rows), np.uint64(int(s) << 60))
        for k in range(c):
            word |= v[starts[rows] + k] << np.uint64(k * w)
        out[place[rows]] = word
    return out.astype("<u8").tobytes()


def decode(words: bytes) -> np.ndarray:
    """The ids of encode()."""
    w = np.frombuffer(words, "<u8")
    if not len(w):
        return np.zeros(0, np.uint64)
    sel = (w >> np.uint64(60)).astype(np.int64)
    raw = np.zeros(len(w), bool)
    escapes = np.flatnonzero(sel == 0)
    if len(escapes):  # a literal may look like an escape: take them in order
        last = -2
        for e in escapes.tolist():
            if e != last + 1 or not raw[e]:
                raw[e + 1], last = True, e
    head = np.flatnonzero(~raw)
    sel = sel[head]
    count = np.maximum(np.array(COUNTS)[sel], 1)
    place = np.cumsum(count) - count
    out = np.zeros(int(count.sum()), np.uint64)
    for s in np.unique(sel):
        rows = np.flatnonzero(sel == s)
        if s == 0:
            out[place[rows]] = w[head[rows] + 1]
            continue
        c, b = COUNTS[s], WIDTHS[s]
        mask = np.uint64((1 << b) - 1)
        word = w[head[rows]]
        for k in range(c):
            out[place[rows] + k] = (word >> np.uint64(k * b)) & mask
    return out


def write(docs: DataFrame, path: str, vocabulary: str, end: int = END, id_col: str = "doc_id", text_col: str = "text") -> None:
    """Writes the token files of docs to path."""
    schema = pa.schema([("shard", pa.int32()), ("block", pa.int64()), ("doc_ids", pa.list_(pa.int64())), ("lengths", pa.list_(pa.int64())), ("words", pa.binary())])

    def run(batches):
        enc, shard = pieces.encoder(vocabulary), TaskContext.get().partitionId()
        ids, lens, parts, held, block = [], [], [], 0, 0
        last = np.array([end], enc.dtype)
        for b in small(batches):
            for doc_id, text in zip(b.column("doc_id").to_pylist(), texts(b), strict=True):
                own = enc.ids(text)
                ids.append(doc_id)
                lens.append(len(own) + 1)
                parts += [own, last]
                held += len(own) + 1
                if held >= BLOCK_IDS:
                    yield batch_of(schema, [shard], [block], [ids], [lens], [encode(np.concatenate(parts))])
                    ids, lens, parts, held, block = [], [], [], 0, block + 1
        if ids:
            yield batch_of(schema, [shard], [block], [ids], [lens], [encode(np.concatenate(parts))])

    rows = docs.select(docs[id_col].cast("long").alias("doc_id"), F.coalesce(docs[text_col], F.lit("")).alias("text"))
    n, size = rows.agg(F.count(F.lit(1)), F.sum(F.octet_length("text"))).head()
    files = max(1, min(n, -(-(size or 0) // FILE_BYTES)))
    # rows that share an id, or have none, are dealt by their texts' hash, so that no id is a hot range
    order = [F.col("doc_id").asc_nulls_first(), F.xxhash64("text").asc()]
    (
        rows.repartitionByRange(files, *order)
        .sortWithinPartitions(*order)
        .mapInArrow(run, BLOCKS)
        .write.mode("overwrite").option("compression", "zstd").parquet(path)
    )


def read(spark: SparkSession, path: str) -> DataFrame:
    """Per document: doc_id, start, n_tokens, ids_crc32, from the files at path."""
    blocks = spark.read.schema(BLOCKS).parquet(path)
    schema = pa.schema([("shard", pa.int32()), ("block", pa.int64()), ("local_start", pa.int64()), ("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("ids_crc32", pa.int64())])

    def run(batches):
        for b in batches:
            for row in b.to_pylist():
                ids = decode(row["words"]).astype("<u4")
                n = len(row["lengths"])
                ends = np.cumsum(row["lengths"])
                starts = ends - row["lengths"]
                crc = [zlib.crc32(ids[a:z]) for a, z in zip(starts.tolist(), ends.tolist(), strict=True)]
                yield batch_of(schema, [row["shard"]] * n, [row["block"]] * n, starts, row["doc_ids"], row["lengths"], crc)

    sizes = blocks.select("shard", "block", F.aggregate("lengths", F.lit(0).cast("long"), lambda a, x: a + x).alias("n"))
    shards = sizes.groupBy("shard").agg(F.sum("n").alias("n"))
    before = shards.select(F.col("shard"), (F.sum("n").over(Window.orderBy("shard")) - F.col("n")).alias("shard_start"))
    within = sizes.select("shard", "block", (F.sum("n").over(Window.partitionBy("shard").orderBy("block")) - F.col("n")).alias("block_start"))
    starts = within.join(before, "shard").select("shard", "block", (F.col("shard_start") + F.col("block_start")).alias("before"))
    docs = blocks.select("shard", "block", "doc_ids", "lengths", "words").mapInArrow(run, "shard int, block long, local_start long, doc_id long, n_tokens long, ids_crc32 long")
    return docs.join(starts, ["shard", "block"]).select("doc_id", (F.col("before") + F.col("local_start")).alias("start"), "n_tokens", "ids_crc32")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = scratch(spark, "token-files")
    write(table(spark, sf_dir, "documents"), path, pieces.path(VOCABULARY))
    return read(spark, path)
