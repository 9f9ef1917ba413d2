"""Packing: order-preserving dynamic programming over document and sentence boundaries.

Documents follow each other in the order in which a task reads them. A sequence is a window of at most ``size`` tokens of that
stream. Windows may end at the end of a document (free), at the end of a sentence (small penalty) or, where a sentence is longer
than a window, inside it (large penalty). With f(j) the least cost of packing everything before boundary j,

    f(j) = penalty(j) + per_sequence + min over i of f(i) + padding(position(j) - position(i)),

and as padding is ``size`` minus the length, the minimum is one of f(i) + position(i) over a sliding window, kept in a monotone
queue: amortised constant time per boundary. Lengths that are a power of two need no padding and are tried besides.

Every task packs what it reads, in blocks of bounded size whose unfinished tail is carried on, so nothing is shuffled and a lost
task is simply run again. sequence_id holds the task's number in its upper bits.

Defined results: a null or empty text is the one end id; a very long text is spread over as many sequences as it needs; repeated
rows are packed each; an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

import zlib
from collections import deque

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from predmap.llm import pieces
from predmap.llm.common import batch_of, small, table, texts

NAME = "op3_packing"
SQL = None  # tests hold it against an exhaustive search and check the pieces
VOCABULARY = "byte_bpe_50k.json"
END, SIZE, BLOCK = 0, 1024, 1 << 19
SENTENCE_PENALTY, INSIDE_PENALTY, PER_SEQUENCE = 8, 256, 48
#: Characters that end a sentence.
ENDERS = ".!?\n"
SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
ARROW = pa.schema([(x, pa.int64()) for x in ("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")])


def boundaries(doc_ends: np.ndarray, sentence_ends: np.ndarray, total: int, size: int = SIZE) -> tuple[list[int], list[int]]:
    """Positions where a window may end, 0 first and total last, and their penalties; no two neighbours are over size apart."""
    pos = np.unique(np.concatenate([[0, total], doc_ends, sentence_ends]).astype(np.int64))
    gaps = np.diff(pos)
    if (gaps > size).any():
        extra = [np.arange(pos[i] + size, pos[i + 1], size) for i in np.flatnonzero(gaps > size)]
        pos = np.unique(np.concatenate([pos, *extra]))
    pen = np.full(len(pos), INSIDE_PENALTY)
    pen[np.isin(pos, sentence_ends, assume_unique=False)] = SENTENCE_PENALTY
    pen[np.isin(pos, doc_ends)] = 0
    return pos.tolist(), pen.tolist()


def padding(length: int, size: int = SIZE) -> int:
    return 0 if length & (length - 1) == 0 else size - length


def best_cuts(pos: list[int], pen: list[int], size: int = SIZE, open_end: bool = False) -> list[int]:
    """Indexes of the boundaries at which windows end, in order. open_end: the last window may be left to a later call."""
    n = len(pos)
    f, back = [0] * n, [0] * n
    place, whole = np.array(pos), {}  # boundary -> those that lie a power of two before it
    for h in (1 << k for k in range(size.bit_length() - 1, -1, -1) if 1 << k < size):
        k = np.searchsorted(place, place - h)
        for j in np.flatnonzero((place >= h) & (place[k] == place - h)).tolist():
            whole.setdefault(j, []).append(int(k[j]))
    queue: deque = deque([(0, 0)])  # (f(i) + position(i), i), rising
    for j in range(1, n):
        p = pos[j]
        while pos[queue[0][1]] < p - size:
            queue.popleft()
        g, i = queue[0]
        cost = g + size - p
        for k in whole.get(j, ()):
            if f[k] < cost:
                cost, i = f[k], k
        cost += PER_SEQUENCE + pen[j]
        f[j], back[j] = cost, i
        g = cost + p
        while queue and queue[-1][0] >= g:
            queue.pop()
        queue.append((g, j))
    j = n - 1
    if open_end and pos[-1] > 2 * size:
        near = [k for k in range(n) if pos[k] > pos[-1] - size]
        j = min(near, key=lambda k: (f[k] - pos[k] * PER_SEQUENCE / size, -k))
    cuts = []
    while j:
        cuts.append(j)
        j = back[j]
    return cuts[::-1]


class Packer:
    """Takes documents, gives pieces; holds a block of tokens at most, besides the document being added."""

    def __init__(self, ends: np.ndarray, size: int, first: int):
        self.ends, self.size, self.next = ends, size, first
        self.held: list[tuple] = []  # (doc_id, start in the document, ids, the document's tokens)
        self.tokens = 0

    def add(self, doc_id, ids: np.ndarray):
        """Pieces that are complete by now."""
        for at in range(0, len(ids), BLOCK):
            part = ids[at : at + BLOCK]
            self.held.append((doc_id, at, part, len(ids)))
            self.tokens += len(part)
            if self.tokens >= BLOCK:
                yield self.flush(False)

    def flush(self, last: bool) -> list[tuple]:
        if not self.held:
            return []
        bounds = np.cumsum([0] + [len(x[2]) for x in self.held])
        stream = np.concatenate([x[2] for x in self.held])
        finished = [i for i, x in enumerate(self.held) if x[1] + len(x[2]) == x[3]]
        pos, pen = boundaries(bounds[1:][finished], np.flatnonzero(self.ends[stream]) + 1, len(stream), self.size)
        cuts = [pos[i] for i in best_cuts(pos, pen, self.size, not last)]
        wide, starts = stream.astype("<u4"), [0, *cuts[:-1]]
        inner = np.unique(np.concatenate([[0], cuts, bounds[bounds < cuts[-1]]]).astype(np.int64))
        whose = np.searchsorted(bounds, inner[:-1], side="right") - 1
        which = np.searchsorted(cuts, inner[:-1], side="right")
        out = []
        for a, b, d, s in zip(inner[:-1].tolist(), inner[1:].tolist(), whose.tolist(), which.tolist(), strict=True):
            doc_id, at, _, n = self.held[d]
            out.append((doc_id, at + a - int(bounds[d]), b - a, zlib.crc32(wide[a:b]), n, self.next + s, a - starts[s]))
        self.next += len(cuts)
        done, held = cuts[-1], []
        for (doc_id, at, ids, n), a, b in zip(self.held, bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
            if b > done:
                held.append((doc_id, at + max(0, done - a), ids[max(0, done - a) :], n))
        self.held, self.tokens = held, len(stream) - done
        return out


def sentence_enders(tokenizer) -> np.ndarray:
    """By id: whether the token's last visible character ends a sentence."""
    n = tokenizer.get_vocab_size()
    out = np.zeros(max(n, 1 << 16), bool)
    for i in range(n):
        t = tokenizer.decode([i]).rstrip(" ")
        out[i] = bool(t) and t[-1] in ENDERS
    return out


_ends: dict = {}


def pack(docs: DataFrame, vocabulary: str, size: int = SIZE, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset."""

    def run(batches):
        enc = pieces.encoder(vocabulary)
        if vocabulary not in _ends:
            _ends[vocabulary] = sentence_enders(enc.tokenizer)
        packer = Packer(_ends[vocabulary], size, TaskContext.get().partitionId() << 36)
        end = np.array([END], enc.dtype)
        for b in small(batches):
            rows: list = []
            for doc_id, text in zip(b.column("doc_id").to_pylist(), texts(b), strict=True):
                for done in packer.add(doc_id, np.concatenate([enc.ids(text), end])):
                    rows += done
            if rows:
                yield batch_of(ARROW, *zip(*rows, strict=True))
        while rows := packer.flush(True):
            yield batch_of(ARROW, *zip(*rows, strict=True))

    return docs.select(docs[id_col].cast("long").alias("doc_id"), F.coalesce(docs[text_col], F.lit("")).alias("text")).mapInArrow(run, SCHEMA)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents"), pieces.path(VOCABULARY))
