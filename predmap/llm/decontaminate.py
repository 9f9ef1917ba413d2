"""Benchmark decontamination: one Aho-Corasick automaton over normalised benchmark texts, one pass over the documents.

A text is normalised to its words (lower-case A-Z, digits and all non-ASCII characters), and words of items to numbers. Every window
of ``size`` consecutive item words is a pattern; an item of fewer words is one pattern. A node of the automaton is a word, so a
window costs at most ``size`` nodes. The items go to the workers, who build the automaton; their size is checked: beyond
``most_bytes`` of text, some 80 MB of automaton, the items are dealt into as many automata as needed, one pass each, so what a
worker holds stays bounded however large the benchmark is. Documents are never shuffled.

Places are kept as word numbers and mapped back to the original text's characters in ``spans``.

Defined results: null and empty texts have no words and no hits; an item without words has no windows; an item id that occurs
twice counts once; an empty benchmark leaves every document clean; repeated rows are scanned each; other columns are kept out.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from predmap.llm.common import batch_of, cut, small, table, texts

NAME = "op2_decontamination"
SIZE, MOST_BYTES = 10, 1 << 20
#: Byte -> byte: lower-case A-Z, other ASCII outside words to a space; bytes of non-ASCII characters stay.
WORDS = bytes(c + 32 if 65 <= c <= 90 else c if 48 <= c <= 57 or 97 <= c <= 122 or c >= 128 else 32 for c in range(256))
IN_WORD = np.frombuffer(WORDS, np.uint8) != 32


def words(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "surrogatepass").translate(WORDS).split()


def windows(text: str | None, size: int = SIZE) -> list[tuple[bytes, ...]]:
    """The patterns of an item."""
    w = words(text)
    return [tuple(w)] if 0 < len(w) < size else [tuple(w[i : i + size]) for i in range(len(w) - size + 1)]


class Scanner:
    """An automaton over the windows of items: [(item_id, text)]."""

    def __init__(self, items: list[tuple], size: int):
        import ahocorasick

        found: dict[tuple[int, ...], set] = {}
        self.number: dict[bytes, int] = {}  # of item words, from 1; other words are 0
        for item, text in items:
            for window in windows(text, size):
                found.setdefault(tuple(self.number.setdefault(w, len(self.number) + 1) for w in window), set()).add(item)
        self.values = [(len(p), sorted(s, key=str)) for p, s in found.items()]
        self.machine = ahocorasick.Automaton(ahocorasick.STORE_INTS, ahocorasick.KEY_SEQUENCE)
        for k, pattern in enumerate(found):
            self.machine.add_word(pattern, k)
        self.machine.make_automaton()
        self.empty = not found

    def scan(self, w: list[bytes]) -> tuple[list[list[int]], set]:
        """Merged [first, last) word intervals inside occurrences, and the items that occur."""
        if self.empty or not w:
            return [], set()
        get = self.number.get
        hits = list(self.machine.iter(tuple([get(x, 0) for x in w])))
        out: list[list[int]] = []
        items: set = set()
        for a, b, k in sorted((e + 1 - self.values[k][0], e + 1, k) for e, k in hits):
            items.update(self.values[k][1])
            if out and a <= out[-1][1]:
                out[-1][1] = max(out[-1][1], b)
            else:
                out.append([a, b])
        return out, items


def original_spans(text: str, intervals: list[list[int]]) -> list[list[int]]:
    """[start, end) in characters of text of word intervals."""
    raw = np.frombuffer(text.encode("utf-8", "surrogatepass"), np.uint8)
    inside = np.concatenate([[False], IN_WORD[raw], [False]])
    edge = np.flatnonzero(inside[1:] != inside[:-1])
    chars = np.concatenate([[0], np.cumsum((raw & 0xC0) != 0x80)])  # characters begun before each byte
    return [[int(chars[edge[2 * a]]), int(chars[edge[2 * b - 1]])] for a, b in intervals]


def _merge(pairs: list[list[int]]) -> list[list[int]]:
    out: list[list[int]] = []
    for a, b in sorted(pairs):
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return out


_scanners: dict = {}


def _parts(benchmark: DataFrame, item_col: str, text_col: str, most_bytes: int) -> list[DataFrame]:
    """benchmark in parts of about most_bytes of text at most."""
    items = benchmark.select(benchmark[item_col].alias("item"), benchmark[text_col].alias("text"))
    total = items.agg(F.sum(F.octet_length("text"))).head()[0] or 0
    n = -(-total // most_bytes) or 1
    return [items] if n == 1 else [items.filter(F.pmod(F.xxhash64("item", "text"), F.lit(n)) == k) for k in range(n)]


def scan(docs: DataFrame, benchmark: DataFrame, size: int = SIZE, most_bytes: int = MOST_BYTES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per document: doc_id, n_words, n_hit, n_items, items_sha256, contaminated, items (strings) and spans (characters)."""
    spark = docs.sparkSession
    out = "doc_id long, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean, items array<string>, spans array<array<int>>"
    schema = pa.schema([("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_hit", pa.int64()), ("n_items", pa.int64()), ("items_sha256", pa.string()), ("contaminated", pa.bool_()), ("items", pa.list_(pa.string())), ("spans", pa.list_(pa.list_(pa.int32())))])
    mid = "doc_id long, text string, _at array<array<int>>, _items array<string>"
    mid_schema = pa.schema([("doc_id", pa.int64()), ("text", pa.string()), ("_at", pa.list_(pa.list_(pa.int32()))), ("_items", pa.list_(pa.string()))])
    frame = docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text"))
    parts = _parts(benchmark, "item_id", "text", most_bytes)
    for k, part in enumerate(parts):
        given = spark.sparkContext.broadcast([(r["item"], r["text"]) for r in part.collect()])
        final, carried = k + 1 == len(parts), k > 0

        def run(batches, given=given, final=final, carried=carried):
            if given.value is not _scanners.get("of"):
                _scanners.update(of=given.value, scanner=Scanner(given.value, size))
            scanner = _scanners["scanner"]
            for b in small(batches):
                rows = []
                at = b.column("_at").to_pylist() if carried else [[]] * b.num_rows
                held = b.column("_items").to_pylist() if carried else [[]] * b.num_rows
                for doc_id, text, old, old_items in zip(b.column("doc_id").to_pylist(), texts(b), at, held, strict=True):
                    w = words(text)
                    found, items = scanner.scan(w)
                    found, names = _merge(old + found) if old else found, sorted({*old_items, *map(str, items)})
                    if not final:
                        rows.append((doc_id, text, found, names))
                        continue
                    n = sum(z - a for a, z in found)
                    rows.append((doc_id, len(w), n, len(names), hashlib.sha256(",".join(names).encode()).hexdigest(), n > 0, names, original_spans(text, found) if found else []))
                if rows:
                    yield batch_of(schema if final else mid_schema, *zip(*rows, strict=True))

        frame = frame.mapInArrow(run, out if final else mid)
        if not final:
            frame = cut(frame)
    return frame


def clean(docs: DataFrame, benchmark: DataFrame, size: int = SIZE, most_bytes: int = MOST_BYTES, text_col: str = "text") -> DataFrame:
    """The rows of docs that hold no window of benchmark, all columns, unshuffled: one filtering pass per automaton."""
    for part in _parts(benchmark, "item_id", "text", most_bytes):
        given = docs.sparkSession.sparkContext.broadcast([(r["item"], r["text"]) for r in part.collect()])

        def run(batches, given=given):
            if given.value is not _scanners.get("of"):
                _scanners.update(of=given.value, scanner=Scanner(given.value, size))
            for b in small(batches):
                yield b.filter(pa.array([not _scanners["scanner"].scan(words(x))[0] for x in texts(b, text_col)], pa.bool_()))

        docs = docs.mapInArrow(run, docs.schema)
    return docs


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")).drop("items", "spans")


SQL = r"""
WITH d AS (
    SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
b AS (
    SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
bw AS (
    SELECT DISTINCT item_id, least(len(w), 10) AS k, array_to_string(w[i : i + least(len(w), 10) - 1], ' ') AS win
    FROM (SELECT item_id, w, unnest(range(1, len(w) - least(len(w), 10) + 2)) AS i FROM b WHERE len(w) > 0)),
ks AS (SELECT DISTINCT k FROM bw),
dw AS (
    SELECT doc_id, i, k, array_to_string(w[i : i + k - 1], ' ') AS win
    FROM (SELECT doc_id, w, k, unnest(range(1, len(w) - k + 2)) AS i FROM d, ks WHERE len(w) >= k)),
hit AS (SELECT doc_id, i, dw.k, item_id FROM dw JOIN bw ON dw.win = bw.win AND dw.k = bw.k),
n AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + k)) AS p FROM hit) GROUP BY doc_id),
its AS (SELECT doc_id, count(*) AS n_items, string_agg(s, ',' ORDER BY s) AS names FROM (SELECT DISTINCT doc_id, item_id::VARCHAR AS s FROM hit) GROUP BY doc_id)
SELECT d.doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
       sha256(coalesce(names, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN n ON d.doc_id = n.doc_id LEFT JOIN its ON d.doc_id = its.doc_id
"""
