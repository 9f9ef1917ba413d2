"""Personal data: patterns, and information-theoretic sanitisation of the terms that give the found entities away.

Pattern matches are the protected entities. Over the whole corpus, with document frequencies n, a term (a word of three letters or
more) discloses of an entity the share

    PMI(term; entity) / IC(entity) = log2(n(term, entity) N / (n(term) n(entity))) / log2(N / n(entity)),

where n(term, entity) counts whole documents that hold both. Terms at ``THRESHOLD`` or more, seen with the entity in at least
``SUPPORT`` different texts (so copies of one text alone flag nothing), are spans of kind ``term`` wherever they stand in a document
that holds the entity. ``sanitise`` replaces entities by their kind and generalises or removes such terms.

How it stays small: only texts with an entity that several texts hold are looked at for terms. Terms that stand in the same such
texts are one class, and so are entities; co-occurrence is counted between classes, and only where n(term) may be at most
N^(1 - threshold) n(entity)^threshold, which the threshold implies. So a text that holds many entities and terms makes no square of
pairs of them. For this n(term) is first taken to be what these texts alone hold, which is never too much, so the share is never too
small. Terms that reach the threshold with it are counted in a sixteenth of the rows, which again is never too much, and those left
after that in all rows: n(term) itself. Both passes add up in the tasks; a Bloom filter of fixed size keeps other terms out, and the
exact join that follows makes its size change the work only.

Defined results: null and empty texts have no spans; rows that repeat an id, or have none, are treated each; a very long text is read
whole; an empty table gives no rows; other columns are not read; spans of different kinds may overlap, but no term overlaps a match.
"""

from __future__ import annotations

import hashlib
import re
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from predmap.llm.common import batch_of, cut, small, table, texts

NAME = "op7_personal_data"
SQL = None  # tests compare with a direct scan
THRESHOLD, SUPPORT, BLOOM_BITS, PROBES, PART = 0.9, 2, 1 << 22, 3, 16
KINDS = ("email", "ip", "card", "phone")
#: The patterns of the contract. Digits before an address or number would start the match earlier.
DOMAIN = re.compile(r"@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
IP = re.compile(r"(?<![0-9])[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")
CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
WORD = re.compile(r"[^\W\d_]{3,}")


def luhn(digits: str) -> bool:
    odd = sum(map(int, digits[-1::-2]))
    return (odd + sum(sum(divmod(2 * int(d), 10)) for d in digits[-2::-2])) % 10 == 0


def emails(text: str) -> list[tuple[int, int]]:
    """The local part is the whole run before an @ that no earlier match has taken, so each @ is tried once."""
    out, free, at = [], 0, text.find("@")
    while at >= 0:
        start = at
        while start > free and text[start - 1] in LOCAL:
            start -= 1
        if start < at and (m := DOMAIN.match(text, at)):
            out.append((start, m.end()))
            free = m.end()
        else:
            free = max(free, at + 1)
        at = text.find("@", max(at + 1, free))
    return out


def find(text: str) -> list[tuple[int, int, str]]:
    """(start, end, kind) by start, then kind as listed."""
    out = [(a, b, "email") for a, b in emails(text)] if "@" in text else []
    for m in IP.finditer(text):
        if all(len(p.lstrip("0")) <= 3 and int(p[-4:]) <= 255 for p in m[0].split(".")):
            out.append((m.start(), m.end(), "ip"))
    for m in CARD.finditer(text):
        if 14 <= m.end() - m.start() <= 40 and 14 <= len(d := re.sub("[^0-9]", "", m[0])) <= 19 and luhn(d):
            out.append((m.start(), m.end(), "card"))
    if "+" in text:
        for m in PHONE.finditer(text):
            if 10 <= len(re.sub("[^0-9]", "", m[0])) <= 15:
                out.append((m.start(), m.end(), "phone"))
    return sorted(out, key=lambda s: (s[0], KINDS.index(s[2])))


def terms_of(text: str, spans: list[tuple[int, int]]) -> list[tuple[str, int, int]]:
    """(term, start, end) of the words of text that overlap none of spans (by start)."""
    out, k, reach = [], 0, 0
    for m in WORD.finditer(text):
        while k < len(spans) and spans[k][0] < m.end():
            reach = max(reach, spans[k][1])
            k += 1
        if reach <= m.start():
            out.append((m[0].lower(), m.start(), m.end()))
    return out


def _hash(text: str) -> int:
    return int.from_bytes(hashlib.blake2b(text.encode("utf-8", "surrogatepass"), digest_size=8).digest(), "little") >> 1


def joined(spans) -> str:
    return ",".join(f"{kind}:{a}:{b}" for a, b, kind in spans)


def split(base: str) -> list[tuple[int, int]]:
    """[start, end) of joined spans."""
    return [(int(x[1]), int(x[2])) for x in (y.split(":") for y in base.split(",") if y)]


FOUND = "uid long, doc_id long, n_email long, n_ip long, n_card long, n_phone long, base string, entities array<long>, content long, held string"


def detect(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: uid (of the row), doc_id, counts by kind, base (spans joined) and, where there are any, the entities' and the text's
    63-bit hashes and the text."""
    schema = pa.schema([("uid", pa.int64()), ("doc_id", pa.int64()), *[(f"n_{k}", pa.int64()) for k in KINDS], ("base", pa.string()), ("entities", pa.list_(pa.int64())), ("content", pa.int64()), ("held", pa.string())])

    def run(batches):
        uid = TaskContext.get().partitionId() << 36
        for b in small(batches):
            text = texts(b)
            spans = [find(x) for x in text]
            kinds = [Counter(k for _, _, k in s) for s in spans]
            entities = [sorted({_hash(k + x[a:z]) for a, z, k in s}) for x, s in zip(text, spans, strict=True)]
            content = [_hash(x) if s else None for x, s in zip(text, spans, strict=True)]
            held = [x if s else None for x, s in zip(text, spans, strict=True)]
            yield batch_of(schema, np.arange(uid, uid + b.num_rows), b.column("doc_id"), *[[c[k] for c in kinds] for k in KINDS], [joined(s) for s in spans], entities, content, held)
            uid += b.num_rows

    return docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text")).mapInArrow(run, FOUND)


def _places(term: str, bits: int = BLOOM_BITS) -> list[int]:
    h = _hash(term)
    return [(h >> 20 * k) % bits for k in range(PROBES)]


def bloom(terms: DataFrame) -> np.ndarray:
    """Bit array of fixed size over terms.term: its words are or-ed where the terms are."""
    schema = pa.schema([("word", pa.int32()), ("bits", pa.int64())])

    def run(batches):
        held = np.zeros(BLOOM_BITS // 32, np.int64)
        for b in batches:
            for t in b.column("term").to_pylist():
                for p in _places(t):
                    held[p >> 5] |= 1 << (p & 31)
        some = np.flatnonzero(held)
        if len(some):
            yield batch_of(schema, some.astype(np.int32), held[some])

    out = np.zeros(BLOOM_BITS // 32, np.int64)
    for r in terms.select("term").mapInArrow(run, "word int, bits long").groupBy("word").agg(F.bit_or("bits").alias("bits")).toLocalIterator():
        out[r["word"]] = r["bits"]
    return out


def term_frequencies(docs: DataFrame, wanted: DataFrame, text_col: str = "text") -> DataFrame:
    """(term, n_term): in how many rows of docs each of wanted.term occurs. The tasks' counts are added up before the join, which so gets a
    term once, and not once from every task; a semi-join could be moved below the sum again."""
    given = docs.sparkSession.sparkContext.broadcast(bloom(wanted))
    schema = pa.schema([("term", pa.string()), ("n", pa.int64())])

    def run(batches):
        bits, known, held = given.value, {}, Counter()
        for b in small(batches):
            for text in texts(b):
                for w in {x.lower() for x in WORD.findall(text)}:
                    if w not in known:
                        if len(known) > 300_000:
                            known.clear()
                        known[w] = all(bits[p >> 5] >> (p & 31) & 1 for p in _places(w))
                    if known[w]:
                        held[w] += 1
            if len(held) > 100_000:
                yield batch_of(schema, list(held), list(held.values()))
                held.clear()
        if held:
            yield batch_of(schema, list(held), list(held.values()))

    counts = docs.select(docs[text_col].alias("text")).mapInArrow(run, "term string, n long")
    return counts.groupBy("term").agg(F.sum("n").alias("n_term")).join(wanted.select("term").distinct(), "term")


def text_terms(rows: DataFrame) -> DataFrame:
    """(content, n, term) for the distinct terms of rows (content, n, base, held)."""
    schema = pa.schema([("content", pa.int64()), ("n", pa.int64()), ("term", pa.string())])

    def run(batches):
        for b in small(batches, 100):
            for r in b.to_pylist():
                found = sorted({t for t, _, _ in terms_of(r["held"], split(r["base"]))})
                if found:
                    yield batch_of(schema, [r["content"]] * len(found), [r["n"]] * len(found), found)

    return rows.select("content", "n", "base", "held").mapInArrow(run, "content long, n long, term string")


def disclosing(docs: DataFrame, found: DataFrame, threshold: float = THRESHOLD, support: int = SUPPORT, text_col: str = "text") -> DataFrame | None:
    """(content, terms): the terms to mark in the texts with that hash; None if no entity has the support."""
    total = float(found.count())
    own = found.filter("content IS NOT NULL")
    spread = own.select("content", F.explode("entities").alias("entity")).groupBy("entity", "content").agg(F.count(F.lit(1)).alias("n"))
    same = F.bit_xor(F.xxhash64("content"))  # alike for those that the same texts hold
    entities = spread.groupBy("entity").agg(F.sum("n").alias("n_entity"), F.count(F.lit(1)).alias("texts"), same.alias("same")).filter(F.col("texts") >= support)
    entities = entities.select("entity", "n_entity", F.xxhash64("n_entity", "texts", "same").alias("entity_class"))
    held = cut(spread.join(entities, "entity").select("content", "entity_class", "n_entity").distinct())
    if held.isEmpty():
        return None
    some = own.join(held.select("content").distinct(), "content", "left_semi")
    reps = some.groupBy("content").agg(F.count(F.lit(1)).alias("n"), F.min("uid").alias("uid"))
    terms = cut(text_terms(some.select("uid", "base", "held").join(reps, "uid")))
    several = terms.groupBy("term").agg(F.count(F.lit(1)).alias("texts"), F.sum("n").alias("n_least"), same.alias("same")).filter(F.col("texts") >= support)
    placed = cut(terms.join(several.select("term", "n_least", F.xxhash64("texts", "same").alias("term_class")), "term"))
    most = F.pow(F.lit(total), F.lit(1 - threshold)) * F.pow(F.col("n_entity").cast("double"), F.lit(threshold))
    share = lambda n: F.log2(F.col("n_both") * total / (F.col(n) * F.col("n_entity"))) / F.greatest(F.log2(total / F.col("n_entity")), F.lit(1e-9))
    met = placed.select("content", "n", "term_class", "n_least").distinct().join(held, "content").filter(F.col("n_least") <= most * (1 + 1e-9))
    pairs = met.groupBy("term_class", "entity_class", "n_least", "n_entity").agg(F.count(F.lit(1)).alias("texts"), F.sum("n").alias("n_both")).filter(F.col("texts") >= support)
    pairs = cut(pairs.filter(share("n_least") >= threshold - 1e-9))
    wanted = cut(placed.join(pairs.select("term_class").distinct(), "term_class", "left_semi").select("term", "term_class").distinct())
    room = pairs.groupBy("term_class").agg(F.max(F.col("n_both") * F.pow(total / F.col("n_entity"), F.lit(1 - threshold))).alias("room"))
    part = docs.filter(F.pmod(F.xxhash64(F.col(text_col)), F.lit(PART)) == 0)
    seen = term_frequencies(part, wanted, text_col).withColumnRenamed("n_term", "seen")
    wanted = cut(wanted.join(room, "term_class").join(seen, "term", "left").filter(F.coalesce("seen", F.lit(0)) <= F.col("room") * (1 + 1e-6)).select("term", "term_class"))
    n_term = cut(wanted.join(term_frequencies(docs, wanted, text_col), "term"))
    classes = n_term.select("term_class", "n_term").distinct()
    pairs = pairs.join(classes, "term_class").filter(share("n_term") >= threshold - 1e-12).select("term_class", "n_term", "entity_class")
    placed = placed.select("content", "term").join(n_term, "term")
    marks = held.join(pairs, "entity_class").select("content", "term_class", "n_term").distinct()
    return placed.join(marks, ["content", "term_class", "n_term"]).groupBy("content").agg(F.collect_set("term").alias("terms"))


AT = "array<struct<start:int,end:int>>"
SCANNED = f"doc_id long, n_email long, n_ip long, n_card long, n_phone long, base string, terms {AT}"


def scan(docs: DataFrame, threshold: float = THRESHOLD, support: int = SUPPORT, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row of docs: doc_id, counts, base (string) and terms (array of struct<start, end>)."""
    found = cut(detect(docs, id_col, text_col))
    marks = disclosing(docs, found, threshold, support, text_col)
    counts = ["doc_id", *[f"n_{k}" for k in KINDS], "base"]
    if marks is None:
        return found.select(*counts, F.array().cast(AT).alias("terms"))
    schema = pa.schema([*[(c, pa.string() if c == "base" else pa.int64()) for c in counts], ("terms", pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32())])))])

    def place(batches):
        for b in small(batches, 100):
            at = []
            for text, base, marked in zip(b.column("held").to_pylist(), b.column("base").to_pylist(), b.column("marked").to_pylist(), strict=True):
                wanted = set(marked or ())
                at.append([{"start": a, "end": z} for t, a, z in terms_of(text, split(base)) if t in wanted] if wanted else [])
            yield batch_of(schema, *[b.column(c) for c in counts], at)

    own = found.filter("content IS NOT NULL").join(marks.withColumnRenamed("terms", "marked"), "content", "left")
    own = own.select(*counts, "held", "marked").mapInArrow(place, SCANNED)
    return found.filter("content IS NULL").select(*counts, F.array().cast(AT).alias("terms")).unionByName(own)


def redact(text: str, spans: str, terms: str = "generalise") -> str:
    """text with every span replaced by its kind in brackets; of overlapping spans the first counts, and the rest goes. Terms are
    generalised to what sort of word they are, or removed."""
    out, at = [], 0
    for x in spans.split(",") if spans else []:
        kind, a, b = x.split(":")
        if int(a) >= at:
            word = text[int(a) : int(b)]
            if kind == "term":
                kind = "" if terms == "remove" else "acronym" if word.isupper() else "name" if word[0].isupper() else "word"
            out += [text[at : int(a)], f"[{kind.upper()}]" if kind else ""]
        at = max(at, int(b))
    return "".join([*out, text[at:]])


def spans_column() -> Column:
    """All spans of scan()'s rows, joined by start, kinds as listed, terms last."""
    order = F.create_map(*[x for i, k in enumerate((*KINDS, "term")) for x in (F.lit(k), F.lit(i))])
    parts = F.transform(F.filter(F.split("base", ","), lambda x: x != ""), lambda x: F.struct(F.split(x, ":")[1].cast("int").alias("start"), order[F.split(x, ":")[0]].alias("k"), x.alias("s")))
    terms = F.transform("terms", lambda t: F.struct(t["start"].alias("start"), F.lit(len(KINDS)).alias("k"), F.concat_ws(":", F.lit("term"), t["start"].cast("string"), t["end"].cast("string")).alias("s")))
    return F.array_join(F.transform(F.array_sort(F.concat(parts, terms)), lambda x: x["s"]), ",")


def sanitise(docs: DataFrame, terms: str = "generalise", id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """The rows of docs, all columns, with entities and disclosing terms gone from the text. Only rows with spans are rewritten; ids must
    be distinct, as they carry the spans to the rows; rows with a null id or a null text are kept as they are."""
    spans = scan(docs, id_col=id_col, text_col=text_col, **options).select(F.col("doc_id").alias("_id"), spans_column().alias("_spans")).filter("_spans <> '' AND _id IS NOT NULL")
    names, at = docs.columns, docs.columns.index(text_col)

    def run(batches):
        for b in small(batches):
            new = [x if not s else redact(x, s, terms) for x, s in zip(b.column(at).to_pylist(), b.column(len(names)).to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(new, b.column(at).type) if i == at else b.column(i) for i in range(len(names))], names=names)

    return docs.join(spans, docs[id_col].cast("long") == spans["_id"], "left").select(*[docs[c] for c in names], "_spans").mapInArrow(run, docs.schema)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = scan(table(spark, sf_dir, "documents"))
    return found.select("doc_id", *[f"n_{k}" for k in KINDS], F.sha2(F.col("base").cast("binary"), 256).alias("base_sha256"), spans_column().alias("spans"))
