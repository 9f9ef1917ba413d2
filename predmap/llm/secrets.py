"""Secret scans through a trigram inverted index.

From each rule's regex a Boolean query over trigrams is derived: an OR of ANDs of trigrams that every match holds, letters folded
to lower case. An index of postings (document, trigram), restricted to trigrams that some query names, is built over the
documents; intersecting the postings gives each rule's candidates, and only those are verified by the regex. A rule that has
no mandatory trigrams is verified on every text.

DataFrame functions only. Postings are grouped by document, so no trigram, however frequent, is a hot key. Places are found
from the lengths of what lies between matches, in code points.

Defined results: null and empty texts have no spans; rows that repeat an id or have a null one are scanned each (rows whose
hashes collide share their postings, which can only add candidates, and candidates are verified); an empty table gives no rows; other columns
are not read; matches of different kinds may overlap.
"""

from __future__ import annotations

import re
from dataclasses import dataclass
from functools import reduce
from re import _constants as sre
from re import _parser as sre_parser

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from predmap.llm.common import table

NAME = "op1_secret_scan"
SQL = None  # tests compare with a direct scan
MOST_STRINGS, WORD, BLOCK = 256, 62, 128


def either_case(word: str) -> str:
    """word as a pattern for both cases of its letters."""
    return "".join(f"[{c.upper()}{c}]" if c.isalpha() else c for c in word)


@dataclass(frozen=True)
class Rule:
    """Matches of pattern whose group has at least least characters."""

    kind: str
    pattern: str
    group: int
    least: int
    base: bool = True


#: The rules of the contract, in its order, then those that the method adds.
ASSIGNED = "|".join(map(either_case, ("password", "passwd", "secret", "token"))) + "|" + either_case("api") + "_?" + either_case("key")
RULES = (
    Rule("assign", rf"""({ASSIGNED})["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 12),
    Rule("access", r"AKIA[A-Z0-9]+", 0, 18),
    Rule("hex", r"[0-9a-f]+", 0, 16),
    Rule("forge", r"gh[pousr]_[A-Za-z0-9]{36,}", 0, 40, False),
    Rule("chat", r"xox[abprs]-[A-Za-z0-9-]{20,}", 0, 25, False),
    Rule("cloud", r"AIza[A-Za-z0-9_-]{35,}", 0, 39, False),
    Rule("pem", r"-----BEGIN [A-Z ]*PRIVATE KEY-----", 0, 1, False),
)


def _strings(tree) -> list[str]:
    """Alternatives of a parsed regex as folded text; NUL stands for anything."""
    out = [""]
    for op, arg in tree:
        if op is sre.LITERAL:
            more = [chr(arg).lower()]
        elif op is sre.IN and all(o is sre.LITERAL or o is sre.RANGE and a[1] - a[0] < 8 for o, a in arg):
            more = sorted({chr(c).lower() for o, a in arg for c in ([a] if o is sre.LITERAL else range(a[0], a[1] + 1))})
            more = more if len(more) <= 8 else ["\0"]
        elif op is sre.SUBPATTERN:
            more = _strings(arg[3])
        elif op is sre.BRANCH:
            more = [s for x in arg[1] for s in _strings(x)]
        elif op in (sre.MAX_REPEAT, sre.MIN_REPEAT):
            low, high, sub = arg
            once = _strings(sub)
            more = ["", *once] if (low, high) == (0, 1) else ["\0"] if low == 0 else once if (low, high) == (1, 1) else [s + "\0" for s in once]
        else:
            more = ["\0"]
        out = [a + b for a in out for b in more] if len(out) * len(more) <= MOST_STRINGS else [a + "\0" for a in out]
    return sorted({*out})


def trigram_query(pattern: str) -> list[frozenset[str]] | None:
    """OR of ANDs of trigrams; None if some match need hold no trigram."""
    clauses = {frozenset(p[i : i + 3] for p in s.split("\0") for i in range(len(p) - 2)) for s in _strings(sre_parser.parse(pattern))}
    if frozenset() in clauses:
        return None
    return sorted((c for c in clauses if not any(o < c for o in clauses)), key=sorted)


def row_key(docs: DataFrame, id_col: str, text_col: str) -> Column:
    """What stands for a row in the index: a hash of id and text, so that rows which share an id, or have none, are no hot key."""
    return F.xxhash64(docs[id_col], docs[text_col])


def postings(docs: DataFrame, trigrams: list[str], id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The inverted index over the given trigrams: (doc, trigram number) for each row and trigram that it holds."""
    rows = docs.select(row_key(docs, id_col, text_col).alias("doc"), F.lower(docs[text_col]).alias("low"))
    return rows.select("doc", F.explode(F.array_compact(F.array(*[F.when(F.contains("low", F.lit(t)), F.lit(i)) for i, t in enumerate(trigrams)]))).alias("trigram"))


def candidates(docs: DataFrame, rules=RULES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc, rules): which rules' Boolean queries hold, as an array of kinds, for documents with any."""
    asked = {r.kind: q for r in rules if (q := trigram_query(r.pattern)) is not None}
    trigrams = sorted({t for q in asked.values() for c in q for t in c})
    number = {t: i for i, t in enumerate(trigrams)}
    words = range(-(-len(trigrams) // WORD))
    held = [F.bit_or(F.when(F.floor(F.col("trigram") / WORD) == w, F.pow(F.lit(2.0), F.col("trigram") - w * WORD).cast("long")).otherwise(F.lit(0).cast("long"))).alias(f"w{w}") for w in words]
    have = postings(docs, trigrams, id_col, text_col).groupBy("doc").agg(*held)

    def holds(clause: frozenset[str]) -> Column:
        masks = [sum(1 << number[t] - w * WORD for t in clause if number[t] // WORD == w) for w in words]
        return reduce(Column.__and__, [F.col(f"w{w}").bitwiseAND(F.lit(m)) == F.lit(m) for w, m in zip(words, masks, strict=True) if m])

    kinds = F.array_compact(F.array(*[F.when(reduce(Column.__or__, map(holds, q)), F.lit(kind)) for kind, q in asked.items()]))
    return have.select("doc", kinds.alias("rules")).filter(F.size("rules") > 0)


def spans_of(text: Column, rule: Rule, number: int) -> Column:
    """array<struct<start, number, end, kind>> of the rule's matches in text, leftmost and non-overlapping."""
    pattern = F.lit(_sized(rule))
    pairs = F.arrays_zip(F.split(text, pattern, -1).alias("gap"), F.regexp_extract_all(text, pattern, F.lit(0)).alias("hit"))
    none = F.array().cast("array<struct<start:int,number:int,end:int,kind:string>>")

    size = F.lit(0)

    def width(x: Column) -> Column:
        return F.length(x["gap"]) + F.coalesce(F.length(x["hit"]), size)

    def step(acc: Column, x: Column) -> Column:
        start = acc["at"] + F.length(x["gap"])
        end = start + F.coalesce(F.length(x["hit"]), size)
        good = x["hit"].isNotNull() if rule.group == 0 else F.length(F.regexp_extract(x["hit"], rule.pattern, rule.group)) >= rule.least
        one = F.array(F.struct(start.alias("start"), F.lit(number).alias("number"), end.alias("end"), F.lit(rule.kind).alias("kind")))
        return F.struct(end.alias("at"), F.when(good, F.concat(acc["out"], one)).otherwise(acc["out"]).alias("out"))

    # an array grows by copying, so a text's matches are placed block by block, each from where the blocks before it end
    def placed(p: Column) -> Column:
        blocks = F.transform(F.sequence(F.lit(0), F.floor((F.size(p) - 1) / BLOCK).cast("int")), lambda k: F.slice(p, k * BLOCK + 1, F.lit(BLOCK)))

        def ends(acc: Column, b: Column) -> Column:
            return F.concat(acc, F.array(F.element_at(acc, -1) + F.aggregate(b, F.lit(0), lambda n, x: n + width(x))))

        def block(b: Column, at: Column) -> Column:
            return F.aggregate(b, F.struct(at.alias("at"), none.alias("out")), step, lambda acc: acc["out"])

        return once(blocks, lambda bs: once(F.aggregate(bs, F.array(F.lit(0)), ends), lambda at: F.flatten(F.transform(bs, lambda b, k: block(b, F.get(at, k))))))

    return F.when(text.rlike(_sized(rule)), once(pairs, placed)).otherwise(none)


def once(value: Column, use) -> Column:
    """use(value), where value is worked out once however often use names it."""
    return F.get(F.transform(F.array(value), use), F.lit(0))


def _sized(rule: Rule) -> str:
    """The pattern with the least length in it, where a match takes a whole maximal run, so that failing ones cannot hide others."""
    if rule.group == 0 and re.fullmatch(r"[A-Za-z]*\[[^\]]+\]\+", rule.pattern):
        head = rule.pattern.index("[")
        return f"{rule.pattern[:-1]}{{{rule.least - head},}}"
    return rule.pattern


def scan(docs: DataFrame, rules=RULES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row of docs: doc_id and found, an array of struct<start, number, end, kind> by start, then rule."""
    found = candidates(docs, rules, id_col, text_col)
    rows = docs.select(docs[id_col].alias("doc_id"), F.coalesce(docs[text_col], F.lit("")).alias("text"), row_key(docs, id_col, text_col).alias("key"))
    rows = rows.join(found, rows["key"] == found["doc"], "left").select("doc_id", "text", "rules")
    lists = []
    for k, rule in enumerate(rules):
        spans = spans_of(F.col("text"), rule, k)
        none = F.array().cast("array<struct<start:int,number:int,end:int,kind:string>>")
        lists.append(spans if trigram_query(rule.pattern) is None else F.when(F.coalesce(F.array_contains("rules", rule.kind), F.lit(False)), spans).otherwise(none))
    return rows.select("doc_id", F.array_sort(F.concat(*lists)).alias("found"))


def joined(found: Column) -> Column:
    """kind:start:end, comma-joined."""
    return F.array_join(F.transform(found, lambda x: F.concat_ws(":", x["kind"], x["start"].cast("string"), x["end"].cast("string"))), ",")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = scan(table(spark, sf_dir, "documents"))
    base = [r.kind for r in RULES if r.base]

    def of(*kinds: str) -> Column:
        return F.filter("found", lambda x: x["kind"].isin(*kinds))

    counts = [F.size(of(kind)).cast("long").alias(f"n_{kind}") for kind in base]
    return found.select("doc_id", *counts, F.sha2(joined(of(*base)).cast("binary"), 256).alias("base_sha256"), joined(F.col("found")).alias("spans"))
