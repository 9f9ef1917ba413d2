import hashlib
import re
from collections import defaultdict

from predmap.llm import exact_dedup

from .helpers import awkward, empty, frame, given


def brute(rows):
    groups = defaultdict(list)
    for r in rows:
        groups[re.sub("[ \t\n\x0b\x0c\r]+", " ", r[1] or "")].append(r[0])
    return {i: (min(g), len(g), i == min(g), hashlib.sha256(t.encode()).hexdigest()) for t, g in groups.items() for i in g}


def test_label_and_dedup(spark):
    rows = awkward()
    want = brute(rows)
    got = {r[0]: tuple(r[1:]) for r in exact_dedup.label(frame(spark, rows)).collect()}
    assert got == want
    kept = exact_dedup.dedup(frame(spark, rows))
    assert kept.columns == frame(spark, rows).columns
    assert sorted(r["doc_id"] for r in kept.collect()) == sorted(i for i, w in want.items() if w[2])


def test_given_rows(spark):
    rows = [(r["doc_id"], r["text"]) for r in given()]
    got = {r[0]: tuple(r[1:]) for r in exact_dedup.query(spark, "/root/testdata/sf0.001").collect()}
    assert got == brute(rows)


def test_repeated_null_and_empty(spark):
    one = [(1, "x", None, None, None, None, None, None)] * 2 + [(None, "x", None, None, None, None, None, None), (None, "y", None, None, None, None, None, None)]
    got = sorted(map(tuple, exact_dedup.label(frame(spark, one)).select("doc_id", "keep_id", "group_size", "kept").collect()), key=str)
    assert got == sorted([(1, 1, 3, True), (1, 1, 3, True), (None, 1, 3, False), (None, None, 1, True)], key=str)
    assert exact_dedup.label(empty(spark)).count() == 0
    assert exact_dedup.dedup(empty(spark)).count() == 0
