import functools
import json
import zlib

import numpy as np
import pytest
from hypothesis import given as sample
from hypothesis import settings
from hypothesis import strategies as st

from predmap.llm import packing, pieces, token_counts, token_files, transducer
from predmap.llm.common import scratch

from .helpers import awkward, empty, frame, given


@functools.cache
def tokenizer(name):
    from tokenizers import Tokenizer

    return Tokenizer.from_file(pieces.path(name))


def library(name, texts):
    t = tokenizer(name)
    return [t.encode(x or "", add_special_tokens=False).ids for x in texts]


@pytest.mark.parametrize(("name", "kind"), [("byte_bpe_50k.json", "byte"), ("word_bpe_49k.json", "word")])
def test_ids_are_the_library_s(name, kind):
    texts = [r[1] for r in awkward()] + [r["text"] for r in given()] + ["a  b\n\nc \n d\t\te ", "don't  I'LL's", "  lead", "x  y z", "ﬁ İ ß Ὀδυσσεύς ΣΑΣ é a ́b", "٣٤ ½ ² 12345 -- ... !?"]
    enc = pieces.encoder(pieces.path(name))
    assert enc.kind == kind
    for text, want in zip(texts, library(name, texts), strict=True):
        assert enc.ids(text or "").tolist() == want


@settings(max_examples=300, deadline=None)
@sample(st.text(alphabet=st.one_of(st.characters(exclude_categories=["Cs"]), st.sampled_from(" \n\t 'sabcé12.,\x1c\x85 "))))
def test_ids_of_any_text(text):
    for name in ("byte_bpe_50k.json", "word_bpe_49k.json"):
        assert pieces.encoder(pieces.path(name)).ids(text).tolist() == library(name, [text])[0]


@pytest.mark.parametrize("change", [lambda d: d.update(normalizer={"type": "Lowercase"}), lambda d: d["pre_tokenizer"].update(use_regex=False)])
def test_other_vocabularies_go_to_the_library(tmp_path, change):
    with open(pieces.path("byte_bpe_50k.json"), encoding="utf-8") as f:
        spec = json.load(f)
    change(spec)
    file = tmp_path / "other.json"
    file.write_text(json.dumps(spec))
    enc = pieces.encoder(str(file))
    assert enc.kind == ""
    for text in ("Don't  PANIC, it's 1234 \n\n x", "Ünï  Çö"):
        want = enc.tokenizer.encode(text, add_special_tokens=False).ids
        assert enc.ids(text).tolist() == want
        assert transducer.Counter(str(file)).counts([text]) == [len(want)]


def test_wide_ids(tmp_path):
    with open(pieces.path("byte_bpe_50k.json"), encoding="utf-8") as f:
        spec = json.load(f)
    spec["model"]["vocab"]["the"] = 70_000
    file = tmp_path / "wide.json"
    file.write_text(json.dumps(spec))
    enc = pieces.encoder(str(file))
    assert enc.dtype == "<u4"
    assert 70_000 in enc.ids("the end").tolist()


COUNTER = transducer.Counter(pieces.path("word_bpe_49k.json"))
ODD = [
    "", "'s", "''s", "don't 'tis 're we've'll", "a'!'s 's's", "x" * 5000, "ab" * 9000, "<|endoftext|> x<|startoftext|>y <|endoftext|><", "a\x1cb \x85 c d", "é é Σας ΑΣ İstanbul ǅ ½ ² ① 中文字 😀😀",
    "12345 3.14,,, !!!''", "İ'S 'LL ’s", "ab̀c ﻿ 　 x", "ſ K Å ﬁ",
]


def test_transducer_counts_are_the_library_s():
    assert COUNTER.fst is not None
    texts = ODD + [r["text"] or "" for r in given()] + [r[1] or "" for r in awkward()]
    want = [len(x) for x in library("word_bpe_49k.json", texts)]
    assert COUNTER.counts(texts) == want
    assert COUNTER.counts(texts, 700) == want


@settings(max_examples=200, deadline=None)
@sample(st.lists(st.text(alphabet=st.one_of(st.characters(exclude_categories=["Cs"]), st.sampled_from("abcdeinst 'sABé1.,\n"))), max_size=4))
def test_transducer_counts_of_any_text(texts):
    assert COUNTER.counts(texts) == [len(x) for x in library("word_bpe_49k.json", texts)]


@settings(max_examples=100, deadline=None)
@sample(st.text(alphabet=" abet\né1."), st.integers(1, 9))
def test_chunks_compose(text, lanes):
    """Wherever a stream is cut, the maps compose to the same arcs; what they emit up to a piece's end are the library's counts."""
    symbols, place = COUNTER.symbols(COUNTER.normal(text))
    out = COUNTER.fst.run(symbols, lanes)
    assert out.tolist() == COUNTER.fst.walk(0, symbols)[1].tolist()
    raw = COUNTER.normal(text).encode()
    for k in np.flatnonzero(symbols >= 256).tolist():
        assert out[: k + 1].sum() == len(library("word_bpe_49k.json", [raw[: place[k] + 1].decode()])[0])


def test_states_are_forgotten(monkeypatch):
    monkeypatch.setattr(transducer, "MOST_STATES", 5)
    texts = [r["text"] or "" for r in given()][:60]
    fst = transducer.Counter(pieces.path("word_bpe_49k.json"))
    assert [fst.counts([x])[0] for x in texts] == [len(x) for x in library("word_bpe_49k.json", texts)]


def test_counts(spark):
    rows = awkward()
    got = {r["doc_id"]: (r["n_bytes"], r["n_tokens"], r["over_limit"]) for r in token_counts.count_tokens(frame(spark, rows), pieces.path("word_bpe_49k.json")).collect()}
    want = {r[0]: (len((r[1] or "").encode()), len(i), len(i) > 2048) for r, i in zip(rows, library("word_bpe_49k.json", [r[1] for r in rows]), strict=True)}
    assert got == want
    assert token_counts.count_tokens(empty(spark), pieces.path("word_bpe_49k.json")).count() == 0


@settings(max_examples=200, deadline=None)
@sample(st.lists(st.one_of(st.integers(0, 3), st.integers(0, 70000), st.integers(0, (1 << 64) - 1), st.integers((1 << 60) - 2, (1 << 60) + 2))))
def test_words_round_trip(ids):
    assert token_files.decode(token_files.encode(np.array(ids, np.uint64))).tolist() == ids


def test_words_are_tight():
    assert len(token_files.encode(np.ones(600, np.uint16))) == 80
    assert len(token_files.encode(np.full(400, 30000, np.uint16))) == 800


def test_files(spark):
    rows = awkward()
    path = scratch(spark, "t")
    token_files.write(frame(spark, rows), path, pieces.path("word_bpe_49k.json"))
    got = {r["doc_id"]: tuple(r)[1:] for r in token_files.read(spark, path).collect()}
    start, want = 0, {}
    for r, i in zip(rows, library("word_bpe_49k.json", [r[1] for r in rows]), strict=True):
        ids = np.array([*i, 1], "<u4")
        want[r[0]] = start, len(ids), zlib.crc32(ids)
        start += len(ids)
    assert got == want
    path = scratch(spark, "t")
    token_files.write(empty(spark), path, pieces.path("word_bpe_49k.json"))
    assert token_files.read(spark, path).count() == 0


def check_pieces(rows, got, vocabulary="byte_bpe_50k.json"):
    ids = {r[0]: np.array([*i, 0], "<u4") for r, i in zip(rows, library(vocabulary, [r[1] for r in rows]), strict=True)}
    at, where = {}, {}
    for p in sorted(got, key=lambda p: (p["doc_id"], p["start"])):
        assert p["start"] == at.get(p["doc_id"], 0)
        assert p["doc_tokens"] == len(ids[p["doc_id"]])
        assert p["ids_crc32"] == zlib.crc32(ids[p["doc_id"]][p["start"] : p["start"] + p["length"]])
        at[p["doc_id"]] = p["start"] + p["length"]
    assert at == {k: len(v) for k, v in ids.items()}
    for p in sorted(got, key=lambda p: (p["sequence_id"], p["offset"])):
        assert p["offset"] == where.get(p["sequence_id"], 0)
        where[p["sequence_id"]] = p["offset"] + p["length"]
    assert max(where.values(), default=0) <= 1024
    return where


def test_packing(spark):
    rows = awkward()
    check_pieces(rows, packing.pack(frame(spark, rows), pieces.path("byte_bpe_50k.json")).collect())
    assert packing.pack(empty(spark), pieces.path("byte_bpe_50k.json")).count() == 0
    rows = [(r["doc_id"], r["text"]) for r in given()]
    lengths = check_pieces(rows, packing.query(spark, "/root/testdata/sf0.001").collect())
    assert sum(packing.padding(n) for n in lengths.values()) < 0.03 * sum(lengths.values())


def test_blocks_carry_on(monkeypatch):
    monkeypatch.setattr(packing, "BLOCK", 3000)
    ends = np.zeros(1 << 16, bool)
    ends[7] = True
    rng, packer, out, docs = np.random.default_rng(1), packing.Packer(ends, 1024, 0), [], {}
    for i, n in enumerate([1, 5000, 20, 9000, 1, 1, 700, 2500, 3000]):
        docs[i] = rng.integers(0, 12, n).astype("<u2")
        for x in packer.add(i, docs[i]):
            out += x
    while x := packer.flush(True):
        out += x
    at = dict.fromkeys(docs, 0)
    for doc, start, length, crc, n, _, _ in out:
        assert (start, n) == (at[doc], len(docs[doc]))
        assert crc == zlib.crc32(docs[doc][start : start + length].astype("<u4"))
        at[doc] += length
    assert at == {k: len(v) for k, v in docs.items()}


@settings(max_examples=60, deadline=None)
@sample(st.lists(st.tuples(st.integers(1, 40), st.sampled_from([0, 8, 256])), min_size=1, max_size=9))
def test_cuts_are_the_best(gaps):
    size, pos = 32, [0]  # a penalty per sequence makes short ones dear, and powers of two are free
    for g, _ in gaps:
        pos.append(pos[-1] + min(g, size))
    pen = [0] + [p for _, p in gaps]

    def cost(cuts):
        total, last = 0, 0
        for j in cuts:
            n = pos[j] - pos[last]
            if n > size:
                return float("inf")
            total += (0 if n & (n - 1) == 0 else size - n) + packing.PER_SEQUENCE + pen[j]
            last = j
        return total

    n = len(pos) - 1
    every = ([*(j for j in range(1, n) if mask >> j & 1), n] for mask in range(0, 1 << n, 2))
    assert cost(packing.best_cuts(pos, pen, size)) == min(map(cost, every))
