import hashlib
import itertools
import re
import zlib

import numpy as np
import pytest
import xxhash

import corpus_pipeline
from predmap.llm import decontaminate, langid, simhash
from predmap.llm.common import SPACES

from .helpers import SCHEMA, awkward, empty, frame, given
from .test_tokens import check_pieces


def lower(text):
    return re.sub("[A-Z]", lambda m: m[0].lower(), text)


def brute_fingerprint(text, k=3):
    w = [x for x in re.split(SPACES, lower(text)) if x]
    if not w:
        return 0
    shingles = [" ".join(w[i : i + k]) for i in range(max(1, len(w) - k + 1))]
    h = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def brute_components(rows, radius=2):
    root = {i: i for i, _ in rows}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for (a, x), (b, y) in itertools.combinations(rows, 2):
        if (x ^ y).bit_count() <= radius:
            p, q = find(a), find(b)
            root[max(p, q)] = min(p, q)
    return {i: find(i) for i in root}


def test_fingerprints():
    for r in awkward() + [(0, x["text"]) for x in given()]:
        assert simhash.fingerprint(r[1] or "") == brute_fingerprint(r[1] or "")


def test_simhash(spark):
    rows = [(r[0], r[1] or "") for r in awkward()] + [(1000 + r["doc_id"], r["text"]) for r in given()]
    fp = [(i, brute_fingerprint(t)) for i, t in rows]
    want = brute_components(fp)
    got = {r["doc_id"]: (r["fp"] & (1 << 64) - 1, r["component_id"]) for r in simhash.near_duplicates(frame(spark, [(*r, *[None] * 6) for r in rows])).collect()}
    assert got == {i: (f, want[i]) for i, f in fp}
    assert simhash.near_duplicates(empty(spark)).count() == 0
    assert simhash.dedup(empty(spark)).count() == 0


@pytest.mark.parametrize("hot", [50_000, 100])
def test_links_of_planted_fingerprints(spark, monkeypatch, hot):
    """With hot at 100 the many fingerprints that share their low half are dealt anew by the other bits."""
    monkeypatch.setattr(simhash, "HOT", hot)
    rng = np.random.default_rng(hot)
    fps = {int(x) for x in rng.integers(0, 1 << 63, 40)} | {int(x) << 32 | 77 for x in rng.integers(0, 1 << 31, 300)}
    for x in list(fps)[:20]:
        for _ in range(4):
            for b in rng.integers(0, 64, rng.integers(1, 4)):
                x ^= 1 << int(b)
            fps.add(x)
    rows = list(enumerate(sorted(fps)))
    df = spark.createDataFrame([(i, x - (1 << 64) if x >> 63 else x) for i, x in rows], "low long, fp long")
    got = {r["node"]: r["root"] for r in simhash.components(simhash.links(df)).collect()}
    want = brute_components(rows)
    assert {i: got.get(i, i) for i, _ in rows} == want
    assert len({*want.values()}) < len(rows)


def test_bk_tree():
    rng = np.random.default_rng(0)
    members = [int(x) for x in {*rng.integers(0, 1 << 12, 300).tolist()}]
    tree = simhash.BKTree(members)
    for x in rng.integers(0, 1 << 12, 50).tolist():
        for radius in (0, 2, 4):
            assert sorted(tree.within(x, radius)) == [i for i, y in enumerate(members) if (x ^ y).bit_count() <= radius]


@pytest.mark.parametrize("task_rows", [8, 1 << 17])
def test_chain_is_one_component(spark, monkeypatch, task_rows):
    """With 8 edges a task the rounds run over the table; else one task does it all."""
    monkeypatch.setattr(simhash, "TASK_ROWS", task_rows)
    edges = spark.createDataFrame([(i + 1, i) for i in range(60)] + [(100, 90)], "a long, b long")
    got = {r["node"]: r["root"] for r in simhash.components(edges).collect()}
    assert got == {**dict.fromkeys(range(61), 0), 100: 90, 90: 90}


@pytest.mark.parametrize("task_rows", [20, 1 << 17])
def test_components_of_random_edges(spark, monkeypatch, task_rows):
    """20 leaves rounds over the table first and one task for what they leave."""
    monkeypatch.setattr(simhash, "TASK_ROWS", task_rows)
    pairs = np.random.default_rng(5).integers(0, 150, (110, 2)).tolist()
    least = {x: x for p in pairs if p[0] != p[1] for x in p}
    for _ in least:
        for a, b in pairs:
            if a != b:
                least[a] = least[b] = min(least[a], least[b])
    got = simhash.components(spark.createDataFrame(pairs, "a long, b long")).collect()
    assert len(got) == len(least) and {r["node"]: r["root"] for r in got} == least


def brute_decontaminate(text, items, size=10):
    find = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", lower(t or ""))
    w, hit, names = find(text), set(), set()
    for item, t in items:
        x = find(t)
        k = min(size, len(x))
        wins = {tuple(x[i : i + k]) for i in range(len(x) - k + 1)} if k else set()
        for i in range(len(w) - k + 1):
            if tuple(w[i : i + k]) in wins:
                hit |= {*range(i, i + k)}
                names.add(str(item))
    return len(w), len(hit), len(names), hashlib.sha256(",".join(sorted(names)).encode()).hexdigest(), bool(hit)


ITEMS = [(1, "one two three four five six seven eight nine ten eleven"), (2, "Alpha—beta gamma"), (3, None), (4, "..."), (10, "x1"), (11, "two three four five six seven eight nine ten eleven twelve")]


@pytest.mark.parametrize("most", [8 << 20, 30])
def test_decontaminate(spark, most):
    items = spark.createDataFrame(ITEMS, "item_id long, text string")
    rows = [r[:2] for r in awkward()] + [(90, "ONE, two;three four-five\nsix seven eight nine ten! eleven twelve"), (91, "so alpha—beta gamma x1 é"), (92, "two three four five six seven eight nine ten")]
    df = frame(spark, [(*r, *[None] * 6) for r in rows])
    out = decontaminate.scan(df, items, most_bytes=most).collect()
    got = {r["doc_id"]: (r["n_words"], r["n_hit"], r["n_items"], r["items_sha256"], r["contaminated"]) for r in out}
    assert got == {i: brute_decontaminate(t, ITEMS) for i, t in rows}
    spans = {r["doc_id"]: [dict(rows)[r["doc_id"]][a:b] for a, b in r["spans"]] for r in out}
    assert spans[90] == [rows[-3][1]] and spans[91] == ["alpha—beta gamma x1"]
    clean = decontaminate.clean(df, items, most_bytes=most)
    assert clean.columns == df.columns
    assert sorted(r["doc_id"] for r in clean.collect()) == sorted(i for i, v in got.items() if not v[4])
    assert decontaminate.scan(empty(spark), items).count() == 0
    assert decontaminate.scan(df, items.limit(0)).filter("contaminated").count() == 0


def test_language(spark):
    rows = {r["doc_id"]: r for r in given(sf="/root/testdata/sf0.01")}
    got = langid.query(spark, "/root/testdata/sf0.01").collect()
    assert len(got) == len(rows)
    for r in got:
        assert r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0)
        assert 0 <= r["score"] <= 1
        assert (r["lang_pred"] == "und") == (not any(c.isalpha() for c in rows[r["doc_id"]]["text"]))
    right = [r["lang_pred"] == rows[r["doc_id"]]["lang"] for r in got if r["held_out"]]
    assert np.mean(right) > 0.97


def test_language_edges(spark):
    model = langid.fit([("the cat and the dog " * 5, "en"), ("der hund und die katze " * 5, "de")] * 20)
    assert model.predict([None, "", "12 34 --", "the dog", "die katze " * 200_000])[0] == ["und", "und", "und", "en", "de"]
    one, many = model.predict(["the dog and"] * 3)[1], model.predict(["x", "the dog and", None, "y z"])[1]
    assert one[0] == pytest.approx(many[1])
    assert langid.fit([]).predict(["abc"]) [0] == ["und"]
    df = frame(spark)
    assert sorted(r["doc_id"] for r in langid.identify(df, model).collect()) == sorted(r[0] for r in awkward())
    kept = langid.accept(df, model)
    assert kept.schema == df.schema
    assert langid.accept(empty(spark), model).count() == 0
    assert langid.identify(empty(spark), langid.train(empty(spark))).count() == 0


def test_digits_and_fractions_are_no_letters():
    model = langid.fit([("der die das und nicht", "de"), ("the and of with not", "en")] * 20)
    lang, score, rejected = model.predict(["½ ² ٣ 12 ①", "2½", None, "", "the ½"])
    assert lang[:4] == ["und"] * 4 and score[:4].tolist() == [0] * 4 and all(rejected[:4])
    assert lang[4] != "und"


def test_language_trains_on_few_labels(spark, monkeypatch):
    """The share that is read follows from the rows that can be used, not from all rows."""
    rows = [(i, f"text {i}", "en" if i % 10 == 0 else None, *[None] * 5) for i in range(3000)]
    df, got = frame(spark, rows), []
    monkeypatch.setattr(langid, "fit", len)
    usable = sum(i % 10 == 0 and zlib.crc32(str(i).encode()) % 5 != 0 for i in range(3000))
    for most in (20, 100, 200, 500):
        got.append(langid.train(df, sample_rows=most))
    assert got == [min(most, usable) for most in (20, 100, 200, 500)]


def jaccard(a, b, k=5):
    cut = lambda t: (w := [x for x in re.split(SPACES, lower(t)) if x]) and {tuple(w[i : i + k]) for i in range(max(1, len(w) - k + 1))} or set()
    x, y = cut(a), cut(b)
    return len(x & y) >= 0.8 * len(x | y)


def survivors(rows):
    """rows {id: text}: the smallest ids of groups joined by similarity."""
    root = {i: i for i in rows}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for a, b in itertools.combinations(sorted(rows), 2):
        if jaccard(rows[a], rows[b]):
            p, q = find(a), find(b)
            root[max(p, q)] = min(p, q)
    return {i for i in root if find(i) == i}


def near_copies():
    rng = np.random.default_rng(8)
    words = [f"w{i}" for i in range(3000)]
    rows = {}
    for i in range(40):
        rows[i] = " ".join(rng.choice(words, 300))
    for i in range(40, 140):  # one to four words changed: similarity 0.87 to 0.97
        w = rows[i % 20].split()
        for at in rng.integers(0, 300, rng.integers(1, 5)):
            w[at] = f"x{i}"
        rows[i] = " ".join(w)
    return rows | {200: None, 201: "", 202: "a b", 203: "A  b", 204: " ".join(rng.choice(words, 9000))}


def test_similar(spark):
    rows = near_copies()
    df = frame(spark, [(i, t, *[None] * 6) for i, t in rows.items()] + [(None, rows[0], *[None] * 6)])
    kept = simhash.dedup_similar(df)
    assert kept.columns == df.columns
    assert {r["doc_id"] for r in kept.collect()} == survivors({i: t or "" for i, t in rows.items()}) | {None}
    assert simhash.dedup_similar(empty(spark)).count() == 0
    pairs = [(r["a"], r["b"]) for r in simhash.similar(df).collect()]
    assert all(jaccard(rows[a] or "", rows[b] or "") for a, b in pairs) and len(pairs) < 3 * len(rows)


def text_frame(spark, rows):
    return frame(spark, [(i, t, *[None] * 6) for i, t in rows.items()])


def test_similar_in_families(spark):
    """Documents that share four fifths of a template, at 0.67 to each other, with near copies of some of them."""
    rng = np.random.default_rng(5)
    words = [f"w{i}" for i in range(20_000)]
    rows = {}
    for family in range(4):
        stem = " ".join(rng.choice(words, 320))
        for i in range(40):
            rows[1000 * family + i] = f"{stem} {' '.join(rng.choice(words, 80))}"
        for i in range(25):
            w = rows[1000 * family + i].split()
            for at in rng.integers(0, 400, 4):
                w[at] = f"x{i}"
            rows[1000 * family + 500 + i] = " ".join(w)
    want = survivors(rows)
    assert len(want) < len(rows) - 60
    assert {r["doc_id"] for r in simhash.dedup_similar(text_frame(spark, rows)).collect()} == want


def test_similar_with_repeats_and_short_texts(spark):
    """Repeating a passage leaves the set of shingles nearly as it is; few shingles at exactly 0.8 must do as well."""
    rng = np.random.default_rng(6)
    words = [f"w{i}" for i in range(20_000)]
    rows = {}
    for i in range(0, 40, 2):
        w = list(rng.choice(words, 404))
        rows[i], rows[i + 1] = " ".join(w), " ".join(w[:240] + w[200:240] * 20 + w[240:])
    for i in range(100, 700, 2):
        w = list(rng.choice(words, 9))
        rows[i], rows[i + 1] = " ".join(w), " ".join(w[:8])
    want = survivors({i: rows[i] for i in range(40)}) | {*range(100, 700, 2)}
    assert want == {*range(0, 40, 2), *range(100, 700, 2)}
    assert {r["doc_id"] for r in simhash.dedup_similar(text_frame(spark, rows)).collect()} == want


def test_planted_near_copies_are_found(spark):
    """Of copies at a similarity of 0.8 to 0.9 hardly any may stay, whatever their SimHash."""
    rng = np.random.default_rng(9)
    words = [f"w{i}" for i in range(30_000)]
    rows = {i: " ".join(rng.choice(words, rng.integers(30, 500))) for i in range(400)}
    for i in range(400):
        w = rows[i].split()
        while True:
            at = int(rng.integers(0, len(w)))
            w[at] = f"y{i}"
            if not jaccard(" ".join(w), rows[i]):
                break
            rows[1000 + i] = " ".join(w)
    planted = {i for i in rows if i >= 1000}
    assert len(planted) > 300
    kept = {r["doc_id"] for r in simhash.dedup_similar(text_frame(spark, rows)).collect()}
    assert {*range(400)} <= kept
    assert len(planted & kept) <= 0.01 * len(planted)


def test_a_hot_leader_is_dealt(spark, monkeypatch):
    monkeypatch.setattr(simhash, "TOGETHER", 7)
    rows = near_copies()
    df = text_frame(spark, rows)
    assert {r["doc_id"] for r in simhash.dedup_similar(df).collect()} == survivors({i: t or "" for i, t in rows.items()})


def test_pipeline(spark):
    sf = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    names = docs.columns
    rows = {r["doc_id"]: r["text"] for r in given()}
    for _, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, sf)
        assert docs.columns == names
    left = {r["doc_id"]: r["text"] for r in docs.collect()}
    accepted = {r["doc_id"] for r in corpus_pipeline.STAGES[0][1](spark, spark.read.parquet(f"{sf}/documents.parquet"), sf).collect()}
    first = {}
    for i in sorted(accepted):
        first.setdefault(re.sub(SPACES, " ", rows[i]), i)
    ids = sorted(first.values())
    stay = survivors({i: rows[i] for i in ids})
    items = [(r["item_id"], r["text"]) for r in given("benchmark")]
    want = {i for i in ids if i in stay and not brute_decontaminate(rows[i], items)[4]}
    assert {*left} == want
    out = corpus_pipeline.run(spark, sf).collect()
    check_pieces(sorted(left.items()), out)


def test_schema_is_awkward():
    assert "keep_id" in SCHEMA
