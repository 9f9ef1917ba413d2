import hashlib

import numpy as np
import pytest

from predmap.llm import suffix_dedup as sd

from .helpers import awkward, empty, frame, given


def brute(rows, length=sd.LENGTH):
    first = {}
    for i, t in sorted(((i, t) for i, t in rows if i is not None), key=lambda r: r[0]):
        for p in range(len(t) - length + 1):
            first.setdefault(t[p : p + length], i)
    out = []
    for i, t in rows:
        gone = np.zeros(len(t), bool)
        if i is not None:
            for p in range(len(t) - length + 1):
                if first[t[p : p + length]] < i:
                    gone[p : p + length] = True
        edge = np.flatnonzero(np.diff(gone, prepend=False, append=False))
        out.append((i, len(t), int(gone.sum()), len(edge) // 2, hashlib.sha256(bytes(b for b, g in zip(t, gone) if not g)).hexdigest()))
    return sorted(out, key=str)


def found(spark, rows, **options):
    df = sd.dedup(frame(spark, [(*r, *[None] * 6) for r in rows]), **options)
    return sorted((tuple(r) for r in df.select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256").collect()), key=str)


def pieces(seed=5):
    rng = np.random.default_rng(seed)
    bits = ["".join(rng.choice(list("abcé \n\0"), n)) for n in (20, 49, 50, 51, 64, 90, 200)] + ["a" * 400, "ab" * 100, "", "a" * 60 + "b" + "a" * 60]
    return [(i, "".join(bits[k] for k in rng.integers(0, len(bits), rng.integers(0, 6)))) for i in range(120)]


def test_planted(spark):
    rows = pieces() + [(None, pieces()[3][1]), (5, pieces()[7][1]), (5, pieces()[7][1]), (200, pieces()[3][1])] + [(300 + r[0], r[1] or "") for r in awkward()]
    assert found(spark, rows) == brute([(i, t.encode()) for i, t in rows])
    assert sd.dedup(empty(spark)).count() == 0


@pytest.mark.parametrize("hot", [0, 3, 40])
def test_hot_anchors_and_small_indexes(spark, hot):
    rows = pieces(9)
    assert found(spark, rows, hot_from=hot, index_bytes=500) == brute([(i, t.encode()) for i, t in rows])


def test_settle():
    rng = np.random.default_rng(2)
    base = bytes(rng.integers(97, 120, 400).astype(np.uint8))
    rows = [(b[:at] + bytes([x]) + b[at + 1 :], d) for d in range(60) for b, at, x in [(base, int(rng.integers(0, 400)), int(rng.integers(97, 120)))]]
    contexts, docs = [], []
    import pyarrow as pa

    c = sd.Chunk(pa.table({"doc_id": [d for _, d in rows], "text": [t.decode() for t, _ in rows]}))
    s, e, _, doc = c.anchors()
    contexts = [c.raw[a : z + sd.LENGTH] for a, z in zip(s.tolist(), e.tolist())]
    docs = np.array(c.ids)[doc]
    first = {}
    for x, d in zip(contexts, docs.tolist()):
        for p in range(len(x) - sd.LENGTH + 1):
            first[x[p : p + sd.LENGTH]] = min(d, first.get(x[p : p + sd.LENGTH], 99))
    for x, d, m in zip(contexts, docs.tolist(), sd.settle(contexts, sd.gram_places(contexts), docs).tolist()):
        assert m == sum(1 << p for p in range(len(x) - sd.LENGTH + 1) if first[x[p : p + sd.LENGTH]] < d)


def test_given(spark):
    got = sorted((tuple(r) for r in sd.query(spark, "/root/testdata/sf0.001").collect()), key=str)
    assert got == brute([(r["doc_id"], r["text"].encode()) for r in given()])


@pytest.mark.parametrize("seed", range(6))
def test_index(seed):
    rng = np.random.default_rng(seed)
    strings = list({bytes(rng.integers(0, 3, rng.integers(3, 30)).astype(np.uint8)) for _ in range(40)})
    numbers = rng.integers(0, 20, len(strings))
    index = sd.RunIndex(strings, numbers, 6)
    want = {}
    for s, n in zip(strings, numbers):
        for p in range(len(s) - 5):
            want[s[p : p + 6]] = min(want.get(s[p : p + 6], 99), n)
    seen = 0
    for which, place, least in index.stream():
        for w, p, x in zip(which, place, least):
            assert want[strings[w][p : p + 6]] == x
            seen += 1
    assert seen == sum(max(0, len(s) - 5) for s in strings)
    assert len(index.head) == len(index.to) == len(index.samples)


def test_slices(monkeypatch):
    import pyarrow as pa

    rows = pa.table({"doc_id": list(range(120)), "text": [t for _, t in pieces()]})
    whole = sd.Chunk(rows).anchors()
    monkeypatch.setattr(sd, "SLICE", 333)
    cut = sd.Chunk(rows).anchors()
    windows = [{(w, h, d) for s, e, h, d in zip(*(x.tolist() for x in runs)) for w in range(s, e + 1)} for runs in (whole, cut)]
    assert windows[0] == windows[1]
