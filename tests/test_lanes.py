"""Solving in lock-step: the same thresholds as inserting row by row, right solutions, and a fraction of the time."""

import time

import numpy as np
import pytest

from predmap.config import MapConfig
from predmap.functions import lanes, ribbon
from predmap.functions.ribbon import BitStore
from predmap.operators.shards import SparseStore

U = np.uint64


def keys(n, seed=0):
    return np.random.default_rng(seed).integers(0, 1 << 63, n).astype(U) * U(2) + U(1)


def strings(n, seed=1):
    rng = np.random.default_rng(seed)
    return keys(n, seed), rng.integers(1, 1 << 5, n).astype(U), rng.integers(0, 1 << 5, n).astype(U)


def both(monkeypatch, build):
    monkeypatch.setattr(ribbon, "LARGE", 1 << 60)
    a = time.perf_counter()
    slow = build()
    b = time.perf_counter()
    monkeypatch.setattr(ribbon, "LARGE", 1)
    fast = build()
    return slow, fast, b - a, time.perf_counter() - b


@pytest.mark.parametrize("width", [16, 32, 64])
@pytest.mark.parametrize("n", [1, 70, 900, 20_000])
@pytest.mark.parametrize("packed", [0, 5])
def test_same_thresholds(monkeypatch, n, width, packed):
    h, care, bits = strings(n)
    if packed:
        care = np.full(n, (1 << packed) - 1, U)
    slow, fast, _, _ = both(monkeypatch, lambda: BitStore.build(h, care, bits, MapConfig(ribbon_width=width), packed_bits=packed))
    assert fast.size_bits() == slow.size_bits()
    for a, b in zip(slow.layers, fast.layers, strict=True):
        assert (a.slots, a.seed) == (b.slots, b.seed) and (a.thresholds == b.thresholds).all()
    fast = BitStore.from_bytes(fast.to_bytes())
    assert ((fast.read_all(h, 5, MapConfig()) ^ bits) & care == 0).all()


def test_equal_rows_that_contradict_are_bumped(monkeypatch):
    """Rows of one start and one coefficient word, with other right sides, in a layer that may bump."""
    monkeypatch.setattr(ribbon, "LARGE", 1)
    n, cfg = 3000, MapConfig()
    layer = ribbon.Layer(0, 3200, 64, 512, 16, np.zeros(3200 // 512 + 1, np.uint8), None)
    start, row, turn, level = layer.rows(keys(n), 1)
    start[1], row[1], level[1], level[0] = start[0], row[0], 3, 9
    bits = np.zeros(n, U)
    bits[1] = 1
    solution, out = lanes.insert(start, row, turn, level, np.ones(n, U), bits, 1, layer, False, cfg.seed)
    assert 1 in out and 0 not in out
    kept = np.setdiff1d(np.arange(n), out)
    padded = np.concatenate([solution[0], np.zeros(64, np.uint8)])
    window = (padded[start[:, None] + np.arange(64)].astype(U) << np.arange(64, dtype=U)).sum(1)
    assert (ribbon.parity(window & row)[kept] == bits[kept]).all()


def one_by_one(cols, bits, size):
    """Sparse rows as integers, reduced to one row per leading position: whether they can be solved."""
    lead = {}
    for c, b in zip(cols.tolist(), bits.tolist(), strict=True):
        row = int(b) << size
        for x in c:
            row ^= 1 << x
        while row:
            p = (row & -row).bit_length() - 1
            if p == size:
                return False
            if p not in lead:
                lead[p] = row
                break
            row ^= lead[p]
    return True


def test_sparse_systems():
    rng = np.random.default_rng(4)
    size, many = 100, 60
    lane = np.repeat(np.arange(many), rng.integers(60, 101, many))
    cols, bits = rng.integers(0, size, (len(lane), 4)), rng.integers(0, 2, len(lane)).astype(U)
    cols[:3] = [[7, 7, 7, 7], [1, 2, 2, 1], [3, 3, 4, 5]]
    bits[:2] = 0
    z, good = lanes.sparse(lane, cols, bits, many, size)
    assert 0 < good.sum() < many
    for k in range(many):
        at = lane == k
        assert good[k] == one_by_one(cols[at], bits[at], size)
        if good[k]:
            assert ((z[k][cols[at]].sum(1) & 1) == bits[at]).all()


def test_time(monkeypatch):
    """Relative to one row after the other on the same machine."""
    h, care, bits = strings(60_000)
    *_, slow, fast = both(monkeypatch, lambda: BitStore.build(h, care & U(7) | U(1), bits, MapConfig()))
    assert fast < 0.8 * slow
    n = 150 * 768
    b = bits[np.arange(n) % len(bits)] & U(1)
    a = time.perf_counter()
    SparseStore.build(keys(n, 3), b)
    took = time.perf_counter() - a
    a = time.perf_counter()
    for k in range(15):
        one_by_one(SparseStore.columns(keys(768, k), 802, 0), b[:768], 802)
    assert took < 0.8 * 10 * (time.perf_counter() - a)


def test_mapping_is_spread_and_kept(spark):
    """A file that one task reads is dealt over all cores, and worked out once."""
    from predmap import workloads
    from predmap.sources.mappings import Mapping

    df = spark.range(0, 1000, 1, 1).selectExpr("id", "id % 3 AS v")
    with workloads.spread_out(Mapping(df, ["id"], "v", [])) as m:
        assert m.df.rdd.getNumPartitions() >= spark.sparkContext.defaultParallelism and m.df.is_cached
        assert sorted(m.df.collect()) == sorted(df.collect())
    assert not m.df.is_cached


def test_external_values_are_looked_up_together():
    """Code words are compared as arrays: calls do not grow with the keys."""
    import sys

    from predmap.functions import codes
    from predmap.operators import shards

    rng = np.random.default_rng(21)
    vid, h = rng.integers(0, 82, 4000), rng.integers(-(1 << 63), (1 << 63) - 1, 4000)
    lengths = np.array(codes.huffman_row(np.bincount(vid, minlength=82).tolist()), np.int64)
    words = shards.canonical_words(lengths)
    store = shards.SparseStore.from_bytes(shards.solve_sparse(h, vid, lengths, words, None)[0]["sparse"])
    calls = []
    sys.setprofile(lambda frame, event, arg: calls.append(event) if event == "c_call" else None)
    try:
        got = shards.read_sparse(store, h, lengths, words)
    finally:
        sys.setprofile(None)
    assert (got == vid).all() and len(calls) < len(vid)
