import numpy as np
import pytest

from predmap.config import MapConfig
from predmap.functions import ribbon
from predmap.functions.ribbon import BitStore
from predmap.operators.shards import SparseStore

U = np.uint64


def keys(n, seed=0):
    return np.random.default_rng(seed).integers(0, 1 << 63, n).astype(U) * U(2) + U(1)


@pytest.mark.parametrize("n", [0, 1, 2, 37, 500, 5000, 30_000])
@pytest.mark.parametrize("bits", [1, 3, 8])
def test_packed(n, bits):
    cfg, h = MapConfig(), keys(n)
    v = np.random.default_rng(1).integers(0, 1 << bits, n).astype(U)
    store = BitStore.from_bytes(BitStore.build(h, v, v, cfg, packed_bits=bits).to_bytes())
    assert (store.read_all(h, bits, cfg) == v).all()
    if n >= 5000:
        size = store.size_bits()
        assert size["words"] + size["bumps"] < 1.05 * n * bits


@pytest.mark.parametrize("layout", ["interleaved", "per_bit_key"])
@pytest.mark.parametrize("n", [1, 300, 8000])
@pytest.mark.parametrize("width", [16, 32, 64])
def test_strings_with_holes(layout, n, width):
    cfg, h, rng = MapConfig(ribbon_width=width, layout=layout), keys(n), np.random.default_rng(2)
    care = rng.integers(0, 1 << 63, n).astype(U) & rng.integers(0, 1 << 63, n).astype(U) & rng.integers(0, 1 << 63, n).astype(U)
    bits = rng.integers(0, 1 << 63, n).astype(U)
    store = BitStore.from_bytes(BitStore.build(h, care, bits, cfg).to_bytes())
    got = store.read_all(h, 64, cfg)
    assert ((got ^ bits) & care == 0).all()
    if n == 8000:
        holes = ~care & U((1 << 63) - 1)
        share = np.bitwise_count(got & holes).sum() / np.bitwise_count(holes).sum()
        assert abs(share - 0.5) < 0.01
        stored = int(np.bitwise_count(care).sum())
        assert sum(store.size_bits().values()) < (1.08 if width > 16 else 1.25) * stored


def test_one_bucket_overloaded():
    cfg = MapConfig(bucket=128, max_layers=6)
    h = keys(6000)
    layer = ribbon.Layer(cfg.seed, 5760, 64, 512, 16, np.zeros(12, np.uint8), None)
    start, *_ = layer.rows(h, 1)
    crowd = h[start < 900]
    v = np.arange(len(crowd)).astype(U) & U(1)
    store = BitStore.build(crowd, v, v, cfg, packed_bits=1)
    assert (store.read_all(crowd, 1, cfg) == v).all()


def test_filters_have_no_false_negatives_and_few_positives():
    cfg, h = MapConfig(), keys(20_000)
    r = (np.arange(20_000) % 8).astype(np.int64)
    care = np.where(r > 0, (U(1) << r.astype(U)) - U(1), U(0))
    store = BitStore.build(h[:10_000], care[:10_000], care[:10_000], cfg)
    zero = np.zeros(10_000, np.int64)
    assert store.ones(h[:10_000], zero, r[:10_000], cfg).all()
    hit = store.ones(h[10_000:], zero, r[10_000:], cfg)
    for k in range(8):
        at = r[10_000:] == k
        assert abs(hit[at].mean() - 2.0**-k) < 4 * np.sqrt(2.0**-k / at.sum()) + 1e-9


def test_dense_and_sparse_systems():
    rng = np.random.default_rng(5)
    solved = 0
    for _ in range(400):
        a, b = rng.integers(0, 2, (24, 24)), rng.integers(0, 2, 24)
        z = ribbon.solve_dense(a, b)
        full = ribbon.solve_dense(a, a @ rng.integers(0, 2, 24) % 2)
        assert full is not None
        if z is not None:
            assert ((a @ z) % 2 == b).all()
        rank_full = len({tuple(r) for r in a.tolist()}) == 24 and abs(round(np.linalg.det(a))) % 2 == 1
        solved += rank_full
    assert abs(solved / 400 - 0.289) < 0.08
    h, bits = keys(3000), rng.integers(0, 2, 3000)
    store = SparseStore.from_bytes(SparseStore.build(h, bits).to_bytes())
    assert (store.read(h) == bits).all()
    assert sum(b[0] for b in store.blocks) < 1.06 * 3000


def test_same_bytes_whatever_the_order():
    cfg, h = MapConfig(), keys(4000)
    v = h & U(1)
    order = np.random.default_rng(3).permutation(4000)
    a, b = BitStore.build(h, v, v, cfg, packed_bits=1), BitStore.build(h[order], v[order], v[order], cfg, packed_bits=1)
    assert (a.read_all(h, 1, cfg) == b.read_all(h, 1, cfg)).all()


def test_ones_hashes_what_is_left(monkeypatch):
    """Bits of one instance are laps of their own: a run of ones is not asked of keys that have fallen out."""
    rng = np.random.default_rng(12)
    h = rng.integers(0, 1 << 63, 4096, dtype=np.uint64)
    care = np.where(np.arange(4096) < 40, np.uint64((1 << 20) - 1), np.uint64(0))
    store = BitStore.build(h, care, care, MapConfig())
    assert store.instances == 1
    rows, r = np.arange(4096), np.full(4096, 20)
    each = np.array([store.read(h, np.full(4096, k), MapConfig()) for k in range(20)]).all(0)
    seen, real = [], ribbon.mix
    monkeypatch.setattr(ribbon, "mix", lambda h, seed: seen.append(len(h)) or real(h, seed))
    assert (store.reader(h, MapConfig()).ones(rows, np.zeros(4096, np.int64), r) == each).all() and each[:40].all()
    assert sum(seen) < 12 * 4096
