import itertools
import math
from fractions import Fraction

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from predmap.config import MapConfig
from predmap.functions import codes, theory

CFG = MapConfig()


def test_goldens():
    assert theory.entropy((0.95, 0.04, 0.01)) == pytest.approx(0.3225, abs=1e-4)
    assert theory.surprisal(0.25) == 2
    assert theory.surprisal(0.9) == pytest.approx(0.1520, abs=1e-4)
    p = (0.5, 0.4, 1 / 3, 0.25, 0.2, 0.15, 0.1, 0.05, 0.01, 0.001)
    r = [theory.r_int(*(int(Fraction(x).limit_denominator(1000) * 3000), 3000 - int(Fraction(x).limit_denominator(1000) * 3000))) for x in p]
    assert r == [0, 0, 0, 1, 1, 2, 3, 4, 6, 9]
    assert [round(theory.space(x, k), 4) for x, k in ((0.25, 1), (0.2, 1), (0.1, 3), (0.05, 4))] == [0.875, 0.8, 0.5125, 0.3094]


def test_overheads():
    grid = [(i / 10000, theory.r_int(i, 10000 - i)) for i in range(1, 5001)]
    over = [(theory.space(p, r) / theory.binary_entropy(p) - 1, p) for p, r in grid]
    assert max(over)[0] == pytest.approx(0.10814, abs=1e-4) and max(over)[1] == pytest.approx(0.2, abs=1e-3)
    real = [(theory.space(p, theory.r_real(p)) / theory.binary_entropy(p) - 1, p) for p, _ in grid]
    assert max(real)[0] == pytest.approx(0.08629, abs=1e-4) and max(real)[1] == pytest.approx(0.1507, abs=2e-3)
    for p, r in grid[::97]:
        assert theory.space(p, r) <= min(theory.space(p, k) for k in range(40)) + 1e-12


def test_trees():
    e = 0.01
    for p, depth, length in (((1 - 2 * e, e, e), (1, 2, 2), 1 + 2 * e), ((0.5, 0.5 - e, e), (1, 2, 2), 1.5), ((2 * e, 0.5 - e, 0.5 - e), (1, 2, 2), 2 - 2 * e)):
        assert theory.expected_length(p, depth) == pytest.approx(length)


def test_worked_example():
    w = np.array([[60, 25, 10, 5]])
    code = codes.Code(w)
    assert code.length.tolist() == [[1, 2, 4, 5]]
    assert [format(int(x) >> (codes.DEPTH - n), f"0{n}b") for x, n in zip(code.word[0], (1, 2, 4, 5))] == ["0", "10", "1100", "11010"]
    count, path = codes.decisions(np.repeat(w, 4, 0), np.arange(4), CFG)
    assert count.tolist() == [1, 2, 3, 3]
    assert path.tolist() == [0, 128, 0, 128, 128, 0, 128, 128, 128]
    count, path = codes.decisions(np.array([[90, 10]] * 2), np.array([0, 1]), CFG)
    assert (count.tolist(), path.tolist()) == ([1, 1], [3, 131])


@settings(max_examples=200, deadline=None)
@given(st.lists(st.integers(1, 1 << 24), min_size=2, max_size=12))
def test_shannon(w):
    row = np.array([w])
    length = codes.shannon_lengths(row)[0]
    assert sum(Fraction(1, 1 << int(x)) for x in length) <= 1
    assert all(x * 2**int(n) >= sum(w) and (n == 0 or x * 2 ** (int(n) - 1) < sum(w)) for x, n in zip(w, length))
    code = codes.Code(row)
    words = [format(int(x) >> (codes.DEPTH - int(n)), f"0{n}b") for x, n in zip(code.word[0], code.length[0])]
    assert not any(a != b and b.startswith(a) for a, b in itertools.permutations(words, 2))


def test_huffman_is_optimal():
    rng = np.random.default_rng(0)
    for _ in range(50):
        w = rng.integers(1, 50, 5)
        best = min(sum(int(a) * d for a, d in zip(w, depth)) for depth in itertools.product(range(1, 5), repeat=5) if sum(2.0**-d for d in depth) <= 1)
        assert sum(int(a) * d for a, d in zip(w, codes.huffman_row(w))) == best


@pytest.mark.parametrize("coder", ["shannon", "huffman", "fixed"])
@pytest.mark.parametrize("mode", ["all", "root", "none"])
def test_walk_mirrors_decisions(coder, mode):
    rng = np.random.default_rng(4)
    n, v = 400, 9
    w = np.maximum(1, (rng.dirichlet(np.full(v, 0.3), n) * (1 << 24)).astype(np.int64))
    vid = rng.integers(0, v, n)
    for head in (True, False):
        cfg = MapConfig(coder=coder, filter=mode, fast_head=head)
        count, path = codes.decisions(w, vid, cfg)
        at = np.cumsum(count) - count
        pointer, seen = at.copy(), []

        def read_filter(rows, pos, r):
            byte = path[pointer[rows]]
            assert ((byte & 127) == r).all()
            pointer[rows] += 1
            seen.append(rows)
            return (byte > 127) | (r == 0)

        def read_correction(rows, pos):
            return path[pointer[rows] - 1] > 127

        assert (codes.walk(w, cfg, read_filter, read_correction) == vid).all()
        assert (pointer == at + count).all()


def test_surprisal_is_the_sum_over_branches():
    rng = np.random.default_rng(1)
    w = rng.integers(1, 1000, (50, 6))
    vid = rng.integers(0, 6, 50)
    for row, v in zip(w.tolist(), vid.tolist()):
        code = codes.Code(np.array([row]))
        rank, i, j, d, p = int(code.rank_of(np.array([v]))[0]), 0, 6, 0, Fraction(1)
        while j - i > 1:
            cut = int(code.split(np.array([0]), np.array([d]), np.array([i]), np.array([j]))[0])
            total = int(code.sums[0, j] - code.sums[0, i])
            a, b = (i, cut) if rank < cut else (cut, j)
            p *= Fraction(int(code.sums[0, b] - code.sums[0, a]), total)
            i, j, d = a, b, d + 1
        assert p == Fraction(row[v], sum(row))
    assert math.isclose(codes.surprisal_bits(np.array([[1, 3]]), np.array([0]))[0], 2)
