"""Prefix codes per key from integer weights, for whole batches of keys.

Weights are integers, so building and querying cannot disagree: no comparison below is one of floating-point numbers. A code is
given by its lengths; leaves are ordered by length (ties by number) and leaf k's word is the leading bits of the sum of 2^-length
over the leaves before it. A tree node is a range of leaves at a depth and is never stored; a node is split by comparing words.
"""

from __future__ import annotations

import heapq
from collections.abc import Callable

import numpy as np

DEPTH = 48  # words are kept in 48 bits
MOST_FILTER = 60


def _exponent(x: np.ndarray) -> np.ndarray:
    """Bit lengths, less a constant, of whole numbers from 1 to 2^53: the exponents of the same doubles."""
    return x.astype(np.float64).view(np.int64) >> 52


def doublings(w: np.ndarray, total: np.ndarray) -> np.ndarray:
    """The least l >= 0 with w 2^l >= total, for w >= 1: the difference of their bit lengths, or one more."""
    out = np.maximum(_exponent(total) - _exponent(w), 0)
    out += (w << out) < total
    return out


def shannon_lengths(w: np.ndarray) -> np.ndarray:
    """n x V weights >= 1: the least l with w 2^l >= total."""
    return doublings(w, w.sum(1, keepdims=True))


def huffman_row(w) -> list[int]:
    """Code lengths of one row of weights; a single value has length 0."""
    heap = [(int(x), i, (i,)) for i, x in enumerate(w)]
    heapq.heapify(heap)
    out, tick = [0] * len(heap), len(heap)
    while len(heap) > 1:
        a, b = heapq.heappop(heap), heapq.heappop(heap)
        for i in a[2] + b[2]:
            out[i] += 1
        heapq.heappush(heap, (a[0] + b[0], tick, a[2] + b[2]))
        tick += 1
    return out


def huffman_bits(counts) -> int:
    """Total bits of a Huffman code for values whose counts are given as (count, how many values have it): equal weights are merged
    together, so the work goes by the number of distinct counts, not of values."""
    heap, many, total = [], {}, 0

    def put(w: int, n: int) -> None:
        if w not in many:
            heapq.heappush(heap, w)
        many[w] = many.get(w, 0) + n

    for w, n in counts:
        put(int(w), int(n))
    while heap:
        w = heapq.heappop(heap)
        n = many.pop(w)
        if n > 1:
            total += 2 * w * (n // 2)
            put(2 * w, n // 2)
        if n % 2 and heap:
            other = heap[0]
            many[other] -= 1
            if not many[other]:
                del many[heapq.heappop(heap)]
            total += w + other
            put(w + other, 1)
    return total


def huffman_lengths(w: np.ndarray) -> np.ndarray:
    """Row by row, equal rows once."""
    rows, which = np.unique(w, axis=0, return_inverse=True)
    return np.array([huffman_row(r) for r in rows], np.int64).reshape(rows.shape)[which.ravel()]


def fixed_lengths(w: np.ndarray) -> np.ndarray:
    """A balanced code whatever the weights."""
    return np.full(w.shape, (w.shape[1] - 1).bit_length(), np.int64)


CODERS: dict[str, Callable[[np.ndarray], np.ndarray]] = {"shannon": shannon_lengths, "huffman": huffman_lengths, "fixed": fixed_lengths}


class Code:
    """The codes of a batch: leaves sorted by length, their words left-aligned in DEPTH bits, and running sums of weights. A single row
    of weights is the code of all keys, however many they are."""

    def __init__(self, w: np.ndarray, coder: str | Callable = "shannon"):
        lengths = (CODERS[coder] if isinstance(coder, str) else coder)(w)
        self.order = np.argsort(lengths, axis=1, kind="stable")
        self.length = np.take_along_axis(lengths, self.order, 1)
        step = np.int64(1) << (DEPTH - self.length)
        self.word = np.cumsum(step, 1) - step
        self.sums = np.zeros((w.shape[0], w.shape[1] + 1), np.int64)
        np.cumsum(np.take_along_axis(w, self.order, 1), 1, out=self.sums[:, 1:])

    def rank_of(self, vid: np.ndarray) -> np.ndarray:
        """Leaf number of each key's value."""
        if len(self.order) == 1:
            return np.argsort(self.order[0])[vid]
        return (self.order == vid[:, None]).argmax(1)

    def split(self, rows: np.ndarray, depth: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        """First leaf of the right child of node (depth, [i, j)): whose word has bit ``depth`` set within the node."""
        base = self.word[rows, i] >> (DEPTH - depth) << (DEPTH - depth)
        half = base + (np.int64(1) << (DEPTH - depth - 1))
        below = np.searchsorted(self.word[0], half) if len(self.word) == 1 else (self.word[rows] < half[:, None]).sum(1)
        return np.clip(below, i, j)


_LAST: list = [None, None]


def code_of(w: np.ndarray, coder: str | Callable) -> Code:
    """The code for w; that of a single row, which batch after batch asks for again, is kept."""
    if len(w) > 1:
        return Code(w, coder)
    key = (coder, w.tobytes())
    if _LAST[0] != key:
        _LAST[:] = key, Code(w, coder)
    return _LAST[1]


def filter_bits(minor: np.ndarray, major: np.ndarray, cap: int) -> np.ndarray:
    """r_int for arrays."""
    return np.minimum(cap, doublings(minor.astype(np.int64) << 1, major))


def rounded_bits(minor: np.ndarray, major: np.ndarray, cap: int, coin: np.ndarray) -> np.ndarray:
    """The real-valued length, rounded up or down so that its mean stays; coin (0..65535) comes from the key's hash."""
    real = np.maximum(0.0, np.log2(np.log(2) * major / np.maximum(minor, 1)))
    return np.minimum(cap, np.floor(real).astype(np.int64) + (coin < np.rint((real - np.floor(real)) * 65536)))


class Walk:
    """Lock-step descent of all n keys of a batch; w has a row for each, or one for all. ``step`` asks for the branch; a node with one
    child is passed freely."""

    def __init__(self, w: np.ndarray, cfg, coin: np.ndarray | None = None, n: int | None = None):
        self.cfg, self.coin = cfg, coin
        self.w = w
        self.n = n = len(w) if n is None else n
        self.out = np.zeros(n, np.int64)
        self.todo = np.arange(n)
        self.total = w.sum(1)
        self.used = np.zeros(n, np.int64)  # filter bits so far; a key has MOST_FILTER at most, later decisions do without

    def _r(self, rows, minor, major, depth):
        cfg = self.cfg
        if cfg.filter == "none":
            return np.zeros(len(rows), np.int64)
        r = filter_bits(minor, major, cfg.r_cap) if cfg.r_mode == "integer" else rounded_bits(minor, major, cfg.r_cap, (self.coin[rows] >> (depth % 4 * 16)) & 0xFFFF)
        r = np.minimum(np.where(depth > 0, 0, r) if cfg.filter == "root" else r, MOST_FILTER - self.used[rows])
        self.used[rows] += r
        return r

    def run(self, step: Callable) -> np.ndarray:
        """step(rows, r, rare_leaves) -> whether each row takes its unlikely branch; rare_leaves(vid rank lookup) is None when querying."""
        n, v, one = self.n, self.w.shape[1], len(self.w) == 1
        if v == 1 or n == 0:
            return self.out
        rest = np.arange(n)
        started = np.zeros(n, bool)
        if self.cfg.fast_head and self.cfg.coder == "shannon":
            top = np.repeat(self.w.argmax(1), n if one else 1)
            most, total = self.w[0 if one else np.arange(n), top], np.repeat(self.total, n if one else 1)
            head = np.flatnonzero(2 * most > total)
            if len(head):
                minor, major = total[head] - most[head], most[head]
                r = self._r(head, minor, major, np.zeros(len(head), np.int64))
                rare = step(head, r, lambda: self.truth[head] != top[head])
                self.out[head] = top[head]
                started[head] = True
                keep = np.ones(n, bool)
                keep[head[~rare]] = False
                rest = np.flatnonzero(keep)
        if not len(rest):
            return self.out
        code = code_of(self.w if one else self.w[rest], self.cfg.coder)
        row = np.zeros(len(rest), np.int64) if one else np.arange(len(rest))
        rank = code.rank_of(self.truth[rest]) if self.truth is not None else None
        m = len(rest)
        i, j, depth = np.zeros(m, np.int64), np.full(m, v), np.zeros(m, np.int64)
        at = np.flatnonzero(started[rest])
        i[at], depth[at] = 1, 1  # the head has the word 0
        active = np.flatnonzero(j - i > 1)
        while len(active):
            a, b, d = i[active], j[active], depth[active]
            cut = code.split(row[active], d, a, b)
            both = np.flatnonzero((cut > a) & (cut < b))
            right = cut <= a  # one child: which
            if len(both):
                rows = active[both]
                left_w = code.sums[row[rows], cut[both]] - code.sums[row[rows], a[both]]
                right_w = code.sums[row[rows], b[both]] - code.sums[row[rows], cut[both]]
                likely_left = left_w >= right_w
                r = self._r(rest[rows], np.minimum(left_w, right_w), np.maximum(left_w, right_w), d[both])
                rare = step(rest[rows], r, lambda rows=rows, both=both, ll=likely_left: (rank[rows] >= cut[both]) == ll)
                right[both] = likely_left == rare
            i[active] = np.where(right, np.maximum(cut, a), a)
            j[active] = np.where(right, b, np.minimum(cut, b))
            depth[active] = d + 1
            active = active[j[active] - i[active] > 1]
        self.out[rest] = code.order[row, i]
        return self.out

    truth: np.ndarray | None = None


def decisions(w: np.ndarray, vid: np.ndarray, cfg, coin: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Paths of known values: (number of decisions per key, their bytes one after the other): r, plus 128 if the branch is unlikely."""
    walk = Walk(w, cfg, coin, len(vid))
    walk.truth = vid
    seen: list[tuple[np.ndarray, np.ndarray]] = []

    def step(rows, r, truth):
        rare = truth()
        seen.append((rows, (r + 128 * rare).astype(np.uint8)))
        return rare

    walk.run(step)
    count = np.zeros(len(vid), np.int64)
    for rows, _ in seen:
        count[rows] += 1
    out, at = np.zeros(int(count.sum()), np.uint8), np.cumsum(count) - count
    for rows, byte in seen:
        out[at[rows]] = byte
        at[rows] += 1
    return count, out


def walk(w: np.ndarray, cfg, read_filter: Callable, read_correction: Callable, coin: np.ndarray | None = None) -> np.ndarray:
    """Values of keys: read_filter(rows, position, r) tells whether all r bits are set, read_correction(rows, position) gives a bit."""
    n = len(w) if coin is None else len(coin)
    at = Walk(w, cfg, coin, n)
    f, c = np.zeros(n, np.int64), np.zeros(n, np.int64)

    def step(rows, r, _):
        rare = np.zeros(len(rows), bool)
        match = read_filter(rows, f[rows], r)
        f[rows] += r
        hit = rows[match]
        rare[match] = read_correction(hit, c[hit])
        c[hit] += 1
        return rare

    return at.run(step)


def surprisal_bits(w: np.ndarray, vid: np.ndarray) -> np.ndarray:
    """log2(total / weight of the value)."""
    return np.log2(w.sum(1)) - np.log2(w[np.arange(len(w)), vid])
