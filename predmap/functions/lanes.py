"""The same elimination as ``ribbon._insert``, for large systems: all buckets of all instances in lock-step, a lane each.

A row of a bucket reaches at most width - 1 columns into the next bucket. So every lane first eliminates all columns but those that the
bucket before it reaches (its left ones), at each column with the row of the highest class, by which only lower classes are reduced. What
remains has left columns only. Then one pass over the buckets keeps the solutions of those columns as a vector and a basis, takes in
the remaining rows by class, and bumps where they contradict. A contradiction is a dependence on rows that go first, whatever the order of the
elimination, so the thresholds are those that inserting row by row gives.
"""

from __future__ import annotations

from functools import reduce
from operator import xor

import numpy as np

U = np.uint64
TOP = U((1 << 63) - 1)
BLOCK = 32  # columns between two compactions
LANES, DENSE = 1024, 32  # at a time: few calls, and arrays that the cache takes


def _sweep(start, row, rhs, rank, lane, lanes: int, bucket: int, width: int):
    """Pivots as columns x lanes arrays (window from the column on, left columns, right side, class + 1 or 0), and the rows that are left:
    lane, left columns, right side, class + 1. Start is within the bucket, rank is class + 1."""
    edge = width - 1
    win, left, right = (np.zeros((bucket, lanes), U) for _ in range(3))
    best = np.zeros((bucket, lanes), np.uint8)
    block = np.maximum(0, start - edge) // BLOCK
    order = np.lexsort((lane, block))
    start, row, rhs, rank, lane, block = (x[order] for x in (start, row, rhs, rank, lane, block))
    blocks = -(-bucket // BLOCK)
    at = np.searchsorted(block, np.arange(blocks + 1))
    early = start < edge
    s = start.astype(U)
    own = np.where(early, (row << np.where(early, s, U(0))) & U((1 << edge) - 1), U(0))
    body = np.where(early, row >> np.where(early, U(edge) - s, U(0)), row)
    gap = np.where(early, 0, start - edge - block * BLOCK).astype(U)
    low, high = (body << gap & U(0xFFFFFFFF)).astype(np.uint32), body >> (U(BLOCK) - gap)
    every = np.arange(lanes)
    lo, hi, le, rh, pr = np.zeros((lanes, 0), np.uint32), *(np.zeros((lanes, 0), U) for _ in range(3)), np.zeros((lanes, 0), np.uint8)
    if single := int(rhs.max(initial=0)) < 2:  # in the top bit of the left columns, which are 63 at most
        own, rhs = own | rhs << U(63), np.zeros_like(rhs)
    for k in range(blocks):
        r, c = np.nonzero(pr)
        old = np.bincount(r, minlength=lanes)
        i, j = at[k], at[k + 1]
        new = np.bincount(lane[i:j], minlength=lanes)
        size = int((old + new).max(initial=0))
        place = np.arange(len(r)) - (np.cumsum(old) - old)[r] + r * size
        fresh = np.arange(j - i) - (np.cumsum(new) - new - old)[lane[i:j]] + lane[i:j] * size

        def merged(kept, added, kind, place=place, fresh=fresh, size=size):
            out = np.zeros(lanes * size, kind)
            out[place], out[fresh] = kept, added
            return out.reshape(lanes, size)

        rest = hi[r, c]
        lo, hi = merged((rest & U(0xFFFFFFFF)).astype(np.uint32), low[i:j], np.uint32), merged(rest >> U(BLOCK), high[i:j], U)
        le, rh, pr = merged(le[r, c], own[i:j], U), merged(rh[r, c], rhs[i:j], U), merged(pr[r, c], rank[i:j], np.uint8)
        if not size:
            continue
        bit, mask, part, short = np.empty_like(lo), np.empty_like(hi), np.empty_like(hi), np.empty_like(lo)
        whole = [hi, le] if single else [hi, le, rh]
        for d in range(min(BLOCK, bucket - k * BLOCK)):
            np.right_shift(lo, np.uint32(d), out=bit)
            bit &= np.uint32(1)
            key = bit.astype(np.uint8)
            key *= pr
            top = key.argmax(1)
            had = key[every, top]
            some = had > 0
            if not some.any():
                continue
            bit[every, top] = 0
            p_lo, p_hi, p_le, p_rh = (np.where(some, x[every, top], 0) for x in (lo, hi, le, rh))
            y = k * BLOCK + d
            win[y], left[y], right[y], best[y] = (p_lo >> np.uint32(d)).astype(U) | p_hi << U(BLOCK - d), p_le, p_rh, had
            gone = every[some], top[some]
            pr[gone], lo[gone] = 0, 0
            np.negative(bit.view(np.int32), out=bit.view(np.int32))
            np.copyto(mask.view(np.int64), bit.view(np.int32))
            lo ^= np.bitwise_and(bit, p_lo[:, None], out=short)
            for x, p in zip(whole, (p_hi, p_le, p_rh)):
                x ^= np.bitwise_and(mask, p[:, None], out=part)
    r, c = np.nonzero(pr)
    le, rh = le[r, c], rh[r, c]
    if single:
        right, left, rh, le = left >> U(63), left & TOP, le >> U(63), le & TOP
    return win, left, right, best, (r, le, rh, pr[r, c])


def _packed(bits: np.ndarray) -> np.ndarray:
    """n x 64 x m bits as n x m words, whose bits are the 64."""
    raw = np.packbits(bits, axis=1, bitorder="little").transpose(0, 2, 1)
    return np.ascontiguousarray(raw).view("<u8")[:, :, 0]


def _right(win, best, edge: int):
    """The equations of lanes' right columns, solved for these: what each column takes of the equations' right sides (lanes x 64 columns, words
    over equations), and what the columns get if an equation's right side changes or, where a column has no equation, if its own value does."""
    lanes = win.shape[1]
    body, own = np.zeros((lanes, 64), U), np.zeros((lanes, 64), U)
    q = np.arange(edge, dtype=U)
    has = best.T > 0
    body[:, :edge] = win.T << q & U((1 << edge) - 1)
    own[:, :edge] = np.where(has, U(1) << q, U(0))
    for k in range(edge - 1, 0, -1):
        mask = U(0) - (body[:, :k] >> U(k) & U(1))
        body[:, :k] ^= mask & body[:, k : k + 1]
        own[:, :k] ^= mask & own[:, k : k + 1]

    def across(x):
        return _packed(np.unpackbits(x.astype("<u8").view(np.uint8).reshape(lanes, 64, 8), axis=2, bitorder="little"))[:, :edge]

    return own, np.where(has, across(own), across(body) ^ U(1) << q)


class Borders:
    """Solutions of the left columns of the current bucket, for each instance: a vector for each right side, and what may be added to any.
    Above the columns' bits, a number says which of the bucket before's free vectors it stands for."""

    def __init__(self, many: int, sides: int, edge: int):
        self.many, self.sides, self.edge, self.mask = many, sides, edge, (1 << edge) - 1
        self.base, self.free = [[0] * sides for _ in range(many)], [[1 << q for q in range(edge)] for _ in range(many)]
        self.trail: list[tuple[list, list]] = []

    def _vectors(self) -> np.ndarray:
        out = np.zeros((self.many, self.sides + max(map(len, self.free))), U)
        for t, (base, free) in enumerate(zip(self.base, self.free, strict=True)):
            out[t, : self.sides + len(free)] = [x & self.mask for x in base + free]
        return out

    def take(self, line, left, rhs, level) -> int:
        """Takes in equations by class, as far as they agree: the class from which on they do, the last class being undone as a whole."""
        sides, bar, group, fresh = self.sides, 0, None, []
        seen: list[dict[int, int]] = [{} for _ in range(self.many)]
        bits = np.packbits(np.bitwise_count(left[:, None] & self._vectors()[line]) & 1, axis=1, bitorder="little")
        wide, raw = bits.shape[1], bits.tobytes()
        for k, (t, y, v) in enumerate(zip(line.tolist(), rhs.tolist(), level.tolist(), strict=True)):
            if v != group:
                group, fresh = v, []
            row, held = int.from_bytes(raw[k * wide : k * wide + wide], "little") ^ y, seen[t]
            while body := row >> sides:
                low = body & -body
                if low not in held:
                    held[low] = row
                    fresh.append((held, low))
                    break
                row ^= held[low]
            else:
                if row:
                    bar = v + 1
                    for held, low in fresh:
                        del held[low]
                    break
        for t, held in enumerate(seen):
            base, free = self.base[t], self.free[t][:]
            for low in sorted(held):
                at, row = low.bit_length() - 1, held[low]
                v, free[at] = free[at], 0
                rest = (row >> sides) ^ low
                while rest:
                    z = rest & -rest
                    free[z.bit_length() - 1] ^= v
                    rest ^= z
                base = [x ^ v if row >> r & 1 else x for r, x in enumerate(base)]
            self.base[t], self.free[t] = base, [v for v in free if v]
        return bar

    def step(self, own, change, dropped, left, right) -> None:
        """On to the next bucket, whose left columns are this one's right ones: own and change as of ``_right``, dropped the columns whose
        equations do not hold or do not exist; left: the left columns in the equations, right: their right sides' bits."""
        sides, edge = self.sides, self.edge
        self.trail.append((self.base, self.free))
        on = np.bitwise_count(left[:, :, None] & self._vectors()[:, None, :]) & 1
        on[:, :, :sides] ^= right
        found = _packed(np.bitwise_count(own[:, :, None] & _packed(on)[:, None, :]) & 1).tolist()
        loose: list[list[int]] = [[] for _ in range(self.many)]
        t, q = np.nonzero(dropped)
        for i, v in zip(t.tolist(), change[t, q].tolist(), strict=True):
            loose[i].append(v)
        for i, (x, free) in enumerate(zip(found, loose, strict=True)):
            free += [v | 1 << (edge + j) for j, v in enumerate(x[sides : sides + len(self.free[i])]) if v]
            if len(free) > edge:  # some are sums of others
                least: list[tuple[int, int]] = []
                for v in free:
                    for p, low in least:
                        if v & low:
                            v ^= p
                    if v & self.mask:
                        least.append((v, v & -v))
                loose[i] = [v for v, _ in least]
        self.base, self.free = [x[:sides] for x in found], loose

    def settle(self, noise: int) -> np.ndarray:
        """Values of all borders: buckets + 1, instances, sides."""
        out = np.zeros((len(self.trail) + 1, self.many, self.sides), U)
        for t in range(self.many):
            for r in range(self.sides):
                pick = noise
                for b, (base, free) in reversed(list(enumerate([*self.trail, (self.base, self.free)]))):
                    x = base[t][r]
                    for j, v in enumerate(free[t]):
                        if pick >> j & 1:
                            x ^= v
                    out[b, t, r] = x & self.mask
                    pick = x >> self.edge
        return out


def insert(start, row, turn, level, care, bits, instances: int, layer, packed: bool, noise: int):
    """Sets the layer's thresholds. Returns the solutions, instances x slots, and the keys that did not fit, or None if they must."""
    bucket, width, edge = layer.bucket, layer.width, layer.width - 1
    many, sides = (1, instances) if packed else (instances, 1)
    count = (layer.slots - width) // bucket + 1
    which = start // bucket
    if packed:
        key, line, rhs = np.arange(len(start)), np.zeros(len(start), np.int64), bits & U((1 << instances) - 1)
    else:
        key, bit = (np.concatenate(x) for x in zip(*[(k, np.full(len(k), i)) for i in range(instances) for k in [np.flatnonzero(care >> U(i) & U(1))]], strict=True))
        line, rhs = (turn[key] + bit) % instances, bits[key] >> bit.astype(U) & U(1)
    lane = which[key] * many + line
    order = np.argsort(lane, kind="stable")
    key, lane, rhs = key[order], lane[order], rhs[order]
    lanes = count * many
    parts, rest = [], []
    for a in range(0, lanes, LANES):
        i, j = np.searchsorted(lane, [a, a + LANES])
        k = key[i:j]
        *pivots, (r, le, rh, pr) = _sweep(start[k] % bucket, row[k], rhs[i:j], (level[k] + 1).astype(np.uint8), lane[i:j] - a, min(LANES, lanes - a), bucket, width)
        parts.append(pivots)
        rest.append((r + a, le, rh, pr))
    win, left, right, best = (np.concatenate(x, 1) for x in zip(*parts, strict=True))
    # the pass over the buckets
    r, le, rh, pr = (np.concatenate(x) for x in zip(*rest, strict=True))
    order = np.lexsort((-pr.astype(np.int64), r // many))
    r, le, rh, pr = r[order], le[order], rh[order], pr[order].astype(np.int64) - 1
    ends = np.searchsorted(r // many, np.arange(count + 1)).tolist()
    low = bucket - edge  # the first right column
    own, change = _right(win[low:], best[low:], edge)
    l_left = np.zeros((lanes, 64), U)
    l_left[:, :edge] = left[low:].T
    l_right = np.zeros((lanes, 64, sides), np.uint8)
    l_right[:, :edge] = right[low:].T[:, :, None] >> np.arange(sides, dtype=U) & U(1)
    l_best = np.ascontiguousarray(best[low:].T).astype(np.int64)
    borders, bars = Borders(many, sides, edge), np.zeros(count, np.int64)
    for b in range(count):
        i, j, k = ends[b], ends[b + 1], slice(b * many, b * many + many)
        if j > i:
            bars[b] = borders.take(r[i:j] % many, le[i:j], rh[i:j], pr[i:j])
            if bars[b] and not layer.levels:
                return None
        borders.step(own[k], change[k], l_best[k] <= bars[b], l_left[k], l_right[k])
    if layer.levels:
        layer.thresholds[:count] = bars
    # back through the lanes, all at once
    edges = borders.settle(noise)
    here, after = edges[:-1].reshape(lanes, sides), edges[1:].reshape(lanes, sides)
    best = best > np.repeat(bars, many)[None]
    out = np.zeros((bucket, lanes, sides), np.uint8)
    for q in range(edge):
        out[q] = here >> U(q) & U(1)
    window, side = after.copy(), np.arange(sides, dtype=U)
    slot = np.repeat(np.arange(count), many) * bucket
    for p in range(bucket - 1, edge - 1, -1):
        k = p - edge
        x = (right[k][:, None] >> side ^ np.bitwise_count(left[k][:, None] & here ^ (win[k] >> U(1))[:, None] & window)) & U(1)
        x = np.where(best[k][:, None], x, (U(noise) >> (slot + p & 63).astype(U) & U(1))[:, None])
        out[p] = x
        window = (window << U(1) | x) & U((1 << 63) - 1)
    lines = np.zeros((many, sides, count * bucket + edge), np.uint8)
    lines[:, :, : count * bucket] = out.reshape(bucket, count, many, sides).transpose(2, 3, 1, 0).reshape(many, sides, -1)
    lines[:, :, count * bucket :] = (edges[-1][:, :, None] >> np.arange(edge, dtype=U) & U(1)).astype(np.uint8)
    solution = np.zeros((instances, layer.slots), np.uint8)
    n = min(layer.slots, lines.shape[2])
    solution[:, :n] = lines.reshape(instances, -1)[:, :n]
    return solution, np.flatnonzero(level < bars[which]) if layer.levels else np.zeros(0, np.int64)


def sparse(lane, columns, rhs, lanes: int, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Small systems, each a lane, of rows with a few ones (columns: rows x ones; two in one place cancel): solutions as lanes x size bits, and
    which lanes have one. As long as a row has one open column, it gives that in terms of others; where there is none, the next column of
    most rows becomes an unknown of a dense system, which is solved last."""
    n, ones = columns.shape
    at = np.sort(columns, 1)
    for k in range(ones - 1):  # equal ones cancel
        same = (at[:, k] == at[:, k + 1]) & (at[:, k] >= 0)
        at[same, k], at[same, k + 1] = -1, -1
        at.sort(1)
    at = np.where(at < 0, lanes * size, lane[:, None] * size + at)  # the last is a column of zeros
    rest = (at < lanes * size).sum(1)
    which = np.bitwise_xor.reduce(np.where(at < lanes * size, at, 0), 1)
    flat = at.ravel()
    by = np.argsort(flat, kind="stable")
    count = np.bincount(flat, minlength=lanes * size + 1)
    begin, by = np.cumsum(count) - count, by // ones
    order = np.argsort(-count[:-1].reshape(lanes, size), axis=1, kind="stable") + np.arange(lanes)[:, None] * size
    terms = np.zeros((lanes * size + 1, 4), U)
    value = np.zeros(lanes * size + 1, U)
    known, owner = np.zeros(lanes * size + 1, bool), np.zeros(lanes * size + 1, np.int64)
    mark = np.zeros(n, np.int64)
    used, turn, unknowns = np.zeros(n, bool), np.zeros(lanes, np.int64), np.zeros(lanes, np.int64)
    busy = np.bincount(lane[rest > 0], minlength=lanes)
    ready = np.flatnonzero(rest == 1)
    while len(ready) or busy.any():
        c = which[ready]
        owner[c] = ready
        mine = owner[c] == ready
        rows, c = ready[mine], c[mine]
        used[rows] = True
        others = at[rows].T
        terms[c], value[c] = reduce(xor, (terms[x] for x in others)), reduce(xor, (value[x] for x in others), rhs[rows])
        moved = np.zeros(lanes, bool)
        moved[lane[rows]] = True
        known[c] = True
        stuck = np.flatnonzero(~moved & (busy > 0))
        if len(stuck):
            old = stuck
            while len(old := old[known[order[old, turn[old]]]]):
                turn[old] += 1
            new, k = order[stuck, turn[stuck]], unknowns[stuck]
            if int(k.max()) >= 64 * terms.shape[1]:
                terms = np.concatenate([terms, np.zeros_like(terms[:, :1])], 1)
            terms[new, k >> 6] = U(1) << (k & 63).astype(U)
            unknowns[stuck] += 1
            known[new] = True
            c = np.concatenate([c, new])
        many = count[c]
        touched = by[np.repeat(begin[c] - np.cumsum(many) + many, many) + np.arange(int(many.sum()))]
        np.subtract.at(rest, touched, 1)
        np.bitwise_xor.at(which, touched, np.repeat(c, many))
        left = rest[touched]
        busy -= np.bincount(lane[_once(touched[left == 0], mark)], minlength=lanes)
        ready = _once(touched[left == 1], mark)
    rows = np.flatnonzero(~used)
    body = np.concatenate([np.bitwise_xor.reduce(terms[at[rows]], 1), (np.bitwise_xor.reduce(value[at[rows]], 1) ^ rhs[rows])[:, None]], 1)
    good, found = np.zeros(lanes, bool), np.zeros((lanes, terms.shape[1]), U)
    for a in range(0, lanes, DENSE):
        some = np.flatnonzero((lane[rows] >= a) & (lane[rows] < a + DENSE))
        found[a : a + DENSE], good[a : a + DENSE] = dense(lane[rows[some]] - a, body[some], min(DENSE, lanes - a))
    out = value[:-1].reshape(lanes, size) ^ np.bitwise_count(np.bitwise_xor.reduce(terms[:-1].reshape(lanes, size, -1) & found[:, None], 2)) & U(1)
    return out.astype(np.uint8), good


def _once(rows: np.ndarray, mark: np.ndarray) -> np.ndarray:
    """Each of rows once; mark is room for a number per row."""
    turn = np.arange(len(rows))
    mark[rows] = turn
    return rows[mark[rows] == turn]


def dense(lane, rows, lanes: int) -> tuple[np.ndarray, np.ndarray]:
    """Systems, each a lane, of rows of words, the last of them the right side: solutions as lanes x words, and which lanes have one. A
    row takes part from its first column on."""
    words = rows.shape[1] - 1
    some = rows.any(1)
    lane, rows = lane[some], rows[some]
    first = (rows != 0).argmax(1)
    order = np.lexsort((lane, first))
    lane, rows, at = lane[order], rows[order], np.searchsorted(first[order], np.arange(words + 2))
    pivots, has, side = np.zeros((words * 64, words, lanes), U), np.zeros((words * 64, lanes), bool), np.zeros((words * 64, lanes), U)
    body, alive, every = np.zeros((words + 2, lanes, 0), U), np.zeros((lanes, 0), bool), np.arange(lanes)
    for k in range(words):  # body: words from k on and right sides x lanes x rows
        r, c = np.nonzero(alive)
        old, new = np.bincount(r, minlength=lanes), np.bincount(lane[at[k] : at[k + 1]], minlength=lanes)
        most = int((old + new).max(initial=0))
        merged, live = np.zeros((words + 1 - k, lanes * most), U), np.zeros(lanes * most, bool)
        fresh = lane[at[k] : at[k + 1]]
        place = np.arange(len(r)) - (np.cumsum(old) - old)[r] + r * most
        then = np.arange(len(fresh)) - (np.cumsum(new) - new - old)[fresh] + fresh * most
        merged[:, place], merged[:, then] = body[1:, r, c], rows[at[k] : at[k + 1], k:].T
        live[place] = live[then] = True
        body, alive = merged.reshape(words + 1 - k, lanes, most), live.reshape(lanes, most)
        if not most:
            continue
        for d in range(64):
            bit = body[0] >> U(d) & U(1)
            key = bit.astype(bool)
            key &= alive
            top = key.argmax(1)
            some = key[every, top]
            if not some.any():
                continue
            p = np.where(some, body[:, every, top], U(0))
            q = 64 * k + d
            pivots[q, k:], side[q], has[q] = p[:-1], p[-1], some
            alive[every[some], top[some]] = False
            bit[every, top] = 0
            np.negative(bit.view(np.int64), out=bit.view(np.int64))
            for x, y in zip(body, p, strict=True):
                x ^= bit & y[:, None]
            body[:, every[some], top[some]] = 0
    wrong = np.where(alive, body[-1], U(0)).any(1)
    wrong |= np.bincount(lane[at[words] : at[words + 1]], minlength=lanes) > 0  # rows without a column, but with a right side
    z = np.zeros((words, lanes), U)
    for q in range(64 * words - 1, -1, -1):
        k = q >> 6
        b = (np.bitwise_count(pivots[q, k:] & z[k:]).sum(0).astype(U) ^ side[q]) & U(1)
        z[k] |= np.where(has[q], b, U(0)) << U(q & 63)
    return z.T, ~wrong
