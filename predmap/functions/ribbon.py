"""Bits of keys as solutions of banded linear systems over GF(2).

A row has a start and ``width`` coefficient bits; a key's bit is the parity of the row and the solution's window there. Rows
are inserted bucket by bucket; a bucket whose rows contradict what is stored bumps its lower classes to the next layer, and
the last layer has slack and new seeds until it solves. Several systems (instances) of equal size share starts, rows, buckets
and thresholds: bit i of a key belongs to instance (offset of the key + i) mod instances, so strings of any length spread evenly.
Their solutions are stored word by word in turn, so a key's windows lie side by side.
"""

from __future__ import annotations

import struct
from dataclasses import dataclass

import numpy as np

from predmap.functions import lanes

U = np.uint64
#: Equations from which on a system is solved in lock-step; smaller ones are inserted row by row.
LARGE = 6_000
#: Bits that an instance holds at least, by ribbon width: what it costs of its own stays small beside them, and as instances bump
#: together, narrow ribbons, which bump more, have fewer of them.
LEAST_BITS = {16: 20_000, 32: 20_000, 64: 8_000}
#: The multipliers of the splitmix64 finaliser.
MIX = (U(0xBF58476D1CE4E5B9), U(0x94D049BB133111EB))


def mix(h: np.ndarray, seed: int | np.ndarray) -> np.ndarray:
    """64-bit finaliser; another seed, which may be each key's own, gives independent bits."""
    if isinstance(seed, np.ndarray):
        x = np.asarray(h, U) + (seed.astype(U) * U(0x9E3779B97F4A7C15) + U(0x632BE59BD9B4E019))
    else:
        x = np.asarray(h, U) + U((seed * 0x9E3779B97F4A7C15 + 0x632BE59BD9B4E019) & (1 << 64) - 1)
    y = x >> U(30)
    x ^= y
    x *= MIX[0]
    x ^= np.right_shift(x, U(27), out=y)
    x *= MIX[1]
    x ^= np.right_shift(x, U(31), out=y)
    return x


def below(h: np.ndarray, n: int) -> np.ndarray:
    """Uniform in [0, n) from the upper 32 bits."""
    return ((h >> U(32)) * U(n) >> U(32)).astype(np.int64)


def parity(x: np.ndarray) -> np.ndarray:
    return np.bitwise_count(x) & 1


@dataclass
class Layer:
    seed: int  # beside the store's
    slots: int  # per instance
    width: int
    bucket: int
    levels: int  # 0: nothing bumps
    thresholds: np.ndarray  # per bucket: classes below it are bumped
    words: np.ndarray  # of all instances in turn

    def rows(self, h: np.ndarray, instances: int, base: int = 0):
        """Start, coefficients, offset and class of keys; base is the store's seed."""
        a, b = mix(h, base + self.seed), mix(h, base + self.seed + 1)
        start = below(a, self.slots - self.width + 1)
        row = (b & U((1 << self.width) - 1)) | U(1)
        turn = (a & U(0xFFFF)).astype(np.int64) % instances
        level = ((a >> U(16)) & U(0xFF)).astype(np.int64) % max(1, self.levels)
        return start, row, turn, level

    def instances_bytes(self, instances: int) -> int:
        """Stored bytes of the solutions."""
        return instances * (self.slots // 64 * 8 + -(-(self.slots % 64) // 8))

    def bumped(self, start, level):
        return level < self.thresholds[start // self.bucket] if self.levels else np.zeros(len(start), bool)


def _insert(order, start, row, turn, level, care, bits, instances, layer: Layer, packed: bool):
    """Online elimination. Returns coefficient and right-side lists per instance and the keys that did not fit, or None if they must."""
    m = layer.slots
    coef = [[0] * m for _ in range(instances)]
    rhs = [[0] * m for _ in range(instances)]
    out: list[int] = []
    start, row, turn, level, care, bits = (x.tolist() for x in (start, row, turn, level, care, bits))
    size, levels = layer.bucket, layer.levels
    bucket, bar, fresh, group = -1, 0, [], []
    for k in order.tolist():
        s0 = start[k]
        if s0 // size != bucket:
            bucket, bar, fresh, group = s0 // size, 0, [], []
        v = level[k]
        if v < bar:
            out.append(k)
            continue
        if group and level[group[-1]] != v:
            fresh, group = [], []
        group.append(k)
        c0, todo, val = row[k], care[k], bits[k]
        t = turn[k]
        ok = True
        while todo:
            low = todo & -todo
            i = 0 if packed else low.bit_length() - 1
            todo = 0 if packed else todo ^ low
            at = (t + i) % instances
            cs, rs = coef[at], rhs[at]
            c, b, s = c0, val if packed else val >> i & 1, s0
            while True:
                here = cs[s]
                if not here:
                    cs[s], rs[s] = c, b
                    fresh.append((at, s))
                    break
                c ^= here
                b ^= rs[s]
                if not c:
                    if b:
                        ok = False
                    break
                z = (c & -c).bit_length() - 1
                c >>= z
                s += z
            if not ok:
                break
        if not ok:
            if not levels:
                return None
            for at, s in fresh:
                coef[at][s] = 0
            out += group
            thresholds = layer.thresholds
            thresholds[bucket] = bar = v + 1
            fresh, group = [], []
    return coef, rhs, out


def _back(coef: list[int], rhs: list[int], m: int, noise: int) -> list[int]:
    """Solution, a bit for each slot; free slots take noise."""
    out, window = [0] * m, 0
    for s in range(m - 1, -1, -1):
        c = coef[s]
        b = (rhs[s] ^ (c >> 1 & window).bit_count()) & 1 if c else noise >> (s & 63) & 1
        out[s] = b
        window = (window << 1 | b) & 0x7FFFFFFFFFFFFFFF
    return out


def solve(h: np.ndarray, care: np.ndarray, bits: np.ndarray, instances: int, cfg, packed: bool = False, seed: int = 0) -> list[Layer]:
    """Layers of a store for keys h: bit i of bits where bit i of care is set. packed: every key has all instances' bits, so
    one elimination with right sides of several bits serves all."""
    layers: list[Layer] = []
    h, care, bits = (np.asarray(x, U) for x in (h, care, bits))
    while True:
        n = len(h) if packed else int(np.bitwise_count(care).sum())
        if not n:
            return layers
        each = n if packed else -(-n // instances)
        last = len(layers) >= cfg.max_layers - 1 or each < 192
        width = min(cfg.ribbon_width, 64 if each > 4000 else 32 if each > 400 else 16)
        tries = 0
        while True:
            slots = max(width + 1, int(each * cfg.last_slack) + width // 2 + tries * max(2, each // 50)) if last else max(width + 1, int(each * cfg.load))
            bucket = max(128, cfg.bucket // instances)
            layer = Layer(2 * len(layers) + 1000 * tries, slots, width, bucket, 0 if last else cfg.threshold_levels, np.zeros(0 if last else slots // bucket + 1, np.uint8), None)
            start, row, turn, level = layer.rows(h, instances, seed)
            if packed:
                turn[:] = 0
            noise = int(mix(np.array([layer.seed], U), 77)[0])
            if n >= LARGE:
                done = lanes.insert(start, row, turn, level, care, bits, instances, layer, packed, noise)
            else:
                order = np.lexsort((-level, start // bucket)) if not last else np.argsort(start, kind="stable")
                done = _insert(order, start, row, turn, level, care, bits, 1 if packed else instances, layer, packed)
                if done:
                    coef, rhs, out = done
                    right = [[b >> t & 1 for b in rhs[0]] if packed else rhs[t] for t in range(instances)]
                    done = np.array([_back(coef[0 if packed else t], right[t], slots, noise) for t in range(instances)], np.uint8), out
            if done:
                break
            tries += 1
        solution, out = done
        words = np.zeros((slots // 64 + 2, instances), U)
        raw = np.zeros((instances, -(-slots // 64) * 8), np.uint8)
        raw[:, : -(-slots // 8)] = np.packbits(solution, axis=1, bitorder="little")
        words[: -(-slots // 64)] = raw.view("<u8").T
        layer.words = words.ravel()
        layers.append(layer)
        at = np.array(out, np.int64)
        h, care, bits = h[at], care[at], bits[at]


class BitStore:
    """Up to 64 bits per key. Strings longer than the number of instances go on in further laps, each a key of its own."""

    def __init__(self, instances: int, layers: list[Layer], packed: bool = False):
        self.instances, self.layers, self.packed = instances, layers, packed

    @classmethod
    def build(cls, h: np.ndarray, care: np.ndarray, bits: np.ndarray, cfg, packed_bits: int = 0, layout: str | None = None, seed: int | None = None) -> BitStore:
        """care: the bits to keep. packed_bits: all keys have that many (one elimination). Bits are masked by the key's hash, so
        reading what was never stored gives fair bits."""
        layout, seed = layout or cfg.layout, cfg.seed if seed is None else seed
        h, care, bits = (np.asarray(x, U) for x in (h, care, bits))
        bits = bits ^ mix(h, seed + 501)
        if packed_bits:
            mask = U((1 << packed_bits) - 1)
            return cls(packed_bits, solve(h, np.full(len(h), mask), bits & mask, packed_bits, cfg, True, seed), True)
        total = int(np.bitwise_count(care).sum())
        longest = int(max(int(care.max(initial=0)).bit_length(), 1))
        many = 1 if layout == "per_bit_key" else max(1, min(longest, total // LEAST_BITS.get(cfg.ribbon_width, 20_000)))
        keys, cares, values = [], [], []
        mask = U((1 << many) - 1) if many < 64 else ~U(0)
        for lap in range(-(-longest // many)):
            part = care >> U(lap * many) & mask
            some = np.flatnonzero(part)
            keys.append(mix(h[some], seed + 900 + lap))
            cares.append(part[some])
            values.append(bits[some] >> U(lap * many) & mask)
        return cls(many, solve(np.concatenate(keys), np.concatenate(cares), np.concatenate(values), many, cfg, False, seed))

    def reader(self, h: np.ndarray, cfg, seed: int | None = None) -> Reader:
        return Reader(self, np.asarray(h, U), cfg.seed if seed is None else seed)

    def read(self, h: np.ndarray, position: np.ndarray, cfg, seed: int | None = None) -> np.ndarray:
        """One bit per key, at its position."""
        return self.reader(h, cfg, seed).read(np.arange(len(h)), np.asarray(position, np.int64))

    def read_all(self, h: np.ndarray, length: int, cfg, seed: int | None = None) -> np.ndarray:
        """The first length bits of each key as an integer."""
        at, out, rows = self.reader(h, cfg, seed), np.zeros(len(h), U), np.arange(len(h))
        for i in range(length):
            out |= at.read(rows, np.full(len(h), i)).astype(U) << U(i)
        return out

    def ones(self, h: np.ndarray, position: np.ndarray, r: np.ndarray, cfg, seed: int | None = None) -> np.ndarray:
        """Whether the r bits from position are all set."""
        return self.reader(h, cfg, seed).ones(np.arange(len(h)), position, r)

    def size_bits(self) -> dict:
        """Stored bits: of solutions, thresholds and headers."""
        words = sum(8 * x.instances_bytes(self.instances) for x in self.layers)
        bumps = sum(8 * -(-len(x.thresholds) * x.levels.bit_length() // 8) for x in self.layers)
        return {"words": words, "bumps": bumps, "header": 8 * (HEAD.size + LAYER.size * len(self.layers))}

    def to_bytes(self) -> bytes:
        out = [HEAD.pack(self.instances, len(self.layers), self.packed)]
        for x in self.layers:
            bits = (x.thresholds[:, None] >> np.arange(x.levels.bit_length(), dtype=np.uint8) & 1).ravel()
            out += [LAYER.pack(x.seed // 1000, x.slots, x.width, x.bucket, x.levels), np.packbits(bits, bitorder="little").tobytes()]
            whole, rest = divmod(x.slots, 64)
            words = x.words.reshape(-1, self.instances).astype("<u8")
            out += [words[:whole].tobytes(), np.ascontiguousarray(words[whole : whole + 1].view(np.uint8).reshape(-1, 8)[:, : -(-rest // 8)]).tobytes()]
        return b"".join(out)

    @classmethod
    def from_bytes(cls, data: bytes) -> BitStore:
        instances, n, packed = HEAD.unpack_from(data)
        at, layers = HEAD.size, []
        for _ in range(n):
            tries, slots, width, bucket, levels = LAYER.unpack_from(data, at)
            at += LAYER.size
            t, each = (slots // bucket + 1 if levels else 0), levels.bit_length()
            size = -(-t * each // 8)
            bits = np.unpackbits(np.frombuffer(data, np.uint8, size, at), count=t * each, bitorder="little").reshape(t, each)
            thresholds = (bits << np.arange(each, dtype=np.uint8)).sum(1, dtype=np.uint8)
            at += size
            whole, rest = divmod(slots, 64)
            words = np.zeros((whole + 2, instances), "<u8")
            words[:whole] = np.frombuffer(data, "<u8", whole * instances, at).reshape(-1, instances)
            at += 8 * whole * instances
            tail = -(-rest // 8)
            words[whole].view(np.uint8).reshape(instances, 8)[:, :tail] = np.frombuffer(data, np.uint8, tail * instances, at).reshape(instances, tail)
            at += tail * instances
            layers.append(Layer(2 * len(layers) + 1000 * tries, slots, width, bucket, levels, thresholds, words.astype(U).ravel()))
        return cls(instances, layers, bool(packed))


#: Stored headers: of a store (instances, layers, packed) and of a layer (tries, slots, width, bucket, levels).
HEAD, LAYER = struct.Struct("<BBB"), struct.Struct("<BIBHB")


class Reader:
    """Keys of one batch in a store: where a lap is asked of many keys, each is hashed once and its layer, window and row are kept for all its
    bits; a lap that few keys reach, or that holds one bit, is worked out for these alone."""

    def __init__(self, store: BitStore, h: np.ndarray, seed: int):
        self.store, self.h, self.seed = store, h, seed
        self.mask = mix(h, seed + 501)
        self.words = np.concatenate([x.words for x in store.layers]) if store.layers else np.zeros(2 * store.instances, U)
        self.laps: dict[int, tuple] = {}

    def _places(self, keys: np.ndarray) -> tuple:
        """(first word, shift, row, turn) of keys that are hashed for their lap; a row of 0 where nothing is stored."""
        store, n = self.store, len(keys)
        word, shift, row, turn = np.zeros(n, np.int64), np.zeros(n, U), np.zeros(n, U), np.zeros(n, np.int64)
        rest, base = np.arange(n), 0
        for layer in store.layers:
            s, c, t, level = layer.rows(keys if len(rest) == n else keys[rest], store.instances, self.seed)
            if layer.levels:
                gone = layer.bumped(s, level)
                here = ~gone
                at, rest, s, c, t = rest[here], rest[gone], s[here], c[here], t[here]
            else:
                at, rest = rest, rest[:0]
            word[at], shift[at], row[at], turn[at] = base + (s >> 6) * store.instances, (s & 63).astype(U), c, 0 if store.packed else t
            base += len(layer.words)
            if not len(rest):
                break
        return word, shift, row, turn

    def _lap(self, k: int) -> tuple:
        """``_places`` of every key in lap k."""
        if k not in self.laps:
            self.laps[k] = self._places(self.h if self.store.packed else mix(self.h, self.seed + 900 + k))
        return self.laps[k]

    def _bits(self, places: tuple, i: np.ndarray) -> np.ndarray:
        word, shift, row, turn = places
        word = word + (turn + i) % self.store.instances
        low = self.words[word] >> shift
        high = np.where(shift > 0, self.words[word + self.store.instances] << ((U(64) - shift) & U(63)), U(0))
        return parity((low | high) & row)

    def read(self, rows: np.ndarray, position: np.ndarray) -> np.ndarray:
        """One bit for each of rows, at its position."""
        if not len(rows):
            return np.zeros(0, np.uint8)
        lap, i = np.divmod(position, self.store.instances)
        out = np.zeros(len(rows), np.uint8)
        many, alone = np.bincount(lap), np.ones(len(rows), bool)
        for k in np.flatnonzero(many).tolist():
            if k in self.laps or self.store.packed or self.store.instances > 1 and 4 * many[k] >= len(self.h):
                at = np.flatnonzero(lap == k)
                out[at] = self._bits(tuple(x[rows[at]] for x in self._lap(k)), i[at])
                alone[at] = False
        at = np.flatnonzero(alone)
        if len(at):
            out[at] = self._bits(self._places(mix(self.h[rows[at]], self.seed + 900 + lap[at])), i[at])
        return out ^ (self.mask[rows] >> (position % 64).astype(U) & U(1)).astype(np.uint8)

    def ones(self, rows: np.ndarray, position: np.ndarray, r: np.ndarray) -> np.ndarray:
        """Whether the r bits from position are all set: bit by bit, as half of the rows fall out at each, and all that is left together once
        that is no more than one bit a row."""
        ok = np.ones(len(rows), bool)
        at, k = np.flatnonzero(r > 0), 0
        while len(at):
            left = r[at] - k
            if int(left.sum()) <= len(rows):
                owner = np.repeat(at, left)
                bit = k + np.arange(len(owner)) - np.repeat(np.cumsum(left) - left, left)
                ok[owner[self.read(rows[owner], position[owner] + bit) == 0]] = False
                break
            got = self.read(rows[at], position[at] + k) == 1
            ok[at[~got]] = False
            at, k = at[got], k + 1
            at = at[r[at] > k]
        return ok


def regular(rows: np.ndarray) -> np.ndarray:
    """Whether each of n systems of m rows (n x m words, whose low m <= 64 bits count) is solvable for every right side."""
    rows = rows.copy()
    n, m = rows.shape
    full, used, every = np.ones(n, bool), np.zeros((n, m), bool), np.arange(n)
    for k in range(m):
        bit = (rows >> np.uint64(k) & np.uint64(1)).astype(bool)
        free = bit & ~used
        at = free.argmax(1)
        some = free[every, at]
        full &= some
        bit[every, at] = False
        used[every, at] |= some
        rows ^= np.where(bit & some[:, None], rows[every, at][:, None], np.uint64(0))
    return full


def solve_dense(rows: np.ndarray, rhs: np.ndarray) -> np.ndarray | None:
    """A solution of a dense 0/1 system over GF(2), or None. For small systems: tests and the share of solvable square ones."""
    a = np.concatenate([rows % 2, (rhs % 2)[:, None]], 1).astype(bool)
    pivots, at = [], 0
    for c in range(rows.shape[1]):
        found = np.flatnonzero(a[at:, c])
        if not len(found):
            continue
        a[[at, at + found[0]]] = a[[at + found[0], at]]
        other = np.flatnonzero(a[:, c])
        a[other[other != at]] ^= a[at]
        pivots.append(c)
        at += 1
        if at == len(a):
            break
    if a[at:, -1].any():
        return None
    z = np.zeros(rows.shape[1], np.uint8)
    z[pivots] = a[: len(pivots), -1]
    return z
