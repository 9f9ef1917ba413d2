"""What happens inside one shard, on numpy arrays: solving a map's structures and reading them.

A solver takes hashes and what is to be stored and gives parts (name -> bytes) and counts; a reader takes the parts and gives
values of queried hashes. Nothing here knows Spark.
"""

from __future__ import annotations

import struct

import numpy as np

from predmap.functions import codes, lanes
from predmap.functions.ribbon import BitStore, mix

U = np.uint64


#: One letter for each part of a shard's structure.
NAMES = {"filter": b"f", "correct": b"c", "fixed": b"v", "bits": b"b", "sparse": b"s", "exceptions": b"x"}


def pack_parts(parts: dict[str, bytes]) -> bytes:
    """Parts one after the other, each after its letter and length; empty exceptions are left out."""
    return b"".join(NAMES[k] + struct.pack("<I", len(v)) + v for k, v in parts.items() if k != "exceptions" or len(v) > 8)


def unpack_parts(data: bytes) -> dict[str, bytes]:
    out, at, names = {"exceptions": struct.pack("<q", 0)}, 0, {v: k for k, v in NAMES.items()}
    while at < len(data):
        size = struct.unpack_from("<I", data, at + 1)[0]
        out[names[data[at : at + 1]]] = data[at + 5 : at + 5 + size]
        at += 5 + size
    return out


def coins(h: np.ndarray) -> np.ndarray:
    """Four 16-bit coins per key, the same when building and when querying."""
    return mix(h, 31).astype(np.int64) & 0x7FFFFFFFFFFFFFFF


def unique_keys(h1: np.ndarray, h2: np.ndarray, vid: np.ndarray):
    """Rows to keep (each key once); raises if a key has two values. Also rows whose h1 is another key's: they become exceptions."""
    order = np.lexsort((h2, h1))
    a, b, v = h1[order], h2[order], vid[order]
    same = np.concatenate([[False], (a[1:] == a[:-1]) & (b[1:] == b[:-1])])
    if (same[1:] & (v[1:] != v[:-1])).any():
        raise ValueError("not a function: a key has more than one value")
    order, a = order[~same], a[~same]
    clash = np.concatenate([[False], a[1:] == a[:-1]])
    return order[~clash], order[clash]


def pack_exceptions(h1, h2, vid) -> bytes:
    return struct.pack("<q", len(h1)) + h1.astype("<i8").tobytes() + h2.astype("<i8").tobytes() + vid.astype("<i8").tobytes()


def apply_exceptions(data: bytes, h1, h2, out) -> None:
    n = struct.unpack_from("<q", data)[0]
    if n:
        a, b, v = np.frombuffer(data, "<i8", 3 * n, 8).reshape(3, n)
        known = {(x, y): z for x, y, z in zip(a.tolist(), b.tolist(), v.tolist(), strict=True)}
        for i in np.flatnonzero(np.isin(h1, a)).tolist():
            out[i] = known.get((int(h1[i]), int(h2[i])), out[i])


def _positions(first: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Running sum of size within groups whose first rows are given, before each row."""
    run = np.cumsum(size) - size
    return run - np.repeat(run[first], np.diff(np.append(first, len(size)))) if len(size) else run


def solve_guided(h1, h2, vid, count, path, cfg) -> tuple[dict[str, bytes], dict[str, int]]:
    """count decisions per key, their bytes in path (r, plus 128 for the unlikely branch). First the filter: r ones for each unlikely
    branch and nothing for likely ones. Then, for each decision that passes the filter (as all unlikely ones do), a correction bit."""
    h = h1.view(U)
    r, rare = (path & 127).astype(np.int64), path > 127
    some = count > 0
    first = (np.cumsum(count) - count)[some]
    owner = np.repeat(np.arange(len(h)), count)
    place = _positions(first, r)
    depth = np.zeros(len(h), np.int64)
    np.add.at(depth, owner, r)
    long = (depth > 64) | (count > 64)
    use = ~long[owner]
    care = np.zeros(len(h), U)
    want = use & rare & (r > 0)
    ones = ((U(1) << r[want].astype(U)) - U(1)) << place[want].astype(U)
    np.bitwise_or.at(care, owner[want], ones)
    front = BitStore.build(h, care, care, cfg)
    match = rare | (r == 0)
    ask = np.flatnonzero(use & ~match)
    match[ask] = front.ones(h[owner[ask]], place[ask], r[ask], cfg)
    nth = _positions(first, match.astype(np.int64))
    keep = use & match
    care2, bits2 = np.zeros(len(h), U), np.zeros(len(h), U)
    bit = U(1) << nth[keep].astype(U)
    np.bitwise_or.at(care2, owner[keep], bit)
    np.bitwise_or.at(bits2, owner[keep], np.where(rare[keep], bit, U(0)))
    back = BitStore.build(h, care2, bits2, cfg, seed=cfg.seed + 5000)
    odd = np.flatnonzero(long)
    parts = {"filter": front.to_bytes(), "correct": back.to_bytes(), "exceptions": pack_exceptions(h1[odd], h2[odd], vid[odd])}
    f, c = front.size_bits(), back.size_bits()
    return parts, {"filter_demand": int(np.bitwise_count(care).sum()), "correct_demand": int(keep.sum()), **{k: f[k] + c[k] for k in f}, "odd": len(odd)}


def read_guided(parts: dict, h1, h2, w, cfg) -> np.ndarray:
    h = h1.view(U)
    front, back = parts["filter"].reader(h, cfg), parts["correct"].reader(h, cfg, cfg.seed + 5000)
    return codes.walk(w, cfg, front.ones, lambda rows, at: back.read(rows, at) == 1, coins(h))


def solve_fixed(h1, vid, bits: int, cfg):
    store = BitStore.build(h1.view(U), vid, vid.astype(U), cfg, packed_bits=bits) if bits else BitStore(1, [])
    return {"fixed": store.to_bytes()}, {"filter_demand": 0, "correct_demand": bits * len(h1), **store.size_bits(), "odd": 0}


def solve_bits(h1, bits, length, cfg):
    """Strings of length bits, in rows of 64-bit words; under the layout "per_position" a store of its own for every position. Each
    word of the strings has stores of its own, so strings may have any length."""
    length = np.asarray(length, np.int64)
    if int(length.max(initial=0)) > 64 * bits.shape[1]:
        raise ValueError("a string is longer than its words")
    stores = []
    for k in range(bits.shape[1]):
        some = np.flatnonzero(length > 64 * k) if k else np.arange(len(length))
        h, word, n = mix(h1[some].view(U), 8000 + k) if k else h1.view(U), bits[some, k].view(U), np.clip(length[some] - 64 * k, 0, 64).astype(U)
        care = np.where(n >= 64, ~U(0), (U(1) << (n & U(63))) - U(1))
        if cfg.layout == "per_position":
            for i in range(int(n.max(initial=0))):
                at = np.flatnonzero(n > i)
                one = np.ones(len(at), U)
                stores.append((k, i, BitStore.build(h[at], one, word[at] >> U(i) & U(1), cfg, seed=cfg.seed + 7 * i)))
        else:
            stores.append((k, 0, BitStore.build(h, care, word, cfg)))
    sizes = [s.size_bits() for _, _, s in stores] or [{"words": 0, "bumps": 0, "header": 0}]
    blob = b"".join(struct.pack("<HBI", k, i, len(b)) + b for k, i, b in ((k, i, s.to_bytes()) for k, i, s in stores))
    return {"bits": blob}, {"filter_demand": 0, "correct_demand": int(length.sum()), **{k: sum(s[k] for s in sizes) for k in sizes[0]}, "odd": 0}


def load_bits(blob: bytes) -> list[tuple[int, int, BitStore]]:
    """(word, position, store)."""
    at, out = 0, []
    while at < len(blob):
        k, i, size = struct.unpack_from("<HBI", blob, at)
        out.append((k, i, BitStore.from_bytes(blob[at + 7 : at + 7 + size])))
        at += 7 + size
    return out


def read_bits(stores: list[tuple[int, int, BitStore]], h1, length: int, cfg) -> np.ndarray:
    """A window of length bits per key, in rows of words; what lies beyond a key's own string is junk."""
    out = np.zeros((len(h1), max(1, -(-length // 64))), U)
    for k, i, s in stores:
        h = mix(h1.view(U), 8000 + k) if k else h1.view(U)
        if cfg.layout == "per_position":
            out[:, k] |= s.read(h, np.zeros(len(h), np.int64), cfg, cfg.seed + 7 * i).astype(U) << U(i)
        elif 64 * k < length:
            out[:, k] = s.read_all(h, min(64, length - 64 * k), cfg)
    return out


class SparseStore:
    """External entropy map: every stored bit is the parity of four random positions of a small block; blocks of about ``block`` bits,
    solved densely, with about 2.4 % more positions than bits. No filter."""

    block, factor, slack = 768, 1.024, 16
    together = 512  # blocks that are solved in lock-step

    def __init__(self, blocks: list[tuple[int, int, bytes]]):
        self.blocks = blocks
        self.bits: np.ndarray | None = None

    @staticmethod
    def columns(h: np.ndarray, size: int | np.ndarray, seed: int) -> np.ndarray:
        x = mix(h, seed)
        return np.stack([(mix(x, k) >> U(33)).astype(np.int64) % size for k in range(4)], 1)

    @classmethod
    def build(cls, h: np.ndarray, bits: np.ndarray) -> SparseStore:
        count = max(1, -(-len(h) // cls.block))
        where = (mix(h, 4242) >> U(40)).astype(np.int64) % count
        order = np.argsort(where, kind="stable")
        at = np.searchsorted(where[order], np.arange(count + 1))
        out: list = [None] * count
        for first in range(0, count, cls.together):
            todo, seed = np.arange(first, min(count, first + cls.together)), 0
            while len(todo):  # those that have no solution again, with another seed
                many = at[todo + 1] - at[todo]
                sizes = (many * cls.factor).astype(np.int64) + cls.slack + 2 * seed
                lane = np.repeat(np.arange(len(todo)), many)
                rows = np.concatenate([order[at[k] : at[k + 1]] for k in todo])
                z, good = lanes.sparse(lane, cls.columns(h[rows], sizes[lane], seed), bits[rows].astype(U), len(todo), int(sizes.max()))
                for k in np.flatnonzero(good).tolist():
                    size = int(sizes[k])
                    out[todo[k]] = size, seed, np.packbits(z[k, :size], bitorder="little").tobytes()
                todo, seed = todo[~good], seed + 1
        return cls(out)

    def read(self, h: np.ndarray) -> np.ndarray:
        where = (mix(h, 4242) >> U(40)).astype(np.int64) % len(self.blocks)
        if self.bits is None:
            self.sizes, self.seeds = (np.array([x[k] for x in self.blocks], np.int64) for k in (0, 1))
            self.bits = np.unpackbits(np.frombuffer(b"".join(x[2] for x in self.blocks), np.uint8), bitorder="little")
        room = -(-self.sizes // 8) * 8
        first = np.cumsum(room) - room
        out = np.zeros(len(h), np.uint8)
        for seed in np.unique(self.seeds).tolist():
            rows = np.flatnonzero(self.seeds[where] == seed)
            k = where[rows]
            out[rows] = self.bits[first[k][:, None] + self.columns(h[rows], self.sizes[k], seed)].sum(1) & 1
        return out

    def to_bytes(self) -> bytes:
        return struct.pack("<I", len(self.blocks)) + b"".join(struct.pack("<HB", s, k) + z for s, k, z in self.blocks)

    @classmethod
    def from_bytes(cls, data: bytes) -> SparseStore:
        n, at, out = struct.unpack_from("<I", data)[0], 4, []
        for _ in range(n):
            size, seed = struct.unpack_from("<HB", data, at)
            z = -(-size // 8)
            out.append((size, seed, data[at + 3 : at + 3 + z]))
            at += 3 + z
        return cls(out)


def solve_sparse(h1, vid, lengths, words, cfg):
    """Global code words of values (Huffman), bit i of a key under its own derived key."""
    h, n = h1.view(U), lengths[vid]
    keys, bits = [], []
    for i in range(int(n.max(initial=0))):
        at = np.flatnonzero(n > i)
        keys.append(mix(h[at], 6000 + i))
        bits.append(words[vid[at]] >> (n[at] - 1 - i) & 1)
    store = SparseStore.build(np.concatenate(keys) if keys else np.zeros(0, U), np.concatenate(bits) if bits else np.zeros(0, np.int64))
    return {"sparse": store.to_bytes()}, {"filter_demand": 0, "correct_demand": int(n.sum()), "words": sum(8 * len(b[2]) for b in store.blocks), "bumps": 0, "header": 32 + 24 * len(store.blocks), "odd": 0}


def read_sparse(store: SparseStore, h1, lengths, words) -> np.ndarray:
    """Bit by bit, until a key's bits are the code word of a value; words of one length are looked up together."""
    h, lengths, words = h1.view(U), np.asarray(lengths, np.int64), np.asarray(words, np.int64)
    out = np.zeros(len(h), np.int64)
    if len(none := np.flatnonzero(lengths == 0)):
        return out + none[-1]
    code, todo = np.zeros(len(h), np.int64), np.arange(len(h))
    for i in range(int(lengths.max(initial=0))):
        code[todo] = code[todo] << 1 | store.read(mix(h[todo], 6000 + i))
        ends = np.flatnonzero(lengths == i + 1)
        if not len(ends):
            continue
        ends = ends[np.argsort(words[ends], kind="stable")]
        at = np.minimum(np.searchsorted(words[ends], code[todo]), len(ends) - 1)
        hit = words[ends[at]] == code[todo]
        out[todo[hit]] = ends[at[hit]]
        todo = todo[~hit]
    return out


def canonical_words(lengths) -> np.ndarray:
    """Code words for lengths, leaves ordered by length, as in the per-key codes."""
    order = np.argsort(lengths, kind="stable")
    depth = int(max(lengths, default=0))
    out, at = np.zeros(len(lengths), np.int64), 0
    for v in order.tolist():
        out[v] = at >> (depth - lengths[v])
        at += 1 << (depth - lengths[v])
    return out

