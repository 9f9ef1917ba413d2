"""Suffix dedup: bytes covered by a string of ``LENGTH`` bytes that also starts in a document with a smaller id.

Four steps over chunks of documents (a hash of the id); the texts are shuffled once and that exchange is read three times.

1. Anchors. Of the ``LENGTH - GRAM + 1`` grams in a window of LENGTH bytes one is its anchor: the least by hash, leftmost of ties.
   That depends on the window's bytes alone, so equal windows have equal anchors. Chunks send each shard of hashes its
   distinct (truncated) ones, sorted and packed, about two bytes per anchor.
2. Shards of hashes answer with two bits each: does the gram occur in two documents, and is it hot? A false yes costs work and
   changes nothing.
3. For anchors that are shared, chunks send the bytes of all windows with that anchor (its context) to the anchor's shard.
   Equal contexts are merged and then indexed, all contexts of an anchor together: a run-compressed Burrows-Wheeler transform with the
   mapping of each run's head, suffix samples at run ends and the borders between suffixes that share less than LENGTH bytes.
   Streaming each context backwards through the index, all contexts side by side, gives for every window its matching
   statistics cut at LENGTH: the interval of suffixes that start with it, and their least document.
4. Chunks get back which windows are repeats, and cover their bytes.

Shards and chunks grow in number with the input, never in size. Where a passage is so frequent that its anchors are hot, its
windows go one by one, each distinct one once per chunk, to shards by a hash of the whole window, so what surrounds the passage
in its many documents spreads over all shards. Nothing is compared pair by pair.

Defined results: null text is empty; documents under LENGTH bytes lose nothing; a row with a null id neither loses bytes nor
takes them from others; rows that repeat an id do not count as smaller than each other; matches never cross documents; an empty
table gives no rows; other columns are not read.
"""

from __future__ import annotations

import hashlib
import struct

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from predmap.llm.common import table

NAME = "op6_suffix_dedup"
SQL = None  # tests compare with a dictionary of all windows
LENGTH, GRAM = 50, 16
SLICE, CHUNK_BYTES, SHARD_ANCHORS, INDEX_BYTES, HOT = 1 << 18, 6 << 20, 1 << 17, 1 << 19, 2000
#: Odd multipliers of the gram hash.
M1, M2, M3 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F), np.uint64(0x165667B19E3779F9)
LOW = np.uint64(0xFFFFFFFF)


def grams(buf: np.ndarray) -> np.ndarray:
    """64-bit hash of the GRAM bytes from each place."""
    n = len(buf) - 7
    u = np.empty(n, np.uint64)
    raw = buf.tobytes()
    for o in range(min(8, n)):
        k = (n - o + 7) // 8
        u[o::8] = np.frombuffer(raw, "<u8", count=k, offset=o)
    h = u[: n - 8] * M1
    w = u[8:] * M2
    w ^= w >> np.uint64(29)
    h ^= w
    h *= M3
    h ^= h >> np.uint64(32)
    h *= M1
    return h


class Chunk:
    """Documents of a chunk in order, and the anchors of their windows."""

    def __init__(self, rows: pa.Table):
        ids = rows.column("doc_id").to_pylist()
        data = [x or b"" for x in rows.column("text").cast(pa.binary()).to_pylist()]
        order = sorted(range(len(ids)), key=lambda i: (ids[i] is None, ids[i] or 0, data[i]))
        self.ids = [ids[i] for i in order]
        data = [data[i] for i in order]
        self.size = np.array([len(x) for x in data], np.int64)
        self.start = np.cumsum(self.size) - self.size
        self.raw = b"".join(data)
        self.buf = np.frombuffer(self.raw, np.uint8)

    def anchors(self):
        """Runs of windows with one anchor: first window, last window, anchor's hash, document's number; as arrays."""
        out: list[list[np.ndarray]] = [[], [], [], []]
        named = np.array([i is not None for i in self.ids], bool)
        good = np.flatnonzero((self.size >= LENGTH) & named)
        first, stop = self.start[good], self.start[good] + self.size[good] - LENGTH + 1  # windows of a document
        for at in range(0, len(self.buf) - LENGTH + 1, SLICE):
            part = self.buf[at : at + SLICE + LENGTH - 1]
            n = len(part) - LENGTH + 1
            lo, hi = np.searchsorted(stop, at, "right"), np.searchsorted(first, at + n, "left")
            if lo >= hi:
                continue
            h = grams(part)
            key = (h & ~LOW) | np.arange(len(h), dtype=np.uint64)
            width = 1
            while width * 2 <= LENGTH - GRAM + 1:
                key = np.minimum(key[:-width], key[width:])
                width *= 2
            rest = LENGTH - GRAM + 1 - width
            if rest:
                key = np.minimum(key[:-rest], key[rest:])
            anchor = (key & LOW).astype(np.int64)
            edge = np.zeros(n + 1, bool)
            edge[0] = edge[n] = True
            edge[1:n] = anchor[1:] != anchor[:-1]
            a, z = np.clip(first[lo:hi] - at, 0, n), np.clip(stop[lo:hi] - at, 0, n)
            edge[a] = edge[z] = True
            run = np.flatnonzero(edge)
            s, e = run[:-1], run[1:]
            doc = np.searchsorted(a, s, "right") - 1
            inside = (doc >= 0) & (s < z[np.maximum(doc, 0)])
            s, e, doc = s[inside], e[inside], doc[inside]
            for o, x in zip(out, (s + at, e - 1 + at, h[anchor[s]], good[lo + doc]), strict=True):
                o.append(x)
        if not out[0]:
            return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.uint64), np.zeros(0, np.int64)
        return tuple(map(np.concatenate, out))


def pack(values: np.ndarray) -> bytes:
    """Rising integers as compressed differences."""
    import zstandard

    d = np.diff(values, prepend=np.zeros(1, values.dtype)).astype("<u8")
    return zstandard.ZstdCompressor(level=1).compress(d.view(np.uint8).reshape(-1, 8).T.tobytes())


def unpack(data: bytes) -> np.ndarray:
    import zstandard

    raw = np.frombuffer(zstandard.ZstdDecompressor().decompress(data), np.uint8)
    return np.cumsum(np.ascontiguousarray(raw.reshape(8, -1).T).view("<u8").ravel()) if len(raw) else np.zeros(0, np.uint64)


def distinct(h: np.ndarray, doc: np.ndarray, bits: int):
    """Sorted distinct hashes cut to bits, whether each is in two documents, how often it is there (up to 65535), and where each of h is."""
    cut = h >> np.uint64(64 - bits)
    order = np.argsort(cut)
    c, d = cut[order], doc[order]
    new = np.ones(len(c), bool)
    new[1:] = c[1:] != c[:-1]
    at = np.flatnonzero(new)
    several = np.minimum.reduceat(d, at) != np.maximum.reduceat(d, at) if len(at) else np.zeros(0, bool)
    count = np.minimum(np.diff(np.append(at, len(c))), 65535).astype("<u2")
    place = np.empty(len(c), np.int64)
    place[order] = np.cumsum(new) - 1
    return c[at], several, count, place


def shared_bits(shards: list[tuple[np.ndarray, np.ndarray, np.ndarray]], hot: int = HOT) -> list[tuple[np.ndarray, np.ndarray]]:
    """For chunks' (sorted distinct hashes, in two documents already, how often): which are in two documents of all, and which are hot."""
    every = np.concatenate([h for h, _, _ in shards])
    order = np.argsort(every)
    e = every[order]
    at = np.flatnonzero(np.concatenate([[True], e[1:] != e[:-1]])) if len(e) else np.zeros(0, np.int64)
    size = np.diff(np.append(at, len(e)))
    total = np.add.reduceat(np.concatenate([n for _, _, n in shards]).astype(np.int64)[order], at) if len(at) else size
    both = np.empty((2, len(e)), bool)
    both[0, order], both[1, order] = np.repeat(size > 1, size), np.repeat(total > hot, size)
    ends = np.cumsum([len(h) for h, _, _ in shards])
    return [(both[0, z - len(h) : z] | several, both[1, z - len(h) : z]) for z, (h, several, _) in zip(ends.tolist(), shards, strict=True)]


class RunIndex:
    """Run-compressed Burrows-Wheeler transform of byte strings, each with a number (the document), for windows of length bytes."""

    def __init__(self, strings: list[bytes], numbers: np.ndarray, length: int = LENGTH):
        self.length, m = length, len(strings)
        size = np.array([len(x) for x in strings], np.int64)
        self.size = size
        text = np.frombuffer(b"".join(x + b"\0" for x in strings), np.uint8)  # the last place of each is its terminator
        n = len(text)
        which = np.repeat(np.arange(m), size + 1)
        left = np.cumsum(size + 1)[which] - 1 - np.arange(n)  # bytes before the terminator
        order, alike = self._sort(text, which, left, m, length)
        before = np.where(np.arange(n) == np.concatenate([[0], np.cumsum(size + 1)[:-1]])[which], 256, np.concatenate([[0], text[:-1]]))
        bwt = before[order]
        new = np.ones(n, bool)
        new[1:] = bwt[1:] != bwt[:-1]
        self.head = np.flatnonzero(new)
        self.run_of = np.cumsum(new, dtype=np.int32) - 1  # rank over run heads
        self.char = bwt[self.head]
        count = np.diff(np.append(self.head, n))
        firsts = np.concatenate([[m], m + np.cumsum(np.bincount(text[left > 0], minlength=256))[:-1]])  # first row of each byte
        self.to = np.zeros(len(self.head), np.int64)  # row that a run's head maps to
        for c in np.unique(self.char[self.char < 256]):
            r = np.flatnonzero(self.char == c)
            self.to[r] = firsts[c] + np.cumsum(count[r]) - count[r]
        self.samples = order[np.append(self.head[1:], n) - 1]  # suffixes at run ends
        border = np.ones(n, bool)
        if alike is not None:  # two windows are equal where both of their ends are
            rank, step = alike
            a = np.where(left >= length, rank, -1 - np.arange(n))[order]
            b = rank[np.minimum(order + (length - step), n - 1)]
            border[1:] = (a[1:] != a[:-1]) | (b[1:] != b[:-1])
        self.border = np.flatnonzero(border)
        self.interval_of = np.cumsum(border, dtype=np.int32) - 1
        self.least = np.minimum.reduceat(numbers[which[order]], self.border)

    @staticmethod
    def _sort(text, which, left, m, length):
        """Rows in suffix order; terminators come first, in the order of their strings. Besides, unless suffixes already differ before,
        the rank of each by its first step bytes, and that step, which is at least half of length and at most length."""
        n, step = len(text), min(7, length)
        padded = np.concatenate([text, np.zeros(step, np.uint8)]).astype(np.uint64)
        key = np.zeros(n, np.uint64)
        for k in range(step):
            key = (key << np.uint64(8)) | np.where(left > k, padded[k : k + n], np.uint64(0))
        key = (key << np.uint64(3)) | np.minimum(left, step).astype(np.uint64)
        order = np.argsort(key)
        k = key[order]
        new = np.ones(n, bool)
        new[1:] = k[1:] != k[:-1]
        at = np.flatnonzero(new)
        rank = np.empty(n, np.int64)
        rank[order] = np.repeat(at, np.diff(np.append(at, n)))  # of equal ones the first place
        # of suffixes that end within the key, equal ones go by their string; a zero byte in the text is told from the end by left
        short = np.flatnonzero(left < step)
        by = short[np.argsort(rank[short] * m + which[short])]
        rank[by] += np.arange(len(by)) - np.searchsorted(rank[by], rank[by])
        alike = None
        # then by twice as many bytes each time, those only that share their rank with others
        open_ = np.flatnonzero(np.bincount(rank, minlength=n)[rank] > 1)
        while len(open_):
            if step <= length <= 2 * step:
                alike = rank.copy(), step
            mine = rank[open_]
            key = mine * (n + 1) + rank[np.minimum(open_ + step, n - 1)]  # open ones are longer than step, ended ones have ranks of their own
            to = np.argsort(key)
            key, mine = key[to], mine[to]
            place = np.arange(len(key))
            new = np.ones(len(key), bool)
            new[1:] = key[1:] != key[:-1]
            first = np.ones(len(key), bool)
            first[1:] = mine[1:] != mine[:-1]
            start, group = np.maximum.accumulate(np.where(new, place, 0)), np.maximum.accumulate(np.where(first, place, 0))
            open_ = open_[to]
            rank[open_] = mine + start - group
            last = np.append(new[1:], True)
            open_ = open_[~(new & last)]
            step *= 2
        order[rank] = np.arange(n)
        return order, alike

    def back(self, row: np.ndarray) -> np.ndarray:
        """Rows of the suffixes one byte longer."""
        r = self.run_of[row]
        return self.to[r] + row - self.head[r]

    def stream(self):
        """For places from the strings' ends: (which strings, place, least number of a string with the same window there)."""
        row = np.arange(len(self.size))
        alive = row
        for done in range(1, int(self.size.max(initial=0)) + 1):
            keep = self.size[alive] >= done
            alive, row = alive[keep], row[keep]
            row = self.back(row)
            if done >= self.length:
                yield alive, self.size[alive] - done, self.least[self.interval_of[row]]


def settle(contexts: list[bytes], gram_at: list[int], docs: np.ndarray, index_bytes: int = INDEX_BYTES) -> np.ndarray:
    """For each context: a bit mask of its windows (bit k: the one at byte k) that occur in a context of a smaller document."""
    number: dict[bytes, int] = {}
    which = np.fromiter((number.setdefault(c, len(number)) for c in contexts), np.int64, len(contexts))
    least = np.full(len(number), np.iinfo(np.int64).max)
    np.minimum.at(least, which, docs)
    anchor: dict[bytes, int] = {}
    seen = np.zeros(len(number), bool)
    group = np.zeros(len(number), np.int64)
    for c, g, w in zip(contexts, gram_at, which.tolist(), strict=True):
        if not seen[w]:
            seen[w] = True
            group[w] = anchor.setdefault(c[g : g + GRAM], len(anchor))
    out = np.zeros(len(contexts), np.uint64)
    names = np.argsort(group, kind="stable")  # an index takes whole groups, as equal windows are in one group
    strings, rows = list(number), np.argsort(which)
    first = np.searchsorted(which[rows], np.arange(len(number) + 1))
    at = 0
    while at < len(names):
        size, z = 0, at
        while z < len(names) and (size < index_bytes or group[names[z]] == group[names[z - 1]]):
            size += len(strings[names[z]])
            z += 1
        part = names[at:z]
        at = z
        for alive, place, low in RunIndex([strings[i] for i in part], least[part]).stream():
            own = part[alive]
            count = first[own + 1] - first[own]
            members = rows[np.repeat(first[own] - np.cumsum(count) + count, count) + np.arange(count.sum())]
            hit = docs[members] > np.repeat(low, count)
            out[members[hit]] |= np.uint64(1) << np.repeat(place, count)[hit].astype(np.uint64)
    return out


PARTS = "shard long, chunk long, data binary"
PARTS_ARROW = pa.schema([("shard", pa.int64()), ("chunk", pa.int64()), ("data", pa.binary())])


def _parts(shard: np.ndarray, shards: int):
    """Slices of rows sorted by shard: (shard, rows)."""
    order = np.argsort(shard.astype(np.uint16) if shards < 1 << 16 else shard, kind="stable")
    at = np.searchsorted(shard[order], np.arange(shards + 1))
    return [(k, order[at[k] : at[k + 1]]) for k in range(shards) if at[k] < at[k + 1]]


def _blob(*arrays) -> bytes:
    import zstandard

    data = [x if isinstance(x, bytes) else x.tobytes() for x in arrays]
    return zstandard.ZstdCompressor(level=1).compress(struct.pack(f"<{len(data)}q", *map(len, data)) + b"".join(data))


def _unblob(data: bytes, *kinds) -> list:
    import zstandard

    raw = zstandard.ZstdDecompressor().decompress(data)
    sizes = struct.unpack_from(f"<{len(kinds)}q", raw)
    out, at = [], 8 * len(kinds)
    for n, kind in zip(sizes, kinds, strict=True):
        out.append(raw[at : at + n] if kind is bytes else np.frombuffer(raw, kind, count=n // np.dtype(kind).itemsize, offset=at))
        at += n
    return out


def _windows(raw: bytes, s: np.ndarray, e: np.ndarray, doc: np.ndarray, use: np.ndarray, shards: int):
    """Single windows of the runs in use, each distinct one once, by a hash of its own: what goes to shards (shard, windows and their
    least document here), and what the chunk itself needs when they answer (shard of each window; for every place its window and document)."""
    number: dict[bytes, int] = {}
    ref: list[int] = []
    for a, z in zip(s[use].tolist(), e[use].tolist(), strict=True):
        ref += [number.setdefault(raw[p : p + LENGTH], len(number)) for p in range(a, z + 1)]
    count = e[use] - s[use] + 1
    place = np.repeat(s[use] - np.cumsum(count) + count, count) + np.arange(count.sum())
    own, lines = np.repeat(doc[use], count), list(number)
    low = np.full(len(lines), np.iinfo(np.int64).max)
    np.minimum.at(low, ref, own)
    h = grams(np.frombuffer(b"".join(x + x[:GRAM] for x in lines), np.uint8))
    at = np.arange(len(lines)) * (LENGTH + GRAM)
    mixed = h[at] ^ (h[at + LENGTH // 3] * M2) ^ (h[at + LENGTH - GRAM] * M3)
    to = ((mixed ^ (mixed >> np.uint64(31))) % np.uint64(shards)).astype(np.int64)
    sent = [(k, _blob(b"".join(lines[i] for i in r.tolist()), low[r])) for k, r in _parts(to, shards)]
    return sent, _blob(to.astype("<u4"), np.array(ref, "<u4"), place.astype("<i8"), own.astype("<i8"))


def _least(told: list) -> list[bytes]:
    """For chunks' distinct windows and their least documents: the least of all chunks."""
    least: dict[bytes, int] = {}
    keys = []
    for body, low in told:
        lines = [body[i : i + LENGTH] for i in range(0, len(body), LENGTH)]
        for x, d in zip(lines, low.tolist(), strict=True):
            if d < least.get(x, 1 << 63):
                least[x] = d
        keys.append(lines)
    return [_blob(np.array([least[x] for x in lines], "<i8")) for lines in keys]


def dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", hot_from: int = HOT, index_bytes: int = INDEX_BYTES) -> DataFrame:
    """Per row: doc_id, n_bytes, n_removed, n_spans, kept_sha256, kept (bytes) and spans (removed [start, end) in bytes)."""
    rows = docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text"))
    total = rows.agg(F.sum(F.octet_length("text"))).head()[0] or 0
    chunks = max(64, -(-total // CHUNK_BYTES))
    about = max(1, total // 16)  # anchors
    shards = max(64, -(-about // SHARD_ANCHORS))
    bits = min(60, about.bit_length() + 10)
    rows = rows.select(F.pmod(F.xxhash64(F.coalesce(F.col("doc_id"), F.crc32(F.col("text").cast("binary")))), F.lit(chunks)).alias("chunk"), "doc_id", "text")

    def shard_of(cut: np.ndarray) -> np.ndarray:
        return (cut % np.uint64(shards)).astype(np.int64)

    def announce(key, part):
        _, _, h, doc = (c := Chunk(part)).anchors()
        # documents by id: rows that repeat an id are one document here
        names = np.unique(np.array([0 if i is None else i for i in c.ids]), return_inverse=True)[1]
        hashes, several, count, _ = distinct(h, names[doc] if len(doc) else doc, bits)
        found = [(k, key[0].as_py(), _blob(pack(hashes[r]), np.packbits(several[r]), count[r])) for k, r in _parts(shard_of(hashes), shards)]
        return pa.Table.from_arrays([pa.array([x[i] for x in found], t.type) for i, t in enumerate(PARTS_ARROW)], schema=PARTS_ARROW)

    def answer(key, part):
        given = []
        for data in part.column("data").to_pylist():
            packed, several, count = _unblob(data, bytes, np.uint8, "<u2")
            h = unpack(packed)
            given.append((h, np.unpackbits(several, count=len(h)).astype(bool), count))
        bitmaps = [np.packbits(np.concatenate(x)).tobytes() for x in shared_bits(given, hot_from)]
        return pa.Table.from_arrays([part.column("shard").combine_chunks(), part.column("chunk").combine_chunks(), pa.array(bitmaps, pa.binary())], schema=PARTS_ARROW)

    def quote(key, part, answers):
        c = Chunk(part)
        s, e, h, doc = c.anchors()
        hashes, _, _, place = distinct(h, doc, bits)
        held, hot = np.zeros(len(hashes), bool), np.zeros(len(hashes), bool)
        mine = dict(_parts(shard_of(hashes), shards))
        for k, data in zip(answers.column("shard").to_pylist(), answers.column("data").to_pylist(), strict=True):
            n = len(mine[k])
            two = np.unpackbits(np.frombuffer(data, np.uint8), count=2 * n).astype(bool)
            held[mine[k]], hot[mine[k]] = two[:n], two[n:]
        use = np.flatnonzero(held[place]) if len(place) else np.zeros(0, np.int64)
        ids = np.array([0 if i is None else i for i in c.ids], "<i8")
        found = []
        warm = use[~hot[place[use]]]
        a, z, own, to = s[warm], e[warm] + LENGTH, ids[doc[warm]], shard_of(hashes[place[warm]])
        for k, r in _parts(to, shards):
            body = b"".join([c.raw[x:y] for x, y in zip(a[r].tolist(), z[r].tolist(), strict=True)])
            found.append((k, key[0].as_py(), b"c" + _blob(a[r].astype("<i8"), (z[r] - a[r]).astype("<u1"), own[r], body)))
        if len(warm) < len(use):
            sent, own = _windows(c.raw, s, e, ids[doc], use[hot[place[use]]], shards)
            found += [(k, key[0].as_py(), b"w" + x) for k, x in sent]
            found.append((shards + key[0].as_py(), key[0].as_py(), b"p" + own))
        return pa.Table.from_arrays([pa.array([x[i] for x in found], t.type) for i, t in enumerate(PARTS_ARROW)], schema=PARTS_ARROW)

    def decide(key, part):
        starts, contexts, ids, counts, told = [], [], [], [], []
        blobs = part.column("data").to_pylist()
        for data in blobs:
            if data[:1] != b"c":
                told += [_unblob(data[1:], bytes, "<i8")] if data[:1] == b"w" else []
                continue
            s, size, doc, body = _unblob(data[1:], "<i8", "<u1", "<i8", bytes)
            ends = np.cumsum(size.astype(np.int64))
            contexts += [body[a:z] for a, z in zip((ends - size).tolist(), ends.tolist(), strict=True)]
            starts.append(s)
            ids.append(doc)
            counts.append(len(s))
        masks = settle(contexts, gram_places(contexts), np.concatenate(ids), index_bytes) if contexts else np.zeros(0, np.uint64)
        cold, hot, at = [], iter(_least(told)), 0
        for s, n in zip(starts, counts, strict=True):
            m = masks[at : at + n]
            some = np.flatnonzero(m)
            cold.append(_blob(s[some], m[some].astype("<u8")))
            at += n
        rest = iter(cold)
        out = [b"w" + next(hot) if data[:1] == b"w" else b"c" + next(rest) if data[:1] == b"c" else data for data in blobs]
        return pa.Table.from_arrays([part.column("shard").combine_chunks(), part.column("chunk").combine_chunks(), pa.array(out, pa.binary())], schema=PARTS_ARROW)

    final = pa.schema([("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("n_removed", pa.int64()), ("n_spans", pa.int64()), ("kept_sha256", pa.string()), ("kept", pa.binary()), ("spans", pa.list_(pa.list_(pa.int64())))])

    def cover(key, part, decided):
        c = Chunk(part)
        n = len(c.buf)
        step = np.zeros(n + 1, np.int32)
        least, own = {}, None
        for shard, data in zip(decided.column("shard").to_pylist(), decided.column("data").to_pylist(), strict=True):
            if data[:1] == b"w":
                least[shard] = _unblob(data[1:], "<i8")[0]
            elif data[:1] == b"p":
                own = _unblob(data[1:], "<u4", "<u4", "<i8", "<i8")
            else:
                s, m = _unblob(data[1:], "<i8", "<u8")
                for k in range(LENGTH - GRAM + 1):
                    at = s[(m >> np.uint64(k)) & np.uint64(1) > 0] + k  # places are distinct: every window has one anchor
                    step[at] += 1
                    step[at + LENGTH] -= 1
        if own:
            to, ref, place, doc = own
            low = np.empty(len(to), np.int64)
            for k, r in _parts(to.astype(np.int64), shards):
                low[r] = least[k]
            at = place[doc > low[ref]]
            step[at] += 1
            step[at + LENGTH] -= 1
        gone = np.cumsum(step, dtype=np.int32)[:n] > 0
        cols: list[list] = [[] for _ in final]
        for i, a, size in zip(c.ids, c.start.tolist(), c.size.tolist(), strict=True):
            g = gone[a : a + size]
            edge = np.flatnonzero(np.diff(g, prepend=False, append=False))
            kept = c.buf[a : a + size][~g].tobytes() if len(edge) else c.raw[a : a + size]
            for col, x in zip(cols, (i, size, size - len(kept), len(edge) // 2, hashlib.sha256(kept).hexdigest(), kept, edge.reshape(-1, 2).tolist()), strict=True):
                col.append(x)
        return pa.Table.from_arrays([pa.array(x, f.type) for x, f in zip(cols, final, strict=True)], schema=final)

    texts = rows.groupBy("chunk")
    told = texts.applyInArrow(announce, PARTS)
    answers = told.groupBy("shard").applyInArrow(answer, PARTS)
    quotes = texts.cogroup(answers.groupBy("chunk")).applyInArrow(quote, PARTS)
    decided = quotes.groupBy("shard").applyInArrow(decide, PARTS)
    return texts.cogroup(decided.groupBy("chunk")).applyInArrow(cover, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary, spans array<array<long>>")


def gram_places(contexts: list[bytes]) -> list[int]:
    """Where the anchor of each context's windows is, from its bytes: the anchor of its first window."""
    out: list[int] = []
    for at in range(0, len(contexts), 4096):
        part = contexts[at : at + 4096]
        size = np.array([len(x) for x in part])
        start = np.cumsum(size) - size
        h = grams(np.frombuffer(b"".join(part), np.uint8)) & ~LOW
        view = h[start[:, None] + np.arange(LENGTH - GRAM + 1)]
        out += view.argmin(1).tolist()
    return out


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dedup(table(spark, sf_dir, "documents")).select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256")
