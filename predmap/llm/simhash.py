"""SimHash near-dedup: fingerprints, and their links through BK-trees.

Fingerprints are made in one pass and grouped, so copies cost one row. Two fingerprints that differ in at most ``radius`` of 64
bits agree in at least m - radius of m equal blocks of bits; each choice of such blocks is a shard key, so every link lies inside
some shard. m is the least whose keys have as many bits as there are fingerprints to tell apart. A shard that is still large is
dealt anew by the bits its members do not share, with the same argument, until none is over ``HOT``: no link is lost and no
task holds an unbounded group.

In a shard a BK-tree (children keyed by their Hamming distance to the parent) is built from each ``LEAF`` members and every member
asks it, following only edges within the radius of its own distance. Found links are united in the task and leave it as a
star, so no pairs are spread out. Components then come from rounds of contraction: every node goes to its least neighbour.

Defined results: null, empty and white-space texts have fingerprint zero and are linked to each other like any others; fewer words
than a shingle are one shingle; rows that repeat an id are returned each; a row with a null id takes the component of its
fingerprint (null if alone); an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

import itertools

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from predmap.llm.common import batch_of, cut, small, table, texts

NAME = "op9_simhash"
SQL = None  # XXH64 with a seed is no SQL function; tests compare with all pairs
SHINGLE, RADIUS, SEED = 3, 2, 42
LEAF, HOT = 2048, 50_000
#: Rows of a few numbers that one task takes in the rounds of components(), and edges at which one task ends the rounds.
TASK_ROWS = 1 << 17
LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))


def fingerprint(text: str, shingle: int = SHINGLE) -> int:
    """64 bits; a bit is 1 if it is set in over half of the shingles' hashes."""
    from xxhash import xxh64_intdigest

    w = text.encode("utf-8", "surrogatepass").translate(LOWER).split()
    if not w:
        return 0
    if len(w) <= shingle:
        return xxh64_intdigest(b" ".join(w), SEED)
    line = b" ".join(w)
    ends = np.cumsum(np.fromiter(map(len, w), np.int64, len(w)) + 1) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])
    counts, n = np.zeros(64, np.int64), len(w) - shingle + 1
    for at in range(0, n, 1 << 16):
        z = min(n, at + (1 << 16))
        h = np.fromiter((xxh64_intdigest(line[a:b], SEED) for a, b in zip(starts[at:z].tolist(), ends[at + shingle - 1 : z + shingle - 1].tolist(), strict=True)), np.uint64, z - at)
        counts += np.unpackbits(h.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(counts * 2 > n, bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, shingle: int = SHINGLE, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, fp (the 64 bits as a signed long)."""
    schema = pa.schema([("doc_id", pa.int64()), ("fp", pa.int64())])

    def run(batches):
        for b in small(batches):
            fp = np.array([fingerprint(x, shingle) for x in texts(b)], np.uint64).view(np.int64)
            yield batch_of(schema, b.column("doc_id"), fp)

    return docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text")).mapInArrow(run, "doc_id long, fp long")


class BKTree:
    """Nodes as parallel lists; children of a node by distance."""

    def __init__(self, members: list[int]):
        self.value, self.child = [members[0]], [{}]
        for x in members[1:]:
            self.add(x)

    def add(self, x: int) -> None:
        at = 0
        while True:
            d = (x ^ self.value[at]).bit_count()
            if d not in self.child[at]:
                break
            at = self.child[at][d]
        self.child[at][d] = len(self.value)
        self.value.append(x)
        self.child.append({})

    def within(self, x: int, radius: int) -> list[int]:
        """Positions of members at radius or less."""
        out, todo = [], [0]
        while todo:
            at = todo.pop()
            d = (x ^ self.value[at]).bit_count()
            if d <= radius:
                out.append(at)
            kids = self.child[at]
            if kids:
                todo += [kids[k] for k in range(d - radius, d + radius + 1) if k in kids]
        return out


def stars(members: list[int], radius: int) -> list[int]:
    """For each member (distinct 64-bit values) the position of its group's first."""
    n = len(members)
    root = list(range(n))

    def find(i: int) -> int:
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    for at in range(0, n, LEAF):
        tree = BKTree(members[at : at + LEAF])
        for i in range(at, n):
            for j in tree.within(members[i], radius):
                a, b = find(i), find(at + j)
                if a != b:
                    root[max(a, b)] = min(a, b)
    return [find(i) for i in range(n)]


def _blocks(bits: list[int], m: int) -> list[int]:
    """Masks of m nearly equal blocks of the given bit numbers."""
    cuts = [len(bits) * k // m for k in range(m + 1)]
    return [sum(1 << b for b in bits[a:z]) for a, z in itertools.pairwise(cuts)]


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def _masks(count: int, radius: int, bits: list[int]) -> list[int]:
    """Masks of shard keys over the given bits: any two values within radius agree under one of them at least."""
    m = radius + 1
    while len(bits) * (m - radius) // m < count.bit_length() and m < radius + 4 and m < len(bits):
        m += 1
    blocks = _blocks(bits, m)
    return [sum(x) for x in itertools.combinations(blocks, m - radius)]


def shards(fps: DataFrame, radius: int = RADIUS) -> DataFrame:
    """(shard, fp, low): every two fingerprints within radius share a shard, and no shard is over HOT, if bits are left."""
    n = fps.count()
    masks = _masks(n, radius, list(range(64)))
    fixed = F.explode(F.array(*[F.lit(_signed(m)) for m in masks]))
    rows = fps.select("fp", "low", fixed.alias("mask")).select("fp", "low", "mask", F.col("fp").bitwiseAND(F.col("mask")).alias("bits"))
    done = None
    while True:
        hot = cut(rows.groupBy("mask", "bits").count().filter(F.col("count") > HOT).select("mask", "bits"))
        none = not hot.count()
        part = rows if none else rows.join(hot, ["mask", "bits"], "left_anti")
        done = part if done is None else done.unionByName(part)
        if none:
            break
        finer = {r["mask"]: [m | (r["mask"] & (1 << 64) - 1) for m in _masks(1, radius, [b for b in range(64) if not r["mask"] >> b & 1])] for r in hot.select("mask").distinct().collect()}
        finer = {k: v for k, v in finer.items() if len({*v}) > 1}
        if not finer:
            done = done.unionByName(rows.join(hot, ["mask", "bits"], "left_semi"))
            break
        deal = F.create_map(*[x for k, v in finer.items() for x in (F.lit(k), F.array(*[F.lit(_signed(y)) for y in v]))])
        rows = rows.join(hot, ["mask", "bits"], "left_semi").select("fp", "low", F.explode(deal[F.col("mask")]).alias("mask")).select("fp", "low", "mask", F.col("fp").bitwiseAND(F.col("mask")).alias("bits"))
    return done


def links(fps: DataFrame, radius: int = RADIUS) -> DataFrame:
    """Edges (a, b), a > b, between the low ids of fingerprints, whose components are those of all links within radius."""
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64())])

    def solve(fp: np.ndarray, low: np.ndarray):
        order = np.argsort(low, kind="stable")
        fp, low = fp[order], low[order]
        at = np.array(stars(fp.view(np.uint64).tolist(), radius))
        other = np.flatnonzero(at != np.arange(len(at)))
        return low[other], low[at[other]]

    def run(batches):
        held: list = []
        key = None

        def close():
            if sum(len(x[0]) for x in held) > 1:
                yield batch_of(schema, *solve(np.concatenate([x[0] for x in held]), np.concatenate([x[1] for x in held])))
            held.clear()

        for b in batches:
            if not b.num_rows:
                continue
            mask, bits, fp, low = (b.column(c).to_numpy(zero_copy_only=False) for c in ("mask", "bits", "fp", "low"))
            edge = np.flatnonzero((mask[1:] != mask[:-1]) | (bits[1:] != bits[:-1])) + 1
            runs = np.concatenate([[0], edge, [len(fp)]])
            outs = []
            for r in range(len(runs) - 1):
                a, z = int(runs[r]), int(runs[r + 1])
                if (mask[a], bits[a]) != key:
                    yield from close()
                    key = mask[a], bits[a]
                if 0 < r < len(runs) - 2:  # whole inside this batch
                    if z - a > 1:
                        outs.append(solve(fp[a:z], low[a:z]))
                else:
                    held.append((fp[a:z], low[a:z]))
            if outs:
                yield batch_of(schema, np.concatenate([x[0] for x in outs]), np.concatenate([x[1] for x in outs]))
        yield from close()

    near = shards(fps.filter(F.col("low").isNotNull()), radius).repartition("mask", "bits").sortWithinPartitions("mask", "bits")
    return near.select("mask", "bits", "fp", "low").mapInArrow(run, "a long, b long")


def _tasks(n: int) -> int:
    """Tasks for n narrow rows. A round over few rows would else take as many tasks as the largest shuffle of the job, and the driver
    would plan, watch and remember them all."""
    return max(2, -(-n // TASK_ROWS))


def _counted(df: DataFrame) -> tuple[DataFrame, int]:
    """df kept, to be read in as many tasks as its rows are worth, and the number of these."""
    df = cut(df)
    n = df.count()
    return df.coalesce(_tasks(n)), n


def _to_roots(up: DataFrame, tasks: int) -> DataFrame:
    """(node, up) with every up followed to its end: pointers double each round, so a chain takes as many rounds as its logarithm."""
    while True:
        far = up.select(F.col("node").alias("up"), F.col("up").alias("far"))
        two = cut(up.join(far, "up").select("node", F.col("far").alias("up"), (F.col("far") != F.col("up")).alias("moved")).coalesce(tasks))
        up = two.select("node", "up")
        if not two.filter("moved").count():  # one job; isEmpty would take several to see that nothing is there
            return up


def _ended(edges: DataFrame) -> DataFrame:
    """(node, up): components of TASK_ROWS edges (a, b) at most, found in one task by pointers to lesser nodes."""
    schema = pa.schema([("node", pa.int64()), ("up", pa.int64())])

    def run(batches):
        both = [np.stack([b.column(0).to_numpy(), b.column(1).to_numpy()]) for b in batches if b.num_rows]
        if not both:
            return
        nodes, at = np.unique(np.concatenate(both, 1), return_inverse=True)
        a, b = at.reshape(2, -1)
        up = np.arange(len(nodes))
        while (up[a] != up[b]).any():
            x, y = up[a], up[b]
            np.minimum.at(up, np.maximum(x, y), np.minimum(x, y))
            while (up[up] != up).any():
                up = up[up]
        yield batch_of(schema, nodes, nodes[up])

    return edges.select("a", "b").coalesce(1).mapInArrow(run, "node long, up long")


def components(edges: DataFrame) -> DataFrame:
    """(node, root): for each node of edges the least node it reaches. A round takes every node to the end of its chain of least
    neighbours; what is left at least halves. Once it fits one task, that task ends it: the result is the same, and the driver is
    spared the many small stages of the last rounds."""
    e, n = _counted(edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).filter("a <> b").distinct())
    layers: list[DataFrame] = []
    while n > TASK_ROWS:
        tasks = _tasks(2 * n)  # an edge has two nodes
        both = e.unionByName(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
        up = cut(both.groupBy("a").agg(F.min("b").alias("p")).select(F.col("a").alias("node"), F.least("a", "p").alias("up")).coalesce(tasks))
        up = _to_roots(up, tasks)
        layers.append(up)
        left = (
            e.join(up.select(F.col("node").alias("a"), F.col("up").alias("x")), "a")
            .join(up.select(F.col("node").alias("b"), F.col("up").alias("y")), "b")
            .filter("x <> y").select(F.greatest("x", "y").alias("a"), F.least("x", "y").alias("b")).distinct()
        )
        e, n = _counted(left.coalesce(tasks))
    if n:
        layers.append(cut(_ended(e)))
    if not layers:
        return edges.select(F.col("a").alias("node"), F.col("b").alias("root")).limit(0)
    out = layers[-1].select("node", F.col("up").alias("root"))
    for up in reversed(layers[:-1]):  # where a node went, and where that went later
        later = out.select(F.col("node").alias("up"), F.col("root").alias("later"))
        out = up.join(later, "up", "left").select("node", F.coalesce("later", "up").alias("root"))
    return out


def near_duplicates(docs: DataFrame, shingle: int = SHINGLE, radius: int = RADIUS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row of docs: doc_id, fp (signed), component_id."""
    rows = cut(fingerprints(docs, shingle, id_col, text_col))
    fps = cut(rows.groupBy("fp").agg(F.min("doc_id").alias("low")))
    roots = components(links(fps, radius))
    where = fps.join(roots, fps["low"] == roots["node"], "left").select(F.col("fp"), F.coalesce("root", "low").alias("component_id"))
    return rows.join(where, "fp").select("doc_id", "fp", "component_id")


def dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """The rows of docs that stay: the smallest id of each component. All columns."""
    gone = near_duplicates(docs, id_col=id_col, text_col=text_col, **options).filter("doc_id <> component_id").select(F.col("doc_id").alias("_gone")).distinct()
    return docs.join(gone, docs[id_col] == gone["_gone"], "left_anti")


# -- near duplicates by similarity of shingle sets: what the pipeline's stage takes

WORDS, SIMILARITY = 5, 0.8
#: Least hashes of a set: bands of ROWS of them are keys, and the low bytes of all LEAST say how similar two sets look. Sets that look
#: less similar than 0.075 below the wanted similarity are not compared: at 0.8 that is three standard deviations.
BANDS, ROWS, LEAST, SLACK = 25, 4, 256, 0.075
#: Members that a leader is compared with in one task, members of a part of a large group, pairs made at once, and the bits of the
#: largest Bloom filter sent out.
TOGETHER, PART, BLOCK, MOST_BITS = 256, 2048, 1 << 14, 1 << 28


def shingle_hashes(text: str, words: int = WORDS) -> np.ndarray:
    """XXH64 of every run of so many words (all words if there are fewer; none for a text without words)."""
    from xxhash import xxh64_intdigest

    w = text.encode("utf-8", "surrogatepass").translate(LOWER).split()
    if not w:
        return np.zeros(0, np.uint64)
    line = b" ".join(w)
    ends = np.cumsum(np.fromiter(map(len, w), np.int64, len(w)) + 1) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])
    k = min(words, len(w))
    n = len(w) - k + 1
    return np.fromiter((xxh64_intdigest(line[a:b], SEED) for a, b in zip(starts[:n].tolist(), ends[k - 1 :].tolist(), strict=True)), np.uint64, n)


def shingle_set(text: str, words: int = WORDS) -> np.ndarray:
    """Distinct hashes of shingles, rising; a text without words has one of its own, so such texts are alike."""
    h = np.unique(shingle_hashes(text, words))
    return h if len(h) else np.zeros(1, np.uint64)


def voted(h: np.ndarray) -> int:
    """The SimHash of a set of hashes, each counted once."""
    counts = np.zeros(64, np.int64)
    for at in range(0, len(h), 1 << 16):
        part = np.ascontiguousarray(h[at : at + (1 << 16)], "<u8")
        counts += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(counts * 2 > len(h), bitorder="little").view("<u8")[0])


_rng = np.random.default_rng(SEED)
TURN = _rng.integers(0, 1 << 32, (LEAST, 1), np.uint32)
SPIN = _rng.integers(0, 1 << 32, (2, LEAST, 1), np.uint32) | np.uint32(1)


def least_hashes(h: np.ndarray) -> np.ndarray:
    """The least value of the set under each of LEAST hash functions; two sets agree in a share of them that is their similarity."""
    h = (h >> np.uint64(32)).astype(np.uint32)
    out = np.full(LEAST, ~np.uint32(0))
    for at in range(0, len(h), 1024):
        x = (h[None, at : at + 1024] ^ TURN) * SPIN[0]
        x ^= x >> np.uint32(15)
        x *= SPIN[1]
        x ^= x >> np.uint32(16)
        out = np.minimum(out, x.min(1))
    return out


def band_keys(least: np.ndarray) -> np.ndarray:
    """n x LEAST to a 64-bit key per band: equal where the band's ROWS least hashes are."""
    out = np.broadcast_to(np.arange(1, BANDS + 1, dtype=np.uint64), (len(least), BANDS))
    for k in range(ROWS):
        out = (out ^ least[:, k : BANDS * ROWS : ROWS]) * np.uint64(0x9E3779B97F4A7C15)
        out ^= out >> np.uint64(29)
    return out


def signed_sets(rows: DataFrame, words: int) -> DataFrame:
    """(doc, fp, keys, looks): SimHash, band keys and low bytes of the least hashes of each row's set of shingles."""
    schema = pa.schema([("doc", pa.int64()), ("fp", pa.int64()), ("keys", pa.list_(pa.int64())), ("looks", pa.binary())])

    def run(batches):
        for b in small(batches):
            sets = [shingle_set(x, words) for x in texts(b)]
            fp = np.array([voted(x) for x in sets], np.uint64).view(np.int64)
            least = np.stack([least_hashes(x) for x in sets])
            keys = pa.ListArray.from_arrays(pa.array(np.arange(len(sets) + 1, dtype=np.int32) * BANDS), pa.array(band_keys(least).view(np.int64).ravel()))
            yield batch_of(schema, b.column("doc_id"), fp, keys, [x.tobytes() for x in least.astype(np.uint8)])

    return rows.mapInArrow(run, "doc long, fp long, keys array<long>, looks binary")


def _whole(batches):
    """Columns, as arrays, of batches sorted by the first column, cut only between its values. Binaries, of equal length, become rows of bytes."""
    held: list = []
    for b in batches:
        if not b.num_rows:
            continue
        cols = [np.frombuffer(b"".join(c.to_pylist()), np.uint8).reshape(len(c), -1) if pa.types.is_binary(c.type) else c.to_numpy(zero_copy_only=False) for c in b.columns]
        z = int(np.searchsorted(cols[0], cols[0][-1]))
        if z or (held and held[-1][0][-1] != cols[0][-1]):
            yield [np.concatenate(x) for x in zip(*held, [c[:z] for c in cols], strict=True)]
            held = []
        held.append([c[z:] for c in cols])
    if held:
        yield [np.concatenate(x) for x in zip(*held, strict=True)]


def _ends(*keys: np.ndarray) -> np.ndarray:
    """For each row the end of its run of equal keys."""
    n = len(keys[0])
    if not n:
        return np.zeros(0, np.int64)
    edge = np.flatnonzero(np.logical_or.reduce([k[1:] != k[:-1] for k in keys])) + 1
    return np.repeat(np.append(edge, n), np.diff(np.concatenate([[0], edge, [n]])))


def meetings(tokens: DataFrame) -> DataFrame:
    """The rows (token, doc, band) whose token another row has. Rows pass in order, so a token may have any number of them."""
    schema = pa.schema([("token", pa.int64()), ("doc", pa.int64()), ("band", pa.int32())])

    def run(batches):
        last = None  # token of the row before
        held = None  # the row whose successor is not known yet
        for b in (*batches, None):
            if b is None or b.num_rows:
                t, *rest = [np.concatenate([*([h] if h is not None else []), *([] if b is None else [b.column(i).to_numpy()])]) if h is not None or b is not None else np.zeros(0, np.int64) for i, h in enumerate(held or [None] * 3)]
                if not len(t):
                    continue
                n = len(t) if b is None else len(t) - 1
                again = np.zeros(len(t), bool)
                again[1:] = t[1:] == t[:-1]
                again[0] = last is not None and t[0] == last
                again[:-1] |= t[1:] == t[:-1]
                out = np.flatnonzero(again[:n])
                if len(out):
                    yield batch_of(schema, t[out], *[x[out] for x in rest])
                last = int(t[n - 1]) if n else last
                held = [x[n:] for x in (t, *rest)]

    return tokens.select("token", "doc", "band").repartition("token").sortWithinPartitions("token").mapInArrow(run, "token long, doc long, band int")


def across(near: DataFrame, similarity: float) -> DataFrame:
    """(doc, leader) of all pairs that share a token of near (token, doc, band, root, looks), differ in root and look similar enough. A
    pair is made in the first band that it shares only. Groups of more than PART are dealt in parts, and every two parts meet."""
    schema = pa.schema([("doc", pa.int64()), ("leader", pa.int64())])
    mixed = near.groupBy("token").agg(F.min("root").alias("lo"), F.max("root").alias("hi"), F.ceil(F.count(F.lit(1)) / PART).alias("parts")).filter("lo <> hi").select("token", "parts")
    own = F.pmod(F.xxhash64("doc"), F.col("parts"))
    dealt = near.join(mixed, "token").withColumn("part", own).withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("parts") - 1)))
    cell = F.xxhash64("token", F.least("part", "other"), F.greatest("part", "other"))
    cells = dealt.select(cell.alias("cell"), "root", "doc", "band", "part", (F.col("part") == F.col("other")).alias("alone"), "looks")

    def run(batches):
        for cell, root, doc, band, part, alone, looks in _whole(batches):
            ends, same = _ends(cell), _ends(cell, root)
            n = ends - same  # partners of a row: the cell's rows behind those of its root
            block = np.cumsum(n) // BLOCK
            for rows in np.split(np.arange(len(n)), np.flatnonzero(block[1:] != block[:-1]) + 1):
                i = np.repeat(rows, n[rows])
                j = np.repeat(same[rows] - np.cumsum(n[rows]) + n[rows], n[rows]) + np.arange(len(i))
                fits = alone[i] | (part[i] != part[j])
                i, j = i[fits], j[fits]
                if not len(i):
                    continue
                alike = looks[i] == looks[j]
                first = alike[:, : BANDS * ROWS].reshape(-1, BANDS, ROWS).all(2).argmax(1)
                good = np.flatnonzero((first == band[i]) & (alike.mean(1) >= similarity - SLACK))
                if len(good):
                    yield batch_of(schema, np.maximum(doc[i[good]], doc[j[good]]), np.minimum(doc[i[good]], doc[j[good]]))

    return cells.repartition("cell").sortWithinPartitions("cell", "root").mapInArrow(run, "doc long, leader long").distinct()


def _asked(rows: DataFrame, ids: DataFrame, n: int) -> DataFrame:
    """The rows whose doc_id is in ids (id), of which there are n at most. A Bloom filter, a byte per id up to MOST_BITS, lets few others be shuffled to the join
    that decides."""
    bits = min(MOST_BITS, 1 << max(16, (8 * n).bit_length()))
    places = [F.pmod(F.xxhash64("id", F.lit(k)), F.lit(bits)) for k in (1, 2)]
    word = ids.select(F.explode(F.array(*places)).alias("p")).groupBy(F.floor(F.col("p") / 32).cast("int").alias("word")).agg(F.bit_or(F.expr("shiftleft(1L, cast(p % 32 as int))")).alias("bits"))
    held, found = np.zeros(bits // 32, np.uint32), word.toArrow()
    held[found.column("word").to_numpy()] = found.column("bits").to_numpy()
    given = rows.sparkSession.sparkContext.broadcast(held)
    marked = rows.select("*", *[F.pmod(F.xxhash64("doc_id", F.lit(k)), F.lit(bits)).alias(f"p{k}") for k in (1, 2)])

    def run(batches):
        for b in batches:
            one, two = (b.column(c).to_numpy() for c in ("p1", "p2"))
            may = (given.value[one >> 5] >> (one & 31) & given.value[two >> 5] >> (two & 31) & 1).astype(bool)
            yield b.select(["doc_id", "text"]).filter(pa.array(may))

    few = marked.mapInArrow(run, "doc_id long, text string")
    return few.join(ids, few["doc_id"] == ids["id"]).select("id", "text")


def compared(rows: DataFrame, pairs: DataFrame, n: int, words: int, similarity: float) -> DataFrame:
    """(a, b), a > b: those of the n pairs (doc, leader; distinct, and read several times) whose sets of shingles have the similarity. Texts travel, as they are smaller than
    their sets; a leader's members are dealt to several tasks, each with its own copy of the leader."""
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64())])
    ids = pairs.select(F.col("doc").alias("id")).distinct().unionByName(pairs.select(F.col("leader").alias("id")).distinct()).distinct()
    known = _asked(rows, ids, 2 * n)
    parts = pairs.groupBy("leader").agg(F.ceil(F.count(F.lit(1)) / TOGETHER).alias("parts"))
    members = pairs.join(parts, "leader").select("leader", F.pmod(F.xxhash64("doc"), "parts").alias("part"), "doc")
    leaders = parts.select("leader", F.explode(F.sequence(F.lit(0).cast("long"), F.col("parts") - 1)).alias("part"), F.lit(None).cast("long").alias("doc"))
    wanted = members.withColumn("id", F.col("doc")).unionByName(leaders.withColumn("id", F.col("leader")))
    texts_of = wanted.join(known, "id").select("leader", "part", "doc", "text")

    def run(batches):
        key, own = None, None
        for b in batches:
            found = []
            for leader, part, doc, text in zip(*(b.column(i).to_pylist() for i in range(4)), strict=True):
                h = shingle_set(text or "", words)
                if doc is None:  # sorted first
                    key, own = (leader, part), h
                elif key == (leader, part) and min(len(h), len(own)) >= similarity * max(len(h), len(own)) - 1e-9:
                    both = len(np.intersect1d(h, own, assume_unique=True))
                    if both >= similarity * (len(h) + len(own) - both) - 1e-9:
                        found.append((max(doc, leader), min(doc, leader)))
            if found:
                yield batch_of(schema, *zip(*found, strict=True))

    near = texts_of.repartition("leader", "part").sortWithinPartitions("leader", "part", F.col("doc").asc_nulls_first()).mapInArrow(run, "a long, b long")
    return near.distinct()


def _found(docs: DataFrame, words: int = WORDS, similarity: float = SIMILARITY, id_col: str = "doc_id", text_col: str = "text") -> tuple[DataFrame, DataFrame, DataFrame | None]:
    """What similar() returns in two parts, of which the second may be missing, and between them the components of the first. Every
    candidate is compared exactly; candidates come

    1. from SimHash: documents whose fingerprints (over distinct shingles) are linked by the BK-trees, with the least of their group;
    2. from bands: each document with the centre of a band's group (the document that shares most bands with others), of those the
       one that it shares most bands with;
    3. from bands again: every two documents of a group that are still in different components and look similar.

    A pair at 0.8 shares no band with a probability of 2e-6 and looks too different with one of 2e-3; more similar ones are safer."""
    rows = docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text")).filter("doc_id IS NOT NULL")
    made = cut(signed_sets(rows, words))
    fps = cut(made.groupBy("fp").agg(F.min("doc").alias("low")))
    groups = components(links(fps, RADIUS))
    roots = fps.join(groups, fps["low"] == groups["node"], "left").select("fp", F.coalesce("root", "low").alias("leader"))
    by_fp = made.select("doc", "fp").join(roots, "fp").filter("doc <> leader").select("doc", "leader")
    held = cut(meetings(made.select("doc", F.posexplode("keys").alias("band", "token"))))
    sizes = held.groupBy("token").agg(F.count(F.lit(1)).alias("n"))
    weights = held.join(sizes, "token").groupBy("doc").agg(F.sum("n").alias("weight"))
    centres = held.join(weights, "doc").groupBy("token").agg(F.max_by("doc", F.struct("weight", -F.col("doc"))).alias("leader"), F.max("weight").alias("weight"))
    shared = held.join(centres, "token").filter("doc <> leader").groupBy("doc", "leader").agg(F.count(F.lit(1)).alias("n"), F.max("weight").alias("weight"))
    by_band = shared.groupBy("doc").agg(F.max_by("leader", F.struct("n", "weight", -F.col("leader"))).alias("leader"))
    pairs, n = _counted(by_fp.unionByName(by_band).distinct())
    first = cut(compared(rows, pairs, n, words, similarity))
    roots = components(first)
    looks = made.select("doc", "looks").dropDuplicates(["doc"])
    near = held.join(roots, F.col("doc") == roots["node"], "left").select("token", "doc", "band", F.coalesce("root", "doc").alias("root"))
    tried = pairs.select(F.greatest("doc", "leader").alias("doc"), F.least("doc", "leader").alias("leader"))
    rest, n = _counted(across(near.join(looks, "doc"), similarity).join(tried, ["doc", "leader"], "left_anti"))
    return first, roots, compared(rows, rest, n, words, similarity) if n else None


def similar(docs: DataFrame, **options) -> DataFrame:
    """(a, b), a > b: documents whose sets of shingles have at least this Jaccard similarity, enough pairs for the components of all
    such pairs. Rows with null ids take no part; of rows that repeat an id, which is one document here, any may be compared. Options:
    words, similarity, id_col, text_col."""
    first, _, second = _found(docs, **options)
    return first if second is None else first.unionByName(second)


def dedup_similar(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """The rows of docs that stay: of each group of similar documents the one with the smallest id. All columns."""
    _, roots, second = _found(docs, id_col=id_col, text_col=text_col, **options)
    if second is not None:  # stars instead of the pairs they came from: one round takes them to their ends
        roots = components(roots.select(F.col("node").alias("a"), F.col("root").alias("b")).unionByName(second))
    gone = roots.filter("node <> root").select(F.col("node").alias("_gone"))
    return docs.join(gone, docs[id_col] == gone["_gone"], "left_anti")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_duplicates(table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
