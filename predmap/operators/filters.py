"""Membership filters: fingerprints in static maps, weighted filters, a Bloom filter to compare with."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from predmap.config import MapConfig
from predmap.functions.hashing import key_hashes, shard_of
from predmap.operators import shards as sh
from predmap.operators.maps import STRUCTURE, StaticMap, _keyed, _solved, as_list

U = np.uint64


def build(members: DataFrame, key, r: int | str, cfg: MapConfig | None = None, path: str | None = None) -> StaticMap:
    """Filter of the keys of members. r: bits per key, a number or a column (a weighted filter), of any size; false positives have a
    share of 2^-r. A fingerprint is a bit string of r ones, so members always pass."""
    cfg, keys = cfg or MapConfig(), as_list(key)
    bits = F.lit(r) if isinstance(r, int) else F.col(r)
    rows, count = _keyed(members, keys, cfg, members.count())
    rows = rows.select("_shard", "_h1", "_h2", bits.cast("long").alias("_vid")).dropDuplicates(["_shard", "_h1", "_h2"])

    words = max(1, -(-int(members.agg(F.max(bits)).head()[0] or 0) // 64))

    def solver(h1, h2, n, use, part):
        ones = np.full((len(use), words), -1, np.int64)
        parts, stats = sh.solve_bits(h1[use], ones, np.maximum(n[use], 0), cfg)
        return {**parts, "exceptions": sh.pack_exceptions(*[np.zeros(0, np.int64)] * 3)}, {**stats, "filter_demand": stats["correct_demand"], "correct_demand": 0}

    return StaticMap("filter", cfg, keys, None, [], None, None, members.count(), count, _solved(rows, solver, path, count), {"r": r})


def might_contain(built: StaticMap, df: DataFrame, as_: str = "might_contain", r: int | str | None = None) -> DataFrame:
    """df with whether each key passes; r as at building (a column for a weighted filter). Members always pass."""
    spark, cfg = df.sparkSession, built.cfg
    r = built.extra["r"] if r is None else r
    h1, _ = key_hashes(df, built.keys, cfg.seed)
    rows = df.select(F.struct("*").alias("_row"), h1.alias("_h1"), (F.lit(r) if isinstance(r, int) else F.col(r)).cast("long").alias("_r"))
    rows = rows.withColumn("_shard", shard_of(F.col("_h1"), built.shards))
    out = rows.select("_row").schema.add("_ok", "boolean")
    structure = spark.read.schema(STRUCTURE).parquet(built.path).select(F.col("shard").alias("_shard"), "parts")

    opened: dict = {}

    def passes(shard: int, blob: bytes | None, h: np.ndarray, n: np.ndarray) -> np.ndarray:
        if blob is None:
            return np.zeros(len(h), bool)
        if shard not in opened:
            opened[shard] = sh.load_bits(sh.unpack_parts(bytes(blob))["bits"])
        ok = np.ones(len(h), bool)
        for k, i, store in opened[shard]:
            own = sh.mix(h.view(U), 8000 + k) if k else h.view(U)
            if cfg.layout == "per_position":
                at = np.flatnonzero(ok & (n > 64 * k + i))
                ok[at] = store.read(own[at], np.zeros(len(at), np.int64), cfg, cfg.seed + 7 * i) == 1
            else:
                at = np.flatnonzero(ok & (n > 64 * k))
                ok[at] = store.ones(own[at], np.zeros(len(at), np.int64), np.minimum(n[at] - 64 * k, 64), cfg)
        return ok

    if (structure.agg(F.sum(F.length("parts"))).head()[0] or 0) > cfg.broadcast_bytes:

        def join(key, q, s):
            h, n = (q.column(k).combine_chunks().to_numpy(zero_copy_only=False) for k in ("_h1", "_r"))
            return pa.Table.from_arrays([q.column("_row"), pa.array(passes(key[0].as_py(), s.column("parts")[0].as_py() if s.num_rows else None, h, n))], names=["_row", "_ok"])

        found = rows.groupBy("_shard").cogroup(structure.groupBy("_shard")).applyInArrow(join, out)
        return found.select("_row.*", F.col("_ok").alias(as_))
    given = spark.sparkContext.broadcast({x["_shard"]: bytes(x["parts"]) for x in structure.collect()})

    def run(batches):
        for b in batches:
            h, n, shard = (b.column(k).to_numpy(zero_copy_only=False) for k in (1, 2, 3))
            ok = np.zeros(b.num_rows, bool)
            for s in np.unique(shard).tolist():
                at = np.flatnonzero(shard == s)
                ok[at] = passes(s, given.value.get(s), h[at], n[at])
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(ok)], names=["_row", "_ok"])

    return rows.mapInArrow(run, out).select("_row.*", F.col("_ok").alias(as_))


def bloom_words(members: DataFrame, key, n: int, r: int, seed: int = 0x5EED) -> DataFrame:
    """A Bloom filter of 1.44 r bits per key as a table (word, bits), by or-ing in the aggregate."""
    size = max(64, math.ceil(n * r / math.log(2)))
    h1, h2 = key_hashes(members, as_list(key), seed)
    probe = F.explode(F.transform(F.sequence(F.lit(0), F.lit(max(1, r) - 1)), lambda k: F.pmod(F.pmod(h1, F.lit(size)) + k.cast("long") * F.pmod(h2, F.lit(size - 1)) + k, F.lit(size))))
    return members.select(probe.alias("p")).groupBy(F.floor(F.col("p") / 63).alias("word")).agg(F.bit_or(F.expr("shiftleft(1L, cast(p % 63 as int))")).alias("bits"))


def bloom_might_contain(df: DataFrame, words: DataFrame, key, n: int, r: int, seed: int = 0x5EED, as_: str = "might_contain") -> DataFrame:
    """df with the Bloom filter's answer, by joining probes with words."""
    size = max(64, math.ceil(n * r / math.log(2)))
    h1, h2 = key_hashes(df, as_list(key), seed)
    rows = df.withColumn("_a", h1).withColumn("_b", h2)
    places = F.transform(F.sequence(F.lit(0), F.lit(max(1, r) - 1)), lambda k: F.pmod(F.pmod(F.col("_a"), F.lit(size)) + k.cast("long") * F.pmod(F.col("_b"), F.lit(size - 1)) + k, F.lit(size)))
    keys = rows.select("_a", "_b").distinct()  # equal keys have equal answers, so hashes name them
    hits = keys.select("_a", "_b", F.explode(places).alias("p")).withColumn("word", F.floor(F.col("p") / 63)).join(words, "word")
    good = hits.filter(F.expr("shiftright(bits, cast(p % 63 as int)) & 1") == 1).groupBy("_a", "_b").agg(F.count(F.lit(1)).alias("_n"))
    return rows.join(good, ["_a", "_b"], "left").withColumn(as_, F.coalesce(F.col("_n"), F.lit(0)) == max(1, r)).drop("_a", "_b", "_n")


def fp_rate(built: StaticMap, universe: DataFrame, r: int) -> DataFrame:
    """(r, probes, hits, rate, bound) of keys that are no members."""
    return might_contain(built, universe).agg(F.lit(r).alias("r"), F.count(F.lit(1)).alias("probes"), F.sum(F.col("might_contain").cast("long")).alias("hits")).select("r", "probes", "hits", (F.col("hits") / F.col("probes")).alias("rate"), F.lit(2.0**-r).alias("bound"))


__all__ = ["bloom_might_contain", "bloom_words", "build", "fp_rate", "might_contain"]
