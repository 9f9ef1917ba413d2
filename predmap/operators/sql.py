"""Maps in SQL: a function that looks keys up, and a table function that lists a structure's layers."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from predmap.functions.hashing import key_hashes
from predmap.functions.ribbon import BitStore
from predmap.operators.maps import StaticMap, feature_column
from predmap.operators.shards import unpack_parts


def register(spark: SparkSession, name: str, built: StaticMap) -> None:
    """Registers name(h1, h2, features) for a map small enough to broadcast; ``hashes`` gives its first arguments."""
    size = built.structure(spark).agg(F.sum(F.length("parts"))).head()[0] or 0
    if size > built.cfg.broadcast_bytes:
        raise ValueError("too large to broadcast: use attach")
    given = spark.sparkContext.broadcast({r["shard"]: bytes(r["parts"]) for r in built.structure(spark).select("shard", "parts").collect()})
    decode, shards, values = built._decoder(), built.shards, [v for v, _ in built.values]

    @F.pandas_udf(built.value_type)
    def look_up(h1: pd.Series, h2: pd.Series, x: pd.Series) -> pd.Series:
        a, b = h1.to_numpy(np.int64), h2.to_numpy(np.int64)
        m = np.stack(x.to_list()).astype(np.float64).reshape(len(x), -1) if len(x) else np.zeros((0, 0))
        shard = ((a.view(np.uint64) >> np.uint64(20)).astype(np.int64)) % shards
        out = np.zeros(len(a), np.int64)
        for s in np.unique(shard).tolist():
            at = np.flatnonzero(shard == s)
            out[at] = decode(a[at], b[at], m[at], s, given.value.get(s))
        return pd.Series([values[k] if 0 <= k < len(values) else None for k in out.tolist()])

    spark.udf.register(name, look_up)


def hashes(df: DataFrame, built: StaticMap) -> DataFrame:
    """df with h1, h2 and features as the registered function takes them."""
    h1, h2 = key_hashes(df, built.keys, built.cfg.seed)
    return df.select("*", h1.alias("h1"), h2.alias("h2"), feature_column(built.features).alias("features"))


class Layers:
    """UDTF over a structure's parts: one row per bit store and layer."""

    def eval(self, parts: bytes):
        for name, blob in unpack_parts(bytes(parts)).items():
            if name in ("filter", "correct", "fixed"):
                store = BitStore.from_bytes(blob)
                for k, x in enumerate(store.layers):
                    yield name, k, x.slots, x.width, store.instances, int((x.thresholds > 0).sum()), len(x.thresholds)


def layer_report(spark: SparkSession, built: StaticMap) -> DataFrame:
    """(shard, part, layer, slots, width, instances, bumped_buckets, buckets)."""
    fn = F.udtf(Layers, returnType="part string, layer int, slots long, width int, instances int, bumped_buckets long, buckets long")
    spark.udtf.register("predmap_layers", fn)
    built.structure(spark).createOrReplaceTempView("predmap_structure")
    return spark.sql("SELECT shard, l.* FROM predmap_structure, LATERAL predmap_layers(parts) l")
