"""Keys as two hashes. A bitmap of NULLs is hashed with the columns, as Spark's hash skips NULLs."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T


def hashable(df: DataFrame, name: str) -> Column:
    """A column that xxhash64 takes: maps become sorted entries."""
    c = F.col(name)
    return F.array_sort(F.map_entries(c)) if isinstance(df.schema[name].dataType, T.MapType) else c


def key_hashes(df: DataFrame, keys: Sequence[str], seed: int) -> tuple[Column, Column]:
    """128 bits: one half routes and addresses, the other tells colliding keys apart when building."""
    cols = [hashable(df, k) for k in keys]
    nulls = F.concat(*[F.when(c.isNull(), F.lit("1")).otherwise(F.lit("0")) for c in cols])
    return F.xxhash64(F.lit(seed), *cols, nulls), F.xxhash64(F.lit(~seed), nulls, *cols)


def shard_of(h: Column, shards: int) -> Column:
    """By the upper bits, which the ribbons' own hashes do not reuse."""
    return F.pmod(F.shiftrightunsigned(h, 20), F.lit(shards)).cast("int")
