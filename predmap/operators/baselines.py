"""What maps are compared with: an explicit table, and the other structures' sizes."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from predmap.operators.maps import MOST_SHARED, as_list, dictionary


BROADCAST_ROWS = 1 << 20


def explicit(df: DataFrame, key, value: str, path: str) -> DataFrame:
    """The table itself, written once: keys and values."""
    df.select(*as_list(key), value).write.mode("overwrite").parquet(path)
    return df.sparkSession.read.parquet(path)


def explicit_lookup(queries: DataFrame, stored: DataFrame, key, value: str, as_: str = "value", hint: str | None = None) -> DataFrame:
    """A join; hint: broadcast, merge or shuffle_hash. A table of more than BROADCAST_ROWS rows is not broadcast, which would take it
    through the driver's memory, but sorted and merged, which can spill."""
    if hint == "broadcast" and stored.count() > BROADCAST_ROWS:
        hint = "merge"
    side = stored.select(*as_list(key), F.col(value).alias(as_))
    return queries.join(side.hint(hint) if hint else side, as_list(key), "left")


def explicit_bits(df: DataFrame, key: Sequence[str], value: str) -> float:
    """Bits per key of keys and values as they are: bytes of strings, widths of numbers; values as dictionary codes."""
    wide = {"string": None, "bigint": 64, "int": 32, "double": 64, "timestamp": 64, "boolean": 1}
    parts = [F.lit(wide[t]) if wide.get(t) else F.octet_length(F.col(c)) * 8 for c, t in df.select(*as_list(key)).dtypes]
    n = max(0, len(dictionary(df, value, MOST_SHARED)) - 1).bit_length()
    return float(df.select(sum(parts, F.lit(n)).alias("b")).agg(F.avg("b")).head()[0] or 0)
