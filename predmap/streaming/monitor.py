"""Streams: lookups on them, generations of maps, and windows over surprisal.

Maps never change. New keys form new generations; a query is answered by the generation that was current at its time. Lookups
in a stream are stateless and drop nothing; watermarks bound the state of monitors only.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from predmap.operators.maps import StaticMap


def file_stream(spark: SparkSession, folder: str, name: str, schema: T.StructType) -> DataFrame:
    """The Parquet table name of a folder, as a stream."""
    return spark.readStream.schema(schema).option("pathGlobFilter", f"{name}.parquet").parquet(folder)


def enrich(stream: DataFrame, built: StaticMap, as_: str = "value") -> DataFrame:
    """The stream with the map's column: a broadcast lookup, no state. A structure over the configured size is refused: look such a map
    up batch by batch (``each_batch``), where ``attach`` can group keys by shard."""
    size = built.structure(stream.sparkSession).agg(F.sum(F.length("parts"))).head()[0] or 0
    if size > built.cfg.broadcast_bytes:
        raise ValueError(f"{size} bytes are too many to broadcast to a stream: use each_batch")
    return built.attach(stream, as_, route="broadcast")


def surprisal_windows(stream: DataFrame, bits: Column, ts: str = "ts", size: str = "1 hour", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """(window_start, n, mean_bits) over tumbling or sliding windows; rows later than late no longer count."""
    w = F.window(ts, size, slide) if slide else F.window(ts, size)
    return stream.withWatermark(ts, late).groupBy(w.alias("w")).agg(F.count(F.lit(1)).alias("n"), F.avg(bits).alias("mean_bits")).select(F.col("w.start").alias("window_start"), "n", "mean_bits")


def sessions(stream: DataFrame, key: str, ts: str = "ts", gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    return stream.withWatermark(ts, late).groupBy(F.session_window(ts, gap).alias("w"), key).agg(F.count(F.lit(1)).alias("n")).select(key, F.col("w.start").alias("session_start"), F.col("w.end").alias("session_end"), "n")


def new_keys(stream: DataFrame, keys: list[str], ts: str = "ts", late: str = "1 hour") -> DataFrame:
    """First sightings within the watermark: what the next generation is built from."""
    return stream.withWatermark(ts, late).dropDuplicatesWithinWatermark(keys)


def run_available(df: DataFrame, checkpoint: str, mode: str = "complete") -> DataFrame:
    """Everything that is there now, as a batch table of files: mode append adds rows, complete writes all groups with each batch."""
    spark, out = df.sparkSession, f"{checkpoint}/rows"
    writer = df.writeStream.outputMode(mode).option("checkpointLocation", f"{checkpoint}/state").trigger(availableNow=True)
    if mode == "append":
        writer.format("parquet").option("path", out).start().awaitTermination()
    else:
        spark.createDataFrame([], df.schema).write.mode("overwrite").parquet(out)
        writer.foreachBatch(lambda batch, _: batch.write.mode("overwrite").parquet(out)).start().awaitTermination()
    return spark.read.schema(df.schema).parquet(out)


def guarded(stream: DataFrame, built: StaticMap, guard: StaticMap, as_: str = "value") -> DataFrame:
    """The stream (or table) with the map's column, NULL for keys that a filter of the member keys turns away: unseen keys pass with 2^-r
    only."""
    from predmap.operators import filters

    known = filters.might_contain(guard, built.attach(stream, as_), "_known")
    return known.withColumn(as_, F.when(F.col("_known"), F.col(as_))).drop("_known")


def labelled_later(keys: DataFrame, labels: DataFrame, key: str, ts: str = "ts", within: str = "1 hour") -> DataFrame:
    """Stream-stream interval join: keys with the labels that arrive at most so much later; state is bounded by both watermarks."""
    a, b = keys.withWatermark(ts, within).alias("k"), labels.withWatermark(ts, within).alias("l")
    on = (F.col(f"k.{key}") == F.col(f"l.{key}")) & (F.col(f"l.{ts}") >= F.col(f"k.{ts}")) & (F.col(f"l.{ts}") <= F.col(f"k.{ts}") + F.expr(f"INTERVAL {within}"))
    return a.join(b, on).select("k.*", *[F.col(f"l.{c}").alias(f"label_{c}") for c in labels.columns if c != key])


def each_batch(stream: DataFrame, build: Callable[[DataFrame, int], None], checkpoint: str) -> None:
    """Calls build(batch, number) for each micro-batch there is: a delta map per generation."""
    stream.writeStream.foreachBatch(build).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()


def generation_at(queries: DataFrame, generations: DataFrame, ts: str = "ts", since: str = "since", name: str = "generation") -> DataFrame:
    """As-of: each query with the latest generation that began by its time. Generations are few (one per build): a range join
    with them broadcast, then the latest by max_by, keyed by query row."""
    g = F.broadcast(generations.select(F.col(since).alias("_since"), F.col(name).alias("_name"), F.lead(since).over(Window.orderBy(since)).alias("_until")))
    on = (queries[ts] >= F.col("_since")) & (F.col("_until").isNull() | (queries[ts] < F.col("_until")))
    return queries.join(g, on, "left").withColumnRenamed("_name", name).drop("_since", "_until")
