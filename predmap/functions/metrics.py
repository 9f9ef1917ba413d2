"""Measures of values, models, predictions and built maps. All are one-pass aggregates; none collects keys."""

from __future__ import annotations

import time
from collections.abc import Callable, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from predmap.functions import theory
from predmap.functions.codes import surprisal_bits
from predmap.models.core import Model, predict_weights


def value_stats(df: DataFrame, value: str) -> DataFrame:
    """One row: n, classes, h0 (bits) and the majority's share."""
    counts = df.groupBy(F.col(value).alias("_v")).agg(F.count(F.lit(1)).alias("c"))
    n = F.sum("c")
    return counts.agg(n.alias("n"), F.count(F.lit(1)).alias("classes"), (F.log2(n) - F.sum(F.col("c") * F.log2("c")) / n).alias("h0"), (F.max("c") / n).alias("majority"))


def bucket_surprisal(df: DataFrame, buckets: Sequence[str | Column], value: str) -> DataFrame:
    """df with share (of the value in its bucket) and bits (its surprisal) under a table of value frequencies per bucket. A
    frequency table is small beside df, so it is aggregated and joined rather than ranked over windows of df."""
    names = [f"_b{i}" for i in range(len(buckets))]
    rows = df.select("*", *[(F.col(b) if isinstance(b, str) else b).alias(n) for n, b in zip(names, buckets, strict=True)])
    counts = rows.groupBy(*names, F.col(value).alias("_v")).agg(F.count(F.lit(1)).alias("_c"))
    shares = counts.select(*[F.col(n).alias(f"{n}k") for n in names], "_v", (F.col("_c") / F.sum("_c").over(Window.partitionBy(*names))).alias("share"))
    on = [F.col(n).eqNullSafe(F.col(f"{n}k")) for n in names] + [F.col(value).eqNullSafe(F.col("_v"))]
    return rows.join(shares, on).withColumn("bits", -F.log2("share")).drop("_v", *names, *[f"{n}k" for n in names])


def class_moments(df: DataFrame, value: str, features: Sequence[str]) -> DataFrame:
    """Per value: n, and mean and population variance of each feature: all of a Gaussian model, in one aggregation."""
    return df.groupBy(value).agg(F.count(F.lit(1)).alias("n"), *[a for f in features for a in (F.avg(f).alias(f"mean_{f}"), F.var_pop(f).alias(f"var_{f}"))])


def predictions(rows: DataFrame, model: Model, bits: int = 24) -> DataFrame:
    """rows (_vid, _x and others) with surprisal, rank of the true value (0 best, ties by number), confidence and hit of the guess."""
    keep = [c for c in rows.columns if c not in ("_x", "surprisal", "rank", "confidence", "hit")]
    rows = rows.select(*keep, "_x")
    from predmap.operators.maps import matrix

    def run(batches):
        for b in batches:
            w = predict_weights(model, matrix(b.column(len(keep))), bits)
            vid = b.column(keep.index("_vid")).to_numpy(zero_copy_only=False).astype(np.int64)
            own = w[np.arange(len(w)), vid][:, None]
            rank = (w > own).sum(1) + ((w == own) & (np.arange(w.shape[1]) < vid[:, None])).sum(1)
            out = [surprisal_bits(w, vid), rank.astype(np.int64), w.max(1) / w.sum(1), (rank == 0).astype(np.int64)]
            yield pa.RecordBatch.from_arrays([b.column(i) for i in range(len(keep))] + [pa.array(x) for x in out], names=[*keep, "surprisal", "rank", "confidence", "hit"])

    schema = rows.select(*keep).schema
    for name, kind in (("surprisal", "double"), ("rank", "long"), ("confidence", "double"), ("hit", "long")):
        schema = schema.add(name, kind)
    return rows.mapInArrow(run, schema)


def total_surprisal(predicted: DataFrame) -> DataFrame:
    return predicted.agg(F.sum("surprisal").alias("s_total"), F.avg("surprisal").alias("s_per_key"))


def topk_accuracy(predicted: DataFrame, *ks: int) -> DataFrame:
    """Columns top<k>: share of keys whose value is among the k likeliest."""
    return predicted.agg(*[F.avg((F.col("rank") < k).cast("double")).alias(f"top{k}") for k in ks])


def reliability(predicted: DataFrame, bins: int = 50, mode: str = "width") -> DataFrame:
    """(bin, n, confidence, accuracy) over bins of equal width or equal count of the confidence column; needs hit."""
    if mode == "width":
        cut = F.least(F.floor(F.col("confidence") * bins), F.lit(bins - 1)).cast("int")
    else:  # borders by sketch, so that no window has to hold all rows
        borders = predicted.agg(F.percentile_approx("confidence", [k / bins for k in range(1, bins)], 100_000)).head()[0] or []
        cut = sum((F.when(F.col("confidence") > F.lit(float(b)), 1).otherwise(0) for b in borders), F.lit(0))
    return predicted.groupBy(cut.alias("bin")).agg(F.count(F.lit(1)).alias("n"), F.avg("confidence").alias("confidence"), F.avg(F.col("hit").cast("double")).alias("accuracy"))


def ece(predicted: DataFrame, bins: int = 50, mode: str = "width") -> DataFrame:
    """Expected calibration error: mean distance of confidence and accuracy over bins, weighted by rows."""
    r = reliability(predicted, bins, mode)
    return r.agg((F.sum(F.col("n") * F.abs(F.col("confidence") - F.col("accuracy"))) / F.sum("n")).alias("ece"))


def stratified(df: DataFrame, value: str, key: str, test: float = 0.2, validation: float = 0.1, as_: str = "part") -> DataFrame:
    """df with the column as_: within each value, by md5 of the salted (distinct) key, the first test share is test, the next validation share of the rest
    validation. Nothing is sorted as a whole: counts of the md5's first twelve bits tell in which two cells of a value its shares end; rows
    of other cells are on one side, and only those two cells' rows are ranked."""
    from predmap.operators.maps import scratch_path

    spark, names = df.sparkSession, df.columns
    path = scratch_path(spark)
    code = F.coalesce(F.unhex(F.md5(F.concat(F.lit("split"), F.col(key).cast("string")))), F.lit(b""))  # features may be made of the key's own md5
    first = F.conv(F.substring(F.hex("_md5"), 1, 3), 16, 10).cast("int")
    df.select(*names, code.alias("_md5")).select("*", F.coalesce(first, F.lit(-1)).alias("_cell")).write.parquet(path)
    rows = spark.read.parquet(path)
    by = Window.partitionBy("_v")
    cells = rows.groupBy(F.col(value).alias("_v"), "_cell").agg(F.count(F.lit(1)).alias("_n"))
    cells = cells.select("_v", F.col("_cell").alias("_c"), "_n", F.sum("_n").over(by).alias("_all"), (F.sum("_n").over(by.orderBy("_cell")) - F.col("_n")).alias("_before"))
    share = lambda at: at / F.greatest(F.col("_all") - 1, F.lit(1))
    part = lambda rank: F.when(rank < test, "test").when(rank < test + (1 - test) * validation, "validation").otherwise("train")
    cells = cells.select("*", part(share(F.col("_before"))).alias("_from"), part(share(F.col("_before") + F.col("_n") - 1)).alias("_to"))
    last = lambda *kinds: F.coalesce(F.max(F.when(F.col("_to").isin(*kinds), F.col("_c"))), F.lit(-2))
    split = F.col("_from") != F.col("_to")
    ends = cells.groupBy("_v").agg(last("test").alias("_tested"), last("test", "validation").alias("_validated"), F.map_from_entries(F.collect_list(F.when(split, F.struct("_c", "_before")))).alias("_open"), F.first("_all").alias("_all"))
    found = rows.join(F.broadcast(ends), F.col(value).eqNullSafe(F.col("_v")))
    before = F.element_at("_open", F.col("_cell"))
    close = found.filter(before.isNotNull()).repartition(spark.sparkContext.defaultParallelism, "_v", "_cell")  # few rows, for which there need not be many tasks
    sure = F.when(F.col("_cell") <= F.col("_tested"), "test").when(F.col("_cell") <= F.col("_validated"), "validation").otherwise("train")
    rank = F.row_number().over(Window.partitionBy("_v", "_cell").orderBy("_md5")) - 1
    return found.filter(before.isNull()).select(*names, sure.alias(as_)).unionAll(close.select(*names, part(share(before + rank)).alias(as_)))


def hashed_split(df: DataFrame, key: str, test: float = 0.2, validation: float = 0.1) -> DataFrame:
    """df with part by the key's md5 alone: no window and no shuffle, so for any size; strata get their shares up to sampling error."""
    u = F.conv(F.substring(F.md5(F.col(key).cast("string")), 1, 8), 16, 10).cast("double") / 4294967296.0
    return df.withColumn("part", F.when(u < test, "test").when(u < test + (1 - test) * validation, "validation").otherwise("train"))


def savings(table: DataFrame, ours: str, others: Sequence[str]) -> DataFrame:
    """From rows (workload, structure, bits_per_key, build_us, query_us): what the structures whose name starts with ours save against
    the smallest of others (percent and factor), and how much slower they are built and queried than it."""
    mine = table.filter(F.col("structure").startswith(ours)).select("workload", *[F.col(c).alias(f"own_{c}") for c in ("bits_per_key", "build_us", "query_us")])
    best = table.filter(F.col("structure").isin(*others)).groupBy("workload").agg(F.min(F.struct("bits_per_key", "structure", "build_us", "query_us")).alias("b"))
    both = mine.join(best, "workload")
    return both.select(
        "workload", F.col("b.structure").alias("against"), (100 * (1 - F.col("own_bits_per_key") / F.col("b.bits_per_key"))).alias("saved_percent"), (F.col("b.bits_per_key") / F.col("own_bits_per_key")).alias("factor"),
        (F.col("own_build_us") / F.col("b.build_us")).alias("build_slowdown"), (F.col("own_query_us") / F.col("b.query_us")).alias("query_slowdown"),
    )


def overhead_curve(shares: DataFrame) -> DataFrame:
    """For rows (i, p) with 0 < p <= 1/2: filter lengths, spaces and overheads over the binary entropy."""
    p = F.col("p")
    grid = shares.select("i", "p", theory.r_int_column(p).alias("r"), F.greatest(F.lit(0.0), F.log2(F.log(F.lit(2.0)) * (1 - p) / p)).alias("r_real"), theory.binary_entropy_column(p).alias("h"))
    out = grid.select("*", theory.space_column(p, F.col("r").cast("double")).alias("space_int"), theory.space_column(p, F.col("r_real")).alias("space_real"))
    return out.select("*", (F.col("space_int") / F.col("h") - 1).alias("over_int"), (F.col("space_real") / F.col("h") - 1).alias("over_real"))


def timed(action: Callable, runs: int = 3) -> tuple[float, float, float]:
    """Mean, least and most seconds of runs of action."""
    took = []
    for _ in range(runs):
        a = time.perf_counter()
        action()
        took.append(time.perf_counter() - a)
    return sum(took) / runs, min(took), max(took)


def noop(df: DataFrame) -> None:
    """Runs df and throws its rows away."""
    df.write.format("noop").mode("overwrite").save()
