"""What keeps maps of many shards fast: shards in tasks of their own, lookups of many keys at once, nothing worked out twice."""

from dataclasses import replace

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from predmap import workloads
from predmap.config import MapConfig
from predmap.functions import codes, metrics
from predmap.models import GaussianNB
from predmap.operators import maps
from predmap.plans import select
from predmap.sources import mappings as src

SMALL = MapConfig(shard_keys=300)


def blobs(spark, built):
    return {r["shard"]: bytes(r["parts"]) for r in built.structure(spark).collect()}


def test_each_shard_is_a_task(spark):
    df = spark.range(6_000).select("id", (F.col("id") % 5).alias("v"))
    built = maps.build_fixed(df, "id", "v", SMALL)
    files = built.structure(spark).select("shard", F.input_file_name().alias("f")).collect()
    assert len(files) == len({r["f"] for r in files}) == built.shards == 20
    assert maps.mismatches(df, built, "v").isEmpty()


def test_more_shards_than_tasks(spark, monkeypatch):
    monkeypatch.setattr(maps, "MOST_TASKS", 3)
    df = spark.range(3_000).select("id", (F.col("id") % 5).alias("v"))
    built = maps.build_entropy(df, "id", "v", SMALL)
    assert built.structure(spark).count() == 10 and maps.mismatches(df, built, "v").isEmpty()


def test_batches_looked_up_together(spark, monkeypatch):
    of = lambda n: pa.RecordBatch.from_arrays([pa.array(np.arange(n))], names=["a"])
    assert [[b.num_rows for b in held] for held in maps.together(map(of, [3, 0, 4, 5, 1, 20, 2]), 7)] == [[3, 4], [5, 1, 20], [2]]
    assert list(maps.together(iter([of(0)]), 7)) == []
    monkeypatch.setattr(maps, "HELD_BYTES", 8)
    assert [len(held) for held in maps.together(map(of, [3, 4]), 1000)] == [1, 1]
    df = spark.range(5_000).select("id", (F.col("id") % 5).alias("v"))
    built = maps.build_entropy(df, "id", "v", SMALL)
    before = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "64")
    try:
        assert built.attach(df, "got", route="broadcast").filter("got = v").count() == 5_000
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", before)


def test_values_checked_where_they_are_built_in(spark):
    m = src.gauss(spark, 4_000, 8, 1.0)
    twice = m.df.union(m.df.limit(500))
    builds = [lambda **k: maps.build_fixed(twice, "id", "class", SMALL, **k), lambda **k: maps.build_sparse(twice, "id", "class", SMALL, **k), lambda **k: maps.build_entropy(twice, "id", "class", SMALL, **k), lambda **k: maps.build_guided(twice, "id", "class", ["x"], GaussianNB(), SMALL, **k)]
    for build in builds:
        assert blobs(spark, build(check=True)) == blobs(spark, build())
    rows, count = maps._keyed(m.df.select("id", F.col("class").alias("_vid")), ["id"], SMALL, 4_000)
    solver = lambda h1, h2, vid, use, part: maps._with_exceptions(maps.sh.solve_fixed(h1[use], vid[use], 3, SMALL))
    with pytest.raises(Exception, match="another value"):
        maps._solved(rows.select("_shard", "_h1", "_h2", "_vid"), solver, None, count, lambda h1, *_: np.zeros(len(h1), np.int64))


def test_equal_entropy_maps(spark):
    """Plans are equal exactly where the stored bytes are, and comparison_pivot has each map's own space."""
    even = spark.range(8_000).select("id", (F.col("id") % 8).cast("int").alias("v"))
    uneven = even.withColumn("v", F.when(F.col("id") % 100 < 80, 0).when(F.col("id") % 100 < 99, 1).otherwise(F.col("v")))
    for df, different in ((even, 1), (uneven, 3)):
        cfgs = [replace(MapConfig(), filter=f) for f in ("none", "root", "all")]
        plans = [maps.entropy_plan(maps.dictionary(df, "v"), cfg) for cfg in cfgs]
        stored = [str(blobs(spark, maps.build_entropy(df, "id", "v", cfg))) for cfg in cfgs]
        assert len(set(plans)) == len(set(stored)) == different
    assert len({maps.entropy_plan([("a", 5), ("b", 1)], replace(MapConfig(), r_mode="randomised", filter=f)) for f in ("root", "all")}) == 2


def test_untimed_structures_take_the_same_space(spark):
    m = src.gauss(spark, 3_000, 8, 0.5)
    a, b = (workloads._compare(spark, None, m, "gauss", GaussianNB(), timed=t) for t in (True, False))
    assert [r[:9] for r in a] == [r[:9] for r in b] and len(a) == 7


def test_code_lengths():
    rng = np.random.default_rng(5)
    w = np.concatenate([rng.integers(1, 1 << k, (200, 6)) for k in (1, 2, 8, 24, 40)] + [np.array([[1, 1, 1, 1, 1, 3], [1, 2, 4, 8, 16, 33], [1, 1, 1, 1, 1, (1 << 52) - 5]])])
    least = [[next(n for n in range(64) if int(x) << n >= int(row.sum())) for x in row] for row in w]
    assert codes.shannon_lengths(w).tolist() == least
    low, high = w.min(1), w.max(1)
    assert codes.filter_bits(low, high, 24).tolist() == [min(24, next(n for n in range(64) if int(x) << (n + 1) >= int(y))) for x, y in zip(low, high, strict=True)]


def test_one_split_for_all_hardnesses(spark):
    """The split of the keys is that of the mapping."""
    keys = select.held_out(src.normal_keys(spark, 2_000, 8), "class", "id")
    names = ["id", "class", "x", select.SPLIT]
    for sigma in (0.3, 4.0):
        own = select.held_out(src.gauss(spark, 2_000, 8, sigma).df, "class", "id")
        assert sorted(map(tuple, src.gauss(spark, 2_000, 8, sigma, keys).df.select(*names).collect())) == sorted(map(tuple, own.select(*names).collect()))


def test_split_sorts_no_table(spark, monkeypatch):
    """The stratified split is that of ranks by md5, though only rows near a share's end are ranked."""
    import hashlib

    monkeypatch.setattr(type(spark.range(1)), "repartitionByRange", lambda *_: pytest.fail("all rows are sorted"))
    rows = [(i, None if i % 50 == 0 else "a" if i % 3 else "b" if i > 3 else "c") for i in range(6_000)]
    got = metrics.stratified(spark.createDataFrame(rows, "id long, v string"), "v", "id").collect()
    groups = {}
    for i, v in rows:
        groups.setdefault(v, []).append((hashlib.md5(f"split{i}".encode()).hexdigest(), i))
    want = {}
    for v, held in groups.items():
        for k, (_, i) in enumerate(sorted(held)):
            rank = k / max(1, len(held) - 1)
            want[i] = (v, "test" if rank < 0.2 else "validation" if rank < 0.28 else "train")
    assert len(got) == len(rows) and {r["id"]: (r["v"], r["part"]) for r in got} == want
