"""Columns with many values, and tables of more rows than the smallest ones."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from predmap import workloads
from predmap.functions import codes
from predmap.operators import baselines, maps


def test_huffman_bits():
    rng = np.random.default_rng(4)
    for n in [[], [7], [1, 1], [3, 1, 1], [1] * 13, *[rng.integers(1, 9, 50).tolist() for _ in range(20)], (2 ** np.arange(20)).tolist()]:
        many = list(zip(*np.unique(n, return_counts=True), strict=True))
        assert codes.huffman_bits(many) == sum(a * b for a, b in zip(n, codes.huffman_row(n), strict=True))


@pytest.fixture(scope="module")
def large(spark, tmp_path_factory):
    """sf0.001 with 400,000 orders, and with 6,000 users in its events."""
    sf = str(tmp_path_factory.mktemp("large"))
    for t in workloads._H0:
        df = spark.read.parquet(f"/root/testdata/sf0.001/{t}.parquet")
        if t == "orders":
            df = spark.range(0, 400_000, 1, 7).select(((F.col("id") * 7919) % 400_000).alias("o_orderkey"), F.element_at(F.array(*map(F.lit, "abcde")), (1 + F.col("id") % 5).cast("int")).alias("o_orderpriority"), F.lit("F").alias("o_orderstatus"))
        if t == "events":
            df = df.crossJoin(spark.range(12)).drop("id").withColumn("event_id", F.monotonically_increasing_id()).withColumn("user_id", F.pmod(F.xxhash64("event_id"), F.lit(6_000)))
        df.write.parquet(f"{sf}/{t}.parquet")
    return sf


def test_huffman_cost_of_many_values(spark, large):
    got = {r["name"]: r for r in workloads.queries()["huffman_cost"](spark, large).collect()}
    r = got["user_id"]
    assert 0 <= r["bits"] - r["entropy_bits"] < 12_000 and len(got) == 20


def test_query_stream_asks_every_key_once(spark, large):
    """The numbers of the keys are the same wherever they are used."""
    before = {k: spark.conf.get(k) for k in ("spark.sql.autoBroadcastJoinThreshold", "spark.sql.adaptive.advisoryPartitionSizeInBytes", "spark.sql.shuffle.partitions")}
    for k, v in zip(before, ("-1", "1m", "16"), strict=True):
        spark.conf.set(k, v)
    try:
        assert tuple(workloads.queries()["query_stream"](spark, large).head()) == (400_000,) * 3
    finally:
        for k, v in before.items():
            spark.conf.set(k, v)


def test_a_large_table_is_not_broadcast(spark, monkeypatch):
    df = spark.range(1000).select("id", (F.col("id") % 3).alias("v"))
    plan = lambda: baselines.explicit_lookup(df.select("id"), df, "id", "v", hint="broadcast")
    assert "BroadcastHashJoin" in plan()._jdf.queryExecution().sparkPlan().toString()
    monkeypatch.setattr(baselines, "BROADCAST_ROWS", 999)
    assert "SortMergeJoin" in plan()._jdf.queryExecution().sparkPlan().toString()
    assert plan().filter("value = id % 3").count() == 1000


@pytest.mark.parametrize("build", [maps.build_entropy, maps.build_fixed, maps.build_sparse])
def test_maps_of_many_values(spark, build):
    df = spark.range(20_000).select("id", F.concat(F.lit("v"), F.pmod(F.xxhash64("id"), F.lit(6_000))).alias("v"))
    built = build(df, "id", "v")
    assert len(built.values) > maps.MOST_VALUES and maps.mismatches(df, built, "v").isEmpty()


@pytest.mark.parametrize("coder", ["shannon", "huffman", "fixed"])
@pytest.mark.parametrize("weights", [[5], [1, 1], [900, 50, 30, 20], list(range(1, 60))])
def test_one_row_of_weights_for_all_keys(coder, weights):
    """The paths are those of the same row for each key."""
    from predmap.config import MapConfig

    w, vid = np.array([weights], np.int64), np.arange(400) % len(weights)
    for filter in ("all", "root", "none"):
        cfg = MapConfig(coder=coder, filter=filter)
        one, each = codes.decisions(w, vid, cfg), codes.decisions(np.repeat(w, 400, 0), vid, cfg)
        assert (one[0] == each[0]).all() and (one[1] == each[1]).all()


def test_regular_systems():
    from predmap.functions.ribbon import regular, solve_dense

    rows = np.random.default_rng(2).integers(0, 1 << 6, (200, 6)).astype(np.uint64)
    for row, full in zip(rows, regular(rows | np.uint64(1 << 40)), strict=True):
        a = (row[:, None] >> np.arange(6).astype(np.uint64) & np.uint64(1)).astype(int)
        assert full == all(solve_dense(a, b) is not None for b in np.eye(6, dtype=int))


@pytest.mark.parametrize("name", ["filter_length_curve", "overhead_curve", "tree_excess_cases", "filter_order_bound", "ribbon_overhead_bound", "solvable_share"])
def test_queries_read_a_table(spark, tmp_path, name):
    """Without the tables there is nothing to work on."""
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        workloads.queries()[name](spark, str(tmp_path)).collect()
