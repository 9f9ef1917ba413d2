"""The experiments on the given tables, and the registry of queries with their SQL."""

from __future__ import annotations

import time
from contextlib import contextmanager
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from predmap.config import MapConfig
from predmap.functions import codes, metrics, theory
from predmap.models import MLP, BucketTable, Custom, GaussianNB, Logistic, Point
from predmap.operators import baselines, filters, maps, sql
from predmap.plans import select
from predmap.sources import mappings as src
from predmap.streaming import monitor

CFG = MapConfig()
QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(name: str, oracle: str | None = None):
    def add(fn):
        QUERIES[name] = fn
        if oracle:
            SQL[name] = oracle
        return fn

    return add


def queries() -> dict:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(SQL)


def given_back(m: src.Mapping, built: maps.StaticMap, route: str = "auto") -> DataFrame:
    """Keys and their values as the map has them."""
    extra = [c for c in m.features if c not in m.keys]
    return built.attach(m.df.select(*m.keys, *extra), "value", route=route).select(*m.keys, "value")


def guided(m: src.Mapping, model, cfg: MapConfig = CFG, check: bool = False) -> maps.StaticMap:
    return maps.build_guided(m.df, m.keys, m.value, m.features, model, cfg, check=check)


def flagship(spark: SparkSession, sf: str) -> DataFrame:
    """The language of each document out of a guided map that holds no document."""
    m = src.language(spark, sf)
    return given_back(m, guided(m, Logistic()))


# -- round trips: build, store, look up every key

query("roundtrip_guided_lang", "SELECT doc_id, lang AS value FROM documents")(flagship)

_LINES = "SELECT l_orderkey, l_partkey, l_suppkey, l_linenumber, l_extendedprice, min({0}) AS value FROM lineitem GROUP BY l_orderkey, l_partkey, l_suppkey, l_linenumber, l_extendedprice, l_shipdate"


def _line_values(spark, sf, value, build):
    df = src.lines(spark, sf)
    return build(df, src.LINE, value).attach(df.select(*src.LINE), "value").drop("l_shipdate")


@query("roundtrip_fixed_returnflag", _LINES.format("l_returnflag"))
def _(spark, sf):
    return _line_values(spark, sf, "l_returnflag", maps.build_fixed)


@query("roundtrip_entropy_discount", _LINES.format("l_discount"))
def _(spark, sf):
    return _line_values(spark, sf, "l_discount", maps.build_entropy)


@query("roundtrip_fixed_quantity", _LINES.format("l_quantity"))
def _(spark, sf):
    return _line_values(spark, sf, "l_quantity", maps.build_fixed)


def _simple(table, key, value, build, **options):
    def run(spark, sf):
        df = src.table(spark, sf, table).select(key, value)
        return build(df, key, value, **options).attach(df.select(key), "value")

    return run


for _kind, _build in (("entropy", maps.build_entropy), ("fixed", maps.build_fixed), ("sparse", maps.build_sparse)):
    query(f"roundtrip_{_kind}_priority", "SELECT o_orderkey, o_orderpriority AS value FROM orders")(_simple("orders", "o_orderkey", "o_orderpriority", _build))
query("roundtrip_sparse_status", "SELECT o_orderkey, o_orderstatus AS value FROM orders")(_simple("orders", "o_orderkey", "o_orderstatus", maps.build_sparse))
for _filter in ("none", "root", "all"):
    query(f"roundtrip_entropy_filter_{_filter}", "SELECT e.doc_id, e.toxic AS value FROM labels e")(_simple("labels", "doc_id", "toxic", maps.build_entropy, cfg=replace(CFG, filter=_filter)))
for _name, _cfg in (("randomised", replace(CFG, r_mode="randomised")), ("huffman", replace(CFG, coder="huffman")), ("fixed_code", replace(CFG, coder="fixed")), ("no_head", replace(CFG, fast_head=False)), ("narrow", replace(CFG, ribbon_width=16, bucket=128)), ("per_bit_key", replace(CFG, layout="per_bit_key"))):

    def _variant(spark, sf, cfg=_cfg):
        m = src.windows(spark, sf)
        return given_back(m, guided(m, GaussianNB(), cfg))

    query(f"roundtrip_guided_{_name}", "SELECT event_id, CAST(floor((dayofmonth(ts) - 1) / 3) AS INTEGER) AS value FROM events")(_variant)


@query("roundtrip_guided_window10", "SELECT event_id, CAST(floor((dayofmonth(ts) - 1) / 3) AS INTEGER) AS value FROM events")
def _(spark, sf):
    m = src.windows(spark, sf)
    return given_back(m, guided(m, GaussianNB()))


@query("roundtrip_guided_window10_mlp", "SELECT event_id, CAST(floor((dayofmonth(ts) - 1) / 3) AS INTEGER) AS value FROM events")
def _(spark, sf):
    m = src.windows(spark, sf)
    return given_back(m, guided(m, MLP(hidden=1, units=50, dtype="int8")))


@query("roundtrip_guided_day", "SELECT event_id, CAST(dayofmonth(ts) AS INTEGER) AS value FROM events")
def _(spark, sf):
    m = src.days(spark, sf)
    return given_back(m, guided(m, GaussianNB()))


@query("roundtrip_guided_day_shuffled", "SELECT event_id, CAST(dayofmonth(ts) AS INTEGER) AS value FROM events")
def _(spark, sf):
    m = src.days(spark, sf)
    return given_back(m, guided(m, GaussianNB(), replace(CFG, shard_keys=1 << 11)), "shuffle")


_SLICE = "CAST(least(floor(((epoch_us(ts) - 1704067200000000) / (30 * 86400000000.0::DOUBLE)) * 82), 81) AS INTEGER)"


@query("roundtrip_guided_slice82", f"SELECT event_id, {_SLICE} AS value FROM events")
def _(spark, sf):
    m = src.slices(spark, sf)
    return given_back(m, guided(m, GaussianNB()))


@query("roundtrip_guided_gauss", "SELECT i AS id, CAST(i % 8 AS INTEGER) AS value FROM range((SELECT count(*) FROM lineitem)) t(i)")
def _(spark, sf):
    m = src.gauss(spark, src.table(spark, sf, "lineitem").count(), 8, 0.5)
    return given_back(m, guided(m, GaussianNB()))


@query("roundtrip_guided_url_english", "SELECT url, contains(html, 'lang=\"en\"') AS value FROM pages")
def _(spark, sf):
    m = src.url_language(spark, sf)
    return given_back(m, guided(m, Logistic()))


@query("roundtrip_guided_quality", "SELECT doc_id, quality AS value FROM labels")
def _(spark, sf):
    m = src.quality(spark, sf)
    return given_back(m, guided(m, Logistic()))


@query("roundtrip_guided_role", "SELECT conv_id, turn, role AS value FROM conversations")
def _(spark, sf):
    m = src.role(spark, sf)
    return given_back(m, guided(m, BucketTable(columns=2)))


@query("roundtrip_guided_region", "SELECT c_custkey, n_nationkey % 5 AS value FROM customer JOIN nation ON c_nationkey = n_nationkey")
def _(spark, sf):
    m = src.region(spark, sf)
    return given_back(m, guided(m, BucketTable(columns=1)))


@query("roundtrip_view_region", "SELECT l_orderkey, l_partkey, l_suppkey, l_linenumber, l_extendedprice, r_name AS value FROM (SELECT DISTINCT l_orderkey, l_partkey, l_suppkey, l_linenumber, l_extendedprice, l_shipdate FROM lineitem) JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey")
def _(spark, sf):
    m = src.view_region(spark, sf)
    return given_back(m, guided(m, BucketTable(columns=1))).drop("l_shipdate")


@query("roundtrip_tuple_flags", "SELECT l_orderkey, l_partkey, l_suppkey, l_linenumber, l_extendedprice, min(l_returnflag) AS flag, min(l_linestatus) AS status FROM lineitem GROUP BY l_orderkey, l_partkey, l_suppkey, l_linenumber, l_extendedprice, l_shipdate")
def _(spark, sf):
    df = src.lines(spark, sf)
    built = maps.compress_columns(df, src.LINE, ["l_returnflag", "l_linestatus"], model=lambda hot: BucketTable(columns=3) if hot else None)
    out = built[0].attach(df.select(*src.LINE), "l_returnflag")
    return built[1].attach(out, "status").withColumnRenamed("l_returnflag", "flag").drop("l_shipdate")


@query("roundtrip_user_model", "SELECT c_custkey, n_nationkey % 5 AS value FROM customer JOIN nation ON c_nationkey = n_nationkey")
def _(spark, sf):
    import numpy as np

    m = src.region(spark, sf)
    order = [v for v, _ in maps.dictionary(m.df, m.value)]
    known = Custom(fn=lambda x: np.where(x[:, :1].astype(int) % 5 == np.array(order), 0.99, 0.0025))
    return given_back(m, guided(m, known))


@query("roundtrip_point_model", "SELECT event_id, CAST(floor((dayofmonth(ts) - 1) / 3) AS INTEGER) AS value FROM events")
def _(spark, sf):
    m = src.windows(spark, sf)
    number = F.create_map(*[F.lit(x) for i, (v, _) in enumerate(maps.dictionary(m.df, m.value)) for x in (v, i)])
    df = m.df.select("event_id", "part", number[F.least(F.floor(F.col("place") * 10), F.lit(9)).cast("int")].cast("double").alias("guess"))
    p = src.Mapping(df, ["event_id"], "part", ["guess"])
    return given_back(p, guided(p, Point(confidence=0.95)))


_BITS = "SELECT word, (SELECT coalesce(sum(CASE WHEN substr(word, k, 1) IN ('a','e','i','o','u') AND substr(word, k + 1, 1) NOT IN ('a','e','i','o','u') THEN 1::BIGINT << (k - 1) ELSE 0 END), 0)::BIGINT FROM range(1, length(word)) t(k)) AS value FROM (SELECT DISTINCT unnest(regexp_extract_all(lower(text), '[a-z]{2,}')) AS word FROM documents) WHERE length(word) <= 63"
for _layout in ("interleaved", "per_position", "per_bit_key"):

    def _bits(spark, sf, layout=_layout):
        df = maps_checkpoint(src.words(spark, sf))
        built = maps.build_bits(df, "word", "value", "size", replace(CFG, layout=layout))
        got = built.attach(df.select("word", "size"), "window")
        return got.select("word", F.expr("window & (shiftleft(1L, cast(size as int)) - 1)").alias("value"))

    query(f"roundtrip_bitstring_{_layout}", _BITS)(_bits)


def maps_checkpoint(df: DataFrame) -> DataFrame:
    """df written once and reread."""
    path = maps.scratch_path(df.sparkSession)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


@query("store_and_load", "SELECT o_orderkey, o_orderpriority AS value FROM orders")
def _(spark, sf):
    df = src.table(spark, sf, "orders").select("o_orderkey", "o_orderpriority")
    path = maps.scratch_path(spark)
    maps.build_entropy(df, "o_orderkey", "o_orderpriority").save(spark, path)
    return maps.StaticMap.load(spark, path).attach(df.select("o_orderkey"), "value")


@query("exceptall_lossless", "SELECT 0::BIGINT AS missing, 0::BIGINT AS added")
def _(spark, sf):
    m = src.region(spark, sf)
    got, want = given_back(m, guided(m, GaussianNB())), m.df.select("c_custkey", F.col("n_regionkey").alias("value"))
    return want.exceptAll(got).agg(F.count(F.lit(1)).alias("missing")).crossJoin(got.exceptAll(want).agg(F.count(F.lit(1)).alias("added")))


@query("group_by_restored_column", "SELECT o_orderpriority AS value, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders GROUP BY o_orderpriority")
def _(spark, sf):
    df = src.table(spark, sf, "orders").select("o_orderkey", "o_orderpriority", "o_totalprice")
    got = maps.build_entropy(df, "o_orderkey", "o_orderpriority").attach(df.select("o_orderkey", "o_totalprice"), "value")
    return got.groupBy("value").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


@query("lookup_where", "SELECT o_orderkey, o_orderpriority AS value FROM orders WHERE o_totalprice > 200000 AND o_orderpriority = '1-URGENT'")
def _(spark, sf):
    df = src.table(spark, sf, "orders")
    built = maps.build_entropy(df, "o_orderkey", "o_orderpriority")
    return built.attach(df.select("o_orderkey", "o_totalprice"), "value", where=F.col("o_totalprice") > 200000).filter("value = '1-URGENT'").select("o_orderkey", "value")


@query("sql_function", "SELECT o_orderkey, o_orderstatus AS value FROM orders")
def _(spark, sf):
    df = src.table(spark, sf, "orders")
    built = maps.build_entropy(df, "o_orderkey", "o_orderstatus")
    sql.register(spark, "static_lookup", built)
    sql.hashes(df.select("o_orderkey"), built).createOrReplaceTempView("predmap_queries")
    return spark.sql("SELECT o_orderkey, static_lookup(h1, h2, features) AS value FROM predmap_queries")


@query("layer_report")
def _(spark, sf):
    df = src.table(spark, sf, "orders")
    return sql.layer_report(spark, maps.build_entropy(df, "o_orderkey", "o_orderpriority", CFG))


@query("duplicate_key_check", "SELECT l_orderkey, l_linenumber, count(*) AS n FROM lineitem GROUP BY ALL HAVING count(DISTINCT l_returnflag) > 1")
def _(spark, sf):
    df = src.table(spark, sf, "lineitem")
    return df.groupBy("l_orderkey", "l_linenumber").agg(F.count(F.lit(1)).alias("n"), F.count_distinct("l_returnflag").alias("d")).filter("d > 1").drop("d")


@query("non_member_keys", "SELECT 0::BIGINT AS outside_values")
def _(spark, sf):
    df = src.table(spark, sf, "orders").select("o_orderkey", "o_orderpriority")
    built = maps.build_entropy(df, "o_orderkey", "o_orderpriority")
    got = built.attach(df.select((F.col("o_orderkey") + 1_000_000_000).alias("o_orderkey")), "value")
    return got.agg(F.sum((~F.col("value").isin(*[v for v, _ in built.values])).cast("long")).alias("outside_values"))


# -- baselines: the explicit table, three ways to join it


for _hint in ("broadcast", "merge", "shuffle_hash"):

    def _explicit(spark, sf, hint=_hint):
        df = src.table(spark, sf, "orders")
        stored = baselines.explicit(df, "o_orderkey", "o_orderpriority", maps.scratch_path(spark))
        return baselines.explicit_lookup(df.select("o_orderkey"), stored, "o_orderkey", "o_orderpriority", hint=hint)

    query(f"explicit_{_hint}", "SELECT o_orderkey, o_orderpriority AS value FROM orders")(_explicit)


# -- filters and memberships


def _building(spark, sf):
    """All customers, whether they are members (of a market segment), and fingerprint lengths of 1 to 12 bits."""
    return src.table(spark, sf, "customer").select("c_custkey", (F.col("c_mktsegment") == "BUILDING").alias("member"), (1 + F.col("c_custkey") % 12).alias("r"))


def _passed(answers: DataFrame, share: float) -> DataFrame:
    """Members that pass, with whether at most about that share of the others does."""
    others = answers.agg(F.sum((~F.col("member")).cast("long")).alias("m"), F.sum((~F.col("member") & F.col("might_contain")).cast("long")).alias("hits"))
    few = others.select((F.col("hits") <= share * F.col("m") + 5 * F.sqrt(share * F.col("m")) + 5).alias("few_others"))
    return answers.filter("member AND might_contain").crossJoin(F.broadcast(few))


_MEMBERS = "SELECT c_custkey, true AS few_others FROM customer WHERE c_mktsegment = 'BUILDING'"


@query("filter_no_false_negatives", _MEMBERS)
def _(spark, sf):
    """All customers ask the filter of a segment: its members pass, and of the others one in 256."""
    every = _building(spark, sf)
    return _passed(filters.might_contain(filters.build(every.filter("member"), "c_custkey", 8), every), 2.0**-8).select("c_custkey", "few_others")


@query("filter_of_64_bits", _MEMBERS)
def _(spark, sf):
    every = _building(spark, sf)
    return _passed(filters.might_contain(filters.build(every.filter("member"), "c_custkey", 64), every), 0.0).select("c_custkey", "few_others")


@query("weighted_filter_members", "SELECT c_custkey, 1 + c_custkey % 12 AS r, true AS few_others FROM customer WHERE c_mktsegment = 'BUILDING'")
def _(spark, sf):
    every = _building(spark, sf)
    answers = filters.might_contain(filters.build(every.filter("member"), "c_custkey", "r"), every, r="r")
    return _passed(answers, sum(2.0**-r for r in range(1, 13)) / 12).select("c_custkey", "r", "few_others")


@query("saved_filter", _MEMBERS)
def _(spark, sf):
    """A filter that a later session loads."""
    every, path = _building(spark, sf), maps.scratch_path(spark)
    filters.build(every.filter("member"), "c_custkey", 8).save(spark, path)
    return _passed(filters.might_contain(maps.StaticMap.load(spark, path), every), 2.0**-8).select("c_custkey", "few_others")


@query("saved_membership", "SELECT doc_id, quality = 0 AS value FROM labels")
def _(spark, sf):
    """A weighted membership that a later session loads."""
    df, path = src.table(spark, sf, "labels").select("doc_id", (F.col("quality") == 0).alias("member")), maps.scratch_path(spark)
    maps.build_membership(df, "doc_id", "member", 0.15).save(spark, path)
    return maps.StaticMap.load(spark, path).attach(df.select("doc_id"), "value")


@query("guarded_lookup", "SELECT o_orderkey, o_orderstatus AS value FROM orders")
def _(spark, sf):
    """Keys asked with as many unseen ones, which a guard of 40 bits turns into NULL."""
    df = src.table(spark, sf, "orders").select("o_orderkey", "o_orderstatus")
    asked = df.select("o_orderkey").unionByName(df.select((F.col("o_orderkey") + 10**9).alias("o_orderkey")))
    return monitor.guarded(asked, maps.build_entropy(df, "o_orderkey", "o_orderstatus"), filters.build(df, "o_orderkey", 40)).filter("value IS NOT NULL")


@query("filter_fp_bound", "SELECT r, true AS ok FROM (VALUES (1), (2), (3), (5)) t(r)")
def _(spark, sf):
    members, out = src.table(spark, sf, "orders").select("o_orderkey"), None
    others = spark.range(50_000).select((F.col("id") + 10**9).alias("o_orderkey"))
    for r in (1, 2, 3, 5):
        row = filters.fp_rate(filters.build(members, "o_orderkey", r), others, r)
        ok = F.abs(F.col("rate") - F.col("bound")) <= 5 * F.sqrt(F.col("bound") / F.col("probes")) + 0.01
        out = row.select("r", ok.alias("ok")) if out is None else out.unionByName(row.select("r", ok.alias("ok")))
    return out


@query("weighted_filter_fp_rates")
def _(spark, sf):
    """False positives by r of a weighted filter whose keys have r of 1 to 12."""
    members = src.table(spark, sf, "orders").select("o_orderkey", (1 + F.col("o_orderkey") % 12).alias("r"))
    others = spark.range(60_000).select((F.col("id") + 10**9).alias("o_orderkey"), (1 + F.col("id") % 12).alias("r"))
    got = filters.might_contain(filters.build(members, "o_orderkey", "r"), others, r="r")
    return got.groupBy("r").agg(F.count(F.lit(1)).alias("probes"), F.avg(F.col("might_contain").cast("double")).alias("rate")).withColumn("bound", F.pow(F.lit(2.0), -F.col("r")))


@query("bloom_members", _MEMBERS)
def _(spark, sf):
    every = _building(spark, sf)
    members = every.filter("member")
    n = members.count()
    return _passed(filters.bloom_might_contain(every, filters.bloom_words(members, "c_custkey", n, 8), "c_custkey", n, 8), 2.0**-7).select("c_custkey", "few_others")


@query("benchmark_filter", "SELECT (SELECT count(*) FROM benchmark) AS n, (SELECT count(*) FROM documents) AS asked, 0::BIGINT AS missed")
def _(spark, sf):
    """Benchmark texts as a set, asked with themselves and with all documents: members are all found, and so are documents that are one."""
    b = src.table(spark, sf, "benchmark").select("text")
    docs = src.table(spark, sf, "documents").select("text")
    f = filters.build(b, "text", 12)
    own = filters.might_contain(f, b).filter("might_contain").agg(F.count(F.lit(1)).alias("n"))
    same = filters.might_contain(f, docs).join(b.distinct().withColumn("same", F.lit(True)), "text", "left")
    rest = same.agg(F.count(F.lit(1)).alias("asked"), F.coalesce(F.sum((F.col("same") & ~F.col("might_contain")).cast("long")), F.lit(0)).alias("missed"))
    return own.crossJoin(rest)


@query("membership_roundtrip", "SELECT doc_id, quality = 0 AS value FROM labels")
def _(spark, sf):
    m = src.quality(spark, sf)
    df = m.df.withColumn("member", F.col("quality") == 0).withColumn("share", F.when(F.col("odd") > 0.1, 0.7).otherwise(0.05))
    return maps.build_membership(df, "doc_id", "member", "share").attach(df.select("doc_id", "share"), "value").drop("share")


@query("membership_unweighted", "SELECT doc_id, toxic = 1 AS value FROM labels")
def _(spark, sf):
    df = src.table(spark, sf, "labels").select("doc_id", (F.col("toxic") == 1).alias("member"))
    return maps.build_membership(df, "doc_id", "member", 0.1).attach(df.select("doc_id"), "value")


# -- measures

_H0 = {"orders": ("o_orderstatus", "o_orderpriority"), "documents": ("lang", "source"), "labels": ("quality", "toxic"), "conversations": ("role",), "events": ("event_type", "user_id"), "part": ("p_brand", "p_type", "p_size"), "lineitem": ("l_returnflag", "l_linestatus", "l_discount", "l_tax", "l_quantity", "l_linenumber"), "customer": ("c_mktsegment",), "supplier": ("s_nationkey",)}
_H0_ONE = "SELECT '{1}' AS name, sum(c)::BIGINT AS n, count(*)::BIGINT AS classes, round(log2(sum(c)) - sum(c * log2(c)) / sum(c), 6) AS h0, round(max(c) / sum(c), 6) AS majority FROM (SELECT count(*) AS c FROM {0} GROUP BY {1})"


@query("zero_order_entropy", " UNION ALL ".join(_H0_ONE.format(t, c) for t, cs in _H0.items() for c in cs))
def _(spark, sf):
    out = None
    for t, cs in _H0.items():
        for c in cs:
            row = metrics.value_stats(src.table(spark, sf, t), c).select(F.lit(c).alias("name"), "n", "classes", F.round("h0", 6).alias("h0"), F.round("majority", 6).alias("majority"))
            out = row if out is None else out.unionByName(row)
    return out


@query("value_dictionary", "SELECT CAST(row_number() OVER (ORDER BY n DESC, value) - 1 AS INTEGER) AS vid, value, n FROM (SELECT o_orderpriority AS value, count(*) AS n FROM orders GROUP BY 1)")
def _(spark, sf):
    rows = maps.dictionary(src.table(spark, sf, "orders"), "o_orderpriority")
    return spark.createDataFrame([(i, v, n) for i, (v, n) in enumerate(rows)], "vid int, value string, n long")


_BUCKET = "SELECT {key}, round(-log2(count(*) OVER (PARTITION BY {b}, {v}) / count(*) OVER (PARTITION BY {b})), 6) AS bits FROM {t}"


@query("bucket_surprisal", _BUCKET.format(key="conv_id, turn", b="turn = 0, turn % 2", v="role", t="conversations"))
def _(spark, sf):
    df = src.table(spark, sf, "conversations").select("conv_id", "turn", "role")
    return metrics.bucket_surprisal(df, [F.col("turn") == 0, F.col("turn") % 2], "role").select("conv_id", "turn", F.round("bits", 6).alias("bits"))


@query("bucket_sigma", "SELECT round(sum(bits), 4) AS s, (SELECT 16 * count(*) FROM (SELECT DISTINCT turn = 0, turn % 2, role FROM conversations)) AS enc FROM (" + _BUCKET.format(key="conv_id", b="turn = 0, turn % 2", v="role", t="conversations") + ")")
def _(spark, sf):
    df = src.table(spark, sf, "conversations").select("turn", "role")
    cells = df.select(F.col("turn") == 0, F.col("turn") % 2, "role").distinct().agg((16 * F.count(F.lit(1))).alias("enc"))
    return metrics.bucket_surprisal(df, [F.col("turn") == 0, F.col("turn") % 2], "role").agg(F.round(F.sum(F.round("bits", 6)), 4).alias("s")).crossJoin(cells)


@query("gnb_moments", "SELECT dayofmonth(ts) AS day, count(*) AS n, round(avg(event_id), 4) AS mean_event_id, round(var_pop(event_id), 2) AS var_event_id FROM events GROUP BY 1")
def _(spark, sf):
    df = src.table(spark, sf, "events").select(F.dayofmonth("ts").cast("long").alias("day"), F.col("event_id").cast("double").alias("event_id"))
    return metrics.class_moments(df, "day", ["event_id"]).select("day", "n", F.round("mean_event_id", 4).alias("mean_event_id"), F.round("var_event_id", 2).alias("var_event_id"))


_GAUSS = "SELECT i, i % 8 AS c, 2 * (i % 8) + {s} * sqrt(-2 * ln((('0x' || substr(md5(i::VARCHAR), 1, 8))::BIGINT + 0.5) / 4294967296.0)) * cos(2 * pi() * (('0x' || substr(md5(i::VARCHAR), 9, 8))::BIGINT + 0.5) / 4294967296.0) AS x FROM range((SELECT count(*) FROM lineitem)) t(i)"
_POSTERIOR = "SELECT {s} AS sigma, round(avg(-log2(exp(-(x - 2 * c) * (x - 2 * c) / (2 * {s} * {s})) / (SELECT sum(exp(-(x - 2 * k) * (x - 2 * k) / (2 * {s} * {s}))) FROM range(8) q(k)))), 3) AS s_per_key FROM (" + _GAUSS + ")"


@query("gauss_surprisal", " UNION ALL ".join(_POSTERIOR.format(s=f"{s}::DOUBLE") for s in (0.25, 0.5, 0.75, 1.0)))
def _(spark, sf):
    """S/n with true posteriors, natively: the numbers to replicate are 0.0002, 0.153, 0.558 and 0.914."""
    n, out = src.table(spark, sf, "lineitem").count(), None
    for s in (0.25, 0.5, 0.75, 1.0):
        df = src.gauss(spark, n, 8, s).df
        like = [F.exp(-((F.col("x") - 2 * k) ** 2) / (2 * s * s)) for k in range(8)]
        own = F.exp(-((F.col("x") - 2 * F.col("class")) ** 2) / (2 * s * s))
        row = df.agg(F.round(F.avg(-F.log2(own / sum(like))), 3).alias("s_per_key")).select(F.lit(s).alias("sigma"), "s_per_key")
        out = row if out is None else out.unionByName(row)
    return out


@query("shannon_lengths", "SELECT value, n, CAST((SELECT min(l) FROM range(64) t(l) WHERE n * (1::HUGEINT << l) >= (SELECT count(*) FROM part)) AS INTEGER) AS length FROM (SELECT p_brand AS value, count(*) AS n FROM part GROUP BY 1)")
def _(spark, sf):
    import numpy as np

    rows = maps.dictionary(src.table(spark, sf, "part"), "p_brand")
    lengths = codes.shannon_lengths(np.array([[n for _, n in rows]]))[0]
    return spark.createDataFrame([(v, n, int(x)) for (v, n), x in zip(rows, lengths, strict=True)], "value string, n long, length int")


_LENGTHS = "SELECT value, n, (SELECT min(l) FROM range(64) t(l) WHERE n * (1::HUGEINT << l) >= (SELECT count(*) FROM events)) AS l FROM (SELECT event_type AS value, count(*) AS n FROM events GROUP BY 1)"


@query("shannon_codes", f"WITH w AS ({_LENGTHS}), s AS (SELECT *, coalesce(sum(2.0 ** -l) OVER (ORDER BY l, n DESC, value ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS f FROM w) SELECT value, lpad(bin(CAST(floor(f * 2.0 ** l) AS BIGINT)), CAST(l AS INTEGER), '0') AS code FROM s")
def _(spark, sf):
    import numpy as np

    rows = maps.dictionary(src.table(spark, sf, "events"), "event_type")
    code = codes.Code(np.array([[n for _, n in rows]], np.int64))
    out = [(rows[v][0], format(int(w) >> (codes.DEPTH - int(n)), f"0{n}b")) for v, w, n in zip(code.order[0], code.word[0], code.length[0], strict=True)]
    return spark.createDataFrame(out, "value string, code string")


@query("huffman_cost")
def _(spark, sf):
    """Total bits of global Huffman codes against n H0, from how many values have which count: columns may have any number of values."""
    out = []
    for t, cs in _H0.items():
        for c in cs:
            counts = src.table(spark, sf, t).groupBy(c).agg(F.count(F.lit(1)).alias("k")).groupBy("k").agg(F.count(F.lit(1)).alias("m")).orderBy("k").collect()
            n = sum(r["k"] * r["m"] for r in counts)
            out.append((c, codes.huffman_bits([(r["k"], r["m"]) for r in counts]), float(sum(r["m"] * r["k"] * theory.surprisal(r["k"] / n) for r in counts))))
    return spark.createDataFrame(out, "name string, bits long, entropy_bits double")


_CURVE = "SELECT i, p FROM (SELECT i, sum(n) OVER (ORDER BY i)::DOUBLE / sum(n) OVER ()::DOUBLE AS p FROM (SELECT CAST(floor(o_totalprice / 50) AS BIGINT) AS i, count(*) AS n FROM orders GROUP BY 1)) WHERE p <= 0.5"
_RINT = "(SELECT count(*) FROM range(1, 41) q(k) WHERE 2.0 ** k < (1 - p) / p)"


def _shares(spark, sf) -> DataFrame:
    """For each price step of 50: the share of orders up to it, as far as that is a half."""
    from pyspark.sql import Window

    steps = src.table(spark, sf, "orders").groupBy(F.floor(F.col("o_totalprice") / 50).alias("i")).agg(F.count(F.lit(1)).alias("n"))
    upto, every = F.sum("n").over(Window.orderBy("i").rowsBetween(Window.unboundedPreceding, 0)), F.sum("n").over(Window.partitionBy())
    return steps.select("i", (upto.cast("double") / every.cast("double")).alias("p")).filter("p <= 0.5")


@query("filter_length_curve", f"SELECT i, CAST({_RINT} AS INTEGER) AS r, round(greatest(0, log2(ln(2) * (1 - p) / p)), 6) AS r_real FROM ({_CURVE})")
def _(spark, sf):
    return metrics.overhead_curve(_shares(spark, sf)).select("i", "r", F.round("r_real", 6).alias("r_real"))


@query("overhead_curve", f"SELECT i, round(si + 1e-9, 6) AS space_int, round(sr + 1e-9, 6) AS space_real, round(h + 1e-9, 6) AS h, round(si / h - 1 + 1e-9, 5) AS over_int, round(sr / h - 1 + 1e-9, 5) AS over_real FROM (SELECT i, p * r + p + (1 - p) * 2.0 ** -r AS si, p * rr + p + (1 - p) * 2.0 ** -rr AS sr, -(p * log2(p) + (1 - p) * log2(1 - p)) AS h FROM (SELECT i, p, {_RINT} AS r, greatest(0, log2(ln(2) * (1 - p) / p)) AS rr FROM ({_CURVE})))")
def _(spark, sf):
    return metrics.overhead_curve(_shares(spark, sf)).select("i", *[F.round(F.col(c) + 1e-9, d).alias(c) for d, cs in ((6, ("space_int", "space_real", "h")), (5, ("over_int", "over_real"))) for c in cs])


_TREES = "WITH t AS (SELECT l_quantity AS value, count(*)::DOUBLE / (SELECT count(*) FROM lineitem)::DOUBLE AS e FROM lineitem GROUP BY 1) SELECT value, name, round(l + 1e-9, 6) AS l, round(l - h + 1e-9, 6) AS excess FROM (SELECT value, 'a' AS name, 1 + 2 * e AS l, -((1 - 2 * e) * log2(1 - 2 * e) + 2 * e * log2(e)) AS h FROM t UNION ALL SELECT value, 'b', 1.5, -(0.5 * log2(0.5) + (0.5 - e) * log2(0.5 - e) + e * log2(e)) FROM t UNION ALL SELECT value, 'c', 2 - 2 * e, -(2 * e * log2(2 * e) + 2 * (0.5 - e) * log2(0.5 - e)) FROM t)"


@query("tree_excess_cases", _TREES)
def _(spark, sf):
    """Three trees of three leaves for each quantity, whose share e of all lines is that of the rare leaves."""
    counts, rows = maps.dictionary(src.table(spark, sf, "lineitem"), "l_quantity"), []
    for value, k in counts:
        e = k / sum(c for _, c in counts)
        for name, p, depth in (("a", (1 - 2 * e, e, e), (1, 2, 2)), ("b", (0.5, 0.5 - e, e), (1, 2, 2)), ("c", (2 * e, 0.5 - e, 0.5 - e), (1, 2, 2))):
            n = theory.expected_length(p, depth)
            rows.append((value, name, round(n + 1e-9, 6), round(n - theory.entropy(p) + 1e-9, 6)))
    return spark.createDataFrame(rows, "value double, name string, l double, excess double")


_CONF = "WITH c AS (SELECT turn = 0 AS b0, turn % 2 AS b1, role, count(*) AS n FROM conversations GROUP BY 1, 2, 3), f AS (SELECT b0, b1, max(n) / sum(n) AS confidence, arg_max(role, (n, role)) AS guess FROM c GROUP BY 1, 2), p AS (SELECT v.conv_id, v.turn, f.confidence, CAST(v.role = f.guess AS BIGINT) AS hit FROM conversations v JOIN f ON (v.turn = 0) = f.b0 AND v.turn % 2 = f.b1)"


def _confident(spark, sf):
    df = src.table(spark, sf, "conversations").select("conv_id", "turn", "role", (F.col("turn") == 0).alias("b0"), (F.col("turn") % 2).alias("b1"))
    n = df.groupBy("b0", "b1", "role").agg(F.count(F.lit(1)).alias("n"))
    best = n.groupBy("b0", "b1").agg((F.max("n") / F.sum("n")).alias("confidence"), F.max_by("role", F.struct("n", "role")).alias("guess"))
    return df.join(best, ["b0", "b1"]).select("conv_id", "turn", "role", "guess", "confidence", (F.col("role") == F.col("guess")).cast("long").alias("hit"))


@query("reliability_curve", _CONF + " SELECT CAST(least(floor(confidence * 50), 49) AS INTEGER) AS bin, count(*) AS n, round(avg(confidence), 6) AS confidence, round(avg(hit), 6) AS accuracy FROM p GROUP BY 1")
def _(spark, sf):
    r = metrics.reliability(_confident(spark, sf))
    return r.select("bin", "n", F.round("confidence", 6).alias("confidence"), F.round("accuracy", 6).alias("accuracy"))


@query("ece_50_bins", _CONF + " SELECT round(sum(n * abs(c - a)) / sum(n), 6) AS ece FROM (SELECT count(*) AS n, avg(confidence) AS c, avg(hit) AS a FROM p GROUP BY least(floor(confidence * 50), 49))")
def _(spark, sf):
    return metrics.ece(_confident(spark, sf)).select(F.round("ece", 6).alias("ece"))


@query("topk_accuracy", "WITH c AS (SELECT p_type, p_brand, count(*) AS n FROM part GROUP BY 1, 2), r AS (SELECT *, row_number() OVER (PARTITION BY p_type ORDER BY n DESC, p_brand) AS k FROM c) SELECT round(sum(CASE WHEN k <= 1 THEN n ELSE 0 END) / sum(n), 6) AS top1, round(sum(CASE WHEN k <= 3 THEN n ELSE 0 END) / sum(n), 6) AS top3 FROM r")
def _(spark, sf):
    from pyspark.sql import Window

    c = src.table(spark, sf, "part").groupBy("p_type", "p_brand").agg(F.count(F.lit(1)).alias("n"))
    r = c.withColumn("k", F.row_number().over(Window.partitionBy("p_type").orderBy(F.desc("n"), "p_brand")))
    return r.agg(*[F.round(F.sum(F.when(F.col("k") <= k, F.col("n")).otherwise(0)) / F.sum("n"), 6).alias(f"top{k}") for k in (1, 3)])


@query("stratified_split_counts", "SELECT o_orderstatus, part, count(*) AS n FROM (SELECT o_orderstatus, CASE WHEN r < 0.2 THEN 'test' WHEN r < 0.28 THEN 'validation' ELSE 'train' END AS part FROM (SELECT o_orderstatus, percent_rank() OVER (PARTITION BY o_orderstatus ORDER BY md5(o_orderkey::VARCHAR)) AS r FROM orders)) GROUP BY 1, 2")
def _(spark, sf):
    df = metrics.stratified(src.table(spark, sf, "orders").select("o_orderkey", "o_orderstatus"), "o_orderstatus", "o_orderkey")
    return df.groupBy("o_orderstatus", "part").agg(F.count(F.lit(1)).alias("n"))


@query("cube_metrics", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
def _(spark, sf):
    return src.table(spark, sf, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"))


@query("topk_surprising", "SELECT conv_id, turn, bits FROM (" + _BUCKET.format(key="conv_id, turn", b="turn = 0, turn % 2", v="role", t="conversations") + ") ORDER BY bits DESC, conv_id, turn LIMIT 20")
def _(spark, sf):
    return QUERIES["bucket_surprisal"](spark, sf).orderBy(F.desc("bits"), "conv_id", "turn").limit(20)


# -- streams

_EVENT_BITS = "(SELECT event_type, -log2(count(*) / (SELECT count(*) FROM events)) AS bits FROM events GROUP BY 1)"


@query("stream_surprisal_windows", f"SELECT date_trunc('hour', ts) AS window_start, count(*) AS n, round(avg(bits), 6) AS mean_bits FROM events JOIN {_EVENT_BITS} USING (event_type) GROUP BY 1")
def _(spark, sf):
    counts = maps.dictionary(src.table(spark, sf, "events"), "event_type")
    n = sum(c for _, c in counts)
    bits = F.create_map(*[F.lit(x) for v, c in counts for x in (v, theory.surprisal(c / n))])[F.col("event_type")]
    stream = monitor.file_stream(spark, sf, "events", src.table(spark, sf, "events").schema).withColumn("ts", F.col("ts").cast("timestamp"))
    out = monitor.run_available(monitor.surprisal_windows(stream, bits), maps.scratch_path(spark))
    return out.select(F.col("window_start").cast("timestamp_ntz").alias("window_start"), "n", F.round("mean_bits", 6).alias("mean_bits"))


@query("stream_enriched", "SELECT event_id, CAST(dayofmonth(ts) AS INTEGER) AS value FROM events")
def _(spark, sf):
    m = src.days(spark, sf)
    built, n = guided(m, GaussianNB()), m.df.count()
    stream = monitor.file_stream(spark, sf, "events", src.table(spark, sf, "events").schema)
    keys = stream.select("event_id", (F.col("event_id") / F.lit(float(max(1, n)))).alias("place"))
    return monitor.run_available(monitor.enrich(keys, built).select("event_id", "value"), maps.scratch_path(spark), "append")


@query("asof_generation", "SELECT event_id, CASE WHEN ts < TIMESTAMP '2024-01-10' THEN 0 WHEN ts < TIMESTAMP '2024-01-20' THEN 1 ELSE 2 END AS generation FROM events")
def _(spark, sf):
    begun = spark.createDataFrame([("2024-01-01", 0), ("2024-01-10", 1), ("2024-01-20", 2)], "since string, generation int").withColumn("since", F.to_timestamp("since"))
    return monitor.generation_at(src.table(spark, sf, "events").select("event_id", "ts"), begun).select("event_id", "generation")


# -- the experiments' tables


def _usual(m: src.Mapping) -> list[tuple]:
    x = m.features
    return [("gaussian", GaussianNB(), x), ("logistic", Logistic(), x), ("mlp 1x50", MLP(hidden=1, units=50), x)]


@query("model_table")
def _(spark, sf):
    """Models on every learnable mapping: size, surprisal, accuracy, calibration, times. The paper's table of models."""
    rows = []
    for name, fn in src.LEARNED.items():
        m = fn(spark, sf)
        best, found = select.best(m.df, m.keys[0], m.value, _usual(m))
        rows += [(name, c.name, c.n, c.params, c.s_per_key, c.enc_per_key, c.sigma, c.top1, c.top3, c.ece, c.fit_us, c.infer_us, c is best) for c in found]
    return spark.createDataFrame(rows, "workload string, model string, n long, params long, s_per_key double, enc_per_key double, sigma double, top1 double, top3 double, ece double, training_us double, inference_us double, chosen boolean")


@query("model_shapes")
def _(spark, sf):
    """Perceptrons of three shapes and logistic regression at three precisions, on the 54-feature mapping and on windows."""
    rows = []
    for name, m in (("language 54", src.language(spark, sf, many=True)), ("windows", src.windows(spark, sf))):
        df = select.held_out(m.df, m.value, m.keys[0])
        for dtype in ("float32", "float16", "int8"):
            for model, title in ((Logistic(dtype=dtype), "logistic"), *((MLP(hidden=h, units=u, dtype=dtype), f"mlp {h}x{u}") for h, u in ((1, 50), (1, 100), (2, 50)))):
                c = select.measure(df, m.keys[0], m.value, title, model, m.features)
                rows.append((name, title, dtype, c.n, c.params, c.s_per_key, c.enc_per_key, c.sigma, c.top1, c.top3, c.ece, c.fit_us, c.infer_us))
    return spark.createDataFrame(rows, "workload string, model string, weights string, n long, params long, s_per_key double, enc_per_key double, sigma double, top1 double, top3 double, ece double, training_us double, inference_us double")


@query("objectives", "SELECT * FROM (VALUES ('space', true), ('latency', true), ('shared', true)) t(objective, as_expected)")
def _(spark, sf):
    """Least space takes the least total; the fastest of the models that pay takes the least inference time; a shared model is free."""
    m = src.windows(spark, sf)
    cases = [("gaussian", GaussianNB(), m.features), ("logistic", Logistic(), m.features)]
    small, found = select.best(m.df, m.keys[0], m.value, cases)
    fast, seen = select.best(m.df, m.keys[0], m.value, cases, "latency")
    free, _ = select.best(m.df, m.keys[0], m.value, cases, model_cost="shared")
    rows = [("space", small.sigma == min(c.sigma for c in found)), ("latency", fast.infer_us == min(c.infer_us for c in seen[1:] if c.sigma < seen[0].sigma)), ("shared", free.enc_per_key == 0.0)]
    return spark.createDataFrame(rows, "objective string, as_expected boolean")


@query("query_stream", "SELECT count(*) AS asked, count(*) AS members, count(*) AS right FROM orders")
def _(spark, sf):
    """As many questions as keys, drawn with replacement by hash, and as many unseen keys among them: members get their values."""
    df = src.table(spark, sf, "orders").select("o_orderkey", "o_orderpriority")
    n = df.count()
    built = maps.build_entropy(df, "o_orderkey", "o_orderpriority")
    spread = df.agg(F.min("o_orderkey").alias("lo"), F.max("o_orderkey").alias("hi")).head()
    place = maps_checkpoint(df.orderBy("o_orderkey").withColumn("_i", F.monotonically_increasing_id()))  # as each plan would sort anew, into other partitions
    numbered = place.select("o_orderkey", "o_orderpriority", (F.shiftright("_i", 33)).alias("_p"), "_i")
    sizes = numbered.groupBy("_p").agg(F.count(F.lit(1)).alias("_n"), F.min("_i").alias("_first"))
    from pyspark.sql import Window

    before = sizes.select("_p", "_first", (F.sum("_n").over(Window.orderBy("_p")) - F.col("_n")).alias("_before"))
    keys = numbered.join(before, "_p").select("o_orderkey", "o_orderpriority", (F.col("_before") + F.col("_i") - F.col("_first")).alias("place"))
    drawn = spark.range(n).select(F.pmod(F.xxhash64("id", F.lit(7)), F.lit(n)).alias("place")).join(keys, "place").select("o_orderkey", "o_orderpriority")
    unseen = spark.range(n).select((F.lit(spread["hi"] + 1) + F.col("id")).alias("o_orderkey"), F.lit(None).cast("string").alias("o_orderpriority"))
    got = built.attach(drawn.unionByName(unseen), "value")
    member = F.col("o_orderpriority").isNotNull()
    return got.agg((F.count(F.lit(1)) / 2).cast("long").alias("asked"), F.sum(member.cast("long")).alias("members"), F.sum((member & (F.col("value") == F.col("o_orderpriority"))).cast("long")).alias("right"))


@query("model_selection", "SELECT * FROM (VALUES ('vectors', true), ('windows', true), ('days', true)) t(workload, as_expected)")
def _(spark, sf):
    """A model must earn its size: none for the vectors, one for windows and days."""
    rows = []
    for name, learn in (("vectors", False), ("windows", True), ("days", True)):
        m = src.LEARNED[name](spark, sf)
        best, _ = select.best(m.df, m.keys[0], m.value, _usual(m)[:2])
        rows.append((name, (best.name != "constant") == learn))
    return spark.createDataFrame(rows, "workload string, as_expected boolean")


@contextmanager
def spread_out(m: src.Mapping):
    """The mapping kept, in memory or on disk, over several partitions a core: a small file is read by few tasks, and of a few large ones the
    last runs alone."""
    least = src.TASKS * m.df.sparkSession.sparkContext.defaultParallelism
    df = m.df.repartition(least, *m.keys) if m.df.rdd.getNumPartitions() < least else m.df
    df = df.persist()
    try:
        yield replace(m, df=df)
    finally:
        df.unpersist()


def _compare(spark, sf, m: src.Mapping, name: str, model, timed: bool = True) -> list[tuple]:
    """Rows of the table of structures for one mapping, which is worked out once and read by all of them. Unless their times are asked
    for, all keys are looked up, and their values compared, in the tasks that build; and an entropy map that equals one before, as no rule
    finds a node for a filter, is that one."""
    with spread_out(m) as m:
        return _compared(spark, sf, m, name, model, timed)


def _compared(spark, sf, m: src.Mapping, name: str, model, timed: bool) -> list[tuple]:
    h0 = metrics.value_stats(m.df, m.value).head()
    rows, df, seen = [], m.df, {}
    rules = {} if timed else {"entropy, no filter": "none", "entropy, root filter": "root", "entropy": "all"}
    values = None if timed else maps.dictionary(df, m.value, maps.MOST_SHARED)
    check = not timed
    build = {
        "fixed": lambda: maps.build_fixed(df, m.keys, m.value, check=check),
        "sparse": lambda: maps.build_sparse(df, m.keys, m.value, check=check),
        "entropy, no filter": lambda: maps.build_entropy(df, m.keys, m.value, replace(CFG, filter="none"), check=check),
        "entropy, root filter": lambda: maps.build_entropy(df, m.keys, m.value, replace(CFG, filter="root"), check=check),
        "entropy": lambda: maps.build_entropy(df, m.keys, m.value, check=check),
        f"guided, {model.kind}": lambda: guided(m, model, check=check),
    }
    for kind, make in build.items():
        plan = maps.entropy_plan(values, replace(CFG, filter=rules[kind])) if kind in rules else kind
        if plan in seen:
            rows.append((name, kind, *seen[plan]))
            continue
        a = time.perf_counter()
        built = make()
        b = time.perf_counter()
        if timed:
            metrics.noop(built.attach(df, "value_got"))
        c = time.perf_counter()
        s = built.space(spark)
        demand = (s["filter_demand"] + s["correct_demand"]) / h0["n"]
        rows.append((name, kind, h0["n"], h0["classes"], h0["h0"], s["bits_per_key"], demand, (s["words"] + s["bumps"] + s["header"]) / h0["n"], s["model"] / h0["n"], (b - a) / h0["n"] * 1e6, (c - b) / h0["n"] * 1e6))
        seen[plan] = rows[-1][2:]
    rows.append((name, "explicit", h0["n"], h0["classes"], h0["h0"], baselines.explicit_bits(df, m.keys, m.value), 0.0, 0.0, 0.0, 0.0, 0.0))
    return rows


SPACE = "workload string, structure string, n long, classes long, h0 double, bits_per_key double, demand_per_key double, structure_per_key double, model_per_key double, build_us double, query_us double"


@query("space_table")
def _(spark, sf):
    """Space and time of all structures on learnable mappings: the paper's table of competitors."""
    rows = []
    for name, model in (("windows", GaussianNB()), ("days", GaussianNB()), ("slices", GaussianNB()), ("language", Logistic()), ("url_language", Logistic()), ("quality", Logistic())):
        rows += _compare(spark, sf, src.LEARNED[name](spark, sf), name, model)
    n = src.table(spark, sf, "lineitem").count()
    for s in (0.25, 0.5, 0.75, 1.0):
        rows += _compare(spark, sf, src.gauss(spark, n, 8, s), f"gauss {s}", GaussianNB())
    return spark.createDataFrame(rows, SPACE)


@query("control_table")
def _(spark, sf):
    """Columns with nothing to learn: the entropy map is near H0."""
    rows = []
    for t, k, v in src.CONTROLS:
        df = src.table(spark, sf, t).select(k, v)
        h0 = metrics.value_stats(df, v).head()
        rows.append((f"{t}.{v}", h0["n"], h0["classes"], h0["h0"], maps.build_entropy(df, k, v).space(spark)["bits_per_key"]))
    return spark.createDataFrame(rows, "name string, n long, classes long, h0 double, entropy_map double")


@query("sweep_gauss")
def _(spark, sf):
    """Overhead and times over hardness and number of classes: the paper's figure."""
    n, rows = src.table(spark, sf, "lineitem").count(), []
    for classes in (2, 8, 32):
        keys = select.held_out(src.normal_keys(spark, n, classes), "class", "id")  # no hardness changes the split
        with spread_out(src.Mapping(keys, ["id"], "class", ["z"])) as kept:
            for sigma in (0.3, 0.5, 0.8, 1.5, 4.0):
                m = src.gauss(spark, n, classes, sigma, kept.df)
                c = select.measure(m.df, "id", "class", "gaussian", GaussianNB(), ["x"])
                m = replace(m, df=m.df.drop(select.SPLIT))
                a = time.perf_counter()
                built = guided(m, c.model)
                b = time.perf_counter()
                metrics.noop(built.attach(m.df, "got"))
                d = time.perf_counter()
                s = built.space(spark)
                rows.append((classes, sigma, c.s_per_key, s["bits_per_key"], (s["words"] + s["bumps"] + s["header"]) / n / c.s_per_key - 1, (s["filter_demand"] + s["correct_demand"]) / n / c.s_per_key - 1, (b - a) / n * 1e6, (d - b) / n * 1e6, c.infer_us))
    return spark.createDataFrame(rows, "classes int, sigma double, s_per_key double, bits_per_key double, overhead double, decision_overhead double, build_us double, query_us double, inference_us double")


@query("hard_slices")
def _(spark, sf):
    """82 classes that overlap: the hard mapping with many values."""
    n, rows = src.table(spark, sf, "lineitem").count(), []
    for sigma in (2.0, 3.0):
        m = src.gauss(spark, n, 82, sigma)
        c = select.measure(m.df, "id", "class", "gaussian", GaussianNB(), ["x"])
        rows.append((sigma, c.s_per_key, c.top1, c.top3, c.ece, guided(m, c.model).space(spark)["bits_per_key"]))
    return spark.createDataFrame(rows, "sigma double, s_per_key double, top1 double, top3 double, ece double, bits_per_key double")


@query("ablation_table")
def _(spark, sf):
    """One change at a time: coder, filter, head shortcut, filter lengths, layout, width, weights' precision, overfitting."""
    m, rows = src.windows(spark, sf), []
    base = lambda **k: (replace(CFG, **k), GaussianNB())
    cases = {
        "base": base(), "huffman per key": base(coder="huffman"), "balanced code": base(coder="fixed"), "root filter": base(filter="root"), "no filter": base(filter="none"), "no head shortcut": base(fast_head=False),
        "randomised lengths": base(r_mode="randomised"), "per-bit keys": base(layout="per_bit_key"), "width 32": base(ribbon_width=32), "width 16": base(ribbon_width=16), "load 1": base(load=1.0), "load 0.9": base(load=0.9),
        "float32": (CFG, GaussianNB(dtype="float32")), "logistic float16": (CFG, Logistic()), "logistic float32": (CFG, Logistic(dtype="float32")), "logistic int8": (CFG, Logistic(dtype="int8")), "logistic overfit": (CFG, Logistic(early_stop_on="train")),
    }
    n = m.df.count()
    for name, (cfg, model) in cases.items():
        a = time.perf_counter()
        built = guided(m, model, cfg)
        b = time.perf_counter()
        metrics.noop(built.attach(m.df, "got"))
        c = time.perf_counter()
        s = built.space(spark)
        rows.append((name, s["bits_per_key"], (s["filter_demand"] + s["correct_demand"]) / n, s["model"] / n, (b - a) / n * 1e6, (c - b) / n * 1e6))
    return spark.createDataFrame(rows, "variant string, bits_per_key double, demand_per_key double, model_per_key double, build_us double, query_us double")


_TRUE = "SELECT true AS ok"


@query("ribbon_overhead_bound", _TRUE)
def _(spark, sf):
    """A fixed-width map of the orders' priorities, of 3 bits, costs at most 4 % more than 3 bits, and 400 bits, besides its dictionary."""
    s = maps.build_fixed(src.table(spark, sf, "orders"), "o_orderkey", "o_orderpriority").space(spark)
    n = src.table(spark, sf, "orders").count()
    return spark.createDataFrame([(s["bits"] - s["dictionary"] < 1.04 * 3 * n + 400,)], "ok boolean")


@query("entropy_map_bound", _TRUE)
def _(spark, sf):
    """The entropy map of a skewed column, at 600,000 keys, needs at most 4 % more than its one weighted membership in theory (itself up to
    10.8 % over H0), and less than one bit per key."""
    df = spark.range(600_000).select("id", F.when(F.pmod(F.xxhash64("id"), F.lit(100)) < 12, 1).otherwise(0).alias("v"))
    (_, most), (_, few) = maps.dictionary(df, "v")
    p, got = few / (most + few), maps.build_entropy(df, "id", "v").space(spark)["bits_per_key"]
    return spark.createDataFrame([(got < 1 and got < 1.04 * theory.space(p, theory.r_int(few, most)),)], "ok boolean")


@query("guided_space_bound", _TRUE)
def _(spark, sf):
    """The guided map of the synthetic mapping stays within 16 % of S plus constants, and below the entropy map and the fixed map."""
    m = src.gauss(spark, 60_000, 8, 0.75)
    s = select.measure(m.df, "id", "class", "gaussian", GaussianNB(), ["x"]).s_per_key
    g, e = guided(m, GaussianNB()).space(spark)["bits_per_key"], maps.build_entropy(m.df, "id", "class").space(spark)["bits_per_key"]
    f = maps.build_fixed(m.df, "id", "class").space(spark)["bits_per_key"]
    return spark.createDataFrame([(g < 1.16 * s + 0.03 and g < e and g < f,)], "ok boolean")


@query("filter_order_bound", _TRUE)
def _(spark, sf):
    """Filters at all nodes need no more than at the root only, and those no more than none, on a skewed column: the orders' price class."""
    df = src.table(spark, sf, "orders").select("o_orderkey", F.expr("CASE WHEN o_totalprice < 450000 THEN 0 WHEN o_totalprice < 485000 THEN 1 WHEN o_totalprice < 495000 THEN 2 ELSE 3 END").alias("v"))
    a, b, c = (maps.build_entropy(df, "o_orderkey", "v", replace(CFG, filter=f)).space(spark)["bits_per_key"] for f in ("all", "root", "none"))
    return spark.createDataFrame([(a <= b * 1.01 and b <= c,)], "ok boolean")


@query("comparison_pivot")
def _(spark, sf):
    """Bits per key of structures side by side."""
    n = src.table(spark, sf, "orders").count()
    rows = [r for s in (0.5, 1.0) for r in _compare(spark, sf, src.gauss(spark, n, 8, s), f"gauss {s}", GaussianNB(), timed=False)]
    return spark.createDataFrame(rows, SPACE).groupBy("workload").pivot("structure").agg(F.round(F.first("bits_per_key"), 4))



@query("savings_table")
def _(spark, sf):
    """Reduction, factor and slow-down of guided maps against the smallest competitor."""
    n, rows = src.table(spark, sf, "orders").count(), []
    rows += _compare(spark, sf, src.windows(spark, sf), "windows", GaussianNB()) + _compare(spark, sf, src.days(spark, sf), "days", GaussianNB())
    for s in (0.5, 1.0):
        rows += _compare(spark, sf, src.gauss(spark, n, 8, s), f"gauss {s}", GaussianNB())
    return metrics.savings(spark.createDataFrame(rows, SPACE), "guided", ("fixed", "sparse"))


@query("solvable_share", "SELECT true AS ok")
def _(spark, sf):
    """Random square systems over GF(2) of 24 rows are solvable for every right side with probability 0.289, for one at random with more.
    The rows are hashes of 24 successive order keys; where fewer keys are left the system is smaller, and so is what is expected."""
    import numpy as np
    import pyarrow as pa

    from predmap.functions.ribbon import regular

    keys = src.table(spark, sf, "orders").select(F.floor(F.col("o_orderkey") / 24).alias("system"), F.xxhash64("o_orderkey").alias("h"))
    systems = keys.groupBy("system").agg(F.sort_array(F.collect_list("h")).alias("rows")).select(F.size("rows").alias("size"), "rows")

    def run(batches):
        for b in batches:
            size = b.column(0).to_numpy(zero_copy_only=False)
            ends = np.cumsum(size)
            flat = b.column(1).flatten().to_numpy(zero_copy_only=False)
            for m in np.unique(size).tolist():
                at = np.flatnonzero(size == m)
                found = regular(flat[(ends[at] - m)[:, None] + np.arange(m)].view(np.uint64))
                yield pa.RecordBatch.from_arrays([pa.array([m]), pa.array([len(at)]), pa.array([int(found.sum())])], names=["size", "n", "full"])

    seen = systems.mapInArrow(run, "size long, n long, full long").groupBy("size").agg(F.sum("n").alias("n"), F.sum("full").alias("full")).collect()
    share = {r["size"]: float(np.prod(1 - 0.5 ** np.arange(1, r["size"] + 1))) for r in seen}
    off = sum(r["full"] - r["n"] * share[r["size"]] for r in seen)
    spread = sum(r["n"] * share[r["size"]] * (1 - share[r["size"]]) for r in seen)
    return spark.createDataFrame([(abs(off) < 4 * spread**0.5,)], "ok boolean")


@query("hashed_split_counts", "SELECT part, count(*) AS n FROM (SELECT CASE WHEN u < 0.2 THEN 'test' WHEN u < 0.28 THEN 'validation' ELSE 'train' END AS part FROM (SELECT ('0x' || substr(md5(o_orderkey::VARCHAR), 1, 8))::BIGINT / 4294967296.0::DOUBLE AS u FROM orders)) GROUP BY 1")
def _(spark, sf):
    return metrics.hashed_split(src.table(spark, sf, "orders").select("o_orderkey"), "o_orderkey").groupBy("part").agg(F.count(F.lit(1)).alias("n"))


def _timed_stream(spark, sf):
    return monitor.file_stream(spark, sf, "events", src.table(spark, sf, "events").schema).withColumn("ts", F.col("ts").cast("timestamp"))


@query("stream_sliding_windows", "SELECT w AS window_start, count(*) AS n, round(avg(value), 6) AS mean_bits FROM (SELECT value, unnest([time_bucket(INTERVAL 15 MINUTE, ts) - k * INTERVAL 15 MINUTE FOR k IN [0, 1, 2, 3]]) AS w FROM events) GROUP BY 1")
def _(spark, sf):
    out = monitor.run_available(monitor.surprisal_windows(_timed_stream(spark, sf), F.col("value"), size="1 hour", slide="15 minutes"), maps.scratch_path(spark))
    return out.select(F.col("window_start").cast("timestamp_ntz").alias("window_start"), "n", F.round("mean_bits", 6).alias("mean_bits"))


@query("stream_sessions", "WITH s AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS b FROM events), g AS (SELECT *, sum(b) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM s) SELECT user_id, min(ts) AS session_start, max(ts) + INTERVAL 30 MINUTE AS session_end, count(*) AS n FROM g GROUP BY user_id, k")
def _(spark, sf):
    out = monitor.run_available(monitor.sessions(_timed_stream(spark, sf), "user_id"), maps.scratch_path(spark))
    return out.select("user_id", *[F.col(c).cast("timestamp_ntz").alias(c) for c in ("session_start", "session_end")], "n")


@query("stream_new_keys", "SELECT count(DISTINCT user_id) AS n FROM events")
def _(spark, sf):
    """First sightings, whose distinct users are all users however often the watermark forgets them."""
    first = monitor.run_available(monitor.new_keys(_timed_stream(spark, sf).select("user_id", "ts"), ["user_id"]), maps.scratch_path(spark), "append")
    return first.agg(F.count_distinct("user_id").alias("n"))


@query("stream_generations", "SELECT event_id, event_type AS value FROM events")
def _(spark, sf):
    """Each micro-batch becomes a generation: a map of its own, which answers for its keys."""
    path, schema = maps.scratch_path(spark), "event_id long, value string"

    def build(batch, number):
        rows = batch.select("event_id", "event_type")
        made = maps.build_entropy(rows, "event_id", "event_type")
        made.attach(rows.select("event_id"), "value").write.mode("overwrite").parquet(f"{path}/rows/generation={number}")

    monitor.each_batch(monitor.file_stream(spark, sf, "events", src.table(spark, sf, "events").schema), build, f"{path}/state")
    return spark.read.schema(schema).parquet(f"{path}/rows").select("event_id", "value")
