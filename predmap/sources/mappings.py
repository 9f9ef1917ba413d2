"""The experiments' mappings on the given tables: key, value and features, as DataFrames; and the synthetic source.

Every function takes (spark, sf_dir) and gives a Mapping. Features are expressions, so scans read only what they name.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

TASKS = 4  # for each core


@dataclass
class Mapping:
    df: DataFrame
    keys: list[str]
    value: str
    features: list[str]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def share(text: Column, sub: str) -> Column:
    """Occurrences of sub per 100 characters."""
    return (F.length(text) - F.length(F.replace(text, F.lit(sub), F.lit("")))) / len(sub) * 100 / F.greatest(F.length(text), F.lit(1))


#: Words and letters that tell the four languages apart.
MARKERS = (" the ", " und ", " der ", " les ", " de ", "é", "ñ", "ü", " of ", " and ", " la ", " el ", " que ", " die ", " est ", "è", "ó", "ä", "ß", "ç")


def text_features(df: DataFrame, text: str = "text", many: bool = False) -> tuple[DataFrame, list[str]]:
    """8 features, or 54: letter rates, markers and structure."""
    low = F.lower(F.coalesce(F.col(text), F.lit("")))
    n = F.greatest(F.length(low), F.lit(1))
    marks = {f"m{i}": share(low, m) for i, m in enumerate(MARKERS if many else MARKERS[:8])}
    if many:
        marks |= {f"l_{c}": share(low, c) for c in "abcdefghijklmnopqrstuvwxyz"}
        raw = F.coalesce(F.col(text), F.lit(""))
        marks |= {
            "s_log": F.log2(n.cast("double")), "s_space": share(low, " "), "s_line": share(low, "\n"), "s_stop": share(low, "."),
            "s_digit": F.regexp_count(raw, F.lit("[0-9]")) * 100 / n, "s_upper": F.regexp_count(raw, F.lit("[A-Z]")) * 100 / n,
            "s_wide": (F.octet_length(raw) - F.length(raw)) * 100 / n, "s_punct": F.regexp_count(raw, F.lit(r"[^\w\s]")) * 100 / n,
        }
    return df.select("*", *[c.alias(k) for k, c in marks.items()]), list(marks)


def language(spark, sf, many=False) -> Mapping:
    df, x = text_features(table(spark, sf, "documents").select("doc_id", "lang", "text"), many=many)
    return Mapping(df.drop("text"), ["doc_id"], "lang", x)


def _label(spark, sf, value) -> Mapping:
    docs = table(spark, sf, "documents").select("doc_id", "text")
    df = table(spark, sf, "labels").join(docs, "doc_id")
    raw = F.greatest(F.length("text"), F.lit(1))
    df = df.select("doc_id", value, (F.regexp_count("text", F.lit(r"[^\p{L}\s]")) / raw).alias("odd"), F.log2(raw.cast("double")).alias("size"))
    return Mapping(df, ["doc_id"], value, ["odd", "size"])


def quality(spark, sf) -> Mapping:
    return _label(spark, sf, "quality")


def toxic(spark, sf) -> Mapping:
    return _label(spark, sf, "toxic")


def events(spark, sf) -> DataFrame:
    return table(spark, sf, "events").withColumn("place", F.col("event_id") / F.lit(float(max(1, table(spark, sf, "events").count()))))


def windows(spark, sf) -> Mapping:
    """Ten values: three days each; 10 features."""
    df = events(spark, sf)
    kinds = [r[0] for r in df.select("event_type").distinct().orderBy("event_type").collect()]
    x = {"place": F.col("place"), "square": F.col("place") ** 2, "amount": F.col("value"), "log": F.log2(F.abs("value") + 1), "k": F.get_json_object("props", "$.k").cast("double")}
    x |= {f"t_{i}": (F.col("event_type") == k).cast("double") for i, k in enumerate(kinds[:5])}
    df = df.select("event_id", F.floor((F.dayofmonth("ts") - 1) / 3).cast("int").alias("part"), *[c.alias(k) for k, c in x.items() if k != "place"], "place")
    return Mapping(df, ["event_id"], "part", list(x))


def slices(spark, sf, count=82) -> Mapping:
    """82 values: equal slices of thirty days."""
    at = F.expr("timestampdiff(MICROSECOND, TIMESTAMP_NTZ '2024-01-01 00:00:00', ts)") / F.lit(30 * 86400_000000.0)
    df = events(spark, sf).select("event_id", "place", F.least(F.floor(at * count), F.lit(count - 1)).cast("int").alias("slice"))
    return Mapping(df, ["event_id"], "slice", ["place"])


def days(spark, sf) -> Mapping:
    return Mapping(events(spark, sf).select("event_id", "place", F.dayofmonth("ts").alias("day")), ["event_id"], "day", ["place"])


def url_language(spark, sf) -> Mapping:
    """Two values; 15 features of the address."""
    df = table(spark, sf, "pages")
    u = F.col("url")
    path = F.lower(F.coalesce(F.parse_url(u, F.lit("PATH")), F.lit("")))
    host = F.coalesce(F.parse_url(u, F.lit("HOST")), F.lit(""))
    x = {
        "https": u.startswith("https"), "size": F.length(u), "digits": F.regexp_count(u, F.lit("[0-9]")), "letters": F.regexp_count(u, F.lit("[A-Za-z]")), "odd": F.regexp_count(u, F.lit("[^A-Za-z0-9]")),
        "dots": F.regexp_count(u, F.lit(r"\.")), "slashes": F.regexp_count(u, F.lit("/")), "query": F.contains(u, F.lit("?")), "fragment": F.contains(u, F.lit("#")), "ext": path.rlike(r"\.[a-z]+$"),
        "labels": F.size(F.split(host, r"\.")), "prefix": host.rlike(r"^(m|blog|www)\."), "en": path.rlike("(^|/)en(/|$)"), "fr": path.rlike("(^|/)fr(/|$)"), "de": path.rlike("(^|/)de(/|$)"),
    }
    df = df.select("url", F.contains("html", F.lit('lang="en"')).alias("english"), *[c.cast("double").alias(k) for k, c in x.items()])
    return Mapping(df, ["url"], "english", list(x))


def url_scheme(spark, sf) -> Mapping:
    m = url_language(spark, sf)
    df = table(spark, sf, "pages").select("page_id", "url").join(m.df.drop("english"), "url").withColumn("secure", F.col("https") == 1.0)
    return Mapping(df.drop("https"), ["page_id"], "secure", [x for x in m.features if x != "https"])


def role(spark, sf) -> Mapping:
    df = table(spark, sf, "conversations").select("conv_id", "turn", "role", (F.col("turn") == 0).cast("double").alias("first"), (F.col("turn") % 2).cast("double").alias("odd"), F.log2(F.length("text") + 1.0).alias("size"))
    return Mapping(df, ["conv_id", "turn"], "role", ["first", "odd", "size"])


def region(spark, sf) -> Mapping:
    """A column that a joined table gives away: region number of customers, from their nation."""
    nation = table(spark, sf, "nation").select(F.col("n_nationkey").alias("c_nationkey"), "n_regionkey")
    df = table(spark, sf, "customer").join(F.broadcast(nation), "c_nationkey").select("c_custkey", "c_nationkey", "n_regionkey")
    return Mapping(df, ["c_custkey"], "n_regionkey", ["c_nationkey"])


def view_region(spark, sf) -> Mapping:
    """Region name per line of a five-way join, which is materialised only as a map."""
    nation, reg = table(spark, sf, "nation"), table(spark, sf, "region")
    geo = nation.join(F.broadcast(reg), nation["n_regionkey"] == reg["r_regionkey"]).select("n_nationkey", "r_name")
    people = table(spark, sf, "customer").select("c_custkey", "c_nationkey")
    orders = table(spark, sf, "orders").select("o_orderkey", "o_custkey")
    df = lines(spark, sf).join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(people, F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(geo), F.col("c_nationkey") == F.col("n_nationkey"))
    return Mapping(df.select(*LINE, "c_nationkey", "r_name"), LINE, "r_name", ["c_nationkey"])


LINE = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_extendedprice", "l_shipdate"]


def lines(spark, sf) -> DataFrame:
    """lineitem with a key: no short one is unique, so rows that agree in LINE are reduced to their least values."""
    rest = ["l_returnflag", "l_linestatus", "l_quantity", "l_discount", "l_tax"]
    return table(spark, sf, "lineitem").groupBy(*LINE).agg(*[F.min(c).alias(c) for c in rest])


def vectors(spark, sf) -> Mapping:
    df = table(spark, sf, "embeddings")
    return Mapping(df.select("vec_id", "label", *[F.col("embedding")[j].cast("double").alias(f"e{j}") for j in range(64)]), ["vec_id"], "label", [f"e{j}" for j in range(64)])


def words(spark, sf) -> DataFrame:
    """Distinct words of up to 63 letters and a bit per letter border: 1 where a vowel is followed by another letter that is none."""
    word = F.explode(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]{2,}"), F.lit(0)))
    df = table(spark, sf, "documents").select(word.alias("word")).filter(F.length("word") <= 63).distinct()
    vowel = lambda k: F.substring("word", k, 1).isin(*"aeiou")
    bits = F.transform(F.sequence(F.lit(1), F.length("word") - 1), lambda k: F.when(F.substr(F.col("word"), k, F.lit(1)).isin(*"aeiou") & ~F.substr(F.col("word"), k + 1, F.lit(1)).isin(*"aeiou"), F.lit(1)).otherwise(F.lit(0)))
    df = df.select("word", bits.alias("bits"))
    value = F.aggregate(F.reverse("bits"), F.lit(0).cast("long"), lambda a, b: a * 2 + b)
    return df.select("word", value.alias("value"), F.size("bits").cast("long").alias("size"))


def uniform(key: Column, at: int) -> Column:
    """Uniform in (0, 1) from eight hexadecimal digits of the key's md5."""
    return (F.conv(F.substring(F.md5(key.cast("string")), at, 8), 16, 10).cast("double") + 0.5) / 4294967296.0


def normal_keys(spark: SparkSession, n: int, classes: int) -> DataFrame:
    """Keys of the synthetic mapping: id, class in turn, and z, a standard normal number made of the id."""
    z = F.sqrt(-2 * F.log(uniform(F.col("id"), 1))) * F.cos(2 * math.pi * uniform(F.col("id"), 9))
    return spark.range(0, n, 1, TASKS * spark.sparkContext.defaultParallelism).select("id", (F.col("id") % classes).cast("int").alias("class"), z.alias("z"))


def gauss(spark: SparkSession, n: int, classes: int, sigma: float, keys: DataFrame | None = None) -> Mapping:
    """Synthetic: classes of equal size, one feature, normally distributed around twice the class. keys: ``normal_keys``, if they are
    there already; further columns of theirs stay."""
    keys = normal_keys(spark, n, classes) if keys is None else keys
    return Mapping(keys.withColumn("x", 2 * F.col("class") + sigma * F.col("z")).drop("z"), ["id"], "class", ["x"])


#: Columns without anything to learn: (table, key, value).
CONTROLS = (
    ("orders", "o_orderkey", "o_orderstatus"), ("orders", "o_orderkey", "o_orderpriority"), ("customer", "c_custkey", "c_mktsegment"), ("events", "event_id", "event_type"), ("events", "event_id", "user_id"),
    ("part", "p_partkey", "p_brand"), ("part", "p_partkey", "p_type"), ("part", "p_partkey", "p_size"), ("supplier", "s_suppkey", "s_nationkey"),
)

LEARNED: dict[str, Callable] = {"language": language, "windows": windows, "slices": slices, "days": days, "url_language": url_language, "url_scheme": url_scheme, "quality": quality, "toxic": toxic, "role": role, "region": region, "vectors": vectors}
