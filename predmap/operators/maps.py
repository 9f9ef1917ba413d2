"""Static maps over DataFrames.

Building: hash the keys, run the model where the rows are (Arrow), send each key's decisions (a few bytes) to its shard, solve the
shard. That is one shuffle. Looking up: model and, if the structure is small by a checked size, structure are broadcast and
nothing is shuffled; otherwise queries are grouped with the structure by shard. The key set is stored nowhere.
"""

from __future__ import annotations

import json
from collections.abc import Sequence
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from predmap.config import MapConfig
from predmap.functions import codes
from predmap.functions.hashing import key_hashes, shard_of
from predmap.functions.ribbon import BitStore
from predmap.models.core import Believed, Constant, Custom, GaussianNB, Model, code_weights, from_json, to_json
from predmap.operators import shards as sh

MOST_VALUES = 4096  # where a model gives each key weights of its own
MOST_SHARED = 1 << 20  # where all keys share one code: what the dictionary takes in a process
FIT_ROWS = 200_000
MOST_TASKS = 4096  # that solve shards; where there are more shards, a task has several
CHECK_ROWS = 1 << 14  # of a shard looked up together
HELD_ROWS, HELD_BYTES, SHARD_ROWS = 1 << 20, 64 << 20, 4096  # queries looked up together at most, and for each shard
STATS = ("filter_demand", "correct_demand", "words", "bumps", "header", "odd")
STRUCTURE = "shard int, n long, parts binary, " + ", ".join(f"{s} long" for s in STATS)
STRUCTURE_ARROW = pa.schema([("shard", pa.int32()), ("n", pa.int64()), ("parts", pa.binary()), *[(s, pa.int64()) for s in STATS]])


def as_list(x) -> list[str]:
    return [x] if isinstance(x, str) else list(x)


def dictionary(df: DataFrame, value: str, most: int = MOST_VALUES) -> list[tuple]:
    """(value, count) by count, then value; NULL is a value. Raises if there are too many for a map of this kind."""
    rows = df.groupBy(F.col(value).alias("v")).agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), F.col("v").asc_nulls_last()).limit(most + 1).collect()
    if len(rows) > most:
        raise ValueError(f"{value} has over {most} values; bucketize it first")
    return [(r["v"], r["n"]) for r in rows]


def with_vid(df: DataFrame, value: str, values: list[tuple], as_: str = "_vid") -> DataFrame:
    """Adds the value's number; the dictionary is bounded by MOST_SHARED, so it is broadcast."""
    schema = T.StructType([T.StructField("_v", df.schema[value].dataType), T.StructField(as_, T.IntegerType(), False)])
    names = df.sparkSession.createDataFrame([(v, i) for i, (v, _) in enumerate(values)], schema)
    return df.join(F.broadcast(names), F.col(value).eqNullSafe(F.col("_v"))).drop("_v")


def together(batches, rows: int):
    """Lists of successive batches of so many rows, or HELD_BYTES, in all; empty ones are left out."""
    held, n, size = [], 0, 0
    for b in batches:
        if b.num_rows:
            held.append(b)
            n, size = n + b.num_rows, size + b.nbytes
        if n >= rows or size >= HELD_BYTES:
            yield held
            held, n, size = [], 0, 0
    if held:
        yield held


def feature_column(features: str | Sequence[str] | Column | None) -> Column:
    """An array<double> of the features; NULL is 0."""
    if features is None:
        return F.array().cast("array<double>")
    if isinstance(features, str):
        return F.transform(F.col(features), lambda x: F.coalesce(x.cast("double"), F.lit(0.0)))
    if isinstance(features, Column):
        return F.transform(features, lambda x: F.coalesce(x.cast("double"), F.lit(0.0)))
    return F.array(*[F.coalesce(F.col(f).cast("double"), F.lit(0.0)) for f in features])


def matrix(column: pa.ChunkedArray | pa.Array) -> np.ndarray:
    """n x features of an Arrow list column."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    n = len(column)
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(n, -1) if n and len(flat) else np.zeros((n, 0))


def fit_model(rows: DataFrame, model: Model, values: list[tuple], fit_rows: int = FIT_ROWS) -> Model:
    """rows: _vid and _x. Constant needs the counts only, a Gaussian one aggregation; others are fitted on at most fit_rows rows."""
    if isinstance(model, Constant):
        model.counts = np.array([n for _, n in values], np.int64)
        return model
    if isinstance(model, (Believed, Custom)):
        return model
    if isinstance(model, GaussianNB):
        width = len(rows.select("_x").head()["_x"])
        aggs = [F.count(F.lit(1)).alias("n")] + [a for j in range(width) for a in (F.avg(F.col("_x")[j]).alias(f"m{j}"), F.var_pop(F.col("_x")[j]).alias(f"v{j}"))]
        got = {r["_vid"]: r for r in rows.groupBy("_vid").agg(*aggs).collect()}
        some = next(iter(got.values()))  # a value that no training row has gets another one's place, as a rare one
        k = [got.get(i) or {**some.asDict(), "n": 1} for i in range(len(values))]
        return model.from_moments([r["n"] for r in k], [[r[f"m{j}"] for j in range(width)] for r in k], [[r[f"v{j}"] for j in range(width)] for r in k])
    n = sum(c for _, c in values)
    sample = rows.select("_vid", "_x", "_h1")
    if n > fit_rows:
        sample = sample.filter(F.pmod(F.xxhash64("_h1"), F.lit(1 << 20)) < F.lit(int((1 << 20) * fit_rows / n)))
    got = sample.orderBy("_h1").limit(fit_rows).toPandas()
    x = np.stack(got["_x"].to_list()) if len(got) else np.zeros((0, 1))
    return model.fit(x.astype(np.float64), got["_vid"].to_numpy(np.int64), len(values))


@dataclass
class StaticMap:
    """A built map: what a query needs, and where its structure is."""

    kind: str
    cfg: MapConfig
    keys: list[str]
    features: object
    values: list[tuple]
    value_type: T.DataType
    model: Model | None
    n: int
    shards: int
    path: str
    extra: dict

    # -- storing
    def save(self, spark: SparkSession, path: str) -> StaticMap:
        """Copies the structure to path, beside the values as a table and the rest as JSON: everything a later session needs. What is
        code (a feature expression, a user's model) must be given again."""
        spark.read.schema(STRUCTURE).parquet(self.path).write.mode("overwrite").parquet(f"{path}/shards")
        kind = self.value_type or T.StringType()
        schema = T.StructType([T.StructField("vid", T.IntegerType()), T.StructField("value", kind), T.StructField("n", T.LongType())])
        spark.createDataFrame([(i, v, n) for i, (v, n) in enumerate(self.values)], schema).coalesce(1).write.mode("overwrite").parquet(f"{path}/dictionary")
        extra = {k: v.tolist() if isinstance(v, np.ndarray) else v for k, v in self.extra.items()}
        info = {
            "kind": self.kind, "keys": self.keys, "features": None if isinstance(self.features, Column) else self.features, "n": self.n, "shards": self.shards, "extra": extra,
            "value_type": self.value_type.json() if self.value_type else None, "model": to_json(self.model) if self.model else None, "config": self.cfg.as_dict(),
        }
        spark.createDataFrame([(json.dumps(info),)], "info string").coalesce(1).write.mode("overwrite").parquet(f"{path}/manifest")
        return replace(self, path=f"{path}/shards")

    @staticmethod
    def load(spark: SparkSession, path: str, features=None, model: Model | None = None) -> StaticMap:
        info = json.loads(spark.read.parquet(f"{path}/manifest").head()["info"])
        kind = T._parse_datatype_json_string(info["value_type"]) if info["value_type"] else None
        values = [(r["value"], r["n"]) for r in spark.read.parquet(f"{path}/dictionary").orderBy("vid").collect()]
        extra = {k: np.array(v, np.int64) if isinstance(v, list) else v for k, v in info["extra"].items()}
        model = model or (from_json(info["model"]) if info["model"] else None)
        return StaticMap(info["kind"], MapConfig(**info["config"]), info["keys"], features if features is not None else info["features"], values, kind, model, info["n"], info["shards"], f"{path}/shards", extra)

    def structure(self, spark: SparkSession) -> DataFrame:
        return spark.read.schema(STRUCTURE).parquet(self.path)

    # -- queries
    @property
    def wide(self) -> bool:
        """Whether a value is several words of bits."""
        return isinstance(self.value_type, T.ArrayType) and self.kind == "bits"

    def _decoder(self):
        """batch, parts of shards -> value numbers (or bit windows)."""
        kind, cfg, model, extra, v = self.kind, self.cfg, self.model, self.extra, len(self.values)
        wide, words = self.wide, max(1, -(-self.extra.get("longest", 1) // 64))
        opened: dict = {}

        def open_parts(key, blob: bytes) -> dict:
            if key not in opened:
                raw = sh.unpack_parts(bytes(blob))
                make = {"filter": BitStore.from_bytes, "correct": BitStore.from_bytes, "fixed": BitStore.from_bytes, "sparse": sh.SparseStore.from_bytes, "bits": sh.load_bits}
                opened[key] = {k: make.get(k, bytes)(x) for k, x in raw.items()}
            return opened[key]

        def decode(h1, h2, x, key, blob) -> np.ndarray:
            if blob is None:
                return np.zeros((len(h1), words) if wide else len(h1), np.int64)
            parts = open_parts(key, blob)
            if kind == "guided":
                out = sh.read_guided(parts, h1, h2, code_weights(model, x, cfg.prob_bits), cfg)
                sh.apply_exceptions(parts["exceptions"], h1, h2, out)
                return out
            if kind == "fixed":
                return parts["fixed"].read_all(h1.view(np.uint64), extra["bits"], cfg).astype(np.int64) % max(1, v)
            if kind == "sparse":
                return sh.read_sparse(parts["sparse"], h1, extra["lengths"], extra["words"])
            window = sh.read_bits(parts["bits"], h1, extra["longest"], cfg).view(np.int64)
            return window if wide else window[:, 0]

        return decode

    def attach(self, df: DataFrame, as_: str = "value", where: Column | str | None = None, route: str = "auto") -> DataFrame:
        """df with the looked-up value as column as_. where (on df's own columns) is applied before the lookup, which Catalyst could not
        do by itself. Keys that were not built in get arbitrary values. route: broadcast, shuffle or auto (by the structure's size)."""
        spark = df.sparkSession
        if as_.lower() in (c.lower() for c in df.columns):
            raise ValueError(f"there is a column {as_} already")
        df = df.filter(where) if where is not None else df
        h1, h2 = key_hashes(df, self.keys, self.cfg.seed)
        x = feature_column(self.features)
        rows = df.select(F.struct("*").alias("_row"), h1.alias("_h1"), h2.alias("_h2"), x.alias("_x")).withColumn("_shard", shard_of(F.col("_h1"), self.shards))
        rows = rows.select("_row", "_h1", "_h2", "_x", "_shard")
        structure = self.structure(spark)
        if route == "auto":
            size = structure.agg(F.sum(F.length("parts"))).head()[0] or 0
            route = "broadcast" if size <= self.cfg.broadcast_bytes else "shuffle"
        decode = self._decoder()
        wide, words = self.wide, max(1, -(-self.extra.get("longest", 1) // 64))
        out_type = T.StructType([rows.schema["_row"], T.StructField("_vid", T.ArrayType(T.LongType()) if wide else T.LongType())])

        def column(found: np.ndarray) -> pa.Array:
            return pa.ListArray.from_arrays(pa.array(np.arange(len(found) + 1, dtype=np.int32) * words), pa.array(found.ravel())) if wide else pa.array(found)

        if route == "broadcast":
            given = spark.sparkContext.broadcast({r["shard"]: bytes(r["parts"]) for r in structure.select("shard", "parts").collect()})

            def run(batches):
                for held in together(batches, min(HELD_ROWS, SHARD_ROWS * len(given.value))):  # so that a shard is asked for many keys at once
                    h1, h2, shard = (np.concatenate([b.column(k).to_numpy(zero_copy_only=False) for b in held]) for k in (1, 2, 4))
                    x = np.concatenate([matrix(b.column(3)) for b in held])
                    out = np.zeros((len(h1), words) if wide else len(h1), np.int64)
                    order = np.argsort(shard, kind="stable")
                    cuts = np.flatnonzero(np.diff(shard[order])) + 1
                    for at in np.split(order, cuts):
                        s = int(shard[at[0]])
                        out[at] = decode(h1[at], h2[at], x[at], s, given.value.get(s))
                    done = 0
                    for b in held:
                        yield pa.RecordBatch.from_arrays([b.column(0), column(out[done : done + b.num_rows])], names=["_row", "_vid"])
                        done += b.num_rows

            found = rows.mapInArrow(run, out_type)
        else:

            def join(key, q, s):
                if not q.num_rows:
                    return pa.Table.from_arrays([q.column("_row"), column(np.zeros((0, words) if wide else 0, np.int64))], names=["_row", "_vid"])
                h1, h2 = (q.column(k).combine_chunks().to_numpy(zero_copy_only=False).copy() for k in ("_h1", "_h2"))
                blob = s.column("parts")[0].as_py() if s.num_rows else None
                out = decode(h1, h2, matrix(q.column("_x")), key[0].as_py(), blob)
                return pa.Table.from_arrays([q.column("_row"), column(out)], names=["_row", "_vid"])

            found = rows.groupBy("_shard").cogroup(structure.select(F.col("shard").alias("_shard"), "parts").groupBy("_shard")).applyInArrow(join, out_type)
        if self.kind == "bits":
            return found.select("_row.*", F.col("_vid").alias(as_))
        if len(self.values) > MOST_VALUES:  # too many for an expression
            schema = T.StructType([T.StructField("_n", T.LongType()), T.StructField("_v", self.value_type)])
            names = spark.createDataFrame([(i, v) for i, (v, _) in enumerate(self.values)], schema)
            return found.join(F.broadcast(names), F.col("_vid") == F.col("_n"), "left").select("_row.*", F.col("_v").alias(as_))
        names = F.array(*[F.lit(v).cast(self.value_type) for v, _ in self.values])
        return found.select("_row.*", F.get(names, F.col("_vid").cast("int")).alias(as_))

    # -- measures
    def model_bits(self) -> int:
        return self.model.size_bits() if self.model else 0

    def space(self, spark: SparkSession) -> dict:
        """Stored bits by part, demand, and bits per key of all that is stored: structure, model and dictionary."""
        r = self.structure(spark).agg(*[F.sum(s).alias(s) for s in STATS], F.sum(F.length("parts")).alias("bytes")).head()
        out = {s: int(r[s] or 0) for s in STATS}
        out["structure"] = 8 * int(r["bytes"] or 0)
        out["header"] = out["structure"] - out["words"] - out["bumps"]
        out["model"] = self.model_bits()
        out["dictionary"] = sum(8 * len(str(v).encode()) + 8 for v, _ in self.values)
        out["bits"] = out["structure"] + out["model"] + out["dictionary"]
        out["bits_per_key"] = out["bits"] / max(1, self.n)
        return out


def scratch_path(spark: SparkSession) -> str:
    """A fresh folder below the shared checkpoint folder, or below a local one where none is set."""
    import tempfile
    import uuid

    base = spark.sparkContext.getCheckpointDir() or spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        base = tempfile.mkdtemp(prefix="predmap-")
        spark.sparkContext.setCheckpointDir(base)
    return f"{base.rstrip('/')}/map-{uuid.uuid4().hex}"


def _solved(rows: DataFrame, solver, path: str | None, shards: int, decode=None) -> str:
    """Groups rows by _shard, solves each and writes the structure. A shard is a task of its own: hashed to partitions, several would
    fall to one task while others had none. decode: with it, the task then looks up all its keys and raises if one has another value."""

    def run(key, part):
        h1, h2, vid = (part.column(k).combine_chunks().to_numpy(zero_copy_only=False).astype(np.int64) for k in ("_h1", "_h2", "_vid"))
        use, clash = sh.unique_keys(h1, h2, vid)
        parts, stats = solver(h1, h2, vid, use, part)
        if len(clash):
            old = np.frombuffer(parts["exceptions"], "<i8", offset=8).reshape(3, -1)
            both = [np.concatenate([o, x[clash]]) for o, x in zip(old, (h1, h2, vid), strict=True)]
            parts["exceptions"] = sh.pack_exceptions(*both)
            stats["odd"] += len(clash)
        row = [key[0].as_py(), len(use) + len(clash), sh.pack_parts(parts), *[stats[s] for s in STATS]]
        for i in range(0, len(vid) if decode else 0, CHECK_ROWS):
            at = slice(i, i + CHECK_ROWS)
            x = matrix(part.column("_x").slice(i, CHECK_ROWS)) if "_x" in part.column_names else np.zeros((len(vid[at]), 0))
            if (decode(h1[at], h2[at], x, row[0], row[2]) != vid[at]).any():
                raise ValueError("a key has another value than it was built with")
        return pa.Table.from_arrays([pa.array([x], f.type) for x, f in zip(row, STRUCTURE_ARROW, strict=True)], schema=STRUCTURE_ARROW)

    path = path or scratch_path(rows.sparkSession)
    rows.repartitionById(min(shards, MOST_TASKS), F.col("_shard")).groupBy("_shard").applyInArrow(run, STRUCTURE).write.mode("overwrite").parquet(path)
    return path


def _keyed(df: DataFrame, keys: list[str], cfg: MapConfig, n: int) -> tuple[DataFrame, int]:
    count = max(1, -(-n // cfg.shard_keys))
    h1, h2 = key_hashes(df, keys, cfg.seed)
    return df.withColumn("_h1", h1).withColumn("_h2", h2).withColumn("_shard", shard_of(F.col("_h1"), count)), count


def build_guided(df: DataFrame, key, value: str, features=None, model: Model | None = None, cfg: MapConfig | None = None, path: str | None = None, fit_rows: int = FIT_ROWS, check: bool = False) -> StaticMap:
    """Model-guided map: only what corrects the model's prediction is stored. Without a model it is the entropy map. check: look up every
    key where it is built in, too."""
    cfg, model, keys = cfg or MapConfig(), model or Constant(), as_list(key)
    values = dictionary(df, value, MOST_SHARED if isinstance(model, Constant) else MOST_VALUES)
    n = sum(c for _, c in values)
    rows, count = _keyed(with_vid(df, value, values), keys, cfg, n)
    rows = rows.select("_shard", "_h1", "_h2", "_vid", feature_column(features).alias("_x"))
    if n:
        model = fit_model(rows, model, values, fit_rows)
    kept = rows.columns if check else rows.columns[:4]

    def paths(batches):
        for b in batches:
            vid = b.column(3).to_numpy(zero_copy_only=False).astype(np.int64)
            h1 = b.column(1).to_numpy(zero_copy_only=False)
            count, body = codes.decisions(code_weights(model, matrix(b.column(4)), cfg.prob_bits), vid, cfg, sh.coins(h1.view(np.uint64)))
            offsets = pa.py_buffer(np.concatenate([[0], np.cumsum(count)]).astype(np.int32))
            path = pa.Array.from_buffers(pa.binary(), b.num_rows, [None, offsets, pa.py_buffer(body)])
            yield pa.RecordBatch.from_arrays([*b.columns[: len(kept)], path], names=[*kept, "_path"])

    def solver(h1, h2, vid, use, part):
        column = part.column("_path").take(pa.array(use)).combine_chunks()
        _, offsets, body = column.buffers()
        ends = np.frombuffer(offsets, np.int32, len(use) + 1, 4 * column.offset).astype(np.int64)
        return sh.solve_guided(h1[use], h2[use], vid[use], np.diff(ends), np.frombuffer(body or b"", np.uint8)[ends[0] : ends[-1]], cfg)

    decided = rows.mapInArrow(paths, "_shard int, _h1 long, _h2 long, _vid int, " + ("_x array<double>, " if check else "") + "_path binary")
    built = StaticMap("guided", cfg, keys, features, values, df.schema[value].dataType, model, n, count, "", {})
    return replace(built, path=_solved(decided, solver, path, count, built._decoder() if check else None))


def _one_code(cfg: MapConfig | None) -> MapConfig:
    cfg = cfg or MapConfig()
    return replace(cfg, coder="huffman" if cfg.coder == "shannon" else cfg.coder)


def build_entropy(df: DataFrame, key, value: str, cfg: MapConfig | None = None, path: str | None = None, check: bool = False) -> StaticMap:
    """Entropy map: one global Huffman code, the filter trick at all nodes, the root or none, as cfg.filter says."""
    return build_guided(df, key, value, None, Constant(), _one_code(cfg), path, check=check)


def entropy_plan(values: list[tuple], cfg: MapConfig | None = None) -> tuple:
    """What decides on the bits of the entropy map of a column with this dictionary: all of cfg but the rule for filters, and every
    value's decisions. Maps of the same keys with equal plans are equal."""
    cfg = _one_code(cfg)
    if cfg.r_mode != "integer":  # a key's decisions are not its value's
        return (cfg,)
    model = Constant(np.array([n for _, n in values], np.int64))
    count, path = codes.decisions(code_weights(model, np.zeros((len(values), 0)), cfg.prob_bits), np.arange(len(values)), cfg, np.zeros(len(values), np.int64))
    return replace(cfg, filter="all"), count.tobytes(), path.tobytes()


def build_fixed(df: DataFrame, key, value: str, cfg: MapConfig | None = None, path: str | None = None, check: bool = False) -> StaticMap:
    """Fixed-width ribbon map: the value's number in ceil(log2 |V|) bits, one elimination for all of them."""
    cfg, keys, values = cfg or MapConfig(), as_list(key), dictionary(df, value, MOST_SHARED)
    n, bits = sum(c for _, c in values), max(0, len(values) - 1).bit_length()
    rows, count = _keyed(with_vid(df, value, values), keys, cfg, n)
    built = StaticMap("fixed", cfg, keys, None, values, df.schema[value].dataType, None, n, count, "", {"bits": bits})
    solver = lambda h1, h2, vid, use, part: _with_exceptions(sh.solve_fixed(h1[use], vid[use], bits, cfg))
    return replace(built, path=_solved(rows.select("_shard", "_h1", "_h2", "_vid"), solver, path, count, built._decoder() if check else None))


def _with_exceptions(solved):
    solved[0].setdefault("exceptions", sh.pack_exceptions(*[np.zeros(0, np.int64)] * 3))
    return solved


def build_sparse(df: DataFrame, key, value: str, cfg: MapConfig | None = None, path: str | None = None, check: bool = False) -> StaticMap:
    """External entropy map: Huffman-coded values in sparse random systems, without filters."""
    cfg, keys, values = cfg or MapConfig(), as_list(key), dictionary(df, value, MOST_SHARED)
    n = sum(c for _, c in values)
    lengths = np.array(codes.huffman_row([c for _, c in values]), np.int64)
    words = sh.canonical_words(lengths)
    rows, count = _keyed(with_vid(df, value, values), keys, cfg, n)
    built = StaticMap("sparse", cfg, keys, None, values, df.schema[value].dataType, None, n, count, "", {"lengths": lengths, "words": words})
    solver = lambda h1, h2, vid, use, part: _with_exceptions(sh.solve_sparse(h1[use], vid[use], lengths, words, cfg))
    return replace(built, path=_solved(rows.select("_shard", "_h1", "_h2", "_vid"), solver, path, count, built._decoder() if check else None))


def build_bits(df: DataFrame, key, bits: str, length: str, cfg: MapConfig | None = None, path: str | None = None) -> StaticMap:
    """Bit-string map: the low ``length`` bits of ``bits``, first bit lowest, a long or, for strings of any length, an array of longs
    with the first 64 bits first. Queries give a window of the longest length, of the same type; the caller knows where its string
    ends, as prefix codes do."""
    cfg, keys = cfg or MapConfig(), as_list(key)
    n, longest = df.agg(F.count(F.lit(1)), F.coalesce(F.max(length), F.lit(0))).head()
    wide = isinstance(df.schema[bits].dataType, T.ArrayType)
    if longest > 64 and not wide:
        raise ValueError("strings over 64 bits are arrays of longs")
    words = max(1, -(-longest // 64))
    rows, count = _keyed(df, keys, cfg, n)
    held = F.transform(F.sequence(F.lit(0), F.lit(words - 1)), lambda k: F.coalesce(F.get(F.col(bits), k), F.lit(0)).cast("long")) if wide else F.array(F.col(bits).cast("long"))
    rows = rows.select("_shard", "_h1", "_h2", F.xxhash64(held, F.col(length)).alias("_vid"), held.alias("_bits"), F.col(length).cast("long").alias("_len"))

    def solver(h1, h2, vid, use, part):
        size = part.column("_len").combine_chunks().to_numpy(zero_copy_only=False)
        return _with_exceptions(sh.solve_bits(h1[use], matrix(part.column("_bits")).reshape(-1, words)[use], size[use], cfg))

    return StaticMap("bits", cfg, keys, None, [], T.ArrayType(T.LongType()) if wide else T.LongType(), None, n, count, _solved(rows, solver, path, count), {"longest": int(longest)})


def build_membership(df: DataFrame, key, member: str, share, cfg: MapConfig | None = None, path: str | None = None) -> StaticMap:
    """Weighted membership: whether a key of the universe df is in the set (column member), given its believed share of being so
    (column name or number). A filter on the set and a correction bit for whatever passes it: one decision of a guided map."""
    order = [bool(v) for v, _ in dictionary(df, member)]
    model = Believed(order=order) if isinstance(share, str) else Believed(order=order, share=float(share))
    return build_guided(df, key, member, [share] if isinstance(share, str) else None, model, cfg, path)


def compress_columns(df: DataFrame, key, columns: Sequence[str], features=None, model=None, cfg: MapConfig | None = None) -> list[StaticMap]:
    """A map per column, each given the columns before it as one-hot features (and any other features)."""
    out, hot = [], [] if features is None else [feature_column(features)]
    for c in columns:
        x = F.concat(*hot) if hot else None
        out.append(build_guided(df, key, c, x, model(bool(hot)) if model else None, cfg))
        values = [v for v, _ in out[-1].values]
        hot = [*hot, F.array(*[F.when(F.col(c).eqNullSafe(F.lit(v)), 1.0).otherwise(0.0) for v in values])]
    return out


def attach_columns(df: DataFrame, maps: Sequence[StaticMap], names: Sequence[str]) -> DataFrame:
    for m, name in zip(maps, names, strict=True):
        df = m.attach(df, name)
    return df


def mismatches(df: DataFrame, built: StaticMap, value: str) -> DataFrame:
    """Rows of df whose value the map does not give back: none, for the rows it was built from."""
    return built.attach(df, "_got").filter(~F.col("_got").eqNullSafe(F.col(value)))

