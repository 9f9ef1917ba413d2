"""Which model, if any, makes the smallest map: the one with the least surprisal plus its own size."""

from __future__ import annotations

import time
from collections.abc import Sequence
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from predmap.functions import metrics
from predmap.models import Constant, Model
from predmap.operators.maps import FIT_ROWS, dictionary, feature_column, fit_model, with_vid


@dataclass
class Candidate:
    name: str
    model: Model
    features: object
    s_per_key: float
    enc_per_key: float
    top1: float
    top3: float
    ece: float
    fit_us: float
    infer_us: float
    params: int
    n: int

    @property
    def sigma(self) -> float:
        return self.s_per_key + self.enc_per_key


SPLIT = "_split"


def held_out(df: DataFrame, value: str, key: str) -> DataFrame:
    """df with its stratified fifth of test rows and a tenth of the rest for validation marked."""
    return metrics.stratified(df, value, key, as_=SPLIT)


def measure(df: DataFrame, key: str, value: str, name: str, model: Model, features, model_cost: str = "owned", fit_rows: int = FIT_ROWS) -> Candidate:
    """Fits the model on the training part and measures it in one pass: surprisal over all keys, as the map stores all of them; accuracy
    and calibration over the test part, which it has not seen. df has been through ``held_out``, or is."""
    df = df if SPLIT in df.columns else held_out(df, value, key)
    values = dictionary(df, value)
    n = max(1, sum(c for _, c in values))
    rows = with_vid(df, value, values).select("_vid", F.xxhash64(F.col(key)).alias("_h1"), (F.col(SPLIT) == "test").alias("_test"), feature_column(features).alias("_x"))
    a = time.perf_counter()
    model = fit_model(rows.filter("NOT _test"), model, values, fit_rows)
    b = time.perf_counter()
    p = metrics.predictions(rows, model)
    bins = F.least(F.floor(F.col("confidence") * 50), F.lit(49))
    cells = p.groupBy("_test", bins.alias("bin")).agg(F.count(F.lit(1)).alias("n"), F.sum("surprisal").alias("s"), F.sum("hit").alias("hit"), F.sum((F.col("rank") < 3).cast("long")).alias("three"), F.sum("confidence").alias("c")).collect()
    c = time.perf_counter()
    test = [r for r in cells if r["_test"]] or cells
    total = lambda rows, k: sum(r[k] for r in rows)
    seen = max(1, total(test, "n"))
    enc = 0.0 if model_cost == "shared" else model.size_bits() / n
    ece = sum(abs(r["c"] - r["hit"]) for r in test) / seen
    return Candidate(name, model, features, total(cells, "s") / n, enc, total(test, "hit") / seen, total(test, "three") / seen, ece, (b - a) / n * 1e6, (c - b) / n * 1e6, model.params(), n)


def best(df: DataFrame, key: str, value: str, candidates: Sequence[tuple[str, Model, object]], objective: str = "space", model_cost: str = "owned") -> tuple[Candidate, list[Candidate]]:
    """The candidate with the least surprisal plus size (space), or the fastest of those that beat the constant model (latency)."""
    df = held_out(df, value, key)
    found = [measure(df, key, value, name, model, x, model_cost) for name, model, x in [("constant", Constant(), None), *candidates]]
    if objective == "space":
        return min(found, key=lambda c: c.sigma), found
    useful = [c for c in found[1:] if c.sigma < found[0].sigma]
    return min(useful or found[:1], key=lambda c: c.infer_us), found
