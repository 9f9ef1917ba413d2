"""Small document tables that hold the awkward cases."""

import numpy as np
import pyarrow.dataset as ds

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, keep_id string, doc string, low int"
SF = "/root/testdata/sf0.001"


def given(table="documents", sf=SF):
    return ds.dataset(f"{sf}/{table}.parquet").to_table().to_pylist()


def awkward():
    rng = np.random.default_rng(3)
    words = ["alpha", "beta", "gamma", "délta", "Eta", "zeta", "key", "tok", "übung", "x1", "9", "Ω"]
    texts = [None, "", " ", "\t\n", "a", "a b", "A  b", "é", "1", "<|endoftext|> x", "a\x1cb \x85 c d", "x" * 5000, "a" * 300 + "@b.c", "one two three four five six seven eight nine ten eleven"]
    texts += [" ".join(rng.choice(words, n)) for n in (3, 4, 30, 60, 400, 3000)]
    texts += [texts[-1], texts[-2] + " more", texts[-2], None, ""]
    return [(i, t, "en" if i % 2 else None, "s", None, "k", "d", 1) for i, t in enumerate(texts)]


def frame(spark, rows=None):
    return spark.createDataFrame(awkward() if rows is None else rows, SCHEMA)


def empty(spark):
    return spark.createDataFrame([], SCHEMA)
