"""Language ID: averaged hashed subword embeddings with a linear softmax, trained by stochastic gradient descent in numpy.

A text is lower-cased, what is not a letter becomes a space, and its subwords are all strings of 3 and of 4 bytes, word borders
included. Each is hashed to one of ``buckets`` embeddings; a text is the mean of its embeddings and a linear softmax reads it.
As both are linear, prediction sums a buckets x languages table: one pass, no shuffle, whole texts.

The model is fitted on at most ``sample_rows`` labelled rows (the documented bound), chosen by hash. A fifth of them is set aside
to fit a temperature, so scores are probabilities, and the rejection threshold: the largest, up to one half, that turns away at
most one in a thousand of the rightly labelled ones.

Defined results: a null text, or one without letters, is ``und`` with score 0; ties between languages go to the first by name; with no
labelled row every text is ``und``; very long texts are read in slices; repeated rows are predicted each; an empty table gives no
rows; other columns are not read, and ``lang`` only by training.
"""

from __future__ import annotations

import pickle
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from predmap.llm.common import batch_of, small, table

NAME = "op5_language_id"
SQL = None  # tests hold it against held-out labels
BUCKETS, DIM, SIZES, EPOCHS, RATE, SAMPLE_ROWS = 1 << 17, 16, (3, 4), 6, 4.0, 4000
SLICE = 1 << 20
#: ASCII that is no letter to a space; other bytes stay.
LETTERS = bytes(c if 65 <= c <= 90 or 97 <= c <= 122 or c >= 128 else 32 for c in range(256))
MIXERS = {3: np.uint32(2654435761), 4: np.uint32(2246822519)}


def has_letter(text: str) -> bool:
    """Digits and fractions are no letters, whatever their script."""
    return any(map(str.isalpha, text))


def subwords(buf: np.ndarray, n: int, buckets: int = BUCKETS) -> np.ndarray:
    """Bucket of the n bytes from every place."""
    m = len(buf) - n + 1
    if m <= 0:
        return np.zeros(0, np.uint32)
    g = np.zeros(m, np.uint32)
    for k in range(n):
        g |= buf[k : k + m].astype(np.uint32) << np.uint32(8 * k)
    g *= MIXERS[n]
    return g >> np.uint32(32 - (buckets.bit_length() - 1))


def spelled(text: str) -> bytes:
    """Lower-case letters between single spaces."""
    return b" " + b" ".join(text.lower().encode("utf-8", "replace").translate(LETTERS).split()) + b" "


@dataclass
class Model:
    langs: list[str]
    table: np.ndarray  # buckets x languages: what a subword adds to the logits
    bias: np.ndarray
    temperature: float
    threshold: float

    def logits(self, data: list[bytes]) -> np.ndarray:
        """Logits of spelled texts; several are read at once, and a long one in slices."""
        out = np.zeros((len(data), len(self.langs)), np.float64)
        i = 0
        while i < len(data):
            if len(data[i]) > SLICE:
                out[i] = self._long(data[i])
                i += 1
                continue
            j, held = i, 0
            while j < len(data) and held + len(data[j]) <= SLICE:
                held += len(data[j])
                j += 1
            out[i:j] = self._block(data[i:j])
            i = j
        return out / self.temperature

    def _block(self, data: list[bytes]) -> np.ndarray:
        buf = np.frombuffer(b"".join(data) + b"    ", np.uint8)
        size = np.array([len(x) for x in data])
        start = np.cumsum(size) - size
        total, seen = np.zeros((len(data), len(self.langs))), np.zeros(len(data))
        for n in SIZES:
            count = np.maximum(size - n + 1, 0)
            marks = np.stack([start, start + count], 1).ravel()
            g = subwords(buf, n)
            for c in range(len(self.langs)):
                total[:, c] += np.where(count > 0, np.add.reduceat(self.table[:, c][g].astype(np.float64), marks)[::2], 0)
            seen += count
        return total / np.maximum(seen, 1)[:, None] + self.bias

    def _long(self, data: bytes) -> np.ndarray:
        buf, total, seen = np.frombuffer(data, np.uint8), np.zeros(len(self.langs)), 0
        for n in SIZES:
            for at in range(0, len(buf) - n + 1, SLICE):
                g = subwords(buf[at : at + SLICE + n - 1], n)
                total += self.table[g].sum(0, dtype=np.float64)
                seen += len(g)
        return total / max(seen, 1) + self.bias

    def predict(self, texts: list[str | None]) -> tuple[list[str], np.ndarray, list[bool]]:
        """Language, calibrated score and whether it is rejected."""
        known = [bool(x) and has_letter(x) and bool(self.langs) for x in texts]
        some = [i for i, k in enumerate(known) if k]
        lang, score = ["und"] * len(texts), np.zeros(len(texts))
        if some:
            p = softmax(self.logits([spelled(texts[i]) for i in some]))
            best = p.argmax(1)
            score[some] = p[np.arange(len(some)), best]
            for i, k in zip(some, best.tolist(), strict=True):
                lang[i] = self.langs[k]
        return lang, score, [not k or s < self.threshold for k, s in zip(known, score.tolist(), strict=True)]


def softmax(x: np.ndarray) -> np.ndarray:
    e = np.exp(x - x.max(-1, keepdims=True))
    return e / e.sum(-1, keepdims=True)


def fit(rows: list[tuple[str, str]], seed: int = 7) -> Model:
    """A model of (text, language) rows."""
    rows = [(t, y) for t, y in rows if t and has_letter(t)]
    langs = sorted({y for _, y in rows})
    if not langs:
        return Model([], np.zeros((BUCKETS, 1)), np.zeros(1), 1.0, 0.0)
    rng = np.random.default_rng(seed)
    bags = []
    for text, y in rows:
        buf = np.frombuffer(spelled(text), np.uint8)
        u, c = np.unique(np.concatenate([subwords(buf, n) for n in SIZES]), return_counts=True)
        bags.append((u, (c / c.sum()).astype(np.float32), langs.index(y)))
    order = rng.permutation(len(bags))
    held, train = order[: len(bags) // 5], order[len(bags) // 5 :]
    emb = rng.uniform(-1 / DIM, 1 / DIM, (BUCKETS, DIM)).astype(np.float32)
    out, bias = np.zeros((len(langs), DIM), np.float32), np.zeros(len(langs), np.float32)
    epochs = max(EPOCHS, -(-6000 // max(1, len(train))))
    for epoch in range(epochs):
        rate = RATE * (1 - epoch / epochs)
        for i in rng.permutation(train):
            u, w, y = bags[i]
            x = w @ emb[u]
            g = softmax(out @ x + bias)
            g[y] -= 1
            back = g @ out
            out -= rate * np.outer(g, x)
            bias -= 0.01 * rate * g
            emb[u] -= rate * np.outer(w, back)
    model = Model(langs, np.ascontiguousarray(emb @ out.T), bias.astype(np.float64), 1.0, 0.0)
    if len(held):
        z = np.stack([(w[:, None] * model.table[u]).sum(0) for u, w, _ in (bags[i] for i in held)]) + bias
        y = np.array([bags[i][2] for i in held])
        grid = np.exp(np.linspace(np.log(0.1), np.log(10), 61))
        model.temperature = float(min(grid, key=lambda t: -np.log(softmax(z / t)[np.arange(len(y)), y] + 1e-12).mean()))
        p = softmax(z / model.temperature)
        right = p.max(1)[p.argmax(1) == y]
        model.threshold = float(min(0.5, np.quantile(right, 0.001))) if len(right) else 0.0
    return model


def held_out(doc_id):
    """crc32 of the id as text, mod 5, is 0."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0, F.lit(False))


def train(docs: DataFrame, sample_rows: int = SAMPLE_ROWS, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> Model:
    """Fits on at most sample_rows labelled rows that are not held out."""
    place = F.pmod(F.xxhash64(docs[id_col]), F.lit(1 << 30))
    rows = docs.filter(~held_out(docs[id_col]) & docs[lang_col].isNotNull() & docs[text_col].isNotNull())
    n = rows.count()
    if n > 4 * sample_rows:  # twice what is wanted: fewer rows are sorted, and the least by hash stay the same
        rows = rows.filter(place < F.lit(int((1 << 30) * 2.0 * sample_rows / n)))
    rows = rows.select(docs[text_col].alias("t"), docs[lang_col].alias("y"), place.alias("p"), docs[id_col].alias("i")).orderBy("p", "i").limit(sample_rows)

    def run(batches):
        yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(fit([(t, y) for b in batches for t, y in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True)]))])], names=["model"])

    # the bounded sample is one partition: it is fitted where it is, and only the model comes to the driver
    return pickle.loads(bytes(rows.select("t", "y").coalesce(1).mapInArrow(run, "model binary").head()["model"]))


def identify(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, held_out, lang_pred, score, rejected."""
    given = docs.sparkSession.sparkContext.broadcast(model)
    schema = pa.schema([("doc_id", pa.int64()), ("held_out", pa.bool_()), ("lang_pred", pa.string()), ("score", pa.float64()), ("rejected", pa.bool_())])

    def run(batches):
        for b in small(batches):
            lang, score, rejected = given.value.predict(b.column("text").to_pylist())
            yield batch_of(schema, b.column("doc_id"), b.column("held_out"), lang, score, rejected)

    rows = docs.select(docs[id_col].cast("long").alias("doc_id"), held_out(docs[id_col]).alias("held_out"), docs[text_col].alias("text"))
    return rows.mapInArrow(run, "doc_id long, held_out boolean, lang_pred string, score double, rejected boolean")


def accept(docs: DataFrame, model: Model, text_col: str = "text") -> DataFrame:
    """The rows of docs whose language the model accepts, all columns, in one pass."""
    given = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for b in small(batches):
            rejected = given.value.predict(b.column(b.schema.names.index(text_col)).to_pylist())[2]
            yield b.filter(pa.array([not x for x in rejected]))

    return docs.mapInArrow(run, docs.schema)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return identify(docs, train(docs)).select("doc_id", "held_out", "lang_pred", "score", "rejected")
