"""Models with exact, order-independent inference.

A model gives log2 scores; these are rounded to 2^-16 and turned into integer weights by a table, so a key gets the same weights
whatever batch it arrives in. Sums over features run feature by feature with elementwise operations: no matrix product, whose
order of additions could depend on the shape of a batch, is used for anything that a stored code depends on.
"""

from __future__ import annotations

import base64
import json
import math
from collections.abc import Callable
from dataclasses import dataclass, field, fields

import numpy as np

STEPS = 4096
#: 2^-(k / STEPS) on a 30-bit grid, for the fraction of a score.
POWERS = np.array([round(2.0 ** (30 - k / STEPS)) for k in range(STEPS)], np.int64)


def weights_of(score: np.ndarray, bits: int = 24) -> np.ndarray:
    """n x V log2 scores to integer weights >= 1, the best near 2^bits."""
    fixed = np.rint(np.clip(score, -1e6, 1e6) * 65536).astype(np.int64)
    drop = fixed.max(1, keepdims=True) - fixed
    whole, part = drop >> 16, (drop & 65535) * STEPS >> 16
    shift = np.minimum(30 - bits + whole, 62)
    return np.maximum(1, POWERS[part] >> shift)


def affine(x: np.ndarray, w: np.ndarray, b: np.ndarray) -> np.ndarray:
    """x @ w + b, added up feature by feature."""
    out = np.broadcast_to(b.astype(np.float64), (len(x), len(b))).copy()
    for j in range(x.shape[1]):
        out += x[:, j : j + 1] * w[j].astype(np.float64)
    return out


class Model:
    """fit() gets a matrix of features and value numbers; scores() gives log2 scores; tensors are what the model's size counts."""

    kind = "model"
    shared = False  # a model that exists anyway costs nothing

    def fit(self, x: np.ndarray, y: np.ndarray, classes: int) -> Model:
        raise NotImplementedError

    def scores(self, x: np.ndarray) -> np.ndarray:
        raise NotImplementedError

    def tensors(self) -> list[np.ndarray]:
        return []

    def set_tensors(self, tensors: list[np.ndarray]) -> None:
        pass

    def extras(self) -> int:
        """Bits that scoring needs besides the tensors."""
        return 0

    def size_bits(self) -> int:
        return 0 if self.shared else sum(8 * t.dtype.itemsize * t.size for t in self.tensors()) + self.extras()

    def params(self) -> int:
        return sum(t.size for t in self.tensors())


def predict_weights(model: Model, x: np.ndarray, bits: int = 24) -> np.ndarray:
    return weights_of(model.scores(x), bits)


def code_weights(model: Model, x: np.ndarray, bits: int = 24) -> np.ndarray:
    """predict_weights for codes, which take one row where all keys have the same."""
    return predict_weights(model, x[:1] if isinstance(model, Constant) else x, bits)


@dataclass
class Constant(Model):
    """The frequencies of the values, whatever the key: a guided map with it is an entropy map. Its weights are the counts."""

    counts: np.ndarray | None = None
    kind = "constant"

    def fit(self, x, y, classes):
        self.counts = np.maximum(1, np.bincount(y, minlength=classes)) if self.counts is None else self.counts
        return self

    def scores(self, x):
        c = np.asarray(self.counts, np.float64)
        return np.broadcast_to(np.log2(c / c.sum()), (len(x), len(c)))

    def size_bits(self):
        return 32 * len(self.counts)


@dataclass
class BucketTable(Model):
    """Value frequencies per bucket of the first features, each taken as a whole number."""

    columns: int = 1
    table: dict = field(default_factory=dict)
    base: np.ndarray | None = None
    kind = "bucket"

    def _keys(self, x):
        return np.rint(x[:, : self.columns]).astype(np.int64)

    def fit(self, x, y, classes):
        keys, which = np.unique(self._keys(x), axis=0, return_inverse=True)
        counts = np.zeros((len(keys), classes), np.int64)
        np.add.at(counts, (which.ravel(), y), 1)
        self.base = np.maximum(1, counts.sum(0))
        self.table = {tuple(k): np.minimum(c, 65535).astype(np.uint16) for k, c in zip(keys.tolist(), counts, strict=True)}
        return self

    def scores(self, x):
        keys, which = np.unique(self._keys(x), axis=0, return_inverse=True)
        rows = [np.log2(np.maximum(self.table.get(tuple(k), self.base).astype(np.float64), 1 / 64)) for k in keys.tolist()]
        return np.array(rows).reshape(len(keys), len(self.base))[which.ravel()]

    def tensors(self):
        return [np.concatenate([*self.table.values(), np.array(list(self.table), np.int16).ravel()])] if self.table else []

    def extras(self):
        return 32 * len(self.base) if self.base is not None else 0


@dataclass
class GaussianNB(Model):
    """Mean and variance of each feature per value; priors are the frequencies unless uniform."""

    dtype: str = "float16"
    mean: np.ndarray | None = None
    var: np.ndarray | None = None
    prior: np.ndarray | None = None
    kind = "gaussian"

    def fit(self, x, y, classes):
        n = np.maximum(np.bincount(y, minlength=classes), 1)
        onehot = (y[:, None] == np.arange(classes)).astype(np.float64)
        mean = onehot.T @ x / n[:, None]
        var = np.maximum(onehot.T @ (x * x) / n[:, None] - mean * mean, 1e-6)
        return self.from_moments(n, mean, var)

    def from_moments(self, n, mean, var):
        """From per-value counts, means and variances, as one aggregation gives them."""
        cast = np.dtype(self.dtype)
        self.mean, self.var = np.asarray(mean).astype(cast), np.maximum(np.asarray(var), 6e-5 if self.dtype == "float16" else 1e-12).astype(cast)
        self.prior = (np.asarray(n, np.float64) / np.sum(n)).astype(np.float32)
        return self

    def scores(self, x):
        mean, var = self.mean.astype(np.float64), self.var.astype(np.float64)
        out = np.broadcast_to(np.log2(self.prior.astype(np.float64)), (len(x), len(self.prior))).copy()
        for j in range(x.shape[1]):
            d = x[:, j : j + 1] - mean[:, j]
            out -= (d * d / (2 * var[:, j])) * math.log2(math.e) + 0.5 * np.log2(2 * math.pi * var[:, j])
        return out

    def tensors(self):
        return [self.mean, self.var]

    def extras(self):
        return 32 * len(self.prior)


@dataclass
class Trained(Model):
    """Common part of models trained by gradients: minibatch Adam on the surprisal, early stop on validation or training loss."""

    dtype: str = "float16"
    early_stop_on: str = "validation"
    least_gain: float = 0.01
    patience: int = 3
    most_epochs: int = 60
    batch: int = 256
    rate: float = 0.01
    seed: int = 1
    scale: np.ndarray | None = None
    layers: list = field(default_factory=list)

    def shapes(self, features: int, classes: int) -> list[int]:
        raise NotImplementedError

    def forward(self, x):
        acts = [x]
        for k, (w, b) in enumerate(self.layers):
            x = x @ w + b
            if k + 1 < len(self.layers):
                x = np.maximum(x, 0)
            acts.append(x)
        return acts

    def loss_bits(self, x, y) -> float:
        z = self.forward(x)[-1]
        z = z - z.max(1, keepdims=True)
        return float(np.mean(np.log2(np.exp(z).sum(1)) - z[np.arange(len(y)), y] * math.log2(math.e))) if len(y) else 0.0

    def fit(self, x, y, classes):
        rng = np.random.default_rng(self.seed)
        mean, std = x.mean(0), x.std(0)
        std[std == 0] = 1
        self.scale = np.stack([mean, std]).astype(np.float32)
        mean, std = self.scale.astype(np.float64)
        x = (x - mean) / std
        order = rng.permutation(len(x))
        cut = max(1, len(x) // 10)
        held, train = (order[:cut], order[cut:]) if len(x) > 20 else (order, order)
        dims = self.shapes(x.shape[1], classes)
        self.layers = [[rng.normal(0, math.sqrt(2 / a), (a, b)), np.zeros(b)] for a, b in zip(dims, dims[1:])]
        state = [[(np.zeros_like(t), np.zeros_like(t)) for t in layer] for layer in self.layers]
        best, stale, steps, kept = math.inf, 0, 0, None
        for _ in range(self.most_epochs):
            for at in range(0, len(train), self.batch):
                rows = rng.permutation(train)[: self.batch] if len(train) <= self.batch else train[rng.integers(0, len(train), self.batch)]
                acts = self.forward(x[rows])
                z = acts[-1] - acts[-1].max(1, keepdims=True)
                g = np.exp(z)
                g /= g.sum(1, keepdims=True)
                g[np.arange(len(rows)), y[rows]] -= 1
                g /= len(rows)
                steps += 1
                for k in range(len(self.layers) - 1, -1, -1):
                    grads = acts[k].T @ g, g.sum(0)
                    g = (g @ self.layers[k][0].T) * (acts[k] > 0) if k else g
                    for t in (0, 1):
                        m, v = state[k][t]
                        m += 0.1 * (grads[t] - m)
                        v += 0.001 * (grads[t] ** 2 - v)
                        self.layers[k][t] = self.layers[k][t] - self.rate * (m / (1 - 0.9**steps)) / (np.sqrt(v / (1 - 0.999**steps)) + 1e-8)
            rows = held if self.early_stop_on == "validation" else train
            now = self.loss_bits(x[rows], y[rows])
            if now < best * (1 - self.least_gain):
                stale = 0
            else:
                stale += 1
            if now < best:
                best, kept = now, [[t.copy() for t in layer] for layer in self.layers]
            if stale >= self.patience:
                break
        self.layers = [[quantise(t, self.dtype) for t in layer] for layer in self.final(kept or self.layers)]
        return self

    def final(self, layers: list) -> list:
        """What of the trained layers is kept."""
        return layers

    def extras(self):
        steps = sum(isinstance(t, tuple) for layer in self.layers for t in layer)
        return 32 * (self.scale.size + steps)

    def scores(self, x):
        scale = self.scale.astype(np.float64)
        z = (np.asarray(x, np.float64) - scale[0]) / scale[1]
        for k, (w, b) in enumerate(self.layers):
            z = affine(z, restore(w), restore(b))
            if k + 1 < len(self.layers):
                z = np.maximum(z, 0)
        return z * math.log2(math.e)

    def tensors(self):
        return [t if isinstance(t, np.ndarray) else t[0] for layer in self.layers for t in layer]


def quantise(t: np.ndarray, dtype: str):
    """float32, float16, or int8 with a scale of its own."""
    if dtype == "int8":
        step = float(np.abs(t).max() / 127) or 1.0
        return np.rint(t / step).astype(np.int8), step
    return t.astype(dtype)


def restore(t) -> np.ndarray:
    return t[0].astype(np.float64) * t[1] if isinstance(t, tuple) else t.astype(np.float64)


@dataclass
class Logistic(Trained):
    """Softmax regression; two values need one column of weights only."""

    kind = "logistic"

    def shapes(self, features, classes):
        return [features, classes]

    def final(self, layers):
        (w, b), = layers
        return [[w[:, 1:] - w[:, :1], b[1:] - b[:1]]] if b.size == 2 else layers

    def scores(self, x):
        z = super().scores(x)
        return np.concatenate([np.zeros((len(z), 1)), z], 1) if z.shape[1] == 1 else z


@dataclass
class Believed(Model):
    """Two values, or one: share, or feature 0, is the believed share of the true one; order tells which value is true."""

    order: list = field(default_factory=list)
    share: float | None = None
    kind = "believed"

    def fit(self, x, y, classes):
        return self

    def scores(self, x):
        q = np.clip(x[:, 0] if self.share is None else np.full(len(x), self.share), 1e-6, 1 - 1e-6)
        return np.log2(np.stack([q if v else 1 - q for v in self.order], 1))


@dataclass
class Custom(Model):
    """A model that is there anyway: fn(x) -> probabilities, n x V; size as declared, 0 if shared."""

    fn: Callable | None = None
    bits: int = 0
    kind = "custom"

    def fit(self, x, y, classes):
        return self

    def scores(self, x):
        return np.log2(np.maximum(self.fn(x), 1e-12))

    def size_bits(self):
        return self.bits


@dataclass
class Point(Model):
    """A weak predictor: feature 0 is its guess (a value number), which is right with a given confidence; the rest by frequency."""

    confidence: float = 0.9
    freq: np.ndarray | None = None
    kind = "point"

    def fit(self, x, y, classes):
        self.freq = np.maximum(np.bincount(y, minlength=classes), 0.5) / max(1, len(y))
        return self

    def scores(self, x):
        guess = np.clip(np.rint(x[:, 0]).astype(np.int64), 0, len(self.freq) - 1)
        p = np.broadcast_to(self.freq, (len(x), len(self.freq))).copy()
        p[np.arange(len(x)), guess] = 0
        p *= (1 - self.confidence) / np.maximum(p.sum(1, keepdims=True), 1e-12)
        p[np.arange(len(x)), guess] = self.confidence
        return np.log2(np.maximum(p, 1e-12))

    def size_bits(self):
        return 32 * (1 + len(self.freq))


def _plain(x):
    """A field as JSON: arrays by type, shape and bytes."""
    if isinstance(x, np.ndarray):
        return {"dtype": x.dtype.str, "shape": x.shape, "data": base64.b64encode(np.ascontiguousarray(x).tobytes()).decode()}
    if isinstance(x, tuple):
        return {"tuple": [_plain(v) for v in x]}
    if isinstance(x, dict):
        return {"dict": [[_plain(k), _plain(v)] for k, v in x.items()]}
    return [_plain(v) for v in x] if isinstance(x, list) else x


def _back(x):
    if isinstance(x, list):
        return [_back(v) for v in x]
    if not isinstance(x, dict):
        return x
    if "dtype" in x:
        return np.frombuffer(base64.b64decode(x["data"]), x["dtype"]).reshape(x["shape"])
    return tuple(_back(v) for v in x["tuple"]) if "tuple" in x else {_back(k): _back(v) for k, v in x["dict"]}


def _kinds(base=Model) -> dict:
    return {k: v for c in base.__subclasses__() for k, v in ({c.kind: c} | _kinds(c)).items()}


def to_json(model: Model) -> str | None:
    """A model as text; None for a user's function, which is code."""
    if isinstance(model, Custom):
        return None
    return json.dumps({"kind": model.kind, "shared": model.shared, "fields": {f.name: _plain(getattr(model, f.name)) for f in fields(model)}})


def from_json(text: str) -> Model:
    from predmap.models import mlp  # noqa: F401  its kind must be known

    held = json.loads(text)
    out = _kinds()[held["kind"]](**{k: _back(v) for k, v in held["fields"].items()})
    out.shared = held["shared"]
    return out
