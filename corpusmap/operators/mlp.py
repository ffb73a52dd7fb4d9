"""The neural language identifier: hashed character trigrams, three ReLU layers with dropout, softmax.

Inputs are at most a few dozen buckets of a window, so the first layer is a
sum of weight rows and only those rows are updated. Training reads balanced
epochs of bounded size (pairs times windows per pair), whatever the corpus.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from corpusmap.functions.text import trigram_buckets


@dataclass
class MLPConfig:
    dims: int = 216_000
    hidden: tuple = (300, 300, 300)
    dropout: float = 0.25
    epochs: int = 3
    per_pair: int = 1000
    rate: float = 1e-3
    batch: int = 128
    seed: int = 1


@dataclass
class MLPModel:
    labels: list[str]
    config: MLPConfig
    weights: list[np.ndarray] = field(default_factory=list)
    biases: list[np.ndarray] = field(default_factory=list)

    def first_layer(self, flat: np.ndarray, starts: np.ndarray, share: np.ndarray) -> np.ndarray:
        return np.add.reduceat(self.weights[0][flat] * share[:, None], starts) + self.biases[0]

    def probabilities(self, flat: np.ndarray, starts: np.ndarray, share: np.ndarray) -> np.ndarray:
        a = np.maximum(self.first_layer(flat, starts, share), 0)
        for w, b in zip(self.weights[1:-1], self.biases[1:-1], strict=True):
            a = np.maximum(a @ w + b, 0)
        z = a @ self.weights[-1] + self.biases[-1]
        e = np.exp(z - z.max(axis=1, keepdims=True))
        return e / e.sum(axis=1, keepdims=True)


def bags(lists: list) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Bucket numbers end to end, first position of each window, frequency of each number (windows are not empty)."""
    sizes = np.array([len(x) for x in lists])
    return np.concatenate([np.asarray(x) for x in lists]).astype(np.int64), np.concatenate(([0], np.cumsum(sizes)[:-1])), np.repeat(1.0 / sizes, sizes).astype(np.float32)


def train_mlp(epoch_of, labels: list[str], cfg: MLPConfig) -> MLPModel:
    """``epoch_of(n)`` gives (lists of buckets, label numbers) of epoch ``n``; Adam, lazy for the rows of the first layer."""
    rng = np.random.default_rng(cfg.seed)
    shape = [cfg.dims, *cfg.hidden, len(labels)]
    m = MLPModel(labels, cfg)
    for i, (a, b) in enumerate(zip(shape, shape[1:], strict=False)):
        m.weights.append(rng.normal(0, 1.0 if i == 0 else np.sqrt(2 / a), (a, b)).astype(np.float32))
        m.biases.append(np.zeros(b, dtype=np.float32))
    state = [[np.zeros_like(x), np.zeros_like(x)] for x in (*m.weights, *m.biases)]
    step = 0

    def adam(x: np.ndarray, g: np.ndarray, s: list, rows=None) -> None:
        one, two = (s[0], s[1]) if rows is None else (s[0][rows], s[1][rows])
        one = 0.9 * one + 0.1 * g
        two = 0.999 * two + 0.001 * g * g
        change = cfg.rate * (one / (1 - 0.9 ** step)) / (np.sqrt(two / (1 - 0.999 ** step)) + 1e-8)
        if rows is None:
            s[0][:], s[1][:] = one, two
            x -= change
        else:
            s[0][rows], s[1][rows] = one, two
            x[rows] -= change

    n = len(shape) - 1
    for epoch in range(cfg.epochs):
        lists, y = epoch_of(epoch)
        order = rng.permutation(len(lists))
        for lo in range(0, len(order), cfg.batch):
            some = order[lo: lo + cfg.batch]
            flat, starts, share = bags([lists[i] for i in some])
            acts, masks = [], []
            z = m.first_layer(flat, starts, share)
            for i in range(1, n + 1):
                mask = ((z > 0) & (rng.random(z.shape) >= cfg.dropout)) / np.float32(1 - cfg.dropout)
                acts.append(z * mask)
                masks.append(mask)
                z = acts[-1] @ m.weights[i] + m.biases[i] if i < n else z
                if i == n - 1:
                    break
            e = np.exp(z - z.max(axis=1, keepdims=True))
            d = e / e.sum(axis=1, keepdims=True)
            d[np.arange(len(some)), y[some]] -= 1
            d /= len(some)
            step += 1
            for i in range(n - 1, 0, -1):
                g_w, g_b = acts[i - 1].T @ d, d.sum(axis=0)
                d = (d @ m.weights[i].T) * masks[i - 1]
                adam(m.weights[i], g_w, state[i])
                adam(m.biases[i], g_b, state[n + i])
            bag = np.repeat(np.arange(len(starts)), np.diff(np.append(starts, len(flat))))
            rows, back = np.unique(flat, return_inverse=True)
            g_rows = np.zeros((len(rows), shape[1]), dtype=np.float32)
            np.add.at(g_rows, back, d[bag] * share[:, None])
            adam(m.weights[0], g_rows, state[0], rows)
            adam(m.biases[0], d.sum(axis=0), state[n])
    return m


def epoch_arrays(epoch: DataFrame, window: str, label: str, labels: list[str], dims: int) -> tuple[list, np.ndarray]:
    """An epoch on the driver: its size is pairs times windows per pair."""
    got = epoch.select(trigram_buckets(F.col(window), dims).alias("x"), label).filter(F.size("x") > 0).toArrow()
    at = {v: i for i, v in enumerate(labels)}
    return got.column("x").to_pylist(), np.array([at[v] for v in got.column(label).to_pylist()])


def predict(samples: DataFrame, model: MLPModel, window: str = "window", min_prob: float | None = None) -> DataFrame:
    """``samples`` plus ``predicted`` and ``prob``; windows without a trigram, or below ``min_prob``, have no label."""
    held = samples.sparkSession.sparkContext.broadcast(model)
    given = samples.columns
    ready = samples.withColumn("_x", trigram_buckets(F.col(window), model.config.dims))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = held.value
        for b in batches:
            x = b.column(len(given)).to_pylist()
            full = [i for i, v in enumerate(x) if v]
            label, prob = [None] * len(x), [None] * len(x)
            for lo in range(0, len(full), 4096):
                some = full[lo: lo + 4096]
                p = m.probabilities(*bags([x[i] for i in some]))
                for i, k, v in zip(some, p.argmax(axis=1).tolist(), p.max(axis=1).tolist(), strict=True):
                    prob[i] = v
                    label[i] = m.labels[k] if min_prob is None or v >= min_prob else None
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array(label, type=pa.string()), pa.array(prob, type=pa.float64())], names=[*given, "predicted", "prob"])

    schema = T.StructType([*samples.schema.fields, T.StructField("predicted", T.StringType()), T.StructField("prob", T.DoubleType())])
    return ready.mapInArrow(run, schema)


def vote(predicted: DataFrame, keys: list[str], how: str = "majority") -> DataFrame:
    """A label for each sample from those of its windows: majority (ties: smaller label), first window, or mean probability."""
    p = predicted.filter("predicted is not null")
    if how == "first":
        return p.groupBy(*keys).agg(F.min_by("predicted", "win").alias("language"))
    weight = F.count(F.lit(1)).cast("double") if how == "majority" else F.sum("prob")
    each = p.groupBy(*keys, "predicted").agg(weight.alias("w"))
    return each.groupBy(*keys).agg(F.array_sort(F.collect_list(F.struct((-F.col("w")).alias("w"), "predicted")))[0]["predicted"].alias("language"))
