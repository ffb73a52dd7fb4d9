"""Document quality by attention-based multiple-instance learning.

A document is a bag of passages. Every passage is encoded by learnt embeddings
of its byte pairs and by some shares of its characters and words, gated
attention weighs the encodings, and the weighted sum is scored. Only document
labels are known; the attention finds the passages.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpusmap.llm.common import documents, fresh_names, held_out, lean, release, ship, text_or_empty
from corpusmap.llm.labelled import labelled_sample

PASSAGE_WORDS = 64
GRAMS, GRAM_SCALE = 4096, 8.0  # buckets of byte pairs; the mean of their embeddings counts so many times
#: fixed values: characters whose shares are features of their own
MARKS = b".,!?|#$%&*"


@dataclass
class MilParams:
    labelled: int = 4000  # most labelled documents to fit on
    labelled_bytes: int = 1 << 24  # and most bytes of their texts
    hidden: int = 16
    epochs: int = 12
    batch: int = 64
    rate: float = 0.01
    decay: float = 1e-4
    seed: int = 3


def passages(text: bytes) -> list[list[bytes]]:
    """The words of the lines of a text, long lines in pieces; no word: one empty passage."""
    out = []
    for line in text.split(b"\n"):
        words = line.split()
        for at in range(0, len(words), PASSAGE_WORDS):
            out.append(words[at: at + PASSAGE_WORDS])
    return out or [[]]


def features(bags: list[list[bytes]]) -> np.ndarray:
    """A row of shares for each passage: byte classes, marks, word repetition, lengths."""
    joined = [b"".join(w) for w in bags]
    size = np.array([len(j) for j in joined], dtype=np.int64)
    owner = np.repeat(np.arange(len(bags)), size)
    raw = np.frombuffer(b"".join(joined), dtype=np.uint8)
    hist = np.bincount(owner * 256 + raw, minlength=256 * len(bags)).reshape(-1, 256).astype(np.float64)
    share = hist / np.maximum(size, 1)[:, None]
    count = np.array([len(w) for w in bags], dtype=np.float64)
    distinct = np.array([len(set(w)) for w in bags]) / np.maximum(count, 1)
    again = np.array([sum(map(bytes.__eq__, w, w[1:])) for w in bags]) / np.maximum(count - 1, 1)
    cols = [share[:, 65:91].sum(1), share[:, 97:123].sum(1), share[:, 48:58].sum(1), share[:, 128:].sum(1), 1 - distinct, again, np.log1p(count) / 4, size / np.maximum(count, 1) / 10]
    cols += [np.minimum(4 * share[:, m], 2.0) for m in MARKS]
    other = [c for c in range(33, 127) if not (48 <= c < 58 or 65 <= c < 91 or 97 <= c < 123 or c in MARKS)]
    return np.stack([*cols, np.minimum(4 * share[:, other].sum(1), 2.0), size == 0], axis=1).astype(np.float32)


N_FEATURES = 8 + len(MARKS) + 2
_BUCKET = (((np.arange(1 << 16, dtype=np.int64) * 40503) & 0xFFFF) >> 4).astype(np.uint16)


@dataclass
class Grams:
    """Byte pairs of passages: buckets end to end, the share of each in its passage, and where each passage begins (none is empty)."""

    ids: np.ndarray
    share: np.ndarray
    starts: np.ndarray


def grams(bags: list[list[bytes]]) -> Grams:
    """All byte pairs of each passage, its words joined by blanks and blanks around it; an empty passage has one pair."""
    joined = [b" " + b" ".join(w) + b" " for w in bags]
    size = np.array([len(j) for j in joined], dtype=np.int64)
    raw = np.frombuffer(b"".join(joined), dtype=np.uint8).astype(np.int64)
    ends = np.cumsum(size)
    pair = np.ones(len(raw), dtype=bool)
    pair[ends - 1] = False  # no pair over the end of a passage
    first = np.flatnonzero(pair)
    return Grams(_BUCKET[raw[first] << 8 | raw[first + 1]], np.repeat((1.0 / (size - 1)).astype(np.float32), size - 1), np.concatenate(([0], np.cumsum(size - 1)[:-1])))


def compact(g: Grams) -> Grams:
    """Equal buckets of a passage as one, with their summed share."""
    owner = np.repeat(np.arange(len(g.starts)), np.diff(np.append(g.starts, len(g.ids))))
    key, back = np.unique(owner * GRAMS + g.ids, return_inverse=True)
    return Grams((key % GRAMS).astype(np.uint16), np.bincount(back, weights=g.share).astype(np.float32), np.searchsorted(key // GRAMS, np.arange(len(g.starts))))


def joined_grams(parts: list[Grams]) -> Grams:
    shift = np.cumsum([0, *(len(p.ids) for p in parts)])
    return Grams(np.concatenate([p.ids for p in parts]), np.concatenate([p.share for p in parts]), np.concatenate([p.starts + s for p, s in zip(parts, shift, strict=False)]))


def initial(p: MilParams) -> dict[str, np.ndarray]:
    rng = np.random.default_rng(p.seed)
    h, wide = p.hidden, lambda *s: rng.normal(0, 1 / np.sqrt(s[0]), s)
    return {"mean": np.zeros(N_FEATURES), "scale": np.ones(N_FEATURES), "emb": rng.normal(0, 0.05, (GRAMS, h)), "enc": wide(N_FEATURES, h), "enc_b": np.zeros(h), "tan": wide(h, h), "sig": wide(h, h), "att": wide(h), "out": wide(h), "out_b": np.zeros(1)}


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * (1 + np.tanh(0.5 * x))


def embedded(m: dict, g: Grams, step: int = 1 << 16) -> np.ndarray:
    """The weighted sum of embeddings of each passage; worked in pieces of whole passages, so that little is held at once."""
    out, at = np.empty((len(g.starts), m["emb"].shape[1])), 0
    bounds = np.append(g.starts, len(g.ids))
    while at < len(g.starts):
        to = max(at + 1, int(np.searchsorted(bounds, bounds[at] + step, side="right")) - 1)
        s = slice(bounds[at], bounds[to])
        out[at:to] = np.add.reduceat(m["emb"][g.ids[s]] * g.share[s, None], g.starts[at:to] - bounds[at])
        at = to
    return GRAM_SCALE * out


def forward(m: dict, x: np.ndarray, g: Grams, at: np.ndarray) -> dict:
    """Scores of bags; ``at`` holds the first passage of each bag (no bag is empty)."""
    r = {"x": (x - m["mean"]) / m["scale"]}
    r["e"] = np.tanh(embedded(m, g) + r["x"] @ m["enc"] + m["enc_b"])
    r["t"], r["s"] = np.tanh(r["e"] @ m["tan"]), _sigmoid(r["e"] @ m["sig"])
    a = (r["t"] * r["s"]) @ m["att"]
    bag = np.repeat(np.arange(len(at)), np.diff(np.append(at, len(x))))
    w = np.exp(a - np.maximum.reduceat(a, at)[bag])
    r["w"] = w / np.add.reduceat(w, at)[bag]
    r["z"] = np.add.reduceat(r["w"][:, None] * r["e"], at)
    r["bag"], r["logit"] = bag, r["z"] @ m["out"] + m["out_b"]
    return r


def gradients(m: dict, r: dict, grams_: Grams, y: np.ndarray, at: np.ndarray) -> dict[str, np.ndarray]:
    d = (_sigmoid(r["logit"]) - y) / len(y)
    g = {"out": r["z"].T @ d, "out_b": d.sum(keepdims=True)}
    dz = d[:, None] * m["out"]
    dzp = dz[r["bag"]]
    dw = (dzp * r["e"]).sum(1)
    da = r["w"] * (dw - np.add.reduceat(r["w"] * dw, at)[r["bag"]])
    ts = r["t"] * r["s"]
    g["att"] = ts.T @ da
    dts = da[:, None] * m["att"]
    dt, ds = dts * r["s"] * (1 - r["t"] ** 2), dts * r["t"] * r["s"] * (1 - r["s"])
    g["tan"], g["sig"] = r["e"].T @ dt, r["e"].T @ ds
    de = (r["w"][:, None] * dzp + dt @ m["tan"].T + ds @ m["sig"].T) * (1 - r["e"] ** 2)
    g["enc"], g["enc_b"] = r["x"].T @ de, de.sum(0)
    part = de[np.repeat(np.arange(len(de)), np.diff(np.append(grams_.starts, len(grams_.ids))))] * (GRAM_SCALE * grams_.share)[:, None]
    g["emb"] = np.stack([np.bincount(grams_.ids, weights=part[:, k], minlength=GRAMS) for k in range(de.shape[1])], axis=1)
    return g


def fit(bags: list[np.ndarray], pairs: list[Grams], y: np.ndarray, p: MilParams) -> dict[str, np.ndarray]:
    """Adam over mini-batches of bags, each with its shares and byte pairs. No labelled bag: a score of one half for all."""
    m = initial(p)
    if not len(bags):
        m["out"][:] = 0
        return m
    every = np.concatenate(bags)
    m["mean"], m["scale"] = every.mean(0, dtype=np.float64), every.std(0, dtype=np.float64) + 1e-3
    m["out_b"][:] = np.log((y.sum() + 0.5) / (len(y) - y.sum() + 0.5))
    rng, names = np.random.default_rng(p.seed), [k for k in m if k not in ("mean", "scale")]
    one, two, step = {k: np.zeros_like(m[k]) for k in names}, {k: np.zeros_like(m[k]) for k in names}, 0
    rounds = max(p.epochs, min(50, -(-400 * p.batch // len(bags))))  # few labels: more rounds
    for epoch in range(rounds):
        order, rate = rng.permutation(len(bags)), p.rate * (1 - epoch / rounds)
        for lo in range(0, len(bags), p.batch):
            some = order[lo: lo + p.batch]
            at = np.concatenate(([0], np.cumsum([len(bags[i]) for i in some])[:-1]))
            some_pairs = joined_grams([pairs[i] for i in some])
            g = gradients(m, forward(m, np.concatenate([bags[i] for i in some]), some_pairs, at), some_pairs, y[some], at)
            step += 1
            for k in names:
                d = g[k] + p.decay * m[k]
                one[k] += 0.1 * (d - one[k])
                two[k] += 0.001 * (d * d - two[k])
                m[k] = m[k] - rate * (one[k] / (1 - 0.9 ** step)) / (np.sqrt(two[k] / (1 - 0.999 ** step)) + 1e-8)
    return m


def train(docs: DataFrame, labels: DataFrame, allowed=None, p: MilParams | None = None) -> dict[str, np.ndarray]:
    """Fit on at most ``labelled`` documents and ``labelled_bytes`` of their texts. Passages are made on the executors.

    Null and empty texts are one empty passage; several rows with one
    identifier are bags of their own with its label; of several labels the
    largest counts; no labelled row gives a score of one half for all.
    """
    p = p or MilParams()
    ship(docs.sparkSession)
    sample = labelled_sample(docs, labels, "quality", F.lit(True) if allowed is None else allowed, p.labelled, p.seed, p.labelled_bytes)
    names = ["x", "ids", "share", "starts"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for t in b.column(2):
                some = passages(t.as_py())
                g = compact(grams(some))
                rows.append((features(some).tobytes(), g.ids.tobytes(), g.share.astype("<f2").tobytes(), g.starts.astype("<i4").tobytes()))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), *(pa.array(c, type=pa.binary()) for c in (zip(*rows, strict=True) if rows else [()] * 4))], names=["doc_id", "y", *names])

    head = sample.select("doc_id", "y").schema.simpleString()[7:-1]
    got = sample.mapInArrow(lean(run), f"{head}, " + ", ".join(f"{n} binary" for n in names)).toArrow().sort_by([("doc_id", "ascending"), ("x", "ascending")])
    bags = [np.frombuffer(x, dtype=np.float32).reshape(-1, N_FEATURES) for x in got.column("x").to_pylist()]
    pairs = [Grams(np.frombuffer(i, dtype=np.uint16), np.frombuffer(s, dtype="<f2").astype(np.float32), np.frombuffer(a, dtype="<i4").astype(np.int64)) for i, s, a in zip(*(got.column(n).to_pylist() for n in names[1:]), strict=True)]
    release(sample)
    return fit(bags, pairs, got.column("y").to_numpy().astype(np.float64), p)


def score(docs: DataFrame, model: dict[str, np.ndarray], keep: list[str] | None = None, name: str = "score") -> DataFrame:
    """``docs(doc_id, ..., text)`` -> ``(doc_id, score double)``, or the columns ``keep`` and the score as ``name``; one row per row.

    Null and empty texts are scored as one empty passage. Map only. ``name``
    must not be among ``keep``.
    """
    ship(docs.sparkSession)
    held = docs.sparkSession.sparkContext.broadcast({k: v.astype(np.float32) if k == "emb" else v for k, v in model.items()})
    keep = keep or ["doc_id"]
    text = fresh_names(docs, "text_bytes")[0]
    kept = docs.select(*keep, text_or_empty("text").cast("binary").alias(text))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = held.value
        for b in batches:
            out, bags, at = [], [], []
            for i, t in enumerate(b.column(len(keep))):
                at.append(len(bags))
                bags += passages(t.as_py())
                if len(bags) >= 4096 or i + 1 == b.num_rows:
                    out.append(_sigmoid(forward(m, features(bags), grams(bags), np.array(at))["logit"]))
                    bags, at = [], []
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array(np.concatenate(out) if out else np.zeros(0))], names=[*keep, name])

    return kept.mapInArrow(lean(run), kept.drop(text).withColumn(name, F.lit(0.0)).schema)


def accepted(docs: DataFrame, labels: DataFrame, threshold: float = 0.3) -> DataFrame:
    """The rows of ``docs`` whose score reaches ``threshold``; columns unchanged, whatever their names.

    Every row is judged by itself: repeated rows stay or go together, rows
    with null or empty texts are scored as one empty passage, rows without
    identifier are scored like any other. An empty table stays empty.
    """
    name = fresh_names(docs, "quality_score")[0]
    return score(docs, train(docs, labels), docs.columns, name).filter(F.col(name) >= threshold).select(*docs.columns)


def op6_attention_mil_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    model = train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"), ~held_out(5, 0))
    return score(docs, model).select("doc_id", held_out(5, 0).alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))
