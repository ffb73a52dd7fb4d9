"""A toxicity classifier regularised by counterfactual swaps of interchangeable terms.

Hashed words and word beginnings give a sentence an additive score. The worst
sentence gives that of the document; of the next two what lies above zero is
added. Terms that may stand in one another's
place form swap sets: given ones (group names of four languages) and sets that
the training rows show, terms that follow the same word and stand in toxic and
neutral documents alike. In every labelled sentence with such a term it is
swapped for another of its set, and the squared change of the score is a
penalty, so that a neutral mention moves no score by itself.

Texts never leave the executors. The driver gets sketches, counts of kept
features and each sentence as numbers of kept features.
"""

from __future__ import annotations

import heapq
import math
import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpusmap.llm.common import documents, held_out, materialize, release, ship, text_or_empty
from corpusmap.llm.labelled import labelled_sample

BUCKETS, CHUNK, CACHE = 1 << 20, 128, 200_000
STRIP, ENDS = b".,!?;:\"'()[]{}|#$%&*", b".!?"
BEGINNINGS = (4, 5, 6, 7, 8, 9)
WORST = 3  # sentences that speak for a document
#: fixed values: names of groups that are swapped with one another, by language
GROUP_NAMES = tuple(tuple(w.encode() for w in line.split()) for line in (
    "women men girls boys muslims christians jews hindus buddhists atheists africans asians europeans americans mexicans arabs indians chinese immigrants refugees foreigners elderly disabled",
    "femmes hommes filles garçons musulmans chrétiens juifs hindous bouddhistes athées africains asiatiques européens américains mexicains arabes indiens chinois immigrés réfugiés étrangers handicapés",
    "frauen männer mädchen jungen muslime christen juden hindus buddhisten atheisten afrikaner asiaten europäer amerikaner mexikaner araber inder chinesen einwanderer flüchtlinge ausländer behinderte",
    "mujeres hombres niñas niños musulmanes cristianos judíos hindúes budistas ateos africanos asiáticos europeos americanos mexicanos árabes indios chinos inmigrantes refugiados extranjeros discapacitados"))


@dataclass
class ToxParams:
    labelled: int = 16_000  # most labelled documents to fit on
    labelled_bytes: int = 1 << 27  # and most bytes of their texts, so that long documents do not make the sample large
    kept_features: int = 4096
    least_ratio: tuple = (14.0, 18.0, 25.0, 35.0)  # tried on an inner split of the training rows
    word_start: float = 4.0
    part_start: float = 1.5
    epochs: int = 30
    rate: float = 0.3
    decay: float = 1e-4
    swap_weight: float = 4.0
    swap_terms: int = 256  # most terms taken from the training rows
    swap_odds: float = 0.7  # such a term is as likely in toxic as in neutral documents up to this log-odds
    seed: int = 3


def word_features(word: bytes) -> tuple[int, ...]:
    """Buckets of the bare word, which comes first, and of its beginnings."""
    bare = word.strip(STRIP)
    if not bare:
        return ()
    return tuple(dict.fromkeys(zlib.crc32(tag + part) % BUCKETS for tag, part in ((b"w:", bare), *((b"%d:" % n, bare[:n]) for n in BEGINNINGS if len(bare) > n))))


def sentences(text: bytes) -> Iterator[list[bytes]]:
    """Lower-cased words up to a closing mark or the end of a line; runs of CHUNK words without one are cut. No word: one empty sentence."""
    some = False
    for line in text.lower().split(b"\n"):
        words, since = line.split(), 0
        for i, w in enumerate(words):
            if w[-1] in ENDS or i + 1 - since == CHUNK or i + 1 == len(words):
                yield words[since: i + 1]
                since, some = i + 1, True
    if not some:
        yield []


@dataclass
class Model:
    weights: dict[int, float]
    bias: float
    swap_sets: tuple[tuple[bytes, ...], ...] = ()
    swaps: int = 0  # labelled sentences with a term that was swapped
    least_ratio: float = 0.0

    def word(self, word: bytes) -> float:
        return sum(self.weights.get(f, 0.0) for f in word_features(word))

    def sentence(self, words: list[bytes]) -> float:
        return self.bias + sum(self.word(w) for w in set(words))


def sketch_of(text: bytes, size: int = 16) -> list[int]:
    """Smallest hashes of five-word runs."""
    words = text.lower().split()
    return heapq.nsmallest(size, {zlib.crc32(b" ".join(words[j: j + 5])) for j in range(max(1, len(words) - 4))})


def copy_classes(sketches: list[list[int]], size: int = 16, shared: int = 8) -> np.ndarray:
    """The first text that each one is nearly the same as: their sketches share enough."""
    group, owner = np.zeros(len(sketches), dtype=np.int64), {}
    for i, low in enumerate(sketches):
        met = Counter(owner[h] for h in low if h in owner).most_common(1)
        group[i] = met[0][0] if met and met[0][1] * size >= shared * len(low) else i
        for h in low:
            owner.setdefault(h, int(group[i]))
    return group


def copy_weights(texts: list[bytes]) -> np.ndarray:
    """One over the number of texts that are nearly the same."""
    group = copy_classes([sketch_of(t) for t in texts])
    return 1.0 / np.bincount(group, minlength=len(texts))[group] if len(texts) else np.ones(0)


def presence(texts: Iterator[bytes], rows: np.ndarray) -> tuple[np.ndarray, dict[bytes, np.ndarray], np.ndarray]:
    """Sums of ``rows`` (one per text) over the texts that hold a feature; the same by whole word; which features are whole words."""
    count, whole, is_word = np.zeros((rows.shape[1], BUCKETS)), {}, np.zeros(BUCKETS, dtype=bool)
    cache: dict[bytes, tuple[int, ...]] = {}
    for t, row in zip(texts, rows, strict=True):
        ids: set[int] = set()
        bare_words = set()
        for w in set(t.lower().split()):
            if w not in cache:
                if len(cache) > CACHE:
                    cache.clear()
                cache[w] = word_features(w)
                is_word[list(cache[w][:1])] = True
            ids.update(cache[w])
            bare_words.add(w.strip(STRIP))
        if ids:
            count[:, np.fromiter(ids, dtype=np.int64)] += row[:, None]
        for w in bare_words:
            if len(w) >= 3:
                whole[w] = whole[w] + row if w in whole else row
    return count, whole, is_word


def log_odds(toxic, neutral, n1: float, n0: float):
    return np.log((toxic + 0.5) / (n1 + 1)) - np.log((neutral + 0.5) / (n0 + 1))


def likelihood_ratio(toxic: np.ndarray, neutral: np.ndarray, n1: float, n0: float) -> np.ndarray:
    """Twice the log-likelihood of a feature's presence under its label against independence."""
    both, share = toxic + neutral, n1 / max(n1 + n0, 1e-9)
    with np.errstate(divide="ignore", invalid="ignore"):
        return 2 * (np.nan_to_num(toxic * np.log(toxic / (both * share))) + np.nan_to_num(neutral * np.log(neutral / (both * (1 - share)))))


def start_weights(ids: np.ndarray, toxic: np.ndarray, neutral: np.ndarray, is_word: np.ndarray, n1: float, n0: float, least: float, p: ToxParams) -> dict[int, float]:
    """Features that go with the label beyond chance, with a first weight: their log-odds within a bound."""
    ratio = likelihood_ratio(toxic, neutral, n1, n0)
    best = [i for i in np.argsort(-ratio, kind="stable")[: p.kept_features] if ratio[i] >= least]
    odds = log_odds(toxic, neutral, n1, n0)
    return {int(ids[i]): float(np.clip(odds[i], -m, m)) for i in best for m in [p.word_start if is_word[i] else p.part_start]}


@dataclass
class Encoded:
    """Training documents as sentences of feature numbers, and how often terms of the swap sets stand in their sentences."""

    bags: list[list[np.ndarray]]
    terms: list[list[bytes]]


def encode(texts: Iterator[bytes], row: dict[int, int], swap_terms: frozenset[bytes]) -> Iterator[tuple[list[tuple[int, ...]], list[bytes]]]:
    cache: dict[bytes, tuple[int, ...]] = {}
    for t in texts:
        bag, found = set(), []
        for s in sentences(t):
            here: set[int] = set()
            for word in set(s):
                if word not in cache:
                    if len(cache) > CACHE:
                        cache.clear()
                    cache[word] = tuple(row[f] for f in word_features(word) if f in row)
                here.update(cache[word])
                bare = word.strip(STRIP)
                if bare in swap_terms:
                    found.append(bare)
            bag.add(tuple(sorted(here)))
        yield sorted(bag), sorted(found)


def worst_sentences(sums: np.ndarray, owner: np.ndarray) -> np.ndarray:
    """Places of the sentences that count: the largest of each document, and the next ones up to WORST if above zero. ``owner`` ascends."""
    by = np.lexsort((-sums, owner))
    rank = np.arange(len(by)) - np.searchsorted(owner[by], owner[by], side="left")
    return by[(rank == 0) | (rank < WORST) & (sums[by] > 0)]


def fit_encoded(data: Encoded, y: np.ndarray, weight: np.ndarray, start: dict[int, float], swap_sets: tuple[tuple[bytes, ...], ...], p: ToxParams, names: np.ndarray | None = None) -> Model:
    """Logistic loss on the worst sentences of each document plus the swap penalty; AdaGrad. ``names`` are the features by number."""
    names = np.array(sorted(start), dtype=np.int64) if names is None else names
    row = {int(f): i for i, f in enumerate(names)}
    w = np.array([*(start.get(int(f), 0.0) for f in names), 0.0])  # the last one pads empty sentences
    used = np.zeros(len(w), dtype=bool)
    used[[row[f] for f in start if f in row]] = True
    n1 = float((weight * y).sum())
    bias, rng = float(np.log((n1 + 0.5) / (weight.sum() - n1 + 0.5))), np.random.default_rng(p.seed)
    terms = [t for s in swap_sets for t in s]
    number = {t: i for i, t in enumerate(terms)}
    set_of = {t: s for s in swap_sets for t in s}
    pad = len(names)
    vector = [[row[f] for f in word_features(t) if f in row] + [pad] for t in terms]
    term_flat, term_size = np.array([f for v in vector for f in v], dtype=np.int64), np.array([len(v) for v in vector], dtype=np.int64)
    term_at = np.concatenate(([0], np.cumsum(term_size)[:-1])).astype(np.int64)
    used[term_flat] = True
    pairs: list[list[tuple[int, int]]] = []
    for found in data.terms:
        pairs.append([])
        for t in found:
            s, i = set_of[t], number[t]
            if len(s) > 1:
                step = 1 + int(rng.integers(len(s) - 1))
                pairs[-1].append((i, number[s[(s.index(t) + step) % len(s)]]))
    bags = [[np.append(b, pad) for b in d] for d in data.bags]
    order = rng.permutation(len(bags))
    batches = []
    for lo in range(0, len(order), 256):
        some = order[lo: lo + 256]
        flat = [b for i in some for b in bags[i]]
        sizes = np.array([len(b) for b in flat])
        count = np.array([len(bags[i]) for i in some])
        two = np.array([pair for i in some for pair in pairs[i]], dtype=np.int64).reshape(-1, 2)
        two, times = np.unique(two, axis=0, return_counts=True)
        batches.append((some, np.concatenate(flat), np.concatenate(([0], np.cumsum(sizes)[:-1])), sizes, np.repeat(np.arange(len(some)), count), two, times))
    seen, seen_bias = np.full(len(w), 1e-2), 1e-2
    for _ in range(p.epochs):
        for some, flat, at, sizes, owner, two, times in batches:
            sums = np.add.reduceat(w[flat], at)
            top = worst_sentences(sums, owner)
            d = weight[some] * (1 / (1 + np.exp(-np.clip(bias + np.bincount(owner[top], weights=sums[top], minlength=len(some)), -50, 50))) - y[some])
            chosen = np.concatenate([flat[at[b]: at[b] + sizes[b]] for b in top])
            grad = np.bincount(chosen, weights=np.repeat(d[owner[top]], sizes[top]), minlength=len(w))
            if len(two):
                value = np.add.reduceat(w[term_flat], term_at)
                change = 2 * p.swap_weight * times * (value[two[:, 0]] - value[two[:, 1]])
                pull = np.bincount(two[:, 0], weights=change, minlength=len(terms)) - np.bincount(two[:, 1], weights=change, minlength=len(terms))
                grad += np.bincount(term_flat, weights=np.repeat(pull, term_size), minlength=len(w))
            grad = grad / len(some) + p.decay * w
            grad[~used] = 0.0
            grad[pad] = 0.0
            grad_bias = float(d.sum()) / len(some)
            seen += grad * grad
            seen_bias += grad_bias ** 2
            w -= p.rate * grad / np.sqrt(seen)
            bias -= p.rate * grad_bias / math.sqrt(seen_bias)
    return Model({int(f): float(x) for f, x in zip(names, w[:-1], strict=True) if abs(x) > 1e-6}, bias, swap_sets, sum(map(len, pairs)))


def fit(texts: list[bytes], y: np.ndarray, p: ToxParams | None = None, swap_sets: tuple[tuple[bytes, ...], ...] = GROUP_NAMES) -> Model:
    """:func:`train` on texts at hand, with the first of ``least_ratio`` and given swap sets."""
    p, y = p or ToxParams(), np.asarray(y, dtype=np.float64)
    if not len(y):
        return Model({}, 0.0)
    weight = copy_weights(texts)
    n1, n0 = float((weight * y).sum()), float((weight * (1 - y)).sum())
    count, _, is_word = presence(iter(texts), np.stack([weight * y, weight * (1 - y)], axis=1))
    ids = np.flatnonzero(count.sum(axis=0))
    start = start_weights(ids, count[0, ids], count[1, ids], is_word[ids], n1, n0, p.least_ratio[0], p)
    start = {f: 0.0 for s in swap_sets for t in s for f in word_features(t)} | start
    row = {f: i for i, f in enumerate(sorted(start))}
    got = list(encode(iter(texts), row, frozenset(t for s in swap_sets for t in s)))
    return fit_encoded(Encoded([[np.array(b, dtype=np.int64) for b in bag] for bag, _ in got], [t for _, t in got]), y, weight, start, swap_sets, p)


def of_sentences(values: list[float]) -> float:
    """The score of a document from those of its different sentences."""
    best = heapq.nlargest(WORST, values)
    return best[0] + sum(v for v in best[1:] if v > 0) if best else 0.0


def scores_of(model: Model, data: Encoded, names: np.ndarray) -> np.ndarray:
    w = np.array([model.weights.get(int(f), 0.0) for f in names])
    raw = np.array([of_sentences([float(w[b].sum()) for b in bag]) for bag in data.bags]) + model.bias
    return 0.5 * (1 + np.tanh(0.5 * raw))


def _f1(predicted: np.ndarray, y: np.ndarray, weight: np.ndarray) -> float:
    both = float((weight * (predicted & (y > 0))).sum())
    return 2 * both / max(float((weight * predicted).sum() + (weight * y).sum()), 1e-9)


def _feature_counts(sample: DataFrame, weights: dict[int, tuple[float, ...]]) -> tuple[DataFrame, DataFrame]:
    """Weighted documents by feature and by whole word, toxic and neutral, of all and of the inner training rows."""
    held = sample.sparkSession.sparkContext.broadcast(weights)
    sums = ["t", "n", "it", "in_"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        of, texts, rows = held.value, [], []
        total = whole = is_word = None

        def flush():
            nonlocal total, whole, is_word
            c, w, i = presence(iter(texts), np.array(rows))
            if total is None:
                total, whole, is_word = c, w, i
            else:
                total, is_word = total + c, is_word | i
                for k, v in w.items():
                    whole[k] = whole[k] + v if k in whole else v

        for b in batches:
            for doc, text in zip(b.column(0).to_pylist(), b.column(2), strict=True):
                if doc in of:
                    texts.append(text.as_py())
                    rows.append(of[doc])
            if len(texts) >= 256:
                flush()
                texts, rows = [], []
        if texts:
            flush()
        if total is not None:
            full = np.flatnonzero(total.any(axis=0))
            none = pa.nulls(len(full), pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array(full), none, pa.array(is_word[full]), *(pa.array(total[k][full]) for k in range(4))], names=["f", "word", "whole", *sums])
            words = list(whole)
            values = np.stack([whole[w] for w in words]) if words else np.zeros((0, 4))
            yield pa.RecordBatch.from_arrays([pa.nulls(len(words), pa.int64()), pa.array(words, type=pa.binary()), pa.nulls(len(words), pa.bool_()), *(pa.array(values[:, k]) for k in range(4))], names=["f", "word", "whole", *sums])

    found = sample.mapInArrow(run, "f long, word binary, whole boolean, t double, n double, it double, in_ double")
    found = materialize(found.groupBy("f", "word").agg(F.max("whole").alias("whole"), *[F.sum(c).alias(c) for c in sums]), "toxic-features")
    return found.filter("f is not null"), found.filter("word is not null")


def _swap_sets(sample: DataFrame, words: DataFrame, n1: float, n0: float, p: ToxParams) -> tuple[tuple[bytes, ...], ...]:
    """Sets of terms that follow the same word most often and stand in toxic and neutral documents alike."""
    odds = F.abs(F.log((F.col("t") + 0.5) / (n1 + 1.0)) - F.log((F.col("n") + 0.5) / (n0 + 1.0)))
    alike = words.filter((F.col("t") >= 2.0) & (F.col("n") >= 2.0) & (F.length("word") >= 4) & (odds <= p.swap_odds))
    terms = [bytes(r[0]) for r in alike.orderBy(F.desc("t"), "word").limit(p.swap_terms).select("word").collect()]
    if not terms:
        return ()
    held = sample.sparkSession.sparkContext.broadcast(frozenset(terms))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        wanted, seen = held.value, Counter()
        for b in batches:
            for t in b.column(2):
                for s in sentences(t.as_py()):
                    bare = [w.strip(STRIP) for w in s]
                    seen.update((x, y) for x, y in zip(bare, bare[1:]) if y in wanted)
        yield pa.RecordBatch.from_arrays([pa.array([k[1] for k in seen], type=pa.binary()), pa.array([k[0] for k in seen], type=pa.binary()), pa.array(list(seen.values()), type=pa.int64())], names=["term", "before", "n"])

    near = sample.mapInArrow(run, "term binary, before binary, n long").groupBy("term", "before").agg(F.sum("n").alias("n"))
    slots: dict[bytes, list[bytes]] = {}
    for r in near.groupBy("term").agg(F.max(F.struct("n", "before")).alias("m")).select("term", "m.before").collect():  # at most swap_terms rows
        slots.setdefault(bytes(r[1]), []).append(bytes(r[0]))
    return tuple(tuple(sorted(s)) for _, s in sorted(slots.items()) if len(s) > 1)


def _encoded(sample: DataFrame, names: np.ndarray, swap_sets: tuple[tuple[bytes, ...], ...], ids: list[int]) -> Encoded:
    held = sample.sparkSession.sparkContext.broadcast(({int(f): i for i, f in enumerate(names)}, frozenset(t for s in swap_sets for t in s)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        row, terms = held.value
        for b in batches:
            got = list(encode((t.as_py() for t in b.column(2)), row, terms))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([g[0] for g in got], type=pa.list_(pa.list_(pa.int32()))), pa.array([g[1] for g in got], type=pa.list_(pa.binary()))], names=["doc_id", "bags", "terms"])

    head = sample.select("doc_id").schema.simpleString()[7:-1]
    got = sample.mapInArrow(run, f"{head}, bags array<array<int>>, terms array<binary>").toArrow()
    bags, terms = {}, {}
    for doc, b, t in zip(got.column("doc_id").to_pylist(), got.column("bags").to_pylist(), got.column("terms").to_pylist(), strict=True):
        bags.setdefault(doc, []).extend(np.array(x, dtype=np.int64) for x in b)  # several rows of one identifier are one document
        terms.setdefault(doc, []).extend(t)
    return Encoded([bags[i] for i in ids], [terms[i] for i in ids])


def train(docs: DataFrame, labels: DataFrame, allowed=None, p: ToxParams | None = None, swap_sets: tuple[tuple[bytes, ...], ...] = GROUP_NAMES) -> Model:
    """Fit on at most ``labelled`` documents and ``labelled_bytes`` of their texts, drawn by hash of the identifier.

    ``least_ratio`` is chosen on an inner split of these rows (copies stay
    together), then all of them are fitted. ``swap_sets`` are joined by sets
    that the rows show. Null and empty texts take part with no word; of
    several rows with one identifier all text counts as one document; no
    labelled row gives a score of one half for all.
    """
    p = p or ToxParams()
    ship(docs.sparkSession)
    sample = labelled_sample(docs, labels, "toxic", F.lit(True) if allowed is None else allowed, p.labelled, p.seed, p.labelled_bytes)

    def outline(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([sketch_of(t.as_py()) for t in b.column(2)], type=pa.list_(pa.int64()))], names=["doc_id", "y", "low"])

    head = sample.select("doc_id", "y").schema.simpleString()[7:-1]
    got = sample.mapInArrow(outline, f"{head}, low array<long>").groupBy("doc_id").agg(F.max("y").alias("y"), F.min("low").alias("low")).toArrow().sort_by("doc_id")
    if not got.num_rows:
        return Model({}, 0.0)
    ids, y = got.column("doc_id").to_pylist(), got.column("y").to_numpy().astype(np.float64)
    group = copy_classes(got.column("low").to_pylist())
    weight = 1.0 / np.bincount(group, minlength=len(ids))[group]
    inner = np.array([zlib.crc32(str(ids[g]).encode()) % 5 != 0 for g in group])
    rows = {d: (w * t, w * (1 - t), w * t * i, w * (1 - t) * i) for d, w, t, i in zip(ids, weight.tolist(), y.tolist(), inner.astype(float).tolist(), strict=True)}
    features, words = _feature_counts(sample, rows)
    totals = [float(sum(r[k] for r in rows.values())) for k in range(4)]

    def ratio(a: str, b: str, n1: float, n0: float):
        x, z, both, share = F.col(a), F.col(b), F.col(a) + F.col(b), n1 / max(n1 + n0, 1e-9)
        part = lambda k, s: F.when((k > 0) & (both > 0) & F.lit(s > 0), k * F.ln(k / (both * s))).otherwise(0.0)
        return 2 * (part(x, share) + part(z, 1 - share))

    def most(a: str, b: str, n1: float, n0: float) -> pa.Table:
        r = ratio(a, b, n1, n0)
        return features.withColumn("r", r).filter(F.col("r") >= min(p.least_ratio) - 1e-9).orderBy(F.desc("r"), "f").limit(p.kept_features).select("f", "whole", F.col(a).alias("a"), F.col(b).alias("b")).toArrow()

    swap_sets = (*swap_sets, *_swap_sets(sample, words, totals[0], totals[1], p))
    part, every = most("it", "in_", totals[2], totals[3]), most("t", "n", totals[0], totals[1])

    def start(t: pa.Table, n1: float, n0: float, least: float) -> dict[int, float]:
        return start_weights(*(t.column(c).to_numpy() for c in ("f", "a", "b", "whole")), n1, n0, least, p)

    named = {f for s in swap_sets for t in s for f in word_features(t)}
    names = np.array(sorted(named | set(part.column("f").to_pylist()) | set(every.column("f").to_pylist())), dtype=np.int64)
    data = _encoded(sample, names, swap_sets, ids)
    release(sample, features, words)
    best, least = -1.0, p.least_ratio[0]
    if len(p.least_ratio) > 1 and 0 < y[inner].sum() < inner.sum() and 0 < y[~inner].sum() < (~inner).sum():
        pick = lambda keep: Encoded([b for b, k in zip(data.bags, keep, strict=True) if k], [t for t, k in zip(data.terms, keep, strict=True) if k])
        for one in p.least_ratio:
            m = fit_encoded(pick(inner), y[inner], weight[inner], start(part, totals[2], totals[3], one), swap_sets, replace(p, epochs=max(1, p.epochs // 3)), names)
            f1 = _f1(scores_of(m, pick(~inner), names) >= 0.3, y[~inner], weight[~inner])
            if f1 > best + 1e-9:
                best, least = f1, one
    model = fit_encoded(data, y, weight, start(every, totals[0], totals[1], least), swap_sets, p, names)
    model.least_ratio = least
    return model


def score(docs: DataFrame, model: Model) -> DataFrame:
    """``docs(doc_id, text)`` -> ``(doc_id, score double)``, one row per row. Null and empty texts have the bias alone. Map only."""
    ship(docs.sparkSession)
    held = docs.sparkSession.sparkContext.broadcast(model)
    kept = docs.select("doc_id", text_or_empty("text").cast("binary").alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m, cache = held.value, {}

        def value(w: bytes) -> float:
            if w not in cache:
                if len(cache) > CACHE:
                    cache.clear()
                cache[w] = m.word(w)
            return cache[w]

        def value_of(text: bytes) -> float:
            words = set(text.lower().split())
            known = {w: v for w in words if (v := value(w))}
            if not known:
                return m.bias
            return m.bias + of_sentences(list({k: sum(known[w] for w in k) for s in sentences(text) for k in [frozenset(w for w in s if w in known)]}.values()))

        for b in batches:
            raw = np.array([value_of(t.as_py()) for t in b.column(1)], dtype=np.float64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(0.5 * (1 + np.tanh(0.5 * raw)))], names=["doc_id", "score"])

    return kept.mapInArrow(run, kept.select("doc_id").withColumn("score", F.lit(0.0)).schema)


def op8_counterfactual_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    model = train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"), ~held_out(4, 2))
    return score(docs, model).select("doc_id", held_out(4, 2).alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))
