"""A hidden Markov language model: Baum-Welch over partitions, exact scaled forward scores.

The states emit classes. A token that makes up at least one in ``heavy`` of
all training tokens is a class of its own (so there are at most ``heavy`` of
them, whatever the corpus); the others share classes by their last bytes, and
a class gives its tokens by their add-one frequencies with one place for the
unseen. Counts of all tokens come from the whole training corpus. So do the
expected counts of the Baum-Welch iterations, which go on until the likelihood
settles; some rounds on a share of the documents, whole ones, come before them
as a first guess. Texts are turned into classes once, for all iterations. Long
documents are cut into stretches that are worked abreast: products of their
transfer matrices carry the state over the cuts exactly.
"""

from __future__ import annotations

import hashlib
import sys
import zlib
from bisect import bisect_right
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import repeat

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpusmap.llm.common import documents, held_out, materialize, release, row_key, ship, text_or_empty

END = b" "  # no token holds a blank
TAIL_CLASSES, TAIL_BYTES = 4096, 3
BLOCK = 1024  # classes whose sums travel together between tasks
GROUP, BUFFER = 1 << 19, 1 << 22  # tokens worked abreast, and tokens held to choose sequences of like lengths from
STEPS = 1 << 13  # tokens whose emissions are looked up at once where they are not kept: they fit a core's cache
SLICE = 1 << 23  # bytes of text that are split at once; a longer text is split by itself
LONG = 64  # bytes; a longer heavy token is held by its digest, so that memory is bounded


def tokens_of(text: bytes) -> list[bytes]:
    """Lower-cases A-Z, splits on separators; the end of the text is not included."""
    return text.lower().split()


@dataclass
class Params:
    states: int = 8
    heavy: int = 1 << 19
    heavy_least: int = 8  # occurrences
    sample_docs: int = 3000  # about so many documents, whole, for the first guess
    sample_rounds: int = 16
    passes: int = 100  # at most; raises if the likelihood has not settled by then
    settled: float = 1e-3  # gain in natural log-likelihood a token between iterations
    segment: int = 2048  # training works longer documents in stretches
    smoothing: float = 0.5
    seed: int = 5


@dataclass
class Model:
    heavy: list[bytes]
    heavy_counts: np.ndarray
    tail_tokens: np.ndarray  # occurrences of each tail class
    tail_types: np.ndarray
    tokens: int
    types: int
    start: np.ndarray = None
    move: np.ndarray = None
    emit: np.ndarray = None  # classes by states

    @property
    def classes(self) -> int:
        return len(self.heavy) + TAIL_CLASSES

    def class_counts(self) -> np.ndarray:
        return np.concatenate((self.heavy_counts, self.tail_tokens)).astype(np.float64)

    def added(self) -> np.ndarray:
        """Class counts with one more for every type, and one unseen type in each tail class."""
        return np.concatenate((self.heavy_counts + 1.0, self.tail_tokens + self.tail_types + 1.0))


def tail_class(token: bytes) -> int:
    return zlib.crc32(token[-TAIL_BYTES:]) % TAIL_CLASSES


def held_as(token: bytes) -> bytes:
    """The name of a heavy token in a model: itself, or after a blank, which no token holds, the MD5 of a long one."""
    return token if len(token) <= LONG else END + hashlib.md5(token).digest()


def encode(text: bytes, index: dict[bytes, int], first_tail: int) -> tuple[np.ndarray, list[bytes]]:
    """Classes of all tokens, the end last, and the tokens that are not heavy."""
    words = tokens_of(text)
    words.append(END)
    ids = np.fromiter(map(index.get, words, repeat(-1)), dtype="<i4", count=len(words))
    tail = []
    for i in np.flatnonzero(ids < 0).tolist():
        w = words[i]
        c = index.get(held_as(w), -1) if len(w) > LONG else -1
        if c < 0:
            c = first_tail + tail_class(w)
            tail.append(w)
        ids[i] = c
    return ids, tail


def _runs(texts: pa.Array) -> Iterator[tuple[int, int]]:
    """Bounds of runs of texts that hold about SLICE bytes together, one text at least."""
    sizes, lo = np.cumsum(pc.binary_length(texts).to_numpy(), dtype=np.int64), 0
    while lo < len(sizes):
        hi = max(lo + 1, int(np.searchsorted(sizes, SLICE + (sizes[lo - 1] if lo else 0), side="right")))
        yield lo, hi
        lo = hi


def split_all(texts: pa.Array) -> tuple[np.ndarray, np.ndarray, pa.Array]:
    """:func:`tokens_of` for binary ``texts`` without nulls: how many each has, their places in a list of the different ones, and that list."""
    split = pc.ascii_split_whitespace(pc.ascii_lower(texts.view(pa.string())))
    lens = pc.list_value_length(split).to_numpy().astype(np.int64)
    coded = split.flatten().view(pa.binary()).dictionary_encode()
    at, words = coded.indices.to_numpy(), coded.dictionary
    blank = pc.index(words, b"").as_py()
    if blank >= 0:  # what lies outside of separators at either end of a text
        real = at != blank
        before, ends = np.concatenate(([0], np.cumsum(real))), np.cumsum(lens)
        lens = before[ends] - before[ends - lens]
        at = at[real]
        at = at - (at > blank)
        words = pa.concat_arrays([words[:blank], words[blank + 1:]])
    return lens, at, words


def _crc_of_bytes() -> np.ndarray:
    c = np.arange(256, dtype=np.uint32)
    for _ in range(8):
        c = np.where(c & 1, (c >> 1) ^ np.uint32(0xEDB88320), c >> 1)
    return c


CRC = _crc_of_bytes()


def tail_classes(tokens: pa.Array) -> np.ndarray:
    """:func:`tail_class` of every token."""
    if not len(tokens):
        return np.zeros(0, dtype=np.int64)
    at = np.frombuffer(tokens.buffers()[1], dtype="<i4")[tokens.offset: tokens.offset + len(tokens) + 1]
    data, lens, ends = np.frombuffer(tokens.buffers()[2], dtype=np.uint8), np.diff(at), at[1:]
    crc = np.full(len(tokens), 0xFFFFFFFF, dtype=np.uint32)
    for back in range(TAIL_BYTES, 0, -1):
        byte = data[np.maximum(ends - back, 0)]
        crc = np.where(lens >= back, CRC[(crc ^ byte) & 255] ^ (crc >> 8), crc)
    return (~crc % TAIL_CLASSES).astype(np.int64)


def encode_all(texts: pa.Array, heavy: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, pa.Array]:
    """:func:`encode` for binary ``texts``: how many tokens each has, the end included, all their classes one after the other, and text and name of each token that is not heavy."""
    lens, at, words = split_all(texts)
    of = pc.index_in(words, value_set=heavy).fill_null(-1).to_numpy().copy()
    long = np.flatnonzero((of < 0) & (pc.binary_length(words).to_numpy() > LONG))
    if len(long):
        named = pa.array([held_as(w) for w in words.take(pa.array(long)).to_pylist()], type=pa.binary())
        of[long] = pc.index_in(named, value_set=heavy).fill_null(-1).to_numpy()
    rest = np.flatnonzero(of < 0)
    of[rest] = len(heavy) + tail_classes(words.take(pa.array(rest)))
    ids, ends = np.empty(len(at) + len(lens), dtype="<i4"), np.cumsum(lens) + np.arange(len(lens))
    inside = np.ones(len(ids), dtype=bool)
    inside[ends] = False
    found = of[at]
    ids[inside] = found
    ids[ends] = pc.index(heavy, END).as_py()
    tail = np.flatnonzero(found >= len(heavy))
    return lens + 1, ids, np.searchsorted(np.cumsum(lens), tail, side="right"), words.take(pa.array(at[tail]))


class _Abreast:
    """Sequences side by side, the longest first; tokens of one step lie together."""

    def __init__(self, seqs: list[np.ndarray]):
        self.lens = np.array([len(s) for s in seqs], dtype=np.int64)
        flat = np.concatenate(seqs)
        at = np.concatenate(([0], np.cumsum(self.lens)[:-1]))
        alive = np.searchsorted(-self.lens, -np.arange(self.lens[0]), side="left")  # sequences longer than t
        off = np.concatenate(([0], np.cumsum(alive)))
        slot = off[np.arange(len(flat)) - np.repeat(at, self.lens)] + np.repeat(np.arange(len(seqs)), self.lens)
        self.ids = np.empty(len(flat), dtype=np.intp)  # as numpy takes places, so that it need not turn them for each state
        self.ids[slot] = flat
        self.alive, self.off = alive.tolist(), off.tolist()  # numbers of Python, which loops read faster

    def unscaled(self, t: int) -> int:
        """How many sequences keep their messages as they are at step ``t``: none at every fourth, else those that go on.

        Four emissions stay far above the smallest double; where a message is
        left unscaled its scale is one.
        """
        return self.alive[t + 1] if t % 4 != 3 and t + 1 < len(self.alive) else 0

    def emitted(self, emit: np.ndarray) -> Iterator[tuple[int, int, np.ndarray]]:
        """Every step, its number of sequences, and what its tokens emit, states by sequences; about STEPS tokens are held."""
        t = 0
        while t < len(self.alive):
            lo = self.off[t]
            end = max(t + 1, bisect_right(self.off, lo + STEPS) - 1)
            out = _by_state(len(emit), self.off[end] - lo, {}, "out")
            for k in range(len(emit)):
                np.take(emit[k], self.ids[lo: self.off[end]], out=out[k], mode="clip")
            for i in range(t, end):
                yield i, self.alive[i], out[:, self.off[i] - lo: self.off[i + 1] - lo]
            t = end

    def forward(self, enter: np.ndarray, move: np.ndarray, emit: np.ndarray, room: dict) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Scaled forward messages, scales, and what each token emits; ``enter`` is what comes before the first tokens.

        Here and below arrays lie state by state: ``emit`` is states by
        classes, messages are states by tokens, ``enter`` is states by sequences.
        """
        h, size = emit.shape[0], len(self.ids)
        out, a, s = _by_state(h, size, room, "out"), _by_state(h, size, room, "a"), np.ones(size)
        for k in range(h):
            np.take(emit[k], self.ids, out=out[k], mode="clip")
        step = np.ascontiguousarray(move.T)
        for t in range(len(self.alive)):
            n, lo = self.alive[t], self.off[t]
            now = a[:, lo: lo + n]
            if t:
                before = self.off[t - 1]
                np.matmul(step, a[:, before: before + n], out=now)
                np.multiply(now, out[:, lo: lo + n], out=now)
            else:
                np.multiply(enter, out[:, :n], out=now)
            keep = self.unscaled(t)
            if keep < n:
                now, scale = now[:, keep:], s[lo + keep: lo + n]
                np.add.reduce(now, axis=0, out=scale)
                now /= scale
        return a, s, out

    def scales(self, start: np.ndarray, move: np.ndarray, emit: np.ndarray) -> np.ndarray:
        """The scales of :meth:`forward` alone; messages are held for one step."""
        s, step, now = np.ones(len(self.ids)), np.ascontiguousarray(move.T), None
        for t, n, out in self.emitted(emit):
            lo = self.off[t]
            np.multiply(out, start[:, None] if now is None else step @ now[:, :n], out=out)
            now, keep = out, self.unscaled(t)
            if keep < n:
                out, scale = out[:, keep:], s[lo + keep: lo + n]
                np.add.reduce(out, axis=0, out=scale)
                out /= scale
        return s


def _by_state(states: int, size: int, room: dict, name: str) -> np.ndarray:
    """Room for ``states`` rows of ``size``, kept in ``room`` for the next call: fresh pages cost more than the work in them.

    Rows begin at different places of a page, so that they do not crowd each other out of the cache.
    """
    wide = (size // 512 + 1) * 512 + 24
    if name not in room or len(room[name]) < states * wide:
        room.pop(name, None)
        room[name] = np.empty(states * wide)
    return room[name][: states * wide].reshape(states, wide)[:, :size]


def forward(seqs: list[np.ndarray], start: np.ndarray, move: np.ndarray, emit: np.ndarray) -> np.ndarray:
    """Natural log-likelihood of each sequence, exactly, by the scaled forward recursion, all sequences abreast."""
    out = np.zeros(len(seqs))
    order = np.argsort([-len(s) for s in seqs], kind="stable")
    if not len(order) or not len(seqs[order[0]]):
        return out
    side = _Abreast([seqs[i] for i in order])
    s = side.scales(start, move, np.ascontiguousarray(emit.T))
    owner = np.arange(len(s)) - np.repeat(side.off[:-1], side.alive)
    out[order] = np.bincount(owner, weights=np.log(s), minlength=len(order))
    return out


def expected_counts(seqs: list[np.ndarray], first: list[bool], start, move, emit, group: int = GROUP):
    """Baum-Welch expectations: (start counts, transition counts, emission counts by class); first: counts towards start."""
    return _counts(seqs, first, start, move, np.ascontiguousarray(emit.T), group)[:3]


def _counts(seqs: list[np.ndarray], first: list[bool], start, move, emit, group: int = GROUP, before: np.ndarray | None = None, after: np.ndarray | None = None, room: dict | None = None):
    """:func:`expected_counts` and the log-likelihood; ``emit`` is states by classes.

    ``before`` holds the forward message at the token that precedes each
    sequence (used where ``first`` is false), ``after`` the backward message at
    its last token; without them a sequence stands alone.
    """
    h = len(start)
    g_start, g_move, g_emit, gain = np.zeros(h), np.zeros((h, h)), np.zeros_like(emit), 0.0
    order = sorted(range(len(seqs)), key=lambda i: -len(seqs[i]))
    room = {} if room is None else room
    while order:
        sizes = np.cumsum([len(seqs[i]) for i in order])
        n_some = max(1, int(np.searchsorted(sizes, group, side="right")))
        some, order = order[:n_some], order[n_some:]
        if not len(seqs[some[0]]):
            break
        side = _Abreast([seqs[i] for i in some])
        opens = np.array([first[i] for i in some], dtype=bool)[: side.alive[0]]
        ends = np.ones((h, len(some))) if after is None else np.ascontiguousarray(after[some].T)
        enter = start[:, None] if before is None else np.where(opens, start[:, None], (before[some] @ move).T[:, : len(opens)])
        a, s, back = side.forward(enter, move, emit, room)
        gain += float(np.log(s[s != 1.0]).sum())
        for t in range(len(side.alive) - 1, -1, -1):
            n, lo = side.alive[t], side.off[t]
            come, now, beta = back[:, lo: lo + n], a[:, lo: lo + n], ends[:, :n]  # those that end here have their end there yet
            keep = side.unscaled(t)
            if keep < n:
                last = come[:, keep:]
                np.divide(last, s[lo + keep: lo + n], out=last)
            np.multiply(come, beta, out=come)
            np.multiply(now, beta, out=now)  # what was the message is now the share of each state
            if t:
                earlier = side.off[t - 1]
                g_move += a[:, earlier: earlier + n] @ come.T
                np.matmul(move, come, out=beta)
            elif before is not None:
                g_move += before[some][:n][~opens].T @ come[:, ~opens].T
        g_start += a[:, : len(opens)][:, opens].sum(axis=1)
        for k in range(h):
            g_emit[k] += np.bincount(side.ids, weights=a[k], minlength=emit.shape[1])
    return g_start, g_move * move, g_emit.T, gain


def _transfers(seqs: list[np.ndarray], left: np.ndarray, move: np.ndarray, emit: np.ndarray) -> np.ndarray:
    """For each sequence, up to a factor, what becomes of the rows ``left``, states before its first token's emission, after its last.

    ``emit`` is states by classes. The identity as ``left`` gives the whole transfer matrix.
    """
    h, rows = len(move), len(left)
    order = np.argsort([-len(s) for s in seqs], kind="stable")
    out, step, got = np.empty((len(seqs), rows, h)), np.ascontiguousarray(move.T), None

    def ended(n: int) -> None:
        done = got[:, :, n:]
        out[order[n: got.shape[2]]] = (done / done.sum(axis=(0, 1))).transpose(2, 1, 0)

    for t, n, emits in _Abreast([seqs[i] for i in order]).emitted(emit):
        emits = emits[:, None, :]
        if got is None:
            got = left.T[:, :, None] * emits
            continue
        if n < got.shape[2]:
            ended(n)
            got = np.ascontiguousarray(got[:, :, :n])
        got = (step @ got.reshape(h, -1)).reshape(h, rows, n)
        got *= emits
        if t % 8 == 7:  # eight emissions stay far above the smallest double
            got /= got.sum(axis=(0, 1))
    ended(0)
    return out


def document_counts(docs: list[np.ndarray], start, move, emit, segment: int = 2048, room: dict | None = None):
    """Exact expectations and log-likelihood of whole documents; cuts after ``segment`` tokens change the work, not the result."""
    h = len(start)
    seqs, first, spans = [], [], []
    for d in docs:
        cut = [d[i: i + segment] for i in range(0, len(d), segment)]
        if len(cut) > 1:
            spans.append((len(seqs), len(seqs) + len(cut)))
        seqs += cut
        first += [True] + [False] * (len(cut) - 1)
    before, after, emit = np.ones((len(seqs), h)), np.ones((len(seqs), h)), np.ascontiguousarray(emit.T)
    if spans:
        # a first stretch is entered in a known state and a last one left in any, so only those between need matrices
        heads = _transfers([seqs[a] for a, _ in spans], start[None], move, emit)
        lasts = _transfers([seqs[b - 1][::-1] for _, b in spans], np.ones((1, h)), move.T, emit)
        inner = [i for a, b in spans for i in range(a + 1, b - 1)]
        through = dict(zip(inner, _transfers([seqs[i] for i in inner], np.eye(h), move, emit), strict=True)) if inner else {}
        for (a, b), head, tail in zip(spans, heads, lasts, strict=True):
            state = before[a + 1] = head[0]
            for i in range(a + 1, b - 1):
                state = (state @ move) @ through[i]
                state = before[i + 1] = state / state.sum()
            back = tail[0]
            for i in range(b - 1, a, -1):
                back = move @ (back if i == b - 1 else through[i] @ back)
                back = after[i - 1] = back / (before[i] @ back)
    return _counts(seqs, first, start, move, emit, before=before, after=after, room=room)


def maximise(model: Model, g_start, g_move, g_emit, smoothing: float) -> None:
    """New probabilities from expected counts; each is drawn a little towards the plain class frequencies."""
    h = len(g_start)
    plain = model.added() / model.added().sum()
    model.start = (g_start + smoothing) / (g_start + smoothing).sum()
    model.move = (g_move + smoothing) / (g_move + smoothing).sum(axis=1, keepdims=True)
    unseen = model.added() / np.maximum(model.class_counts(), 1.0)  # room for tokens that training has not seen
    grown = g_emit * unseen[:, None] + smoothing * plain[:, None] * max(1.0, g_emit.sum() / h / 20)
    model.emit = grown / grown.sum(axis=0)


def token_counts(texts: DataFrame) -> DataFrame:
    """``(token binary, n long)`` over every whole text; each text adds one END. Combined in the task first."""
    ship(texts.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n_texts = 0
        for b in batches:
            n_texts += b.num_rows
            for lo, hi in _runs(b.column(0)):
                _, at, words = split_all(b.column(0).slice(lo, hi - lo))
                yield pa.RecordBatch.from_arrays([words, pa.array(np.bincount(at, minlength=len(words)), type=pa.int64())], names=["token", "n"])
        if n_texts:
            yield pa.RecordBatch.from_arrays([pa.array([END], type=pa.binary()), pa.array([n_texts], type=pa.int64())], names=["token", "n"])

    return texts.mapInArrow(run, "token binary, n long").groupBy("token").agg(F.sum("n").alias("n"))


def gather(counts: DataFrame, p: Params) -> Model:
    """Totals, heavy tokens and tail classes from the counts; bounded by ``heavy`` and TAIL_CLASSES."""
    tokens, types = counts.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count(F.lit(1))).first()
    big = (F.col("token") == F.lit(END)) | ((F.col("n") * p.heavy >= tokens) & (F.col("n") >= p.heavy_least))
    name = F.when(F.length("token") > LONG, F.concat(F.lit(END), F.unhex(F.md5("token")))).otherwise(F.col("token"))
    heavy = counts.filter(big).select(name.alias("token"), "n").orderBy(F.desc("n"), "token").toArrow()
    names, n = heavy.column("token").to_pylist(), heavy.column("n").to_numpy()
    if END not in names:
        names, n = [*names, END], np.append(n, 0)
    tail_tokens, tail_types = np.zeros(TAIL_CLASSES, dtype=np.int64), np.zeros(TAIL_CLASSES, dtype=np.int64)
    last = F.when(F.length("token") > TAIL_BYTES, F.substring("token", -TAIL_BYTES, TAIL_BYTES)).otherwise(F.col("token"))
    for c, a, b in counts.filter(~big).groupBy(F.pmod(F.crc32(last), F.lit(TAIL_CLASSES)).cast("int").alias("c")).agg(F.sum("n"), F.count(F.lit(1))).collect():
        tail_tokens[c], tail_types[c] = a, b
    return Model(names, np.asarray(n, dtype=np.int64), tail_tokens, tail_types, int(tokens), int(types))


def random_states(model: Model, p: Params) -> None:
    """Class frequencies, disturbed at random for each state; states tend to last."""
    rng = np.random.default_rng(p.seed)
    plain = model.added()
    model.emit = plain[:, None] * np.exp(rng.normal(0, 0.7, (model.classes, p.states)))
    model.emit /= model.emit.sum(axis=0)
    model.start = np.full(p.states, 1 / p.states)
    model.move = np.full((p.states, p.states), 0.4 / p.states) + 0.6 * np.eye(p.states)


def encoded(texts: DataFrame, model: Model) -> DataFrame:
    """``texts(text binary, drawn boolean)`` -> ``(ids binary, drawn)``: the classes of every text, the end last, four bytes each."""
    ship(texts.sparkSession)
    held = texts.sparkSession.sparkContext.broadcast(model.heavy)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        heavy = pa.array(held.value, type=pa.binary())
        for b in batches:
            for lo, hi in _runs(b.column(0)):
                lens, ids, _, _ = encode_all(b.column(0).slice(lo, hi - lo), heavy)
                cuts = np.concatenate(([0], np.cumsum(lens * 4))).astype("<i4")
                packed = pa.Array.from_buffers(pa.binary(), len(lens), [None, pa.py_buffer(cuts), pa.py_buffer(ids)])
                yield pa.RecordBatch.from_arrays([packed, b.column(1).slice(lo, hi - lo)], names=["ids", "drawn"])

    return texts.mapInArrow(run, "ids binary, drawn boolean")


def _packed(sums: np.ndarray, kind: str, first: int = 0) -> list[tuple[int, bytes, bytes]]:
    """Rows of ``sums`` that are not all zero, by blocks of BLOCK classes: (block, places in it, values)."""
    out = []
    for at in range(0, len(sums), BLOCK):
        part = sums[at: at + BLOCK]
        full = np.flatnonzero(part.any(axis=1))
        if len(full):
            out.append((first + at // BLOCK, full.astype("<u2").tobytes(), part[full].astype(kind).tobytes()))
    return out


def _blocks(rows: list[tuple[int, bytes, bytes]]) -> pa.RecordBatch:
    block, at, sums = zip(*rows, strict=True) if rows else ((), (), ())
    return pa.RecordBatch.from_arrays([pa.array(block, pa.int32()), pa.array(at, pa.binary()), pa.array(sums, pa.binary())], names=["block", "at", "sums"])


def train_pass(ids: DataFrame, model: Model, p: Params) -> float | None:
    """One Baum-Welch iteration over every text of ``ids``; expected counts are added up by blocks of classes across partitions.

    Returns the natural log-likelihood of the texts before it, none where there is no text.
    """
    spark, h = ids.sparkSession, p.states
    held = spark.sparkContext.broadcast((model.start, model.move, model.emit))
    ship(spark)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        start, move, emit = held.value
        sums, room = None, sys.__dict__.setdefault("_corpusmap_hmm", {})  # the worker's next task finds it
        seqs, size = [], 0

        def add():
            got = document_counts(seqs, start, move, emit, p.segment, room)
            return got if sums is None else tuple(a + b for a, b in zip(sums, got, strict=True))

        for b in batches:
            for t in b.column(0):
                seqs.append(np.frombuffer(t.as_buffer(), dtype="<i4"))
                size += len(seqs[-1])
                if size >= BUFFER:
                    sums = add()
                    seqs, size = [], 0
        if seqs:
            sums = add()
        if sums is not None:
            whole = np.concatenate((sums[0], sums[1].ravel(), [sums[3]]))
            yield _blocks([(-1, b"", whole.astype("<f8").tobytes())])
            yield _blocks(_packed(np.ascontiguousarray(sums[2]), "<f4"))  # of one task; they are added up in double precision

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        whole, held_sums = None, {}
        for batch in batches:
            for block, at, part in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if block < 0:
                    part = np.frombuffer(part, dtype="<f8")
                    whole = part if whole is None else whole + part
                else:
                    into = held_sums.setdefault(block, np.zeros((BLOCK, h)))
                    into[np.frombuffer(at, dtype="<u2")] += np.frombuffer(part, dtype="<f4").reshape(-1, h)
        if whole is not None:
            yield _blocks([(-1, b"", whole.astype("<f8").tobytes())])
        for block, into in held_sums.items():
            yield _blocks(_packed(into, "<f8", block))

    schema = "block int, at binary, sums binary"
    got = ids.select("ids").mapInArrow(run, schema).repartition("block").mapInArrow(merge, schema).toArrow()
    held.unpersist()
    if not got.num_rows:
        return None
    g_emit = np.zeros((model.classes, h))
    for block, at, part in zip(*(c.to_pylist() for c in got.columns), strict=True):
        part = np.frombuffer(part, dtype="<f8")
        if block < 0:
            g_start, g_move, gain = part[:h], part[h:-1].reshape(h, h), part[-1]
        else:
            g_emit[block * BLOCK + np.frombuffer(at, dtype="<u2")] = part.reshape(-1, h)
    maximise(model, g_start, g_move, g_emit, p.smoothing)
    return float(gain)


def train(docs: DataFrame, p: Params | None = None) -> tuple[Model, DataFrame]:
    """Model and token counts from every row of ``docs`` (columns doc_id and text).

    Null and empty texts are one end each; rows without identifier and
    repeated rows count like any other; texts of any length are read whole. An
    empty table gives a model that knows the end alone.
    """
    p = p or Params()
    texts = docs.select(text_or_empty("text").cast("binary").alias("text"))
    counts = materialize(token_counts(texts), "token-counts")
    model = gather(counts, p)
    random_states(model, p)
    n_docs = int(model.heavy_counts[model.heavy.index(END)])
    drawn = F.pmod(F.xxhash64(F.lit(p.seed), "doc_id", "text"), F.lit(1 << 30)) < int(min(1.0, p.sample_docs / max(n_docs, 1)) * (1 << 30))  # copies are drawn apart
    ids = materialize(encoded(docs.select(text_or_empty("text").cast("binary").alias("text"), drawn.alias("drawn")), model), "class-ids")
    some = materialize(ids.filter("drawn"), "class-ids-drawn")
    for _ in range(p.sample_rounds):
        train_pass(some, model, p)
    last = -np.inf
    for _ in range(p.passes):
        now = train_pass(ids, model, p)
        if now is None or now - last < p.settled * model.tokens:
            break
        last = now
    else:
        raise RuntimeError("the likelihood did not settle")
    release(ids, some)
    return model, counts


def score(docs: DataFrame, model: Model, counts: DataFrame) -> DataFrame:
    """``docs(doc_id, text)`` -> ``(doc_id, n_tokens, n_known, base_score, score)``, one row per row.

    Scores are log10. Null and empty texts are one END. Texts of any length
    are scored whole. Counts of tokens that are not heavy come by a join; a
    row is known by 128 bits, so null and repeated identifiers do no harm.
    """
    spark = docs.sparkSession
    held = spark.sparkContext.broadcast(model)
    text = text_or_empty("text")
    keyed = docs.select("doc_id", *row_key(F.col("doc_id"), text), text.cast("binary").alias("text"))
    names = ["doc_id", "k1", "k2", "token", "n_tokens", "n_known", "base", "score"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sys.__dict__.pop("_corpusmap_hmm", None)  # room of the training, which is over
        m = held.value
        heavy, n_heavy = pa.array(m.heavy, type=pa.binary()), len(m.heavy)
        logs = np.concatenate((np.log10(m.heavy_counts + 1.0), np.zeros(TAIL_CLASSES)))
        seen = np.concatenate((m.heavy_counts > 0, np.zeros(TAIL_CLASSES, dtype=bool)))
        inside = np.concatenate((np.zeros(n_heavy), -np.log10(m.tail_tokens + m.tail_types + 1.0)))
        floor = np.log10(m.tokens + m.types + 1.0)

        def out(part: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            lens, flat, rows, tail = encode_all(part.column(3), heavy)
            at = np.concatenate(([0], np.cumsum(lens)[:-1]))
            base = np.add.reduceat(logs[flat], at) - lens * floor
            known = np.add.reduceat(seen[flat].astype(np.int64), at)
            full = forward(np.split(flat, at[1:]), m.start, m.move, m.emit) / np.log(10) + np.add.reduceat(inside[flat], at)
            mark = pa.array([END + k.to_bytes(8, "little", signed=True) for k in part.column(1).to_pylist()], type=pa.binary())  # no token, and spread over the join's keys
            yield pa.RecordBatch.from_arrays([*part.columns[:3], mark, pa.array(lens), pa.array(known), pa.array(base), pa.array(full)], names=names)
            if len(rows):
                r, n = pa.array(rows), len(rows)
                yield pa.RecordBatch.from_arrays([pa.nulls(n, part.column(0).type), part.column(1).take(r), part.column(2).take(r), tail, pa.nulls(n, pa.int64()), pa.nulls(n, pa.int64()), pa.nulls(n, pa.float64()), pa.nulls(n, pa.float64())], names=names)

        for b in batches:
            for lo, hi in _runs(b.column(3)):
                yield from out(b.slice(lo, hi - lo))

    head = keyed.select("doc_id", "k1", "k2").schema.simpleString()[7:-1]
    found = keyed.mapInArrow(run, f"{head}, token binary, n_tokens long, n_known long, base double, score double")
    joined = found.join(counts, "token", "left")
    is_doc = F.col("n_tokens").isNotNull()
    log = F.when(~is_doc, F.log10(F.coalesce("n", F.lit(0)) + 1.0))
    sums = joined.groupBy("k1", "k2").agg(
        F.max("doc_id").alias("doc_id"), F.count("n_tokens").alias("copies"), F.max("n_tokens").alias("n_tokens"), F.max("n_known").alias("heavy_known"),
        F.max("base").alias("base"), F.max("score").alias("score"), F.sum(F.coalesce(log, F.lit(0.0))).alias("log"),
        F.sum(F.when(~is_doc & F.col("n").isNotNull(), 1).otherwise(0)).alias("tail_known"))
    each = F.col("log") / F.col("copies")
    return (sums.select("doc_id", "n_tokens", (F.col("heavy_known") + F.col("tail_known") / F.col("copies")).cast("long").alias("n_known"), (F.col("base") + each).alias("base_score"), (F.col("score") + each).alias("score"), F.explode(F.sequence(F.lit(1).cast("long"), "copies")))
            .drop("col"))


def op1_hmm_language_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    model, counts = train(docs.filter(~held_out(7, 2)))
    return score(docs, model, counts).select("doc_id", held_out(7, 2).alias("held_out"), "n_tokens", "n_known", F.lit(model.tokens).cast("long").alias("train_tokens"), "base_score", "score")
