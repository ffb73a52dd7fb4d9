"""Removal of repeated word windows through a compacted de Bruijn graph.

Nodes are sampled k-mers: the leftmost smallest hash in each window of words,
so equal windows always share their node. Edges are the words from a node to
the next one. A node whose every occurrence has the same two edges does not
branch; a run of such nodes compacts into one path, and all windows inside a
path repeat if the path does. Only windows whose node repeats but branches are
looked at one by one. Each claimed span, path or window, is verified at its
source coordinates by a digest of its words.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpusmap.llm.common import documents, fresh_names, materialize, release, row_key, ship, text_or_empty

WINDOW, NODE_WORDS, CHUNK_WORDS = 35, 10, 1 << 17
U = np.uint64


def _mix(z: np.ndarray) -> np.ndarray:
    z = z ^ (z >> U(33))
    z *= U(0xFF51AFD7ED558CCD)
    z ^= z >> U(33)
    z *= U(0xC4CEB9FE1A85EC53)
    return z ^ (z >> U(33))


class Rolling:
    """Hash of any stretch of a word sequence in constant time (polynomial, modulo 2**64)."""

    def __init__(self, words: np.ndarray, base: int):
        n = len(words)
        inverse = pow(base, -1, 1 << 64)
        power = np.cumprod(np.concatenate((np.ones(1, dtype=U), np.full(n, base, dtype=U))))
        self.back = np.cumprod(np.concatenate((np.ones(1, dtype=U), np.full(n, inverse, dtype=U))))
        self.sums = np.concatenate((np.zeros(1, dtype=U), np.cumsum(words * power[:n], dtype=U)))

    def __call__(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return _mix((self.sums[end] - self.sums[start]) * self.back[start])


class Chunk:
    """Some whole documents, their windows and nodes."""

    def __init__(self, rows: list[int], words: list[list[bytes]], window: int, k: int, seed: int):
        import xxhash

        self.rows, self.words, self.window = rows, words, window
        digest = xxhash.xxh3_64_intdigest
        self.offset = np.concatenate(([0], np.cumsum([len(w) for w in words]))).astype(np.int64)
        n = int(self.offset[-1])
        flat = np.fromiter((digest(x, seed) for w in words for x in w), dtype=U, count=n)
        rng = np.random.default_rng(seed)
        self.one, self.two = (Rolling(flat, int(b) | 1) for b in rng.integers(1 << 61, 1 << 62, 2))
        doc = np.repeat(np.arange(len(words)), np.diff(self.offset))
        empty = np.zeros(0, dtype=np.int64)
        self.start = self.node = self.pos = self.doc = self.h = self.ctx = self.lo = self.hi = empty
        if n < window:
            return
        at = np.arange(n - k + 1)
        kmer = self.one(at, at + k)
        low, span, step = at, window - k + 1, 1
        while 2 * step <= span:
            low = self._leftmost(kmer, low, step)
            step *= 2
        if span > step:
            low = self._leftmost(kmer, low, span - step)
        whole = self.offset[1:][doc[: n - window + 1]] >= np.arange(n - window + 1) + window
        self.start = np.flatnonzero(whole)
        low = low[: n - window + 1][whole]
        if not len(low):
            return
        new = np.concatenate(([True], low[1:] != low[:-1]))
        self.node = np.cumsum(new) - 1  # of each window
        self.pos = low[new]
        self.doc = doc[self.pos]
        same = self.doc[1:] == self.doc[:-1]
        no = np.zeros(1, dtype=bool)
        before, after = np.concatenate((no, same)), np.concatenate((same, no))
        self.lo = np.where(before, np.concatenate((self.pos[:1], self.pos[:-1])), self.offset[self.doc])
        self.hi = np.where(after, np.concatenate((self.pos[1:], self.pos[-1:])) + k, self.offset[self.doc + 1])
        self.after = after
        self.h = kmer[self.pos]
        shape = (self.pos - self.lo).astype(U) * U(0x9E3779B97F4A7C15) + (self.hi - self.pos).astype(U) * U(0xC2B2AE3D27D4EB4F) + before.astype(U) * U(3) + after.astype(U)
        self.ctx = _mix(self.one(self.lo, self.hi) + shape) ^ self.two(self.lo, self.hi)

    @staticmethod
    def _leftmost(kmer: np.ndarray, low: np.ndarray, step: int) -> np.ndarray:
        a, b = low[:-step], low[step:]
        return np.where(kmer[a] <= kmer[b], a, b)


def _chunks(texts: list, window: int, k: int, seed: int) -> Iterator[Chunk]:
    rows, words, n = [], [], 0
    for i, t in enumerate(texts):
        w = t.split()
        rows.append(i)
        words.append(w)
        n += len(w)
        if n >= CHUNK_WORDS:
            yield Chunk(rows, words, window, k, seed)
            rows, words, n = [], [], 0
    if rows:
        yield Chunk(rows, words, window, k, seed)


def _signed(x: np.ndarray) -> pa.Array:
    return pa.array(x.astype(U).view(np.int64))


def _keyed(docs: DataFrame) -> DataFrame:
    """Rows are known by 128 bits of doc_id and text; rows that share them are equal and share their fate."""
    text = text_or_empty("text")
    keys = row_key(F.col("doc_id"), text)
    return docs.select("doc_id", keys[0].alias("r1"), keys[1].alias("r2"), text.cast("binary").alias("text"))


def node_occurrences(keyed: DataFrame, window: int, k: int, seed: int) -> DataFrame:
    """``(r1, r2, pos, h, ctx)``: the nodes of every document and a hash of the two edges at each."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for c in _chunks(b.column(2).to_pylist(), window, k, seed):
                row = pa.array(np.array(c.rows, dtype=np.int64)[c.doc])
                pos = pa.array((c.pos - c.offset[c.doc]).astype(np.int32))
                yield pa.RecordBatch.from_arrays([b.column(0).take(row), b.column(1).take(row), pos, _signed(c.h), _signed(c.ctx)], names=["r1", "r2", "pos", "h", "ctx"])

    return keyed.select("r1", "r2", "text").mapInArrow(run, "r1 long, r2 long, pos int, h long, ctx long")


def _digest(words: list[bytes]) -> bytes:
    return hashlib.sha256(b" ".join(words)).digest()


def _paths(joined: DataFrame, window: int, k: int, seed: int) -> DataFrame:
    """Second pass, over ``(doc_id, r1, r2, text, nodes array<struct<pos,solid>>)``.

    Gives four kinds of row. 0: a document that is settled (n_words,
    n_removed, sha, spans). 1: one that waits for windows (text, spans). 2: such a
    window (start, k1, k2). 3: a path (k1 names it, sha of its words).
    """
    names = ["doc_id", "r1", "r2", "kind", "n_words", "n_removed", "start", "k1", "k2", "sha", "text", "spans"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            heads, texts, lists = b.columns[:3], b.column(3).to_pylist(), b.column(4)
            for c in _chunks(texts, window, k, seed):
                repeated, solid = np.zeros(len(c.pos), dtype=bool), np.zeros(len(c.pos), dtype=bool)
                edge = np.searchsorted(c.doc, np.arange(len(c.rows) + 1))
                for i, r in enumerate(c.rows):
                    if lists[r].is_valid and len(lists[r]):
                        got = lists[r].values
                        at = edge[i] + np.searchsorted(c.pos[edge[i]: edge[i + 1]] - c.offset[i], got.field(0).to_numpy(zero_copy_only=False))
                        repeated[at] = True
                        solid[at] = got.field(1).to_numpy(zero_copy_only=False)
                linked = np.zeros(len(c.pos), dtype=bool)
                linked[1:] = solid[1:] & solid[:-1] & (c.doc[1:] == c.doc[:-1])
                first = np.flatnonzero(solid & ~linked)
                run_of = np.cumsum(solid & ~linked) - 1
                last = np.flatnonzero(solid & ~np.concatenate((linked[1:], np.zeros(1, dtype=bool)))) if len(solid) else first
                lo, hi = c.lo[first], c.hi[last]
                cover = np.zeros(len(c.start), dtype=bool)
                on = np.flatnonzero(solid[c.node]) if len(c.node) else np.zeros(0, dtype=np.int64)
                run_at = run_of[c.node[on]]
                cover[on] = (c.start[on] >= lo[run_at]) & (c.start[on] + window <= hi[run_at])
                rest = c.start[repeated[c.node] & ~cover] if len(c.node) else c.start
                owner = np.searchsorted(c.offset, rest, side="right") - 1
                waits = set(owner.tolist())
                spans: dict[int, list[list[int]]] = {}
                rows: list[tuple] = []
                for f, s, e in zip(first.tolist(), lo.tolist(), hi.tolist(), strict=True):
                    d, o = int(c.doc[f]), int(c.offset[c.doc[f]])
                    if e - s >= window:
                        spans.setdefault(d, []).append([s - o, e - o])
                        rows.append((c.rows[d], 3, None, None, s - o, int(c.h[f:f + 1].view(np.int64)[0]), None, _digest(c.words[d][s - o:e - o]), None, None))
                for d, r in enumerate(c.rows):
                    if d in waits:
                        rows.append((r, 1, None, None, None, None, None, None, texts[r], spans.get(d, [])))
                    else:
                        n, gone, sha, cut = _kept(c.words[d], spans.get(d, []))
                        rows.append((r, 0, n, gone, None, None, None, sha, None, cut))
                if rows:
                    cols = list(zip(*rows, strict=True))
                    types = [pa.int32(), pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.binary(), pa.binary(), pa.list_(pa.list_(pa.int32()))]
                    row = pa.array(cols[0])
                    yield pa.RecordBatch.from_arrays([*(x.take(row) for x in heads), *(pa.array(v, type=t) for v, t in zip(cols[1:], types, strict=True))], names=names)
                if len(rest):
                    row, n = pa.array(np.array(c.rows, dtype=np.int64)[owner]), len(rest)
                    no = [pa.nulls(n, t) for t in (pa.int64(), pa.int64())]
                    yield pa.RecordBatch.from_arrays([*(x.take(row) for x in heads), pa.array(np.full(n, 2, dtype=np.int32)), *no, pa.array((rest - c.offset[owner]).astype(np.int32)), _signed(c.one(rest, rest + window)), _signed(c.two(rest, rest + window)), pa.nulls(n, pa.binary()), pa.nulls(n, pa.binary()), pa.nulls(n, pa.list_(pa.list_(pa.int32())))], names=names)

    head = joined.select("doc_id", "r1", "r2").schema.simpleString()[7:-1]
    return joined.mapInArrow(run, f"{head}, kind int, n_words long, n_removed long, start int, k1 long, k2 long, sha binary, text binary, spans array<array<int>>")


def _stay(n_words: int, spans: list) -> np.ndarray:
    """True for the words that no span covers."""
    gone = np.zeros(n_words + 1, dtype=np.int64)
    for s, e in spans:
        gone[s] += 1
        gone[e] -= 1
    return np.cumsum(gone[:-1]) == 0


def _kept(words: list[bytes], spans: list) -> tuple[int, int, bytes, list[list[int]]]:
    """Words, words removed, digest of what is left, and the spans that go, apart and ascending."""
    if not spans:
        return len(words), 0, _digest(words), []
    stay = _stay(len(words), spans)
    edge = np.flatnonzero(np.diff(np.concatenate(([True], stay, [True])).astype(np.int8)))
    return len(words), int((~stay).sum()), _digest([w for w, k in zip(words, stay.tolist(), strict=True) if k]), edge.reshape(-1, 2).tolist()


def _finish(waiting: DataFrame, window: int) -> DataFrame:
    """``(doc_id, r1, r2, text, spans, starts)`` -> the settled rows, and a row ``(k1, k2, d1, d2, d3, d4)`` for every repeated window, read at its source.

    The digest of a window comes as four longs, which a hash aggregate can hold. ``k1`` is null in settled rows only.
    """
    marks = ["k1", "k2", "d1", "d2", "d3", "d4"]
    names = ["doc_id", "r1", "r2", "n_words", "n_removed", "sha", "spans", *marks]
    kinds = [pa.int64(), pa.int64(), pa.binary(), pa.list_(pa.list_(pa.int32()))]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, 256):
                part = b.slice(at, 256)
                out, keys, digests = [], [], []
                for t, spans, starts in zip(part.column(3), part.column(4).to_pylist(), part.column(5), strict=True):
                    words, first = t.as_py().split(), []
                    if starts.is_valid and len(starts):
                        first, *key = (starts.values.field(i).to_numpy(zero_copy_only=False) for i in range(3))
                        first = first.tolist()
                        keys.append(key)
                        digests += [_digest(words[i: i + window]) for i in first]
                    out.append(_kept(words, [*spans, *([i, i + window] for i in first)]))
                cols = zip(*out, strict=True) if out else ((), (), (), ())
                yield pa.RecordBatch.from_arrays([*part.columns[:3], *(pa.array(x, type=k) for x, k in zip(cols, kinds, strict=True)), *(pa.nulls(len(out), pa.int64()) for _ in marks)], names=names)
                if keys:
                    n, told = len(digests), np.frombuffer(b"".join(digests), dtype="<i8").reshape(-1, 4)
                    heads = [pa.nulls(n, x.type) for x in part.columns[:3]]
                    yield pa.RecordBatch.from_arrays([*heads, *(pa.nulls(n, k) for k in kinds), *(pa.array(np.concatenate([k[i] for k in keys])) for i in (0, 1)), *(pa.array(told[:, i]) for i in range(4))], names=names)

    head = waiting.select("doc_id", "r1", "r2").schema.simpleString()[7:-1]
    return waiting.mapInArrow(run, f"{head}, n_words long, n_removed long, sha binary, spans array<array<int>>, {', '.join(f'{m} long' for m in marks)}")


def _any(rows: DataFrame) -> bool:
    """Whether there is a row; through a written table, so that the shuffle files of the question go at once."""
    asked = materialize(rows.select(F.lit(1).alias("one")).limit(1), "any")
    try:
        return bool(asked.collect())
    finally:
        release(asked)


def remove_repeats(docs: DataFrame, window: int = WINDOW, k: int = NODE_WORDS, seeds: tuple = (11, 12, 13)) -> DataFrame:
    """``(doc_id, r1, r2, n_words, n_removed, sha binary, spans array<array<int>>)``, one row per row of ``docs``.

    A word goes if a window of ``window`` words over it starts elsewhere too,
    in any document. ``spans`` are the first word of each removed stretch and
    the one after its last. Null and empty texts have no words; texts shorter
    than a window lose none. Repeated rows repeat each other's windows. ``sha``
    is SHA-256 over the kept words, joined by one space; ``r1, r2`` are the
    row's key. An empty table gives an empty result. If a path or window fails
    its verification (different words under one fingerprint) the next seed is
    used.
    """
    spark = docs.sparkSession
    ship(spark)
    keyed = _keyed(docs)
    for seed in seeds:
        seen = materialize(node_occurrences(keyed, window, k, seed), "occurrences")  # read twice
        nodes = (seen.groupBy("h").agg(F.count(F.lit(1)).alias("n"), F.min("ctx").alias("a"), F.max("ctx").alias("b"))
                 .filter("n > 1").select("h", (F.col("a") == F.col("b")).alias("solid")))
        nodes = materialize(nodes, "nodes")  # a table of its own: joins with it can be split where a node is hot
        lists = seen.drop("ctx").join(nodes, "h").groupBy("r1", "r2").agg(F.array_sort(F.collect_set(F.struct("pos", "solid"))).alias("nodes"))
        joined = keyed.join(lists, ["r1", "r2"], "left").select("doc_id", "r1", "r2", "text", "nodes")
        found = materialize(_paths(joined, window, k, seed), "paths")
        release(seen, nodes)
        paths = found.filter("kind = 3").groupBy("k1").agg(F.min("sha").alias("a"), F.max("sha").alias("b"), F.count(F.lit(1)).alias("n"))
        if _any(paths.filter("a <> b or n < 2")):
            release(found)
            continue
        windows = found.filter("kind = 2").select("r1", "r2", "start", "k1", "k2")
        twice = materialize(windows.groupBy("k1", "k2").agg(F.count(F.lit(1)).alias("n")).filter("n > 1").drop("n"), "windows")
        starts = materialize(windows.join(twice, ["k1", "k2"]).groupBy("r1", "r2").agg(F.collect_set(F.struct("start", "k1", "k2")).alias("starts")), "starts")
        waiting = found.filter("kind = 1").select("doc_id", "r1", "r2", "text", "spans").join(starts, ["r1", "r2"], "left").select("doc_id", "r1", "r2", "text", "spans", "starts")
        ended = materialize(_finish(waiting, window), "ended")
        release(twice, starts)
        told = ended.filter("k1 is not null").groupBy("k1", "k2").agg(*[f(f"d{i}").alias(f"{n}{i}") for i in range(1, 5) for n, f in (("a", F.min), ("b", F.max))])
        if not _any(told.filter(" or ".join(f"a{i} <> b{i}" for i in range(1, 5)))):
            break
        release(found, ended)
    else:
        raise RuntimeError("paths and windows could not be verified with any seed")
    names = ["doc_id", "r1", "r2", "n_words", "n_removed", "sha", "spans"]
    return found.filter("kind = 0").select(*names).unionByName(ended.filter("k1 is null").select(*names))


def without_repeats(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """``docs`` with the words of repeated windows cut from ``text``; rows and columns unchanged, whatever their names.

    A text that loses words is its kept words, joined by one space; any other
    is left as it is, null too. Rows are met by their key in the shuffle.
    """
    r1, r2, cut = fresh_names(docs, "r1", "r2", "spans")
    keys = row_key(F.col("doc_id"), text_or_empty("text"))
    lost = materialize(remove_repeats(docs, window).filter("n_removed > 0").select(F.col("r1").alias(r1), F.col("r2").alias(r2), F.col("spans").alias(cut)).dropDuplicates([r1, r2]), "repeats")
    met = docs.withColumns({r1: keys[0], r2: keys[1]}).join(lost, [r1, r2], "left")

    @F.pandas_udf("string")
    def rest(text, spans):
        import pandas

        out = []
        for t, s in zip(text, spans, strict=True):
            words = t.encode().split()
            out.append(b" ".join(w for w, k in zip(words, _stay(len(words), s).tolist(), strict=True) if k).decode())
        return pandas.Series(out, dtype=object)

    changed = met.filter(F.col(cut).isNotNull()).withColumn("text", rest("text", cut))
    return met.filter(F.col(cut).isNull()).select(*docs.columns).unionByName(changed.select(*docs.columns))


def op2_debruijn_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(documents(spark, sf_dir)).select("doc_id", "n_words", "n_removed", F.lower(F.hex("sha")).alias("kept_sha256"))


#: DuckDB: every window as a string
OP2_SQL = r"""
WITH d AS (
  SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS (
  SELECT doc_id, i, md5(array_to_string(w[i : i + 34], ' ')) AS h
  FROM (SELECT doc_id, w, unnest(range(1, len(w) - 33)) AS i FROM d WHERE len(w) >= 35)),
r AS (SELECT h FROM s GROUP BY h HAVING count(*) > 1),
gone AS (
  SELECT DISTINCT doc_id, unnest(range(i, i + 35)) AS j FROM s WHERE h IN (SELECT h FROM r)),
word AS (SELECT doc_id, unnest(range(1, len(w) + 1)) AS j, unnest(w) AS x FROM d WHERE len(w) > 0),
kept AS (
  SELECT doc_id, count(*) AS n_kept, string_agg(x, ' ' ORDER BY j) AS t
  FROM word WHERE NOT EXISTS (SELECT 1 FROM gone WHERE gone.doc_id = word.doc_id AND gone.j = word.j)
  GROUP BY doc_id)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(len(w) - coalesce(n_kept, 0) AS BIGINT) AS n_removed,
       sha256(coalesce(t, '')) AS kept_sha256
FROM d LEFT JOIN kept USING (doc_id)
"""
