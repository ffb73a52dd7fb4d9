"""Embedding near-duplicates by an epsilon grid order join.

Unit vectors at cosine c are sqrt(2 - 2c) apart, and projections on orthogonal
axes are never further apart than the vectors. Vectors are sorted by label and
by the grid cells of their leading principal coordinates (cell width epsilon),
the order is cut into blocks, and blocks whose boxes lie further apart than
epsilon are never joined. In a pair of blocks, intervals of the sequence are
halved and skipped in the same way before anything is multiplied.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpusmap.llm.common import materialize, ship
from corpusmap.llm.components import connected_components

BLOCK_BYTES, LEAF, AXES, SLACK = 1 << 20, 64, 12, 1e-9
BANDED = (256, 65_536)  # blocks from which on boxes are banded by two axes, by three


def unit(v: np.ndarray) -> np.ndarray:
    v = v.astype(np.float64)
    v = v / np.abs(v).max(axis=1, keepdims=True)  # no overflow or underflow in the squares
    return v / np.sqrt((v * v).sum(axis=1, keepdims=True))


def principal_axes(vectors: DataFrame, axes: int) -> np.ndarray:
    """Leading eigenvectors of the second moments over all vectors: sums of a square matrix per task, added up."""
    def moments(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = None
        for b in batches:
            if b.num_rows:
                dims = len(b.column(0)[0])
                v = unit(b.column(0).flatten().to_numpy(zero_copy_only=False).reshape(-1, dims))
                total = v.T @ v if total is None else total + v.T @ v
        if total is not None:
            n = total.shape[0]
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(np.arange(n), n)), pa.array(np.tile(np.arange(n), n)), pa.array(total.ravel())], names=["i", "j", "x"])

    got = vectors.select("v").mapInArrow(moments, "i long, j long, x double").groupBy("i", "j").agg(F.sum("x")).collect()  # dimensions squared
    if not got:
        return np.zeros((0, 0))
    n = max(r[0] for r in got) + 1
    m = np.zeros((n, n))
    for i, j, x in got:
        m[i, j] = x
    return np.linalg.eigh(m)[1][:, ::-1][:, : min(axes, n)].copy()


def _apart(lo_a, hi_a, lo_b, hi_b) -> float:
    gap = np.maximum(0.0, np.maximum(lo_a - hi_b, lo_b - hi_a))
    return float((gap * gap).sum())


def join_intervals(va, pa_, vb, pb, cosine: float, same: bool) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Index pairs at or above ``cosine``; halves intervals of both sequences, skipping distant ones.

    With ``same`` the sequences are one and a pair is given once, smaller index first.
    """
    reach = 2 - 2 * cosine + SLACK
    todo = [(0, len(va), 0, len(vb))]
    while todo:
        a0, a1, b0, b1 = todo.pop()
        if a0 == a1 or b0 == b1 or same and b1 <= a0 + 1:
            continue
        if _apart(pa_[a0:a1].min(0), pa_[a0:a1].max(0), pb[b0:b1].min(0), pb[b0:b1].max(0)) > reach:
            continue
        if a1 - a0 <= LEAF and b1 - b0 <= LEAF:
            dots = va[a0:a1] @ vb[b0:b1].T
            i, j = np.nonzero(dots >= cosine - SLACK)
            i, j = i + a0, j + b0
            if same:
                i, j = i[i < j], j[i < j]
            close = dots[i - a0, j - b0] < cosine + SLACK  # too near to the threshold for a product whose order of sums is open
            if close.any():
                ok = np.ones(len(i), dtype=bool)
                for n in np.flatnonzero(close):
                    ok[n] = math.fsum(va[i[n]] * vb[j[n]]) >= cosine
                i, j = i[ok], j[ok]
            if len(i):
                yield i, j
        else:
            am, bm = ((a0 + a1) // 2 if a1 - a0 > LEAF else a1), ((b0 + b1) // 2 if b1 - b0 > LEAF else b1)
            todo += [(x, y, z, w) for x, y in ((a0, am), (am, a1)) for z, w in ((b0, bm), (bm, b1))]


def _blocks(ordered: DataFrame, axes: np.ndarray, block: int, kind: str) -> DataFrame:
    """Consecutive vectors of one key as a row: nodes, weights, vectors as bytes of ``kind``, box of the projections."""
    names, dims = ["key", "nodes", "weights", "raw", "lo", "hi"], axes.shape[0]
    whole, real = pa.list_(pa.int64()), pa.list_(pa.float64())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []

        def out() -> pa.RecordBatch:
            node, weight, v = (np.concatenate([h[i] for h in held]) for i in (1, 2, 3))
            p = unit(v) @ axes
            return pa.RecordBatch.from_arrays([pa.array([held[0][0]], type=pa.string()), pa.array([node], type=whole), pa.array([weight], type=whole), pa.array([v.astype(kind).tobytes()], type=pa.binary()), pa.array([p.min(0)], type=real), pa.array([p.max(0)], type=real)], names=names)

        for b in batches:
            key = b.column(0).to_pylist()
            node, weight = (b.column(i).to_numpy(zero_copy_only=False) for i in (1, 2))
            v = b.column(3).flatten().to_numpy(zero_copy_only=False).reshape(-1, dims)
            at = 0
            while at < len(key):
                to = next((i for i in range(at, len(key)) if key[i] != key[at]), len(key))
                while at < to:
                    if held and (held[0][0] != key[at] or sum(len(h[1]) for h in held) >= block):
                        yield out()
                        held = []
                    n = min(to - at, block - sum(len(h[1]) for h in held))
                    held.append((key[at], node[at: at + n], weight[at: at + n], v[at: at + n]))
                    at += n
        if held:
            yield out()

    return ordered.select("key", "node", "weight", "v").mapInArrow(run, "key string, nodes array<long>, weights array<long>, raw binary, lo array<double>, hi array<double>")


def block_pairs(boxes: DataFrame, width: float, n_axes: int) -> DataFrame:
    """``(block, block2)`` of one key whose boxes lie no further apart than ``width``, from ``boxes(key, block, lo, hi)``.

    Boxes meet in the cells that both cover, on one axis or more as blocks
    become many. The left one also covers the cells beyond its ends, so boxes
    within reach always share one.
    """
    n_blocks = boxes.count()
    by = min(n_axes, 1 + sum(n_blocks >= b for b in BANDED))
    left, right = boxes, boxes.select("key", F.col("block").alias("block2"), F.col("lo").alias("lo2"), F.col("hi").alias("hi2"))
    cell = lambda c, i: F.floor(F.col(c)[i] / width)
    for i in range(by):
        left = left.withColumn(f"s{i}", F.explode(F.sequence(cell("lo", i) - 1, cell("hi", i) + 1)))
        right = right.withColumn(f"s{i}", F.explode(F.sequence(cell("lo2", i), cell("hi2", i))))
    gap = F.zip_with(F.zip_with("lo", "hi2", lambda x, y: x - y), F.zip_with("lo2", "hi", lambda x, y: x - y), lambda x, y: F.greatest(x, y, F.lit(0.0)))
    far = F.aggregate(gap, F.lit(0.0), lambda s, x: s + x * x)
    met = left.join(right, ["key", *(f"s{i}" for i in range(by))]).filter("block <= block2").filter(far <= width * width)
    return met.select("block", "block2").distinct()


def _join_blocks(pairs: DataFrame, axes: np.ndarray, cosine: float, kind: str) -> DataFrame:
    """Per pair of blocks: how many links each vector has there (weighted), and links that keep connectivity."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        dims = axes.shape[0]
        read = lambda x: unit(np.frombuffer(x, dtype=kind).reshape(-1, dims))
        for b in batches:
            for n_a, w_a, r_a, n_b, w_b, r_b, same in zip(*(b.column(i) for i in range(7)), strict=True):
                same, n_a, w_a, n_b, w_b = same.as_py(), *(x.values.to_numpy() for x in (n_a, w_a, n_b, w_b))
                va = read(r_a.as_buffer())
                vb = va if same else read(r_b.as_buffer())
                nodes, weight = (n_a, w_a) if same else (np.concatenate((n_a, n_b)), np.concatenate((w_a, w_b)))
                shift, links, top, edges = 0 if same else len(n_a), np.zeros(len(nodes), dtype=np.int64), list(range(len(nodes))), []

                def root(x: int, top=top) -> int:
                    while top[x] != x:
                        top[x] = top[top[x]]
                        x = top[x]
                    return x

                pa_ = va @ axes
                for i, j in join_intervals(va, pa_, vb, pa_ if same else vb @ axes, cosine, same):
                    j = j + shift
                    np.add.at(links, i, weight[j])
                    np.add.at(links, j, weight[i])
                    for x, y in zip(i.tolist(), j.tolist(), strict=True):
                        p, q = root(x), root(y)
                        if p != q:
                            top[max(p, q)] = min(p, q)
                            edges.append((x, y))
                full = np.flatnonzero(links)
                a = np.concatenate((nodes[full], nodes[[e[0] for e in edges]] if edges else nodes[:0]))
                to = np.concatenate((nodes[full], nodes[[e[1] for e in edges]] if edges else nodes[:0]))
                n = np.concatenate((links[full], np.zeros(len(edges), dtype=np.int64)))
                yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(to), pa.array(n)], names=["a", "b", "n"])

    return pairs.mapInArrow(run, "a long, b long, n long")


def cosine_classes(vectors: DataFrame, cosine: float = 0.98, block: int | None = None, axes: int = AXES, report: dict | None = None) -> DataFrame:
    """``vectors(vec_id, embedding, label)`` -> ``(vec_id, n_links, component_id, kept)``, one row per row.

    Only equal labels that are not null are compared, in double precision.
    Vectors that are null, empty, zero or hold a null or non-finite component
    link with nothing. Vectors of different length never link. Equal vectors
    are one node of the join with a weight, so copies cost nothing more; their
    links are all counted. Repeated rows with one vec_id are separate vectors.
    An empty table gives an empty result; other columns are ignored.

    ``block`` is the vectors of a block (default: ``BLOCK_BYTES`` of them).
    ``report`` receives blocks, pairs of blocks of one label, and the pairs
    that were joined.
    """
    spark = vectors.sparkSession
    ship(spark)
    c = F.col
    kind = "<f4" if vectors.schema["embedding"].dataType.simpleString() == "array<float>" else "<f8"  # as exact as what was given
    v = c("embedding").cast("array<double>")
    fit = (c("label").isNotNull() & v.isNotNull() & F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists(v, lambda x: x != 0))
    # -0.0 and 0.0 are one value in a vector
    rows = vectors.select("vec_id", c("label").cast("string").alias("label"), F.transform(v, lambda x: x + F.lit(0.0)).alias("v"), F.coalesce(fit, F.lit(False)).alias("fit"))
    key = F.when(c("fit"), F.concat_ws(":", F.size("v").cast("string"), "label"))  # vectors of one length and label
    rows = rows.select("vec_id", F.when(c("fit"), c("v")).alias("v"), key.alias("key"), *[F.when(c("fit"), F.xxhash64(F.lit(n), key, "v")).alias(f"h{n}") for n in (1, 2)], F.monotonically_increasing_id().alias("row"))
    rows = materialize(rows, "vectors")
    found = rows.filter("key is not null").groupBy("h1", "h2").agg(F.min("row").alias("node"), F.count(F.lit(1)).alias("weight"), F.first("key").alias("key"), F.first("v").alias("v"))
    dims = rows.agg(F.max(F.size("v"))).first()[0]
    if dims is None or dims < 1:
        return rows.select("vec_id", F.lit(0).cast("long").alias("n_links"), c("vec_id").alias("component_id"), F.lit(True).alias("kept"))
    # zeros behind a shorter vector change no angle, and lengths are never mixed
    found = materialize(found.withColumn("v", F.concat("v", F.array_repeat(F.lit(0.0), F.lit(dims) - F.size("v")))), "vector-nodes")
    block = block or max(256, BLOCK_BYTES // (int(kind[2]) * dims))
    basis = principal_axes(found, axes)
    width = math.sqrt(2 - 2 * cosine + SLACK)
    norm = F.sqrt(F.aggregate("v", F.lit(0.0), lambda s, x: s + x * x))
    cells = [f"c{i}" for i in range(min(6, basis.shape[1]))]
    cell = [F.floor(F.aggregate(F.zip_with("v", F.array(*[F.lit(float(x)) for x in basis[:, i]]), lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x) / norm / width) for i in range(len(cells))]
    ordered = found.withColumns(dict(zip(cells, cell, strict=True))).repartitionByRange("key", *cells, "node").sortWithinPartitions("key", *cells, "node")
    held = materialize(_blocks(ordered, basis, block, kind).withColumn("block", F.monotonically_increasing_id()), "vector-blocks")
    near = materialize(block_pairs(held.select("key", "block", "lo", "hi"), width, basis.shape[1]), "vector-pairs")
    if report is not None:
        per = held.groupBy("key").count().agg(F.sum("count"), F.sum(c("count") * (c("count") + 1) / 2)).first()
        report.update(blocks=per[0], possible=int(per[1]), joined=near.count())
    a = held.select("block", "nodes", "weights", "raw")
    b = held.select(c("block").alias("block2"), c("nodes").alias("nodes2"), c("weights").alias("weights2"), c("raw").alias("raw2"))
    pairs = near.join(a, "block").join(b, "block2").select("nodes", "weights", "raw", "nodes2", "weights2", "raw2", (c("block") == c("block2")).alias("same"), "block", "block2")
    pairs = pairs.repartition(F.xxhash64("block", "block2")).drop("block", "block2")
    joined = materialize(_join_blocks(pairs, basis, cosine, kind), "vector-links")
    n_links = joined.filter("a = b").groupBy(c("a").alias("node")).agg(F.sum("n").alias("n"))
    tops = connected_components(joined.filter("a <> b").select("a", "b")).withColumnRenamed("id", "node")
    facts = found.select("h1", "h2", "node", "weight").join(n_links, "node", "left").join(tops, "node", "left").select("h1", "h2", (F.coalesce("n", F.lit(0)) + c("weight") - 1).alias("n_links"), F.coalesce("component", "node").alias("class"))
    placed = materialize(rows.select("vec_id", "h1", "h2").join(materialize(facts, "vector-facts"), ["h1", "h2"], "left"), "vector-placed")
    least = placed.filter("class is not null").groupBy("class").agg(F.min("vec_id").alias("component_id"))
    out = placed.join(materialize(least, "vector-least"), "class", "left")
    top = F.coalesce("component_id", "vec_id")
    return out.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), top.alias("component_id"), (c("vec_id") == top).alias("kept"))


def op10_epsilon_grid_neardup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cosine_classes(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))


#: DuckDB: all pairs
OP10_SQL = r"""
WITH RECURSIVE v AS (
  SELECT vec_id, label, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings
  WHERE label IS NOT NULL AND embedding IS NOT NULL),
u AS (SELECT *, sqrt(list_sum(list_transform(e, lambda x: x * x))) AS n FROM v),
l AS (
  SELECT a.vec_id AS a, b.vec_id AS b FROM u a JOIN u b ON a.label = b.label AND a.vec_id <> b.vec_id
  WHERE a.n > 0 AND b.n > 0 AND isfinite(a.n) AND isfinite(b.n) AND list_dot_product(a.e, b.e) / (a.n * b.n) >= 0.98),
reach(a, b) AS (SELECT a, b FROM l UNION SELECT reach.a, l.b FROM reach JOIN l ON reach.b = l.a),
top AS (SELECT a, least(a, min(b)) AS component_id FROM reach GROUP BY a),
deg AS (SELECT a, count(*) AS n_links FROM l GROUP BY a)
SELECT vec_id, coalesce(n_links, 0) AS n_links, coalesce(component_id, vec_id) AS component_id,
       vec_id = coalesce(component_id, vec_id) AS kept
FROM embeddings LEFT JOIN top ON top.a = vec_id LEFT JOIN deg ON deg.a = vec_id
"""
