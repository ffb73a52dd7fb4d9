"""SimHash near-duplicate classes through a byte-position inverted index with count filtering.

A fingerprint has eight bytes. Two fingerprints at most three bits apart
differ in at most three bytes, so at least five positional bytes are shared.
Split into two halves of four bytes, one half then shares three bytes or more;
posting lists are kept for the eight (position triple, three bytes) keys. In a
list, the shared positional bytes of each pair are tallied, pairs below five
are dropped, the rest verified on their bits. Lists longer than a bound are
cut into blocks that meet pairwise in separate tasks, so nothing is capped.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpusmap.llm.common import documents, keep_by_fate, materialize, row_key, ship, text_or_empty
from corpusmap.llm.components import connected_components

#: fixed values: three of the four positions in either half
TRIPLES = tuple((h, h + i, h + j, h + k) for h in (0, 4) for i, j, k in ((0, 1, 2), (0, 1, 3), (0, 2, 3), (1, 2, 3)))
SMALL = 32


def majority_bits(hashes: np.ndarray) -> int:
    """The bits that are set in over half of 64-bit hashes."""
    counts = np.zeros(64, dtype=np.int64)
    for at in range(0, len(hashes), 1 << 16):
        part = np.ascontiguousarray(hashes[at: at + (1 << 16)]).view(np.uint8).reshape(-1, 8)
        counts += np.unpackbits(part, axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    over = (2 * counts > len(hashes)).astype(np.uint8)
    return int(np.packbits(over, bitorder="little").view("<u8")[0])


def fingerprint(text: bytes, shingle: int = 3, seed: int = 42) -> int:
    """The 64-bit SimHash of word shingles; no word gives zero."""
    import xxhash

    words = text.lower().split()  # bytes: folds A-Z only, splits on the six separators
    if not words:
        return 0
    digest = xxhash.xxh64_intdigest
    if len(words) <= shingle:
        hashes = [digest(b" ".join(words), seed)]
    else:
        line = b" ".join(words)
        ends = np.cumsum(np.fromiter(map(len, words), dtype=np.int64, count=len(words)) + 1)
        starts = np.concatenate(([0], ends[:-1]))
        hashes = [digest(line[s:e], seed) for s, e in zip(starts[: len(words) - shingle + 1].tolist(), (ends[shingle - 1:] - 1).tolist(), strict=True)]
    return majority_bits(np.array(hashes, dtype="<u8"))


def with_fingerprints(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", shingle: int = 3) -> DataFrame:
    """``(doc_id, k1, k2, fp long)``: the fingerprint as a signed long and the row's key, one row per input row. Nulls count as empty."""
    ship(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fps = np.array([fingerprint(t.as_py(), shingle) for t in b.column(3)], dtype=np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([*b.columns[:3], pa.array(fps)], names=["doc_id", "k1", "k2", "fp"])

    plain = text_or_empty(text)
    kept = docs.select(F.col(doc_id).alias("doc_id"), *row_key(F.col(doc_id), plain), plain.cast("binary").alias("text"))
    return kept.mapInArrow(run, kept.drop("text").withColumn("fp", F.lit(0).cast("long")).schema)


def _links_in_lists(max_bits: int, min_shared: int):
    """Scan posting lists that arrive sorted by list; emit links that keep each list's connectivity."""

    def near(x: np.ndarray) -> np.ndarray:
        shared = (x.view(np.uint8).reshape(*x.shape, 8) == 0).sum(axis=-1)  # the tally of positional bytes
        ok = shared >= min_shared
        ok[ok] = np.bitwise_count(x[ok]) <= max_bits
        return ok

    def forest(fp, node, block, cross) -> list[tuple[int, int]]:
        """Union-find over one long list; only links that join two sets are emitted."""
        top = np.arange(len(fp))

        def root(i: int) -> int:
            while top[i] != i:
                top[i] = top[top[i]]
                i = top[i]
            return i

        out = []
        for at in range(0, len(fp), 64):
            rows = np.ascontiguousarray(fp[at: at + 64, None] ^ fp[None, at:])
            ok = near(rows)
            if cross:
                ok &= block[at: at + 64, None] != block[None, at:]
            for i, j in zip(*np.nonzero(np.triu(ok, 1))):
                a, b = root(at + int(i)), root(at + int(j))
                if a != b:
                    top[max(a, b)] = min(a, b)
                    out.append((int(node[at + i]), int(node[at + j])))
        return out

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] | None = None

        def table(cols: list[np.ndarray]) -> tuple[pa.RecordBatch, None]:
            t, k, x, y, b, fp, node = cols
            new = np.ones(len(t), dtype=bool)
            new[1:] = (t[1:] != t[:-1]) | (k[1:] != k[:-1]) | (x[1:] != x[:-1]) | (y[1:] != y[:-1])
            starts = np.flatnonzero(new)
            sizes = np.diff(np.append(starts, len(t)))
            group = np.repeat(np.arange(len(starts)), sizes)
            ends_a, ends_b = [], []
            u = fp.view(np.uint64)
            small = (sizes <= SMALL)[group] & (x == y)
            for d in range(1, min(SMALL, int(sizes.max(initial=1)))):
                at = np.flatnonzero((group[:-d] == group[d:]) & small[:-d])
                if len(at):
                    at = at[near(u[at] ^ u[at + d])]
                    ends_a.append(node[at])
                    ends_b.append(node[at + d])
            for g in np.flatnonzero((sizes > SMALL) | ((sizes > 1) & (x[starts] != y[starts]))):
                s = slice(starts[g], starts[g] + sizes[g])
                pairs = forest(u[s], node[s], b[s], bool(x[starts[g]] != y[starts[g]]))
                if pairs:
                    one, two = zip(*pairs, strict=True)
                    ends_a.append(np.array(one, dtype=np.int64))
                    ends_b.append(np.array(two, dtype=np.int64))
            flat = [np.concatenate(e) if e else np.zeros(0, dtype=np.int64) for e in (ends_a, ends_b)]
            return pa.RecordBatch.from_arrays([pa.array(flat[0]), pa.array(flat[1])], names=["a", "b"])

        for batch in batches:
            cols = [c.to_numpy(zero_copy_only=False) for c in batch.columns]
            if not len(cols[0]):
                continue
            if held is not None:
                cols = [np.concatenate(p) for p in zip(held, cols, strict=True)]
            same = np.ones(len(cols[0]), dtype=bool)
            for c in cols[:4]:
                same &= c == c[-1]
            cut = int(np.flatnonzero(~same)[-1]) + 1 if not same.all() else 0  # the last list may go on
            if cut:
                yield table([c[:cut] for c in cols])
            held = [c[cut:] for c in cols]
        if held is not None and len(held[0]):
            yield table(held)

    return scan


def fingerprint_links(prints: DataFrame, max_bits: int = 3, list_bound: int = 8192) -> DataFrame:
    """Links ``(a, b)`` between nodes of ``prints(node long, fp long)``, one row per different fingerprint.

    ``max_bits`` must be at most three: the triples guarantee it. Every list
    keeps its connectivity: a pair of linked fingerprints is always joined by
    emitted links, though in long lists not always by its own.
    """
    if not 0 <= max_bits <= 3:
        raise ValueError("the index answers up to three differing bits")
    ship(prints.sparkSession)
    byte = lambda p: F.shiftrightunsigned(F.col("fp"), 8 * p).bitwiseAND(255)
    keys = F.array(*[F.struct(F.lit(n).cast("int").alias("t"), (byte(i) * 65536 + byte(j) * 256 + byte(k)).cast("int").alias("k")) for n, (_, i, j, k) in enumerate(TRIPLES)])
    posted = prints.select("node", "fp", F.explode(keys).alias("key")).select("node", "fp", "key.t", "key.k")
    long_lists = posted.groupBy("t", "k").count().filter(F.col("count") > list_bound).select("t", "k", F.ceil(F.col("count") * 2 / list_bound).cast("int").alias("blocks"))
    posted = (posted.join(long_lists, ["t", "k"], "left")
              .withColumn("blocks", F.coalesce("blocks", F.lit(1)))
              .withColumn("block", F.pmod(F.xxhash64("fp"), F.col("blocks")).cast("int"))
              .withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
              .select("t", "k", F.least("block", "other").alias("x"), F.greatest("block", "other").alias("y"), "block", "fp", "node"))
    return (posted.repartition("t", "k", "x", "y").sortWithinPartitions("t", "k", "x", "y")
            .mapInArrow(_links_in_lists(max_bits, 8 - max_bits), "a long, b long"))


def simhash_classes(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", max_bits: int = 3, shingle: int = 3) -> DataFrame:
    """``(doc_id, k1, k2, fp long, class long, component_id long)`` for every row of ``docs``.

    component_id is the smallest identifier reachable over links of at most
    ``max_bits`` bits (null if all are null); ``class`` names the class. Null and empty texts have
    fingerprint zero and link like any other; a fingerprint is one node, so
    copies cost nothing more and rows that share an identifier stay apart. An
    empty table gives an empty result; other columns are ignored.
    """
    found = materialize(with_fingerprints(docs, doc_id, text, shingle), "fingerprints")
    nodes = materialize(found.groupBy("fp").agg(F.min("doc_id").alias("least")), "nodes")
    parts = connected_components(fingerprint_links(nodes.select(F.col("fp").alias("node"), "fp"), max_bits))
    placed = nodes.join(parts.withColumnRenamed("id", "fp"), "fp", "left").select("fp", "least", F.coalesce("component", "fp").alias("component"))
    placed = materialize(placed, "placed")
    least = materialize(placed.groupBy("component").agg(F.min("least").alias("component_id")), "least")
    tops = placed.join(least, "component").select("fp", F.col("component").alias("class"), "component_id")
    return found.join(materialize(tops, "classes"), "fp").select("doc_id", "k1", "k2", "fp", "class", "component_id")


def one_of_each_class(docs: DataFrame, max_bits: int = 3, shingle: int = 3) -> DataFrame:
    """One row of ``docs`` for each near-duplicate class, that with its smallest doc_id; columns unchanged.

    Of rows with that identifier one stays; a class without any identifier
    keeps one row as well. An empty table stays empty.
    """
    found = materialize(simhash_classes(docs, max_bits=max_bits, shingle=shingle).withColumn("row", F.monotonically_increasing_id()), "simhash-rows")
    return keep_by_fate(docs, fate_of_classes(found))


def fate_of_classes(found: DataFrame) -> DataFrame:
    """``(k1, k2, keep, n)`` of a written table ``found(doc_id, k1, k2, row, class)``: of each class of several rows that with the smallest identifier stays."""
    first = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "row")
    best = found.groupBy("class").agg(F.min(first).alias("best"), F.count(F.lit(1)).alias("size")).filter("size > 1").select("class", F.col("best.row").alias("stays"))
    told = found.join(materialize(best, "best"), "class").groupBy("k1", "k2").agg(F.max(F.col("row") == F.col("stays")).alias("keep"), F.count(F.lit(1)).alias("n"))
    return materialize(told, "fate")


def op7_simhash_neardup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash_classes(documents(spark, sf_dir))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
