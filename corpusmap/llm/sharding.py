"""Histogram sort: documents into byte-balanced shards with one exchange.

Rows are ordered by (hash of the text, doc_id), so equal texts are neighbours.
Groups of equal texts that are large, but fit into a shard, are laid down
whole, the largest first, each in the emptiest shard. The rest fills the
shards up: splitters are found by counting exact bytes below candidate
boundaries over all partitions and narrowing the candidates. Only a group that
no shard can hold is cut, by doc_id.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from corpusmap.llm.common import documents, fresh_names, materialize, ship, text_or_empty

LOW, HIGH = -(1 << 63), (1 << 63) - 1
Key = tuple[int, int]


def interval_of(h: np.ndarray, d: np.ndarray, probe_h: np.ndarray, probe_d: np.ndarray) -> np.ndarray:
    """How many of the sorted probes are at or below each (h, d)."""
    at = np.searchsorted(probe_h, h, side="right")
    left = np.searchsorted(probe_h, h, side="left")
    for value in np.unique(h[at > left]):
        rows = np.flatnonzero(h == value)
        a, b = left[rows[0]], at[rows[0]]
        at[rows] = a + np.searchsorted(probe_d[a:b], d[rows], side="right")
    return at


def _histogram(keys: DataFrame, probes: list[Key]) -> tuple[np.ndarray, np.ndarray]:
    """Exact bytes and rows below each probe; one pass, partial sums per task."""
    ph = np.array([p[0] for p in probes], dtype=np.int64)
    pd = np.array([p[1] for p in probes], dtype=np.int64)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        size = np.zeros(len(ph) + 1, dtype=np.int64)
        rows = np.zeros(len(ph) + 1, dtype=np.int64)
        for b in batches:
            h, d, s = (c.to_numpy(zero_copy_only=False) for c in b.columns)
            at = interval_of(h, d, ph, pd)
            np.add.at(size, at, s)
            rows += np.bincount(at, minlength=len(rows))
        full = np.flatnonzero(rows)
        yield pa.RecordBatch.from_arrays([pa.array(full.astype(np.int64)), pa.array(size[full]), pa.array(rows[full])], names=["at", "size", "rows"])

    got = keys.select("h", "d", "size").mapInArrow(count, "at long, size long, rows long").groupBy("at").agg(F.sum("size"), F.sum("rows")).collect()  # at most a row per probe
    size, rows = np.zeros(len(ph) + 1, dtype=object), np.zeros(len(ph) + 1, dtype=np.int64)
    for at, s, n in got:
        size[at], rows[at] = s, n
    return np.cumsum(size)[:-1], np.cumsum(rows)[:-1]


@dataclass
class _Search:
    target: float
    tolerance: float
    group_tolerance: float
    lo: Key = (LOW, LOW)
    hi: Key = (HIGH, HIGH)
    lo_bytes: int = 0
    hi_bytes: int = 0
    key: Key | None = None

    def settle(self) -> None:
        down, up = self.target - self.lo_bytes, self.hi_bytes - self.target
        key, off = (self.lo, down) if down <= up else (self.hi, up)
        one_group = self.hi[0] - self.lo[0] <= 1 and self.lo[1] == LOW and self.hi[1] == LOW
        atom = self.hi[0] == self.lo[0] and self.hi[1] - self.lo[1] <= 1
        if off <= self.tolerance or one_group and off <= self.group_tolerance or atom:
            self.key = key
        elif one_group:
            self.hi = (self.lo[0], HIGH)  # cut inside the group; bytes at the end are those below the next group

    def probes(self, n: int) -> list[Key]:
        if self.lo[0] == self.hi[0]:
            a, b = self.lo[1], self.hi[1]
            return [(self.lo[0], a + (b - a) * i // (n + 1)) for i in range(1, n + 1)]
        a, b = self.lo[0], self.hi[0]
        return [(a + (b - a) * i // (n + 1), LOW) for i in range(1, n + 1)]


def splitters(keys: DataFrame, targets: list[float], tolerance: float, group_tolerance: float, n_probes: int = 64, max_rounds: int = 80) -> list[Key]:
    """Boundaries with ``targets`` bytes of ``keys`` below them, ascending; tolerances are bytes.

    A boundary that cuts a group needs ``group_tolerance``, else it stays at
    the nearer end. Raises if ``max_rounds`` passes do not settle them all.
    """
    total, first, last = keys.agg(F.coalesce(F.sum("size"), F.lit(0)), F.min("d"), F.max("d")).first()
    search = [_Search(min(t, total), tolerance, group_tolerance, hi_bytes=total) for t in targets]
    for s in search:
        s.settle()
    for _ in range(max_rounds):
        open_ = [s for s in search if s.key is None]
        if not open_:
            return sorted(s.key for s in search)
        for s in open_:  # inside a group only identifiers that exist are of interest
            if s.lo[0] == s.hi[0]:
                s.lo = (s.lo[0], max(s.lo[1], first))
                s.hi = (s.hi[0], min(s.hi[1], last + 1))
        probes = sorted({p for s in open_ for p in s.probes(n_probes)})
        size, _ = _histogram(keys, probes)
        for s in open_:
            for p, b in zip(probes, size, strict=True):
                if s.lo < p <= s.hi and b <= s.target and (p[1] == LOW or p[0] == s.lo[0]):
                    s.lo, s.lo_bytes = p, int(b)
                elif s.lo < p < s.hi and b > s.target and (p[1] == LOW or p[0] == s.hi[0]):
                    s.hi, s.hi_bytes = p, int(b)
            s.settle()
    raise RuntimeError("the splitters did not settle")


def lay_down(groups: list[tuple[int, int]], shards: int, room: float) -> tuple[dict[int, int], list[int]]:
    """``(hash, bytes)``, the largest first, each whole into the emptiest shard if it fits there: places and loads. The others are left."""
    place, load = {}, [0] * shards
    for h, size in sorted(groups, key=lambda g: (-g[1], g[0])):
        s = min(range(shards), key=lambda i: (load[i], i))
        if load[s] + size <= room:
            place[h] = s
            load[s] += size
    return place, load


def byte_shards(docs: DataFrame, shards: int = 16, tolerance: float = 0.001, whole: float = 0.002, rows_per_part: int = 1_000_000) -> DataFrame:
    """``docs`` plus ``shard_size, shard_crc32, shard int, slot long``, one row per row, dealt to their shards by one exchange.

    ``shard_size`` is the UTF-8 bytes of the text plus one, so null and empty
    texts are placed too. Slots count from 0 without gaps in every shard. The
    bytes of shards differ by ``tolerance`` and half of ``whole`` at most, as
    parts of a shard, and by one row. Equal texts share a shard while one can
    hold them beside larger groups; a group that none can hold is cut by
    doc_id (rows of one text without identifier cannot be told apart and stay
    together). Repeated rows take a slot each. An empty table gives an empty
    result. The four names are reserved; other names do no harm.
    """
    spark = docs.sparkSession
    ship(spark)
    h_, d_, sub_, n_ = fresh_names(docs, "h", "d", "sub", "n")
    text = text_or_empty("text")
    marked = docs.withColumns({h_: F.xxhash64(text), d_: F.coalesce("doc_id", F.lit(LOW)), "shard_size": (F.octet_length(text) + 1).cast("long"), "shard_crc32": F.crc32(text.cast("binary"))})
    keys = materialize(marked.select(F.col(h_).alias("h"), F.col(d_).alias("d"), F.col("shard_size").alias("size")), "shard-keys")
    total, rows = keys.agg(F.coalesce(F.sum("size"), F.lit(0)), F.count(F.lit(1))).first()
    room = total / shards
    large = keys.groupBy("h").agg(F.sum("size").alias("b")).filter(F.col("b") >= max(2.0, whole * room)).filter(F.col("b") <= room)  # at most shards / whole groups
    place, load = lay_down([(r[0], r[1]) for r in large.collect()], shards, room)
    placed = spark.createDataFrame(sorted(place.items()), "h long, own int")
    others = keys.join(F.broadcast(placed), "h", "left_anti")
    bounds = splitters(others, np.cumsum([room - x for x in load])[:-1].tolist(), tolerance * room, whole * room) if total else []
    parts = max(1, -(-rows // (shards * rows_per_part)))

    def put(df: DataFrame, h: str, d: str, sub: str) -> DataFrame:
        """Columns ``shard`` and ``sub``: the part of its shard that numbers the row."""
        past = sum([((F.col(h) > a) | (F.col(h) == a) & (F.col(d) >= b)).cast("int") for a, b in bounds], F.lit(0))
        met = df.join(F.broadcast(placed.select(F.col("h").alias(h), F.col("own").alias("shard"))), h, "left")
        return met.withColumns({"shard": F.coalesce("shard", past), sub: F.pmod(F.xxhash64(h, d), F.lit(parts)).cast("int")})

    counts = put(keys, "h", "d", "sub").groupBy("shard", "sub").count().collect()  # rows over rows_per_part, and shards
    offsets, at = [], {}
    for s, k, n in sorted(map(tuple, counts)):
        offsets.append((s, k, at.get(s, 0)))
        at[s] = at.get(s, 0) + n
    first = spark.createDataFrame(offsets, f"shard int, {sub_} int, {n_} long")
    order = Window.partitionBy("shard", sub_).orderBy(h_, d_)
    out = put(marked, h_, d_, sub_).withColumn("slot", F.row_number().over(order)).join(F.broadcast(first), ["shard", sub_])
    return out.select(*docs.columns, "shard_size", "shard_crc32", "shard", (F.col(n_) + F.col("slot") - 1).alias("slot"))


def op9_histogram_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return byte_shards(documents(spark, sf_dir)).select("doc_id", F.col("shard_size").alias("size"), F.col("shard_crc32").alias("text_crc32"), F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
