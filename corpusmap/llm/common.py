"""Helpers shared by the training-data operators."""

from __future__ import annotations

import ctypes
import functools
import sys
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from corpusmap.session import fresh_path, materialize, release, shared_dir, ship

__all__ = ["WORD", "documents", "fresh_names", "fresh_path", "held_out", "keep_by_fate", "lean", "materialize", "release", "row_key", "shared_dir", "ship", "short_batches", "text_or_empty", "thinned", "without_separators", "word_count"]

#: fixed value: the separators between words, everywhere in this subpackage
WORD = r"[^\x20\x09-\x0D]+"
#: fixed value: the separators one by one, as characters
SEPARATORS = ("\x20", "\x09", "\x0a", "\x0b", "\x0c", "\x0d")


#: what operators keep in a worker process from task to task, under these names in ``sys``
KEPT = ("_corpusmap_encoders", "_corpusmap_hmm")
#: rows of an Arrow batch in stages that carry whole rows
BATCH_ROWS = 1024


def lean(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], keeps: str = "") -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """``run`` in a worker that outlives its tasks: what other operators left there goes first, free memory goes back to the system at the end.

    Of ``KEPT`` only ``keeps`` stays.
    """

    @functools.wraps(run)
    def over(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for name in KEPT:
            if name != keeps:
                sys.__dict__.pop(name, None)
        try:
            yield from run(batches)
        finally:
            pa.default_memory_pool().release_unused()
            trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc alone has it
            if trim is not None:
                trim(0)

    return over


def short_batches(spark: SparkSession) -> None:
    """Arrow batches of this session hold at most BATCH_ROWS rows from here on; a smaller setting stays.

    Executors and their workers hold some batches of whole rows at once for
    each task, outside the heap.
    """
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(key)) <= BATCH_ROWS:
        spark.conf.set(key, str(BATCH_ROWS))


def fresh_names(df: DataFrame, *names: str) -> list[str]:
    """``names``, each with underscores before it until no column of ``df`` is called so, in any case of letters."""
    taken, out = {c.lower() for c in df.columns}, []
    for n in names:
        while n.lower() in taken:
            n = f"_{n}"
        taken.add(n.lower())
        out.append(n)
    return out


def text_or_empty(col: str | Column = "text") -> Column:
    """Null counts as the empty text."""
    return F.coalesce(F.col(col) if isinstance(col, str) else col, F.lit(""))


def row_key(doc_id: Column, text: Column) -> list[Column]:
    """Two longs ``k1, k2``, 128 bits that tell rows apart by identifier and text, null and repeated identifiers too."""
    return [F.xxhash64(F.lit(n), doc_id, doc_id.isNull(), text).alias(f"k{n}") for n in (1, 2)]


BUCKETS = 1 << 20


def keep_by_fate(docs: DataFrame, fate: DataFrame) -> DataFrame:
    """``docs`` without the rows that ``fate(k1, k2, keep boolean, n long)`` drops; columns unchanged, whatever their names.

    A row is known by :func:`row_key`. Rows that are not in ``fate`` stay. Of
    the ``n`` rows of one kept key one stays. Only rows in a bucket of keys of
    ``fate`` are shuffled; the others go straight through.
    """
    k1, k2, b, keep, n = fresh_names(docs, "k1", "k2", "bucket", "keep", "n")
    bucket = lambda k: F.pmod(F.col(k), F.lit(BUCKETS))
    keys = row_key(F.col("doc_id"), text_or_empty("text"))
    marked = docs.withColumns({k1: keys[0], k2: keys[1]}).withColumn(b, bucket(k1))
    hit = F.broadcast(fate.select(bucket("k1").alias(b)).distinct())  # at most BUCKETS rows of eight bytes
    told = fate.select(F.col("k1").alias(k1), F.col("k2").alias(k2), F.col("keep").alias(keep), F.col("n").alias(n))
    met = marked.join(hit, b, "left_semi").join(told, [k1, k2], "left")
    out = marked.join(hit, b, "left_anti").select(*docs.columns)
    if not fate.filter("keep and n > 1").limit(1).count():
        return out.unionByName(met.filter(F.col(keep).isNull() | F.col(keep)).select(*docs.columns))
    once = met.filter(F.col(keep).isNull() | F.col(keep) & (F.col(n) == 1)).select(*docs.columns)
    many = met.filter(F.col(keep) & (F.col(n) > 1)).groupBy(k1, k2).agg(F.first(F.struct(*[F.col(c) for c in docs.columns])).alias(b))  # combined in the task first
    return out.unionByName(once).unionByName(many.select(f"{b}.*"))


def without_separators(col: Column) -> Column:
    """The text with every separator character deleted (byte-wise replaces, no regular expression)."""
    for s in SEPARATORS:
        col = F.replace(col, F.lit(s), F.lit(""))
    return col


def word_count(col: Column) -> Column:
    return F.regexp_count(col, F.lit(WORD)).cast("long")


def held_out(modulus: int, remainder: int, doc_id: str = "doc_id") -> Column:
    """True where crc32 of the identifier written as text leaves ``remainder``."""
    return F.coalesce(F.pmod(F.crc32(F.col(doc_id).cast("string").cast("binary")), F.lit(modulus)) == remainder, F.lit(False))


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def thinned(df: DataFrame, hashed: Column, wanted: int, of: int, spare: float = 4.0) -> DataFrame:
    """Rows by hash, about ``spare`` times ``wanted`` of ``of``: what a sample is then picked from stays small however long the table."""
    share = min(1.0, spare * wanted / max(of, 1))
    return df if share >= 1 else df.filter(F.pmod(hashed, F.lit(1 << 30)) < int(share * (1 << 30)))
