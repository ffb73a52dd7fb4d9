"""Exact de-duplication with disk-backed keyed streaming state.

The state (RocksDB, no expiry) holds per digest of the normalised text the row
that stays: its length, its identifier and a locator, the place of its record
in the feed; and the number of rows. The locator tells rows apart that have one
identifier or none. Any later feed is folded into the same state. Where a
digest is hit more than once, the full bytes of all its rows are compared; if
two texts share a digest, all is done again with a longer one.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from corpusmap.llm.common import BUCKETS, documents, fresh_path, keep_by_fate, materialize, release, row_key, text_or_empty, without_separators

_PROVIDER = "spark.sql.streaming.stateStore.providerClass"
_BOUNDED = "spark.sql.streaming.stateStore.rocksdb.boundedMemoryUsage"
_BOUND_MB = "spark.sql.streaming.stateStore.rocksdb.maxMemoryUsageMB"
_RESERVE = "spark.sql.streaming.stateStore.rocksdb.allowFAllocate"


def sha256_digest(normalised: Column) -> Column:
    return F.unhex(F.sha2(normalised, 256))


class StreamingDeduplicator:
    """Keyed duplicate state over a growing folder of digest records.

    ``add`` writes the records of more documents to the feed and folds them
    into the state; ``state`` returns it. Both the feed and the state live in
    the session's shared folder, so a restarted query goes on where it was.
    """

    def __init__(self, spark: SparkSession, digest=sha256_digest, memory_mb: int = 256):
        self.spark, self.digest, self.memory_mb = spark, digest, memory_mb
        self.feed, self.checkpoint, self.out = (fresh_path(spark, n) for n in ("dedup-feed", "dedup-state", "dedup-out"))
        self.schema, self.added = None, 0

    def records(self, docs: DataFrame) -> DataFrame:
        text = text_or_empty("text")
        return (docs.select("doc_id", text.alias("text")).withColumn("norm", without_separators(F.col("text")))
                .select("doc_id", self.digest(F.col("norm")).alias("digest"), F.char_length("text").cast("long").alias("points"),
                        F.struct(F.lit(self.added).alias("add"), F.monotonically_increasing_id().alias("row")).alias("at"), *row_key(F.col("doc_id"), F.col("text"))))

    def add(self, docs: DataFrame) -> StreamingDeduplicator:
        records = self.records(docs)
        self.schema = records.schema
        records.write.mode("append").parquet(self.feed)
        self.added += 1
        conf = self.spark.conf
        before = {k: conf.get(k, None) for k in (_PROVIDER, _BOUNDED, _BOUND_MB, _RESERVE)}
        conf.set(_PROVIDER, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
        conf.set(_BOUNDED, "true")
        conf.set(_BOUND_MB, str(self.memory_mb))
        conf.set(_RESERVE, "false")  # a store for each shuffle partition: none reserves space it does not use
        out = self.out
        try:
            best = F.struct(F.col("points"), (-F.col("doc_id")).alias("back"), (-F.col("at.add")).alias("add"), (-F.col("at.row")).alias("row"))
            stream = self.spark.readStream.schema(self.schema).parquet(self.feed).groupBy("digest").agg(F.count(F.lit(1)).alias("group_size"), F.max(best).alias("best"))
            query = (stream.writeStream.outputMode("update").option("checkpointLocation", self.checkpoint)
                     .foreachBatch(lambda df, n: df.withColumn("batch", F.lit(n)).write.mode("overwrite").parquet(f"{out}/step={n}"))
                     .trigger(availableNow=True).start())
            query.awaitTermination()
        finally:
            for k, v in before.items():
                conf.unset(k) if v is None else conf.set(k, v)
        return self

    def state(self) -> DataFrame:
        """``(digest, group_size, keep_id, keep_points, keep_at)``: the last word on every digest."""
        schema = "digest binary, group_size long, best struct<points:long,back:long,add:int,row:long>, batch long"
        seen = self.spark.read.schema(schema).option("recursiveFileLookup", "true").parquet(self.out)
        at = F.struct((-F.col("s.best.add")).alias("add"), (-F.col("s.best.row")).alias("row"))
        return (seen.groupBy("digest").agg(F.max(F.struct("batch", "group_size", "best")).alias("s"))
                .select("digest", F.col("s.group_size").alias("group_size"), (-F.col("s.best.back")).alias("keep_id"), F.col("s.best.points").alias("keep_points"), at.alias("keep_at")))


def _bytes_differ(docs: DataFrame, dedup: StreamingDeduplicator, hits: DataFrame) -> bool:
    """Whether two texts share a digest. Copies are compared and combined in the task that reads them first."""
    bucket = F.pmod(F.xxhash64("digest"), F.lit(BUCKETS))
    touched = F.broadcast(hits.select(bucket.alias("bucket")).distinct())  # at most BUCKETS rows of eight bytes
    found = (docs.select(without_separators(text_or_empty("text")).alias("norm")).withColumn("digest", dedup.digest(F.col("norm"))).withColumn("bucket", bucket)
             .join(touched, "bucket", "left_semi"))  # some digests that were not hit pass too; they do no harm
    wrong = found.groupBy("digest").agg(F.min("norm").alias("lo"), F.max("norm").alias("hi")).filter("lo <> hi")
    return bool(wrong.limit(1).count())


def _settled(docs: DataFrame, digest=sha256_digest) -> tuple[StreamingDeduplicator, DataFrame]:
    """A deduplicator and its written state in which no digest stands for two texts."""
    for use in (digest, lambda n: F.concat(digest(n), F.unhex(F.sha2(n, 512)))):
        dedup = StreamingDeduplicator(docs.sparkSession, use).add(docs)
        state = materialize(dedup.state(), "dedup-classes")
        if not _bytes_differ(docs, dedup, state.filter("group_size > 1")):
            return dedup, state
        release(state)
    raise RuntimeError("two texts share a digest of 512 bits and more")


def exact_classes(docs: DataFrame, digest=sha256_digest) -> DataFrame:
    """``(doc_id, keep_id, group_size long, kept boolean, digest binary)`` for every row of ``docs``.

    Texts are equal when identical after deleting separators; null counts as
    empty. The row with the most code points stays, then the smallest doc_id
    (null last), then one of the rows with that doc_id: exactly one row of
    every group is kept, whether identifiers are null or repeated. An empty
    table gives an empty result; other columns are ignored.
    """
    dedup, state = _settled(docs, digest)
    rows = docs.sparkSession.read.schema(dedup.schema).parquet(dedup.feed)
    return rows.join(state, "digest").select("doc_id", "keep_id", "group_size", (F.col("at") == F.col("keep_at")).alias("kept"), "digest")


def without_copies(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` that stay, one of every group of equal texts; columns unchanged, whatever their names.

    Which row stays is as in :func:`exact_classes`; of rows with one text and
    identifier it is any one. Null texts are empty and one group, null
    identifiers come last. An empty table stays empty.
    """
    dedup, state = _settled(docs)
    rows = docs.sparkSession.read.schema(dedup.schema).parquet(dedup.feed)
    many = rows.join(state.filter("group_size > 1"), "digest")
    fate = many.groupBy("k1", "k2").agg(F.max(F.col("at") == F.col("keep_at")).alias("keep"), F.count(F.lit(1)).alias("n"))
    return keep_by_fate(docs, materialize(fate, "dedup-fate"))


def op5_streaming_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_classes(documents(spark, sf_dir)).select("doc_id", "keep_id", "group_size", "kept", F.lower(F.hex(F.substring("digest", 1, 32))).alias("text_sha256"))


#: DuckDB; of rows with one identifier and one length, any stays
OP5_SQL = r"""
WITH t AS (
  SELECT doc_id, length(coalesce(text, '')) AS points,
         regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]', '', 'g') AS norm
  FROM documents),
w AS (
  SELECT *, first_value(doc_id) OVER o AS keep_id, row_number() OVER o AS place, count(*) OVER (PARTITION BY norm) AS group_size
  FROM t WINDOW o AS (PARTITION BY norm ORDER BY points DESC, doc_id NULLS LAST))
SELECT doc_id, keep_id, group_size, place = 1 AS kept, sha256(norm) AS text_sha256 FROM w
"""
