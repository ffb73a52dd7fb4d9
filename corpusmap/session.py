"""The session, the package on the executors, and the SQL surface."""

from __future__ import annotations

import hashlib
import os
import tempfile
import threading
import uuid
import zipfile

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def session(master: str = "local[*]", partitions: int = 8) -> SparkSession:
    return (SparkSession.builder.master(master).config("spark.sql.shuffle.partitions", partitions).config("spark.sql.adaptive.enabled", "true")
            .config("spark.sql.session.timeZone", "UTC").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate())


def ship(spark: SparkSession) -> None:
    """Send this package to the executors' Python workers, whatever their working folder is."""
    root = os.path.dirname(os.path.abspath(__file__))
    files = sorted(os.path.join(d, n) for d, _, names in os.walk(root) for n in names if n.endswith(".py"))
    digest = hashlib.sha256()
    for f in files:
        with open(f, "rb") as fh:
            digest.update(f.encode() + fh.read())
    tag, sc = digest.hexdigest()[:16], spark.sparkContext
    if getattr(sc, "_corpusmap_shipped", None) == tag:
        return
    target = os.path.join(tempfile.mkdtemp(prefix="corpusmap_zip_"), f"corpusmap_{tag}.zip")
    with zipfile.ZipFile(target, "w", zipfile.ZIP_DEFLATED) as z:
        for f in files:
            z.write(f, os.path.relpath(f, os.path.dirname(root)))
    sc.addPyFile(target)
    sc._corpusmap_shipped = tag


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share.

    Where the session names none, a local master (tests) gets a temporary
    folder; on a cluster that folder would be each machine's own, so it is an error.
    """
    sc = spark.sparkContext
    told = sc.getConf().get("spark.checkpoint.dir")
    if told:
        return told
    held = sc._jsc.sc().getCheckpointDir()
    if held.isDefined():
        return held.get()
    if not sc.master.startswith("local"):
        raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
    sc.setCheckpointDir(tempfile.mkdtemp(prefix="corpusmap_"))
    return sc._jsc.sc().getCheckpointDir().get()


def fresh_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark).rstrip('/')}/corpusmap/{name}-{uuid.uuid4().hex}"


_CLEAN_UP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_writing = {"lock": threading.Lock(), "n": 0, "before": None}


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: cuts lineage, survives lost executors.

    The shuffle files of the step are removed as soon as its table is written.
    Several threads may write at once: the setting is restored by the last.
    The table stays until :func:`release` is called on the result.
    """
    spark = df.sparkSession
    path = fresh_path(spark, name)
    with _writing["lock"]:
        if not _writing["n"]:
            _writing["before"] = spark.conf.get(_CLEAN_UP)
            spark.conf.set(_CLEAN_UP, "true")
        _writing["n"] += 1
    try:
        df.write.parquet(path)
    finally:
        with _writing["lock"]:
            _writing["n"] -= 1
            if not _writing["n"]:
                spark.conf.set(_CLEAN_UP, _writing["before"])
    found = spark.read.schema(df.schema).parquet(path)
    found._written_to = path
    return found


def release(*tables: DataFrame) -> None:
    """Delete tables that :func:`materialize` wrote. Only for those that nothing unwritten is still built on."""
    for t in tables:
        path = t.__dict__.pop("_written_to", None)
        if path:
            spark = t.sparkSession
            where = spark._jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


def spread(df: DataFrame) -> DataFrame:
    """``df`` over all cores where its files give fewer tasks than that; a table of many files is left as it is."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(cores) if df.rdd.getNumPartitions() < cores else df


def register_sql(spark: SparkSession, folder: str) -> None:
    """Views ``corpus_documents``, ``corpus_pages``, ``corpus_unigrams`` and the table function ``text_windows(text, size)``."""
    from pyspark.sql.functions import udtf

    from corpusmap.functions import surrogate
    from corpusmap.operators.similarity import unigram_counts

    docs = surrogate.documents(spark, folder)
    docs.createOrReplaceTempView("corpus_documents")
    surrogate.pages(spark, folder).createOrReplaceTempView("corpus_pages")
    unigram_counts(docs, ["register", "lang", "country"]).createOrReplaceTempView("corpus_unigrams")

    @udtf(returnType="win int, window string")
    class TextWindows:
        def eval(self, text: str, size: int):
            for i in range(len(text or "") // size):
                yield i, text[i * size: (i + 1) * size]

    spark.udtf.register("text_windows", TextWindows)


def spearman_udaf():
    """A grouped aggregate for notebooks; the operators use window ranks instead."""
    return F.pandas_udf(lambda a, b: float(a.rank().corr(b.rank())), "double", F.PandasUDFType.GROUPED_AGG)


def heavy_tokens(counts: DataFrame, k: int) -> DataFrame:
    return counts.groupBy("token").agg(F.sum("n").alias("n")).orderBy(F.desc("n"), "token").limit(k)
