"""A bounded sample of labelled documents, for fitting classifiers."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from corpusmap.llm.common import materialize, text_or_empty, thinned


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, allowed: Column, most: int, seed: int, most_bytes: int | None = None) -> DataFrame:
    """``(doc_id, y int, text binary)`` of at most ``most`` labelled documents, the same at every run; a written table.

    Rows without label or identifier and those outside ``allowed`` are never
    read; of several labels of one document the largest counts. The sample is
    drawn on the labels alone, so the documents meet a table of bounded size.
    With ``most_bytes`` documents follow in the order of their draw until
    their texts have so many bytes; the first one is always taken.
    """
    y, order = F.col(label), (F.xxhash64(F.lit(seed), "doc_id"), F.col("doc_id"))
    fit = labels.filter(y.isNotNull() & F.col("doc_id").isNotNull() & allowed)
    some = (thinned(fit, F.xxhash64(F.lit(seed + 1), "doc_id"), most, fit.count()).groupBy("doc_id").agg(F.max(y).cast("int").alias("y"))
            .orderBy(*order).limit(most))
    found = docs.select("doc_id", text_or_empty("text").cast("binary").alias("text")).join(F.broadcast(some), "doc_id").select("doc_id", "y", "text")
    found = materialize(found, f"labelled-{label}")
    if most_bytes is None:
        return found
    sizes = found.groupBy("doc_id").agg(F.sum(F.octet_length("text")).alias("size"))  # at most ``most`` rows
    upto = sizes.withColumn("upto", F.sum("size").over(Window.orderBy(*order)))
    taken = upto.filter((F.col("upto") <= most_bytes) | (F.col("upto") == F.col("size"))).select("doc_id")
    return found.join(F.broadcast(taken), "doc_id", "left_semi")
