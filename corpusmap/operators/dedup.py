"""Two-scope de-duplication of samples: inside a site, then across the sites of one period."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from corpusmap.session import materialize

#: most rows, of eight bytes, of the table that is broadcast before a join
BUCKETS = 1 << 20


def fingerprint(text: Column, key: str = "exact") -> Column:
    """128 bits of the text, or of its lower-cased letters and digits."""
    if key == "normalized":
        text = F.regexp_replace(F.lower(text), r"[^\p{L}\p{N}]+", " ")
    return F.md5(text)


def with_fingerprint(samples: DataFrame, text: str = "text", key: str = "exact") -> DataFrame:
    """Columns ``_f1, _f2``: 128 bits as two longs, so that aggregations hash and do not sort."""
    t = F.col(text) if key == "exact" else F.regexp_replace(F.lower(F.col(text)), r"[^\p{L}\p{N}]+", " ")
    return samples.withColumns({f"_f{n}": F.xxhash64(F.lit(n), t) for n in (1, 2)})


def unique_samples(samples: DataFrame, ids: list[str], site: str = "site", period: str = "period", text: str = "text",
                   keep: str = "none", site_scope: str = "period", scopes: str = "both", key: str = "exact") -> DataFrame:
    """The samples that survive. ``ids`` name a sample.

    keep "none" drops every copy, "first" keeps the one with the smallest ids.
    scopes: "site", "period" or both in this order: copies that the site scope
    has dropped no longer count across sites.

    ``samples`` is written once with its fingerprints. The aggregations then
    read nothing but fingerprints and scopes and are combined in the task, so
    a line with very many copies moves as few records. Texts are shuffled only
    where their fingerprint falls into a bucket with a dropped one.
    """
    held = materialize(with_fingerprint(samples, text, key), "samples")
    at = F.struct(*ids)
    marked = held.select(F.col(period).alias("_p"), F.col(site).alias("_s"), "_f1", "_f2", at.alias("_at"))
    drop = []
    if scopes in ("both", "site"):
        by = ["_p", "_s", "_f1", "_f2"] if site_scope == "period" else ["_s", "_f1", "_f2"]
        first = [] if keep == "none" else [F.min(F.struct("_p", "_at")).alias("_first")]
        inside = materialize(marked.groupBy(*by).agg(F.count(F.lit(1)).alias("_n"), *([F.max("_p").alias("_of")] if "_p" not in by else []), *first), "site-copies")
        drop.append((by, inside.filter("_n > 1"), first))
        stay = inside.filter("_n = 1") if keep == "none" else inside
        stay = stay.select((F.col("_first._p") if first else F.col("_p" if "_p" in by else "_of")).alias("_p"), "_f1", "_f2", *([F.col("_first._at").alias("_at")] if first else []))
    else:
        stay = marked
    if scopes in ("both", "period"):
        by = ["_p", "_f1", "_f2"]
        first = [] if keep == "none" else [F.struct(F.lit(None).alias("_x"), F.min("_at").alias("_at")).alias("_first")]
        drop.append((by, materialize(stay.groupBy(*by).agg(F.count(F.lit(1)).alias("_n"), *first).filter("_n > 1"), "period-copies"), first))
    out = held.withColumns({"_p": F.col(period), "_s": F.col(site)})
    bucket = F.pmod(F.col("_f1"), F.lit(BUCKETS))
    hit = drop[0][1].select(bucket.alias("_b"))
    for _, table, _ in drop[1:]:
        hit = hit.union(table.select(bucket.alias("_b")))
    hit = F.broadcast(hit.distinct())  # at most BUCKETS rows
    out = out.withColumn("_b", bucket)
    through, met = out.join(hit, "_b", "left_anti").select(*samples.columns), out.join(hit, "_b", "left_semi")
    for by, table, first in drop:
        if first:
            told = table.select(*by, F.col("_first._at").alias("_keep"))
            met = met.join(told, by, "left").filter(F.col("_keep").isNull() | (F.struct(*ids) == F.col("_keep"))).drop("_keep")
        else:
            met = met.join(table.select(*by), by, "left_anti")
    return through.unionByName(met.select(*samples.columns))


def against_earlier(samples: DataFrame, seen: DataFrame, text: str = "text") -> DataFrame:
    """Samples whose fingerprint no earlier period had; ``seen(fp)``."""
    return samples.withColumn("fp", fingerprint(F.col(text))).join(seen.select("fp").distinct(), "fp", "left_anti").drop("fp")


def first_period_only(samples: DataFrame, ids: list[str], period: str = "period", text: str = "text") -> DataFrame:
    """Samples of the first period in which their text occurs; texts that no later period repeats are not shuffled."""
    held = materialize(with_fingerprint(samples, text), "samples")
    first = held.groupBy("_f1", "_f2").agg(F.min(period).alias("_first"), F.max(period).alias("_last")).filter("_first < _last").select("_f1", "_f2", "_first")
    first = materialize(first, "first-periods")
    bucket = F.pmod(F.col("_f1"), F.lit(BUCKETS))
    hit = F.broadcast(first.select(bucket.alias("_b")).distinct())  # at most BUCKETS rows
    out = held.withColumn("_b", bucket)
    met = out.join(hit, "_b", "left_semi").join(first, ["_f1", "_f2"], "left").filter(F.col("_first").isNull() | (F.col(period) == F.col("_first")))
    return out.join(hit, "_b", "left_anti").select(*samples.columns).unionByName(met.select(*samples.columns))
