"""Columns that stand in for what the given tables lack: country, period, register, demography."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpusmap.functions.geo import host
from corpusmap.sources.tables import load

#: fixed values: two-letter to three-letter language codes
ISO = {"en": "eng", "fr": "fra", "de": "deu", "es": "spa"}


def documents(spark: SparkSession, folder: str) -> DataFrame:
    """documents plus country (nation 0-19), period, register (web or social) and v3 (earlier version)."""
    d = load(spark, folder, "documents").select("doc_id", "text", "lang", "source")
    hexed = lambda *c: F.substring(F.md5(F.concat(*c)), 1, 1)
    return d.withColumns({
        "country": (F.col("doc_id") % 20).cast("int"), "period": (F.floor(F.col("doc_id") / 20) % 12).cast("int"),
        "register": F.when(hexed(F.col("doc_id").cast("string")) < "8", "web").otherwise("social"),
        "v3": hexed(F.lit("v3"), F.col("doc_id").cast("string")) < "4"})


def pages(spark: SparkSession, folder: str) -> DataFrame:
    """pages plus host, language of the address, country by a hash of the host, period."""
    p = load(spark, folder, "pages").withColumn("host", host(F.col("url")))
    return p.withColumns({
        "country": (F.conv(F.substring(F.md5("host"), 1, 8), 16, 10).cast("bigint") % 25).cast("int"),
        "period": (F.col("page_id") % 6).cast("int"), "lang": F.regexp_extract("url", r"/(en|fr|de|es)/", 1)})


def demography(spark: SparkSession, folder: str) -> DataFrame:
    """country, population, gdp_pc, internet: customers, their orders' value per head, share with a recent order."""
    spent = load(spark, folder, "orders").groupBy(F.col("o_custkey").alias("c_custkey")).agg(F.sum("o_totalprice").alias("spent"), F.max((F.col("o_orderdate") >= F.lit("2001-01-01").cast("timestamp_ntz")).cast("int")).alias("recent"))
    each = load(spark, folder, "customer").select("c_custkey", F.col("c_nationkey").alias("country")).join(spent, "c_custkey", "left")
    people = F.count(F.lit(1))
    return each.groupBy("country").agg(people.alias("population"), (F.sum(F.coalesce("spent", F.lit(0.0))) / people).alias("gdp_pc"), (F.sum(F.coalesce("recent", F.lit(0))) / people).alias("internet"))


def nations(spark: SparkSession, folder: str) -> DataFrame:
    """country, n_name, r_name."""
    n, r = load(spark, folder, "nation"), load(spark, folder, "region")
    return n.join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey")).select(F.col("n_nationkey").alias("country"), "n_name", "r_name")


def cities(spark: SparkSession, folder: str) -> DataFrame:
    k = F.col("n_nationkey")
    return load(spark, folder, "nation").select(k.alias("city_id"), k.alias("country"), (-60.0 + 5 * k).cast("double").alias("lat"), (-170.0 + 13 * k).cast("double").alias("lon"))


def posts(spark: SparkSession, folder: str) -> DataFrame:
    """conversations as posts near the city of their country."""
    h = F.md5(F.col("conv_id").cast("string"))
    off = lambda a: (F.conv(F.substring(h, a, 4), 16, 10).cast("long") % 200 - 100) / 100.0
    return load(spark, folder, "conversations").withColumn("country", (F.col("conv_id") % 25).cast("int")).withColumns({"lat": -60.0 + 5 * F.col("country") + off(1), "lon": -170.0 + 13 * F.col("country") + off(5)})
