"""Reading and writing: Parquet tables, corpus CSV, JSON lines, text, binary, file streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpusmap.session import spread

CORPUS_SCHEMA = "language string, url string, n_words long, text string"


#: tables whose rows are long texts: worth dealing to all cores where one file holds them
TEXTS = ("documents", "pages", "conversations")


def load(spark: SparkSession, folder: str, name: str) -> DataFrame:
    table = spark.read.parquet(f"{folder}/{name}.parquet")
    return spread(table) if name in TEXTS else table


def publish_corpus(rows: DataFrame, path: str, files_per_cell: int = 4, rows_per_file: int = 100_000) -> None:
    """Region, country, language folders of gzip CSV with at most ``rows_per_file`` rows a file.

    Salted, so that one large folder is written by several tasks.
    """
    salt = F.pmod(F.xxhash64("url", "n_words"), F.lit(files_per_cell))
    cells = [F.col("region"), F.col("country"), F.col("language_folder")]
    (rows.withColumn("language_folder", F.col("language")).repartition(*cells, salt)
     .select("region", "country", "language_folder", "language", "url", "n_words", "text").write.mode("overwrite")
     .partitionBy("region", "country", "language_folder").option("maxRecordsPerFile", rows_per_file)
     .option("compression", "gzip").option("quoteAll", True).option("escape", '"').option("header", False).csv(path))


def read_corpus_csv(spark: SparkSession, path: str) -> DataFrame:
    schema = f"{CORPUS_SCHEMA}, region string, country string, language_folder string"
    return spark.read.schema(schema).option("multiLine", True).option("quote", '"').option("escape", '"').csv(path)


def publish_unigrams(lists: DataFrame, path: str, files_per_list: int = 4) -> None:
    """Gzip CSV of tokens and counts in folders by register and language; salted, so that one long list is written by several tasks."""
    salt = F.pmod(F.xxhash64("token"), F.lit(files_per_list))
    lists.repartition("register", "language", salt).write.mode("overwrite").partitionBy("register", "language").option("compression", "gzip").csv(path)


def read_json(spark: SparkSession, path: str, schema: str) -> DataFrame:
    return spark.read.schema(schema).json(path)


def read_text(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.text(path)


def read_binary(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.format("binaryFile").load(path)


def save_bucketed(df: DataFrame, table: str, keys: list[str], buckets: int) -> None:
    df.write.mode("overwrite").bucketBy(buckets, *keys).sortBy(*keys).saveAsTable(table)


def overwrite_partitions(df: DataFrame, path: str, by: list[str]) -> None:
    """Replace only the partitions that ``df`` holds: a repeated run changes nothing."""
    df.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy(*by).parquet(path)
