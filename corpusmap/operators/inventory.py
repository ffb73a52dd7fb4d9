"""How much there is, where, and how it goes with populations."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from corpusmap.functions.text import n_words
from corpusmap.operators.similarity import safe_corr


def word_counts(docs: DataFrame, keys: list[str]) -> DataFrame:
    return docs.groupBy(*keys).agg(F.sum(n_words(F.col("text"))).alias("n_words"))


def words_by_region(counts: DataFrame, region: str, corpora: list[str], corpus: str = "register") -> DataFrame:
    """One row per region, words and per cent of each corpus; ``counts(region, corpus, n_words)``."""
    wide = counts.groupBy(region).agg(*[F.coalesce(F.sum(F.when(F.col(corpus) == c, F.col("n_words"))), F.lit(0)).alias(f"{c}_words") for c in corpora])
    every = Window.partitionBy()  # a row per region
    return wide.select(region, *[x for c in corpora for x in (F.col(f"{c}_words"), (100.0 * F.col(f"{c}_words") / F.sum(f"{c}_words").over(every)).alias(f"{c}_pct"))])


def coverage(cells: DataFrame, thresholds: list[int]) -> DataFrame:
    """Languages, countries and pairs that reach each threshold; ``cells(lang, country, n_words)`` is small."""
    level = lambda name, *k: cells.groupBy(*k).agg(F.sum("n_words").alias("w")).select(F.lit(name).alias("level"), "w")
    sums = level("languages", "lang").union(level("countries", "country")).union(level("pairs", "lang", "country"))
    cut = cells.sparkSession.createDataFrame([(t,) for t in thresholds], "threshold long")
    reached = lambda name: F.count_if((F.col("level") == name) & (F.col("w") >= F.col("threshold"))).alias(f"n_{name}")
    return sums.crossJoin(F.broadcast(cut)).groupBy("threshold").agg(reached("languages"), reached("countries"), reached("pairs"))


def growth(old: DataFrame, new: DataFrame, key: str) -> DataFrame:
    a, b = old.withColumnRenamed("n_words", "old_words"), new.withColumnRenamed("n_words", "new_words")
    return a.join(b, key, "full").select(key, F.coalesce("old_words", F.lit(0)).alias("old_words"), F.coalesce("new_words", F.lit(0)).alias("new_words"), F.try_divide(F.col("new_words"), F.col("old_words")).alias("growth"))


def representation_ratio(words: DataFrame, people: DataFrame, key: str) -> DataFrame:
    """Share of words over share of people; both tables have a row per key."""
    every = Window.partitionBy()
    both = words.join(people, key)
    return both.withColumns({"word_share": F.col("n_words") / F.sum("n_words").over(every), "people_share": F.col("population") / F.sum("population").over(every)}).withColumn("ratio", F.try_divide("word_share", "people_share"))


def nonmajority(cells: DataFrame, leading: int = 1) -> DataFrame:
    """Languages of a country below its ``leading`` largest."""
    order = Window.partitionBy("country").orderBy(F.desc("n_words"), "lang")
    return cells.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") > leading)


def topk_share(counts: DataFrame, keys: list[str], k: int) -> DataFrame:
    """Share of the ``k`` largest; a top-k and a total, nothing is sorted as a whole."""
    top = counts.orderBy(F.desc("n_words"), *keys).limit(k).agg(F.sum("n_words").alias("top_words"))
    return top.crossJoin(counts.agg(F.sum("n_words").alias("all_words"))).withColumn("share", F.col("top_words") / F.col("all_words"))


def density_correlation(a: DataFrame, b: DataFrame, key: str, missing: str = "drop") -> DataFrame:
    both = a.select(key, F.col("n_words").cast("double").alias("x")).join(b.select(key, F.col("n_words").cast("double").alias("y")), key, "full")
    both = both.na.fill(0.0, ["x", "y"]) if missing == "zero" else both.na.drop()
    return both.agg(safe_corr("x", "y").alias("r"), F.count(F.lit(1)).alias("n"))


def factors(demo: DataFrame) -> DataFrame:
    """Every product of the three factors; pop_net is the digital population, all the combined estimate."""
    p, g, i = F.col("population").cast("double"), F.col("gdp_pc"), F.col("internet")
    return demo.select("country", p.alias("pop"), g.alias("gdp"), i.alias("net"), (p * i).alias("pop_net"), (p * g).alias("pop_gdp"), (i * g).alias("net_gdp"), (p * i * g).alias("all"))


def factor_grid(counts: DataFrame, demo: DataFrame, corpus: str) -> DataFrame:
    """Correlation of words per country with each product, all in one aggregation."""
    names = ["pop", "gdp", "net", "pop_net", "pop_gdp", "net_gdp", "all"]
    met = counts.join(F.broadcast(factors(demo)), "country")
    return met.groupBy(corpus).agg(*[safe_corr(F.col("n_words").cast("double"), F.col(n)).alias(f"r_{n}") for n in names], F.count(F.lit(1)).alias("n"))


def language_share(cells: DataFrame, by: list[str] | None = None) -> DataFrame:
    by = by or ["country"]
    return cells.withColumn("pct", 100.0 * F.col("n_words") / F.sum("n_words").over(Window.partitionBy(*by)))


def composition(a: DataFrame, b: DataFrame, missing: str = "zero") -> DataFrame:
    """Per cent of each language in each country that both corpora know, side by side."""
    places = a.select("country").distinct().intersect(b.select("country").distinct())
    tongues = a.select("lang").union(b.select("lang")).distinct()
    grid = places.crossJoin(F.broadcast(tongues))  # countries times languages, both small
    x = language_share(a).select("country", "lang", F.col("pct").alias("x"))
    y = language_share(b).select("country", "lang", F.col("pct").alias("y"))
    both = grid.join(x, ["country", "lang"], "left").join(y, ["country", "lang"], "left")
    return both.na.fill(0.0, ["x", "y"]) if missing == "zero" else both.na.drop()


def downsampling_rates(counts: DataFrame, demo: DataFrame, target: float | None = None) -> DataFrame:
    """country, words_before, pop_share, rate: what to keep so that shares follow the population."""
    every = Window.partitionBy()  # a row per country
    both = counts.join(demo.select("country", "population"), "country").withColumn("pop_share", F.col("population") / F.sum("population").over(every))
    total = F.lit(target) if target else F.min(F.col("n_words") / F.col("pop_share")).over(every)
    return both.withColumn("rate", F.least(F.lit(1.0), total * F.col("pop_share") / F.col("n_words"))).select("country", F.col("n_words").alias("words_before"), "pop_share", "rate")


def downsample(docs: DataFrame, rates: DataFrame, key: str) -> DataFrame:
    """One pass: a row stays if its hashed key lies below the rate of its country."""
    unit = F.conv(F.substring(F.md5(F.col(key).cast("string")), 1, 8), 16, 10).cast("double") / 4294967296.0
    return docs.join(F.broadcast(rates.select("country", "rate")), "country").filter(unit < F.col("rate")).drop("rate")
