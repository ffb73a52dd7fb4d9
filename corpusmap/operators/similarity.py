"""Unigram lists and rank correlation between and within corpora."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from corpusmap.functions.text import words


def safe_corr(a, b) -> Column:
    """Pearson correlation; null where a side does not vary (the built-in one divides by zero in ANSI mode)."""
    return F.try_divide(F.covar_pop(a, b), F.stddev_pop(a) * F.stddev_pop(b))


def unigram_counts(docs: DataFrame, keys: list[str], text: str = "text") -> DataFrame:
    """``keys, token, n``; counts are combined in the task before they move."""
    return docs.select(*keys, F.explode(words(F.col(text))).alias("token")).groupBy(*keys, "token").agg(F.count(F.lit(1)).alias("n"))


def eligible(counts: DataFrame, keys: list[str], min_words: int, registers: tuple = ("web", "social")) -> DataFrame:
    """Keys with at least ``min_words`` in every register; ``counts(register, keys, n_words)``."""
    enough = counts.groupBy(*keys, "register").agg(F.sum("n_words").alias("w")).filter(F.col("w") >= min_words)
    return enough.groupBy(*keys).agg(F.count(F.lit(1)).alias("k")).filter(F.col("k") == len(registers)).drop("k")


def apply_rate_threshold(lists: DataFrame, keys: list[str], per_10m: float = 5.0) -> DataFrame:
    """Tokens at or above the rate in their own list; list totals are a small aggregate."""
    totals = lists.groupBy(*keys).agg(F.sum("n").alias("total"))
    return lists.join(totals, keys).filter(F.col("n") * 1e7 >= F.col("total") * per_10m).drop("total")


def average_rank(value: Column, keys: list) -> Column:
    """Rank among the rows of ``keys``; ties share the mean of their ranks."""
    order = Window.partitionBy(*keys).orderBy(value)
    ties = Window.partitionBy(*keys, value)
    return F.rank().over(order) + (F.count(F.lit(1)).over(ties) - 1) / 2.0


def rank_correlation(aligned: DataFrame, keys: list[str], a: str = "n_a", b: str = "n_b") -> DataFrame:
    """``keys, n_shared, rho`` from aligned counts; null where a side does not vary."""
    ranked = aligned.withColumns({"ra": average_rank(F.col(a), keys), "rb": average_rank(F.col(b), keys)})
    return ranked.groupBy(*keys).agg(F.count(F.lit(1)).alias("n_shared"), safe_corr("ra", "rb").alias("rho"))


def spearman_similarity(lists: DataFrame, keys: list[str], sides: tuple = ("web", "social"), per_10m: float = 5.0, top_n: int | None = None) -> DataFrame:
    """Two registers of ``lists(register, keys, token, n)``, aligned in one aggregation, then ranked."""
    passed = lists if top_n else apply_rate_threshold(lists, ["register", *keys], per_10m)
    if top_n:
        passed = passed.withColumn("r", F.row_number().over(Window.partitionBy("register", *keys).orderBy(F.desc("n"), "token"))).filter(F.col("r") <= top_n).drop("r")
    side = lambda s: F.max(F.when(F.col("register") == s, F.col("n")))
    both = passed.groupBy(*keys, "token").agg(side(sides[0]).alias("n_a"), side(sides[1]).alias("n_b")).filter("n_a is not null and n_b is not null")
    return rank_correlation(both, keys)


def ranked_before_alignment(lists: DataFrame, keys: list[str], sides: tuple = ("web", "social"), per_10m: float = 5.0) -> DataFrame:
    """Variant: ranks are taken in the whole lists."""
    ranked = apply_rate_threshold(lists, ["register", *keys], per_10m).withColumn("r", average_rank(F.col("n"), ["register", *keys]))
    side = lambda s: F.max(F.when(F.col("register") == s, F.col("r")))
    both = ranked.groupBy(*keys, "token").agg(side(sides[0]).alias("a"), side(sides[1]).alias("b")).filter("a is not null and b is not null")
    return both.groupBy(*keys).agg(F.count(F.lit(1)).alias("n_shared"), safe_corr("a", "b").alias("rho"))


def chi2_similarity(lists: DataFrame, keys: list[str], sides: tuple = ("web", "social"), top_n: int = 500) -> DataFrame:
    """Chi-square over the most frequent joint tokens, and per degree of freedom."""
    side = lambda s: F.coalesce(F.sum(F.when(F.col("register") == s, F.col("n"))), F.lit(0))
    both = lists.groupBy(*keys, "token").agg(side(sides[0]).alias("o1"), side(sides[1]).alias("o2"))
    own = Window.partitionBy(*keys)
    both = both.withColumns({"t1": F.sum("o1").over(own), "t2": F.sum("o2").over(own), "r": F.row_number().over(own.orderBy(F.desc(F.col("o1") + F.col("o2")), "token"))}).filter(F.col("r") <= top_n)
    e = lambda t: F.col(t) * (F.col("o1") + F.col("o2")) / (F.col("t1") + F.col("t2"))
    term = F.pow(F.col("o1") - e("t1"), 2) / e("t1") + F.pow(F.col("o2") - e("t2"), 2) / e("t2")
    return both.filter("t1 > 0 and t2 > 0").groupBy(*keys).agg(F.count(F.lit(1)).alias("n_tokens"), F.sum(term).alias("chi2")).withColumn("chi2_per_df", F.try_divide(F.col("chi2"), F.col("n_tokens") - 1))


def baseline(sim: DataFrame, language: str, countries: list) -> DataFrame:
    return sim.filter((F.col("lang") == language) & F.col("country").isin(*countries)).agg(F.count(F.lit(1)).alias("n"), F.avg("n_shared").alias("avg_unigrams"), F.avg("rho").alias("avg_rho"))


def similarity_by(sim: DataFrame, key: str, least: int = 2, ddof: int = 1) -> DataFrame:
    sd = F.stddev_samp if ddof else F.stddev_pop
    return sim.groupBy(key).agg(F.count(F.lit(1)).alias("n"), F.avg("rho").alias("avg_rho"), sd("rho").alias("sd_rho")).filter(F.col("n") >= least)


def pairs_above(sim: DataFrame, cut: float, language: str = "en") -> DataFrame:
    over = F.col("rho") > cut
    return sim.agg(F.count(F.lit(1)).alias("n"), F.count_if(over).alias("n_above"), F.count_if(over & (F.col("lang") == language)).alias("n_above_language"))


def pairwise_similarity(lists: DataFrame, keys: list[str], country: str = "country", per_10m: float = 5.0) -> DataFrame:
    """All country pairs of one language inside a register: ``keys, c1, c2, n_shared, rho``."""
    passed = apply_rate_threshold(lists, [*keys, country], per_10m)
    a = passed.select(*keys, "token", F.col(country).alias("c1"), F.col("n").alias("n_a"))
    b = passed.select(*keys, "token", F.col(country).alias("c2"), F.col("n").alias("n_b"))
    return rank_correlation(a.join(b, [*keys, "token"]).filter("c1 < c2"), [*keys, "c1", "c2"])


def variation_by_language(pairs: DataFrame) -> DataFrame:
    """Mean and population SD of the pairs, web and social side by side."""
    pick = lambda r: F.when(F.col("register") == r, F.col("rho"))
    return pairs.groupBy("lang").agg(F.avg(pick("web")).alias("web_rho"), F.stddev_pop(pick("web")).alias("web_sd"), F.avg(pick("social")).alias("social_rho"), F.stddev_pop(pick("social")).alias("social_sd"))


def correlation_with_t(table: DataFrame, a: str, b: str) -> DataFrame:
    """r, n and the t statistic of two columns of a small table."""
    got = table.filter(F.col(a).isNotNull() & F.col(b).isNotNull()).agg(safe_corr(a, b).alias("r"), F.count(F.lit(1)).alias("n"))
    return got.withColumn("t", F.try_divide(F.col("r") * F.sqrt(F.greatest(F.col("n") - 2, F.lit(0))), F.sqrt(1 - F.col("r") * F.col("r"))))
