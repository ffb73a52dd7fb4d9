"""Raw pages to corpus rows."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusmap.functions.geo import cap_pages, with_country
from corpusmap.functions.text import NoiseRules, n_words, paragraphs
from corpusmap.operators.dedup import unique_samples


@dataclass
class BuildConfig:
    rules: NoiseRules = field(default_factory=NoiseRules)
    keep: str = "none"
    site_scope: str = "period"
    non_latin_tlds: bool = True
    page_ceiling: int | None = None

    @classmethod
    def earlier(cls) -> BuildConfig:
        """One length limit for all scripts, Latin domains only, a low page ceiling."""
        return cls(NoiseRules(script_aware=False), non_latin_tlds=False, page_ceiling=50)

    def pages(self, pages: DataFrame, domains: DataFrame | None = None, key: str = "page_id") -> DataFrame:
        """The pages this corpus is made of: those of a usable country domain of ``domains``, if given, up to the ceiling of each country."""
        if domains is not None:
            pages = with_country(pages.drop("country"), domains, non_latin=self.non_latin_tlds).drop("tld")
        return cap_pages(pages, "country", self.page_ceiling, key) if self.page_ceiling else pages


def samples_of(pages: DataFrame, cfg: BuildConfig) -> DataFrame:
    """Kept samples of ``pages(page_id, host, period, html, ...)``: rules, two-scope de-duplication, cleaning, length."""
    # the limit on length holds after cleaning, the other rules and the fingerprints on the raw text
    good = paragraphs(pages, rules=cfg.rules).filter("reason IS NULL")
    kept = unique_samples(good, ["page_id", "pos"], site="host", keep=cfg.keep, site_scope=cfg.site_scope)
    return kept.withColumn("text", F.col("clean")).drop("clean", "reason")


def assemble(samples: DataFrame, keys: list[str], text: str = "text", pos: str = "pos") -> DataFrame:
    """One row per ``keys`` with the samples in order, a line each, and the number of words."""
    rows = F.array_sort(F.collect_list(F.struct(F.col(pos).alias("p"), F.col(text).alias("t"))))
    return samples.groupBy(*keys).agg(F.count(F.lit(1)).alias("n_samples"), F.sum(n_words(F.col(text))).alias("n_words"), F.array_join(F.transform(rows, lambda r: r["t"]), "\n").alias("text"))


def build_corpus(pages: DataFrame, cfg: BuildConfig | None = None, label=None, domains: DataFrame | None = None) -> DataFrame:
    """Corpus rows (page_id, url, country, language, n_samples, n_words, text).

    ``label`` maps samples to samples with a column ``language``; without it
    the column ``lang`` of the pages is the label. ``domains`` gives countries
    (see ``with_country``); without it the pages have a column ``country``.
    """
    cfg = cfg or BuildConfig()
    kept = samples_of(cfg.pages(pages, domains), cfg)
    kept = label(kept) if label else kept.withColumn("language", F.col("lang"))
    return assemble(kept, ["page_id", "url", "country", "language"])
