"""Text columns: words, cleaning, script shares, noise rules, paragraphs, windows, trigram buckets."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: fixed values: scripts whose words are not set apart by letters and blanks
NON_ALPHABETIC = ("Han", "Hiragana", "Katakana", "Hangul", "Thai", "Lao", "Khmer", "Myanmar", "Tibetan")


def words(text: Column) -> Column:
    return F.regexp_extract_all(F.lower(text), F.lit(r"\p{L}+"), F.lit(0))


def n_words(text: Column) -> Column:
    return F.regexp_count(text, F.lit(r"\p{L}+")).cast("long")


def clean_text(text: Column) -> Column:
    """Addresses, hash tags, mentions, symbols and emoji go; blanks are squeezed."""
    out = F.regexp_replace(text, r"https?://[^\s]+|www\.[^\s]+", " ")
    out = F.regexp_replace(out, r"[#@][\p{L}\p{N}_]+", " ")
    out = F.regexp_replace(out, r"[^\p{L}\p{M}\p{N}\p{P}\p{Z}\s]", " ")
    return F.trim(F.regexp_replace(out, r"\s+", " "))


def non_alphabetic_share(text: Column) -> Column:
    kind = "".join(rf"\p{{Is{s}}}" for s in NON_ALPHABETIC)
    letters = F.regexp_count(text, F.lit(r"\p{L}"))
    return F.when(letters == 0, 0.0).otherwise(F.regexp_count(text, F.lit(f"[{kind}]")) / letters)


def long_enough(text: Column, min_words: int = 15, min_chars: int = 30, script_aware: bool = True) -> Column:
    """Enough words, or enough characters where the script has no words set apart."""
    by_words = n_words(text) >= min_words
    if not script_aware:
        return by_words
    return F.when(non_alphabetic_share(text) > 0.5, F.char_length(text) >= min_chars).otherwise(by_words)


@dataclass
class NoiseRules:
    min_words: int = 15
    min_chars: int = 30
    script_aware: bool = True
    error_words: tuple = ("error", "errors", "404", "forbidden", "unavailable")
    max_error_hits: int = 1
    nav_chars: str = "|"
    max_nav_chars: int = 4
    extra: list = field(default_factory=list)  # (name, Column -> Column that is true for noise)


def reject_reason(text: Column, rules: NoiseRules | None = None, clean: Column | None = None) -> Column:
    """The first rule that a sample breaks; null if none. ``clean``: its cleaned text, if at hand."""
    r = rules or NoiseRules()
    clean = clean_text(text) if clean is None else clean
    errors = F.regexp_count(F.lower(text), F.lit(r"\b(" + "|".join(r.error_words) + r")\b"))
    nav = F.char_length(text) - F.char_length(F.translate(text, r.nav_chars, ""))
    out = F.when(~long_enough(clean, r.min_words, r.min_chars, r.script_aware), "short").when(errors > r.max_error_hits, "error").when(nav > r.max_nav_chars, "navigation")
    for name, test in r.extra:
        out = out.when(test(text), name)
    return out


def paragraphs(pages: DataFrame, html: str = "html", rules: NoiseRules | None = None) -> DataFrame:
    """One row per non-empty ``<p>`` block: ``pos`` and ``text``; unclosed blocks end at the next block tag.

    With ``rules`` also ``clean``, the cleaned text, and ``reason``, as ``reject_reason`` gives it.
    """
    plain = F.regexp_replace(html, r"(?is)<(script|style)[^>]*>.*?</(script|style)>|<!--.*?-->", "")
    parts = F.slice(F.split(plain, r"(?i)<p(\s[^>]*)?>"), 2, 1 << 20)

    def sample(part: Column) -> Column:
        part = F.element_at(F.split(part, r"(?i)</p>|</article>|</div>|</body>|<footer"), 1)
        out = F.trim(F.regexp_replace(F.regexp_replace(part, r"<[^>]*>", " "), r"\s+", " "))
        for entity, char in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&nbsp;", " "), ("&amp;", "&")):
            out = F.replace(out, F.lit(entity), F.lit(char))
        return out

    rest = [c for c in pages.columns if c != html]
    # the texts are made before they are exploded: what follows refers to a column and does not work them out again
    if rules is None:
        return pages.select(*rest, F.posexplode(F.transform(parts, sample)).alias("pos", "text")).filter("text <> ''")
    both = F.transform(F.transform(parts, sample), lambda t: F.struct(t.alias("text"), clean_text(t).alias("clean")))
    all_three = F.transform(both, lambda s: F.struct(s["text"].alias("text"), s["clean"].alias("clean"), reject_reason(s["text"], rules, s["clean"]).alias("reason")))
    return pages.select(*rest, F.posexplode(all_three).alias("pos", "_s")).select(*rest, "pos", "_s.*").filter("text <> ''")


def lines(docs: DataFrame, text: str = "text") -> DataFrame:
    rest = [c for c in docs.columns if c != text]
    return docs.select(*rest, F.posexplode(F.split(text, "\n")).alias("pos", "text")).withColumn("text", F.trim("text")).filter("text <> ''")


def windows(docs: DataFrame, text: str = "text", size: int = 50, step: int | None = None) -> DataFrame:
    """Windows of exactly ``size`` characters; texts that are shorter give none."""
    step = step or size
    if step == size:  # one pass over the text, however long
        rest = [c for c in docs.columns if c != text]
        return docs.select(*rest, F.posexplode(F.regexp_extract_all(F.col(text), F.lit(f"(?s).{{{size}}}"), F.lit(0))).alias("win", "window"))
    count = F.when(F.char_length(text) >= size, F.floor((F.char_length(text) - size) / step) + 1).otherwise(0)
    at = F.when(count > 0, F.sequence(F.lit(0), (count - 1).cast("int"))).otherwise(F.array().cast("array<int>"))
    rest = [c for c in docs.columns if c != text]
    return docs.select(*rest, F.col(text).alias("_t"), F.explode(at).alias("win")).withColumn("window", F.substring(F.col("_t"), F.col("win") * step + 1, F.lit(size))).drop("_t")


def ngrams(text: Column, n: int) -> Column:
    def of(t: Column) -> Column:
        last = F.char_length(t) - n + 1
        return F.when(last >= 1, F.transform(F.sequence(F.lit(1), F.greatest(last, F.lit(1))), lambda i: F.substring(t, i, F.lit(n)))).otherwise(F.array().cast("array<string>"))

    # bound as a variable, the text is worked out once, not once a gram
    return F.element_at(F.transform(F.array(text), of), 1)


def trigram_buckets(text: Column, dims: int = 216_000, portable: bool = False) -> Column:
    """Bucket numbers of character trigrams; ``portable`` hashes with MD5, as other engines can."""
    def bucket(g: Column) -> Column:
        return (F.conv(F.substring(F.md5(g), 1, 8), 16, 10).cast("long") % dims if portable else F.pmod(F.xxhash64(g), F.lit(dims))).cast("int")

    return F.transform(ngrams(F.lower(text), 3), bucket)
