"""Language identification: sampling, splits, n-gram Bayes baselines, purge, F1; the neural model is in ``mlp``."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from corpusmap.functions.text import ngrams
from corpusmap.session import materialize, ship

MAJORITY = ("en", "es", "fr")


def unit_hash(*parts: Column) -> Column:
    """A number in [0, 1) from MD5, as any engine can compute it."""
    return F.conv(F.substring(F.md5(F.concat_ws("|", *parts)), 1, 8), 16, 10).cast("double") / 4294967296.0


def split_three(docs: DataFrame, doc: Column, shares: tuple = (0.8, 0.1, 0.1), seed: str = "split", truth: Column | None = None) -> DataFrame:
    """Column ``split``, by document, so that the windows of one text stay together; only true labels are evaluated."""
    u = unit_hash(F.lit(seed), doc.cast("string"))
    split = F.when(u < shares[0], "train").when(u < shares[0] + shares[1], "test").otherwise("evaluation")
    return docs.withColumn("split", F.when(~truth, "train").otherwise(split) if truth is not None else split)


def balanced_epoch(rows: DataFrame, by: tuple, key: str, per_pair: int, epoch: int = 0, seed: str = "epoch") -> DataFrame:
    """Exactly ``per_pair`` rows of each pair: large pairs are thinned by hash before they are ranked, small ones repeat."""
    counts = rows.groupBy(*by).agg(F.count(F.lit(1)).alias("_n"))
    copies = F.ceil(F.lit(per_pair) / F.col("_n")).cast("int")
    order = F.md5(F.concat_ws("|", F.lit(seed), F.lit(str(epoch)), F.col(key).cast("string"), F.col("_copy").cast("string")))
    many = rows.join(F.broadcast(counts), list(by)).withColumn("_copy", F.explode(F.sequence(F.lit(1), copies))).withColumn("_o", order)
    unit = F.conv(F.substring("_o", 1, 8), 16, 10).cast("double") / 4294967296.0
    thin = many.filter(unit < (2.0 * per_pair + 100) / F.col("_n"))
    return thin.withColumn("_r", F.row_number().over(Window.partitionBy(*by).orderBy("_o", key))).filter(F.col("_r") <= per_pair).drop("_n", "_copy", "_o", "_r")


def natural_epoch(rows: DataFrame, key: str, share: float, epoch: int = 0) -> DataFrame:
    return rows.filter(unit_hash(F.lit(f"natural{epoch}"), F.col(key).cast("string")) < share)


def byte_ngrams(text: Column, n: int) -> Column:
    """Grams of ``n`` UTF-8 bytes as hexadecimal digits."""
    def of(h: Column) -> Column:
        last = F.length(h) / 2 - n + 1
        return F.when(last >= 1, F.transform(F.sequence(F.lit(1), F.greatest(last, F.lit(1)).cast("int")), lambda i: F.substring(h, 2 * i - 1, F.lit(2 * n)))).otherwise(F.array().cast("array<string>"))

    return F.element_at(F.transform(F.array(F.hex(F.encode(text, "UTF-8"))), of), 1)


def _grams(text: Column, ns: tuple[int, ...], of) -> Column:
    """Grams of several lengths; no gram stands for one of another length."""
    return of(text, ns[0]) if len(ns) == 1 else F.concat(*[of(text, n) for n in ns])


def bayes_table(train: DataFrame, label: str, text: str, n: int | tuple[int, ...], least: int = 2, features: DataFrame | None = None, of=ngrams) -> DataFrame:
    """``gram, logp array<double>``: Laplace-smoothed grams, a row per gram with a place for each language in code-point order.

    The languages are ``bayes_languages(train, label)``; the rows are bounded by the features.
    """
    ns = (n,) if isinstance(n, int) else tuple(n)
    langs = bayes_languages(train, label)
    counts = train.select(F.col(label).alias("lang"), F.explode(_grams(F.lower(F.col(text)), ns, of)).alias("gram")).groupBy("gram", "lang").agg(F.count(F.lit(1)).alias("n"))
    return _table(counts, langs, least, features)


def _table(counts: DataFrame, langs: list[str], least: int, features: DataFrame | None) -> DataFrame:
    """The table of :func:`bayes_table` from ``counts(gram, lang, n)``."""
    told = F.collect_list(F.when(F.col("lang").isNotNull(), F.struct("lang", "n")))
    rows = counts.groupBy("gram").agg(F.sum("n").alias("all"), F.map_from_entries(told).alias("m")).filter(F.col("all") >= least)
    if features is not None:
        rows = rows.join(features.select("gram"), "gram", "left_semi")
    rows = materialize(rows.select("gram", F.array(*[F.coalesce(F.try_element_at("m", F.lit(v)), F.lit(0)) for v in langs]).alias("n")), "bayes-counts")
    totals = rows.agg(F.count(F.lit(1)).alias("size"), *[F.sum(F.col("n")[i]).alias(f"t{i}") for i in range(len(langs))]).first()  # one row
    size = int(totals["size"])
    logs = [F.when(F.lit(bool(totals[f"t{i}"])), F.ln((F.col("n")[i] + 1) / F.lit(float((totals[f"t{i}"] or 0) + size)))).alias(f"l{i}") for i in range(len(langs))]
    return materialize(rows.select("gram", F.array(*logs).alias("logp")), "bayes-table")


def bayes_languages(train: DataFrame, label: str) -> list[str]:
    """Labels in code-point order; some hundreds at most."""
    return sorted((r[0] for r in train.select(label).distinct().collect() if r[0] is not None), key=lambda v: v.encode())


#: bytes of a table of grams that is broadcast; a larger one is joined by a shuffle
BROADCAST_BYTES = 64 << 20


def _small(table: DataFrame, n_langs: int) -> DataFrame:
    return F.broadcast(table) if table.count() * (8 * n_langs + 32) <= BROADCAST_BYTES else table


def bayes_scores(samples: DataFrame, key: list[str], text: str, table: DataFrame, n: int | tuple[int, ...], langs: list[str], of=ngrams) -> DataFrame:
    """``key, s array<double>``: sums of log-probabilities by language, for samples that hold a known gram.

    One row per gram of a sample meets the table; its sums are combined in
    the task where the table is broadcast, so one row per sample is shuffled,
    not one per language. Sums are exact and rounded once: neither the order
    of the grams nor the partitions change them.
    """
    ns = (n,) if isinstance(n, int) else tuple(n)
    grams = samples.select(*key, F.explode(_grams(F.lower(F.col(text)), ns, of)).alias("gram"))
    halves = table.select("gram", F.transform("logp", lambda x: F.floor(x * UNIT)).alias("whole"), F.transform("logp", lambda x: x * UNIT - F.floor(x * UNIT)).alias("rest"))
    met = grams.join(_small(halves, 2 * len(langs)), "gram")
    sums = met.groupBy(*key).agg(*[F.sum(F.col(c)[i]).alias(f"{c}{i}") for i in range(len(langs)) for c in ("whole", "rest")])
    return sums.select(*key, _rounded_sums(len(langs)).alias("s"))


#: log-probabilities are added in whole units of 1 / UNIT and their rests apart; both sums are exact in double precision
UNIT = float(1 << 30)


def _rounded_sums(n_langs: int) -> Column:
    """Scores from the columns ``whole<i>`` and ``rest<i>``."""
    return F.array(*[F.round((F.col(f"whole{i}") + F.col(f"rest{i}")) / UNIT, 6) for i in range(n_langs)])


def _best_label(s: Column, langs: list[str]) -> Column:
    return F.element_at(F.array(*[F.lit(v) for v in langs]), F.array_position(s, F.array_max(s)).cast("int"))  # the first place of the largest


def bayes_predict(samples: DataFrame, key: list[str], text: str, table: DataFrame, n: int | tuple[int, ...], langs: list[str], of=ngrams) -> DataFrame:
    """``key, predicted, score``: the largest sum wins, ties to the smaller label."""
    scores = bayes_scores(samples, key, text, table, n, langs, of)
    return scores.select(*key, _best_label(F.col("s"), langs).alias("predicted"), F.array_max("s").alias("score"))


def information_gain(train: DataFrame, label: str, text: str, n: int | tuple[int, ...], least: int = 5, of=ngrams) -> DataFrame:
    """``gram, ig``: gain of a gram's presence about ``label``."""
    ns = (n,) if isinstance(n, int) else tuple(n)
    present = train.select(F.col(label).alias("y"), F.explode(F.array_distinct(_grams(F.lower(F.col(text)), ns, of))).alias("gram")).groupBy("gram", "y").agg(F.count(F.lit(1)).alias("k"))
    return _gain(present, {r[0]: r[1] for r in train.groupBy(label).agg(F.count(F.lit(1))).collect()}, least)  # a row per label


def _gain(present: DataFrame, sizes: dict, least: int) -> DataFrame:
    """``gram, ig`` from ``present(gram, y, k)``, samples with the gram by label, and the samples of each label."""
    total = float(sum(sizes.values()))
    part = lambda o, e: F.when(o > 0, o / total * F.ln(o * total / e)).otherwise(0.0)
    m = F.element_at(F.create_map(*[x for y, k in sorted(sizes.items(), key=str) if y is not None for x in (F.lit(y), F.lit(float(k)))]), F.col("y"))
    # of labels without the gram only their sizes count: their terms add up to those of the rest of all samples
    seen = present.withColumn("m", m).groupBy("gram").agg(F.sum("k").alias("g"), F.sort_array(F.collect_list(F.when(F.col("y").isNotNull(), F.struct("k", "m")))).alias("cells"), F.sum("m").alias("met")).filter(F.col("g") >= least)
    gain = F.aggregate("cells", F.lit(0.0), lambda s, c: s + part(c["k"], F.col("g") * c["m"]) + part(c["m"] - c["k"], (total - F.col("g")) * c["m"]))
    rest = F.lit(total) - F.col("met")
    return seen.select("gram", (gain + F.when(rest > 0, rest / total * F.ln(total / (total - F.col("g")))).otherwise(0.0)).alias("ig"))


def selected_features(train: DataFrame, text: str, n: int | tuple[int, ...], most: int, language: str = "lang", domain: str = "domain", of=ngrams) -> DataFrame:
    """The grams that tell languages, not domains: largest gain for the language less that for the domain, one ranking over all lengths."""
    return _ranked(information_gain(train, language, text, n, of=of), information_gain(train, domain, text, n, of=of), most)


def _ranked(a: DataFrame, b: DataFrame, most: int) -> DataFrame:
    return a.join(b.withColumnRenamed("ig", "ig_domain"), "gram").select("gram", F.round(F.col("ig") - F.col("ig_domain"), 9).alias("score")).orderBy(F.desc("score"), "gram").limit(most)


#: bits of the number of a gram of up to four bytes (a one, then its bytes); samples worked at once; counts held in a task
GRAM_BITS, SAMPLES, HELD = 33, 1 << 13, 1 << 20
#: stands for the whole sample among the numbers of grams
WHOLE = 0


def gram_numbers(texts: pa.Array, ns: tuple[int, ...]) -> tuple[np.ndarray, np.ndarray]:
    """Place of the text and number of every gram of ``ns`` bytes, four at most, of binary ``texts``."""
    wide = pa.types.is_large_binary(texts.type)
    at = np.frombuffer(texts.buffers()[1], dtype=np.int64 if wide else np.int32)[texts.offset: texts.offset + len(texts) + 1].astype(np.int64) if len(texts) else np.zeros(1, dtype=np.int64)
    data = np.frombuffer(texts.buffers()[2] or b"", dtype=np.uint8)[at[0]: at[-1]]
    size = np.diff(at)
    owner = np.repeat(np.arange(len(size)), size)
    left = np.repeat(at[1:] - at[0], size) - np.arange(len(data))  # bytes from here to the end of the text
    number, found = np.ones(len(data), dtype=np.int64), []
    for n in range(1, max(ns) + 1):
        number = number[: max(len(data) - n + 1, 0)] << 8 | data[n - 1:]
        if n in ns:
            fits = left[: len(number)] >= n
            found.append((owner[: len(number)][fits], number[fits]))
    return np.concatenate([o for o, _ in found]), np.concatenate([c for _, c in found])


def byte_gram_counts(train: DataFrame, by: list[str], text: str, ns: tuple[int, ...] = (1, 2, 3, 4)) -> DataFrame:
    """``gram, *by, k, n``: samples that hold a gram of lower-cased bytes and its occurrences, all of one pass; the empty gram counts the samples.

    Grams are counted as numbers inside the task before any row leaves it.
    Numbers hold four bytes at most; longer grams: :func:`information_gain`, :func:`bayes_table`.
    """
    if max(ns) > 4:
        raise ValueError("grams of four bytes at most")
    ship(train.sparkSession)
    low = (1 << GRAM_BITS) - 1

    def merged(parts: list) -> list:
        key, k, n = (np.concatenate(c) for c in zip(*parts, strict=True))
        order = np.argsort(key)
        key = key[order]
        starts = np.flatnonzero(np.append(True, key[1:] != key[:-1])[: len(key)])
        return [(key[starts], np.add.reduceat(k[order], starts), np.add.reduceat(n[order], starts))]

    def rows(part: tuple, cells: dict) -> Iterator[pa.RecordBatch]:
        names = [pa.array(list(c), type=t) for c, t in zip(zip(*cells, strict=True), types, strict=True)]
        for at in range(0, len(part[0]), 1 << 16):
            key, k, n = (c[at: at + (1 << 16)] for c in part)
            yield pa.RecordBatch.from_arrays([pa.array(key & low), *(c.take(pa.array(key >> GRAM_BITS)) for c in names), pa.array(k), pa.array(n)], names=["gram", *by, "k", "n"])

    types: list = []

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cells, held = {}, []
        for b in batches:
            types[:] = [c.type for c in b.columns[:-1]]
            for at in range(0, b.num_rows, SAMPLES):
                part = b.slice(at, SAMPLES)
                cell = np.array([cells.setdefault(c, len(cells)) for c in zip(*(c.to_pylist() for c in part.columns[:-1]), strict=True)], dtype=np.int64)
                told, near = np.unique(cell, return_inverse=True)
                owner, number = gram_numbers(part.column(len(by)), ns)
                key = np.sort((near[owner] << GRAM_BITS | number) << 13 | owner)
                pair = key >> 13
                starts = np.flatnonzero(np.append(True, pair[1:] != pair[:-1])[: len(key)])
                if len(key):
                    first = np.append(True, key[1:] != key[:-1]).astype(np.int64)  # a gram's first occurrence in a sample
                    top = pair[starts]
                    held.append((told[top >> GRAM_BITS] << GRAM_BITS | top & low, np.add.reduceat(first, starts), np.diff(np.append(starts, len(key)))))
                whole = np.bincount(near)
                held.append((told << GRAM_BITS | WHOLE, whole, whole))
                if sum(len(h[0]) for h in held) > 2 * HELD:
                    held = merged(held)
                    if len(held[0][0]) > HELD:
                        yield from rows(held[0], cells)
                        held = []
        if held:
            yield from rows(merged(held)[0], cells)

    kept = train.select(*by, F.coalesce(F.lower(F.col(text)), F.lit("")).cast("binary").alias("gram_bytes"))
    zero = F.lit(0).cast("long")
    schema = train.select(zero.alias("gram"), *by, zero.alias("k"), zero.alias("n")).schema
    some = kept.mapInArrow(run, schema).groupBy("gram", *by).agg(F.sum("k").alias("k"), F.sum("n").alias("n"))
    return some.withColumn("gram", F.when(F.col("gram") == WHOLE, "").otherwise(F.substring(F.hex("gram"), 2, 8)))


def selecting_model(train: DataFrame, text: str, most: int, ns: tuple[int, ...] = (1, 2, 3, 4), language: str = "lang", domain: str = "domain", least: int = 2) -> tuple[DataFrame, list[str]]:
    """The table and languages of the Bayes model over :func:`selected_features` of bytes, from one pass over ``train``."""
    counts = materialize(byte_gram_counts(train, [language, domain], text, ns), "gram-counts")
    whole = counts.filter("gram = ''").select(language, domain, "k").collect()  # a row per language and domain
    counts = counts.filter("gram <> ''")

    def gain(label: str) -> DataFrame:
        sizes: dict = {}
        for r in whole:
            sizes[r[label]] = sizes.get(r[label], 0) + r["k"]
        return _gain(counts.groupBy("gram", F.col(label).alias("y")).agg(F.sum("k").alias("k")), sizes, 5)

    langs = sorted({r[language] for r in whole if r[language] is not None}, key=lambda v: v.encode())
    features = materialize(_ranked(gain(language), gain(domain), most), "gram-features")
    return _table(counts.groupBy("gram", F.col(language).alias("lang")).agg(F.sum("n").alias("n")), langs, least, features), langs


def with_prediction(samples: DataFrame, key: list[str], text: str, table: DataFrame, langs: list[str], ns: tuple[int, ...] = (1, 2, 3, 4), unique: bool = False) -> DataFrame:
    """``samples`` without ``text`` and with ``predicted``, as :func:`bayes_predict` of lower-cased byte grams tells it for their key.

    The table meets the samples inside the task. Samples of one key are judged
    together; ``unique``: no two share one, so nothing is shuffled. A sample
    without known gram or with a null in its key has no prediction.
    """
    rest = [c for c in samples.columns if c != text]
    if table.count() * (16 * len(langs) + 32) > BROADCAST_BYTES:
        return samples.drop(text).join(bayes_predict(samples, key, text, table, ns, langs, of=byte_ngrams), key, "left")
    ship(samples.sparkSession)
    got = table.toArrow()  # within BROADCAST_BYTES
    number = np.array([int("1" + g, 16) for g in got.column("gram").to_pylist()], dtype=np.int64)
    logp = np.array(got.column("logp").to_pylist(), dtype=np.float64).reshape(len(number), len(langs))[np.argsort(number)] * UNIT
    held = samples.sparkSession.sparkContext.broadcast((np.sort(number), np.floor(logp).T.copy(), (logp - np.floor(logp)).T.copy()))
    live = [i for i in range(len(langs)) if len(number) and not np.isnan(logp[:, i]).any()]  # a language without any counted gram is no candidate
    sums = [f"{c}{i}" for i in live for c in ("whole", "rest")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, whole, left = held.value
        for b in batches:
            for at in range(0, b.num_rows, SAMPLES):
                part = b.slice(at, SAMPLES)
                owner, number = gram_numbers(part.column(len(rest)), ns)
                place = np.minimum(np.searchsorted(known, number), len(known) - 1) if len(known) else number[:0]
                hit = known[place] == number if len(known) else np.zeros(0, dtype=bool)
                owner, place = (owner[hit], place[hit]) if len(known) else (number[:0], number[:0])
                of = lambda w, o=owner, p=place, n=part.num_rows: pa.array(np.bincount(o, weights=w[p], minlength=n))
                hits = pa.array(np.bincount(owner, minlength=part.num_rows).astype(np.int64))
                yield pa.RecordBatch.from_arrays([*part.columns[:-1], hits, *(of(w[i]) for i in live for w in (whole, left))], names=[*rest, "hits", *sums])

    kept = samples.select(*rest, F.coalesce(F.lower(F.col(text)), F.lit("")).cast("binary").alias("gram_bytes"))
    like = kept.drop("gram_bytes").withColumn("hits", F.lit(0).cast("long")).withColumns({c: F.lit(0.0) for c in sums})
    out = kept.mapInArrow(run, like.schema)
    if not unique:
        out = out.select(*rest, *[F.sum(c).over(Window.partitionBy(*key)).alias(c) for c in ("hits", *sums)])
    if not live:
        return out.select(*rest, F.lit(None).cast("string").alias("predicted"))
    score = F.array(*[F.round((F.col(f"whole{i}") + F.col(f"rest{i}")) / UNIT, 6) for i in live])
    told = F.col("hits") > 0
    for k in key:
        told = told & F.col(k).isNotNull()
    return out.select(*rest, F.when(told, _best_label(score, [langs[i] for i in live])).alias("predicted"))


def profile_predict(samples: DataFrame, key: list[str], text: str, table: DataFrame, ns: tuple[int, ...], langs: list[str], trials: int = 5, share: float = 0.5, seed: str = "trial") -> DataFrame:
    """Naive Bayes over grams of lengths ``ns`` on random halves of them; posteriors are averaged over the trials.

    The grams of a sample are made once; each trial is a condition on their sums.
    """
    grams = samples.select(*key, F.explode(_grams(F.lower(F.col(text)), ns, ngrams)).alias("gram")).join(_small(table, len(langs)), "gram")
    drawn = [unit_hash(F.lit(f"{seed}{t}"), *[F.col(k).cast("string") for k in key], F.col("gram")) < share for t in range(trials)]
    grams = grams.withColumns({f"_d{t}": d for t, d in enumerate(drawn)})
    sums = grams.groupBy(*key).agg(*[F.sum(F.when(F.col(f"_d{t}"), F.col("logp")[i])).alias(f"s{t}_{i}") for t in range(trials) for i in range(len(langs))])

    def posterior(t: int) -> Column:
        s = F.array(*[F.col(f"s{t}_{i}") for i in range(len(langs))])
        top = F.array_max(s)
        e = F.transform(s, lambda x: F.exp(x - top))
        every = F.aggregate(e, F.lit(0.0), lambda a, b: a + b)
        return F.transform(e, lambda x: x / every)

    posts = [posterior(t) for t in range(trials)]
    mean = F.array(*[F.round(sum((F.coalesce(p[i], F.lit(0.0)) for p in posts), F.lit(0.0)) / trials, 9) for i in range(len(langs))])
    out = sums.select(*key, mean.alias("p"))
    return out.select(*key, F.element_at(F.array(*[F.lit(v) for v in langs]), F.array_position("p", F.array_max("p")).cast("int")).alias("predicted"))


def survives_purge(predicted: str = "predicted", truth: str = "is_truth", label: str = "lang", majority: tuple = MAJORITY, spare_majority: bool = False) -> Column:
    """False for a bootstrapped window that a second identifier calls a majority language."""
    keep = F.col(truth) | ~F.coalesce(F.col(predicted), F.lit("")).isin(*majority)
    return keep | F.col(label).isin(*majority) if spare_majority else keep


def purge_bootstrap(rows: DataFrame, **how) -> DataFrame:
    """``rows`` without the windows that :func:`survives_purge` denies."""
    return rows.filter(survives_purge(**how))


def assert_independent(train: DataFrame, other: DataFrame, text: str) -> DataFrame:
    """Texts of ``other`` that occur in ``train``."""
    return other.select(F.md5(text).alias("fp")).distinct().join(train.select(F.md5(text).alias("fp")).distinct(), "fp", "left_semi")


def f1_by_domain(pred: DataFrame, domain: str = "domain", label: str = "lang", predicted: str = "predicted") -> DataFrame:
    """Micro, macro and weighted F1, labels and windows of every domain.

    A label that is only predicted counts as a false positive in the micro
    figure and is no class of the macro one.
    """
    p = F.coalesce(F.col(predicted), F.lit(""))
    cells = pred.groupBy(F.col(domain).alias("domain"), F.col(label).alias("y"), p.alias("p")).agg(F.count(F.lit(1)).alias("n"))
    support = cells.groupBy("domain", F.col("y").alias("c")).agg(F.sum("n").alias("support"), F.sum(F.when(F.col("y") == F.col("p"), F.col("n")).otherwise(0)).alias("tp"))
    named = cells.groupBy("domain", F.col("p").alias("c")).agg(F.sum("n").alias("named"))
    each = support.join(named, ["domain", "c"], "left").withColumn("f1", 2 * F.col("tp") / (F.col("support") + F.coalesce("named", F.lit(0))))
    return each.groupBy("domain").agg(F.count(F.lit(1)).alias("n_langs"), F.sum("support").alias("n_test"), (F.sum("tp") / F.sum("support")).alias("f1_micro"), F.avg("f1").alias("f1_macro"), (F.sum(F.col("f1") * F.col("support")) / F.sum("support")).alias("f1_weighted"))


def languages_above(pred: DataFrame, cut: float = 0.95, label: str = "lang") -> DataFrame:
    """Languages whose F1 over all windows, rounded to two digits, reaches ``cut``."""
    one = pred.withColumn("_d", F.col(label))
    tp = one.groupBy(F.col(label).alias("c")).agg(F.count(F.lit(1)).alias("support"), F.count_if(F.col(label) == F.col("predicted")).alias("tp"))
    named = one.groupBy(F.col("predicted").alias("c")).agg(F.count(F.lit(1)).alias("named"))
    return tp.join(named, "c", "left").withColumn("f1", F.round(2 * F.col("tp") / (F.col("support") + F.coalesce("named", F.lit(0))), 2)).filter(F.col("f1") >= cut).select(F.col("c").alias("lang"), "f1")
