"""Known answers, hand-made fixtures and invariants of the methods."""

import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from corpusmap.functions import geo, text
from corpusmap.operators import build, dedup, inventory, lid, mlp, similarity

#: fixed values: within-source means of 24 languages, web and social
WITHIN = [(.628, .572), (.741, .700), (.812, .704), (.732, .690), (.758, .667), (.687, .657), (.731, .635), (.672, .649), (.474, .322), (.520, .580), (.792, .691), (.764, .635),
          (.475, .400), (.797, .653), (.726, .601), (.743, .649), (.736, .770), (.735, .622), (.661, .764), (.802, .671), (.802, .739), (.550, .262), (.693, .512), (.839, .703)]


def test_within_source_agreement(spark):
    df = spark.createDataFrame([(str(i), a, b) for i, (a, b) in enumerate(WITHIN)], "lang string, web_rho double, social_rho double")
    r = similarity.correlation_with_t(df, "web_rho", "social_rho").first()
    assert round(r["r"], 3) == 0.776 and r["n"] == 24
    m = df.agg(F.avg("web_rho"), F.avg("social_rho")).first()
    assert round(m[0], 3) == 0.703 and round(m[1], 3) == 0.619


def test_inner_circle_baseline(spark):
    six = [(.513, 21970), (.775, 32482), (.761, 30741), (.752, 30732), (.636, 23809), (.731, 29517)]
    sim = spark.createDataFrame([("en", i, n, r) for i, (r, n) in enumerate(six)], "lang string, country int, n_shared long, rho double")
    b = similarity.baseline(sim, "en", list(range(6))).first()
    assert math.floor(b["avg_rho"] * 1000) == 694 and math.floor(b["avg_unigrams"]) == 28208


def test_digital_population(spark):
    demo = spark.createDataFrame([(1, 100_000_000, 1000.0, 0.5)], "country int, population long, gdp_pc double, internet double")
    f = inventory.factors(demo).first()
    assert f["pop_net"] == 50_000_000 and f["all"] == 50_000_000_000


@pytest.mark.parametrize("n_a,n_b,rho", [([1, 2, 3, 4], [10, 20, 30, 40], 1.0), ([1, 2, 3, 4], [4, 3, 2, 1], -1.0), ([5, 5, 5], [1, 2, 3], None), ([7], [3], None), ([1, 2, 2, 3], [1, 2, 3, 3], 5 / 6)])
def test_spearman_fixtures(spark, n_a, n_b, rho):
    df = spark.createDataFrame([("k", str(i), a, b) for i, (a, b) in enumerate(zip(n_a, n_b))], "k string, token string, n_a long, n_b long")
    got = similarity.rank_correlation(df, ["k"]).first()["rho"]
    assert got is None if rho is None else abs(got - rho) < 1e-9


def test_spearman_is_blind_to_size(spark):
    random.seed(1)
    rows = [(r, "l", t, random.randint(10, 99) * k) for r, k in (("web", 1), ("social", 1)) for t in map(str, range(60))]
    lists = spark.createDataFrame(rows, "register string, lang string, token string, n long")
    bigger = lists.withColumn("n", F.when(F.col("register") == "web", F.col("n") * 50).otherwise(F.col("n")))
    one, two = (similarity.spearman_similarity(x, ["lang"]).first()["rho"] for x in (lists, bigger))
    assert one == pytest.approx(two)
    c = similarity.chi2_similarity(bigger.filter("register = 'web'").unionByName(bigger.filter("register = 'web'").withColumn("register", F.lit("social"))), ["lang"]).first()
    assert c["chi2"] == pytest.approx(0)


def test_two_scopes(spark):
    rows = [(1, 0, "A", 0, "x"), (2, 0, "A", 0, "x"), (3, 0, "B", 0, "x"), (4, 0, "A", 0, "y"), (5, 0, "B", 0, "y"), (6, 0, "A", 0, "z"), (7, 0, "A", 1, "z")]
    s = spark.createDataFrame(rows, "id int, pos int, site string, period int, text string")
    ids = lambda **k: sorted(r[0] for r in dedup.unique_samples(s, ["id", "pos"], **k).select("id").collect())
    assert ids() == [3, 6, 7]  # the copies on A are gone before the sites are compared
    assert ids(keep="first") == [1, 4, 6, 7]
    assert ids(site_scope="all") == [3]
    texts = lambda **k: {r[0] for r in dedup.unique_samples(s, ["id", "pos"], **k).select("text").collect()}
    assert texts() <= texts(keep="first")  # as texts: keeping none may keep a later copy than keeping the first
    assert sorted(r[0] for r in dedup.first_period_only(s, ["id", "pos"]).select("id").collect()) == [1, 2, 3, 4, 5, 6]


def test_paragraph_fixtures(spark):
    html = "<body><p>one<p>two <b>bold</b></p><script>x</p></script><P CLASS=x>a &amp; b</p><!-- <p>no --><p></p><pre>not</pre></body>"
    got = text.paragraphs(spark.createDataFrame([(1, html)], "page_id int, html string")).orderBy("pos").collect()
    assert [r["text"] for r in got] == ["one", "two bold", "a & b"]


def test_noise_fixtures(spark):
    long = "word " * 20
    rows = [(0, long + "||||"), (1, long + "|||||"), (2, long + "error"), (3, long + "error error"), (4, "word " * 14), (5, "漢" * 30), (6, "漢" * 29), (7, None)]
    df = spark.createDataFrame(rows, "i int, t string").withColumn("r", text.reject_reason(F.col("t")))
    got = {r["i"]: r["r"] for r in df.collect()}
    assert [got[i] for i in range(7)] == [None, "navigation", None, "error", "short", None, "short"]


def test_cleaning(spark):
    raw = "see https://a.b/c?d #tag @user and 5 € \U0001F469‍\U0001F4BB\U0001F3FD ok"
    got = spark.createDataFrame([(raw,)], "t string").select(text.clean_text(F.col("t"))).first()[0]
    assert got == "see and 5 ok"


def test_domains(spark):
    table = spark.createDataFrame([("ca", "Canada", True, "Latin"), ("fr", "France", True, "Latin"), ("tv", "Tuvalu", False, "Latin"), ("uk", "UK", True, "Latin"), ("xn--h2brj9c", "India", True, "Devanagari")], "tld string, country string, usable boolean, script string")
    urls = ["http://a.ca/x", "http://b.fr", "http://c.com", "http://d.tv", "http://g.xn--h2brj9c/", "http://h.co.uk:80/", "http://10.0.0.1/", "nothing"]
    pages = spark.createDataFrame([(u,) for u in urls], "url string")
    assert sorted(r["country"] for r in geo.with_country(pages, table).collect()) == ["Canada", "France", "India", "UK"]
    assert geo.with_country(pages, table, non_latin=False).count() == 3
    assert geo.normalise_tlds(["भारत"]) == {"भारत": "xn--h2brj9c"}


def test_radius_edges(spark):
    cities = spark.createDataFrame([(0, 0, 10.0, 179.9), (1, 1, 89.8, 0.0), (2, 2, 0.0, 0.0), (3, 3, 60.0, -179.95)], "city_id int, country int, lat double, lon double")
    random.seed(3)
    posts = [(i, *p) for i, p in enumerate([(10.0, -179.9), (89.9, 180.0), (0.449, 0.0), (0.4505, 0.0), (-0.2, -0.3), (60.1, 179.9)] + [(random.uniform(-90, 90), random.uniform(-180, 180)) for _ in range(300)] + [(random.gauss(0, .4), random.gauss(0, .4)) for _ in range(100)])]
    p = spark.createDataFrame(posts, "id int, lat double, lon double")
    a, b = (sorted((r["id"], r["city_id"]) for r in geo.within_radius(p, cities, 50.0, m).collect()) for m in ("grid", "cross"))
    assert a == b and {0, 1, 2, 5} <= {x[0] for x in a} and 3 not in {x[0] for x in a}


def test_windows_and_trigrams(spark):
    df = spark.createDataFrame([(1, "a" * 49), (2, "b" * 50), (3, "0123456789" * 12), (4, ""), (5, None)], "i int, text string")
    got = [(r["i"], r["window"]) for r in text.windows(df).collect()]
    assert sorted(i for i, _ in got) == [2, 3, 3] and all(len(w) == 50 for _, w in got)
    sizes = df.select("i", F.size(text.trigram_buckets(F.col("text"), 100)).alias("n"), F.array_max(text.trigram_buckets(F.col("text"), 100)).alias("m")).collect()
    assert {r["i"]: r["n"] for r in sizes if r["i"] in (1, 2, 4)} == {1: 47, 2: 48, 4: 0} and all((r["m"] or 0) < 100 for r in sizes)


def test_balanced_epoch_counts(spark):
    rows = [("en", "a", f"x{i}") for i in range(3)] + [("en", "b", f"y{i}") for i in range(5000)]
    got = lid.balanced_epoch(spark.createDataFrame(rows, "lang string, domain string, key string"), ("lang", "domain"), "key", 10).groupBy("domain").count().collect()
    assert {r[0]: r[1] for r in got} == {"a": 10, "b": 10}


def test_f1_by_hand(spark):
    rows = [("d", "a", "a"), ("d", "a", "b"), ("d", "b", "b"), ("d", "b", "x"), ("d", "c", "c")]
    r = lid.f1_by_domain(spark.createDataFrame(rows, "domain string, lang string, predicted string")).first()
    assert r["f1_micro"] == pytest.approx(3 / 5) and r["f1_macro"] == pytest.approx((2 / 3 + 1 / 2 + 1) / 3) and r["f1_weighted"] == pytest.approx((2 * 2 / 3 + 2 * .5 + 1) / 5)


def test_purge(spark):
    rows = [(1, True, "de", "en"), (2, False, "de", "en"), (3, False, "de", "de"), (4, False, "en", "en")]
    df = spark.createDataFrame(rows, "i int, is_truth boolean, lang string, predicted string")
    assert sorted(r["i"] for r in lid.purge_bootstrap(df).collect()) == [1, 3]
    assert sorted(r["i"] for r in lid.purge_bootstrap(df, spare_majority=True).collect()) == [1, 3, 4]


def test_mlp_learns(spark):
    rng = random.Random(2)
    words = {"aa": ["kala", "moro", "tiki"], "bb": ["stru", "blen", "grat"]}
    line = lambda w: " ".join(rng.choice(w) for _ in range(12))[:50]
    rows = [(lang, line(w)) for lang, w in words.items() for _ in range(200)]
    df = spark.createDataFrame(rows, "lang string, window string")
    cfg = mlp.MLPConfig(dims=512, hidden=(32, 32, 32), epochs=4)
    model = mlp.train_mlp(lambda e: mlp.epoch_arrays(df, "window", "lang", ["aa", "bb"], 512), ["aa", "bb"], cfg)
    got = mlp.predict(df.union(spark.createDataFrame([("aa", "x")], df.schema)), model)
    assert got.filter("lang = predicted").count() >= 396 and got.filter("predicted is null").count() == 1
    flat, starts, share = mlp.bags([[1, 2], [3]])
    assert model.first_layer(flat, starts, share)[0] == pytest.approx((model.weights[0][1] + model.weights[0][2]) / 2 + model.biases[0], abs=1e-5)


def test_build_edges(spark):
    good = " ".join(f"wort{chr(97 + i)}" for i in range(16))
    html = lambda *p: "<body>" + "".join(f"<p>{x}</p>" for x in p) + "</body>"
    pages = spark.createDataFrame([(1, "http://a", "a", 0, 0, "de", html(good, "short")), (2, "http://b", "b", 0, 0, "de", html(good + " eins", good)), (3, "http://c", "c", 0, 0, "de", None)], "page_id int, url string, host string, period int, country int, lang string, html string")
    got = build.build_corpus(pages).collect()
    assert [(r["page_id"], r["n_samples"], r["n_words"]) for r in got] == [(2, 1, 17)]
    assert build.build_corpus(pages.limit(0)).count() == 0


def test_plans(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    plan = similarity.unigram_counts(docs.filter("lang = 'en'"), ["lang"])._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(lang), EqualTo(lang,en)]" in plan and "n_chars" not in plan and "Python" not in plan


def test_streams_equal_batch(spark, tmp_path):
    from corpusmap.streaming import ingest

    rows = [(f"2024-01-0{d} 0{h}:00:00", d * h % 3, "x" if h % 2 else "y", 1.5) for d in (1, 2, 3) for h in range(8)] + [("2024-01-09 00:00:00", 9, "late", 0.0)]
    e = spark.createDataFrame(rows, "ts string, user_id long, event_type string, value double").withColumn("ts", F.col("ts").cast("timestamp"))
    e.coalesce(1).write.parquet(str(tmp_path / "in"))
    feed = ingest.with_lateness(ingest.read_feed(spark, str(tmp_path / "in"), e.schema))
    keys = ["user_id", "event_type"]
    ingest.run_available(ingest.keep_singletons(feed, keys), str(tmp_path / "one"), str(tmp_path / "c1"))
    closed = lambda df: sorted(map(str, df.filter("period < '2024-01-08'").collect()))
    assert closed(spark.read.parquet(str(tmp_path / "one"))) == closed(ingest.keep_singletons(e, keys))
    ingest.run_available(ingest.keep_first(ingest.with_lateness(ingest.read_feed(spark, str(tmp_path / "in"), e.schema), delay="30 days"), keys), str(tmp_path / "first"), str(tmp_path / "c2"))
    assert spark.read.parquet(str(tmp_path / "first")).count() == e.select(*keys).distinct().count()


def test_csv_round_trip(spark, tmp_path):
    from corpusmap.sources.tables import overwrite_partitions, publish_corpus, read_corpus_csv

    rows = [("EU", "FR", "fra", "http://a", 3, 'line one\nline "two", end'), ("EU", "DE", "deu", "http://b", 1, "ü")]
    df = spark.createDataFrame(rows, "region string, country string, language string, url string, n_words long, text string")
    publish_corpus(df, str(tmp_path / "csv"))
    back = read_corpus_csv(spark, str(tmp_path / "csv")).select(*df.columns)
    assert sorted(map(tuple, back.collect())) == sorted(rows)
    for _ in range(2):
        overwrite_partitions(df, str(tmp_path / "p"), ["country"])
    assert spark.read.parquet(str(tmp_path / "p")).count() == 2


def test_downsampling_follows_population(spark):
    counts = spark.createDataFrame([(0, 1000), (1, 9000)], "country int, n_words long")
    demo = spark.createDataFrame([(0, 50), (1, 50)], "country int, population long")
    assert {r["country"]: round(r["rate"], 4) for r in inventory.downsampling_rates(counts, demo).collect()} == {0: 1.0, 1: round(1 / 9, 4)}


def test_udaf_and_sql_surface(spark):
    from corpusmap.session import register_sql, spearman_udaf

    df = spark.createDataFrame([(1, 1), (2, 3), (3, 2)], "a long, b long")
    assert df.agg(spearman_udaf()("a", "b")).first()[0] == pytest.approx(similarity.rank_correlation(df.select(F.lit(1).alias("k"), F.lit("t").alias("token"), F.col("a").alias("n_a"), F.col("b").alias("n_b")), ["k"]).first()["rho"])
    register_sql(spark, "/root/testdata/sf0.001")
    assert spark.sql("SELECT count(*) FROM corpus_documents d, LATERAL text_windows(d.text, 50)").first()[0] == text.windows(spark.table("corpus_documents").select("doc_id", "text")).count()
    assert np.isfinite(spark.table("corpus_unigrams").agg(F.sum("n")).first()[0])


def test_bayes_scores_do_not_depend_on_the_order_of_grams(spark):
    """One set of grams in many orders, its sum next to half a millionth: plain addition gives two scores."""
    rng = random.Random(5)
    logp = {chr(97 + i): -rng.random() * 9 for i in range(25)}
    grams = [rng.choice("abcdefghijklmnopqrstuvwxy") for _ in range(60)]
    logp["z"] = -(500 + 5e-7) - math.fsum(map(logp.get, grams))
    grams.append("z")
    table = spark.createDataFrame([(g, [v]) for g, v in logp.items()], "gram string, logp array<double>")
    rows = spark.createDataFrame([(i, "".join(rng.sample(grams, len(grams)))) for i in range(400)], "k int, t string")
    found = {r["s"][0] for r in lid.bayes_scores(rows, ["k"], "t", table, 1, ["en"]).collect()}
    assert len(found) == 1 and abs(found.pop() - math.fsum(map(logp.get, grams))) < 1e-6


def _odd_windows(spark, n=300):
    rng = random.Random(1)
    words = {"en": ["the", "and", "House"], "fr": ["été", "les", "Maison"], "de": ["straße", "und", "Haus"], None: ["x", "zz"]}
    rows = [(i // 2 if i % 11 else None, i % 3, lang := rng.choice(list(words)), rng.choice(["a", "b", None]), None if i % 29 == 0 else "" if i % 31 == 0 else " ".join(rng.choices(words[lang], k=6))) for i in range(n)]
    return spark.createDataFrame(rows, "doc_id int, win int, lang string, domain string, window string").repartition(3)


def test_selecting_model_of_one_pass_equals_its_parts(spark):
    """Null and empty texts, null labels, several bytes a letter; no row per gram leaves a task."""
    rows, ns = _odd_windows(spark), (1, 2, 3, 4)
    counts = lid.byte_gram_counts(rows, ["lang", "domain"], "window")
    assert "Generate" not in counts._jdf.queryExecution().executedPlan().toString()
    grams = F.concat(*[lid.byte_ngrams(F.lower("window"), n) for n in ns])
    n = rows.select("lang", "domain", F.explode(grams).alias("gram")).groupBy("gram", "lang", "domain").agg(F.count(F.lit(1)).alias("n"))
    k = rows.select("lang", "domain", F.explode(F.array_distinct(grams)).alias("gram")).groupBy("gram", "lang", "domain").agg(F.count(F.lit(1)).alias("k"))
    of = lambda df, c: sorted(((r["gram"], r["lang"] or "", r["domain"] or "", r[c]) for r in df.collect()))
    held = counts.filter("gram <> ''")
    assert of(held, "n") == of(n, "n") and of(held, "k") == of(k, "k")
    assert counts.filter("gram = ''").agg(F.sum("k")).first()[0] == rows.count()
    known = rows.filter("lang is not null and domain is not null")
    table, langs = lid.selecting_model(known, "window", 150)
    features = lid.selected_features(known, "window", ns, 150, of=lid.byte_ngrams)
    want = lid.bayes_table(known, "lang", "window", ns, features=features, of=lid.byte_ngrams)
    assert {r[0]: r[1] for r in table.collect()} == {r[0]: r[1] for r in want.collect()} and langs == ["de", "en", "fr"]
    assert lid.selecting_model(rows, "window", 150)[1] == langs


@pytest.mark.parametrize("unique", [False, True])
def test_prediction_inside_the_task_equals_the_join(spark, unique):
    rows = _odd_windows(spark)
    rows = rows.dropDuplicates(["doc_id", "win"]) if unique else rows.unionByName(rows.limit(50))
    rows = rows.localCheckpoint()
    train = rows.filter("lang is not null and domain is not null")
    table, langs = lid.selecting_model(train, "window", 100)
    got = lid.with_prediction(rows, ["doc_id", "win"], "window", table, langs, unique=unique)
    want = rows.join(lid.bayes_predict(rows, ["doc_id", "win"], "window", table, (1, 2, 3, 4), langs, of=lid.byte_ngrams), ["doc_id", "win"], "left")
    cols = ["doc_id", "win", "lang", "domain", "predicted"]
    assert sorted(map(str, got.select(*cols).collect())) == sorted(map(str, want.select(*cols).collect()))
    if unique:
        assert "Exchange hash" not in got._jdf.queryExecution().executedPlan().toString()
