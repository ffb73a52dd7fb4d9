"""Domains in both forms, the earlier version, plans, streams, readers, and the neural identifier's gate."""

import pytest
from pyspark.sql import functions as F

from corpusmap.functions import geo, surrogate, text
from corpusmap.operators import build, dedup, lid, mlp
from corpusmap.session import fresh_path, materialize, release
from corpusmap.sources import tables
from corpusmap.streaming import ingest

FOLDER = "/root/testdata/sf0.001"


def test_domains_meet_in_both_forms(spark):
    domains = spark.createDataFrame([("рф", "RU", True, "Cyrillic"), ("xn--p1b6ci4b4b3a", "IN", True, "Devanagari"), ("fr", "FR", True, "Latin"), ("tv", "TV", False, "Latin")], "tld string, country string, usable boolean, script string")
    pages = spark.createDataFrame([(1, "http://a.рф/x"), (2, "http://a.xn--p1ai/x"), (3, "http://b.fr/"), (4, "http://c.tv/"), (5, "http://1.2.3.4/"), (6, "http://d.xn--p1b6ci4b4b3a/")], "page_id long, url string")
    met = {r["page_id"]: r["country"] for r in geo.with_country(pages, domains).collect()}
    assert met == {1: "RU", 2: "RU", 3: "FR", 6: "IN"}
    assert {r["page_id"] for r in geo.with_country(pages, domains, non_latin=False).collect()} == {3}
    assert {r["page_id"] for r in build.BuildConfig.earlier().pages(pages, domains).collect()} == {3}


def test_earlier_version_is_smaller_and_capped(spark):
    from corpusmap.workloads import DOMAINS

    domains = spark.createDataFrame(list(DOMAINS), "tld string, country int, usable boolean, script string")
    pages = surrogate.pages(spark, FOLDER)
    cfg = build.BuildConfig.earlier()
    assert cfg.pages(pages, domains).groupBy("country").count().agg(F.max("count")).first()[0] <= cfg.page_ceiling
    new, old = (build.build_corpus(pages, c, domains=domains).agg(F.sum("n_words")).first()[0] for c in (build.BuildConfig(), cfg))
    assert 0 < old <= new


def test_survivors_move_no_text_unless_their_bucket_is_hit(spark):
    rows = spark.createDataFrame([(i, 0, "p", f"s{i % 3}", f"text {i if i % 10 else 0}") for i in range(200)], "id int, pos int, period string, site string, text string")
    plan = dedup.unique_samples(rows, ["id", "pos"])._jdf.queryExecution().executedPlan().toString()
    through = plan.split("Union")[1].split("BroadcastHashJoin")[1]
    assert "LeftAnti" in through and "SortMergeJoin" not in plan.split("LeftSemi")[0].split("LeftAnti")[0]
    assert dedup.unique_samples(rows, ["id", "pos"]).count() == 180


def test_byte_grams_and_one_row_a_window(spark):
    df = spark.createDataFrame([("é1",), ("",), (None,)], "t string")
    got = [r[0] for r in df.select(lid.byte_ngrams(F.col("t"), 2).alias("g")).collect()]
    assert got == [["C3A9", "A931"], [], None] or got == [["C3A9", "A931"], [], []]
    rows = spark.createDataFrame([(i, lab, w) for i, (lab, w) in enumerate([("a", "xxxyyy"), ("b", "zzzyyy"), ("b", "zzzz"), ("a", "xxxx")] * 5)], "id int, lang string, window string")
    table = lid.bayes_table(rows, "lang", "window", 2)
    pred = lid.bayes_predict(spark.createDataFrame([(1, "xxx"), (2, "zzz"), (3, "yyy"), (4, "qq")], "id int, window string"), ["id"], "window", table, 2, ["a", "b"])
    plan = pred._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 1  # sums are combined before the one shuffle
    found = {r["id"]: r["predicted"] for r in pred.collect()}
    assert found[1] == "a" and found[2] == "b" and set(found) == {1, 2, 3}


def test_ties_go_to_the_smaller_label(spark):
    rows = spark.createDataFrame([("es", "abab"), ("en", "abab")], "lang string, window string")
    table = lid.bayes_table(rows, "lang", "window", 2, least=1)
    got = lid.bayes_predict(spark.createDataFrame([(1, "abab")], "id int, window string"), ["id"], "window", table, 2, lid.bayes_languages(rows, "lang")).first()
    assert got["predicted"] == "en"


def test_neural_identifier_reaches_its_gate(spark):
    """The full shape on few windows: F1 of 0.95 on documents that training never saw; a threshold leaves weak windows without a label."""
    docs = text.windows(tables.load(spark, FOLDER, "documents").select("doc_id", "lang", F.col("source").alias("domain"), "text"))
    parts = lid.split_three(docs, F.col("doc_id"), (0.7, 0.0, 0.3))
    rows = parts.filter("split = 'train'").withColumn("key", F.concat_ws("-", "doc_id", "win"))
    labels = sorted(r[0] for r in rows.select("lang").distinct().collect())
    cfg = mlp.MLPConfig(dims=8192, per_pair=400, epochs=2, rate=2e-3)
    model = mlp.train_mlp(lambda e: mlp.epoch_arrays(lid.balanced_epoch(rows, ("lang",), "key", cfg.per_pair, e), "window", "lang", labels, cfg.dims), labels, cfg)
    out = mlp.predict(parts.filter("split = 'evaluation'"), model).cache()
    right = out.filter("lang = predicted").count() / out.count()
    assert right >= 0.95
    sure = mlp.predict(parts.filter("split = 'evaluation'"), model, min_prob=0.99)
    assert 0 < sure.filter("predicted is not null").count() < out.count()
    voted = mlp.vote(out, ["doc_id", "lang"])
    assert voted.filter("lang = language").count() / voted.count() >= right
    assert {mlp.vote(out, ["doc_id"], how).count() for how in ("majority", "first", "probability")} == {voted.count()}


def test_periods_are_ingested_once(spark):
    feed, out, check = (fresh_path(spark, n) for n in ("feed", "out", "check"))
    lines = lambda period, *texts: spark.createDataFrame([(i, 0, period, "s", t) for i, t in enumerate(texts)], "id int, pos int, period string, site string, text string")
    survivors = lambda df: dedup.unique_samples(df, ["id", "pos"])
    one = lines("p1", "a", "b", "b")
    one.coalesce(1).write.parquet(feed)
    ingest.ingest_periods(ingest.read_feed(spark, feed, one.schema), out, check, survivors)
    lines("p2", "c", "c", "a").coalesce(1).write.mode("append").parquet(feed)
    for _ in range(2):  # a second start has nothing left to do
        ingest.ingest_periods(ingest.read_feed(spark, feed, one.schema), out, check, survivors)
        assert sorted((r["period"], r["text"]) for r in spark.read.parquet(out).collect()) == [("p1", "a"), ("p2", "a")]


def test_readers_and_written_tables(spark, tmp_path):
    (tmp_path / "x.json").write_text('{"a": 1}\n{"a": 2}\n')
    (tmp_path / "x.txt").write_text("one\ntwo\n")
    assert [r["a"] for r in tables.read_json(spark, str(tmp_path / "x.json"), "a int").collect()] == [1, 2]
    assert tables.read_text(spark, str(tmp_path / "x.txt")).count() == 2
    assert tables.read_binary(spark, str(tmp_path / "x.txt")).first()["length"] == 8
    lists = spark.createDataFrame([("web", "en", f"t{i}", i) for i in range(50)], "register string, language string, token string, n int")
    tables.publish_unigrams(lists, str(tmp_path / "uni"))
    back = spark.read.csv(str(tmp_path / "uni"))
    assert back.count() == 50 and {r["language"] for r in back.collect()} == {"en"}
    held = materialize(lists, "lists")
    assert held.count() == 50
    release(held)
    with pytest.raises(Exception, match="(?i)not.*exist|not.*found"):
        held.filter("n > 3").collect()
