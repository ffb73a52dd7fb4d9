"""What a worker process keeps from stage to stage, and how much it is handed at once."""

import sys

import pyarrow as pa

import corpus_pipeline
from corpusmap.llm import quality_mil
from corpusmap.llm.common import lean


def test_pipeline_stages_hand_over_short_batches(spark):
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(key)
    docs = spark.range(5000).coalesce(1).selectExpr("id AS doc_id", "concat('word ', id) AS text")
    try:
        assert corpus_pipeline.pack(spark, docs, "").count() == 5000
        sizes = docs.mapInArrow(lambda batches: (pa.RecordBatch.from_pydict({"n": [b.num_rows]}) for b in batches), "n long").collect()
        assert max(r.n for r in sizes) <= 1024 and sum(r.n for r in sizes) == 5000
        spark.conf.set(key, "100")
        corpus_pipeline.pack(spark, docs, "")
        assert spark.conf.get(key) == "100"
    finally:
        spark.conf.set(key, before)


def test_a_stage_drops_what_another_left_in_the_worker(spark, monkeypatch):
    monkeypatch.setitem(sys.__dict__, "_corpusmap_encoders", {"path": "encoder"})
    assert list(lean(lambda b: (yield from b), "_corpusmap_encoders")(iter([1, 2]))) == [1, 2] and sys._corpusmap_encoders
    docs, held = spark.createDataFrame([(1, "a")], "doc_id long, text string"), []
    monkeypatch.setattr(type(docs), "mapInArrow", lambda self, run, schema: held.append(run) or self)
    quality_mil.score(docs, quality_mil.initial(quality_mil.MilParams()))
    assert list(held[0](iter([]))) == [] and not hasattr(sys, "_corpusmap_encoders")
