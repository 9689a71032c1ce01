"""What operators hold on the driver, as its Python sees it."""

import tracemalloc

import numpy as np

import corpus_pipeline
from tilemul.llm import nearcopies, pii, quality


def test_quality_sample_comes_as_numbers_not_objects(spark, monkeypatch):
    monkeypatch.setattr(quality, "train", lambda x, y: (x.copy(), y))
    n, width = 4000, 2 * 2 * quality.DIM + quality.COUNTS
    docs = spark.range(n).selectExpr("id as doc_id", "repeat('some words ', int(1 + id % 5)) as text")
    labels = spark.range(n).selectExpr("id as doc_id", "int(id % 2) as quality")
    quality.fit(docs.limit(1), labels.limit(1))
    tracemalloc.start()
    model = quality.fit(docs, labels)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    x, y = model.network
    assert 0 < len(x) < n and x.shape[1] == width and set(y) == {0.0, 1.0}
    ids = [r.doc_id for r in docs.where(~quality.held_out("doc_id")).orderBy("doc_id").collect()]
    want = [quality.features(quality.buckets_of("some words " * (1 + i % 5)), model.vectors) for i in ids]
    assert np.array_equal(x, np.array(want)) and y.tolist() == [i % 2 for i in ids]
    assert peak < 2.5 * x.nbytes + 4_000_000  # the sample twice and tables of words; as objects it took four times as much more


def _broadcasts(spark, after):
    """Broadcasts in the plans of the executions since ``after``; the number of the last execution."""
    spark._jsparkSession.sparkContext().listenerBus().waitUntilEmpty()
    runs = spark._jsparkSession.sharedState().statusStore().executionsList()
    runs = [runs.apply(n) for n in range(runs.size())]
    mine = [r for r in runs if r.executionId() > after]
    return sum(r.physicalPlanDescription().split("== Initial Plan ==")[0].count("BroadcastExchange (") for r in mine), max(r.executionId() for r in runs)


def test_near_copies_broadcast_only_what_hints_name(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    spark.range(1).collect()
    _, last = _broadcasts(spark, -1)
    kept = nearcopies.near_copies(docs)
    many, _ = _broadcasts(spark, last)
    assert kept.count() == docs.count()
    assert spark.conf.get("spark.sql.autoBroadcastJoinThreshold") != "-1"  # as it was
    # hints: three tables of few rows to each of the rounds, and as many again for a plan that is listed twice
    assert many <= 2 * 3 * nearcopies.ROUNDS, many


def test_masking_in_the_pipeline_broadcasts_only_what_hints_name(spark, sf, monkeypatch):
    names = ("spark.sql.autoBroadcastJoinThreshold", "spark.sql.adaptive.autoBroadcastJoinThreshold")
    seen = []
    monkeypatch.setattr(pii, "masked", lambda docs: seen.extend(spark.conf.get(n) for n in names) or docs)
    before = [spark.conf.get(n, None) for n in names]
    corpus_pipeline.mask_personal_data(spark, spark.range(1), sf)
    assert seen == ["-1", "-1"]
    assert [spark.conf.get(n, None) for n in names] == before
