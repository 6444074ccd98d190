from __future__ import annotations

import corpus_pipeline as cp
from pyspark.sql import functions as F

from stepsql.llm import langid, packing, quality, simhash
from stepsql.llm.common import pick, written

DATA = "/root/testdata/sf0.01"


def test_stages_in_order(spark):
    assert [n for n, _ in cp.STAGES] == ["language_id", "quality_classifier", "exact_dedup", "simhash_near_dedup", "best_fit_packing"]
    docs = spark.read.parquet(f"{DATA}/documents.parquet")
    docs = docs.unionByName(spark.createDataFrame([(10**6, "1234 !!", "en", "s", 7), (10**6 + 1, None, None, None, None)], docs.schema))
    rows = {}
    for name, stage in cp.STAGES:
        rows[name] = docs
        docs = written(stage(spark, docs, DATA))
        if name != "best_fit_packing":
            assert docs.columns == list(cp.COLUMNS)
    after = rows["quality_classifier"]
    assert after.where("doc_id >= 1000000").count() == 0
    predicted = langid.predict(rows["language_id"], langid.fit(rows["language_id"]))
    assert after.count() == predicted.where("not rejected").count() >= 0.98 * rows["language_id"].count()
    labels = spark.read.parquet(f"{DATA}/labels.parquet")
    bad = rows["exact_dedup"].join(labels, "doc_id")
    assert bad.where("quality = 0").count() <= 0.1 * labels.where("quality = 0").count()
    assert bad.where("quality = 1").count() >= 0.97 * rows["quality_classifier"].join(labels, "doc_id").where("quality = 1").count()
    lower = F.translate("text", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    near = rows["simhash_near_dedup"]
    assert near.count() == near.select(lower).distinct().count() == rows["exact_dedup"].select(lower).distinct().count()
    kept = rows["best_fit_packing"]
    classes = simhash.components(near)
    assert sorted(r.doc_id for r in kept.collect()) == sorted(r.component_id for r in classes.select("component_id").distinct().collect())
    assert docs.select("doc_id").distinct().count() == kept.count()
    assert docs.groupBy("sequence_id").agg(F.sum("length").alias("n")).where("n > 2048").count() == 0


def test_odd_rows_and_empty_tables(spark):
    schema = "doc_id bigint, text string, lang string, source string, n_chars bigint"
    rows = [(1, "some words here", "en", None, None), (1, "some words here", "en", None, None), (None, "Some words here", None, None, 3), (2, None, None, None, None), (3, "", "en", "s", 0), (4, "a " * 40_000, None, "s", 1)]
    docs = spark.createDataFrame(rows, schema).withColumn("Text2", F.lit(1))
    for name, stage in cp.STAGES:
        docs = written(stage(spark, docs, DATA))
    assert {r.doc_id for r in docs.collect()} <= {1, 4}
    empty = spark.createDataFrame([], schema)
    for _, stage in cp.STAGES:
        assert stage(spark, empty, DATA).count() == 0


def test_near_copies_leave_one(spark):
    base = " ".join(f"word{k}" for k in range(400))
    rows = [(k, base + f" tail{k}" * (k % 2), "en", "s", 1) for k in range(6)] + [(50, "quite another text about other things", "en", "s", 1)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint")
    got = sorted(r.doc_id for r in cp.drop_near_copies(spark, cp.drop_copies(spark, docs, DATA), DATA).collect())
    assert got[-1] == 50
    want = simhash.components(pick(docs, *cp.COLUMNS)).select("component_id").distinct().count()
    assert len(got) == want


def test_reject_thresholds_are_parameters():
    assert quality.Config().reject_below == 0.5 and langid.Config().reject_cap <= 0.5 and packing.Config().capacity == 2048
