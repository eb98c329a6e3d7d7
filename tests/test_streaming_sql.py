"""Streams equal batches; late rows are dropped; SQL functions agree with transform()."""

import os

import pytest
from latentseg import sqlapi, streaming, workloads
from latentseg.io import read_table
from latentseg.model import SegmentModel
from pyspark.sql import functions as F


@pytest.fixture(scope="module")
def model(spark, sf):
    tr, _ = workloads.train_test(spark, sf, 60, 40, 20)
    return SegmentModel.fit(tr, workloads.small_vocab(tr, 200, 3), rounds=2)


@pytest.fixture(scope="module")
def shards(spark, sf, tmp_path_factory):
    at = str(tmp_path_factory.mktemp("shards"))
    docs = read_table(spark, sf, "documents", ["doc_id", "text", "source"]).withColumn("ts", F.timestamp_seconds(F.col("doc_id") * 600 + 1))
    for k in range(3):
        docs.where(F.col("doc_id") % 3 == k).coalesce(1).write.mode("append").parquet(f"{at}/in")
    return at, docs


def test_stateless_stream_equals_batch(spark, model, shards):
    at, docs = shards
    s = streaming.source(spark, f"{at}/in", docs.schema)
    streaming.write(streaming.label_stream(s, model).select("doc_id", "label"), f"{at}/out", f"{at}/c1").awaitTermination()
    got = spark.read.parquet(f"{at}/out").select("doc_id", "label")
    want = model.transform(docs).select("doc_id", "label")
    assert got.exceptAll(want).count() == 0 and got.count() == want.count()


def test_windows_and_counts(spark, model, shards):
    at, docs = shards
    s = streaming.source(spark, f"{at}/in", docs.schema, 10)
    labelled = s.withColumn("label", F.col("source"))
    q = streaming.memory(streaming.label_mix(labelled, "1 hour"), "mix", "complete", f"{at}/c2")
    q.awaitTermination()
    want = docs.groupBy(F.window("ts", "1 hour").alias("w"), F.col("source").alias("label")).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "label", "n")
    assert spark.table("mix").exceptAll(want).count() == 0 and spark.table("mix").count() == want.count()
    q = streaming.memory(streaming.running_counts(labelled), "counts", "complete", f"{at}/c3")
    q.awaitTermination()
    assert spark.table("counts").agg(F.sum(F.length("chunk") * F.col("n"))).first()[0] == docs.agg(F.sum(F.length("text"))).first()[0]


def test_dedup_and_refresh(spark, model, shards):
    at, docs = shards
    s = streaming.source(spark, f"{at}/in", docs.schema, 10)
    q = streaming.memory(streaming.dedup(s, ["text"], watermark="100 days").select("doc_id"), "unique_docs", "append", f"{at}/c4")
    q.awaitTermination()
    assert spark.table("unique_docs").count() == docs.select("text").distinct().count()
    run = streaming.refresher(model, f"file://{at}/refresh", rounds=1)
    run(docs.limit(20).select("text", F.lit("de").alias("label")), 0)
    run(docs.limit(20).select("text", F.lit("de").alias("label")), 0)
    new = SegmentModel.load(spark, f"file://{at}/refresh/model")
    sizes = {r["label"]: r["n_samples"] for r in new.stats.collect()}
    assert sizes["de"] == 20 and {k: v for k, v in sizes.items() if k != "de"} == {r["label"]: r["n_samples"] for r in model.stats.where("label <> 'de'").collect()}  # rows, not chunks
    assert new.labels() == model.labels() and os.path.isdir(f"{at}/refresh/counts/batch=0")
    assert spark.read.parquet(f"{at}/refresh/counts").agg(F.sum(F.length("chunk") * F.col("n"))).first()[0] == docs.limit(20).agg(F.sum(F.length("text"))).first()[0]


def test_sql_functions(spark, model, sf):
    sqlapi.register(spark, model)
    docs = read_table(spark, sf, "documents", ["doc_id", "text"]).limit(30)
    docs.createOrReplaceTempView("d")
    want = {r[0]: r[1] for r in model.transform(docs).select("doc_id", "label").collect()}
    assert {r[0]: r[1] for r in spark.sql("select doc_id, detect_label(text) from d").collect()} == want
    r = spark.sql("select label_topk(text, 2) t, label_margin(text) m, label_posterior(text) p from d limit 1").first()
    assert len(r["t"]) == 2 and abs(r["t"][0]["score"] - r["t"][1]["score"] - r["m"]) < 1e-6 and abs(sum(r["p"].values()) - 1) < 1e-9
    assert spark.sql("select count(*) from d, lateral label_scores(text)").first()[0] == 120
    assert spark.sql("select array_join(segment_text('the house', 'en'), '') s").first()[0] == "the house"
    assert spark.sql("select detect_label(null) x").first()[0] is None
    assert len(spark.sql("select label_mixture(text) m from d").first()[0]) == 4
