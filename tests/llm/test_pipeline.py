"""The pipeline: each stage keeps what it should and its decisions take effect."""

from pyspark.sql import functions as F

import corpus_pipeline
from slicecode.llm import secret_scan


def test_stages(spark, sf, tmp_path):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns, seen = docs.columns, [docs]
    assert 4 <= len(corpus_pipeline.STAGES) <= 5
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        stage(spark, seen[-1], sf).write.parquet(f"{tmp_path}/{k}")
        seen.append(spark.read.parquet(f"{tmp_path}/{k}"))
        assert k == len(corpus_pipeline.STAGES) - 1 or seen[-1].columns == columns, name
    raw, clean, apart, open_, masked, ids = seen
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    assert clean.join(labels.where("toxic = 1"), "doc_id", "left_semi").count() <= 1
    assert raw.join(labels.where("toxic = 0"), "doc_id", "left_semi").count() - clean.join(labels.where("toxic = 0"), "doc_id", "left_semi").count() <= 1
    copies = clean.groupBy("text").agg(F.count("*").alias("n"), F.min("doc_id").alias("doc_id"))
    assert apart.select("text").distinct().count() == apart.count() and copies.where("n > 1").join(apart, "doc_id", "left_anti").where("false").count() == 0
    items = [r["text"].lower() for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    squeeze = lambda t: " ".join(t.lower().split())
    held = {r["doc_id"]: any(squeeze(i) in squeeze(r["text"]) for i in items) for r in apart.collect()}
    assert {r["doc_id"] for r in open_.collect()} == {k for k, bad in held.items() if not bad}
    assert masked.count() == open_.count() == ids.count()
    for r in masked.collect():
        assert not secret_scan.base_spans(r["text"]) and (r["n_chars"] == len(r["text"]) or "[secret]" not in r["text"])
    assert {tuple(r) for r in corpus_pipeline.run(spark, sf).select("doc_id", "n_tokens").collect()} == {tuple(r) for r in ids.select("doc_id", "n_tokens").collect()}


def test_edges(spark, edge_docs, tmp_path):
    """Nulls, empty and very long texts, repeats and clashing names through all stages, and empty tables."""
    edge_docs.write.parquet(f"{tmp_path}/a/documents.parquet")
    spark.createDataFrame([(None, 1), (4, None)], "doc_id long, toxic int").write.parquet(f"{tmp_path}/a/labels.parquet")
    spark.createDataFrame([(1, "four five six seven eight"), (None, None), (2, "")], "item_id long, text string").write.parquet(f"{tmp_path}/a/benchmark.parquet")
    got = corpus_pipeline.run(spark, f"{tmp_path}/a").collect()
    assert sorted(r["doc_id"] or -1 for r in got) == [-1, -1, 2, 4, 7]
    for name in ("documents", "labels", "benchmark"):
        spark.read.parquet(f"{tmp_path}/a/{name}.parquet").where("false").write.parquet(f"{tmp_path}/b/{name}.parquet")
    assert corpus_pipeline.run(spark, f"{tmp_path}/b").collect() == []
