"""The pipeline, stage by stage, against what its operators say."""

from pyspark.sql import functions as F

import corpus_pipeline as p
from divmerge.llm import quality
from divmerge.llm.minhash import near_duplicates
from divmerge.session import table


def test_stages(spark, sf):
    docs = table(spark, sf, "documents")
    cols = docs.columns
    kept = p.quality_rules(spark, docs, sf).cache()
    verdict = {r["doc_id"] for r in quality.judge(docs, quality.train(docs, table(spark, sf, "labels"))).where("kept").collect()}
    assert {r["doc_id"] for r in kept.collect()} == verdict and kept.columns == cols
    once = p.near_dedup(spark, kept, sf).cache()
    assert {r["doc_id"] for r in once.collect()} == {r["class_id"] for r in near_duplicates(kept).collect()} and once.columns == cols
    cut = p.substring_dedup(spark, once, sf).cache()
    assert cut.columns == cols and cut.count() == once.count()
    assert all(r["n_chars"] == len(r["text"]) for r in cut.collect())
    mixed = p.mix_sources(spark, cut, sf).cache()
    assert mixed.columns == cols and 0 < mixed.count() < cut.count()
    coded = p.encode_pieces(spark, mixed, sf)
    assert {r["doc_id"] for r in coded.where("round_trip").collect()} == {r["doc_id"] for r in mixed.collect()}


def test_empty_tables(spark, sf):
    docs = table(spark, sf, "documents").where("false")
    for _, stage in p.STAGES:
        docs = stage(spark, docs, sf)
    assert docs.count() == 0


def test_names():
    assert [n for n, _ in p.STAGES] == ["quality rules", "near dedup", "substring dedup", "mix sources", "encode pieces"]


def test_odd_rows_go_through(spark, sf):
    """Null ids, rows that share an id, equal rows, null and empty texts, and a further column."""
    docs = table(spark, sf, "documents").where("doc_id < 60").withColumn("key", F.lit("x"))
    text = docs.where("n_chars > 400").first()["text"]
    row = lambda i, t: (i, t, "en", "src0", len(t or ""), "x")
    more = spark.createDataFrame([row(None, text + " extra"), row(7, text), row(7, text), row(8, None), row(9, ""), row(None, None)], docs.schema)
    rows = docs.unionByName(more)
    once = p.near_dedup(spark, rows, sf)
    assert once.columns == docs.columns
    kept = [r["text"] for r in once.collect()]
    assert sum(t == text for t in kept) + sum(t == text + " extra" for t in kept) == 1 and sum(not t for t in kept) >= 3
    cut = p.substring_dedup(spark, rows, sf)
    assert cut.columns == docs.columns and cut.count() == rows.count()
    mixed = p.mix_sources(spark, rows, sf)
    assert mixed.columns == docs.columns and 0 < mixed.count() <= rows.count()
    assert p.quality_rules(spark, rows, sf).columns == docs.columns
    coded = p.encode_pieces(spark, rows, sf)
    assert coded.where("not round_trip").count() == 0 and coded.where("rank = 1").count() == rows.count()
