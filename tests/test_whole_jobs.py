"""Queries and operators that read all they are given, whatever its size."""

import pytest
from pyspark.sql import functions as F

from divmerge.operators import evaluate, gold, measures, vocab
from divmerge.operators.corpus import encode
from divmerge.operators.evaluate import neighbours
from divmerge.plans import workloads as w
from divmerge.queries import QUERIES


def test_sharded_trainer_reads_every_sentence(spark, sf):
    sent = w.corpus(spark, sf)
    n = F.size("ids")
    of = F.aggregate(F.sequence(F.lit(1), F.lit(10)), F.lit(0), lambda s, d: s + 2 * F.greatest(n - d, F.lit(0)))
    all_pairs = encode(sent.select("sent_id", "tokens"), vocab.global_vocab(sent)).agg(F.sum(of)).first()[0]
    assert sent.count() > 2000 and w.sharded_baseline(spark, sf, block=700).first()["pairs"] == all_pairs


def test_neighbours_of_every_query_in_blocks(spark):
    emb = spark.range(300).select(F.concat(F.lit("w"), "id").alias("word"), F.array(F.cos("id"), F.sin("id"), F.cos(F.col("id") * 3)).alias("vec"))
    q = emb.select(F.col("word").alias("query"), "vec")
    one, many = ({(r["query"], r["rank"]): (r["word"], r["score"]) for r in neighbours(q, emb, 4, block=b).collect()} for b in (1000, 70))
    assert one == many and len(one) == 300 * 4


def test_search_grows_with_the_table(spark):
    got = QUERIES["knn_topk"](spark, "/root/testdata/sf0.1").select("query").distinct().count()
    assert got == 40  # of 2,000 rows


def test_divergence_is_the_mean_over_all_slices(spark, sf):
    sent = w.corpus(spark, sf)
    d = w.division_of(sent, "sequential", 5.0)
    n, each = d.n, [r["kl"] for r in measures.kl_divergence(d.route(sent, ("tokens",)), sent, 1).collect()]
    got = w.kl_table(spark, sf, (5.0,), (1,), divisions=("sequential",)).first()["kl"]
    assert n == len(each) == 20 and abs(got - sum(each) / 20) < 1e-6


def test_every_analogy_is_answered_in_blocks(spark):
    emb, q = gold.planted_relations(spark.read.parquet("/root/testdata/sf0.01/embeddings.parquet").limit(120))
    one, many = ({tuple(r) for r in evaluate.analogy_answers(q, emb, block=b).collect()} for b in (1000, 50))
    assert one == many and len(many) == q.count() > 100


def test_nothing_asked_or_answered(spark):
    emb = spark.createDataFrame([("a", [1.0, 0.0])], "word string, vec array<float>")
    none = spark.createDataFrame([("a", "b", "c", "d")], "a string, b string, c string, d string")
    got = evaluate.analogy_accuracy(none, emb).first()
    assert (got["n_asked"], got["n_answered"], got["n_right"], got["accuracy"]) == (1, 0, 0, None)
    assert neighbours(emb.select(F.col("word").alias("query"), "vec").where("false"), emb, 3).count() == 0


def test_several_embeddings_at_once(spark):
    emb, q = gold.planted_relations(spark.read.parquet("/root/testdata/sf0.01/embeddings.parquet").limit(120))
    both = emb.withColumn("m", F.lit("x")).unionByName(emb.where("word <> 'w0'").withColumn("m", F.lit("y")))
    got = {r["m"]: r for r in evaluate.analogy_accuracy(q, both, by=("m",)).collect()}
    one = evaluate.analogy_accuracy(q, emb).first()
    assert got["x"]["n_right"] == one["n_right"] and got["y"]["n_answered"] < got["x"]["n_answered"] == one["n_answered"]


def test_once_follows_its_source(spark, tmp_path):
    from divmerge.session import once

    at = str(tmp_path / "t.parquet")
    spark.range(3).write.parquet(at)
    read = lambda: once(spark, at, "n", lambda: spark.read.parquet(at).select("id")).count()
    assert read() == read() == 3
    spark.range(5).write.mode("overwrite").parquet(at)
    assert read() == 5


def test_clusters_never_drop_words(spark, monkeypatch):
    monkeypatch.setattr(evaluate, "MAX_BENCHMARK", 10)
    emb = spark.range(11).select(F.concat(F.lit("w"), "id").alias("word"), F.array(F.cos("id"), F.sin("id")).alias("vec"))
    with pytest.raises(ValueError):
        evaluate.clusters(emb.select("word", F.lit("x").alias("cls")), emb, 2)


def test_removal_is_judged_on_all_words(spark, sf, monkeypatch):
    """Answers to analogies are sought among all words of a merged model, not among the benchmarks' own."""
    judged, real = [], w.evaluate
    monkeypatch.setattr(w, "evaluate", lambda emb, *a, **k: judged.append(emb) or real(emb, *a, **k))
    cfg = w.SkipGramConfig(dim=4, window=2, epochs=1)
    w.removal_effect(spark, sf, (0.0,), 50.0, cfg)
    sub, n = w.trained(w.study_corpus(spark, sf), "epoch_sample", 50.0, cfg)
    held = sub.groupBy("word").count()
    got = {r["method"]: r["count"] for e in judged for r in e.groupBy("method").count().collect()}
    assert got == {"concat": held.where(F.col("count") == n).count(), "pca": held.where(F.col("count") == n).count(), "consensus_pca": held.count()}


def test_study_corpus_writes_its_documents_once(spark, sf):
    """The documents' sentences are read where the corpus has them, in its order; orders and deliveries follow."""
    sent, study = w.corpus(spark, sf), w.study_corpus(spark, sf)
    n, rows = sent.count(), study.groupBy("lang").agg(F.count("*").alias("n"), F.min("sent_id").alias("lo"), F.max("sent_id").alias("hi")).collect()
    by = {r["lang"]: r for r in rows}
    assert (by["~orders"]["lo"], by["~supply"]["lo"]) == (n, n + by["~orders"]["n"]) and all(by[k]["hi"] - by[k]["lo"] + 1 == by[k]["n"] for k in ("~orders", "~supply"))
    assert study.where(f"sent_id < {n}").exceptAll(sent.select(F.coalesce("lang", F.lit("")), "tokens", "sent_id")).isEmpty()
    assert set(sent.inputFiles()) <= set(study.inputFiles())
