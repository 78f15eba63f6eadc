"""What larger tables brought up: jobs that stopped, were cut or read no table."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from divmerge.operators import evaluate, gold, vocab
from divmerge.operators.merge import extra
from divmerge.operators.merge.basic import merge_concat
from divmerge.queries import ORACLE_SQL, QUERIES
from oracle import rows_of, twin_rows


def test_trained_vocabulary_has_words_beyond_the_one_list(spark, sf, monkeypatch):
    whole = vocab.global_vocab
    monkeypatch.setattr(vocab, "global_vocab", lambda sent, size=0: whole(sent, 50))
    assert rows_of(QUERIES["trained_vocabulary"](spark, sf)) == twin_rows(ORACLE_SQL["trained_vocabulary"], sf)


@pytest.mark.parametrize("name", ["averaging_counterexample", "miss_threshold"])
def test_query_reads_its_table(spark, sf, tmp_path, name):
    """Other tables, other results."""
    import os

    for t in ("documents", "embeddings"):
        os.symlink(f"/root/testdata/sf0.01/{t}.parquet", tmp_path / f"{t}.parquet")
    spark.read.parquet(f"{sf}/{'documents' if name == 'miss_threshold' else 'embeddings'}.parquet").limit(150).write.parquet(str(tmp_path / "less"))
    at = tmp_path / "two"
    at.mkdir()
    for t in ("documents", "embeddings"):
        os.symlink(tmp_path / "less", at / f"{t}.parquet")
    assert rows_of(QUERIES[name](spark, str(at))) != rows_of(QUERIES[name](spark, str(tmp_path)))
    assert rows_of(QUERIES[name](spark, str(tmp_path))) == twin_rows(ORACLE_SQL[name], str(tmp_path))


def _planted(spark, rows=150):
    base = gold.planted_base(spark.read.parquet("/root/testdata/sf0.001/embeddings.parquet").where(F.col("vec_id") < rows))
    return base, gold.planted_shifted(base, 3)


def test_low_rank_and_lle_of_any_number_of_words(spark, monkeypatch):
    raw = spark.read.parquet("/root/testdata/sf0.001/embeddings.parquet").where("vec_id < 150")
    sub = gold.planted_shifted(raw.select(F.concat(F.lit("w"), "vec_id").alias("word"), F.col("embedding").alias("vec")), 3)
    monkeypatch.setattr(extra, "MAX_WORDS", 100, raising=False)
    assert extra.merge_low_rank(sub, 3, 5).count() == 150
    whole = {r["word"]: r["vec"] for r in extra.merge_lle(sub, 3, 5).collect()}
    monkeypatch.setattr(extra, "MAX_DENSE", 100)
    parts = {r["word"]: r["vec"] for r in extra.merge_lle(sub, 3, 5).collect()}
    a, b = (np.array([x[k] for k in sorted(whole)]) for x in (whole, parts))
    assert len(parts) == 150 and np.allclose(np.abs(a.T @ b), np.eye(5), atol=1e-3)


def test_neighbours_of_blocks_are_those_of_the_whole(spark):
    rows = extra.number_sentences(merge_concat(_planted(spark)[1], 3), ["word"])
    one, many = (extra._neighbours(rows, 192, 10, 1e-3, b) for b in (1000, 40))
    assert one[0] == many[0] and (one[1] == many[1]).all() and np.allclose(one[2], many[2])


def test_clusters_in_passes_are_those_of_one_task(spark, monkeypatch):
    base, sub = _planted(spark)
    emb = sub.select("model", "word", "vec").unionByName(merge_concat(sub, 3).select(F.lit(9).alias("model"), "word", "vec"))
    cat = base.select("word", "cls")
    one, many = ({(r["model"], r["word"]): (r["cls"], r["cluster"]) for r in f(cat, emb, 10, by=["model"]).collect()} for f in (evaluate.clusters, evaluate.clusters_in_passes))
    assert one == many and len(one) == 4 * 150


def test_missing_word_study_beyond_one_task(spark, sf, monkeypatch):
    from divmerge.plans import workloads as w

    want = rows_of(w.missing_words(spark, sf, (10.0,), n=3))
    for m in (evaluate, w):
        monkeypatch.setattr(m, "MAX_BENCHMARK", 100, raising=False)
    assert rows_of(w.missing_words(spark, sf, (10.0,), n=3)) == want


def test_search_asks_in_blocks_and_ranks_rounded_scores(spark, monkeypatch):
    from divmerge.functions import sql

    def lateral(*_, **__):
        raise AssertionError("a pass over all words for each query")

    rows = [(i, f"w{i}", [1.0, x]) for i, x in enumerate((0.0, 1e-4, 2e-4, 1.0))]
    emb = spark.createDataFrame(rows, "vec_id long, word string, vec array<double>")
    got = evaluate.neighbours(emb.where("vec_id = 2").select(F.col("word").alias("query"), "vec"), emb, 3, digits=6, own=True).orderBy("rank").collect()
    assert [r["word"] for r in got] == ["w0", "w1", "w2"] and {r["score"] for r in got} == {1.0}
    monkeypatch.setattr(sql, "register_neighbours", lateral)
    sf = "/root/testdata/sf0.1"
    assert rows_of(QUERIES["sql_neighbours"](spark, sf)) == twin_rows(ORACLE_SQL["sql_neighbours"], sf)


def test_languages_are_calibrated_on_every_text(spark):
    from divmerge.llm import langid

    words = {"en": ["stone", "river", "light", "house"], "fi": ["kivi", "joki", "valo", "talo"]}
    rows = [(i, f"{words[x][i % 4]} {words[x][i // 4 % 4]}", x) for i, x in enumerate(["en", "fi"] * 1200)]
    docs = spark.createDataFrame([*rows, *((5000 + i, "kivi joki", "en") for i in range(300))], "doc_id long, text string, lang string")
    for size in (langid.MAX_NGRAMS, 1):  # one group, and a group for each language
        m = langid.train(docs, max_ngrams=size)
        parts = list(m.parts()) if isinstance(m, langid.LanguageGroups) else [m]
        seen = docs.collect()
        mean = np.concatenate([np.concatenate([p.text_scores(c)[0] for c in langid.chunks(langid.pa.array([r["text"] for r in seen]))]) for p in parts], 1)
        truth = np.array([m.languages.index(r["lang"]) for r in seen])
        loss = []
        for t in langid.TEMPERATURES:
            z = (mean - mean.max(1, keepdims=True)) / t
            loss.append((np.log(np.exp(z).sum(1)) - z[np.arange(len(z)), truth]).mean())
        z = np.exp((mean - mean.max(1, keepdims=True)) / m.temperature)
        right = (z.max(1) / z.sum(1))[mean.argmax(1) == truth]
        assert np.isclose(m.temperature, langid.TEMPERATURES[int(np.argmin(loss))]) and np.isclose(m.reject, min(0.5, np.quantile(right, 0.001)))
