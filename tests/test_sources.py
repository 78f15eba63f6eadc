from pyspark.sql import functions as F

from divmerge.operators.corpus import rows_to_sentences, strip_html
from divmerge.sources import corpora, models


def test_vectors_round_trip(spark, tmp_path):
    emb = spark.createDataFrame([("a", [1.0, 2.5]), ("b", [0.0, -1.0])], "word string, vec array<float>")
    models.write_text_vectors(emb, str(tmp_path / "v"))
    assert sorted(models.read_text_vectors(spark, str(tmp_path / "v")).collect()) == sorted(emb.collect())


def test_submodels_prune_by_model(spark, tmp_path):
    sub = spark.createDataFrame([(0, "a", [1.0], 1), (1, "a", [2.0], 3)], "model int, word string, vec array<float>, cnt long")
    models.save_submodels(sub, str(tmp_path / "m"))
    one = models.load_submodels(spark, str(tmp_path / "m"), 1)
    assert [r["vec"] for r in one.collect()] == [[2.0]]
    assert "PartitionFilters: [isnotnull(model" in one._jdf.queryExecution().toString()


def test_scans_read_only_what_is_named(spark, sf):
    plan = corpora.document_sentences(spark, sf).where("lang = 'en'")._jdf.queryExecution().toString()
    assert "ReadSchema: struct<doc_id:bigint,text:string,lang:string>" in plan and "EqualTo(lang,en)" in plan


def test_html_and_rows(spark):
    h = spark.createDataFrame([("<p>a <b>b</b></p><script>x</script>&amp;c",)], "h string").select(strip_html(F.col("h"))).first()[0]
    assert h == "a b c"
    assert rows_to_sentences(spark.range(1), ["id"], ["id"]).first()["tokens"] == ["0"]


def test_files(spark, tmp_path):
    (tmp_path / "t.txt").write_text("one\ntwo\n")
    assert corpora.text_lines(spark, str(tmp_path / "t.txt")).count() == 2
    (tmp_path / "j.json").write_text('{"id": "1", "text": "x"}\n')
    assert corpora.json_lines(spark, str(tmp_path / "j.json")).first()["text"] == "x"
