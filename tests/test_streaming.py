import glob
import shutil

from pyspark.sql import functions as F

from divmerge.streaming import events as ev


def test_stream_counts_equal_batch(spark, sf, tmp_path):
    folder = tmp_path / "in"
    folder.mkdir()
    for p in glob.glob(f"{sf}/events.parquet"):
        shutil.copy(p, folder / "events-0.parquet")
    s = ev.windowed_counts(ev.event_stream(spark, str(folder)), late=None)
    q = s.writeStream.outputMode("complete").format("memory").queryName("counts").trigger(availableNow=True).start()
    q.awaitTermination(120)
    want = {(r["start"], r["event_type"]): r["n"] for r in ev.windowed_counts(ev.events(spark, sf)).collect()}
    assert {(r["start"], r["event_type"]): r["n"] for r in spark.table("counts").collect()} == want


def test_routing_a_stream(spark, tmp_path):
    rows = spark.range(200).select(F.col("id").alias("sent_id"), F.array(F.lit("a"), F.lit("b")).alias("tokens"))
    rows.write.parquet(str(tmp_path / "s"))
    got = []
    stream = spark.readStream.schema(rows.schema).parquet(str(tmp_path / "s"))
    q = ev.route_stream(stream, 4, 50.0, lambda df, k: got.append((k, df.count())), checkpoint=str(tmp_path / "c"))
    q.awaitTermination(120)
    assert sum(n for _, n in got) > 200


def test_dedup_and_sessions(spark, sf):
    e = ev.events(spark, sf)
    assert ev.dedup_events(e.union(e)).count() == e.count()
    assert ev.session_sentences(e).agg(F.sum(F.size("tokens"))).first()[0] == e.count()
    assert ev.joined_within(e.where("event_id % 2 = 0"), e.where("event_id % 2 = 1")).columns == ["user_id", "first_id", "second_id"]
