"""Streams: routing of arriving sentences, windowed counts with late data, sessions, dedup, and drift of the vocabulary."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.corpus import token_counts
from ..operators.divide import divide_epoch_sample
from ..operators.measures import kl_from_counts

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a batch, with a zoned timestamp."""
    return spark.read.schema(EVENTS).parquet(f"{sf_dir}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))


def event_stream(spark: SparkSession, folder: str) -> DataFrame:
    """The same as a stream over a folder of files."""
    return spark.readStream.schema(EVENTS).option("pathGlobFilter", "events*.parquet").parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))


def windowed_counts(ev: DataFrame, size: str = "1 day", slide: str | None = None, late: str | None = "1 hour") -> DataFrame:
    """(start, event_type, n, total): tumbling windows, or sliding ones with ``slide``."""
    rows = ev.withWatermark("ts", late) if late and ev.isStreaming else ev
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return rows.groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("total")).select(F.col("w.start").alias("start"), "event_type", "n", "total")


def session_sentences(ev: DataFrame, gap: str = "30 minutes", late: str | None = "1 hour") -> DataFrame:
    """(user_id, start, tokens): each user's session as a sentence of event types in order of time."""
    rows = ev.withWatermark("ts", late) if late and ev.isStreaming else ev
    s = rows.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.array_sort(F.collect_list(F.struct("ts", "event_id", "event_type"))).alias("e"))
    return s.select("user_id", F.col("w.start").alias("start"), F.transform("e", lambda x: x["event_type"]).alias("tokens"))


def drop_late(ev: DataFrame, arrived: str, late_seconds: int) -> DataFrame:
    """Batch twin of a watermark: rows whose time is within ``late_seconds`` of the highest time among earlier arrivals.

    The running maximum is taken over ranges of arrival: within each, and against the maxima of those before.
    """
    from pyspark.sql import Window

    rows = ev.withColumn("_part", F.floor(F.col(arrived) / 4096))
    tops = rows.groupBy("_part").agg(F.max("ts").alias("_top"))
    tops = tops.withColumn("_before", F.max("_top").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1))).drop("_top")
    own = F.max("ts").over(Window.partitionBy("_part").orderBy(arrived).rowsBetween(Window.unboundedPreceding, -1))
    seen = rows.join(tops, "_part").withColumn("_high", F.greatest(own, F.col("_before")))
    return seen.where(F.col("_high").isNull() | (F.unix_micros("ts") >= F.unix_micros("_high") - late_seconds * 1_000_000)).drop("_part", "_before", "_high")


def dedup_events(ev: DataFrame, late: str = "1 hour") -> DataFrame:
    """The first of each event id; on a stream, within the watermark."""
    return ev.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"]) if ev.isStreaming else ev.dropDuplicates(["event_id"])


def joined_within(left: DataFrame, right: DataFrame, minutes: int = 10, late: str = "1 hour") -> DataFrame:
    """Stream-stream (or batch) join: a user's events of ``right`` at most ``minutes`` after one of ``left``.

    Both sides carry the time in steps of ``minutes`` as a second key (an event of ``right`` looks into its own step and the one
    before), so what one key brings together is bounded by a step, whatever a user does in a day.
    """
    step = lambda ts: F.floor(F.unix_micros(ts) / (minutes * 60_000_000))
    a = (left.withWatermark("ts", late) if left.isStreaming else left).select(F.col("user_id").alias("user"), step(F.col("ts")).alias("step"), F.col("ts").alias("t1"), F.col("event_id").alias("first_id"))
    b = right.withWatermark("ts", late) if right.isStreaming else right
    b = b.select("user_id", F.explode(F.array(step(F.col("ts")), step(F.col("ts")) - 1)).alias("back"), F.col("ts").alias("t2"), F.col("event_id").alias("second_id"))
    near = (F.col("t2") > F.col("t1")) & (F.col("t2") <= F.col("t1") + F.expr(f"INTERVAL {minutes} MINUTES"))
    return a.join(b, (F.col("user") == F.col("user_id")) & (F.col("step") == F.col("back")) & near).select("user_id", "first_id", "second_id")


def route_stream(sent: DataFrame, n: int, rate: float, sink: Callable[[DataFrame, int], None], seed: int = 1, checkpoint: str | None = None):
    """Route arriving sentences(sent_id, tokens) batch by batch; the batch number is the epoch, so no draw is remembered."""

    def each(batch: DataFrame, batch_id: int) -> None:
        sink(divide_epoch_sample(batch, n, rate, 1, seed + batch_id, keep=("tokens",)).withColumn("epoch", F.lit(batch_id)), batch_id)

    w = sent.writeStream.foreachBatch(each)
    return (w.option("checkpointLocation", checkpoint) if checkpoint else w).trigger(availableNow=True).start()


def vocabulary_drift(sent: DataFrame, reference: DataFrame, window: str = "1 day") -> DataFrame:
    """(model, kl): divergence of each time window's words (``model`` is its start) from ``reference(word, cnt)``, words of the reference only."""
    rows = sent.select(F.window("ts", window)["start"].cast("string").alias("model"), "tokens")
    sub = token_counts(rows, "model").join(reference.select("word"), "word", "left_semi")
    return kl_from_counts(sub, reference, ["word"])
