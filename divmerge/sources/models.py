"""Stores for sub-models and merged vectors: partitioned tables, bucketed tables, and the usual text exchange format."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def save_submodels(sub: DataFrame, path: str) -> None:
    """One folder for each model, so that reading a model prunes the others."""
    sub.write.mode("overwrite").partitionBy("model").parquet(path)


def load_submodels(spark: SparkSession, path: str, model: int | None = None) -> DataFrame:
    out = spark.read.schema("word string, vec array<float>, cnt long, model int").parquet(path)
    return out if model is None else out.where(F.col("model") == model)


def save_merged(merged: DataFrame, table: str, buckets: int = 8) -> None:
    """A table bucketed and sorted by word, so that joins on words need no exchange."""
    merged.write.mode("overwrite").bucketBy(buckets, "word").sortBy("word").saveAsTable(table)


def write_text_vectors(emb: DataFrame, path: str) -> None:
    """Lines of a word and its numbers, parted by spaces."""
    emb.select(F.concat_ws(" ", F.col("word"), F.concat_ws(" ", F.transform("vec", lambda x: x.cast("string")))).alias("value")).write.mode("overwrite").text(path)


def read_text_vectors(spark: SparkSession, path: str) -> DataFrame:
    """(word, vec); a header line of two numbers is left out."""
    parts = F.split("value", " ")
    rows = spark.read.text(path).where(F.size(parts) > 2)
    return rows.select(F.get(parts, F.lit(0)).alias("word"), F.transform(F.slice(parts, F.lit(2), F.size(parts) - 1), lambda x: x.cast("float")).alias("vec"))


def as_views(**frames: DataFrame) -> None:
    """Temporary views for SQL users."""
    for name, df in frames.items():
        df.createOrReplaceTempView(name)
