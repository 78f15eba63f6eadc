"""Vocabulary policies: a global list by frequency, thresholds, noise weights, and overlap between sub-models."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..session import materialize
from .corpus import token_counts
from .divide import Division

TOP_WORDS = 300_000


def global_vocab(sent: DataFrame, size: int = TOP_WORDS) -> DataFrame:
    """The ``size`` most frequent words (ties by word): (word, word_id, cnt). Counting combines map-side; the top is a bounded sort."""
    top = token_counts(sent).orderBy(F.desc("cnt"), "word").limit(size)
    return top.select("word", (F.row_number().over(Window.orderBy(F.desc("cnt"), "word")) - 1).cast("int").alias("word_id"), "cnt")


def min_count_vocab(sent: DataFrame, at_least: int) -> DataFrame:
    """Words with ``at_least`` occurrences or more (the built-in trainer's rule)."""
    return token_counts(sent).where(F.col("cnt") >= at_least)


def noise_distribution(vocab: DataFrame, power: float = 0.75) -> DataFrame:
    """(word, cnt, p): counts to the ``power``, normalised."""
    w = vocab.select("word", "cnt", F.pow(F.col("cnt").cast("double"), F.lit(power)).alias("w"))
    total = w.agg(F.sum("w")).first()[0] or 1.0
    return w.select("word", "cnt", (F.col("w") / F.lit(total)).alias("p"))


def submodel_counts(route: DataFrame) -> DataFrame:
    """(model, word, cnt) of ``route(model, mult, tokens)``, one epoch's: a word counts once for each time its sentence is read."""
    words = route.select("model", "mult", F.explode("tokens").alias("word"))
    return words.groupBy("model", "word").agg(F.sum("mult").cast("long").alias("cnt"))


def submodel_vocab(route: DataFrame, more_than: float) -> DataFrame:
    """(model, word, cnt): words that occur more than the threshold in a sub-corpus (strictly)."""
    return submodel_counts(route).where(F.col("cnt") > more_than)


def vocabulary_for(division: Division, sent: DataFrame, size: int = TOP_WORDS, more_than: float | None = None) -> DataFrame:
    """The words a division trains: one list (word, word_id, cnt), made once and reused in every epoch, or a list for each model (model, word, cnt).

    ``more_than`` is the threshold of models with lists of their own, 100 / n where it is not given.
    """
    if not division.own_vocabulary:
        return materialize(global_vocab(sent, size), "vocab")
    return submodel_vocab(division.route(sent, ("tokens",), one_epoch=True), 100 / division.n if more_than is None else more_than)


def vocab_overlap(sub: DataFrame, n: int) -> DataFrame:
    """(word, n_models, in_all) over (model, word)."""
    held = sub.groupBy("word").agg(F.countDistinct("model").alias("n_models"))
    return held.select("word", "n_models", (F.col("n_models") == n).alias("in_all"))


def coverage(sub: DataFrame, n: int, reference: DataFrame) -> DataFrame:
    """One row: sizes of intersection, union and reference, and the share of the reference that all sub-models hold."""
    held = vocab_overlap(sub, n).join(reference.select("word", F.lit(1).alias("known")), "word", "full")
    return held.agg(
        F.count_if("in_all").alias("n_intersection"), F.count("n_models").alias("n_union"), F.sum("known").cast("long").alias("n_reference"),
        (F.count_if(F.col("in_all") & F.col("known").isNotNull()) / F.sum("known")).alias("coverage"),
    )
