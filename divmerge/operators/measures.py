"""Measures: divergence, PMI, rank correlation, purity, analogy accuracy, out-of-vocabulary counts, recovery."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.vectors import cosine
from .corpus import bigrams, token_counts


def kl_from_counts(sub: DataFrame, full: DataFrame, key: Sequence[str], by: Sequence[str] = ("model",)) -> DataFrame:
    """(by..., kl): sum p ln(p / q) from ``sub(by..., key..., cnt)`` to ``full(key..., cnt)``; the support of sub lies in that of full.

    With t and T the totals this is sum(cnt ln(cnt / q)) / t + ln(T / t), so one join and one pass are enough.
    """
    q = full.select(*key, F.col("cnt").alias("_q"))
    total = full.agg(F.sum("cnt").cast("double").alias("_all"))
    c = F.col("cnt").cast("double")
    sums = sub.join(q, list(key)).groupBy(*by).agg(F.sum(c * F.log(c / F.col("_q"))).alias("s"), F.sum(c).alias("t"))
    return sums.join(F.broadcast(total)).select(*by, (F.col("s") / F.col("t") + F.log(F.col("_all") / F.col("t"))).alias("kl"))


def counts_of(rows: DataFrame, order: int, *by: str) -> DataFrame:
    """Counts of words (1) or adjacent pairs (2), times ``mult`` where there is one: (by..., word, cnt) or (by..., w1, w2, cnt)."""
    if "mult" not in rows.columns:
        return token_counts(rows, *by) if order == 1 else bigrams(rows, *by)
    each = token_counts(rows, *by, "mult") if order == 1 else bigrams(rows, *by, "mult")
    return each.groupBy(*by, *KEYS[order]).agg(F.sum(F.col("cnt") * F.col("mult")).alias("cnt"))


KEYS = {1: ("word",), 2: ("w1", "w2")}


def kl_divergence(route: DataFrame, sent: DataFrame, order: int = 1, by: Sequence[str] = ("model",)) -> DataFrame:
    """KL of every sub-corpus of ``route(by..., mult, tokens)`` to the corpus, on words (1) or adjacent pairs (2)."""
    return kl_from_counts(counts_of(route, order, *by), counts_of(sent, order), KEYS[order], by)


def shifted_pmi(pairs: DataFrame, k: int = 1, positive: bool = False) -> DataFrame:
    """(word, ctx, cnt, pmi): ln(P(w,c) / P(w)P(c)) - ln k over ``pairs(word, ctx, cnt)``. Totals go along as a row, so ``pairs`` should be written."""
    w = pairs.groupBy("word").agg(F.sum("cnt").alias("cw"))
    c = pairs.groupBy("ctx").agg(F.sum("cnt").alias("cc"))
    total = w.agg(F.sum("cw").cast("double").alias("total"))
    pmi = F.log(F.col("cnt") * F.col("total") / (F.col("cw").cast("double") * F.col("cc"))) - F.log(F.lit(float(k)))
    out = pairs.join(w, "word").join(c, "ctx").join(F.broadcast(total)).select("word", "ctx", "cnt", pmi.alias("pmi"))
    return out.where("pmi > 0") if positive else out


def ppmi_similarity(pairs: DataFrame, words: DataFrame) -> DataFrame:
    """(w1, w2, gold): cosines of positive PMI rows, for ``words(w1, w2)``."""
    rows = shifted_pmi(pairs, 1, positive=True).select("word", "ctx", "pmi")
    wanted = words.select(F.col("w1").alias("word")).union(words.select("w2")).distinct()
    rows = rows.join(wanted, "word", "left_semi")
    norm = rows.groupBy("word").agg(F.sqrt(F.sum(F.col("pmi") * F.col("pmi"))).alias("norm"))
    a = rows.select(F.col("word").alias("w1"), "ctx", F.col("pmi").alias("p1"))
    b = rows.select(F.col("word").alias("w2"), "ctx", F.col("pmi").alias("p2"))
    both = words.select("w1", "w2").distinct().join(a, "w1").join(b, ["w2", "ctx"]).groupBy("w1", "w2").agg(F.sum(F.col("p1") * F.col("p2")).alias("dot"))
    out = words.select("w1", "w2").distinct().join(both, ["w1", "w2"], "left")
    out = out.join(norm.select(F.col("word").alias("w1"), F.col("norm").alias("n1")), "w1").join(norm.select(F.col("word").alias("w2"), F.col("norm").alias("n2")), "w2")
    return out.select("w1", "w2", (F.coalesce("dot", F.lit(0.0)) / (F.col("n1") * F.col("n2"))).alias("gold"))


def score_pairs(sim: DataFrame, emb: DataFrame, by: Sequence[str] = ()) -> DataFrame:
    """``sim(w1, w2, gold, ...)`` with the cosine of ``emb(by..., word, vec)``; pairs with a missing word have a null score."""
    every = sim.join(F.broadcast(emb.select(*by).distinct())) if by else sim
    a = emb.select(*by, F.col("word").alias("w1"), F.col("vec").alias("v1"))
    b = emb.select(*by, F.col("word").alias("w2"), F.col("vec").alias("v2"))
    both = every.join(a, [*by, "w1"], "left").join(b, [*by, "w2"], "left")
    return both.withColumn("score", cosine(F.col("v1"), F.col("v2"))).select(*by, *sim.columns, "score")


def spearman(scored: DataFrame, x: str = "gold", y: str = "score", by: Sequence[str] = ()) -> DataFrame:
    """(by..., n, rho): correlation of average ranks over rows where both are known.

    A value's rank is the number of lesser rows plus half of its equals, from counts by value. Without ``by`` the counts of one
    column are one window's, over its distinct values: benchmarks are small, and that is what they are for.
    """
    rows = scored.where(F.col(x).isNotNull() & F.col(y).isNotNull())

    def ranks(c: str) -> DataFrame:
        n = rows.groupBy(*by, F.col(c).alias("_v")).agg(F.count("*").alias("_n"))
        below = Window.partitionBy(*(by or [F.lit(1)])).orderBy("_v").rowsBetween(Window.unboundedPreceding, -1)
        return n.select(*by, F.col("_v").alias(c), (F.coalesce(F.sum("_n").over(below), F.lit(0)) + (F.col("_n") + 1) / 2.0).alias(f"_r_{c}"))

    ranked = rows.join(ranks(x), [*by, x]).join(ranks(y), [*by, y])
    return ranked.groupBy(*by).agg(F.count("*").alias("n"), F.corr(f"_r_{x}", f"_r_{y}").alias("rho"))


def purity(assigned: DataFrame, by: Sequence[str] = ()) -> DataFrame:
    """(by..., n, purity) of ``assigned(cluster, cls)``: the share of the majority class, over clusters."""
    each = assigned.groupBy(*by, "cluster", "cls").agg(F.count("*").alias("k"))
    top = each.groupBy(*by, "cluster").agg(F.max("k").alias("top"), F.sum("k").alias("n"))
    return top.groupBy(*by).agg(F.sum("n").alias("n"), (F.sum("top") / F.sum("n")).alias("purity"))


def oov_count(words: DataFrame, emb: DataFrame, by: Sequence[str] = (), sets: Sequence[str] = ()) -> DataFrame:
    """(by..., sets..., n_words, n_oov) over the distinct benchmark ``words(sets..., word)``, against ``emb(by..., word)``."""
    own = words.select(*sets, "word").distinct()
    own = own.join(F.broadcast(emb.select(*by).distinct())) if by else own
    known = emb.select(*by, "word", F.lit(1).alias("known")).distinct()
    return own.join(known, [*by, "word"], "left").groupBy(*by, *sets).agg(F.count("*").alias("n_words"), F.count_if(F.col("known").isNull()).alias("n_oov"))


def recovery(merged: DataFrame, truth: DataFrame, pairs: DataFrame) -> DataFrame:
    """One row (n, corr, max_error): cosines of merged vectors against the true ones, over ``pairs(w1, w2)``."""
    gold = score_pairs(pairs.select("w1", "w2"), truth).withColumnRenamed("score", "gold")
    got = score_pairs(gold, merged).where("score is not null and gold is not null")
    return got.agg(F.count("*").alias("n"), F.corr("gold", "score").alias("corr"), F.max(F.abs(F.col("gold") - F.col("score"))).alias("max_error"))


def loss_from_removal(results: DataFrame, value: str = "value", removed: str = "removed", by: Sequence[str] = ("method", "benchmark")) -> DataFrame:
    """(by..., removed, value, loss): how much a measure falls against the run in which nothing was removed."""
    base = results.where(F.col(removed) == 0).select(*by, F.col(value).alias("_base"))
    return results.join(base, list(by)).select(*by, removed, value, (F.col("_base") - F.col(value)).alias("loss"))
