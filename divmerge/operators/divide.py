"""The divide phase: which sub-model reads which sentence, how often, in which epoch.

A route is (epoch, model, sent_id, mult), with any columns of the sentence that are to go along (``keep``). Draws are hashes
of (seed, epoch, model, sentence), so no sample is stored and a retried task routes alike. All divisions but the exact
``fixed_sample`` are functions of the row: its hits are worked out in place, and nothing is joined.
"""

from __future__ import annotations

import math
from collections.abc import Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.draws import SPAN, below, u60

@dataclass(frozen=True)
class DivisionPlan:
    n: int  # sub-models
    m: int  # sentences in a sample


def plan_division(rate: float, n_sentences: int) -> DivisionPlan:
    """100 / rate sub-models (rounded) of rate percent of the sentences each."""
    if not 0 < rate <= 100:
        raise ValueError("the rate is a percentage")
    return DivisionPlan(max(1, round(100 / rate)), int(rate * n_sentences / 100))


def _route(rows: DataFrame, keep: Sequence[str], epoch: Column, model: Column, mult: Column | None = None) -> DataFrame:
    mult = F.lit(1) if mult is None else mult
    return rows.select(epoch.cast("int").alias("epoch"), model.cast("int").alias("model"), "sent_id", mult.cast("long").alias("mult"), *keep)


def divide_sequential(sent: DataFrame, n: int, n_sentences: int, remainder: str = "last", keep: Sequence[str] = ()) -> DataFrame:
    """Contiguous equal slices in corpus order; what is left over joins the last slice or is dropped."""
    m = max(1, n_sentences // n)
    model = F.floor(F.col("sent_id") / m)
    out = _route(sent, keep, F.lit(0), F.least(model, F.lit(n - 1)) if remainder == "last" else model)
    return out if remainder == "last" else out.where(F.col("model") < n)


def _cuts(log_pmf, many: int) -> list[int]:
    """Upper ends, in 60 bits, of the first outcomes 0, 1, ... of a distribution, up to where less than 2**-60 is left."""
    out, c, k = [], 0.0, 0
    while k < many:
        c += math.exp(log_pmf(k))
        out.append(int(min(c, 1.0) * SPAN))
        if out[-1] >= SPAN or (k > 0 and log_pmf(k) < log_pmf(k - 1) and log_pmf(k) < -42):
            break
        k += 1
    return out


def binomial_cuts(n: int, p: float) -> list[int]:
    """Cuts of Binomial(n, p): a 60-bit draw at or above the k-th cut is more than k."""
    if p >= 1:
        return [0] * n
    return _cuts(lambda k: math.lgamma(n + 1) - math.lgamma(k + 1) - math.lgamma(n - k + 1) + k * math.log(p) + (n - k) * math.log1p(-p), n)


def poisson_cuts(mean: float) -> list[int]:
    return _cuts(lambda k: k * math.log(mean) - mean - math.lgamma(k + 1), 1 << 20) if mean > 0 else [SPAN]


def _above(u: Column, cuts: list[int]) -> Column:
    """How many cuts a draw reaches."""
    return F.size(F.filter(F.array(*[F.lit(c).cast("long") for c in cuts]), lambda c: u >= c))


def divide_fixed_sample(sent: DataFrame, n: int, m: int, n_sentences: int, seed: int = 1, mode: str = "exact", hash_fn: str = "md5", keep: Sequence[str] = ()) -> DataFrame:
    """n samples of m sentences with replacement, the same in every epoch.

    ``exact`` draws n * m positions and counts them (and joins the sentences where columns are kept). ``poisson`` gives every
    sentence in every sample an independent Poisson count with the same mean, in one narrow pass (sizes then vary): the sum
    over samples is drawn first, and then the sample of each, so a sentence costs as many hashes as it has hits.
    """
    if mode == "exact":
        draw = sent.sparkSession.range(n * m).select((F.col("id") / m).cast("int").alias("model"), (F.col("id") % m).alias("k"))
        draw = draw.select("model", (u60(seed, "fixed", "model", "k", hash_fn=hash_fn) % n_sentences).alias("sent_id"))
        hits = draw.groupBy("model", "sent_id").agg(F.count("*").alias("mult"))
        if keep:
            hits = hits.join(sent.select("sent_id", *keep), "sent_id")
        return _route(hits, keep, F.lit(0), F.col("model"), F.col("mult"))
    if mode != "poisson":
        raise ValueError(f"no such mode: {mode}")
    rows = sent.select("sent_id", *keep).withColumn("_u", u60(seed, "poisson", "sent_id", hash_fn=hash_fn))
    rows = rows.withColumn("_many", _above(F.col("_u"), poisson_cuts(n * m / max(1, n_sentences)))).where("_many > 0")
    rows = rows.withColumn("_hits", F.transform(F.sequence(F.lit(1), F.col("_many")), lambda j: u60(seed, "poisson-model", j, F.col("sent_id"), hash_fn=hash_fn) % n))
    each = F.transform(F.array_distinct("_hits"), lambda k: F.struct(k.alias("model"), F.size(F.filter("_hits", lambda h: h == k)).alias("mult")))
    return _route(rows.select("sent_id", *keep, F.inline(each).alias("_model", "_mult")), keep, F.lit(0), F.col("_model"), F.col("_mult"))


def _chosen(n: int, many: Column, draw) -> Column:
    """``many`` distinct models below n, from that many draws: the j-th is below n - many + j + 1, or the highest of these where it was taken already."""

    def step(taken: Column, j: Column) -> Column:
        top = F.lit(n).cast("long") - many + j
        pick = draw(j) % (top + 1)
        return F.array_append(taken, F.when(F.array_contains(taken, pick), top).otherwise(pick))

    return F.aggregate(F.transform(F.sequence(F.lit(0), many - 1), lambda j: j.cast("long")), F.array().cast("array<long>"), step)


def divide_epoch_sample(
    sent: DataFrame, n: int, rate: float, epochs: int = 1, seed: int = 1, draw: str = "bernoulli", resample: bool = True, hash_fn: str = "md5", keep: Sequence[str] = ()
) -> DataFrame:
    """For each epoch, model and sentence a coin of ``rate`` percent; with ``resample=False`` the epoch is left out of the draw.

    ``bernoulli`` tosses n coins a sentence. ``binomial_subset`` draws how many models first and then which, one hash for each
    hit and one more: the same law, for many models. Only hits leave the row.
    """
    p = rate / 100.0
    rows = sent.select("sent_id", *keep, F.explode(F.sequence(F.lit(0), F.lit(epochs - 1))).alias("epoch"))
    key = F.col("epoch") if resample else F.lit(0)
    if draw == "bernoulli":
        hit = F.filter(F.sequence(F.lit(0), F.lit(n - 1)), lambda k: below(u60(seed, "epoch", key, k, F.col("sent_id"), hash_fn=hash_fn), p))
    elif draw == "binomial_subset":
        many = _above(u60(seed, "binomial", key, F.col("sent_id"), hash_fn=hash_fn), binomial_cuts(n, p))
        rows = rows.withColumn("_many", many).where("_many > 0")
        hit = _chosen(n, F.col("_many"), lambda j: u60(seed, "subset", key, j, F.col("sent_id"), hash_fn=hash_fn))
    else:
        raise ValueError(f"no such draw: {draw}")
    return _route(rows.select("epoch", F.explode(hit).alias("model"), "sent_id", *keep), keep, F.col("epoch"), F.col("model"))


def divide_fixed_bernoulli(sent: DataFrame, n: int, rate: float, epochs: int = 1, seed: int = 1, hash_fn: str = "md5", keep: Sequence[str] = ()) -> DataFrame:
    """The same coins in every epoch, without keeping them."""
    return divide_epoch_sample(sent, n, rate, epochs, seed, resample=False, hash_fn=hash_fn, keep=keep)


@dataclass(frozen=True)
class Division:
    """A way of dividing, settled for one corpus."""

    name: str  # sequential, fixed_sample, poisson_sample, fixed_bernoulli or epoch_sample
    rate: float
    n_sentences: int
    epochs: int = 1
    seed: int = 1
    hash_fn: str = "md5"

    @property
    def n(self) -> int:
        return plan_division(self.rate, self.n_sentences).n

    @property
    def own_vocabulary(self) -> bool:
        """Whether sub-models count their own words; the others share one list."""
        return self.name in ("sequential", "fixed_sample", "poisson_sample")

    def route(self, sent: DataFrame, keep: Sequence[str] = (), one_epoch: bool = False) -> DataFrame:
        """(epoch, model, sent_id, mult, keep...). Samples that do not change have epoch 0 alone, to be read in every epoch."""
        m, epochs = plan_division(self.rate, self.n_sentences).m, 1 if one_epoch else self.epochs
        if self.name == "sequential":
            return divide_sequential(sent, self.n, self.n_sentences, keep=keep)
        if self.name in ("fixed_sample", "poisson_sample"):
            return divide_fixed_sample(sent, self.n, m, self.n_sentences, self.seed, "exact" if self.name == "fixed_sample" else "poisson", self.hash_fn, keep)
        if self.name == "fixed_bernoulli":
            return divide_fixed_bernoulli(sent, self.n, self.rate, 1, self.seed, self.hash_fn, keep)
        if self.name != "epoch_sample":
            raise ValueError(f"no such division: {self.name}")
        return divide_epoch_sample(sent, self.n, self.rate, epochs, self.seed, hash_fn=self.hash_fn, keep=keep)


def miss_threshold(u: float, ell: float) -> float:
    """Occurrence probability above which a word is missed by exponentially few samples of rate ``u``, at sentence length ``ell``."""
    return 1.0 - (1.0 - u) ** ((1.0 - u) / (ell * u))


def miss_threshold_col(u: Column, ell: Column) -> Column:
    return 1.0 - F.pow(1.0 - u, (1.0 - u) / (ell * u))


def expected_missing(sent: DataFrame, n: int, u: float, scheme: str = "epoch_sample") -> DataFrame:
    """(word, cnt, n_sent, expected): how many of the n sub-corpora are expected to lack the word.

    ``epoch_sample``: n (1 - u)^sentences that hold it. ``fixed_sample``: n (1 - share of sentences)^(sentences drawn).
    """
    each = F.transform(F.array_distinct("tokens"), lambda w: F.struct(w.alias("word"), F.size(F.filter("tokens", lambda t: t == w)).alias("k")))
    words = sent.select(F.inline(each)).groupBy("word").agg(F.sum("k").alias("cnt"), F.count("*").alias("n_sent"))
    if scheme == "epoch_sample":
        e = n * F.pow(F.lit(1.0 - u), F.col("n_sent"))
    else:
        total = sent.count()
        e = n * F.pow(1.0 - F.col("n_sent") / total, F.lit(float(int(u * total))))
    return words.withColumn("expected", e)


def observed_missing(route: DataFrame, sent: DataFrame, n: int) -> DataFrame:
    """(word, observed): sub-corpora without the word; ``route(model, tokens)`` of one epoch, ``sent(tokens)`` for words that no sample has."""
    held = route.select("model", F.explode("tokens").alias("word")).distinct().groupBy("word").agg(F.count("*").alias("k"))
    words = sent.select(F.explode("tokens").alias("word")).distinct()
    return words.join(held, "word", "left").select("word", (F.lit(n) - F.coalesce("k", F.lit(0))).alias("observed"))


def unigram_mean(route: DataFrame, sent: DataFrame, n: int) -> DataFrame:
    """(word, p, mean_p): corpus probability, and the mean over sub-corpora of the relative frequency; ``route(model, mult, tokens)``."""
    from .corpus import token_counts
    from .vocab import submodel_counts

    full = token_counts(sent)
    total = full.agg(F.sum("cnt")).first()[0] or 1
    sub = submodel_counts(route)
    size = sub.groupBy("model").agg(F.sum("cnt").alias("t"))
    mean = sub.join(F.broadcast(size), "model").groupBy("word").agg((F.sum(F.col("cnt") / F.col("t")) / n).alias("mean_p"))
    return full.select("word", (F.col("cnt") / total).alias("p")).join(mean, "word", "left").fillna(0.0, ["mean_p"])
