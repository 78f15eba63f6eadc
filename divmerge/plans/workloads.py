"""The experiments, on the given tables: what is divided, trained, merged and measured, as tables of results."""

from __future__ import annotations

import time
from collections.abc import Iterator, Sequence
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.draws import u60
from ..operators import gold, measures, vocab
from ..operators.baselines import train_dim_sharded, train_mllib
from ..operators.cells import pair_similarity
from ..operators.corpus import encode, number_sentences
from ..operators.divide import Division
from ..operators.evaluate import MAX_BENCHMARK, clusters, clusters_in_passes, evaluate, neighbours
from ..operators.kernel import SkipGramConfig
from ..operators.merge.basic import by_word, merge_concat, merge_mean, merge_pca, merge_single
from ..operators.merge.consensus import merge_consensus, merge_procrustes
from ..operators.tally import divergences
from ..operators.train import train_central, train_submodels
from ..session import discard, materialize, once
from ..sources.corpora import nation_sentences, numbered_larger, numbered_sentences, supply_sentences

DIVISIONS = ("sequential", "fixed_sample", "epoch_sample")
MERGES = ("concat", "pca", "consensus_random", "consensus_pca")
SMALL = SkipGramConfig(dim=16, window=5, negatives=5, epochs=2)
RATES = (1.0, 5.0, 6.67, 10.0, 20.0, 25.0, 33.0, 50.0)


def union(frames: Sequence[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def corpus(spark: SparkSession, sf_dir: str, order: str = "lang") -> DataFrame:
    """Numbered sentences of the documents in language order (a corpus with drift) or document order."""
    return numbered_sentences(spark, sf_dir, order)


def study_corpus(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(lang, tokens, sent_id): the documents in language order, then sentences of orders and of deliveries, whose relations the analogies ask for.

    The documents keep the numbers that they have; only the others are numbered and written.
    """

    def numbered(rows: DataFrame, by: Sequence[str]) -> DataFrame:
        return number_sentences(rows.withColumn("tokens", F.transform("tokens", lambda t: F.lower(t))), by).select("tokens", "sent_id")

    orders = once(spark, f"{sf_dir}/orders.parquet", "study-orders", lambda: numbered(nation_sentences(spark, sf_dir), ["o_orderkey"]))
    supply = once(spark, f"{sf_dir}/lineitem.parquet", "study-supply", lambda: numbered(supply_sentences(spark, sf_dir), ["l_orderkey", "l_linenumber"]))
    parts, before = [], 0
    for lang, rows in ((F.coalesce("lang", F.lit("")), corpus(spark, sf_dir)), (F.lit("~orders"), orders), (F.lit("~supply"), supply)):
        parts.append(rows.select(lang.alias("lang"), "tokens", (F.col("sent_id") + F.lit(before).cast("long")).alias("sent_id")))
        before += rows.count()
    return union(parts)


def division_of(sent: DataFrame, name: str, rate: float, epochs: int = 1, seed: int = 1, hash_fn: str = "md5", n_sentences: int | None = None) -> Division:
    return Division(name, rate, sent.count() if n_sentences is None else n_sentences, epochs, seed, hash_fn)


def trained(sent: DataFrame, name: str, rate: float, cfg: SkipGramConfig, top: int = vocab.TOP_WORDS, seed: int = 1, more_than: float | None = None, words: DataFrame | None = None) -> tuple[DataFrame, int]:
    """Sub-models of a division, written out, on its vocabulary: the ``top`` words of the corpus, or each model's own words above the threshold; or on ``words``, which were made before."""
    division = division_of(sent, name, rate, cfg.epochs, seed, "xxhash64")
    words = vocab.vocabulary_for(division, sent, top, more_than) if words is None else words
    return materialize(train_submodels(sent, division, words, cfg), "submodels"), division.n


def merged(sub: DataFrame, n: int, method: str, iters: int = 3, seed: int = 1) -> DataFrame:
    """(word, vec) by name of the method."""
    if method == "concat":
        return merge_concat(sub, n)
    if method == "pca":
        return merge_pca(sub, n)
    if method == "mean":
        return merge_mean(sub).select("word", "vec")
    if method.startswith("single"):
        return merge_single(sub, int(method.partition(":")[2] or 0))
    if method == "procrustes":
        return merge_procrustes(sub, n).merged.select("word", "vec")
    return merge_consensus(sub, n, init=method.partition("_")[2] or "pca", iters=iters, seed=seed).merged.select("word", "vec")


def merged_or_none(sub: DataFrame, n: int, method: str, iters: int = 3) -> DataFrame:
    """The same; no rows where the merge needs common words and there are none."""
    try:
        return merged(sub, n, method, iters)
    except ValueError:
        return merge_concat(sub, n).where("false")


def flagship(spark: SparkSession, sf_dir: str, rate: float = 25.0, cfg: SkipGramConfig = SkipGramConfig(dim=16, window=5, epochs=1), top: int = vocab.TOP_WORDS, words: int = 4393) -> DataFrame:
    """Divide, train, merge, judge: (method, n_words, purity) by language for concatenation, consensus and one sub-model."""
    sent = corpus(spark, sf_dir)
    sub, n = trained(sent, "epoch_sample", rate, cfg, top)
    classes = materialize(gold.language_classes(sent, size=words), "classes")
    judged = sub.join(F.broadcast(classes.select("word")), "word", "left_semi")  # merges treat words one by one, but for the rotations
    frames = [merged(judged if m == "concat" else sub, n, m).select(F.lit(m).alias("method"), "word", "vec") for m in ("concat", "consensus_random", "single:0")]
    found = clusters(classes, union(frames), 4, by=("method",))
    return measures.purity(found, by=("method",)).select("method", F.col("n").alias("n_words"), F.round("purity", 4).alias("purity"))


# --- divergence and coverage -----------------------------------------------------------------------------------------


def kl_table(spark: SparkSession, sf_dir: str, rates: Sequence[float] = (10.0,), orders: Sequence[int] = (1, 2), order_by: str = "lang", divisions: Sequence[str] = DIVISIONS, seed: int = 1) -> DataFrame:
    """(order_by, division, rate, gram, kl): mean over all sub-corpora of the divergence from the corpus.

    All divisions and rates go through one count (``operators/tally.py``), which meets the corpus's own in the same place.
    """
    sent = corpus(spark, sf_dir, order_by)
    out = []
    for g in orders:
        kl = divergences(sent, divisions, rates, g, seed).groupBy("division", "rate").agg(F.round(F.avg("kl"), 6).alias("kl"))
        out.append(kl.select(F.lit(order_by).alias("order_by"), "division", "rate", F.lit(g).alias("gram"), "kl"))
    return union(out)


def coverage_table(spark: SparkSession, sf_dir: str, rate: float = 10.0, more_than: float = 0, seed: int = 1) -> DataFrame:
    """(division, n_intersection, n_union, n_reference, coverage) of the sub-corpus vocabularies, against all words of the corpus."""
    sent = corpus(spark, sf_dir)
    total = sent.count()
    plans = [division_of(sent, d, rate, seed=seed, n_sentences=total) for d in DIVISIONS]
    routes = union([p.route(sent, ("tokens",)).select(F.lit(p.name).alias("division"), "model", "mult", "tokens") for p in plans])
    if more_than > 0:
        counts = measures.counts_of(routes, 1, "division", "model").where(F.col("cnt") > more_than)
    else:
        counts = routes.select("division", "model", F.explode("tokens").alias("word")).distinct()
    held = counts.groupBy("division", "word").agg(F.count("*").alias("k"))
    known = sent.select(F.explode("tokens").alias("word")).agg(F.countDistinct("word").alias("n_reference"))
    sums = held.groupBy("division").agg(F.count_if(F.col("k") == plans[0].n).alias("n_intersection"), F.count("*").alias("n_union"))
    return sums.join(F.broadcast(known)).withColumn("coverage", F.round(F.col("n_intersection") / F.col("n_reference"), 6))


# --- quality ---------------------------------------------------------------------------------------------------------


def benchmarks(spark: SparkSession, sf_dir: str, sent: DataFrame, win: int = 5) -> tuple[DataFrame, DataFrame, DataFrame]:
    """The eight sets, from the structure of the tables: (benchmark, w1, w2, gold), (benchmark, word, cls), (benchmark, a, b, c, d).

    Similarity: pairs of the 750 most frequent words, of 48 frequent ones, of words seen 5 to 20 times, and of words of the
    benchmark passages, with the cosine of their PPMI rows on the whole corpus. Categories: language, and language with
    frequency band. Analogies: nation to region, supplier to nation.
    """
    source = f"{sf_dir}/documents.parquet"

    def words() -> DataFrame:
        counts = sent.where(~F.startswith("lang", F.lit("~"))).select("lang", F.explode("tokens").alias("word")).groupBy("word", "lang").agg(F.count("*").alias("k"))
        return counts.groupBy("word").agg(F.sum("k").alias("cnt"), F.min_by("lang", F.struct(-F.col("k"), "lang")).alias("cls"))

    def sims() -> DataFrame:
        seen = once(spark, source, "study-words", words)
        top = seen.orderBy(F.desc("cnt"), "word").select("word", "cnt")
        rare = seen.where("cnt between 5 and 20").orderBy(F.md5("word"), "word").limit(2951).select("word")
        passages = spark.read.parquet(f"{sf_dir}/benchmark.parquet").select(F.explode(F.regexp_extract_all(F.lower("text"), F.lit(r"\p{L}+"), 0)).alias("word")).distinct()
        mixed = passages.orderBy(F.md5("word"), "word").limit(437)
        sets = [("sim_large", top.limit(750), 3000), ("sim_small", top.limit(48), 65), ("sim_rare", rare, 2034), ("sim_mixed", mixed, 353)]
        pairs = union([gold.hashed_pairs(w.select("word"), n, i + 1).select(F.lit(name).alias("benchmark"), "w1", "w2") for i, (name, w, n) in enumerate(sets)])
        pairs = materialize(pairs, "pairs")
        known = pair_similarity(sent, pairs, win)
        return pairs.join(known, ["w1", "w2"], "left").select("benchmark", "w1", "w2", F.coalesce("gold", F.lit(0.0)).alias("gold"))

    def cats() -> DataFrame:
        seen = once(spark, source, "study-words", words).orderBy(F.desc("cnt"), "word")
        band = F.when(F.col("cnt") > 100, "frequent").when(F.col("cnt") > 20, "middle").otherwise("low")
        small = seen.limit(402).select(F.lit("cat_small").alias("benchmark"), "word", "cls")
        return small.unionByName(seen.limit(4393).select(F.lit("cat_large").alias("benchmark"), "word", F.concat_ws(" ", "cls", band).alias("cls")))

    def anas() -> DataFrame:
        nations = gold.nation_analogies(spark, sf_dir).select(F.lit("ana_nation").alias("benchmark"), "a", "b", "c", "d")
        return nations.unionByName(gold.supplier_analogies(spark, sf_dir).select(F.lit("ana_supplier").alias("benchmark"), "a", "b", "c", "d"))

    return once(spark, source, f"gold-sims-{win}", sims), once(spark, source, "gold-cats", cats), once(spark, source, "gold-anas", anas)


def division_effect(spark: SparkSession, sf_dir: str, rates: Sequence[float] = (10.0, 1.0), cfg: SkipGramConfig = SMALL, baselines: bool = True, top: int = vocab.TOP_WORDS, min_count: int = 100) -> DataFrame:
    """(method, benchmark, measure, value, answered, missing) of each division, merged by consensus from principal components in three rounds, beside the baselines.

    Sub-models of ``sequential`` and ``fixed_sample`` have the words seen more than 100 / n times in their own sub-corpus.
    """
    sent = study_corpus(spark, sf_dir)
    sets, frames = benchmarks(spark, sf_dir, sent), []
    for r in rates:
        for d in DIVISIONS:
            sub, n = trained(sent, d, r, cfg, top)
            rows = materialize(by_word(sub), "by_word")
            discard(sub)
            frames.append(materialize(merged(rows, n, "consensus_pca").select(F.lit(f"{d} {r:g}%").alias("method"), "word", "vec"), "merged"))
            discard(rows)
    if baselines:
        words = materialize(vocab.global_vocab(sent, top), "vocab")
        frames.append(materialize(train_central(sent, words, cfg).select(F.lit("central").alias("method"), "word", "vec"), "central"))
        frames += [materialize(train_mllib(sent, k, min_count, cfg.dim, cfg.window, cfg.epochs).select(F.lit(f"mllib {k}").alias("method"), "word", "vec"), "mllib") for k in (10, 100)]
    return evaluate(union(frames), *sets, written=True)


def merge_effect(spark: SparkSession, sf_dir: str, rates: Sequence[float] = (10.0, 5.0, 1.0), cfg: SkipGramConfig = SMALL, top: int = vocab.TOP_WORDS) -> DataFrame:
    """(rate, method, benchmark, measure, value, answered, missing) of each merge of the epoch-sampled sub-models; ``single`` is the mean over all of them.

    For ``single``, ``answered`` and ``missing`` are those of the best and the worst sub-model.
    """
    sent = study_corpus(spark, sf_dir)
    sets, frames = benchmarks(spark, sf_dir, sent), []
    for r in rates:
        sub, n = trained(sent, "epoch_sample", r, cfg, top)
        rate = F.lit(float(r)).alias("rate")
        rows = materialize(by_word(sub), "by_word")
        for m in MERGES:
            emb = merged_or_none(rows, n, m)
            frames.append(materialize(emb.select(rate, F.lit(m).alias("method"), "word", "vec"), "merged"))
        discard(rows)
        frames.append(sub.select(rate, F.concat(F.lit("single:"), "model").alias("method"), "word", "vec"))
    got = evaluate(union(frames), *sets, by=("rate", "method"), written=True)
    alone = F.startswith("method", F.lit("single:"))
    mean = got.where(alone).groupBy("rate", "benchmark", "measure").agg(F.avg("value").alias("value"), F.max("answered").alias("answered"), F.max("missing").alias("missing"))
    return got.where(~alone).unionByName(mean.withColumn("method", F.lit("single")))


def removal_effect(spark: SparkSession, sf_dir: str, percents: Sequence[float] = (0.0, 10.0, 50.0), rate: float = 10.0, cfg: SkipGramConfig = SMALL, top: int = vocab.TOP_WORDS) -> DataFrame:
    """(method, benchmark, removed, value, loss, answered, missing): words of the benchmarks are taken out of some of the sub-models of ``epoch_sample``, never out of all, and the merges compared."""
    sent = study_corpus(spark, sf_dir)
    sims, cats, anas = benchmarks(spark, sf_dir, sent)
    words = union([sims.select(F.explode(F.array("w1", "w2")).alias("word")), cats.select("word"), anas.select(F.explode(F.array("a", "b", "c", "d")).alias("word"))]).distinct()
    words = materialize(words, "words")
    sub, n = trained(sent, "epoch_sample", rate, cfg, top)
    rows = materialize(by_word(sub), "by_word")
    discard(sub)
    frames = []
    for p in percents:
        less = gold.drop_words(rows, words, p, n) if p else rows
        for m in ("concat", "pca", "consensus_pca"):
            emb = merged_or_none(less, n, m)
            frames.append(materialize(emb.select(F.lit(m).alias("method"), F.lit(float(p)).alias("removed"), "word", "vec"), "merged"))
    discard(rows)
    got = materialize(evaluate(union(frames), sims, cats, anas, by=("method", "removed"), written=True), "scores")
    loss = measures.loss_from_removal(got)
    return loss.join(got.select("method", "benchmark", "removed", "measure", "answered", "missing"), ["method", "benchmark", "removed"])


def missing_words(spark: SparkSession, sf_dir: str, percents: Sequence[float] = (0.0, 10.0, 50.0), n: int = 10, sigma: float = 0.5, iters: int = 3) -> DataFrame:
    """(method, removed, answered, corr, missing, purity) on planted sub-models with words taken from some of them.

    Scores count a pair with a missing word as lost: the correlation is over answered pairs, ``missing`` says how many words are gone.
    """
    base = materialize(gold.planted_base(spark.read.parquet(f"{sf_dir}/embeddings.parquet")), "base")
    sub = materialize(gold.planted_rotated(base, n, sigma), "planted")
    w = base.select("word", F.expr("cast(substring(word, 2) as int)").alias("i"))
    pairs = w.select(F.col("word").alias("w1"), "i").join(w.select(F.col("word").alias("w2"), (F.col("i") - 1).alias("i")), "i").select("w1", "w2")
    sims = measures.score_pairs(pairs, base.select("word", "vec")).withColumnRenamed("score", "gold")
    frames = []
    for p in percents:
        less = materialize(gold.drop_words(sub, base.select("word"), p, n), "less")
        frames += [merged_or_none(less, n, m, iters).select(F.lit(m).alias("method"), F.lit(float(p)).alias("removed"), "word", "vec") for m in MERGES]
    by = ["method", "removed"]
    emb = materialize(union(frames), "merged")
    corr = measures.score_pairs(sims, emb, by).groupBy(*by).agg(F.count("score").alias("answered"), F.corr("gold", "score").alias("corr"))
    few = base.count() <= MAX_BENCHMARK
    pure = measures.purity((clusters if few else clusters_in_passes)(base.select("word", "cls"), emb, 10, by=by), by).select(*by, "purity")
    lost = measures.oov_count(base.select("word"), emb, by).select(*by, F.col("n_oov").alias("missing"))
    return corr.join(lost, by).join(pure, by, "left")


def recovered(spark: SparkSession, sf_dir: str, n: int = 10, percent: float = 10.0, iters: int = 20) -> DataFrame:
    """(words, n, corr, max_error): how well cosines of planted vectors come back, over all words and over those that some model lost."""
    base = materialize(gold.planted_base(spark.read.parquet(f"{sf_dir}/embeddings.parquet")), "base")
    sub = materialize(gold.drop_words(gold.planted_shifted(base, n), base.select("word"), percent, n), "less")
    got = merge_consensus(sub, n, init="random", iters=iters, missing="present_only").merged
    every = base.select("word", F.expr("cast(substring(word, 2) as int)").alias("i"))
    pairs = every.select(F.col("word").alias("w1"), "i").join(every.select(F.col("word").alias("w2"), (F.col("i") - 1).alias("i")), "i").select("w1", "w2")
    lost = got.where(F.col("n_present") < n).select(F.col("word").alias("w1"))
    out = [("all", pairs), ("lost", pairs.join(lost, "w1", "left_semi"))]
    return union([measures.recovery(got, base.select("word", "vec"), p).select(F.lit(k).alias("words"), "n", "corr", "max_error") for k, p in out])


def counterexample(spark: SparkSession) -> DataFrame:
    """(method, nearest): word 1's nearest word in two models of three words, in their plain mean, and after alignment."""
    a, b = [(-3.0, -1.0), (0.0, -1.0), (-1.0, 0.0)], [(-2.0, -2.0), (-4.0, 0.0), (-2.0, -4.0)]
    sub = spark.createDataFrame([(k, f"w{i + 1}", list(v), 1) for k, m in enumerate((a, b)) for i, v in enumerate(m)], "model int, word string, vec array<float>, cnt long")
    frames = {"model 0": merge_single(sub, 0), "model 1": merge_single(sub, 1), "mean": merge_mean(sub).select("word", "vec"), "aligned": merge_procrustes(sub, 2, max_iter=50).merged.select("word", "vec")}
    from ..functions.vectors import cosine

    emb = union([f.select(F.lit(k).alias("method"), "word", "vec") for k, f in frames.items()])
    one = emb.where("word = 'w1'").select("method", F.col("vec").alias("v1"))
    return emb.where("word <> 'w1'").join(F.broadcast(one), "method").groupBy("method").agg(F.max_by("word", cosine(F.col("vec"), F.col("v1"))).alias("nearest"))


def averaging(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(method, n, cosine): how near, in truth, the words are that two turned models, their plain mean and their alignment find nearest to each row whose id is divisible by 50."""
    base = materialize(gold.planted_base(spark.read.parquet(f"{sf_dir}/embeddings.parquet")), "base")
    sub = materialize(gold.planted_shifted(base, 2), "planted")
    frames = {"model 0": merge_single(sub, 0), "model 1": merge_single(sub, 1), "mean": merge_mean(sub).select("word", "vec"), "aligned": merge_procrustes(sub, 2, max_iter=50).merged.select("word", "vec")}
    found = []
    for k, emb in frames.items():
        emb = materialize(emb, "turned")
        asked = emb.where(F.expr("cast(substring(word, 2) as long) % 50 = 0")).select(F.col("word").alias("query"), "vec")
        found.append(neighbours(asked, emb, 1).select(F.lit(k).alias("method"), F.col("query").alias("w1"), F.col("word").alias("w2")))
    got = measures.score_pairs(union(found), base.select("word", "vec"))
    return got.groupBy("method").agg(F.count("*").alias("n"), F.round(F.avg("score"), 4).alias("cosine"))


def convergence(spark: SparkSession, sf_dir: str, n: int = 10, iters: int = 10, removed: float = 0.0) -> DataFrame:
    """(round, displacement): the mean normalised displacement after each round."""
    base = gold.planted_base(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))
    sub = gold.planted_rotated(base, n)
    sub = gold.drop_words(sub, base.select("word"), removed, n) if removed else sub
    got = merge_consensus(sub, n, init="random", iters=iters)
    return spark.createDataFrame([(i + 1, float(x)) for i, x in enumerate(got.displacements)], "round int, displacement double")


# --- time ------------------------------------------------------------------------------------------------------------


def _noop(df: DataFrame) -> None:
    df.write.format("noop").mode("overwrite").save()


def training_times(spark: SparkSession, sf_dir: str, rates: Sequence[float] = RATES, cfg: SkipGramConfig = SkipGramConfig(dim=16, window=5, epochs=1), baselines: bool = True, top: int = vocab.TOP_WORDS) -> DataFrame:
    """(method, models, train_s, pca_s, consensus_s, speed_up): wall-clock by sampling rate, beside the baselines; the speed-up is that of training over ``central``.

    All of them but the built-in trainer have the same list of words. It is made once, and its time is part of each ``train_s``.
    """
    sent = corpus(spark, sf_dir)
    sent.count()  # the corpus is prepared before the clock runs
    t = time.time()
    words = materialize(vocab.global_vocab(sent, top), "vocab")
    listed = time.time() - t
    rows: list[tuple] = []
    for r in rates:
        t = time.time() - listed
        sub, n = trained(sent, "epoch_sample", r, cfg, words=words)
        t1 = time.time()
        try:
            _noop(merge_pca(sub, n))
            pca = time.time() - t1
        except ValueError:
            pca = None  # no common word
        t2 = time.time()
        _noop(merge_consensus(sub, n, init="random", iters=3).merged)
        rows.append((f"epoch_sample {r:g}%", n, t1 - t, pca, time.time() - t2))
        discard(sub)
    if baselines:
        t = time.time() - listed
        materialize(train_central(sent, words, cfg), "central")
        rows.append(("central", 1, time.time() - t, None, None))
        for k in (10, 100):
            t = time.time()
            _noop(train_mllib(sent, k, 100, cfg.dim, cfg.window, cfg.epochs))
            rows.append((f"mllib {k}", 1, time.time() - t, None, None))
    from .phases import speed_up

    times = spark.createDataFrame(rows, "method string, models int, train_s double, pca_s double, consensus_s double")
    return times.join(speed_up(times).select("method", "speed_up"), "method", "left") if baselines else times


def scaling(spark: SparkSession, sf_dir: str, shares: Sequence[int] = (25, 50, 75, 100), rate: float = 10.0, cfg: SkipGramConfig = SkipGramConfig(dim=16, window=5, epochs=1), top: int = vocab.TOP_WORDS) -> DataFrame:
    """(corpus, method, share, sentences, seconds): training time for growing parts of both corpora, and of the built-in trainer in 100 partitions on the smaller."""
    rows = []
    for name, sent in (("smaller", corpus(spark, sf_dir)), ("larger", numbered_larger(spark, sf_dir))):
        total = sent.count()
        for s in shares:
            part = sent.where(u60(7, "share", "sent_id", hash_fn="xxhash64") % 100 < s) if s < 100 else sent
            t = time.time()
            discard(trained(part, "epoch_sample", rate, cfg, top)[0])
            rows.append((name, f"epoch_sample {rate:g}%", s, total * s // 100, time.time() - t))
            if name == "smaller":
                t = time.time()
                _noop(train_mllib(part, 100, 100, cfg.dim, cfg.window, cfg.epochs))
                rows.append((name, "mllib 100", s, total * s // 100, time.time() - t))
    return spark.createDataFrame(rows, "corpus string, method string, share int, sentences long, seconds double")


def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Lists of ``ids`` as bytes, a row for a batch: the ids one after the other, and how many each list has."""
    for b in batches:
        lists = b.column("ids")
        size = np.diff(np.asarray(lists.offsets)).astype(np.int32)
        yield pa.RecordBatch.from_arrays([pa.array([np.asarray(lists.flatten()).astype(np.int32).tobytes()], pa.binary()), pa.array([size.tobytes()], pa.binary())], names=["ids", "size"])


def sharded_baseline(spark: SparkSession, sf_dir: str, top: int = vocab.TOP_WORDS, shards: int = 4, block: int = 2000) -> DataFrame:
    """(shards, pairs, round_trips, scalars_sent, seconds_per_1000_pairs) of the dimension-sharded trainer, on all sentences in order (it is measured, not used).

    ``block`` sentences are on the driver at once, beside one partition of the encoded table, packed.
    """
    sent = corpus(spark, sf_dir)
    words = materialize(vocab.global_vocab(sent, top), "vocab")
    packed = materialize(encode(sent.select("sent_id", "tokens"), words), "coded").orderBy("sent_id").mapInArrow(pack, "ids binary, size binary")

    def blocks():
        ids, size = np.zeros(0, np.int32), np.zeros(0, np.int32)
        for r in packed.toLocalIterator():
            ids, size = np.concatenate([ids, np.frombuffer(r["ids"], np.int32)]), np.concatenate([size, np.frombuffer(r["size"], np.int32)])
            while len(size) >= block:
                cut = size[:block].sum()
                yield ids[:cut].astype(np.int64), np.repeat(np.arange(block), size[:block])
                ids, size = ids[cut:], size[block:]
        if len(size):
            yield ids.astype(np.int64), np.repeat(np.arange(len(size)), size)

    got = train_dim_sharded(blocks, np.array([r["cnt"] for r in words.orderBy("word_id").collect()], float), shards)
    return spark.createDataFrame([(shards, got.pairs, got.round_trips, got.scalars_sent, 1000 * got.seconds / max(1, got.pairs))], "shards int, pairs long, round_trips long, scalars_sent long, seconds_per_1000_pairs double")
