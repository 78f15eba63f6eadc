"""Gold standards from the structure of the given tables, and planted sub-models whose truth is known."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.draws import SPAN, u60
from ..session import ship
from .corpus import token_counts, window_pairs
from .measures import ppmi_similarity
from .merge.linalg import lists_of


def language_classes(sent: DataFrame, lang: str = "lang", size: int = 1000) -> DataFrame:
    """(word, cls): the ``size`` most frequent words with their dominant language (ties: alphabetical)."""
    by = token_counts(sent, lang).where(F.col(lang).isNotNull())
    top = by.groupBy("word").agg(F.sum("cnt").alias("cnt"), F.min_by(lang, F.struct(-F.col("cnt"), F.col(lang))).alias("cls"))
    return top.orderBy(F.desc("cnt"), "word").limit(size).select("word", "cls")


def hashed_pairs(words: DataFrame, n_pairs: int, seed: int = 1) -> DataFrame:
    """(w1, w2): about ``n_pairs`` distinct pairs of ``words(word)``, each word with hash-picked partners; the words go along as one list (a benchmark's)."""
    every = words.agg(F.array_sort(F.collect_set("word")).alias("every"))
    n = max(1, words.count())
    partners = F.transform(F.sequence(F.lit(1), F.lit(-(-n_pairs // n))), lambda k: F.get("every", (u60(seed, "pair", F.col("word"), k) % n).cast("int")))
    rows = words.select("word").distinct().join(F.broadcast(every)).select(F.col("word"), F.explode(F.array_distinct(partners)).alias("other")).where("word <> other")
    rows = rows.select(F.least("word", "other").alias("w1"), F.greatest("word", "other").alias("w2")).distinct()
    return rows.orderBy(F.md5(F.concat_ws(":", F.lit(str(seed)), "w1", "w2")), "w1", "w2").limit(n_pairs)


def planted_base(embeddings: DataFrame, n_classes: int = 10) -> DataFrame:
    """(word, cls, vec): the given unit vectors with a class signal planted by their label."""
    own = embeddings.select(F.concat(F.lit("w"), F.col("vec_id")).alias("word"), F.col("label").alias("cls"), F.col("embedding").alias("e"))
    centre = embeddings.where(F.col("vec_id") < n_classes).select(F.col("vec_id").cast("int").alias("cls"), F.col("embedding").alias("c"))
    return own.join(F.broadcast(centre), "cls").select("word", "cls", F.zip_with("e", "c", lambda x, y: (x + y * F.lit(1.5).cast("float")).cast("float")).alias("vec"))


PARTNERS = 50


def planted_relations(embeddings: DataFrame, seed: int = 1) -> tuple[DataFrame, DataFrame]:
    """Vectors (word, vec) with a planted relation, and the questions (a, b, c, d) about it.

    With m a tenth of the rows, row m + i becomes row i, plus half the last row, plus 0.3 of row 2 m + i. Each pair (i, m + i) is
    asked about with up to ``PARTNERS`` others, picked by a hash. Ids are dense from 0.
    """
    m = embeddings.count() // 10
    e = embeddings.select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("e"))
    last = e.agg(F.max_by("e", "vec_id").alias("shift"))
    a = e.where(F.col("vec_id") < m).select((F.col("vec_id") + m).alias("vec_id"), F.col("e").alias("a"))
    c = e.where((F.col("vec_id") >= 2 * m) & (F.col("vec_id") < 3 * m)).select((F.col("vec_id") - m).alias("vec_id"), F.col("e").alias("c"))
    made = a.join(c, "vec_id").join(F.broadcast(last))
    made = made.select("vec_id", F.zip_with(F.zip_with("a", "shift", lambda x, y: x + y * 0.5), "c", lambda x, y: x + y * 0.3).alias("e"))
    rows = e.where((F.col("vec_id") < m) | (F.col("vec_id") >= 2 * m)).unionByName(made)
    word = lambda x: F.concat(F.lit("w"), x.cast("string"))
    emb = rows.select(word(F.col("vec_id")).alias("word"), F.transform("e", lambda x: x.cast("float")).alias("vec"))
    i = e.where(F.col("vec_id") < m).select(F.col("vec_id").alias("i"))
    away = F.transform(F.sequence(F.lit(1), F.lit(PARTNERS)), lambda k: u60(seed, "partner", F.col("i"), k) % max(1, m - 1) + 1)
    q = i.where(F.lit(m > 1)).select("i", F.explode(F.array_distinct(away)).alias("away")).withColumn("j", (F.col("i") + F.col("away")) % m)
    return emb, q.select(word(F.col("i")).alias("a"), word(F.col("i") + m).alias("b"), word(F.col("j")).alias("c"), word(F.col("j") + m).alias("d"))


def planted_shifted(base: DataFrame, n: int, dim: int = 64) -> DataFrame:
    """Sub-models (model, word, vec, cnt): a cyclic shift by 7 * model and a sign flip of every (model + 2)-th coordinate, both orthogonal."""
    models = base.select("word", "vec", F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias("model"))
    j = F.sequence(F.lit(0), F.lit(dim - 1))
    vec = F.transform(j, lambda k: F.get("vec", (k + F.col("model") * 7) % dim) * F.when(k % (F.col("model") + 2) == 0, -1.0).otherwise(1.0).cast("float"))
    return models.select("model", "word", vec.alias("vec"), F.lit(1).cast("long").alias("cnt"))


def _normals(keys: np.ndarray, d: int) -> np.ndarray:
    """(keys, d) standard normals, each from a counter under its key."""
    with np.errstate(over="ignore"):
        x = keys.astype(np.uint64)[:, None] + (np.arange(2 * d, dtype=np.uint64) + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15)
        for shift, by in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
            x = (x ^ (x >> np.uint64(shift))) * np.uint64(by)
        x ^= x >> np.uint64(31)
    u = ((x >> np.uint64(11)).astype(np.float64) + 0.5) / (1 << 53)
    return np.sqrt(-2 * np.log(u[:, :d])) * np.cos(2 * np.pi * u[:, d:])


def planted_rotated(base: DataFrame, n: int, sigma: float = 0.5, seed: int = 0) -> DataFrame:
    """Sub-models (model, word, vec, cnt) by seeded random rotations, with noise of total size ``sigma``; made row by row in tasks."""
    ship(base.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        turns: list[np.ndarray] = []
        for b in batches:
            if not b.num_rows:
                continue
            x = b.column("vec").flatten().to_numpy().reshape(b.num_rows, -1).astype(np.float64)
            d = x.shape[1]
            if not turns:
                turns = [np.linalg.qr(np.random.default_rng((seed, k)).standard_normal((d, d)))[0] for k in range(n)]
            for k, turn in enumerate(turns):
                key = b.column("key").to_numpy().view(np.uint64) + np.uint64(k * 7919 + 1)
                y = x @ turn + sigma * _normals(key, d) / np.sqrt(d)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(y), k, np.int32)), b.column("word"), lists_of(y), pa.array(np.ones(len(y), np.int64))], names=["model", "word", "vec", "cnt"])

    return base.select("word", "vec", F.xxhash64(F.lit(seed), "word").alias("key")).mapInArrow(run, "model int, word string, vec array<float>, cnt long")


def drop_words(sub: DataFrame, words: DataFrame, percent: float, n: int, seed: int = 1) -> DataFrame:
    """Remove ``percent`` of the benchmark words from some of the sub-models that hold them, hash-chosen; never from all, so a word of one model stays.

    Of sub-models that are grouped by word, (word, models, flat), in one narrow pass; ``words`` go along as a list (a benchmark's).
    """
    w = words.select("word").distinct().where(u60(seed, "drop", "word") < int(percent / 100 * SPAN))
    if "flat" in sub.columns:
        many = (u60(seed, "many", "word") % (F.size("models") - 1) + 1).cast("int")
        rank = F.array_sort(F.transform("models", lambda k: F.struct(u60(seed, "which", F.col("word"), k).alias("u"), k.alias("k"))))
        gone = F.transform(F.slice(rank, F.lit(1), many), lambda s: s["k"])
        d = (F.size("flat") / F.size("models")).cast("int")
        at = F.array_except(F.sequence(F.lit(1), F.size("models")), F.transform(gone, lambda k: F.array_position("models", k).cast("int")))
        kept = F.struct(F.transform(at, lambda i: F.get("models", i - 1)).alias("models"), F.flatten(F.transform(at, lambda i: F.slice("flat", (i - 1) * d + 1, d))).alias("flat"))
        rows = sub.join(F.broadcast(w.withColumn("_drop", F.lit(True))), "word", "left")
        kept = F.when(F.col("_drop") & (F.size("models") > 1), kept).otherwise(F.struct("models", "flat"))
        return rows.select("word", kept.alias("kept")).select("word", "kept.models", "kept.flat")
    held = sub.select("word", "model").join(w, "word", "left_semi").groupBy("word").agg(F.collect_set("model").alias("held")).where(F.size("held") > 1)
    held = held.withColumn("many", (u60(seed, "many", "word") % (F.size("held") - 1) + 1).cast("int"))
    rank = F.array_sort(F.transform("held", lambda k: F.struct(u60(seed, "which", F.col("word"), k).alias("u"), k.alias("k"))))
    gone = held.select("word", F.explode(F.transform(F.slice(rank, F.lit(1), F.col("many")), lambda s: s["k"])).alias("model"))
    return sub.join(gone, ["word", "model"], "left_anti").select("model", "word", "vec", "cnt")


def _asked(pairs: DataFrame, per_pair: int, seed: int) -> DataFrame:
    """(a, b, c, d): each of ``pairs(word, cls)`` beside up to ``per_pair`` others of another class, picked by a hash."""
    n = max(1, pairs.count())
    numbered = F.array_sort(F.collect_set(F.struct("word", "cls"))).alias("every")
    every = pairs.agg(numbered)  # a benchmark's words
    picks = F.transform(F.sequence(F.lit(1), F.lit(per_pair)), lambda k: F.get("every", (u60(seed, "asked", F.col("word"), k) % n).cast("int")))
    rows = pairs.join(F.broadcast(every)).select("word", "cls", F.explode(F.array_distinct(picks)).alias("o")).where("o.cls <> cls")
    return rows.select(F.col("word").alias("a"), F.col("cls").alias("b"), F.col("o.word").alias("c"), F.col("o.cls").alias("d"))


def nation_regions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(word, cls): nation names with their region, in lower case."""
    n = spark.read.parquet(f"{sf_dir}/nation.parquet")
    r = spark.read.parquet(f"{sf_dir}/region.parquet")
    return n.join(F.broadcast(r), n.n_regionkey == r.r_regionkey).select(F.lower("n_name").alias("word"), F.lower("r_name").alias("cls"))


def nation_analogies(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(a, b, c, d): nation, its region, a nation of another region, and its region."""
    return _asked(nation_regions(spark, sf_dir), 40, 1)


def supplier_analogies(spark: SparkSession, sf_dir: str, n_asked: int = 2531) -> DataFrame:
    """(a, b, c, d): supplier, its nation, a supplier of another nation, and its nation; about ``n_asked`` of them."""
    s = spark.read.parquet(f"{sf_dir}/supplier.parquet")
    n = spark.read.parquet(f"{sf_dir}/nation.parquet")
    pairs = s.join(F.broadcast(n), s.s_nationkey == n.n_nationkey).select(F.lower("s_name").alias("word"), F.lower("n_name").alias("cls"))
    return _asked(pairs, max(1, -(-n_asked // max(1, pairs.count()))), 2)
