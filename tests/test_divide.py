import math

import pytest
from pyspark.sql import functions as F

from divmerge.functions.draws import gaussian
from divmerge.operators import divide
from divmerge.operators.corpus import number_sentences, split_sentences, window_pairs


@pytest.fixture(scope="module")
def sent(spark):
    return spark.range(4000).select(F.col("id").alias("sent_id"), F.array(F.concat(F.lit("w"), (F.col("id") % 50).cast("string")), F.lit("the")).alias("tokens")).cache()


def test_plan_of_rates():
    assert [divide.plan_division(r, 1000).n for r in (1, 5, 6.67, 10, 20, 25, 33, 50)] == [100, 20, 15, 10, 5, 4, 3, 2]
    with pytest.raises(ValueError):
        divide.plan_division(0, 10)


def test_sequential_slices_and_remainder(sent):
    part = sent.where("sent_id < 12")
    assert [r["count"] for r in divide.divide_sequential(part, 5, 12).groupBy("model").count().orderBy("model").collect()] == [2, 2, 2, 2, 4]
    assert divide.divide_sequential(part, 5, 12, "drop").count() == 10


def test_sample_sizes_are_binomial(sent):
    n, p = 4000, 0.1
    for draw in ("bernoulli", "binomial_subset"):
        sizes = [r["count"] for r in divide.divide_epoch_sample(sent, 10, 10.0, 1, 3, draw).groupBy("model").count().collect()]
        assert len(sizes) == 10 and all(abs(s - n * p) < 4.5 * math.sqrt(n * p * (1 - p)) for s in sizes)
    exact = divide.divide_fixed_sample(sent, 10, 400, n, 3).groupBy("model").agg(F.sum("mult").alias("m")).collect()
    assert {r["m"] for r in exact} == {400}
    loose = divide.divide_fixed_sample(sent, 10, 400, n, 3, mode="poisson").groupBy("model").agg(F.sum("mult").alias("m")).collect()
    assert all(abs(r["m"] - 400) < 4.5 * 20 for r in loose)


def test_many_models(sent):
    for n in (1000, 10_000):
        per = divide.divide_epoch_sample(sent, n, 100 / n, 1, 3, "binomial_subset").groupBy("sent_id").agg(F.count("*").alias("k"), F.countDistinct("model").alias("d"), F.max("model").alias("top")).collect()
        assert all(r["k"] == r["d"] and r["top"] < n for r in per) and abs(sum(r["k"] for r in per) - 4000) < 4.5 * 64
    wide = divide.divide_epoch_sample(sent.limit(50), 1100, 10.0, 1, 3, "binomial_subset").groupBy("sent_id").count().collect()
    assert len(wide) == 50 and abs(sum(r["count"] for r in wide) - 5500) < 4.5 * 71
    assert divide.divide_epoch_sample(sent.limit(10), 7, 100.0, 1, 3, "binomial_subset").count() == 70


def test_binomial_cuts_are_those_of_the_law():
    for n, p in ((10, 0.1), (100, 0.01), (40, 0.5)):
        c, want = 0.0, []
        for k in range(n):
            c += math.comb(n, k) * p**k * (1 - p) ** (n - k)
            want.append(c)
        got = [x / (1 << 60) for x in divide.binomial_cuts(n, p)]
        assert all(abs(a - b) < 1e-12 for a, b in zip(got, want)) and (len(got) == n or got[-1] > 1 - 1e-12)


def test_fixed_coins_repeat_and_fresh_ones_do_not(sent):
    per = lambda r, e: {(x["model"], x["sent_id"]) for x in r.where(F.col("epoch") == e).collect()}
    fixed, fresh = divide.divide_fixed_bernoulli(sent, 4, 25.0, 2), divide.divide_epoch_sample(sent, 4, 25.0, 2)
    assert per(fixed, 0) == per(fixed, 1) and per(fresh, 0) != per(fresh, 1)
    assert per(fixed, 0) == per(divide.divide_epoch_sample(sent, 4, 25.0, 1), 0)


def test_draws_do_not_depend_on_partitions(sent):
    a = divide.divide_epoch_sample(sent.repartition(1), 4, 25.0, hash_fn="xxhash64").orderBy("model", "sent_id").collect()
    assert a == divide.divide_epoch_sample(sent.repartition(13), 4, 25.0, hash_fn="xxhash64").orderBy("model", "sent_id").collect()


def test_miss_threshold_values():
    for (u, ell), want in {(0.1, 100): 0.009438, (0.01, 100): 0.009900, (0.1, 10): 0.090467}.items():
        assert abs(divide.miss_threshold(u, ell) - want) < 1e-6


def test_expected_and_observed_misses_agree(sent):
    route = divide.divide_epoch_sample(sent, 10, 10.0, 1, 5, keep=("tokens",))
    both = divide.expected_missing(sent, 10, 0.1).join(divide.observed_missing(route, sent, 10), "word").agg(F.sum("expected").alias("e"), F.sum("observed").alias("o")).first()
    assert abs(both["e"] - both["o"]) < 5


def test_gaussian_draws(spark):
    r = spark.range(20000).select(gaussian(1, "t", F.col("id")).alias("x")).agg(F.avg("x").alias("m"), F.stddev("x").alias("s")).first()
    assert abs(r["m"]) < 0.03 and abs(r["s"] - 1) < 0.03


def test_sentences_of_odd_texts(spark):
    rows = spark.createDataFrame([(0, ""), (1, "... !!"), (2, None), (3, "one"), (4, "A b. C\n\nd e")], "doc_id long, text string")
    got = [(r["doc_id"], r["tokens"]) for r in split_sentences(rows).orderBy("doc_id", "pos").collect()]
    assert got == [(3, ["one"]), (4, ["a", "b"]), (4, ["c"]), (4, ["d", "e"])]
    numbered = number_sentences(split_sentences(rows), ["doc_id", "pos"])
    assert sorted(r["sent_id"] for r in numbered.collect()) == [0, 1, 2, 3]


def test_window_pairs_by_hand(spark):
    s = spark.createDataFrame([(["a", "b", "c"],)], "tokens array<string>")
    got = {(r["word"], r["ctx"]): r["cnt"] for r in window_pairs(s, 1).collect()}
    assert got == {("a", "b"): 1, ("b", "a"): 1, ("b", "c"): 1, ("c", "b"): 1}
    assert window_pairs(s, 2).count() == 6
