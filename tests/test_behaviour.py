"""The behaviour the experiments report, as far as the given tables can show it."""

from divmerge.operators import vocab
from divmerge.operators.corpus import token_counts
from divmerge.plans import workloads as w

SF = "/root/testdata/sf0.01"


def test_shared_vocabulary_by_division(spark):
    got = {r["division"]: (r["n_intersection"], r["n_union"]) for r in w.coverage_table(spark, SF).collect()}
    assert got["epoch_sample"][0] > got["fixed_sample"][0] > 10 * got["sequential"][0]
    assert got["sequential"][1] >= max(got["epoch_sample"][1], got["fixed_sample"][1])


def test_samples_diverge_less_than_slices(spark):
    got = {r["division"]: r["kl"] for r in w.kl_table(spark, SF, (10.0,), (1,)).collect()}
    assert got["sequential"] > 1.5 * max(got["fixed_sample"], got["epoch_sample"])


def test_flagship_runs(spark, sf):
    got = {r["method"]: r["n_words"] for r in w.flagship(spark, sf).collect()}
    assert got["consensus_random"] >= got["concat"] and got["consensus_random"] >= got["single:0"]


def test_words_that_the_merged_models_lack(spark):
    """Own thresholds keep rare words that a global list, cut by frequency, does not have: sequential, then fixed samples, then the list."""
    sent = w.corpus(spark, SF)
    rare = token_counts(sent).where("cnt between 5 and 20").select("word")
    lacking = {}
    for name in w.DIVISIONS:
        d = w.division_of(sent, name, 10.0)
        words = vocab.vocabulary_for(d, sent, size=5000, more_than=0)
        lacking[name] = rare.join(words.select("word").distinct(), "word", "left_anti").count()
    assert lacking["sequential"] < lacking["fixed_sample"] < lacking["epoch_sample"]
    strict = {n: vocab.submodel_vocab(w.division_of(sent, n, 10.0).route(sent, ("tokens",)), 10).select("word").distinct().count() for n in ("sequential", "fixed_sample")}
    assert 0 < strict["fixed_sample"] < strict["sequential"]  # language order gathers a language's words in few slices


def test_scores_of_a_small_experiment(spark, sf):
    """Every set is judged for every method, and a merge on the union lacks no more words than one on the intersection."""
    got = w.merge_effect(spark, sf, (25.0,), w.SkipGramConfig(dim=8, window=3, epochs=1)).collect()
    by = {(r["method"], r["benchmark"]): r for r in got}
    assert len(by) == 5 * 8 and {r["measure"] for r in got} == {"spearman", "purity", "accuracy"}
    for b in {r["benchmark"] for r in got}:
        assert by["consensus_pca", b]["missing"] == by["consensus_random", b]["missing"] <= by["concat", b]["missing"] == by["pca", b]["missing"]
        assert by["consensus_pca", b]["missing"] <= by["single", b]["missing"]


def test_removed_words_come_back(spark, sf):
    got = w.removal_effect(spark, sf, (0.0, 50.0), 25.0, w.SkipGramConfig(dim=8, window=3, epochs=1)).collect()
    by = {(r["method"], r["benchmark"], r["removed"]): r for r in got}
    for b in {r["benchmark"] for r in got}:
        assert by["consensus_pca", b, 50.0]["missing"] == by["consensus_pca", b, 0.0]["missing"]
        assert by["concat", b, 50.0]["missing"] > by["concat", b, 0.0]["missing"] or by["concat", b, 0.0]["answered"] == 0
    assert {r["loss"] for r in got if r["removed"] == 0.0} <= {0.0, None}
