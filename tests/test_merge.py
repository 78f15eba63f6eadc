import numpy as np
import pytest

from divmerge.operators import gold, measures
from divmerge.operators.merge.basic import by_word, components, merge_concat, merge_mean, merge_pca
from divmerge.operators.merge.consensus import merge_consensus, merge_in_groups, merge_procrustes, reconstruct
from divmerge.operators.merge.extra import merge_lle, merge_low_rank
from divmerge.operators.merge.linalg import procrustes
from divmerge.plans.workloads import counterexample
from divmerge.session import materialize


@pytest.fixture(scope="module")
def base(spark):
    rng = np.random.default_rng(3)
    x = rng.standard_normal((80, 8))
    return spark.createDataFrame([(f"w{i}", i % 4, [float(v) for v in r]) for i, r in enumerate(x)], "word string, cls int, vec array<float>")


def frame(df):
    return {r["word"]: np.array(r["vec"], float) for r in df.collect()}


def cosines(v, names):
    x = np.array([v[n] / np.linalg.norm(v[n]) for n in names])
    return x @ x.T


def test_procrustes_is_orthogonal_and_finds_a_rotation():
    rng = np.random.default_rng(0)
    x, (q, _) = rng.standard_normal((50, 6)), np.linalg.qr(rng.standard_normal((6, 6)))
    w = procrustes(x.T @ (x @ q))
    assert np.allclose(w @ w.T, np.eye(6), atol=1e-8) and np.allclose(w, q, atol=1e-8)


def test_concat_and_pca_against_numpy(base):
    sub = gold.planted_shifted(base, 3, 8)
    c = frame(merge_concat(sub, 3))
    assert len(c) == 80 and all(len(v) == 24 for v in c.values())
    x = np.array([c[f"w{i}"] for i in range(80)])
    _, vec, var = components(merge_concat(sub, 3), 24, 4)
    val = np.linalg.eigvalsh(np.cov(x.T))[::-1][:4]
    assert np.allclose(var, val, rtol=1e-6)
    _, _, again = components(merge_concat(sub, 3), 24, 4, solver="randomized")
    assert np.allclose(again, val, rtol=1e-4)
    assert all(len(v) == 8 for v in frame(merge_pca(sub, 3)).values())


def test_consensus_finds_the_cosines_when_nothing_is_missing(base):
    names = [f"w{i}" for i in range(80)]
    true = cosines(frame(base), names)
    for init in ("random", "pca", "first"):
        got = merge_consensus(gold.planted_shifted(base, 4, 8), 4, init=init, iters=2)
        assert np.abs(cosines(frame(got.merged), names) - true).max() < 1e-4
        assert all(np.allclose(w @ w.T, np.eye(8), atol=1e-6) for w in got.rotations.values())


def test_consensus_covers_the_union_and_reconstructs(base):
    sub = gold.planted_shifted(base, 4, 8)
    less = gold.drop_words(sub, base.select("word"), 50.0, 4).cache()
    assert merge_concat(less, 4).count() < 80
    slow = merge_consensus(less, 4, init="random", iters=3)
    quick = merge_consensus(less, 4, init="random", iters=25, missing="present_only")
    assert slow.merged.count() == quick.merged.count() == 80
    names = [f"w{i}" for i in range(80)]
    true = cosines(frame(base), names)
    assert np.abs(cosines(frame(quick.merged), names) - true).max() < 1e-2
    back, whole = reconstruct(quick, less, 2), {(r["model"], r["word"]): np.array(r["vec"]) for r in sub.collect()}
    rows = back.collect()
    assert rows and all(np.dot(r["vec"], whole[2, r["word"]]) / np.linalg.norm(r["vec"]) / np.linalg.norm(whole[2, r["word"]]) > 0.99 for r in rows)


def test_displacement_falls(base):
    d = merge_consensus(gold.planted_rotated(base, 5, 0.5), 5, init="random", iters=6).displacements
    assert all(b <= a + 1e-9 for a, b in zip(d, d[1:])) and d[-1] > 0


def test_empty_intersection(spark):
    rows = [(0, "a", [1.0, 0.0], 1), (1, "b", [0.0, 1.0], 1)]
    sub = spark.createDataFrame(rows, "model int, word string, vec array<float>, cnt long")
    assert merge_concat(sub, 2).count() == 0
    with pytest.raises(ValueError):
        merge_pca(sub, 2)
    got = merge_consensus(sub, 2, init="pca", iters=1)
    assert got.init == "random" and got.merged.count() == 2


def test_alignment_before_averaging(spark):
    assert {r["method"]: r["nearest"] for r in counterexample(spark).collect()} == {"model 0": "w3", "model 1": "w3", "mean": "w2", "aligned": "w3"}


def test_generic_consensus_and_extras(base):
    sub = gold.planted_shifted(base, 3, 8)
    names = [f"w{i}" for i in range(80)]
    assert np.abs(cosines(frame(merge_procrustes(sub, 3).merged), names) - cosines(frame(base), names)).max() < 1e-4
    mean = frame(merge_mean(sub))
    every = {(r["model"], r["word"]): np.array(r["vec"], float) for r in sub.collect()}
    assert all(np.allclose(mean[w], sum(every[k, w] for k in range(3)) / 3, atol=1e-6) for w in names)


def test_low_rank_and_lle_against_numpy(base):
    sub = gold.planted_shifted(base, 3, 8)
    c = frame(merge_concat(sub, 3))
    names = sorted(c)
    x = np.array([c[n] for n in names])
    m = np.zeros((80, 80))
    for part in np.split(x, 3, 1):  # projections off each model's leading directions
        z = part - part.mean(0)
        val, vec = np.linalg.eigh(z @ z.T)
        lead = vec[:, np.sqrt(np.maximum(val, 0)) > 0.1 * np.sqrt(val[-1])]
        off = np.eye(80) - lead @ lead.T
        m += off.T @ off / 3
    low = frame(merge_low_rank(sub, 3, 5))
    y = np.array([low[n] for n in names])
    assert np.allclose(y.T @ y, np.eye(5), atol=1e-5) and abs(np.trace(y.T @ m @ y) - np.linalg.eigvalsh(m)[:5].sum()) < 1e-6
    w = np.zeros((80, 80))
    for i in range(80):
        far = ((x - x[i]) ** 2).sum(1)
        far[i] = np.inf
        near = np.argsort(far)[:10]
        g = (x[near] - x[i]) @ (x[near] - x[i]).T
        v = np.linalg.solve(g + np.eye(10) * 1e-3 * np.trace(g), np.ones(10))
        w[i, near] = v / v.sum()
    r = (np.eye(80) - w).T @ (np.eye(80) - w)
    lle = frame(merge_lle(sub, 3, 5))
    y = np.array([lle[n] for n in names])
    assert abs(np.trace(y.T @ r @ y) - np.linalg.eigvalsh(r)[1:6].sum()) < 1e-5


def reference_consensus(sub, n, d, y, rounds):
    """The rounds by their definition: missing rows are made, everything is averaged."""
    moved = []
    for _ in range(rounds):
        aligned = np.zeros((n, *y.shape))
        for k in range(n):
            on = ~np.isnan(sub[k, :, 0])
            u, _, vt = np.linalg.svd(sub[k, on].T @ y[on])
            aligned[k] = np.where(on[:, None], np.nan_to_num(sub[k]) @ (u @ vt), y)
        y = aligned.mean(0)
        moved.append(np.mean([np.linalg.norm(y - a) for a in aligned]) / np.sqrt(y.size))
    return y, moved


@pytest.mark.parametrize("history", [1 << 40, 1])
def test_consensus_is_the_plain_iteration(base, monkeypatch, history):
    from divmerge.operators.merge import consensus

    monkeypatch.setattr(consensus, "HISTORY_BYTES", history)
    sub = gold.drop_words(gold.planted_rotated(base, 3, 0.5), base.select("word"), 60.0, 3).cache()
    start = merge_consensus(sub, 3, init="random", iters=0)
    y0 = frame(start.merged)
    names = sorted(y0)
    held = np.full((3, 80, 8), np.nan)
    for r in sub.collect():
        held[r["model"], names.index(r["word"])] = r["vec"]
    got = merge_consensus(sub, 3, init="random", iters=4)
    y, moved = reference_consensus(held, 3, 8, np.array([y0[x] for x in names]), 4)
    assert np.allclose(got.displacements, moved, atol=1e-5)
    out = frame(got.merged)
    assert np.allclose(np.array([out[x] for x in names]), y, atol=1e-5)


def test_a_round_is_one_narrow_pass(base):
    from divmerge.operators.merge import consensus

    sub = gold.planted_shifted(base, 3, 8)
    plan = merge_consensus(sub, 3, init="random", iters=3).merged._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "Join" not in plan and consensus.HISTORY_BYTES > 0


def test_groups_of_models(base):
    names = [f"w{i}" for i in range(80)]
    got = merge_in_groups(gold.planted_shifted(base, 7, 8), 7, 3, init="random", iters=3)
    assert np.abs(cosines(frame(got.merged), names) - cosines(frame(base), names)).max() < 1e-4


def test_nothing_to_merge(base):
    none = gold.planted_shifted(base, 2, 8).where("false")
    assert merge_consensus(none, 2).merged.count() == merge_concat(none, 2).count() == merge_mean(none).count() == 0


def test_measures_by_hand(spark):
    s = spark.createDataFrame([(1.0, 1.0), (2.0, 3.0), (2.0, 2.0), (4.0, 4.0), (None, 9.0)], "gold double, score double")
    assert abs(measures.spearman(s).first()["rho"] - np.corrcoef([1, 2.5, 2.5, 4], [1, 3, 2, 4])[0, 1]) < 1e-12
    p = spark.createDataFrame([(0, "x"), (0, "x"), (0, "y"), (1, "y"), (1, "x"), (1, "y")], "cluster int, cls string")
    assert abs(measures.purity(p).first()["purity"] - 4 / 6) < 1e-12


def test_recovery_and_loss(spark, base):
    pairs = spark.createDataFrame([("w1", "w2"), ("w3", "w4"), ("w5", "gone")], "w1 string, w2 string")
    same = measures.recovery(base.select("word", "vec"), base.select("word", "vec"), pairs).first()
    assert same["n"] == 2 and same["max_error"] < 1e-12
    rows = spark.createDataFrame([("a", "x", 0.0, 0.9), ("a", "x", 50.0, 0.4)], "method string, benchmark string, removed double, value double")
    assert {r["removed"]: round(r["loss"], 9) for r in measures.loss_from_removal(rows).collect()} == {0.0: 0.0, 50.0: 0.5}


def test_merges_of_sub_models_that_were_grouped_once(base):
    """A written table by word serves all merges: the same results as from rows, without another exchange."""
    sub = materialize(gold.drop_words(gold.planted_rotated(base, 3), base.select("word"), 40.0, 3), "less")
    rows = materialize(by_word(sub), "by_word")
    makes = (lambda s: merge_concat(s, 3), lambda s: merge_pca(s, 3), lambda s: merge_consensus(s, 3, init="pca").merged, lambda s: merge_consensus(s, 3, init="random").merged)
    for make in makes:
        plain, shared = frame(make(sub)), make(rows)
        got = frame(shared)
        assert got.keys() == plain.keys() and all(np.allclose(got[k], plain[k], atol=1e-4) for k in got)
        assert "Exchange" not in shared._jdf.queryExecution().executedPlan().toString()


def test_words_are_dropped_from_grouped_sub_models_alike(base):
    sub, words = gold.planted_rotated(base, 4), base.select("word").limit(60)
    of = lambda rows: {r["word"]: (r["models"], r["flat"]) for r in rows.collect()}
    for percent in (30.0, 100.0):
        less = of(gold.drop_words(materialize(by_word(sub), "by_word"), words, percent, 4))
        assert less == of(by_word(gold.drop_words(sub, words, percent, 4))) and 0 < sum(len(m) < 4 for m, _ in less.values()) <= 60
