import numpy as np
import pytest
from pyspark.sql import functions as F

from divmerge.operators import vocab
from divmerge.operators.corpus import encode, vocabulary_of
from divmerge.operators.divide import Division
from divmerge.operators.kernel import _Matrix, NoiseTable, SkipGram, SkipGramConfig, contexts_of, pairs_of, windows_of
from divmerge.operators.train import _Task, deliver, train_central, train_submodels


def test_gradient_is_that_of_the_objective():
    m = SkipGram(np.array([5, 4, 3, 2, 1]), SkipGramConfig(dim=4, negatives=2), 1)
    rng = np.random.default_rng(0)
    m.words, m.contexts = rng.standard_normal((5, 4)).astype(np.float64), rng.standard_normal((5, 4)).astype(np.float64)
    w, c, neg = np.array([1]), np.array([[2, -1, 0]]), np.array([[3, 4]])

    def objective():  # pair by pair, each with all the negatives
        x, log_sigmoid = m.words[1], lambda v: -np.log1p(np.exp(-v))
        return sum(log_sigmoid(m.contexts[k] @ x) + sum(log_sigmoid(-m.contexts[n] @ x) for n in (3, 4)) for k in (2, 0))

    gx, gy, gz, v = m.gradients(w, c, neg)
    assert abs(v - objective()) < 1e-6 and not gy[0, 1].any()
    for matrix, row, grad in ((m.words, 1, gx[0]), (m.contexts, 2, gy[0, 0]), (m.contexts, 0, gy[0, 2]), (m.contexts, 3, gz[0, 0])):
        for j in range(4):
            matrix[row, j] += 1e-5
            up = objective()
            matrix[row, j] -= 2e-5
            down = objective()
            matrix[row, j] += 1e-5
            assert abs((up - down) / 2e-5 - grad[j]) < 1e-4


def test_shrunk_windows_and_subsampling():
    ids, sent = np.arange(40) % 4, np.zeros(40, int)
    whole, part = pairs_of(ids, sent, 5), pairs_of(ids, sent, 5, np.random.default_rng(0))
    assert 0 < len(part[0]) < len(whole[0])
    m = SkipGram(np.array([1000.0, 1, 1, 1]), SkipGramConfig(dim=2, window=2, subsample=1e-4), 1)
    m.train(np.zeros(4000, np.int64), np.zeros(4000, int), 0.0)
    assert m.pairs < 4000 and m.seen[0] == 4000


def test_noise_follows_its_power():
    counts = np.array([1000.0, 100, 10])
    got = np.bincount(NoiseTable(counts).draw(np.random.default_rng(0), 200_000), minlength=3) / 200_000
    assert np.allclose(got, counts**0.75 / (counts**0.75).sum(), atol=0.005)


def test_pairs_stay_inside_sentences():
    w, c = pairs_of(np.array([0, 1, 2, 3]), np.array([0, 0, 1, 1]), 5)
    assert sorted(zip(w.tolist(), c.tolist())) == [(0, 1), (1, 0), (2, 3), (3, 2)]
    assert len(pairs_of(np.array([7]), np.array([0]), 5)[0]) == 0


@pytest.mark.parametrize("shrunk", [False, True])
def test_a_run_of_positions_is_the_sum_of_its_positions(shrunk):
    rng = np.random.default_rng(3)
    m = SkipGram(np.ones(30), SkipGramConfig(dim=6, negatives=3), 1)
    m.words, m.contexts = (rng.standard_normal((30, 6)).astype(np.float32) for _ in range(2))
    ids, sent = rng.integers(0, 30, 50), np.repeat([0, 1, 2, 3], [20, 1, 9, 20])
    near = contexts_of(ids, sent, 4, np.random.default_rng(5) if shrunk else None)
    on = windows_of(sent, 4, np.random.default_rng(5) if shrunk else None)
    assert on.shape == (50, 9) and on.sum() == (near >= 0).sum()
    lo, hi, reach = 7, 40, 4
    neg = rng.integers(0, 30, (hi - lo, 3))
    padded = np.concatenate([[0] * reach, ids, [0] * reach])
    gx, gy, gz, v = m.run_gradients(ids[lo:hi], padded[lo : hi + 2 * reach], on[lo:hi], neg)
    hx, hy, hz, u = m.gradients(ids[lo:hi], near[lo:hi], neg)
    want, got = (np.zeros((30, 6)) for _ in range(2))
    np.add.at(want, near[lo:hi][near[lo:hi] >= 0], hy[near[lo:hi] >= 0])
    np.add.at(got, padded[lo : hi + 2 * reach], gy)
    assert np.allclose(gx, hx, atol=1e-4) and np.allclose(gz, hz, atol=1e-4) and np.allclose(got, want, atol=1e-4) and abs(u - v) < 1e-2


def test_noise_is_searched_from_a_table():
    counts = np.random.default_rng(0).zipf(1.5, 5000).astype(float)
    noise = NoiseTable(counts)
    u = np.random.default_rng(7).random(20_000)
    assert (noise.draw(np.random.default_rng(7), 20_000) == np.searchsorted(noise.cum, u, "right")).all()
    assert noise.steps >= 2 * len(counts)


def test_training_raises_the_objective():
    rng = np.random.default_rng(1)
    ids = np.concatenate([rng.choice([0, 1, 2], 3000), rng.choice([3, 4, 5], 3000)])
    sent = np.arange(6000) // 6
    m = SkipGram(np.bincount(ids).astype(float), SkipGramConfig(dim=8, window=3, rate=0.1, batch_pairs=512), 1)
    values = [m.train(ids, sent, 0.0) for _ in range(5)]
    assert values[-1] > values[0]
    x = m.words / np.linalg.norm(m.words, axis=1, keepdims=True)
    assert (x @ x.T)[0, 1] > (x @ x.T)[0, 4]


@pytest.fixture(scope="module")
def sent(spark):
    return spark.range(600).select(F.col("id").alias("sent_id"), F.transform(F.sequence(F.lit(0), F.lit(7)), lambda k: F.concat(F.when(F.col("id") % 2 == 0, "a").otherwise("b"), F.pmod(F.xxhash64("id", k), F.lit(5)).cast("string"))).alias("tokens")).cache()


def vectors(df):
    return {(r["model"], r["word"]): np.array(r["vec"]) for r in df.collect()}


def test_each_model_has_its_own_task_and_words(sent):
    words = vocab.global_vocab(sent, 100)
    cfg = SkipGramConfig(dim=8, window=3, epochs=2)
    d = Division("epoch_sample", 25.0, 600, 2)
    got = vectors(train_submodels(sent, d, words, cfg))
    assert {m for m, _ in got} == {0, 1, 2, 3} and len(got) == 40
    again = vectors(train_submodels(sent.repartition(7), d, words, cfg))
    assert all(np.allclose(got[k], again[k]) for k in got)
    slices = vectors(train_submodels(sent, Division("sequential", 33.0, 600), words, cfg))
    assert {m for m, _ in slices} == {0, 1, 2}


def test_one_exchange_brings_sentences_to_their_models(sent):
    d = Division("epoch_sample", 25.0, 600, 2)
    plan = train_submodels(sent, d, vocab.global_vocab(sent, 100), SkipGramConfig(dim=2, epochs=2))._jdf.queryExecution().sparkPlan()
    text = train_submodels(sent, d, vocab.global_vocab(sent, 100), SkipGramConfig(dim=2, epochs=2))._jdf.queryExecution().executedPlan().toString()
    assert text.count("Exchange") == 1 and "Join" not in text and plan is not None


def test_rounds_and_central(sent):
    words = vocab.global_vocab(sent, 100)
    cfg = SkipGramConfig(dim=8, window=3, epochs=2)
    d = Division("epoch_sample", 50.0, 600, 2)
    rounds = vectors(train_submodels(sent, d, words, cfg, epoch_plan="rounds"))
    assert len(rounds) == 20
    once = vectors(train_submodels(sent, d, words, SkipGramConfig(dim=8, window=3, epochs=1), epoch_plan="rounds"))
    assert any(not np.allclose(once[k], rounds[k]) for k in once)
    central = vectors(train_central(sent, words, cfg))
    assert len(central) == 10


@pytest.mark.parametrize("name", ["sequential", "fixed_sample", "poisson_sample"])
def test_models_with_words_of_their_own(sent, name):
    d = Division(name, 25.0, 600, 1, hash_fn="xxhash64")
    route = d.route(sent, ("tokens",))
    counts = {(r["model"], r["word"]): r["cnt"] for r in vocab.submodel_counts(route).collect()}
    least = sorted(counts.values())[len(counts) // 3]
    words = vocab.vocabulary_for(d, sent, more_than=least)
    got = train_submodels(sent, d, words, SkipGramConfig(dim=4, window=2, epochs=2)).collect()
    assert {(r["model"], r["word"]): r["cnt"] for r in got} == {k: 2 * c for k, c in counts.items() if c > least}


def test_blocks_do_not_depend_on_batches(sent):
    words, counts = vocabulary_of(vocab.global_vocab(sent, 100))
    rows = deliver(Division("epoch_sample", 50.0, 600).route(encode(sent, words), ("ids",)), 1, 1).where("model = 0").toArrow()
    out = []
    for size in (7, 1000):
        task = _Task(SkipGramConfig(dim=4, window=2, epochs=1), 0, words, counts)
        out.append([m.words for _, m, _ in task.models(iter(rows.combine_chunks().to_batches(max_chunksize=size)), True)][0])
    assert np.allclose(*out)


def test_unseen_words_are_not_in_a_model(sent):
    words = vocab.global_vocab(sent, 100)
    got = vectors(train_submodels(sent.where("sent_id % 2 = 0"), Division("sequential", 100.0, 600), words, SkipGramConfig(dim=4, window=2, epochs=1)))
    assert {w[0] for _, w in got} == {"a"}


def test_no_words_and_no_sentences(sent):
    cfg = SkipGramConfig(dim=4, window=2, epochs=1)
    assert train_submodels(sent, Division("epoch_sample", 50.0, 600), vocab.global_vocab(sent.where("false"), 10), cfg).count() == 0
    assert train_submodels(sent.where("false"), Division("epoch_sample", 50.0, 1), vocab.global_vocab(sent, 10), cfg).count() == 0
    d = Division("sequential", 50.0, 600)
    assert train_submodels(sent, d, vocab.vocabulary_for(d, sent, more_than=1e9), cfg).count() == 0


def test_rows_that_come_again_get_all_their_gradients():
    rng = np.random.default_rng(4)
    m = _Matrix(rng.standard_normal((12, 3)).astype(np.float32))
    rows, grads, weight = rng.integers(0, 9, 40), rng.standard_normal((40, 3)).astype(np.float32), rng.integers(0, 4, 40).astype(np.float32)
    want = m.vectors.astype(float)
    for r in set(rows.tolist()):
        want[r] += 0.1 * grads[rows == r].sum(0) / np.sqrt(max(1, weight[rows == r].sum()))
    m.scatter(rows, m.vectors.take(rows, 0), grads.copy(), weight, 0.1)
    assert np.allclose(m.vectors, want, atol=1e-5) and not m.pairs.any()


@pytest.mark.parametrize("n, window", [(1, 2), (31, 4), (32, 4), (33, 4), (100, 20)])
def test_runs_of_any_length_and_width(n, window):
    rng = np.random.default_rng(5)
    m = SkipGram(np.ones(30), SkipGramConfig(dim=5, negatives=2), 1)
    m.words, m.contexts = (rng.standard_normal((30, 5)).astype(np.float32) for _ in range(2))
    ids, sent = rng.integers(0, 30, n), np.sort(rng.integers(0, 3, n))
    near, on, neg = contexts_of(ids, sent, window), windows_of(sent, window), rng.integers(0, 30, (n, 2))
    padded = np.pad(ids, on.shape[1] // 2)
    gx, gy, gz, v = m.run_gradients(ids, padded, on, neg)
    hx, hy, hz, u = m.gradients(ids, near, neg)
    want, got = (np.zeros((30, 5)) for _ in range(2))
    np.add.at(want, near[near >= 0], hy[near >= 0])
    np.add.at(got, padded, gy)
    assert np.allclose(gx, hx, atol=1e-3) and np.allclose(gz, hz, atol=1e-3) and np.allclose(got, want, atol=1e-3) and abs(u - v) < 1e-3 * max(1, abs(u))


def test_language_classes_are_worked_out_once(spark, sf, monkeypatch):
    from divmerge import queries

    given = []
    monkeypatch.setattr(queries, "train_central", lambda s, *_: s.sparkSession.createDataFrame([], "word string, vec array<float>"))
    monkeypatch.setattr(queries, "clusters", lambda cat, emb, k: given.append(cat) or cat)
    assert queries.language_clusters(spark, sf).count() > 1000
    assert "Aggregate" not in given[0]._jdf.queryExecution().optimizedPlan().toString()
