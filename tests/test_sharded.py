import numpy as np
import pytest
from pyspark.sql import functions as F

from divmerge.operators import baselines
from divmerge.operators.baselines import train_dim_sharded
from divmerge.operators.kernel import NoiseTable, SkipGramConfig, pairs_of, sigmoid
from divmerge.plans import workloads as w


def plainly(blocks, counts, shards, cfg, batch):
    """Shard after shard, row after row."""
    rng = np.random.default_rng(cfg.seed)
    noise, columns = NoiseTable(counts, cfg.noise_power), np.array_split(np.arange(cfg.dim), shards)
    x = [(rng.random((len(counts), len(c))) - 0.5) / cfg.dim for c in columns]
    y = [np.zeros((len(counts), len(c))) for c in columns]
    trips = 0
    for epoch in range(cfg.epochs):
        rate = max(cfg.least_rate, cfg.rate * (1 - epoch / cfg.epochs))
        for ids, sent in blocks():
            a, b = pairs_of(ids, sent, cfg.window)
            order = rng.permutation(len(a))
            for lo in range(0, len(a), batch):
                pick = order[lo : lo + batch]
                i, j = a[pick], np.concatenate([b[pick][:, None], noise.draw(rng, len(pick) * cfg.negatives).reshape(len(pick), -1)], 1)
                g = -sigmoid(sum(np.einsum("ij,ikj->ik", s[i], t[j]) for s, t in zip(x, y)))
                g[:, 0] += 1
                trips += 2
                for s, t in zip(x, y):
                    gs, gt = np.einsum("ik,ikj->ij", g, t[j]), g[:, :, None] * s[i][:, None, :]
                    np.add.at(s, i, rate * gs)
                    np.add.at(t, j.reshape(-1), rate * gt.reshape(-1, gt.shape[-1]))
    return np.concatenate(x, 1), trips


@pytest.mark.parametrize("dim, shards", [(16, 4), (7, 3)])
def test_sharded_trainer_is_the_plain_one(dim, shards, monkeypatch):
    rng = np.random.default_rng(2)
    parts = [(rng.integers(0, 40, n), np.sort(rng.integers(0, 1 + n // 5, n))) for n in (300, 1, 170)]
    cfg, counts = SkipGramConfig(dim=dim, window=3, negatives=2, epochs=2), np.arange(40, 0, -1.0)
    want, trips = plainly(lambda: iter(parts), counts, shards, cfg, 64)
    drawn = []
    monkeypatch.setattr(baselines, "NoiseTable", type("Counted", (NoiseTable,), {"draw": lambda self, rng, n: drawn.append(n) or NoiseTable.draw(self, rng, n)}))
    got = train_dim_sharded(lambda: iter(parts), counts, shards, cfg, 64)
    assert np.allclose(got.words, want, atol=1e-4) and got.round_trips == trips and got.scalars_sent == 2 * shards * 3 * got.pairs
    assert len(drawn) <= 2 * len(parts)  # once a block, whatever the number of minibatches


def test_packed_blocks_are_the_sentences(spark, monkeypatch):
    sent = spark.range(500).select(F.col("id").alias("sent_id"), F.transform(F.sequence(F.lit(0), F.col("id") % 7), lambda k: F.concat(F.lit("w"), (F.col("id") * k % 11).cast("string"))).alias("tokens"))
    seen = []
    monkeypatch.setattr(w, "corpus", lambda *_: sent)
    monkeypatch.setattr(w, "train_dim_sharded", lambda blocks, counts, shards: seen.extend(blocks()) or baselines.ShardedResult(np.zeros(0), 0, 0, 0.0, 0))
    w.sharded_baseline(spark, "", block=70)
    words = [r["word"] for r in w.vocab.global_vocab(sent).orderBy("word_id").collect()]
    assert [int(s.max()) + 1 for _, s in seen] == [70] * 7 + [10]
    assert [words[i] for ids, _ in seen for i in ids] == [t for r in sent.orderBy("sent_id").collect() for t in r["tokens"]]
