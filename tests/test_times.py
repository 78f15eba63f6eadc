from divmerge.operators.kernel import SkipGramConfig
from divmerge.plans import workloads as w


def test_the_list_of_words_is_made_once(spark, sf, monkeypatch):
    made, make = [], w.vocab.global_vocab
    monkeypatch.setattr(w.vocab, "global_vocab", lambda *a: made.append(1) or make(*a))
    monkeypatch.setattr(w, "train_mllib", lambda sent, *_: sent.limit(1))
    got = {r["method"]: r for r in w.training_times(spark, sf, (50.0, 33.0), SkipGramConfig(dim=4, window=2, epochs=1)).collect()}
    assert len(made) == 1 and set(got) == {"epoch_sample 50%", "epoch_sample 33%", "central", "mllib 10", "mllib 100"}
    assert got["central"]["speed_up"] == 1 and got["epoch_sample 33%"]["models"] == 3 and all(r["train_s"] > 0 for r in got.values())
