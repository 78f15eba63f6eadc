"""Divergences counted in packed runs, against the plain operators; and what they leave on disk."""

import hashlib

import numpy as np
from pyspark.sql import functions as F

from divmerge import session
from divmerge.functions.draws import md5_draws
from divmerge.operators import measures, tally
from divmerge.plans import workloads as w


def test_draws_in_arrays_are_those_of_md5():
    ids, prefixes = np.array([0, 9, 10, 99, 100, 12_345, 999_999, 1_000_000, 10**10]), ["1:epoch:0:3:", "1:fixed:99:"]
    got = {(k, int(i)): int(x) for k, run, u in md5_draws(prefixes, ids) for i, x in zip(ids[run], u)}
    assert got == {(k, int(i)): int(hashlib.md5(f"{p}{i}".encode()).hexdigest()[:15], 16) for k, p in enumerate(prefixes) for i in ids}


def _plain(sent, rate, order):
    total = sent.count()
    routes = w.union([w.division_of(sent, d, rate, n_sentences=total).route(sent, ("tokens",)).select(F.lit(d).alias("division"), "model", "mult", "tokens") for d in w.DIVISIONS])
    return {(r["division"], r["model"]): r["kl"] for r in measures.kl_divergence(routes, sent, order, ("division", "model")).collect()}


def test_packed_divergences_are_the_plain_ones(spark, sf, monkeypatch):
    sent = w.corpus(spark, sf)
    for name, small in (("MAX_ENTRIES", 20_000), ("MAX_HITS", 1_500), ("DRAWS", 700), ("SENTENCES", 300)):  # many works, ranges of sentences, pieces and parts
        monkeypatch.setattr(tally, name, small)
    rates = (10.0, 33.0)
    for order in (1, 2):
        got = {(r["rate"], r["division"], r["model"]): r["kl"] for r in tally.divergences(sent, w.DIVISIONS, rates, order).collect()}
        want = {(rate, *k): x for rate in rates for k, x in _plain(sent, rate, order).items()}
        assert got.keys() == want.keys() and all(abs(got[k] - x) < 1e-9 for k, x in want.items())


def test_a_pair_travels_as_few_bytes(spark, sf):
    sent = w.corpus(spark, sf)
    slots = tally.Slots(w.DIVISIONS, (10.0,), sent.count(), 1)
    rows = sent.select("sent_id", "tokens").coalesce(1).mapInArrow(tally._count(slots, 1 + len(slots.rows), 2, 4, 0, None), "part int, counts binary")
    size, pairs = rows.agg(F.sum(F.octet_length("counts"))).first()[0], sent.agg(F.sum(F.size("tokens") - 1)).first()[0]
    assert 0 < size < 14 * pairs  # two words and a sub-corpus were some 30 bytes, three times


def test_tables_that_only_led_to_a_kept_one_are_deleted(spark, tmp_path):
    spark.range(3).write.parquet(f"{tmp_path}/t")
    made = []

    def make():
        made.append(session.materialize(spark.range(5), "between"))
        return made[0].where("id > 1")

    assert session.once(spark, f"{tmp_path}/t", "kept", make).count() == 3
    assert not session._files(spark, made[0]._written_at)[0].exists(session._files(spark, made[0]._written_at)[1])


def test_hits_go_along_as_about_the_bits_of_their_slots():
    rng = np.random.default_rng(1)
    who, slot = np.sort(rng.integers(0, 50_000, 350_000)).astype(np.uint32), rng.integers(0, 200, 350_000).astype(np.uint16)
    blob = tally._steps(who, slot)
    got = tally._stepped(blob)
    assert (got[0] == who).all() and (got[1] == slot).all() and len(blob) < 2 * len(who)  # six bytes as arrays
