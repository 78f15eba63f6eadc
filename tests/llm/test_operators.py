"""Each operator against a brute-force version, on small fixtures with nulls, empty and long texts, ties and repeated rows."""

import hashlib
import re
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from divmerge.llm import langid, media, minhash, mixing, quality, segment, substring, textnum, tokenids, toxicity, urls
from divmerge.llm.queries import ORACLE_SQL, QUERIES, tokenizer_file
from oracle import rows_of, twin_rows

WORD = re.compile(r"[^\x20\x09-\x0D]+")
ODD = [None, "", " \n\t ", "one", "é ß\u2003x", "a " * 3000, "\U0001f600 \x00 <|endoftext|>", "the cat sat\nthe cat sat\n\nthe cat", "x" * 5000]


def passage(seed, n=60):
    rng = np.random.default_rng(seed)
    return " ".join(f"w{rng.integers(10**6)}" for _ in range(n))


@pytest.fixture(scope="module")
def odd(spark):
    """Odd texts, repeated rows, and columns whose names clash with the operators' own."""
    rows = [(i, t, "en" if i % 2 else None, f"src{i % 3}", 5, "x") for i, t in enumerate(ODD)] + [(3, "one", None, None, 1, "y"), (None, "no id", "en", "src0", 1, "z")]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, unit int, part string").cache()


@pytest.fixture(scope="module")
def none(odd):
    return odd.where("false")


# --- 10 substring dedup


def brute_substrings(rows, window):
    seen, out = set(), {}
    for key, text in sorted(rows, key=lambda r: r[0]):
        w = WORD.findall(text or "")
        gone = set()
        for s in range(len(w) - window + 1):
            k = tuple(w[s : s + window])
            if k in seen:
                gone.update(range(s, s + window))
            seen.add(k)
        kept = [x for i, x in enumerate(w) if i not in gone]
        out[key] = (len(w), len(gone), hashlib.sha256(" ".join(kept).encode()).hexdigest())
    return out


@pytest.mark.parametrize("window", [20, 7, 3])
def test_substrings(spark, window):
    a, b = passage(1, 55), passage(2, 25)
    texts = [a, f"x {a} y", f"{b} {b}", f"{a[:100]} {b} z", None, "", a, "la " * 50, f"{b}\n{a}"] + ODD[1:]
    rows = list(enumerate(texts))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r["doc_id"]: (r["n_words"], r["n_removed"], r["kept_sha256"]) for r in substring.remove_repeats(df, window, unit_bytes=200).collect()}
    assert got == brute_substrings(rows, window)


def test_substrings_of_rows_that_share_an_id(spark):
    """Rows with one id, or none, are ordered by a hash of their text; the ids of all rows together do not matter to what is cut."""
    a, b = passage(11, 30), passage(12, 30)
    rows = [(None, a), (None, f"{a} x"), (None, a), (7, b), (7, f"y {b}"), (7, b), (9, f"{a} {b}")]
    df = spark.createDataFrame([(i, t, 1, "z") for i, t in rows], "doc_id long, text string, __part int, hashes string").repartition(3)
    got = [(r["doc_id"], r["n_words"], r["n_removed"]) for r in substring.remove_repeats(df, 20, unit_bytes=100).collect()]
    assert len(got) == 7 and all(n == 60 for i, _, n in got if i == 9)
    for key, size in ((None, 91), (7, 91)):
        assert sum(w for i, w, _ in got if i == key) == size and sum(n for i, _, n in got if i == key) == 60
    assert substring.remove_repeats(df.where("false"), 20).count() == 0


def test_cover_finds_every_shift():
    for period, cover in substring.COVERS.items():
        assert {(a - b) % period for a in cover for b in cover} == set(range(period))


def test_cut_rows_keep_columns(spark, odd):
    a = passage(3, 30)
    df = spark.createDataFrame([(1, a, 7), (2, f"before\n{a} after", 8)], "doc_id long, text string, part int")
    got = {r["doc_id"]: (r["text"], r["part"]) for r in substring.remove_repeats(df, what="rows").collect()}
    assert got == {1: (a, 7), 2: ("before\nafter", 8)}
    out = substring.remove_repeats(odd, what="rows")
    assert out.columns == odd.columns and out.count() == odd.count()


# --- 2 near duplicates


def jp(x, y):
    keys = set(x) | set(y)
    return sum(1 / sum(max(x[k] / x[d], y[k] / y[d]) for k in keys) for d in set(x) & set(y))


def shingle_counts(text):
    w = WORD.findall(text or "")
    return Counter(tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))) if w else Counter()


def near_copy(text, k, seed):
    w = text.split()
    for i in np.random.default_rng(seed).choice(len(w), k, replace=False):
        w[i] = f"z{seed}_{i}"
    return " ".join(w)


def test_near_duplicates(spark):
    base = passage(5, 200)
    texts = [near_copy(base, k, s) for s, k in enumerate([0, 1, 2, 3, 4, 6, 9, 20, 1, 2, 5, 8])] + [base, base, passage(6, 80), "a b", "a b", "a  b\n", None, "", " "]
    texts += [("to be or not " * 30) + passage(7, 40), ("to be or not " * 31) + passage(7, 40)]
    sets = [shingle_counts(t) for t in texts]
    label = list(range(len(texts)))
    for i in range(len(texts)):
        for j in range(i):
            if sets[i] and sets[j] and jp(sets[i], sets[j]) >= 0.8:
                label = [label[j] if x == label[i] else x for x in label]
    want = {i: min(k for k, x in enumerate(label) if x == label[i]) for i in range(len(texts))}
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    assert {r["doc_id"]: r["class_id"] for r in minhash.near_duplicates(df, block=3).collect()} == want


def test_near_duplicates_of_odd_rows(spark, odd, none):
    base = passage(21, 100)
    rows = [(1, base), (1, passage(22, 50)), (2, passage(22, 50)), (3, near_copy(base, 2, 1)), (None, base), (None, None), (5, ""), (3, near_copy(base, 2, 1))]
    df = spark.createDataFrame([(i, t, "a", 1) for i, t in rows], "doc_id long, text string, bands string, rep_id int")
    got = sorted((r["doc_id"] or 0, r["class_id"] or 0) for r in minhash.near_duplicates(df).collect())
    assert got == [(0, 0), (0, 1), (1, 1), (1, 1), (2, 1), (3, 1), (3, 1), (5, 5)]  # each text of id 1 leads its own class
    kept = minhash.one_of_each(df)
    assert kept.columns == df.columns
    assert sorted((r["doc_id"] or 0, r["text"] or "") for r in kept.collect()) == sorted([(1, base), (1, passage(22, 50)), (0, ""), (5, "")])
    assert minhash.near_duplicates(none).count() == minhash.one_of_each(none).count() == 0
    assert minhash.near_duplicates(odd).count() == odd.count()


def test_one_of_equal_rows_stays(spark):
    text = passage(23, 40)
    df = spark.createDataFrame([(4, text)] * 5 + [(6, text), (None, text)] + [(None, passage(24, 30))] * 3, "doc_id long, text string")
    assert sorted((r["doc_id"] or 0) for r in minhash.one_of_each(df).collect()) == [0, 4]


def test_near_duplicates_lose_no_link_on_the_table(spark):
    """Every pair of the table at 0.8 or more is in one class, and every class hangs together by such pairs."""
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text")
    cls = {r["doc_id"]: r["class_id"] for r in minhash.near_duplicates(docs).collect()}
    rows = [(r["doc_id"], r["text"]) for r in docs.orderBy("doc_id").collect() if WORD.search(r["text"] or "")]
    doc, h, x = minhash._sets(pa.chunked_array([pa.array([t for _, t in rows])]), 5)
    at = np.searchsorted(doc, np.arange(len(rows) + 1))
    holders = {}
    for d, k in zip(doc.tolist(), h.tolist()):
        holders.setdefault(k, []).append(d)
    shared = Counter()
    for own in holders.values():
        shared.update((a, b) for i, a in enumerate(own) for b in own[i + 1 :])
    linked, parent = 0, list(range(len(rows)))

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for (a, b), n in shared.items():
        if n >= 0.5 * min(at[a + 1] - at[a], at[b + 1] - at[b]):
            sim = minhash.probability_jaccard(h[at[a] : at[a + 1]], x[at[a] : at[a + 1]], h[at[b] : at[b + 1]], x[at[b] : at[b + 1]])
            if sim >= 0.8:
                linked += 1
                assert cls[rows[a][0]] == cls[rows[b][0]]
                parent[find(a)] = find(b)
    assert linked > 50
    groups = {}
    for i, (k, _) in enumerate(rows):
        groups.setdefault(cls[k], set()).add(find(i))
    assert all(len(g) == 1 for g in groups.values())


def test_signature_agreement_is_probability_jaccard():
    rng = np.random.default_rng(0)
    h = rng.integers(0, 2**63, 60).astype(np.uint64)
    x, y = rng.integers(1, 5, 50), rng.integers(1, 5, 50)
    doc = np.repeat([0, 1], 50)
    sig = minhash.signatures(doc, np.concatenate([h[:50], h[10:]]), np.concatenate([x, y]), 2, 4000)
    a, b = dict(zip(h[:50].tolist(), x)), dict(zip(h[10:].tolist(), y))
    want = jp(Counter(a), Counter(b))
    assert abs((sig[0] == sig[1]).mean() - want) < 0.035
    o, p = np.argsort(h[:50]), np.argsort(h[10:])
    assert abs(minhash.probability_jaccard(h[:50][o], x[o], h[10:][p], y[p]) - want) < 1e-9


def test_components(spark):
    edges = [(i, i + 1) for i in range(20)] + [(100, 50), (50, 77)]
    got = {r["node"]: r["component"] for r in minhash.connected_components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert all(got[i] == 0 for i in range(21)) and got[100] == got[77] == 50


# --- 3 media


def test_png_filters_and_damage():
    rng = np.random.default_rng(0)
    for c in (1, 2, 3, 4):
        x = rng.integers(0, 256, (9, 7, c), dtype=np.uint8)
        rows = x.reshape(9, -1)
        for kinds in (*(np.full(9, k) for k in range(5)), rng.integers(0, 5, 9)):
            assert (media.unfilter_rows(media.filter_rows(rows, c, kinds), c, kinds) == rows).all()
        data = media.encode_png(x)
        assert (media.decode_png(data) == x).all()
        for at in (0, 20, 30, len(data) - 20, len(data) - 2):
            with pytest.raises(media.PngError):
                media.decode_png(data[:at] + bytes([data[at] ^ 1]) + data[at + 1 :])
        with pytest.raises(media.PngError):
            media.decode_png(data[:-5])


def test_written_rows_use_the_filters(spark):
    import struct

    text = passage(1, 400)
    data = bytes(media.write_media(spark.createDataFrame([(1, text)], "doc_id long, text string")).first()["media"])
    at = data.index(b"IDAT") + 4
    body = zlib.decompress(data[at : at + struct.unpack(">I", data[at - 8 : at - 4])[0]])
    kinds = set(body[:: media.ROW_BYTES + 1])
    assert kinds <= {0, 1, 2} and kinds & {1, 2}


def brute_hash(x):
    """The hash by its definition, sum by sum."""
    h, w, c = x.shape
    luma = [[float(0.299 * p[0] + 0.587 * p[1] + 0.114 * p[2]) if c >= 3 else float(p[0]) for p in row] for row in x.tolist()]

    def part(values, k):  # mean over the k-th of 32 equal stretches
        a, b = k * len(values) / 32, (k + 1) * len(values) / 32
        return sum(v * max(0.0, min(b, i + 1) - max(a, i)) for i, v in enumerate(values)) / (b - a)

    small = [[part(row, k) for k in range(32)] for row in luma]
    small = list(zip(*[[part(col, k) for k in range(32)] for col in zip(*small)]))
    low = [[sum(small[i][j] * np.cos(np.pi * u * (2 * i + 1) / 64) * np.cos(np.pi * v * (2 * j + 1) / 64) for i in range(32) for j in range(32)) for v in range(8)] for u in range(8)]
    flat = [v for row in low for v in row]
    return flat, float(np.median(flat[1:]))


def test_cosine_hash_by_definition():
    rng = np.random.default_rng(3)
    for shape in ((5, 64, 3), (70, 33, 1), (32, 64, 4)):
        x = rng.integers(0, 256, shape, dtype=np.uint8)
        flat, middle = brute_hash(x)
        bits = np.unpackbits(np.frombuffer(media.cosine_hash(x), np.uint8))
        assert all(b == (v > middle) for b, v in zip(bits, flat) if abs(v - middle) > 1e-2)


def test_media_of_odd_texts(spark, odd, none):
    rows = media.read_media(media.write_media(odd)).collect()
    texts = sorted((t or "").encode() for t in [r["text"] for r in odd.collect()])
    want = sorted((len(t), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-16:])) for t in texts for p in [t.ljust(max(1, -(-len(t) // 192)) * 192)])
    assert sorted((r["n_bytes"], r["payload_sha256"], r["tail_crc32"]) for r in rows) == want
    assert media.read_media(media.write_media(none)).count() == 0
    bad = spark.createDataFrame([(1, b"no", "keep"), (2, None, "keep")], "doc_id long, media binary, feature string")
    assert all(r["error"] and r["payload_bytes"] is None for r in media.read_media(bad).collect())


def test_cosine_hash_bears_noise():
    img = np.kron(np.random.default_rng(4).integers(20, 230, (8, 8)), np.ones((12, 8), int))[:, :, None].repeat(3, 2).astype(np.uint8)
    noisy = np.clip(img.astype(int) + np.random.default_rng(0).integers(-4, 5, img.shape), 0, 255).astype(np.uint8)
    bits = lambda z: np.unpackbits(np.frombuffer(media.cosine_hash(z), np.uint8))
    assert (bits(img) != bits(noisy)).sum() <= 6 < (bits(img) != bits(img[::-1])).sum()


# --- 4 quality


def brute_base(text):
    w = WORD.findall(text or "")
    seen, dup = set(), 0
    for line in (text or "").split("\n"):
        if WORD.search(line):
            dup += line in seen
            seen.add(line)
    grams = [tuple(w[i : i + 8]) for i in range(len(w) - 7)]
    n, cov = Counter(grams), set()
    for i, g in enumerate(grams):
        if n[g] > 1:
            cov.update(range(i, i + 8))
    return [len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", text or "")), dup, len(cov)]


def test_statistics():
    texts = ODD + ["a b c d e f g h i\n" * 3 + "\n\n#x|", "\n", "x\n\nx\n", passage(1, 30)]
    got = np.concatenate([quality.statistics(c)[0] for c in textnum.chunks(pa.array(texts), 64)])
    assert got.tolist() == [brute_base(t) for t in texts]


def test_trees_are_monotonic_and_learn():
    rng = np.random.default_rng(0)
    x = rng.random((1500, 3))
    y = ((x[:, 0] < 0.5) ^ (rng.random(1500) < 0.1)).astype(float)
    m = quality.fit_trees(x, y, np.array([-1, 0, 0]), n_trees=40)
    assert ((m.score(x) > 0.5) == (x[:, 0] < 0.5)).mean() > 0.95
    grid = np.repeat(rng.random((20, 3)), 50, 0)
    grid[:, 0] = np.tile(np.linspace(0, 1, 50), 20)
    assert (np.diff(m.score(grid).reshape(20, 50), axis=1) <= 1e-12).all()
    assert (quality.fit_trees(x, np.ones(1500), np.zeros(3)).score(x) > 0.99).all()


def test_scores_are_those_of_a_walk_down_each_tree():
    rng = np.random.default_rng(1)
    x = rng.random((400, 4))
    y = ((x[:, 0] + x[:, 1] * x[:, 2] + 0.2 * rng.random(400)) > 0.8).astype(float)
    m = quality.fit_trees(x, y, np.zeros(4), n_trees=12, depth=3)
    for row, score in zip(x[:80], m.score(x)[:80]):
        total = m.base
        for at in m.roots:
            while m.left[at] != at:
                at = m.left[at] if row[m.feature[at]] <= m.threshold[at] else m.right[at]
            total += m.value[at]
        assert abs(1 / (1 + np.exp(-total)) - score) < 1e-12


def test_the_first_split_is_the_best_of_all():
    rng = np.random.default_rng(2)
    x = np.round(rng.random((60, 3)), 1)
    y = (x[:, 1] > 0.45).astype(float)
    y[:6] = 1 - y[:6]
    m = quality.fit_trees(x, y, np.zeros(3), n_trees=1, depth=1, least_rows=1)
    p = y.mean()
    g, h = p - y, p * (1 - p)
    best = max((sum(g[s].sum() ** 2 / (h * s.sum() + 1) for s in (x[:, j] <= t, x[:, j] > t)), -j, t) for j in range(3) for t in np.unique(x[:, j])[:-1])
    root = m.roots[0]
    assert (m.feature[root], m.threshold[root]) == (-best[1], best[2])
    left = x[:, m.feature[root]] <= m.threshold[root]
    assert abs(m.value[m.left[root]] - 0.15 * -g[left].sum() / (h * left.sum() + 1)) < 1e-12


def test_judge_odd_texts(spark, odd, none, sf):
    labels = spark.createDataFrame([(1, None), (None, 1)], "doc_id long, quality int")
    m = quality.train(odd, labels)
    got = quality.judge(odd, m).collect()
    assert len(got) == odd.count() and all(r["kept"] == (not r["base_failed"]) for r in got)
    assert quality.judge(none, m).count() == 0 and quality.keep(odd, m).columns == odd.columns


# --- 5 language


def test_languages_held_out(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text", "lang")
    m = langid.train(docs.where("doc_id % 5 <> 0"))
    got = langid.predict(docs.where("doc_id % 5 = 0"), m).join(docs.select("doc_id", "lang"), "doc_id").collect()
    assert np.mean([r["lang"] == r["lang_pred"] for r in got]) > 0.98 and all(0 <= r["score"] <= 1 for r in got)


def brute_kneser_ney(words, order, discount):
    """Interpolated Kneser-Ney by its definition, on raw counts: a function (history, letter) -> probability."""
    counts = [Counter() for _ in range(order + 1)]
    for word in words:
        t = f" {word} "
        for i in range(1, len(t)):
            for n in range(1, min(order, i + 1) + 1):
                counts[n][t[i - n + 1 : i + 1]] += 1
    alphabet = len(counts[1])

    def use(gram):
        n = len(gram)
        if n == order or n > 1 and gram[0] == " ":  # nothing can stand before a word's start
            return counts[n][gram]
        return sum(1 for g in counts[n + 1] if g[1:] == gram)

    def prob(history, letter):
        n = len(history) + 1
        below = prob(history[1:], letter) if n > 1 else 1 / alphabet
        grams = [g for g in counts[n] if g[:-1] == history]
        total = sum(map(use, grams))
        if not total:
            return below
        kinds = sum(1 for g in grams if use(g) > 0)
        return max(use(history + letter) - discount, 0) / total + discount * kinds / total * below

    return prob


def test_kneser_ney_by_definition(spark):
    texts = ["the cat sat on the mat", "a cat and the hat that sat", "then the cat ate"]
    m = langid.train(spark.createDataFrame([(i, t, "en") for i, t in enumerate(texts)], "doc_id long, text string, lang string"), order=3, calibration_rows=0)
    prob = brute_kneser_ney([w for t in texts for w in t.split()], 3, langid.DISCOUNT)
    for word in ("the", "cat", "mate", "zat", "ttt", "a"):
        total, _, _ = m.position_scores([word])
        t = f" {word} "
        want = [prob(t[max(0, i - 2) : i], t[i]) for i in range(1, len(t))]
        assert np.allclose(np.exp(total[:, 0]), want, rtol=1e-4), word


def test_kneser_ney_sums_to_one():
    order = 3
    words = ["ab", "aab", "b", "abab", "ba", "aaa"]
    rows = Counter()
    for x in words:
        t = f" {x} "
        for i in range(1, len(t)):
            for n in range(1, min(order, i + 1) + 1):
                rows[n, t[i - n + 1 : i + 1]] += 1
    keys = list(rows)
    m = langid.kneser_ney(np.array(["q"] * len(keys)), np.array([k[0] for k in keys]), np.array([k[1] for k in keys], object), np.array([rows[k] for k in keys]), ["q"], order, 0.75)
    for history in ("", "a", "ab", "bb", "aba"):
        total = 0.0
        for c in "ab ":  # a letter, or the end of the word
            if c == " " and not history:
                continue
            total += np.exp(m.position_scores([(history + c).strip()])[0][len(history), 0])
        assert history == "" and total <= 1 + 1e-4 or abs(total - 1) < 1e-4


def test_languages_keep_every_ngram_and_language(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text", "lang")
    whole, few = langid.train(docs), langid.train(docs, max_ngrams=500)
    assert whole.languages == few.languages and len(few.groups) == len(few.languages) > 1
    a, b = ({r["doc_id"]: r for r in langid.predict(docs, m).collect()} for m in (whole, few))
    assert a.keys() == b.keys()
    for k, r in a.items():
        assert r["lang_pred"] == b[k]["lang_pred"] and abs(r["score"] - b[k]["score"]) < 1e-6 and r["rejected"] == b[k]["rejected"]
        assert (r["cross_entropy"] is None) == (b[k]["cross_entropy"] is None) and abs((r["cross_entropy"] or 0) - (b[k]["cross_entropy"] or 0)) < 1e-6


def test_more_languages_than_two_hundred(spark):
    rows = [(i, " ".join(chr(0x4E00 + 20 * i + j) * 3 for j in range(5)), f"x{i:03}") for i in range(230)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    m = langid.train(docs)
    got = {r["doc_id"]: r["lang_pred"] for r in langid.predict(docs, m).collect()}
    assert len(m.languages) == 230 and all(got[i] == x for i, _, x in rows)


def test_undetermined(spark, odd, none):
    m = langid.train(odd)
    got = {r["doc_id"]: r["lang_pred"] for r in langid.predict(odd, m).collect()}
    assert got[0] == got[1] == got[2] == "und" and got[3] in m.languages
    assert langid.predict(none, m).count() == 0
    assert {r["lang_pred"] for r in langid.predict(odd, langid.train(none)).collect()} == {"und"}


def test_texts_are_scored_once_for_calibration_and_prediction(spark, monkeypatch):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text", "lang")
    docs = docs.unionByName(spark.createDataFrame([(-1, None, "en"), (-2, "12 ,", "en"), (-3, "words of no label", None)], docs.schema))
    training, passes = F.col("doc_id") % 5 != 0, []
    scored = langid._scored
    monkeypatch.setattr(langid, "_scored", lambda model, rows: passes.append(rows.count()) or scored(model, rows))
    for size in (langid.MAX_NGRAMS, 500):  # one group, and a group for each language
        want = {r["doc_id"]: r for r in langid.predict(docs, langid.train(docs.where(training), max_ngrams=size)).collect()}
        passes.clear()
        got = {r["doc_id"]: r for r in langid.train_and_predict(docs, training, max_ngrams=size).collect()}
        assert passes == [docs.count()] and got.keys() == want.keys()
        for k, r in want.items():
            assert (r["lang_pred"], r["rejected"]) == (got[k]["lang_pred"], got[k]["rejected"]) and abs(r["score"] - got[k]["score"]) < 1e-9
            assert (r["cross_entropy"] is None) == (got[k]["cross_entropy"] is None) and abs((r["cross_entropy"] or 0) - (got[k]["cross_entropy"] or 0)) < 1e-9


# --- 7 toxicity


def test_pairs_that_weights_cannot_learn():
    rng = np.random.default_rng(2)
    a, b = rng.random(4000) < 0.5, rng.random(4000) < 0.5
    y = (a & b).astype(float) + 0
    y = np.where(a ^ b, 0.0, np.where(a & b, 1.0, rng.random(4000) < 0.5))
    rows = [np.flatnonzero([p, q, True]) for p, q in zip(a, b)]
    doc, term = np.repeat(np.arange(4000), [len(r) for r in rows]), np.concatenate(rows)
    bias, w, v = toxicity.fit(y, doc, term, 3, epochs=30, l2=0.0)
    fm = toxicity.FactorizationMachine(np.arange(3), bias, w, v)
    score = lambda t: float(fm.raw(np.zeros(len(t), int), np.array(t), 1)[0])
    both, one, other = score([0, 1, 2]), score([0, 2]), score([1, 2])
    assert both > 0 > one and other < 0
    assert abs(fm.raw(np.zeros(2, int), np.array([0, 1]), 1)[0] - (bias + w[0] + w[1] + v[0] @ v[1])) < 1e-9


def brute_machine(m, text):
    """The score pair by pair, from terms found by a regular expression."""
    low = "".join(c.lower() if c.isascii() or "\u00c0" <= c <= "\u00de" else c for c in text).encode()
    found = set()
    for word in re.findall(rb"[0-9a-z\x80-\xff]+", low):
        for part, factor in [(word, 1)] + [(word[:n], 2 * n + 1) for n in toxicity.STEMS if len(word) > n]:
            prefix = textnum.prefix_hash(np.frombuffer(part, np.uint8))
            h = int(textnum.span_hash(prefix, np.array([0]), np.array([len(part)]))[0]) * factor % (1 << 64)
            found.add(int(m.row[h >> 44]))
    on = sorted(found - {-1})
    raw = m.bias + sum(m.w[i] for i in on) + sum(float(m.v[i] @ m.v[j]) for a, i in enumerate(on) for j in on[a + 1 :])
    return 1 / (1 + np.exp(-(m.scale * raw + m.shift)))


def test_scores_of_whole_texts_pair_by_pair(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text")
    m = toxicity.train(docs, spark.read.parquet("/root/testdata/sf0.01/labels.parquet"))
    rows = docs.where("doc_id % 7 = 0").collect()
    got = {r["doc_id"]: r["score"] for r in toxicity.score(docs, m).collect()}
    assert len(m.w) > 5
    for r in rows:
        assert abs(got[r["doc_id"]] - brute_machine(m, r["text"] or "")) < 1e-9


def test_toxic_terms_are_found(spark, odd, none):
    rng = np.random.default_rng(0)
    rows = [(i, passage(i, 40) + (" vileword" if i % 5 == 0 else "")) for i in range(400)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(i % 5 == 0)) for i in range(300)], "doc_id long, toxic int")
    m = toxicity.train(docs, labels)
    got = {r["doc_id"]: r["predicted"] for r in toxicity.score(docs.where("doc_id >= 300"), m).collect()}
    assert got == {i: int(i % 5 == 0) for i in range(300, 400)} and rng is not None
    assert all(0 <= r["score"] <= 1 for r in toxicity.score(odd, m).collect()) and toxicity.score(none, m).count() == 0
    assert {r["score"] for r in toxicity.score(odd, toxicity.train(docs, labels.where("false"))).collect()} == {0.0}


# --- 8 URLs


def test_urls_against_brute_force(spark):
    rules = [("net", "/", "block"), ("example.net", "/en/", "allow"), ("COM", "", "block"), ("a.com", "/x", "allow"), ("a.com", "/x", "block"), ("b.a.com", "/x/y", "allow")]
    pages = [None, "", "no scheme", "http://", "http://NET/", "http://net", "ftp://q.example.net/en/1?x#y", "http://q.example.net/e", "http://b.a.com/x/yz/../", "http://a.com/xylo", "http://ba.com/x", "x://a.com?p=/x", "http://example.net/en/1", "http://example.net/en/1"]
    got = {(r["page_id"], r["host"], r["path"], r["rule"], r["verdict"]) for r in urls.filter_urls(spark.createDataFrame(list(enumerate(pages)), "page_id long, url string"), spark.createDataFrame(rules, "host string, path string, action string")).collect()}
    want = set()
    for i, u in enumerate(pages):
        rest = u.split("://", 1)[1] if u and "://" in u else ""
        host = re.match(r"[^/?#]*", rest)[0].lower()
        path = re.match(r"[^/?#]*([^?#]*)", rest)[1]
        fit = [(len(h + p), len(h), a == "block", h.lower() + p, a) for h, p, a in rules if (host == h.lower() or host.endswith("." + h.lower())) and path.startswith(p)] if rest else []
        best = max(fit, default=None)
        want.add((i, host, path, best and best[3], best[4] if best else "allow"))
    assert got == want
    assert urls.filter_urls(spark.createDataFrame([(1, "http://a")], "page_id long, url string"), spark.createDataFrame([], "host string, path string, action string")).first()["verdict"] == "allow"


def test_urls_of_no_pages_and_of_other_columns(spark):
    rules = spark.createDataFrame([("net", "/", "block")], "host string, path string, action string")
    pages = spark.createDataFrame([(1, "http://a.net/x", "h", "r", 5), (1, "http://a.net/x", "h", "r", 5), (None, "http://b.org", "h", "r", 5), (2, None, "h", "r", 5)], "page_id long, url string, host string, rule string, n int")
    got = sorted(((r["page_id"] or 0), r["host"], r["rule"], r["verdict"]) for r in urls.filter_urls(pages, rules).collect())
    assert got == [(0, "b.org", None, "allow"), (1, "a.net", "net/", "block"), (1, "a.net", "net/", "block"), (2, "", None, "allow")]
    assert urls.filter_urls(pages.where("false"), rules).count() == 0


def test_pages_of_a_popular_url(spark, monkeypatch):
    from divmerge.llm import joins

    monkeypatch.setattr(joins, "HEAVY_ROWS", 10)
    rules = spark.createDataFrame([("net", "/", "block")], "host string, path string, action string")
    pages = spark.range(200).selectExpr("id as page_id", "case when id < 150 then 'http://hot.net/' else concat('http://', id % 20, '.net/') end as url")
    got = urls.filter_urls(pages, rules).collect()
    assert len(got) == 200 and {r["verdict"] for r in got} == {"block"}


# --- 6 mixing


def test_budgets_by_hand(spark):
    leaves = spark.createDataFrame([("a", "en", "s1", 100, 1), ("a", "en", "s2", 1000, 1), ("b", "en", "s1", 50, 1), ("b", "de", "s1", 1000, 1)], "domain string, lang string, source string, tokens long, docs long")
    got = {(r["domain"], r["lang"], r["source"]): r["budget"] for r in mixing.budgets(leaves, {"lang": {"en": 3}}, 1000, 1).collect()}
    # 500 to each domain; s1 is full at 100 and its sibling takes the rest; in b English is full at 50
    assert got == {("a", "en", "s1"): 100, ("a", "en", "s2"): 400, ("b", "en", "s1"): 50, ("b", "de", "s1"): 450}


def test_mixing_odd_rows(spark, odd, none):
    df = odd.selectExpr("*", "'d' as domain")
    got = mixing.mix(df, {}, share=0.5, max_epochs=1).collect()
    assert len(got) == df.count() and sum(r["repeats"] * r["n_tokens"] for r in got) <= 0.5 * sum(r["n_tokens"] for r in got)
    assert mixing.mix(none.selectExpr("*", "'d' as domain"), {}).count() == 0
    twice = mixing.mix(df, {}, share=2.0, max_epochs=2).collect()
    assert {r["repeats"] for r in twice if r["n_tokens"]} == {2}


# --- 9 token files


def test_segments():
    rng = np.random.default_rng(0)
    for n in (0, 1, 255, 256, 257, 5000):
        x = rng.integers(0, 50_000, n).astype(np.uint32)
        x[::50] = rng.integers(0, 2**32, len(x[::50]))
        sizes = np.array([n // 3, n - n // 3])
        s = tokenids.Segment(tokenids.encode_segment(np.array([1, 2]), sizes, x))
        assert (s.ids() == x).all() and (s.document(1) == x[n // 3 :]).all()
    with pytest.raises(ValueError):
        tokenids.Segment(tokenids.encode_segment(np.array([1]), np.array([3]), np.arange(3))[:-1])


def test_token_files(spark, odd, none):
    from tokenizers import Tokenizer

    path = tokenizer_file("word_bpe_49k.json")
    tok = Tokenizer.from_file(path)
    got = sorted((r["start"], r["doc_id"], r["n_tokens"], r["ids_crc32"]) for r in tokenids.token_files(odd, path).collect())
    rows = sorted(((r["doc_id"] if r["doc_id"] is not None else -1, r["text"] or "") for r in odd.select("doc_id", "text").collect()))
    start, want = 0, []
    for k, t in rows:
        ids = tok.encode(t, add_special_tokens=False).ids + [2]
        want.append((start, None if k < 0 else k, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())))
        start += len(ids)
    assert got == want
    assert tokenids.token_files(none, path).count() == 0


def test_a_tokenizer_that_joins_words(spark, odd):
    """Byte-level pieces hold the space before a word, so whole texts are encoded."""
    from tokenizers import Tokenizer

    path = tokenizer_file("byte_bpe_50k.json")
    tok = Tokenizer.from_file(path)
    assert not tokenids.WordIds(path).by_words and tokenids.WordIds(tokenizer_file("word_bpe_49k.json")).by_words
    rows = odd.where("doc_id is not null").select("doc_id", "text").collect()
    got = Counter((r["doc_id"], r["n_tokens"], r["ids_crc32"]) for r in tokenids.token_files(odd.where("doc_id is not null"), path).collect())
    want = Counter()
    for r in rows:
        ids = tok.encode(r["text"] or "", add_special_tokens=False).ids + [2]
        want[r["doc_id"], len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())] += 1
    assert got == want


# --- 1 segmentation


@pytest.fixture(scope="module")
def sampler():
    return segment.Sampler(tokenizer_file("piece_bpe_32k.model"), k=4)


def test_sampled_segmentations(sampler):
    for text in ("", "a", "the and  x", " a\n\tb", "é漢字 \U0001f600 Ａ", "x" * 300):
        rows = next(sampler.batch([text], [5]))
        assert len({tuple(r[3]) for r in rows}) == len(rows) <= 4
        assert all(sampler.pieces.decode(r[3]) == text for r in rows)
        assert all(a[1] >= b[1] for a, b in zip(rows, rows[1:]))


def test_sampling_is_without_replacement_and_unbiased(sampler):
    n, first, seen, weight, logp = 8000, Counter(), Counter(), Counter(), {}
    for rows in sampler.batch(["thea"] * n, list(range(n))):
        first[tuple(rows[0][3])] += 1
        for lp, _, inc, ids in rows:
            seen[tuple(ids)] += 1
            weight[tuple(ids)] += np.exp(lp) / inc / n
            logp[tuple(ids)] = lp
    assert abs(sum(map(np.exp, logp.values())) - 1) < 1e-3
    keys = list(logp)
    g = np.array([logp[k] for k in keys]) + np.random.default_rng(0).gumbel(size=(n, len(keys)))
    top = Counter(np.argsort(-g, 1)[:, :4].reshape(-1).tolist())
    for i, k in enumerate(keys):
        p = np.exp(logp[k])
        assert abs(first[k] / n - p) < 0.025 and abs(seen[k] - top[i]) / n < 0.03
        assert p < 0.01 or abs(weight[k] - p) < 0.03


def spelt(text, pieces):
    """All segmentations of a text, with the sum of their pieces' scores."""
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=tokenizer_file("piece_bpe_32k.model"))
    known = {sp.id_to_piece(i): i for i in range(sp.get_piece_size()) if not (sp.is_byte(i) or sp.is_control(i) or sp.is_unknown(i))}
    rest = "\u2581" + text.replace(" ", "\u2581")

    def go(at):
        if at == len(rest):
            yield (), 0.0
        for end in range(at + 1, len(rest) + 1):
            if (i := known.get(rest[at:end])) is not None:
                for ids, score in go(end):
                    yield (i, *ids), score + pieces.score[i]

    return dict(go(0))


def test_log_probabilities_are_those_of_all_segmentations(sampler):
    every = spelt("the cat", sampler.pieces)
    norm = np.logaddexp.reduce(list(every.values()))
    for rows in sampler.batch(["the cat"] * 40, list(range(40))):
        for lp, _, _, ids in rows:
            assert abs(every[tuple(ids.tolist())] - norm - lp) < 1e-9


def test_a_small_store_of_lattices_gives_the_same(monkeypatch):
    texts = [passage(i, 40) for i in range(12)] + ["the cat " * 30]
    out = []
    for most, run in ((10**9, 1 << 17), (200, 64)):
        monkeypatch.setattr(segment, "MAX_ENTRIES", most)
        monkeypatch.setattr(segment, "RUN_CHARS", run)
        s = segment.Sampler(tokenizer_file("piece_bpe_32k.model"), k=3)
        out.append([[(round(r[0], 6), r[3].tolist()) for r in next(s.batch([t], [i]))] for i, t in enumerate(texts * 2)])
    assert out[0] == out[1]


def test_batches_do_not_matter(sampler):
    texts = [passage(i, 30) for i in range(5)]
    alone = [[(r[0], r[1], r[3].tolist()) for r in next(sampler.batch([t], [i]))] for i, t in enumerate(texts)]
    joint = [[(r[0], r[1], r[3].tolist()) for r in rows] for rows in sampler.batch(texts, list(range(5)))]
    for a, b in zip(alone, joint):
        assert [x[2] for x in a] == [x[2] for x in b] and np.allclose([x[:2] for x in a], [x[:2] for x in b])


def test_segment_odd_texts(spark, odd, none):
    model = tokenizer_file("piece_bpe_32k.model")
    got = segment.sample_segmentations(odd, model, check=True)
    assert all(r["round_trip"] for r in got.collect()) and segment.sample_segmentations(none, model).count() == 0
    back = segment.decode_pieces(got.where("rank = 1"), model).where("doc_id = 4").first()["text"]
    assert back == ODD[4]


# --- registered queries


@pytest.mark.parametrize("name", sorted(ORACLE_SQL))
def test_twin(spark, sf, name):
    assert rows_of(QUERIES[name](spark, sf)) == twin_rows(ORACLE_SQL[name], sf)
