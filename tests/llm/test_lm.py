"""Gradients, the sums of conditionals, scores against plain Python, partitions, sense in scores, and odd rows."""

import math

import numpy as np
from pyspark.sql import functions as F

from bitparse.llm import lm
from bitparse.llm.decontaminate import Words, words_of as split


def scores(train_on, docs):
    words_of, shares = lm.vocabulary(train_on)
    net = lm.train(lm.encode(train_on, words_of), words_of)
    return lm.score(lm.encode(docs, words_of), shares, words_of, net), words_of, net


def test_gradient():
    net, rng = lm.Net(1000, kind=np.float64), np.random.default_rng(4)
    around, target = rng.integers(0, 50, (30, 4)), rng.integers(0, 1000, 30)
    net.log_probability(around, target, learn=True)
    grads = net.grads.copy()
    for k in np.concatenate([rng.choice(np.flatnonzero(grads), 60), [0, len(grads) - 1]]):
        before = net.flat[k]
        net.flat[k] = before + 1e-5
        up = -net.log_probability(around, target).sum()
        net.flat[k] = before - 1e-5
        down = -net.log_probability(around, target).sum()
        net.flat[k] = before
        assert abs((up - down) / 2e-5 - grads[k]) < 1e-4


def test_conditionals_sum_to_one():
    net = lm.Net(1000, kind=np.float64)
    around = np.tile(np.array([[1, 2, 3, 1000]]), (1000, 1))
    assert abs(np.exp(net.log_probability(around, np.arange(1000))).sum() - 1) < 1e-9


def test_spellings_sum_to_one():
    pairs = np.random.default_rng(3).integers(0, 9, lm.SYMBOLS**2).astype(float)
    places = lm.Vocabulary.of([], pairs, 3, 7, 10)
    alphabet = [bytes([c]) for c in range(256) if lm._SYMBOL[c]]
    assert abs(np.exp(places.spelled(Words([b" ".join(alphabet)]))).sum() - 1) < 1e-9
    assert abs(np.exp(places.spelled(Words([b" ".join(a + b for a in alphabet for b in alphabet)]))).sum() - 1) < 1e-9
    tail = [(1 - places.longer) * places.longer**k for k in range(500)]
    assert abs(sum(tail) - 1) < 1e-9


def test_neighbours_stay_in_their_text():
    x, text = np.array([5, 6, 7, 8]), np.array([0, 0, 1, 1])
    assert lm.neighbours(x, text, np.array([1, 2]), 99).tolist() == [[99, 5, 99, 99], [99, 99, 8, 99]]


def test_around_and_pairs_equal_plain_python():
    """Windows made once for all places of some texts, and pairs of neighbouring bytes by symbols."""
    texts = [[4, 5, 6, 7, 8], [9], [1, 2], [3, 3, 3]]
    x, text = np.concatenate(texts), np.repeat([0, 1, 3, 4], [len(t) for t in texts])  # number 2 is an empty text
    want = [[t[i + d] if 0 <= i + d < len(t) else 99 for d in (-2, -1, 1, 2)] for t in texts for i in range(len(t))]
    around = lm.Around(x, text, 99)
    assert around(np.arange(len(x))).tolist() == want
    assert around(np.array([7, 0, 5])).tolist() == [want[7], want[0], want[5]]
    assert lm.Around(x[:0], text[:0], 99)(np.zeros(0, np.int64)).shape == (0, 4)
    plain = Words([b"Ab 0z", bytes(range(128, 256))]).plain
    sym = [int(lm._SYMBOL[c]) for c in plain]
    assert lm.pairs_of(plain).tolist() == [a * lm.SYMBOLS + b for a, b in zip([0, *sym], sym)]


def test_scores_equal_plain_python(spark, monkeypatch):
    """Sums over a text, word by word: the tree of softmaxes, the shares of rare words and their spelling."""
    monkeypatch.setattr(lm, "GROWTH", 1)
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text").orderBy("doc_id")
    found, words_of, net = scores(docs, docs)
    rows, got = docs.collect(), {r.doc_id: r for r in found.collect()}
    place = dict(zip(words_of.keys.tolist(), words_of.places.tolist(), strict=True))
    count, total = {}, [0] * (lm.LENGTHS + 1)
    hashed = lambda w: int(Words([w]).hash[0])
    known = {}
    for r in rows:
        for w in split(r.text.encode()):
            known.setdefault(w, hashed(w))
            if known[w] not in place:
                count[w] = count.get(w, 0) + 1
                total[min(len(w), lm.LENGTHS)] += 1
    soft = lambda z, at: float(z[at] - z.max() - np.log(np.exp(z - z.max()).sum()))
    for r in rows[:12]:
        words = split(r.text.encode())[:60_000]
        x = [place.get(known[w], min(len(w), lm.LENGTHS) - 1) for w in words]
        expected, p, k = 0.0, {n: v.astype(np.float64) for n, v in net.p.items()}, net.k
        for i, w in enumerate(words):
            z = p["bias"].copy()
            for slot, step in enumerate((-2, -1, 1, 2)):
                z += p["vectors"][x[i + step] if 0 <= i + step < len(x) else net.size] * p["place"][slot]
            h, a, b = np.append(np.tanh(z), 1), x[i] // k**2, x[i] // k
            expected += soft(p["top"][0] @ h, a) + soft(p["middle"][a] @ h, b % k) + soft(p["leaf"][b] @ h, x[i] % k)
            if known[w] not in place:
                spelled = float(words_of.spelled(Words([w]))[0])
                expected += math.log(lm.SHARE * count[w] / total[min(len(w), lm.LENGTHS)] + (1 - lm.SHARE) * math.exp(spelled))
        assert got[r.doc_id].n_words == len(words)
        assert abs(got[r.doc_id].log_likelihood - expected) < 1e-4 * max(1, len(words))


def test_partitions_and_order_do_not_matter(spark, monkeypatch):
    monkeypatch.setattr(lm, "SHARD", 10_000)  # several shards and rounds
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text")
    made = []
    for n in (1, 4, 8):
        found, _, net = scores(docs.repartition(n, F.rand(n)), docs)
        made.append((net.flat, {r.doc_id: r.log_likelihood / max(1, r.n_words) for r in found.collect()}))
    for flat, rows in made[1:]:
        assert (flat == made[0][0]).all()
        assert all(abs(rows[k] - v) < 1e-5 for k, v in made[0][1].items())


def test_scores(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text")
    words_of, shares = lm.vocabulary(docs)
    net = lm.train(lm.encode(docs, words_of), words_of)
    rows = docs.limit(100).collect()
    rng = np.random.default_rng(1)
    mixed = [(r.doc_id, " ".join(rng.permutation(r.text.split()))) for r in rows]
    total = lambda df, own: lm.score(lm.encode(df, words_of), shares, words_of, own).agg(F.sum("log_likelihood"), F.sum("n_words")).first()
    real = total(spark.createDataFrame(rows), net)
    shuffled = total(spark.createDataFrame(mixed, "doc_id long, text string"), net)
    untrained = total(spark.createDataFrame(rows), lm.Net(words_of.size))
    assert real[1] == shuffled[1] and real[0] > untrained[0] and real[0] > shuffled[0]


def test_the_vocabulary_grows(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text")
    small, large = lm.vocabulary(docs.filter("doc_id % 8 = 0"))[0], lm.vocabulary(docs)[0]
    assert large.size > 1.5 * small.size and len(large.keys) == int(lm.GROWTH * large.words ** (1 / 3))


def test_odd_rows(spark):
    df = spark.createDataFrame([(1, None, 1), (2, "", 1), (3, " -- ", 1), (4, "one two", 1), (4, "one two", 1), (None, "a " * 3000, 1), (5, "x" * 100_000, 1)], "doc_id long, text string, row int")
    got = scores(df, df)[0].collect()
    assert sorted(r.n_words for r in got) == [0, 0, 0, 1, 2, 2, 3000]
    assert all(r.log_likelihood == 0 if r.n_words == 0 else r.log_likelihood < 0 for r in got)
    unknown = scores(df, spark.createDataFrame([(1, "never " + "q" * 5000)], "doc_id long, text string"))[0].first()
    assert unknown.n_words == 2 and -1e6 < unknown.log_likelihood < -100
    assert scores(df.limit(0), df.limit(0))[0].count() == 0


def test_every_word_is_a_target(spark):
    """Each word once: the bias of each word's leaf moves only if the word is a target."""
    texts = spark.createDataFrame([(1, " ".join(f"word{k}" for k in range(32)))], "doc_id long, text string")
    words_of, _ = lm.vocabulary(texts)
    net, before = lm.train(lm.encode(texts, words_of), words_of), lm.Net(words_of.size)
    moved = (net.p["leaf"] != before.p["leaf"])[:, :, -1].ravel()
    assert moved[words_of.places].all()
