"""Sums over segmentations against enumeration, held-out accuracy, and odd rows."""

import math

import numpy as np

from bitparse.llm import langid


def every_cut(word):
    if not word:
        yield []
    for k in range(1, len(word) + 1):
        for rest in every_cut(word[k:]):
            yield [word[:k], *rest]


def place(model, piece):
    keys, first = model.keys[len(piece)]
    return first + int(np.searchsorted(keys, langid._hashes(np.array([[ord(c) for c in piece]], np.uint64))[0][0, -1]))


def test_long_words_and_long_pieces_are_learnt():
    import public_tokenizers

    word, piece = "donaudampfschifffahrtsgesellschaftskapitaen", "internationally"
    model = langid.Model(["schiff", "fahrt", piece], ["x", "y"]).fit([{word: 50, piece: 50}, {"a": 1}], rounds=1)
    assert (model.table[[place(model, p) for p in ("schiff", "fahrt", piece)], 0] > 0.01).all()
    assert max(map(len, langid.pieces(public_tokenizers.path(langid.VOCABULARY)))) > 10


def test_forward_sums_all_segmentations():
    vocabulary = ["a", "b", "ab", "ba", "▁a", "aba", "▁"]
    model = langid.Model([p for p in vocabulary if p != "▁"], ["x", "y"])
    rng = np.random.default_rng(1)
    model.table = rng.random(model.table.shape)
    row = {p: place(model, p) for p in vocabulary if p != "▁"}
    for word in ("a", "abab", "bac", "abcabab"):
        want = np.zeros(2)
        for cut in every_cut("▁" + word):
            p = np.ones(2)
            for piece in cut:
                p = p * (model.table[row[piece]] if piece in row else model.table[-1] if len(piece) == 1 else 0)
            want += p
        assert np.allclose(model.log_probability([word])[0], np.log(want))


def test_long_words_keep_their_scale():
    model = langid.Model(["a"], ["x"])
    model.table[:] = [[1e-9], [1e-9]]
    assert math.isclose(model.log_probability(["a" * 48])[0, 0], 49 * math.log(1e-9), rel_tol=1e-9)


def test_long_texts_go_piece_by_piece(monkeypatch):
    model = langid.Model(["a", "b", "ab"], ["x", "y"])
    model.table[:] = np.random.default_rng(2).random(model.table.shape)
    texts = [b"ab ba " * 400, None, b"", b"a", b"b" * 900, "é ab ".encode() * 300]
    want = langid.Scorer(model).texts(texts)
    monkeypatch.setattr(langid, "PART", 64)
    got = langid.Scorer(model).texts(texts)
    assert got[0] == want[0] and np.allclose(got[1], want[1])


def test_held_out(spark, sf):
    got = {r.doc_id: r for r in langid.op5_langid(spark, sf).collect()}
    docs = spark.read.parquet(f"{sf}/documents.parquet").collect()
    held = [(got[d.doc_id].lang_pred, d.lang) for d in docs if got[d.doc_id].held_out]
    assert len(got) == len(docs) and sum(a == b for a, b in held) >= 0.9 * len(held)
    assert all(0 <= r.score <= 1 for r in got.values())


def test_odd_rows(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    model = langid.train(docs)
    rows = [(1, None), (2, ""), (3, "123 -- ++"), (4, "the " * 5), (4, "the " * 5), (None, "a" * 5000), (6, "«¿»")]
    df = spark.createDataFrame([(*r, "x", 0.5) for r in rows], "doc_id long, text string, lang_pred string, score double")
    got = [(r.doc_id, r.lang_pred) for r in langid.identify(df, model).collect()]
    assert sorted(p for i, p in got if i in (1, 2, 3, 6)) == ["und"] * 4 and len(got) == len(rows)
    assert all(p in model.langs for i, p in got if i in (4, None))
    empty = langid.train(docs.filter("false"))
    assert {r.lang_pred for r in langid.identify(df, empty).collect()} == {"und"}
