"""Fingerprints and components against brute force."""

import random

import numpy as np
import pytest
import xxhash

from bitparse.llm import simhash
from bitparse.llm.components import components


def brute_fp(text):
    words = [w for w in (text or "").translate({c: c + 32 for c in range(65, 91)}).translate({c: " " for c in range(9, 14)}).split(" ") if w]
    shingles = [" ".join(words[k : k + 4]) for k in range(max(1, len(words) - 3))] if words else []
    h = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def union(ids, pairs):
    up = {i: i for i in ids}

    def top(i):
        while up[i] != i:
            i = up[i]
        return i

    for a, b in pairs:
        a, b = top(a), top(b)
        up[max(a, b)] = min(a, b)
    return {i: top(i) for i in ids}


def test_documents(spark, sf):
    docs = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    fp = {k: brute_fp(t) for k, t in docs.items()}
    got = {r.doc_id: r for r in simhash.op7_simhash(spark, sf).collect()}
    assert {k: r.fingerprint for k, r in got.items()} == {k: f"{v:016x}" for k, v in fp.items()}
    ids = sorted(fp)
    want = union(ids, [(a, b) for k, a in enumerate(ids) for b in ids[k + 1 :] if (fp[a] ^ fp[b]).bit_count() <= 4])
    assert {k: r.component_id for k, r in got.items()} == want


def test_manhattan_is_a_lower_bound():
    fps = np.random.default_rng(2).integers(0, 1 << 63, 500, dtype=np.uint64) * np.uint64(2)
    counts = np.array([[int(f) >> 2 * s & 1 for s in range(32)] for f in fps]) + [[int(f) >> 2 * s + 1 & 1 for s in range(32)] for f in fps]
    vector = simhash.embedded(fps)
    for k in range(1, 500):
        manhattan = int(np.abs(counts[k] - counts[k - 1]).sum())
        assert manhattan == int(vector[k] ^ vector[k - 1]).bit_count() <= int(fps[k] ^ fps[k - 1]).bit_count()


def test_keep_one_and_clashing_names(spark):
    text = "a b c d e f g h i j k l m n o p q r s t"
    rows = [(1, text, 1, 1, 1), (2, text, 2, 2, 2), (3, "quite another text of its own words", 3, 3, 3), (3, "quite another text of its own words", 4, 4, 4)]
    df = spark.createDataFrame(rows, "doc_id long, text string, of long, n long, __of long")
    got = simhash.keep_one(df).collect()
    assert sorted(r.doc_id for r in got) == [1, 3] and got[0].__fields__ == df.columns


@pytest.mark.parametrize("groups", [5, 6, 7])
def test_grid_finds_all(spark, monkeypatch, groups):
    rng = random.Random(7)
    base = [rng.getrandbits(64) for _ in range(60)]
    fps = sorted({b ^ sum(1 << k for k in rng.sample(range(64), rng.randrange(6))) for b in base for _ in range(6)})
    real = simhash.grid
    masks = real({5: 1000, 6: 10**7, 7: 10**8}[groups])
    monkeypatch.setattr(simhash, "grid", lambda n, d=4: masks)
    monkeypatch.setattr(simhash, "BLOCK", 40)  # so that hot cells are dealt in blocks
    signed = np.array(fps, np.uint64).view(np.int64).tolist()
    df = spark.createDataFrame([(x,) for x in signed], "fp long")
    roots = {r.id: r.root for r in components(simhash.near_edges(df, len(fps))).collect()}
    want = union(fps, [(a, b) for k, a in enumerate(fps) for b in fps[k + 1 :] if (a ^ b).bit_count() <= 4])
    for a, s in zip(fps, signed, strict=True):
        for b, t in zip(fps, signed, strict=True):
            assert (want[a] == want[b]) == (roots.get(s, s) == roots.get(t, t))


def test_odd_rows(spark):
    text = "a b c d e f g h i j k l m n o p q r s t"
    rows = [(3, None, "x"), (4, "", "x"), (5, " \t\n", "x"), (6, "A b\x0bC", "x"), (6, "a b c", "x"), (7, text, "x"), (8, text.upper(), "x"), (None, text, "x"), (9, "\x85a b c", "x")]
    df = spark.createDataFrame(rows, "doc_id long, text string, fp string")
    got = simhash.near_duplicates(df).collect()
    assert len(got) == len(rows)
    of = {r.doc_id: r.component_id for r in got}
    assert of[3] == of[4] == of[5] == 3 and of[6] == 6 and of[7] == of[8] == of[None] == 7
    assert simhash.near_duplicates(df.limit(0)).count() == 0


def test_path_in_id_order(spark):
    edges = spark.range(1, 200).selectExpr("id as a", "id + 1 as b")
    roots = components(edges.union(edges)).collect()
    assert len(roots) == 200 and len({r.root for r in roots}) == 1
