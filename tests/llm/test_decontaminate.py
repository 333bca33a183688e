"""Hits and items against brute force over words, several blocks of items, and odd rows."""

import hashlib
import random
import re

import numpy as np
import pytest

from bitparse.llm import decontaminate as d


def words(text):
    lower = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", lower)


def brute(docs, items, n=13):
    windows = {}
    for item, text in items:
        w = words(text)
        for k in range(max(1, len(w) - n + 1) if w else 0):
            windows.setdefault(tuple(w[k : k + n]), set()).add(str(item))
    sizes = {len(w) for w in windows}
    out = []
    for key, text in docs:
        w, hit, found = words(text), set(), set()
        for size in sizes:
            for k in range(len(w) - size + 1):
                if (own := tuple(w[k : k + size])) in windows:
                    hit.update(range(k, k + size))
                    found |= windows[own]
        out.append((key, len(w), len(hit), tuple(sorted(found))))
    return out


def test_documents(spark, sf):
    docs = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    got = {r.doc_id: r for r in d.op2_decontaminate(spark, sf).collect()}
    for key, n, hit, found in brute(docs, items):
        r = got[key]
        assert (r.n_words, r.n_hit, r.n_items, r.items_sha256) == (n, hit, len(found), hashlib.sha256(",".join(found).encode()).hexdigest())
        assert r.contaminated == (hit > 0 and 20 * hit >= n)
    assert len(got) == len(docs)


@pytest.mark.parametrize("block", [10**9, 30])
def test_odd_rows(spark, block):
    long = " ".join(f"w{k}" for k in range(30))
    items = [(1, "a b"), (2, None), (3, " .. "), (4, long), (4, "Ünder é9"), (None, "zz"), (5, long[:40]), (6, "a b")]
    docs = [(1, None), (2, ""), (3, "A, B; a b"), (3, "A, B; a b"), (4, "x " + long.upper() + " y"), (5, long[4:]), (None, "ünder É9 ünder é9 zz"), (7, "a"), (8, "b a"), (9, "\x80é a b " * 500), (10, "q" * 3_000_000 + " a b")]
    got = d.decontaminate(spark.createDataFrame([(*r, "x") for r in docs], "doc_id long, text string, items string"), spark.createDataFrame(items, "item_id long, text string"), block_chars=block).collect()
    want = brute(docs, [("" if i is None else i, t) for i, t in items])
    key = lambda r: (r[0] is None, r[0] or 0, r[1], r[2])
    assert sorted([(r.doc_id, r.n_words, r.n_hit, tuple(r["items"])) for r in got], key=key) == sorted(want, key=key)


def test_windows_are_small():
    """20 million characters of items would make ten blocks; one block of them fits many times over."""
    import pickle
    import random

    rng = random.Random(1)
    items = [(str(k), " ".join(f"w{rng.randrange(50_000)}" for _ in range(300)).encode()) for k in range(1000)]
    chars = sum(len(t) for _, t in items)
    made = d.Windows(items)
    made.file(np.zeros(len(made.keys), np.int64))
    assert len(pickle.dumps(made)) < 25 * chars


def test_many_blocks_of_items(spark, monkeypatch):
    monkeypatch.setattr(d, "AT_ONCE", 2)
    rng = random.Random(4)
    pool = [f"w{k}" for k in range(40)]
    items = [(k, " ".join(rng.choices(pool, k=rng.randrange(1, 30)))) for k in range(60)]
    docs = [(k, " ".join([*rng.choices(pool, k=20), rng.choice(items)[1], *rng.choices(pool, k=20), rng.choice(items)[1]])) for k in range(40)]
    got = d.decontaminate(spark.createDataFrame([(*r, 1, 2, "x") for r in docs], "doc_id long, text string, marks int, __text int, body string"), spark.createDataFrame(items, "item_id long, text string"), keep=("doc_id", "marks", "body"), block_chars=600).collect()
    assert sorted((r.doc_id, r.n_words, r.n_hit, tuple(r["items"])) for r in got) == brute(docs, items)
    assert {(r.marks, r.body) for r in got} == {(1, "x")}


def test_empty_tables(spark):
    docs = spark.createDataFrame([(1, "a b")], "doc_id long, text string")
    items = spark.createDataFrame([(1, "a b")], "item_id long, text string")
    assert d.decontaminate(docs.limit(0), items).count() == 0
    assert [(r.n_words, r.n_hit) for r in d.decontaminate(docs, items.filter("false")).collect()] == [(2, 0)]
