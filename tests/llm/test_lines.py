"""Deleted lines against brute force over all runs of lines, and odd rows."""

import random

import pyarrow as pa

from bitparse.llm import lines


def brute(docs, least):
    """Deletes every line in a run of enough words that also begins at an earlier place. docs: (doc_id, text), in order."""
    flat = [[x.strip() for x in (t or "").split("\n") if x.strip()] for _, t in docs]
    places = [(d, k) for d, own in enumerate(flat) for k in range(len(own))]
    gone = set()
    for d, k in places:
        for e, j in places:
            if (e, j) >= (d, k):
                break
            n = 0
            while k + n < len(flat[d]) and j + n < len(flat[e]) and flat[d][k + n] == flat[e][j + n]:
                n += 1
            if sum(len(x.split()) for x in flat[d][k : k + n]) >= least:
                gone |= {(d, k + i) for i in range(n)}
    return [[x for k, x in enumerate(own) if (d, k) not in gone] for d, own in enumerate(flat)]


def test_random(spark):
    rng = random.Random(5)
    pool = [" ".join(rng.choice("abcdef") for _ in range(rng.randrange(1, 7))) for _ in range(12)]
    docs = []
    for k in range(60):
        own = [rng.choice(pool) for _ in range(rng.randrange(0, 14))]
        if docs and rng.random() < 0.5:
            own += rng.choice(docs)[1].split("\n")
        docs.append((k, "\n".join(own)))
    df = spark.createDataFrame(docs, "doc_id long, text string")
    for least in (4, 10, 25):
        got = {r.doc_id: [x.strip() for x in r.text.split("\n") if x.strip()] for r in lines.dedup(df, least).collect()}
        assert [got[k] for k, _ in docs] == brute(docs, least)


def test_documents(spark, sf):
    docs = sorted((r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect())
    got = {r.doc_id: [x.strip() for x in r.text.split("\n") if x.strip()] for r in lines.op9_lines(spark, sf).collect()}
    assert [got[k] for k, _ in docs] == brute(docs, lines.MIN_WORDS)


def test_clashing_names_and_a_long_text(spark):
    long = "\n".join(f"line {k} of a long text" for k in range(30_000))
    df = spark.createDataFrame([(1, long, 1, 2, 3, 4, 5), (2, long + "\nlast", 1, 2, 3, 4, 5)], "doc_id long, text string, gone int, __gone int, o int, h int, __o int")
    got = {r.doc_id: r for r in lines.dedup(df).collect()}
    assert got[1].text == long and got[2].text == "last" and got[2].n_removed == 30_000 and (got[2].gone, got[2].o, got[2].h, got[2]["__gone"]) == (1, 3, 4, 2)


def test_odd_rows(spark):
    long = " ".join(["word"] * 60)
    rows = [(1, None), (2, ""), (3, "\n\n"), (4, long), (5, f" {long}\r\n\nown line\n"), (5, f" {long}\r\n\nown line\n"), (None, "x\n" + long), (7, f"{long}\n{long}"), (8, "word")]
    df = spark.createDataFrame([(*r, k, "x") for k, r in enumerate(rows)], "doc_id long, text string, l int, o string")
    got = {r.l: (r.text, r.n_removed) for r in lines.dedup(df).collect()}
    assert got[0] == (None, 0) and got[1] == ("", 0) and got[2] == ("\n\n", 0) and got[8] == ("word", 0)
    assert got[6] == ("x\n" + long, 0) and got[3] == ("", 1) and got[4] == got[5] == ("\nown line\n", 1) and got[7] == ("", 2)
    assert lines.dedup(df.limit(0)).count() == 0


def test_workers_give_memory_back_after_each_partition(monkeypatch):
    from bitparse.llm import common

    given = []
    monkeypatch.setattr(common, "give_back", lambda: given.append(1))
    assert list(common.giving_back(lambda batches: (2 * x for x in batches))(iter([1, 2]))) == [2, 4]
    assert given == [1]


def test_rows_of_lines_of_many_texts(spark):
    docs = spark.range(1000).selectExpr("id as doc_id", "concat('a line\nof ', id) as text").coalesce(1)
    sizes = lines.line_rows(docs).mapInArrow(lambda batches: (pa.RecordBatch.from_pydict({"n": [b.num_rows]}) for b in batches), "n long")
    assert sum(r.n for r in sizes.collect()) == 2000
