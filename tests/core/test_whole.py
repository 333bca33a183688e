"""Queries that must read all of their input, on small tables made for that."""

import numpy as np

import pytest
from pyspark.sql import functions as F

from bitparse import workloads
from bitparse.functions.codes import n_plateaus
from bitparse.workloads import applications, parsing


@pytest.fixture(scope="module")
def hot(spark, tmp_path_factory):
    """Events of a user with 300, whose second half repeats the first, and of one with 20."""
    path = tmp_path_factory.mktemp("hot")
    half = np.random.default_rng(5).integers(0, 4, 150).tolist()
    rows = [(7, k, f"e{s}") for k, s in enumerate(half + half)] + [(8, 1000 + k, f"e{k % 3}") for k in range(20)]
    events = spark.createDataFrame(rows, "user_id long, event_id long, event_type string").withColumn("ts", F.timestamp_seconds("event_id"))
    events.write.parquet(str(path / "events.parquet"))
    return str(path)


def test_degree_of_long_sequences(spark, hot):
    got = {r.seq_id: r for r in workloads.QUERIES["max_degree"](spark, hot).collect()}
    assert {k: r.bound for k, r in got.items()} == {7: 2 * n_plateaus("gamma", 300), 8: 2 * n_plateaus("gamma", 20)}
    assert all(r.max_degree <= r.bound for r in got.values())


def test_near_copies_edited_anywhere_are_found(spark, tmp_path):
    rng = np.random.default_rng(2)
    word = lambda: "".join(map(chr, rng.integers(97, 123, 6)))
    base = [word() for _ in range(120)]
    texts = [" ".join(base), "edited " + " ".join(base[1:]), " ".join(base), " ".join([*base[:60], "other", *base[61:]]), " ".join(word() for _ in range(120))]
    spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {r.a: (r.b, r.distance) for r in applications.QUERIES["ncd_near_copies"](spark, str(tmp_path)).collect()}
    assert {a: b for a, (b, _) in got.items()} == {1: 0, 3: 0} and all(d < 0.3 for _, d in got.values())


def test_nearest_copy_is_found_among_all_texts_that_share_a_phrase(spark, tmp_path):
    """The nearest of a large group, which is not its first one, and one that shares a single phrase."""
    rng = np.random.default_rng(4)
    word = lambda: "".join(map(chr, rng.integers(97, 123, 6)))
    text = lambda words: " ".join(words)
    base = [word() for _ in range(200)]
    many = [[*base[: 40 + 10 * k], *(word() for _ in range(160 - 10 * k))] for k in range(8)]
    many.append([*base[:111], *many[6][111:]])  # all eight share its first words; the seventh is the nearest
    lone = [[word() for _ in range(300)] for _ in range(2)]
    lone[1][200:205] = lone[0][100:105]
    texts = list(map(text, [*many, *lone, ["only", "short"], ["only", "short"]])) + ["", None]
    spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {r.a: (r.b, r.distance) for r in applications.QUERIES["ncd_near_copies"](spark, str(tmp_path)).collect()}
    pairs = [(a, b) for a in range(9) for b in range(a)] + [(10, 9)]
    every = applications.ncd(spark.createDataFrame([(a, b, texts[a], texts[b]) for a, b in pairs], "a long, b long, x string, y string")).collect()
    want = {}
    for r in sorted(every, key=lambda r: (r.distance, r.b)):
        want.setdefault(r.a, (r.b, r.distance))
    assert got == want and got[8][0] == 6 and got[10][0] == 9


def test_bits_after_history():
    """Against all parses, by copies of every length from every earlier place."""
    gamma = lambda x: 2 * (x + 1).bit_length() - 1
    rng = np.random.default_rng(3)
    for _ in range(40):
        x, held = rng.integers(1, 4, 24).tolist(), int(rng.integers(0, 12))
        best = {len(x): 0}
        for i in range(len(x) - 1, held - 1, -1):
            steps = [gamma(0) + gamma(x[i]) + best[i + 1]]
            for k in range(i):
                n = 0
                while i + n < len(x) and x[k + n] == x[i + n]:
                    n += 1
                    steps.append(gamma(i - k) + gamma(n) + best[i + n])
            best[i] = min(steps)
        assert applications.bits_after(np.array(x[:held], np.int64), np.array(x[held:], np.int64)) == best[held]


def test_leak_reads_documents(spark, tmp_path):
    item, short = "seven brown foxes quietly crossed the frozen river", "amber lantern"
    docs = [(1, f"Intro words. {item.upper()} and {item} again."), (2, "nothing of that kind stands here at all"), (3, f"an {short} hung there"), (4, None)]
    spark.createDataFrame(docs, "doc_id long, text string").write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(10, item), (11, short), (12, "")], "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    got = {(r.item_id, r.doc_id): r for r in workloads.QUERIES["benchmark_leak_bits"](spark, str(tmp_path)).collect()}
    assert set(got) == {(10, 1), (11, 3)}
    assert all(r.saved == r.alone - r.after_item > 0 for r in got.values())


def test_frontier_of_long_sequences(spark, hot):
    want = {r.seq_id: r.bits for r in parsing.totals("events")(spark, hot).collect()}
    assert {r.seq_id: r.bits for r in workloads.QUERIES["chunk_frontier_exact"](spark, hot).collect()} == want
