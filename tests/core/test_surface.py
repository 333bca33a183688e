"""Streams against their batch twins, the SQL surface, chunks, odd sequences."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from bitparse import sql, streaming
from bitparse.functions import codes
from bitparse.operators import bits, chunks, lz78, parsers, shortest
from bitparse.operators.parsers import Sequence
from bitparse.sources import sequences
from bitparse.workloads import structure, tables

SMALL = "/root/testdata/sf0.001"


def _run(stream, name, spark):
    query = stream.writeStream.format("memory").queryName(name).outputMode("append").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.table(name).collect()


@pytest.fixture(scope="module")
def stream_of(spark, tmp_path_factory):
    folder = str(tmp_path_factory.mktemp("events") / "in")
    events = tables.ranked(tables.read(spark, SMALL, "events"), F.col("event_type"))
    streaming.symbols(events, F.col("sym")).orderBy("ts").repartitionByRange(4, "ts").write.parquet(folder)
    schema = spark.read.parquet(folder).schema
    return lambda: spark.readStream.schema(schema).option("maxFilesPerTrigger", 8).parquet(folder)


def test_growing_dictionary_stream(spark, stream_of):
    got = _run(streaming.lz78(stream_of()), "grown", spark)
    want = lz78.run(tables.events(spark, SMALL), ("greedy",)).collect()
    by_key = {}
    for r in got:
        by_key.setdefault(r.key, []).append((r.k, r.id, r.sym))
    for r in want:
        assert sorted(by_key.get(r.seq_id, [])) == [(k, p.id, p.sym) for k, p in enumerate(r.parse, 1) if p.sym is not None]


def test_windowed_stream(spark, tmp_path):
    """With rows that end the keys the parts cover every symbol once, without a cut: their bits are the batch's."""
    events = streaming.symbols(tables.ranked(tables.read(spark, SMALL, "events"), F.col("event_type")), F.col("sym"))
    ends = events.groupBy("key").agg(F.lit(None).cast("long").alias("s"), F.max("ts").alias("ts"), (F.max("event_id") + 1).alias("event_id"))
    folder = f"{tmp_path}/in"
    events.unionByName(ends).repartitionByRange(5, "ts", "event_id").write.parquet(folder)
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 8).parquet(folder)
    parts = {}
    for r in _run(streaming.windowed_optimal(stream, 16, 12), "near", spark):
        parts.setdefault(r.key, []).append((r.start, r.n, r.bits))
    c = codes.gamma()
    for r in tables.events(spark, SMALL).collect():
        own = sorted(parts[r.seq_id])
        assert [s for s, _, _ in own] == [1 + sum(n for _, n, _ in own[:k]) for k in range(len(own))] and sum(n for _, n, _ in own) == len(r.syms)
        assert sum(b for _, _, b in own) == sum(p[4] for p in chunks.Online(16, 12).feed(np.array(r.syms), last=True))
        free = parsers.Sequence(np.array(r.syms), c, c, 16)
        assert sum(p[4] for p in chunks.Online(16, 1000).feed(np.array(r.syms), last=True)) == free.total(free.optimal())


def test_online_equals_the_whole():
    rng = np.random.default_rng(3)
    c = codes.gamma()
    for k in range(60):
        s = rng.integers(1, 4, rng.integers(0, 60))
        window, most = int(rng.integers(1, 20)), int(rng.integers(1, 12))
        own, found = chunks.Online(window, most), []
        cut = np.sort(rng.integers(0, len(s) + 1, 4))
        for part in np.split(s, cut):
            found += own.feed(part)
        found += own.feed(np.zeros(0, np.int64), last=True)
        best = [0] + [1 << 60] * len(s)
        for i in range(len(s)):
            best[i + 1] = min(best[i + 1], best[i] + 1 + c.bits(int(s[i])))
            for d in range(1, min(i, window) + 1):
                n = 0
                while n < most and i + n < len(s) and s[i + n] == s[i + n - d]:
                    n += 1
                    best[i + n] = min(best[i + n], best[i] + c.bits(d) + c.bits(n))
        assert sum(p[4] for p in found) == best[-1] and [p[0] for p in found] == [sum(q[1] for q in found[:j]) for j in range(len(found))]
        assert len(own.waiting) == 0 and len(own.held) <= window


def test_long_sequences_come_and_go_in_parts(spark):
    """A million symbols in rows of 50,000: parsed, written and read back without a row that holds them."""
    rng = np.random.default_rng(8)
    words = [rng.integers(97, 123, rng.integers(2, 9)).tolist() + [32] for _ in range(300)]
    text = [c for k in rng.integers(0, 300, 165_000) for c in words[k]][:1_000_000]
    rows = [(7, k, text[at : at + 50_000]) for k, at in enumerate(range(0, len(text), 50_000))] + [(8, 0, [1, 2, 1, 2, 1]), (9, 0, None)]
    parts = spark.createDataFrame(rows, "seq_id long, c int, syms array<int>").repartition(6)
    phrases = chunks.online(parts, 4096, 4096).cache()
    made = {r.seq_id: (r.n, r.bits) for r in phrases.groupBy("seq_id").agg(F.sum("len").alias("n"), F.sum("bits").alias("bits")).collect()}
    assert made[7][0] == len(text) and made[7][1] < 5 * len(text) and made[8][0] == 5 and 9 not in made
    payloads = {}
    for r in bits.of_phrases(phrases).orderBy("seq_id", "part").collect():
        payloads.setdefault(r.seq_id, []).append(r.payload)
    assert len(payloads[7]) > 10 and bits.to_symbols(payloads[7]) == text and bits.to_symbols(payloads[8]) == [1, 2, 1, 2, 1]


def test_deduplicated_stream(spark, stream_of):
    once = _run(streaming.deduplicated(stream_of()), "once", spark)
    assert len(once) == len({r.event_id for r in once})


def test_window_stream(spark, stream_of):
    windowed = streaming.window_bits(stream_of().withWatermark("ts", "1 second"), F.window("ts", "7 days"))
    got = {(r.key, r.begins): (r.n, r.bits) for r in _run(windowed, "weeks", spark)}
    batch = streaming.symbols(tables.ranked(tables.read(spark, SMALL, "events"), F.col("event_type")), F.col("sym"))
    want = {(r.key, r.begins): (r.n, r.bits) for r in streaming.window_bits(batch, F.window("ts", "7 days")).collect()}
    assert got and all(want[k] == v for k, v in got.items())


def test_sql_surface(spark):
    sql.register(spark)
    own = Sequence(np.array([ord(c) for c in "abracadabra"]), codes.gamma(), codes.gamma())
    row = spark.sql("select lz_optimal_bits('abracadabra', 'gamma', 'gamma') as o, lz_greedy_bits('abracadabra', 'gamma', 'gamma') as g, lz_optimal_bits(null, 'gamma', 'gamma') as z").first()
    assert (row.o, row.g, row.z) == (own.total(own.optimal()), own.total(own.greedy()), 0)
    assert spark.sql("select sum(bits) as b, sum(len) as n from lz_phrases('abracadabra', 'gamma', 'gamma')").first() == (row.o, 11)
    assert spark.sql("select p.* from (select 'abab' as t) d, lateral lz_edges(d.t) p").count() == 3
    assert spark.sql("select lz_bits_agg(i, s) as b from (select posexplode(array(1, 2, 1, 2, 1, 2)) as (i, s))").first().b > 0
    family = {r.l: r.text for r in spark.read.format("bad_family").option("most", 5).load().collect()}
    assert sorted(family) == [2, 3, 4, 5] and family[2] == "baaccccbabaa"


def test_recursive_sql(spark):
    priced = structure._edges("orders", spark, SMALL)
    priced.filter("seq_id < 20").createOrReplaceTempView("steps")
    got = {r.seq_id: r.bits for r in spark.sql(shortest.recursive_sql("steps")).collect()}
    want = {r.seq_id: r.bits for r in shortest.fold_costs(priced).collect()}
    assert got and all(want[k] == v for k, v in got.items())


def test_chunks(spark):
    text = ("the cat sat on the mat and the cat ate the rat " * 6).strip()
    seq = sequences.from_text(spark.createDataFrame([(1, text), (2, "a" * 300), (3, ""), (4, None)], "id long, t string"), "id", "t")
    whole = {r.seq_id: r.bits for r in parsers.optimal(seq, window=64).collect()}
    exact = {r.seq_id: r.bits for r in chunks.exact(seq, 37, 64, 400).collect()}
    cut = {r.seq_id: r for r in chunks.seams(seq, 37, 64).collect()}
    for k in (1, 2):
        assert exact[k] == whole[k] <= cut[k].bits <= whole[k] + cut[k].allowance
    assert whole[3] == whole[4] == 0


def test_odd_sequences(spark):
    rows = [(1, ""), (2, None), (3, "a"), (4, "aa"), (5, "é\U0001f600é\U0001f600é"), (6, "a" * 500), (7, "abc" * 40 + "\n")]
    df = spark.createDataFrame(rows, "id long, t string")
    for unit in ("codepoint", "byte"):
        seq = sequences.from_text(df, "id", "t", unit)
        for name in ("optimal", "optimal_block", "greedy", "greedy_triple"):
            parse = parsers.run(seq, (name,), "delta", "fibonacci")
            back = {r.seq_id: r.syms for r in bits.decode(bits.encode(parse)).collect()}
            for k, t in rows:
                assert back[k] == (list(map(ord, t or "")) if unit == "codepoint" else list((t or "").encode()))
    seq = sequences.from_text(df, "id", "t")
    assert {r.seq_id: r.text for r in sequences.to_text(seq).collect()} == {k: t or "" for k, t in rows}
    for scope in ("global", "sequence"):
        for r, own in zip(sequences.remap(seq, scope).orderBy("seq_id").collect(), seq.orderBy("seq_id").collect(), strict=True):
            order = sorted(set(own.syms))
            if scope == "sequence":
                assert r.syms == [order.index(s) + 1 for s in own.syms]
            assert len(r.syms) == own.n
