"""What keeps queries over whole documents within their time: work that is shared, joined or dealt out, with the same results."""

import numpy as np
import pyarrow as pa

from bitparse.functions.codes import code
from bitparse.operators import bits, blocks, chunks, lz78, parsers, repeats
from bitparse.workloads import applications

GAMMA = code("gamma")


def some(n, sigma, seed):
    return np.random.default_rng(seed).integers(1, sigma + 1, n)


def test_greedy_takes_its_matches_from_the_steps_of_the_optimum(monkeypatch):
    x = np.concatenate([some(300, 4, 1), some(300, 4, 1)[50:]])
    alone, both = parsers.Sequence(x, GAMMA, GAMMA), parsers.Sequence(x, GAMMA, GAMMA)
    want = alone.greedy()
    both.optimal()
    monkeypatch.setattr(blocks.Suffixes, "__init__", lambda *a: 1 / 0)  # no second search for matches
    assert both.greedy() == want


def test_gaps_are_priced_together_without_phrases(monkeypatch):
    """The optimum and greedy bits of many sequences at once equal those of each alone: odd ones, many copies, longer than a pack."""
    monkeypatch.setattr(parsers, "PACK", 900)
    monkeypatch.setattr(parsers, "RACK", 2000)
    every = [np.zeros(0, np.int64), *(some(n, k, n + k) for n in (1, 2, 3, 17, 200, 880) for k in (1, 2, 9)), np.tile(some(30, 9, 1), 29), some(950, 3, 2), np.ones(1200, np.int64), some(70, 60_000, 3)]
    for f, g in (("gamma", "gamma"), ("delta", "omega"), ("varbyte", "nibble")):
        f, g = code(f), code(g)
        each = [parsers.Sequence(x, f, g) for x in every]
        want = [s.total(s.optimal()) for s in each], [s.total(s.greedy()) for s in each]
        with monkeypatch.context() as m:
            m.setattr(parsers.Sequence, "path", lambda *a: 1 / 0)  # no phrases of an optimum
            assert parsers.gap_totals(every, f, g) == want


def test_short_sequences_go_through_the_blocks_together(monkeypatch):
    every = [some(n, 3, n) for n in (0, 1, 40, 90, 400)] + [np.ones(200, np.int64)] * 2
    one = [(s.total(p), len(p)) for s, p in ((s, s.optimal("block")) for s in (parsers.Sequence(x, GAMMA, GAMMA) for x in every))]
    calls, stream = [], blocks.stream
    monkeypatch.setattr(blocks, "stream", lambda *a, **k: calls.append(1) or stream(*a, **k))
    assert parsers.block_totals(every, GAMMA, GAMMA) == one
    assert len(calls) == 1


def test_paths_of_many_blocks_go_on_together(monkeypatch):
    """Bits and phrases as of each alone, ties too; only a sequence longer than a block has a path of its own."""
    monkeypatch.setattr(blocks, "SPAN", 600)
    monkeypatch.setattr(parsers, "RACK", 1500)
    every = [some(n, k, n + k) for n in (0, 1, 2, 40, 90, 400, 599) for k in (1, 2, 3, 30)] + [np.tile(some(30, 9, 1), 15), some(2000, 3, 7), some(70, 60_000, 3)]
    for f, g, window in (("gamma", "gamma", None), ("delta", "omega", 50), ("varbyte", "nibble", None), ("fibonacci", "gamma", None)):
        f, g = code(f), code(g)
        want = [(s.total(p), len(p)) for s, p in ((s, s.optimal("block")) for s in (parsers.Sequence(x, f, g, window) for x in every))]
        made, start = [], parsers.shortest.Path.__init__
        with monkeypatch.context() as m:
            m.setattr(parsers.shortest.Path, "__init__", lambda self, n, literal, made=made: made.append(n) or start(self, n, literal))
            assert parsers.block_totals(every, f, g, window) == want
        assert made == [2000]


def test_passes_that_follow_one_another_need_no_links_in_second_windows(monkeypatch):
    """Of each position what is longer than all nearer copies, as by passes that look at nothing but their plateau."""
    for x in (some(900, 2, 1), some(900, 4, 2), np.tile(some(37, 5, 3), 20), np.ones(300, np.int64)):
        own, calls, back = blocks.Suffixes(x), [], blocks.back
        monkeypatch.setattr(blocks, "back", lambda v, calls=calls: calls.append(1) or back(v))
        best = np.zeros(len(x), np.int64)
        for lo, hi in ((1, 2), (3, 6), (7, 14), (15, 30), (31, 62), (63, 126), (127, 254), (255, 299)):
            queries = np.arange(lo, len(x))
            want, at, visits = blocks.one_pass(own, lo, hi, 0, len(x), queries)
            calls.clear()
            got, source, same = blocks.rising_pass(own, lo, hi, 0, len(x), queries)
            news = want > best[queries]
            assert len(calls) <= 2 and same == visits
            assert np.array_equal(got > best[queries], news) and np.array_equal(got[news], want[news]) and np.array_equal(source[news], at[news])
            best[queries] = np.maximum(best[queries], want)
        monkeypatch.undo()


def test_steps_down_the_tree_are_found_together(monkeypatch):
    x = some(500, 3, 2).tolist()
    scan = lz78.Scan(x)
    rows = [(i, n, k) for i in range(scan.n) for n, k in scan.entries(i)]
    monkeypatch.setattr(lz78.Scan, "entries", lambda *a: 1 / 0)  # no walk of one position
    star = scan.star()
    assert list(zip(star.i.tolist(), star.length.tolist(), star.dist.tolist(), strict=True)) == rows
    assert lz78.Scan([]).star().i.size == lz78.Scan([5]).star().i.size == 0


def test_cuts_at_seams_share_the_steps_of_the_whole(monkeypatch):
    x = np.concatenate([some(300, 4, 5), np.ones(300, np.int64)])
    for given in (x, np.ones(700, np.int64)):  # steps that are listed, and too many to list
        want = sum(chunks.chunk_parse(given[c - min(c, 100) : c + 64], min(c, 100), GAMMA, GAMMA, 100)[0] for c in range(0, len(given), 64))
        own = parsers.Sequence(given, GAMMA, GAMMA, 100)
        own.optimal()
        with monkeypatch.context() as m:
            m.setattr(repeats, "levels", lambda *a, **k: 1 / 0)
            if own.listed is not None:
                assert chunks.cut_bits(own, 64) == want
        assert chunks.cut_bits(parsers.Sequence(given, GAMMA, GAMMA, 100), 64) == want


def test_compression_distance_takes_texts(spark):
    rows = [(2, 1, "abcabcabd", "abcabc"), (3, 1, "", "abcabc"), (4, 1, "ä€😀ä€😀", "abcabc")]
    points = [(a, b, [ord(c) for c in x], [ord(c) for c in y]) for a, b, x, y in rows]
    got, want = (sorted(map(tuple, applications.ncd(spark.createDataFrame(r, f"a long, b long, x {k}, y {k}")).collect())) for r, k in ((rows, "string"), (points, "array<int>")))
    assert got == want


def test_compression_distance_prices_pairs_together(monkeypatch):
    every = [np.zeros(0, np.int64), *(some(n, k, n + k) for n in (1, 3, 200) for k in (1, 2, 9)), np.tile(some(30, 9, 1), 29)]
    want = [parsers.Sequence(x, GAMMA, GAMMA).fewest_bits() for x in every]
    monkeypatch.setattr(parsers.Sequence, "fewest_bits", lambda *a: 1 / 0)  # none of them alone
    monkeypatch.setattr(parsers.Sequence, "greedy", lambda *a: 1 / 0)
    assert parsers.fewest_totals(every, GAMMA, GAMMA) == want


def test_compression_distance_takes_known_sizes(spark):
    """The size of a text is found once, not for each of its pairs."""
    texts = {1: "abcabcabd", 2: "abcabc", 3: None}
    docs = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    bits = {r.doc_id: r.bits for r in applications.sizes(docs).collect()}
    pairs = spark.createDataFrame([(2, 1), (3, 1)], "a long, b long")
    given = applications._with_texts(pairs, applications.sizes(docs), 15)
    plain = spark.createDataFrame([(a, b, texts[a], texts[b]) for a, b in ((2, 1), (3, 1))], "a long, b long, x string, y string")
    got = sorted(map(tuple, applications.ncd(given).collect()))
    assert got == sorted(map(tuple, applications.ncd(plain).collect())) and [r[2:4] for r in got] == [(bits[2], bits[1]), (bits[3], bits[1])]
    marked = given.withColumn("cx", given.cx * 0 + 7)
    assert {r.cx for r in applications.ncd(marked).collect()} == {7}


def test_codewords_are_made_once_for_each_value(spark):
    x = np.concatenate([some(200, 5, 8), some(200, 5, 8)])
    seq = spark.createDataFrame([(1, len(x), x.tolist()), (2, 0, []), (3, 1, [70000])], "seq_id long, n int, syms array<int>")
    for name in ("optimal", "greedy_triple"):
        parse = parsers.run(seq, (name,), "delta", "gamma").collect()
        made = {r.seq_id: r.payload for r in bits.encode(spark.createDataFrame(parse, parsers.PARSE)).collect()}
        for r in parse:
            head, body = bits.to_bits(r.n, [p.asDict() for p in r.phrases], code("delta"), GAMMA)
            assert format(int.from_bytes(b"\1" + made[r.seq_id], "big"), "b")[1:].rstrip("0") == (head + body).rstrip("0")
            if r.phrases:
                assert bits._body(pa.array([p.asDict() for p in r.phrases], parsers._PHRASE), code("delta"), GAMMA) == body
            assert bits.from_bits(head + body, code("delta"), GAMMA, name == "greedy_triple") == {1: x.tolist(), 2: [], 3: [70000]}[r.seq_id]
