"""The array kernels against brute force: codes, repeats, stars, parsers, the growing dictionary, bits."""

import itertools
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from bitparse.functions import codes
from bitparse.operators import bits, blocks, lz78, repeats, stars
from bitparse.operators.parsers import PARSERS, Sequence

NAMES = ("gamma", "delta", "omega", "fibonacci", "varbyte", "nibble", "rice2", "unary", "deflate30")


def strings(count, seed=1, most=24):
    rng = random.Random(seed)
    for k in range(count):
        sigma = rng.choice([1, 2, 3, 4, 30])
        yield np.array([rng.randrange(1, sigma + 1) for _ in range(rng.randrange(0, most))], np.int64)


@pytest.mark.parametrize("name", [*NAMES, "fixed12"])
def test_codes(name):
    c = codes.code(name)
    words = [c.word(x) for x in range(300)]
    assert [len(w) for w in words] == [c.bits(x) for x in range(300)]
    r = codes.Reader("".join(words))
    assert [c.read(r) for _ in words] == list(range(300))
    if name != "unary":
        ordered = sorted(words)
        assert not any(b.startswith(a) for a, b in itertools.pairwise(ordered))
    rows = codes.plateaus(c, 299)
    assert [b for lo, hi, b in rows for _ in range(lo, hi + 1)] == [c.bits(x) for x in range(300)]
    assert all(a[2] < b[2] for a, b in itertools.pairwise(rows))


def test_values_without_a_codeword_are_refused(spark):
    short, own = codes.fixed(3), codes.table([(0, 3, 2)])
    for c, x in ((short, 8), (own, 4)):
        for use in (c.bits, c.word):
            with pytest.raises(ValueError):
                use(x)
        with pytest.raises(Exception, match="no codeword"):
            spark.range(x, x + 1).select(c.column(F.col("id"))).collect()
    assert spark.range(8).select(short.column(F.col("id")).alias("b")).agg(F.sum("b")).first()[0] == 24
    with pytest.raises(ValueError):
        Sequence(np.array([1, 9, 1, 9]), short, short).optimal("pruned")
    rows = spark.createDataFrame([(0, 3, 3), (4, 11, 4)], "lo long, hi long, bits long")
    assert [codes.table_of(rows).bits(x) for x in (0, 4, 11)] == [3, 4, 4]


def test_known_codewords():
    assert [codes.gamma().word(y - 1) for y in (1, 2, 4)] == ["1", "010", "00100"]
    assert [codes.fibonacci().word(y - 1) for y in (1, 2, 3, 5)] == ["11", "011", "0011", "00011"]
    assert [codes.delta().word(y - 1) for y in (1, 2, 4)] == ["1", "0100", "01100"]
    assert [codes.omega().word(y - 1) for y in (1, 2, 4, 16)] == ["0", "100", "101000", "10100100000"]


def test_entropy_code_is_refused():
    c = codes.static_entropy({1: 1, 2: 100, 3: 1})
    assert not c.monotone and codes.by_name(c.name).bits(2) == c.bits(2)
    r = codes.Reader(c.word(2) + c.word(77) + c.word(1))
    assert [c.read(r) for _ in range(3)] == [2, 77, 1]
    with pytest.raises(codes.NotMonotone):
        Sequence(np.array([1, 2, 1, 2]), c, c).optimal("pruned")
    assert Sequence(np.array([1, 2, 1, 2]), c, c).optimal("full")


def brute_copies(s, window=None):
    out = {}
    for i in range(len(s)):
        for n in range(1, len(s) - i + 1):
            for p in range(i - 1, -1, -1):
                if window and i - p > window:
                    break
                if all(s[p + x] == s[i + x] for x in range(n)):
                    out[i, n] = i - p
                    break
    return out


def brute_optimum(s, f, g, window=None):
    best = [0] + [1 << 60] * len(s)
    copies = brute_copies(s, window)
    for i in range(len(s)):
        best[i + 1] = min(best[i + 1], best[i] + f.bits(0) + g.bits(int(s[i])))
        for n in range(1, len(s) - i + 1):
            if (i, n) in copies:
                best[i + n] = min(best[i + n], best[i] + f.bits(copies[i, n]) + g.bits(n))
    return best[-1]


def test_repeats():
    for s in strings(60):
        own = s.tolist()
        rank = repeats.suffix_ranks(s)
        assert [sorted(range(len(own)), key=lambda i: own[i:]).index(i) for i in range(len(own))] == rank.tolist()
        star = stars.full(s)
        assert {(i, n): d for i, n, d in zip(star.i.tolist(), star.length.tolist(), star.dist.tolist(), strict=True)} == brute_copies(own)
        copies = brute_copies(own)
        assert repeats.longest_repeat(s) == max([0, *(n for _, n in copies)])
        suffixes = blocks.Suffixes(s)
        length = suffixes.longest().tolist() if len(own) else []
        assert length == [max([0, *(m for p, m in copies if p == i)]) for i in range(len(own))]
        at = [i for i in range(len(own)) if length[i]]
        assert suffixes.nearest(at, [length[i] for i in at]) == [copies[i, length[i]] for i in at]


@pytest.mark.parametrize("f", ["gamma", "delta", "fibonacci", "rice2", "varbyte", "unary", "deflate30"])
def test_optimum_by_every_strategy(f):
    rng = random.Random(3)
    for s in strings(60, seed=len(f)):
        g = rng.choice(NAMES)
        own = Sequence(s, codes.code(f), codes.code(g))
        want = brute_optimum(s.tolist(), codes.code(f), codes.code(g))
        for strategy in ("full", "pruned", "block", "auto"):
            assert own.total(own.optimal(strategy)) == want, (s.tolist(), f, g, strategy)
        star = own.star("block")
        if len(star.i):
            degree = np.bincount(star.i).max() + 1
            assert degree <= codes.n_plateaus(f, len(s)) + codes.n_plateaus(g, len(s))
        for window in (1, 3, 100):
            near = Sequence(s, codes.code(f), codes.code(g), window)
            for strategy in ("full", "pruned", "block"):
                assert near.total(near.optimal(strategy)) == brute_optimum(s.tolist(), codes.code(f), codes.code(g), window), (s.tolist(), window, strategy)


@pytest.mark.parametrize("f", ["gamma", "fibonacci", "rice2", "varbyte"])
def test_blocks_find_every_maximal_edge(f):
    for s in strings(80, seed=9, most=40):
        price = stars.Pricer(f, max(1, len(s)))
        made = stars.block(s, price)
        have = set(zip(made.i.tolist(), made.length.tolist(), price(made.dist).tolist(), strict=True))
        want = stars.prune(stars.full(s), price, price, "d")
        assert set(zip(want.i.tolist(), want.length.tolist(), price(want.dist).tolist(), strict=True)) <= have
        assert all((s[i + x] == s[i + x - d]) for i, n, d in zip(made.i, made.length, made.dist, strict=True) for x in range(n))


def repetitive(n):
    rng = random.Random(n)
    word = "the cat sat on the mat and saw a rat in the hat "
    yield np.ones(n, np.int64)
    yield np.array([1 + (k % 7 == 0) for k in range(n)])
    yield np.array([rng.randrange(1, 5) for _ in range(n)])
    yield np.array([ord(c) for c in "".join(rng.choice(word.split()) + " " for _ in range(n // 4))][:n], np.int64)
    half = [rng.randrange(1, 90) for _ in range(n // 2)]
    yield np.array(half + half)


@pytest.mark.parametrize("span", [16, 64, 1 << 14])
@pytest.mark.parametrize("f", ["gamma", "fibonacci"])
def test_blocks_hold_few_steps_and_lose_none(monkeypatch, f, span):
    """The steps that are held are measured: at most a few times n at any moment, while those made in all are more."""
    monkeypatch.setattr(blocks, "SPAN", span)
    for s in repetitive(700):
        own = Sequence(s, codes.code(f), codes.gamma())
        assert own.total(own.optimal("block")) == own.total(own.optimal("levels"))
        assert own.counters is not None
        made = Sequence(s, codes.code(f), codes.gamma())
        made.optimal("block")
        q = codes.n_plateaus(f, len(s))
        assert made.counters["live_edges"] <= 7 * len(s) + q * min(span, len(s))
        star = stars.block(s, own.f)
        want = stars.prune(stars.full(s), own.f, own.g, "d")
        have = set(zip(star.i.tolist(), star.length.tolist(), own.f(star.dist).tolist(), strict=True))
        assert set(zip(want.i.tolist(), want.length.tolist(), own.f(want.dist).tolist(), strict=True)) == have


def test_long_chains_of_links():
    values = np.concatenate(([blocks._TOP], np.arange(500)[::-1], [-1]))
    to = blocks.back(values)
    assert to[501] == 500 and (to[1:501] == np.arange(500)).all()
    assert blocks.climb(values, to, np.array([500, 500, 500]), np.array([0, 300, 499])).tolist() == [500, 200, 1]
    assert blocks.climb(values, to, np.array([500]), np.array([500])).tolist() == [0]


def test_greedy_is_fast_on_repetitive_input():
    import time

    began = time.time()
    own = Sequence(np.ones(200_000, np.int64), codes.gamma(), codes.gamma())
    assert [p[:2] for p in own.greedy()] == [(0, 1), (1, 199_999)] and len(own.fewest()) == 2 and len(own.lazy()) <= 3
    assert time.time() - began < 20


@pytest.mark.parametrize("window", [2, 5])
def test_windowed_greedy(window):
    for s in strings(40, seed=2):
        copies = brute_copies(s.tolist(), window)
        near = Sequence(s, codes.gamma(), codes.gamma(), window)
        for i, n, kind, d, _, _ in near.greedy("copy"):
            most = max([0, *(m for p, m in copies if p == i)])
            assert n == max(1, most) and (kind == "literal" if not most else d == copies[i, most])


def test_literal_rule_loses_the_optimum():
    s = np.array([100, 100, 97, 98, 100, 100, 100])
    own = Sequence(s, codes.gamma(), codes.fibonacci())
    star = _no_ones(own)
    cost = own.f(star.dist) + own.g(star.length)
    assert own.total(own.path(star, own.literal, cost)) == 67
    # by the printed rule a literal goes where the copy of two symbols beside it is no dearer
    literal = own.literal.copy()
    two = star.length == 2
    literal[star.i[two][cost[two] <= own.literal[star.i[two]]]] = 1 << 40
    pruned = stars.prune(star, own.f, own.g, "cost")
    assert own.total(own.path(pruned, literal, own.f(pruned.dist) + own.g(pruned.length))) == 69
    assert own.total(own.optimal("pruned")) == brute_optimum(s.tolist(), codes.gamma(), codes.fibonacci())


def _no_ones(own):
    star = stars.full(own.syms)
    keep = star.length > 1
    return stars.Star(star.i[keep], star.length[keep], star.dist[keep])


def test_parsers_and_bits():
    for s in strings(50, seed=4):
        own = Sequence(s, codes.gamma(), codes.delta())
        best = own.total(own.optimal())
        phrases = {name: p(own) for name, p in PARSERS.items()}
        for name, parse in phrases.items():
            if name != "greedy_triple":
                assert own.total(parse) >= best
            assert sum(p[1] for p in parse) == len(s)
            rows = [{"start": p[0] + 1, "len": p[1], "kind": p[2], "dist": p[3], "sym": p[4], "next": p[5]} for p in parse]
            head, body = bits.to_bits(len(s), rows, codes.gamma(), codes.delta())
            assert len(body) == own.total(parse)
            assert bits.from_bits(head + body, codes.gamma(), codes.delta(), name == "greedy_triple") == s.tolist()
        assert len(phrases["greedy"]) == len(phrases["fewest"])
        same = Sequence(s, codes.fixed(6), codes.fixed(6))
        assert same.total(same.greedy("copy")) == same.total(same.optimal("full"))


def brute_lz78(scan, f, g, unit=False):
    best = [0] + [1 << 60] * scan.n
    for i in range(scan.n):
        for n, c in [(1, 1 if unit else f.bits(0) + g.bits(scan.syms[i])), *((n, 1 if unit else f.bits(k)) for n, k in scan.entries(i))]:
            best[i + n] = min(best[i + n], best[i] + c)
    return best[-1]


def test_growing_dictionary():
    f, g = codes.gamma(), codes.gamma()
    for s in strings(150, seed=8, most=60):
        own = s.tolist()
        scan = lz78.Scan(own)
        made = {m: lz78.parse(own, m, f, g) for m in lz78.METHODS}
        assert sum(x[-1] for x in made["optimal"]) == sum(x[-1] for x in made["optimal_full"]) == brute_lz78(scan, f, g)
        assert len(made["flexible"]) == len(made["fewest"]) == brute_lz78(scan, f, g, unit=True) <= len(made["greedy_walk"])
        assert lz78.expand([(k, c) for _, _, k, c, _ in made["greedy"]], True) == own
        assert lz78.expand([(k, c) for _, _, k, c, _ in made["optimal"]], False) == own


def test_static_dictionary():
    entries = {(1,): 1, (1, 2): 2, (2, 1, 1): 3, (2,): 4}
    for s in strings(30, seed=6):
        own = Sequence(s % 2 + 1, codes.gamma(), codes.gamma())
        parse = own.static(entries, 3)
        best = [0] + [1 << 60] * own.n
        for i in range(own.n):
            options = [(1, 1 + codes.gamma().bits(int(own.syms[i])))] + [(len(p), codes.gamma().bits(k)) for p, k in entries.items() if tuple(own.syms[i : i + len(p)]) == p]
            for n, c in options:
                best[i + n] = min(best[i + n], best[i] + c)
        assert own.total(parse) == best[-1]
