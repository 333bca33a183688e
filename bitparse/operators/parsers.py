"""Parsers of the sliding dictionary: optimal, greedy and heuristic, over sequences in DataFrames.

A sequence (seq_id, n, syms) is parsed whole in one Arrow kernel, so nothing is shuffled. A parse is
(seq_id, n, parser, f, g, bits, phrases); phrases are structs (start from 1, len, kind, dist, sym,
next, bits). A literal costs f(0) + g(symbol), a copy f(distance) + g(length).
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bitparse.functions.codes import Code, NotMonotone, code, static_entropy
from bitparse.operators import blocks, shortest, stars
from bitparse.operators.stars import Pricer, Star

PHRASE = "struct<start:int,len:int,kind:string,dist:int,sym:int,next:int,bits:bigint>"
PARSE = f"seq_id long, n int, parser string, f string, g string, bits long, phrases array<{PHRASE}>, counters map<string,bigint>"
_PHRASE = pa.struct([("start", pa.int32()), ("len", pa.int32()), ("kind", pa.string()), ("dist", pa.int32()), ("sym", pa.int32()), ("next", pa.int32()), ("bits", pa.int64())])
#: Edges of the full graph per position, times the plateaus, up to which they are enumerated by length.
LEVEL_FACTOR = 4
#: Symbols of parses that are given back together.
BATCH = 1 << 18
#: Symbols whose copies are listed together, so few that 16 bits number them, and whose paths go on together.
PACK, RACK = 1 << 16, 1 << 19

Phrase = tuple[int, int, str, int, int, int | None]  # start from 0, length, kind, distance, symbol, next symbol


class Sequence:
    """One sequence under two codes, and what its parsers share."""

    def __init__(self, syms: np.ndarray, f: Code, g: Code, window: int | None = None):
        self.syms, self.n, self.window = np.asarray(syms, np.int64), len(syms), window
        self.f, self.g = Pricer(f, max(1, self.n)), Pricer(g, int(max(self.n, self.syms.max(initial=0), 1)))
        self.literal = self.f(np.zeros(self.n, np.int64)) + self.g(self.syms)
        self.listed: Star | None = None  # all copies
        self.maximal: Star | None = None  # the steps of all parsers but greedy ones, once they are listed

    @cached_property
    def suffixes(self) -> blocks.Suffixes:
        return blocks.Suffixes(self.syms)

    def star(self, strategy: str, one_copies: bool = True) -> Star:
        monotone = self.f.code.monotone and self.g.code.monotone
        if strategy in ("pruned", "levels", "block", "auto") and not monotone:
            raise NotMonotone(f"{self.f.code.name}, {self.g.code.name}: only the full graph is optimal for such codes")
        if strategy == "full" or not one_copies:
            star = stars.full(self.syms, self.window)
            self.listed = star
            if not one_copies:
                keep = star.length > 1
                star = Star(star.i[keep], star.length[keep], star.dist[keep])
            return star if strategy == "full" else stars.prune(star, self.f, self.g)
        if strategy != "block":
            allowed = None if strategy in ("pruned", "levels") else LEVEL_FACTOR * self.n * (len(self.f.lo) + len(self.g.lo))
            self.listed = stars.full(self.syms, self.window, allowed)
            self.maximal = stars.prune(self.listed, self.f, self.g)
            return self.maximal
        return stars.split_lengths(stars.block(self.syms, self.f, self.window), self.f, self.g)

    def edges(self) -> Star:
        """The maximal copies, listed by length while they are few, else by blocks."""
        try:
            return self.star("auto")
        except OverflowError:
            star = self.star("block")
            order = np.lexsort((star.length, star.i))
            return Star(star.i[order], star.length[order], star.dist[order])

    def path(self, star: Star, literal: np.ndarray, cost: np.ndarray) -> list[Phrase]:
        _, start, edge = shortest.relax(self.n, literal, star, cost)
        own, dist = self.syms.tolist(), star.dist.tolist()
        return [(i, j - i, "copy", dist[e], -1, None) if e >= 0 else (i, 1, "literal", 0, own[i], None) for i, j, e in shortest.backtrace(self.n, start, edge)]

    def optimal(self, strategy: str = "auto", one_copies: bool = True) -> list[Phrase]:
        """The fewest bits over all parses."""
        if self.f.code.name.startswith("fixed") and self.g.code.name.startswith("fixed"):
            return self.greedy("copy")  # of equal lengths, as many symbols a phrase as can be
        try:
            star = self.star(strategy, one_copies) if strategy != "block" else None
        except OverflowError:  # auto: too many steps to list
            star = None
        if star is None:
            return self._by_blocks()
        self.counters = {"edges": len(star.i) + self.n, **star.counters}
        star, cost = self.worth(star)
        return self.path(star, self.literal, cost)

    @cached_property
    def spelled(self) -> np.ndarray:
        """The bits of the symbols before each position as literals."""
        return np.concatenate(([0], np.cumsum(self.literal)))

    def worth(self, star: Star) -> tuple[Star, np.ndarray]:
        """The copies in order of start that cost no more than their symbols as literals, which no best path takes instead, and their costs."""
        cost = self.f(star.dist) + self.g(star.length)
        keep = np.flatnonzero(cost <= self.spelled[star.i + star.length] - self.spelled[star.i])
        if len(keep) > 1 and (star.i[1:] < star.i[:-1]).any():
            keep = keep[np.argsort(star.i[keep], kind="stable")]
        return Star(star.i[keep], star.length[keep], star.dist[keep]), cost[keep]

    def fewest_bits(self) -> int:
        """The bits of the optimum, without its phrases."""
        if self.f.code.name.startswith("fixed") and self.g.code.name.startswith("fixed"):
            return self.total(self.optimal())
        path = shortest.Path(self.n, self.literal)
        try:
            path.add(0, self.n, *self.worth(self.star("auto")))
        except OverflowError:
            path = self._path_by_blocks()
        return path.best[self.n]

    def _by_blocks(self) -> list[Phrase]:
        """The same by steps that are made block by block and dropped when the path has passed them."""
        path, own = self._path_by_blocks(), self.syms.tolist()
        return [(i, n, "copy", d, -1, None) if d else (i, 1, "literal", 0, own[i], None) for i, n, d in path.steps()]

    def _path_by_blocks(self) -> shortest.Path:
        if not (self.f.code.monotone and self.g.code.monotone):
            raise NotMonotone(f"{self.f.code.name}, {self.g.code.name}: only the full graph is optimal for such codes")
        path, self.counters, edges = shortest.Path(self.n, self.literal), {}, self.n
        for a, b, i, length, dist in blocks.stream(self.syms, self.f.code, self.window, self.counters, self.suffixes if self.n > 1 else None):
            star = stars.split_lengths(Star(i, length, dist), self.f, self.g)
            edges += len(star.i)
            path.add(a, b, *self.worth(star))
        self.counters = {"edges": edges, **self.counters}
        return path

    def _longest(self):
        """Lengths of the longest earlier matches, and a way to their nearest sources."""
        if self.n < 2:
            return [0] * self.n, lambda at, length: []
        if self.maximal is not None:  # the longest copy of each position and its right-most source are among the maximal ones
            star = self.maximal
            last = np.flatnonzero(np.concatenate((star.i[1:] != star.i[:-1], [True]))) if len(star.i) else np.zeros(0, np.int64)
            most, far = np.zeros(self.n, np.int64), np.zeros(self.n, np.int64)
            most[star.i[last]], far[star.i[last]] = star.length[last], star.dist[last]

            def nearest(at, length):
                at, length = np.array(at, np.int64), np.array(length, np.int64)
                out, cut = far[at], np.flatnonzero(length != most[at])
                if len(cut):  # shorter ones may have a nearer source
                    out[cut] = self.suffixes.nearest(at[cut].tolist(), length[cut].tolist())
                return out.tolist()

            return most.tolist(), nearest
        own = self.suffixes
        if self.window is None or self.window >= self.n:
            return own.longest().tolist(), own.nearest
        length = np.zeros(self.n, np.int64)
        for a in range(0, self.n, max(self.window, blocks.SPAN)):
            every = np.arange(a, min(self.n, a + max(self.window, blocks.SPAN)))
            every = every[every > 0]
            length[every] = blocks.one_pass(own, 1, self.window, a, int(every[-1]) + 1, every)[0] if len(every) else 0
        return length.tolist(), own.nearest  # the right-most source is in the window if any is

    def _walk(self, take, triple: bool = False) -> list[Phrase]:
        """A parse from left to right: ``take`` gives the length to copy at a position, 0 for a literal."""
        length, nearest = self._longest()
        own, steps, i = self.syms.tolist(), [], 0
        while i < self.n:
            n = min(length[i], self.n - 1 - i) if triple else take(length, i)
            steps.append((i, n))
            i += n + 1 if triple else max(1, n)
        copies = [(i, n) for i, n in steps if n]
        dist = dict(zip((i for i, _ in copies), nearest(*zip(*copies, strict=True)) if copies else (), strict=True))
        if triple:
            return [(i, n + 1, "triple", dist.get(i, 0), -1, own[i + n]) for i, n in steps]
        return [(i, n, "copy", dist[i], -1, None) if n else (i, 1, "literal", 0, own[i], None) for i, n in steps]

    def fewest(self) -> list[Phrase]:
        """The fewest phrases: copies may end anywhere, so the longest match at each step, also of one symbol."""
        return self.greedy("copy")

    def length_only(self) -> list[Phrase]:
        """The path that is best if only the lengths' codewords counted: the longest match, and its cuts at the ends of plateaus."""
        length, nearest = self._longest()
        none = np.zeros(0, np.int64)
        at = np.flatnonzero(np.array(length, np.int64))
        whole = Star(at, np.array(length, np.int64)[at], np.ones(len(at), np.int64)) if len(at) else Star(none, none, none)
        star = stars.split_lengths(whole, self.f, self.g) if self.g.lo is not None else self.star("full")
        order = np.lexsort((star.length, star.i))
        star = Star(star.i[order], star.length[order], star.dist[order])
        made = self.path(star, self.g(self.syms), self.g(star.length))
        copies = [(p[0], p[1]) for p in made if p[2] == "copy"]
        dist = dict(zip((i for i, _ in copies), nearest(*zip(*copies, strict=True)) if copies else (), strict=True))
        return [(i, n, kind, dist[i] if kind == "copy" else d, s, c) for i, n, kind, d, s, c in made]

    def greedy(self, one: str = "literal") -> list[Phrase]:
        """The longest match at each step, else a literal; a match of one symbol is a literal unless ``one`` is copy."""
        least = 1 if one == "copy" else 2
        return self._walk(lambda length, i: length[i] if length[i] >= least else 0)

    def greedy_triple(self) -> list[Phrase]:
        """The longest match and the symbol after it; the last match is shortened so that a symbol is left."""
        return self._walk(None, triple=True)

    def lazy(self) -> list[Phrase]:
        """Greedy, but a literal first where the next position has a longer match."""
        return self._walk(lambda length, i: length[i] if length[i] >= 2 and not (i + 1 < self.n and length[i + 1] > length[i]) else 0)

    def ratio_greedy(self) -> list[Phrase]:
        """At each step the edge of the fewest bits a symbol; of equal ones the longer."""
        star = self.edges()
        cost = (self.f(star.dist) + self.g(star.length)).tolist()
        ptr = np.searchsorted(star.i, np.arange(self.n + 1)).tolist()
        length, dist, own, lits, out, i = star.length.tolist(), star.dist.tolist(), self.syms.tolist(), self.literal.tolist(), [], 0
        while i < self.n:
            best = min([(lits[i], -1, -1), *((cost[e] / length[e], -length[e], e) for e in range(ptr[i], ptr[i + 1]))])
            e = best[2]
            out.append((i, length[e], "copy", dist[e], -1, None) if e >= 0 else (i, 1, "literal", 0, own[i], None))
            i += out[-1][1]
        return out

    def iterated_entropy(self, rounds: int = 3) -> list[Phrase]:
        """A heuristic without a guarantee: parse, fit codes to the parse, parse again under them; the best parse under
        the codes that this sequence was given is kept."""
        star = stars.full(self.syms, self.window)
        best = current = self.path(star, self.literal, self.f(star.dist) + self.g(star.length))
        for _ in range(rounds):
            dists, lengths = {}, {}
            for _, n, kind, d, s, _ in current:
                dists[d] = dists.get(d, 0) + 1
                v = n if kind == "copy" else s
                lengths[v] = lengths.get(v, 0) + 1
            f, g = Pricer(static_entropy(dists), max(1, self.n)), Pricer(static_entropy(lengths), int(max(self.n, self.syms.max(initial=0), 1)))
            current = self.path(star, f(np.zeros(self.n, np.int64)) + g(self.syms), f(star.dist) + g(star.length))
            best = min(best, current, key=self.total)
        return best

    def static(self, phrases: dict[tuple[int, ...], int], longest: int) -> list[Phrase]:
        """The fewest bits with a fixed dictionary: a phrase costs f(id), with ids from 1; a symbol f(0) + g(symbol)."""
        own, at = self.syms.tolist(), []
        for i in range(self.n):
            for n in range(1, min(longest, self.n - i) + 1):
                if (k := phrases.get(tuple(own[i : i + n]))) is not None:
                    at.append((i, n, k))
        i, n, k = np.array(at, np.int64).reshape(-1, 3).T
        return [(a, b, "entry" if c == "copy" else c, d, s, x) for a, b, c, d, s, x in self.path(Star(i, n, k), self.literal, Pricer(self.f.code, int(k.max(initial=1)))(k))]

    def prices(self, parse: list[Phrase]) -> np.ndarray:
        """The bits of each phrase."""
        if not parse:
            return np.zeros(0, np.int64)
        _, n, kind, d, s, c = zip(*parse, strict=True)
        n, d = np.array(n, np.int64), np.array(d, np.int64)
        if "entry" in kind:
            entry = np.array([k == "entry" for k in kind])
            out = Pricer(self.f.code, int(d.max(initial=1)))(np.where(entry, d, 0))
            return out + np.where(entry, 0, self.g(np.maximum(np.array(s, np.int64), 0)))
        if "triple" in kind:
            return self.f(d) + self.g(n - 1) + self.g(np.array(c, np.int64))
        return self.f(d) + self.g(np.where(d > 0, n, np.array(s, np.int64)))

    def total(self, parse: list[Phrase]) -> int:
        return int(self.prices(parse).sum())


def block_totals(every: list[np.ndarray], f: Code, g: Code, window: int | None = None) -> list[tuple[int, int]]:
    """(bits, phrases) of the block-wise optimum of each sequence. Short ones go together, with symbols of their own, so that no copy
    leaves its sequence and the passes over blocks do not begin anew for each; the paths of many go on together, position by position."""
    if not (f.monotone and g.monotone):
        raise NotMonotone(f"{f.name}, {g.name}: only the full graph is optimal for such codes")
    groups, size = [[]], 0
    for k in sorted(range(len(every)), key=lambda k: len(every[k])):
        if groups[-1] and size + len(every[k]) > blocks.SPAN:
            groups.append([])
            size = 0
        groups[-1].append(k)
        size += len(every[k])
    out, rack, held = [(0, 0)] * len(every), [], 0
    for own in groups:
        lengths = np.array([len(every[k]) for k in own], np.int64)
        if not lengths.sum():
            continue
        s = Sequence(np.concatenate([every[k] for k in own]), f, g, min(window or int(lengths.max()), int(lengths.max())))
        if s.n > blocks.SPAN:  # one long sequence: its steps are dropped behind the path
            path = shortest.Path(s.n, s.literal)
            for a, b, i, length, dist in blocks.stream(s.syms, f, s.window):
                path.add(a, b, *s.worth(stars.split_lengths(Star(i, length, dist), s.f, s.g)))
            out[own[0]] = path.best[s.n], len(path.steps())
            continue
        starts = np.cumsum(lengths) - lengths
        distinct, symbols = np.unique(s.syms, return_inverse=True)
        doc = np.repeat(np.arange(len(own)), lengths)
        apart = np.unique(doc * len(distinct) + symbols, return_inverse=True)[1].astype(np.int64)
        literal, parts = s.literal.copy(), []
        for _, _, i, length, dist in blocks.stream(apart, f, s.window):  # all of it is one block
            star, cost = s.worth(stars.split_lengths(Star(i, length, dist), s.f, s.g))
            one = star.length == 1
            literal[star.i[one]] = np.minimum(literal[star.i[one]], cost[one])
            more = np.flatnonzero(~one)
            parts.append((star.i.take(more), star.length.take(more), cost.take(more)))
        parts.append((np.arange(s.n), np.ones(s.n, np.int64), literal))
        i, length, cost = (np.concatenate(x) for x in zip(*parts, strict=True))
        rack.append((own, doc.take(i), i - starts.take(doc.take(i)), length, cost))
        held += s.n
        if held >= RACK:
            _counted_paths(rack, every, out)
            rack, held = [], 0
    if rack:
        _counted_paths(rack, every, out)
    return out


def _counted_paths(rack: list, every: list[np.ndarray], out: list[tuple[int, int]]) -> None:
    """Puts the bits and phrases of the best paths of some groups where they belong."""
    keys = [k for own, *_ in rack for k in own]
    first = np.cumsum([0] + [len(own) for own, *_ in rack])
    number = np.concatenate([x[1] + first[r] for r, x in enumerate(rack)])
    edges = [np.concatenate([x[c] for x in rack]) for c in (2, 3, 4)]
    for k, got in zip(keys, shortest.together_counted(np.array([len(every[k]) for k in keys], np.int64), number, *edges), strict=True):
        out[k] = got


def fewest_totals(every: list[np.ndarray], f: Code, g: Code) -> list[int]:
    """The bits of the optimum of each sequence, without phrases."""
    return gap_totals(every, f, g, False)[0]


def gap_totals(every: list[np.ndarray], f: Code, g: Code, walk: bool = True) -> tuple[list[int], list[int]]:
    """The bits of the optimum and, unless not to ``walk``, of the greedy parse of each sequence, without phrases.

    Sequences go together, each with groups of its own, so that no copy leaves its sequence: copies are listed by length for all of
    a pack of at most PACK symbols, maximal ones are told as the next length comes, and the paths of all packs go on position by
    position together. Sequences of more copies than are listed, or longer than a pack, are parsed alone.
    """
    optimal, greedy, alone = [0] * len(every), [0] * len(every), []
    packs, size = [[]], 0
    for k in sorted(range(len(every)), key=lambda k: -len(every[k])):
        if len(every[k]) > PACK:
            alone.append((k, True))
            continue
        if size + len(every[k]) > PACK:
            packs.append([])
            size = 0
        packs[-1].append(k)
        size += len(every[k])
    rack, held = [], 0
    for own in packs:
        own = [k for k in own if len(every[k])]
        if own:
            over, walked, edges = _pack([every[k] for k in own], f, g, walk)
            alone += [(k, False) for k, x in zip(own, over, strict=True) if x]
            for k, bits in zip(own, walked, strict=True):
                greedy[k] = bits
            rack.append((own, over, edges))
            held += sum(len(every[k]) for k in own)
        if held >= RACK:
            _paths(rack, every, optimal)
            rack, held = [], 0
    if rack:
        _paths(rack, every, optimal)
    for k, listed in alone:
        s = Sequence(every[k], f, g)
        optimal[k] = s.fewest_bits() if listed else s._path_by_blocks().best[s.n]
        greedy[k] = s.total(s.greedy()) if walk else 0
    return optimal, greedy


def _paths(rack: list, every: list[np.ndarray], optimal: list[int]) -> None:
    """Puts the bits of the best paths of some packs, longest sequences first, where they belong."""
    own = [k for keys, over, _ in rack for k, x in zip(keys, over, strict=True) if not x]
    counts = np.cumsum([0] + [len(over) - int(over.sum()) for _, over, _ in rack])
    edges = [np.concatenate([np.concatenate(parts) + (counts[r] if c == 0 else 0) for r, (_, _, edges) in enumerate(rack) if (parts := edges[c])] or [np.zeros(0, np.int64)]) for c in range(4)]
    for k, bits in zip(own, shortest.together(np.array([len(every[k]) for k in own], np.int64), *edges), strict=True):
        optimal[k] = bits


def _pack(every: list[np.ndarray], f: Code, g: Code, walk: bool) -> tuple[np.ndarray, list[int], tuple[list, list, list, list]]:
    """Of sequences that are not empty: which have too many copies to list; the bits of the greedy parses, if wanted; and of all others, numbered in
    order, the edges (number, start, length, bits) of the optimum, literals among them."""
    lengths = np.array([len(x) for x in every], np.int64)
    syms, n = np.concatenate(every), int(lengths.sum())
    most = int(lengths.max())
    price_f, price_g = Pricer(f, most), Pricer(g, int(max(most, syms.max())))
    ends = np.cumsum(lengths)
    starts, doc = ends - lengths, np.repeat(np.arange(len(every)), lengths)
    end, local = ends[doc], np.arange(n) - starts[doc]
    literal = price_f.bits[0] + price_g(syms)
    spelled = np.concatenate(([0], np.cumsum(literal)))
    allowed, total, over = LEVEL_FACTOR * lengths * (len(price_f.lo) + len(price_g.lo)), np.zeros(len(every), np.int64), np.zeros(len(every), bool)
    far = price_f(np.arange(most + 1))
    by_length = price_g(np.arange(most + 1))
    symbols = np.unique(syms, return_inverse=True)[1].astype(np.uint16)
    step, longest, worth = literal.copy(), np.ones(n, np.int64), []  # step: the bits of greedy steps
    before, ahead = None, np.full(n, 1 << 62)  # the copies of the last length; the bits of the distance of the next longer one

    def keep(rises: bool) -> None:
        pos, bits, length = before
        if not rises:
            own = np.flatnonzero(ahead.take(pos) > bits)
            pos, bits = pos.take(own), bits.take(own)
        cost = bits + by_length[length]
        own = np.flatnonzero(cost <= spelled.take(pos + length) - spelled.take(pos))
        worth.append((pos.take(own), length, cost.take(own)))

    at, length = np.arange(n), 1
    number = np.unique(doc * (int(symbols.max()) + 1) + symbols, return_inverse=True)[1]
    number = number.astype(np.uint16)
    order = np.argsort(number, kind="stable")
    while len(at):
        at, number, symbol = at.take(order), number.take(order), None if length == 1 else symbol.take(order)
        same = number[1:] == number[:-1]
        if symbol is not None:
            same &= symbol[1:] == symbol[:-1]
        near = np.flatnonzero(same) + 1
        pos = at.take(near)
        total += np.bincount(doc.take(pos), minlength=len(every))
        over |= total > allowed
        bits = far.take(pos - at.take(near - 1))
        if before is not None:
            ahead[pos] = bits
            keep(bool(by_length[length] > by_length[length - 1]))
            ahead[before[0]] = 1 << 62
        before = pos, bits, length
        if walk and length > 1:
            longest[pos] = length
            step[pos] = bits + by_length[length]
        # those of a group of two or more that can be longer
        whole = np.concatenate(([False], same, [False]))
        alive = np.flatnonzero(whole[1:] | whole[:-1])
        at, number = at.take(alive), np.cumsum(~whole[:-1]).take(alive)
        if over.any():
            end[over[doc]] = 0
        alive = np.flatnonzero(at + length < end.take(at))
        at, number = at.take(alive), (number.take(alive) - 1).astype(np.uint16)
        symbol = symbols.take(at + length)
        order = np.argsort(symbol, kind="stable")
        order = order.take(np.argsort(number.take(order), kind="stable"))
        length += 1
    if before is not None:
        keep(True)
    after, i, steps = (np.arange(n) + longest).tolist(), 0, []
    while walk and i < n:
        steps.append(i)
        i = after[i]
    walked = np.bincount(doc[steps], step[steps], len(every)).astype(np.int64)  # exact below 2^53
    renumbered = np.cumsum(~over) - 1
    edges = [], [], [], []
    fine = np.flatnonzero(~over[doc])
    for pos, length, cost in worth:
        if length == 1:
            literal[pos] = np.minimum(literal[pos], cost)
            continue
        own = ~over[doc[pos]]
        pos, cost = pos[own], cost[own]
        for to, x in zip(edges, (renumbered[doc[pos]], local[pos], np.full(len(pos), length), cost), strict=True):
            to.append(x)
    for to, x in zip(edges, (renumbered[doc[fine]], local[fine], np.ones(len(fine), np.int64), literal[fine]), strict=True):
        to.append(x)
    return over, walked.tolist(), edges


PARSERS: dict[str, Callable[[Sequence], list[Phrase]]] = {
    "optimal": Sequence.optimal,
    "optimal_full": lambda s: s.optimal("full"),
    "optimal_pruned": lambda s: s.optimal("pruned"),
    "optimal_block": lambda s: s.optimal("block"),
    "greedy": Sequence.greedy,
    "greedy_copy": lambda s: s.greedy("copy"),
    "greedy_triple": Sequence.greedy_triple,
    "fewest": Sequence.fewest,
    "length_only": Sequence.length_only,
    "lazy": Sequence.lazy,
    "ratio_greedy": Sequence.ratio_greedy,
    "iterated_entropy": Sequence.iterated_entropy,
}


def run(seq: DataFrame, parsers: tuple[str, ...], f: Code | str = "gamma", g: Code | str = "gamma", window: int | None = None, dictionary: list[tuple[int, ...]] | None = None, phrases: bool = True, work: bool = True) -> DataFrame:
    """Parses of every sequence by each of the named parsers, which share one read of it. A null sequence counts as empty.

    Without ``phrases`` and ``work`` (the counters of the steps made) optimal_block takes short sequences together. ``dictionary`` is for the parser ``static``: at most as large as what is broadcast with a closure.
    """
    f, g = code(f).name, code(g).name
    known = {p: k for k, p in enumerate(dictionary or (), 1)}
    longest = max(map(len, known), default=0)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own_f, own_g = code(f), code(g)
        for batch in batches:
            out = _Rows(f, g)
            if parsers == ("optimal_block",) and not phrases and not work:
                every = [x.values.to_numpy(zero_copy_only=False).astype(np.int64) if x.is_valid else np.zeros(0, np.int64) for x in batch["syms"]]
                for key, x, (bits, number) in zip(batch["seq_id"].to_pylist(), every, block_totals(every, own_f, own_g, window), strict=True):
                    out.total(key, len(x), "optimal_block", bits, {}, number)
                yield out.batch()
                continue
            for key, syms in zip(batch["seq_id"].to_pylist(), batch["syms"], strict=True):
                syms = syms.values.to_numpy(zero_copy_only=False).astype(np.int64) if syms.is_valid else np.zeros(0, np.int64)
                s = Sequence(syms, own_f, own_g, window)
                for name in parsers:
                    s.counters = {}
                    parse = s.static(known, longest) if name == "static" else PARSERS[name](s)
                    out.add(key, len(syms), name, parse, s.prices(parse), s.counters, phrases)
                if out.size >= BATCH:
                    yield out.batch()
                    out = _Rows(f, g)
            yield out.batch()

    return seq.select(F.col("seq_id").cast("long").alias("seq_id"), "syms").mapInArrow(kernel, PARSE)


class _Rows:
    """Parses gathered into columns."""

    def __init__(self, f: str, g: str):
        self.names, self.size, self.rows, self.ends, self.parts, self.bits = (f, g), 0, [], [0], [], []

    def add(self, key, n: int, name: str, parse: list[Phrase], bits: np.ndarray, counters: dict, phrases: bool) -> None:
        if phrases:
            self.parts += parse
            self.bits.append(bits)
        self.total(key, n, name, int(bits.sum()), counters, len(parse))

    def total(self, key, n: int, name: str, bits: int, counters: dict, phrases: int) -> None:
        self.rows.append((key, n, name, bits, [*counters.items(), ("phrases", phrases)]))
        self.ends.append(len(self.parts))
        self.size += 64 + n

    def batch(self) -> pa.RecordBatch:
        key, n, name, bits, counters = zip(*self.rows, strict=True) if self.rows else [()] * 5
        start, size, kind, dist, sym, after = zip(*self.parts, strict=True) if self.parts else [()] * 6
        sym = np.array(sym, np.int64)
        flat = [pa.array(np.array(start, np.int32) + np.int32(1)), pa.array(size, pa.int32()), pa.array(kind, pa.string()), pa.array(dist, pa.int32()), pa.array(sym.astype(np.int32), mask=sym < 0), pa.array(after, pa.int32()), pa.array(np.concatenate([*self.bits, np.zeros(0, np.int64)]))]
        lists = pa.ListArray.from_arrays(pa.array(self.ends, pa.int32()), pa.StructArray.from_arrays(flat, fields=list(_PHRASE)))
        k = len(self.rows)
        return pa.RecordBatch.from_arrays([pa.array(key, pa.int64()), pa.array(n, pa.int32()), pa.array(name, pa.string()), *(pa.array([x] * k, pa.string()) for x in self.names), pa.array(bits, pa.int64()), lists, pa.array(counters, pa.map_(pa.string(), pa.int64()))], ["seq_id", "n", "parser", "f", "g", "bits", "phrases", "counters"])


def optimal(seq: DataFrame, f: Code | str = "gamma", g: Code | str = "gamma", one_copies: bool = True, window: int | None = None, stars: str = "auto") -> DataFrame:
    """The bit-optimal parse. ``stars`` names how steps are found: auto, full, pruned or block."""
    if not one_copies:
        raise ValueError("without copies of one symbol only the full graph is optimal; use Sequence.optimal('full', False)")
    return run(seq, ({"auto": "optimal", "full": "optimal_full", "pruned": "optimal_pruned", "block": "optimal_block"}[stars],), f, g, window)


def greedy(seq: DataFrame, f: Code | str = "gamma", g: Code | str = "gamma", window: int | None = None, one: str = "literal") -> DataFrame:
    return run(seq, ("greedy" if one == "literal" else "greedy_copy",), f, g, window)


def compare(seq: DataFrame, f: Code | str = "gamma", g: Code | str = "gamma", parsers: tuple[str, ...] = ("greedy", "optimal"), window: int | None = None) -> DataFrame:
    """(seq_id, n, a column of bits for each parser): several parsers over one read, without phrases."""
    own_f, own_g = code(f), code(g)
    if set(parsers) == {"optimal", "greedy"} and window is None and own_f.monotone and own_g.monotone and own_f.limit is None and own_g.limit is None:
        f, g = own_f.name, own_g.name

        def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                ends, lo = np.cumsum([len(x) if x.is_valid else 0 for x in batch["syms"]]), 0
                while lo < batch.num_rows:  # not all of a batch is unpacked at once
                    hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + 4 * RACK, "right")))
                    part = batch.slice(lo, hi - lo)
                    every = [x.values.to_numpy(zero_copy_only=False).astype(np.int64) if x.is_valid else np.zeros(0, np.int64) for x in part["syms"]]
                    bits = dict(zip(("optimal", "greedy"), gap_totals(every, code(f), code(g)), strict=True))
                    yield pa.RecordBatch.from_arrays([part["seq_id"], pa.array([len(x) for x in every], pa.int32()), *(pa.array(bits[p], pa.int64()) for p in parsers)], ["seq_id", "n", *parsers])
                    lo = hi

        made = seq.select(F.col("seq_id").cast("long").alias("seq_id"), "syms").mapInArrow(kernel, f"seq_id long, n int, {', '.join(f'{p} long' for p in parsers)}")
        return made.groupBy("seq_id", "n").agg(*(F.first(p).alias(p) for p in parsers))
    return run(seq, parsers, f, g, window, phrases=False).groupBy("seq_id", "n").pivot("parser", list(parsers)).agg(F.first("bits"))


def explode(parse: DataFrame) -> DataFrame:
    """A row for each phrase, numbered from 1."""
    return parse.select("seq_id", "parser", F.posexplode("phrases").alias("k", "p")).select("seq_id", "parser", (F.col("k") + 1).alias("k"), "p.*")
