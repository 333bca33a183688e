"""Copies made as the shortest path needs them: the longest match in each plateau of distances.

For distances lo..hi a pass takes blocks of positions as long as the plateau is wide. The sources of a
block are the window of its first position and what lies beyond it up to the last one's; of a
position all those of the first half that are not too far, and of the second that are not too
near, may be copied. Suffixes of block and sources stand in suffix order, where the longest match of a position
is the nearest allowed source on either side: the nearest place with a value over a threshold, found
over links to the next greater value. All blocks of a pass within SPAN positions go together.

Passes are interleaved: blocks shorter than SPAN are made when the path reaches them, longer ones when
it reaches their first position. What was used is dropped, so of each pass no more steps are held than its
block or SPAN has positions, together a few times n.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

from bitparse.functions.codes import plateaus
from bitparse.operators import repeats

NEAR, SPAN, _TOP, _SMALL = 32, 1 << 14, 1 << 62, 1 << 17


class Suffixes:
    """Suffix order, common prefixes, and their range minima in linear space."""

    def __init__(self, syms: np.ndarray):
        self.syms, self.n = syms, len(syms)
        self.rank, self.common = repeats.ranks_and_lcp(syms)
        self.order = np.empty(self.n, np.int64)
        self.order[self.rank] = np.arange(self.n)
        if self.n <= _SMALL:  # least values over all ranges of 2^k, without blocks of 16
            self.flat = repeats.minima(self.common)
            return
        self.flat = None
        padded = np.concatenate([self.common, np.full(-self.n % 16, self.n, np.int64)]).reshape(-1, 16)
        self.ahead = np.minimum.accumulate(padded, axis=1).ravel()
        self.behind = np.minimum.accumulate(padded[:, ::-1], axis=1)[:, ::-1].ravel()
        self.tables = [padded.min(axis=1)] if self.n else []
        while self.tables and 1 << len(self.tables) <= len(self.tables[0]):
            step = 1 << (len(self.tables) - 1)
            self.tables.append(np.minimum(self.tables[-1][:-step], self.tables[-1][step:]))

    def least(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """The least common prefix over ranks a..b."""
        if self.flat is not None:
            level = np.frexp((b - a + 1).astype(np.float64))[1] - 1
            row = level * np.int64(self.n)
            return np.minimum(self.flat[row + a], self.flat[row + b + 1 - (1 << level)]).astype(np.int64)
        low, high = a >> 4, b >> 4
        out = np.minimum(self.behind[a], self.ahead[b])
        inside = np.flatnonzero(low == high)
        if len(inside):
            at, last, least = a[inside].copy(), b[inside], self.common[a[inside]]
            for _ in range(15):
                at = np.minimum(at + 1, last)
                least = np.minimum(least, self.common[at])
            out[inside] = least
        wide = np.flatnonzero(high - low > 1)
        if len(wide):
            first, last = low[wide] + 1, high[wide] - 1
            level = np.frexp((last - first + 1).astype(np.float64))[1] - 1
            for k in np.unique(level).tolist():
                own = level == k
                out[wide[own]] = np.minimum(out[wide[own]], np.minimum(self.tables[k][first[own]], self.tables[k][last[own] - (1 << k) + 1]))
        return out

    def match(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """The common prefix of the suffixes at a and b, which differ."""
        a, b = self.rank[a], self.rank[b]
        return self.least(np.minimum(a, b) + 1, np.maximum(a, b))

    def longest(self) -> np.ndarray:
        """Of each position the length of its longest earlier match: with the nearest smaller position on either side in suffix order."""
        out = np.zeros(self.n, np.int64)
        for order in (self.order, self.order[::-1]):
            values = np.concatenate(([_TOP], self.n - order))
            to = back(values)[1:]
            has = np.flatnonzero(to > 0)
            out[order[has]] = np.maximum(out[order[has]], self.match(order[has], order[to[has] - 1]))
        return out

    def nearest(self, at: list[int], length: list[int]) -> list[int]:
        """The distance to the right-most earlier source of each match."""
        order, common, rank, n = self.order, self.common, self.rank, self.n
        out, seen = [], {}
        for h, size in zip(at, length, strict=True):
            if size <= 8:
                if size not in seen:  # places of equal short substrings, by one pass over suffix order
                    group = np.cumsum(common < size)
                    by = np.lexsort((order, group))
                    gap = np.zeros(n, np.int64)
                    places, own = order[by], group[by]
                    gap[places[1:]] = np.where(own[1:] == own[:-1], places[1:] - places[:-1], 0)
                    seen[size] = gap
                out.append(int(seen[size][h]))
                continue
            lo = hi = int(rank[h])
            step = 16
            while lo and common[lo] >= size:
                cut = np.flatnonzero(common[max(0, lo - step) + 1 : lo + 1][::-1] < size)
                if len(cut):
                    lo -= int(cut[0])
                    break
                lo, step = max(0, lo - step), step * 2
            step = 16
            while hi + 1 < n and common[hi + 1] >= size:
                cut = np.flatnonzero(common[hi + 1 : hi + 1 + step] < size)
                if len(cut):
                    hi += int(cut[0])
                    break
                hi, step = min(n - 1, hi + step), step * 2
            own = order[lo : hi + 1]
            out.append(h - int(own[own < h].max()))
        return out


def back(values: np.ndarray) -> np.ndarray:
    """Of each place the nearest one before it with a greater value. Places of value _TOP point to themselves; place 0 is one."""
    to = np.arange(-1, len(values) - 1)
    top = values >= _TOP
    to[top] = np.flatnonzero(top)
    todo = np.flatnonzero((values[to] <= values) & ~top)
    while len(todo):
        to[todo] = to[to[todo]]
        todo = todo[values[to[todo]] <= values[todo]]
    return to


def climb(values: np.ndarray, to: np.ndarray, at: np.ndarray, least: np.ndarray) -> np.ndarray:
    """From each place the first one along the links whose value is not under the threshold."""
    at = at.copy()
    todo = np.flatnonzero(values[at] < least)
    for _ in range(8):
        at[todo] = to[at[todo]]
        todo = todo[values[at[todo]] < least[todo]]
        if not len(todo):
            return at
    jumps = [to]  # a long chain: links of powers of two
    while (values[jumps[-1]] < _TOP).any():
        jumps.append(jumps[-1][jumps[-1]])
    for far in reversed(jumps):
        here = todo[values[far[at[todo]]] < least[todo]]
        at[here] = far[at[here]]
    at[todo] = to[at[todo]]
    return at


def one_pass(own: Suffixes, lo: int, hi: int, a: int, b: int, queries: np.ndarray) -> tuple[np.ndarray, np.ndarray, int]:
    """Of each query position in a..b-1 the longest match at distances lo..hi and its source; and how many suffixes were visited.

    The windows of consecutive blocks follow one another, and what lies beyond a block's window is in the next block's. So each
    source stands once, by window and rank, and a position looks into two windows.
    """
    n, width = own.n, hi - lo + 1
    length, source = np.zeros(len(queries), np.int64), np.zeros(len(queries), np.int64)
    begin, end = max(a - hi, 0), b - lo
    if end <= begin or not len(queries):
        return length, source, 0
    places = np.arange(begin, end)
    window = (places - (a - hi)) // width
    windows = int(window[-1]) + 2
    key = np.concatenate([window * (n + 2) + own.rank[begin:end] + 1, np.arange(windows + 1) * (n + 2)])
    order = np.argsort(key, kind="stable")
    key, home, rank = key[order], (queries - a) // width, own.rank[queries]
    position = np.concatenate([places, np.full(windows + 1, _TOP)])[order]
    edge = position == _TOP
    for beyond, least in ((0, np.maximum(queries - hi, 0)), (1, n - queries + lo)):
        values = np.where(edge, _TOP, n - position) if beyond else position
        spot = np.searchsorted(key, (home + beyond) * (n + 2) + rank + 1)
        for forward in (True, False):
            own_values, at = (values, spot - 1) if forward else (values[::-1], len(order) - 1 - spot)
            found = climb(own_values, back(own_values), at, least)
            got = position[found if forward else len(order) - 1 - found]
            ok = np.flatnonzero((got < _TOP) & (got != queries))
            size = own.match(queries[ok], got[ok])
            better = size > length[ok]
            length[ok[better]], source[ok[better]] = size[better], got[ok[better]]
    return length, source, len(order) + len(queries)


def rising_pass(own: Suffixes, lo: int, hi: int, a: int, b: int, queries: np.ndarray) -> tuple[np.ndarray, np.ndarray, int]:
    """The same where a match is longer than all at less than lo; elsewhere lengths may be any that are not longer, or 0.

    So a source of the second window may be too near, as then it is no news. Where a plateau is at most twice as far as it begins,
    nothing behind the query is in that window, and its neighbours in suffix order are the next rows: no links are followed.
    """
    n, width = own.n, hi - lo + 1
    begin, end = max(a - hi, 0), b - lo
    if hi > 2 * lo or end <= begin or not len(queries):
        return one_pass(own, lo, hi, a, b, queries)
    length, source = np.zeros(len(queries), np.int64), np.zeros(len(queries), np.int64)
    places = own.order.compress((own.order >= begin) & (own.order < end))
    window = (places - (a - hi)) // width
    windows = (end - 1 - (a - hi)) // width + 2
    by = np.argsort(window.astype(np.uint16) if windows <= 1 << 16 else window, kind="stable")
    places, window = places.take(by), window.take(by)
    edges = np.arange(windows + 1)
    firsts = np.searchsorted(window, edges) + edges
    at = np.arange(len(places)) + window + 1  # an edge before each window
    position, key = np.full(len(places) + windows + 1, _TOP), np.empty(len(places) + windows + 1, np.int64)
    position[at], key[at] = places, window * (n + 2) + own.rank.take(places) + 1
    key[firsts] = edges * (n + 2)
    home = (queries - a) // width
    wanted = home * (n + 2) + own.rank.take(queries) + 1

    def better(rows: np.ndarray, got: np.ndarray) -> None:
        ok = np.flatnonzero(got < _TOP)
        rows, got = rows.take(ok), got.take(ok)
        size = own.match(queries.take(rows), got)
        ok = np.flatnonzero(size > length.take(rows))
        rows = rows.take(ok)
        length[rows], source[rows] = size.take(ok), got.take(ok)

    every, spot, least = np.arange(len(queries)), np.searchsorted(key, wanted), queries - hi
    for forward in (True, False):
        values, at = (position, spot - 1) if forward else (position[::-1], len(position) - 1 - spot)
        found = values.take(at)
        far = np.flatnonzero(found < least)
        if len(far):
            values = np.ascontiguousarray(values)
            found[far] = values.take(climb(values, back(values), at.take(far), least.take(far)))
        better(every, found)
    beyond = np.flatnonzero(queries > a + home * width)  # else the first window has all of the plateau
    spot, own_place = np.searchsorted(key, wanted.take(beyond) + (n + 2)), queries.take(beyond)
    better(beyond, position.take(spot - 1))
    better(beyond, position.take(spot + (position.take(spot) == own_place)))
    length[source > queries - lo] = 0
    return length, source, len(position) + len(queries)


def near(syms: np.ndarray, lo: int, hi: int) -> tuple[np.ndarray, np.ndarray]:
    """Of every position the longest match at distances lo..hi, which are few, and its source: by runs of equal symbols."""
    n = len(syms)
    length, source = np.zeros(n, np.int32), np.zeros(n, np.int32)
    for d in range(lo, min(hi, n - 1) + 1):
        stop = np.where(syms[d:] == syms[:-d], n - d, np.arange(n - d))
        run = np.minimum.accumulate(stop[::-1])[::-1] - np.arange(n - d)
        better = np.flatnonzero(run > length[d:])
        length[better + d], source[better + d] = run[better], better
    return length, source


def stream(syms: np.ndarray, code, window: int | None = None, counters: dict | None = None, own: Suffixes | None = None) -> Iterator[tuple[int, int, np.ndarray, np.ndarray, np.ndarray]]:
    """(a, b, start, length, distance) for consecutive ranges a..b-1 of positions: of each the copies that are longer than all
    of no dearer distance, in order of distance. ``counters`` gets the visits, the steps made and the most that were held."""
    n, counts = len(syms), {"visits": 0, "emitted": 0, "live_edges": 0}
    reach = max(1, min(n, window or n))
    rows = [(lo, min(hi, reach)) for lo, hi, _ in plateaus(code, reach, 1) if lo <= reach] if n > 1 else []
    own = (own or Suffixes(syms)) if rows else None
    most = own.longest() if rows else np.zeros(n, np.int64)
    held: dict[int, tuple[int, np.ndarray, np.ndarray]] = {}  # pass: end, lengths, sources
    for a in range(0, n, SPAN):
        b = min(n, a + SPAN)
        best, parts, made = np.zeros(b - a, np.int64), [], 0
        for k, (lo, hi) in enumerate(rows):
            if hi <= NEAR:
                if k not in held:
                    held[k] = (n, *near(syms, lo, hi))
                    counts["visits"] += n
                length, source = held[k][1][a:b].astype(np.int64), held[k][2][a:b].astype(np.int64)
            elif hi - lo + 1 <= SPAN:
                want = a + np.flatnonzero(most[a:b] > best)
                found, at, visits = rising_pass(own, lo, hi, a, b, want[want >= lo])
                length, source = np.zeros(b - a, np.int64), np.zeros(b - a, np.int64)
                length[want[want >= lo] - a], source[want[want >= lo] - a] = found, at
                counts["visits"] += visits
                made += len(found)
            else:
                if k not in held or held[k][0] <= a:
                    end = min(n, a + (hi - lo + 1) // SPAN * SPAN)
                    want = a + np.flatnonzero(most[a:end])
                    want = want[want >= lo]
                    found, at, visits = rising_pass(own, lo, hi, a, end, want)
                    length, source = np.zeros(end - a, np.int32), np.zeros(end - a, np.int32)
                    length[want - a], source[want - a] = found, at
                    held[k] = (end, length, source)
                    counts["visits"] += visits
                end, length, source = held[k]
                from_end = slice(len(length) - (end - a), len(length) - (end - b))
                length, source = length[from_end].astype(np.int64), source[from_end].astype(np.int64)
            longer = np.flatnonzero(length > best)
            best[longer] = length[longer]
            parts.append((longer + a, length[longer], longer + a - source[longer]))
        counts["live_edges"] = max(counts["live_edges"], made + sum(len(x[1]) for x in held.values()))
        for k in [k for k, x in held.items() if x[0] <= b]:
            del held[k]
        start, length, dist = (np.concatenate(x) for x in zip(*parts, strict=True)) if parts else (np.zeros(0, np.int64),) * 3
        order = np.argsort(start, kind="stable")
        counts["emitted"] += len(start)
        yield a, b, start[order], length[order], dist[order]
    if counters is not None:
        counters.update(counts)
