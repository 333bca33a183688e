"""The phrase dictionary that grows with the parse: greedy, flexible and bit-optimal parsing.

The dictionary of every method is that of the greedy scan; a phrase may be used from the position on
at which the scan has completed it, so a decoder that repeats the scan knows it. Ids start at 1.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bitparse.functions.codes import Code, code
from bitparse.operators import shortest
from bitparse.operators.stars import Pricer, Star

METHODS = ("greedy", "flexible", "optimal", "optimal_full", "fewest", "greedy_walk")


class Scan:
    """The greedy scan of a sequence: phrases (start, length, id of the longest known prefix, next symbol) and the tree."""

    def __init__(self, syms: list[int]):
        self.syms, self.n = syms, len(syms)
        self.child: dict[tuple[int, int], int] = {}
        self.available = [0]
        self.phrases, i = [], 0
        while i < self.n:
            node, j = 0, i
            while j < self.n and (node, syms[j]) in self.child:
                node, j = self.child[node, syms[j]], j + 1
            if j < self.n:
                self.child[node, syms[j]] = len(self.available)
                self.available.append(j + 1)
                self.phrases.append((i, j + 1 - i, node, syms[j]))
                i = j + 1
            else:  # the last phrase may repeat a known one
                self.phrases.append((i, j - i, node, None))
                i = j

    def entries(self, i: int) -> list[tuple[int, int]]:
        """(length, id) of the phrases that are known at i and stand there."""
        out, node, j = [], 0, i
        while j < self.n and (node := self.child.get((node, self.syms[j]), 0)) and self.available[node] <= i:
            j += 1
            out.append((j - i, node))
        return out

    def star(self) -> Star:
        """The same of all positions: they go down the tree together, a symbol at a time."""
        none = np.zeros(0, np.int64)
        if not self.child:
            return Star(none, none, none)
        distinct, syms = np.unique(np.array(self.syms, np.int64), return_inverse=True)
        sigma = len(distinct)
        node, symbol = np.array(list(self.child), np.int64).T
        keys = node * sigma + np.searchsorted(distinct, symbol)
        order = np.argsort(keys)
        keys, below = keys[order], np.fromiter(self.child.values(), np.int64, len(keys))[order]
        since, at, node, depth, parts = np.array(self.available, np.int64), np.arange(self.n), np.zeros(self.n, np.int64), 0, []
        while len(at):
            key = node * sigma + syms[at + depth]
            found = np.minimum(np.searchsorted(keys, key), len(keys) - 1)
            node = below[found]
            known = np.flatnonzero((keys[found] == key) & (since[node] <= at))
            at, node, depth = at[known], node[known], depth + 1
            parts.append((at, np.full(len(at), depth), node))
            inside = np.flatnonzero(at + depth < self.n)
            at, node = at[inside], node[inside]
        i, length, entry = (np.concatenate(x) for x in zip(*parts, strict=True))
        order = np.argsort(i, kind="stable")
        return Star(i[order], length[order], entry[order])


def prune_left(star: Star, cost: np.ndarray) -> Star:
    """For every end, of the steps from left to right those that are cheaper than all before: what a prefix-complete
    dictionary needs."""
    order = np.lexsort((star.i, star.i + star.length))
    end, c = (star.i + star.length)[order], cost[order]
    # later ends count as cheaper than all before, so that each begins anew
    c = c - end * (int(c.max(initial=0)) - int(c.min(initial=0)) + 1)
    keep = np.ones(len(order), bool)
    keep[1:] = c[1:] < np.minimum.accumulate(c)[:-1]
    own = np.sort(order[keep])
    return Star(star.i[own], star.length[own], star.dist[own])


def parse(syms: list[int], method: str, f: Code, g: Code) -> list[tuple[int, int, int, int | None, int]]:
    """(start, length, id, symbol, bits). Greedy writes f(id) and g(next symbol); the others f(id), or f(0) and g(symbol)."""
    scan = Scan(syms)
    if method == "greedy":
        return [(i, n, k, c, f.bits(k) + (g.bits(c) if c is not None else 0)) for i, n, k, c in scan.phrases]
    if method in ("flexible", "greedy_walk"):
        reach = [max([1, *(n for n, _ in scan.entries(i))]) for i in range(scan.n)]
        out, i = [], 0
        while i < scan.n:
            n = reach[i]
            if method == "flexible" and i + n < scan.n:
                n = max(range(1, n + 1), key=lambda m: (i + m + reach[i + m] if i + m < scan.n else i + m, m))
            k = dict(scan.entries(i)).get(n, 0)
            out.append((i, n, k, None if k else syms[i], f.bits(k) + (0 if k else g.bits(syms[i]))))
            i += n
        return out
    star, most = scan.star(), max(len(scan.available), 2)
    price = Pricer(f, most)
    literal = f.bits(0) + Pricer(g, max([*syms, 1]))(np.array(syms, np.int64)) if syms else np.zeros(0, np.int64)
    cost = price(star.dist)
    if method == "optimal":
        star = prune_left(star, cost)
        cost = price(star.dist)
        spelled = np.concatenate(([0], np.cumsum(literal)))
        keep = cost <= spelled[star.i + star.length] - spelled[star.i]  # dearer ones no best path takes
        star, cost = Star(star.i[keep], star.length[keep], star.dist[keep]), cost[keep]
    weights = (np.ones(scan.n, np.int64), np.ones(len(star.i), np.int64)) if method == "fewest" else (literal, cost)
    _, start, edge = shortest.relax(scan.n, weights[0], star, weights[1])
    return [(i, j - i, int(star.dist[e]), None, int(cost[e])) if e >= 0 else (i, 1, 0, syms[i], int(literal[i])) for i, j, e in shortest.backtrace(scan.n, start, edge)]


def expand(phrases: list[tuple[int, int | None]], pairs: bool) -> list[int]:
    """The symbols again, from (id, symbol) alone: ``pairs`` for the greedy form, else the walk's, which repeats the scan."""
    if pairs:
        known, out = [[]], []
        for k, c in phrases:
            own = known[k] + ([c] if c is not None else [])
            known.append(own)
            out += own
        return out
    out: list[int] = []
    for k, c in phrases:
        if k:
            scan, at = Scan(out), k
            back = {v: key for key, v in scan.child.items()}
            own = []
            while at:
                at, s = back[at]
                own.append(s)
            out += own[::-1]
        else:
            out.append(c)
    return out


def run(seq: DataFrame, methods: tuple[str, ...] = ("greedy",), f: Code | str = "gamma", g: Code | str = "gamma", detail: bool = True) -> DataFrame:
    """(seq_id, n, method, phrases, bits, parse) of every sequence by each method; without ``detail`` no parse."""
    f, g = code(f).name, code(g).name
    names = ["seq_id", "n", "method", "phrases", "bits"] + ["parse"] * detail
    kind = pa.struct([("start", pa.int32()), ("len", pa.int32()), ("id", pa.int32()), ("sym", pa.int32()), ("bits", pa.int64())])

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own_f, own_g = code(f), code(g)
        for batch in batches:
            for key, x in zip(batch["seq_id"].to_pylist(), batch["syms"], strict=True):
                syms = x.values.to_numpy(zero_copy_only=False).tolist() if x.is_valid else []
                made = [parse(syms, m, own_f, own_g) for m in methods]
                m = len(methods)
                columns = [pa.array([key] * m, pa.int64()), pa.array([len(syms)] * m, pa.int32()), pa.array(methods), pa.array([len(p) for p in made], pa.int64()), pa.array([sum(x[-1] for x in p) for p in made], pa.int64())]
                if detail:
                    columns.append(pa.array([[{"start": i + 1, "len": n, "id": e, "sym": c, "bits": b} for i, n, e, c, b in p] for p in made], pa.list_(kind)))
                yield pa.RecordBatch.from_arrays(columns, names)

    return seq.select(F.col("seq_id").cast("long").alias("seq_id"), F.col("syms").cast("array<bigint>").alias("syms")).mapInArrow(kernel, "seq_id long, n int, method string, phrases long, bits long" + ", parse array<struct<start:int,len:int,id:int,sym:int,bits:bigint>>" * detail)
