"""Forward stars: the copies that can start at each position, whole, pruned, or generated block by block.

An edge (i, j) is a phrase of the symbols i..j-1. A copy has the distance to its right-most earlier
source and a length from 1 on; a literal has distance 0 and its symbol as second number. Positions
start at 0 in arrays and at 1 in relations.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from bitparse.functions.codes import Code, code, plateaus
from bitparse.operators import blocks, repeats


class Pricer:
    """Lengths of codewords for arrays of values."""

    def __init__(self, named: Code | str, most: int):
        self.code = code(named)
        if self.code.monotone:
            rows = plateaus(self.code, max(most, 1))
            self.lo = np.array([r[0] for r in rows], np.int64)
            self.bits = np.array([r[2] for r in rows], np.int64)
        else:
            self.lo = None
            self.every = np.array([self.code.bits(x) for x in range(most + 1)], np.int64)
        self.limit = self.code.limit

    def __call__(self, values: np.ndarray) -> np.ndarray:
        if self.limit is not None and len(values) and int(values.max()) > self.limit:
            raise ValueError(f"{self.code.name} has no codeword for {int(values.max())}")
        if self.lo is None:
            return self.every[values]
        return self.bits[np.searchsorted(self.lo, values, "right") - 1]


@dataclass
class Star:
    """Copies in order of start and length."""

    i: np.ndarray
    length: np.ndarray
    dist: np.ndarray
    counters: dict = field(default_factory=dict)


def _ordered(i, length, dist, **counters) -> Star:
    order = np.lexsort((length, i))
    return Star(i[order], length[order], dist[order], counters)


def full(syms: np.ndarray, window: int | None = None, most_edges: int | None = None) -> Star:
    """Every copy edge."""
    parts = [(at, np.full(len(at), n), gap) for n, at, gap in repeats.levels(syms, most_edges, window)]
    if not parts:
        none = np.zeros(0, np.int64)
        return Star(none, none, none)
    return _ordered(*(np.concatenate(x) for x in zip(*parts, strict=True)))


def prune(star: Star, f: Pricer, g: Pricer, rule: str = "right") -> Star:
    """The maximal edges: those whose next longer edge costs more in the field that the rule names; the longest stays."""
    if not len(star.i):
        return star
    last = np.concatenate((star.i[1:] != star.i[:-1], [True]))
    df, dg = (np.concatenate((c[1:] - c[:-1], [1])) for c in (f(star.dist), g(star.length)))
    keep = last | {"d": df > 0, "l": dg > 0, "right": (df > 0) | (dg > 0), "cost": df + dg > 0}[rule]
    return Star(star.i[keep], star.length[keep], star.dist[keep], dict(star.counters))


def block(syms: np.ndarray, f: Pricer, window: int | None = None) -> Star:
    """All copies of the longest match in each plateau of distances, gathered from the passes over blocks."""
    counters: dict = {}
    parts = [x[2:] for x in blocks.stream(np.asarray(syms, np.int64), f.code, window, counters)]
    if not parts:
        none = np.zeros(0, np.int64)
        return Star(none, none, none, counters)
    return _ordered(*(np.concatenate(x) for x in zip(*parts, strict=True)), **counters)


def split_lengths(star: Star, f: Pricer, g: Pricer) -> Star:
    """Cuts between the ends of a position's copies at every plateau of lengths: all maximal edges.

    A copy counts if it is longer than every copy of the position that is no dearer in distance.
    """
    if not len(star.i):
        return star
    i, length, dist, far = star.i, star.length, star.dist, f(star.dist)
    same = i[1:] == i[:-1]
    if (i[1:] < i[:-1]).any() or (same & ((length[1:] <= length[:-1]) | (far[1:] <= far[:-1]))).any():
        order = np.lexsort((dist, -length, far, i))
        i, length, dist = i[order], length[order], dist[order]
        wide = int(length.max()) + 1
        most = np.maximum.accumulate(i * wide + length)
        before = np.maximum(np.concatenate(([-1], most[:-1])) - i * wide, 0)
        rising = length > before
        i, length, dist, before = i[rising], length[rising], dist[rising], before[rising]
    else:  # in order, as from the passes over blocks: longer copies are dearer
        before = np.concatenate(([0], np.where(same, length[:-1], 0)))
    ends = np.append(g.lo[1:] - 1, 1 << 62)
    first, last = np.searchsorted(ends, before, "right"), np.searchsorted(ends, length, "left")
    each = last - first + 1
    row = np.repeat(np.arange(len(i)), each)
    k = np.arange(len(row)) - np.repeat(np.cumsum(each) - each, each) + first[row]
    cut = np.minimum(ends[np.minimum(k, len(ends) - 1)], length[row])
    return Star(i[row], cut, dist[row], dict(star.counters))


def maxlcp_bruteforce(syms: np.ndarray, rows: list[tuple[int, int, int]]) -> list[tuple[int, int, int, int]]:
    """(position, plateau, nearest best source, its match) by comparing with every source of the window."""
    own, out = syms.tolist(), []
    for h in range(len(own)):
        for k, (lo, hi, _) in enumerate(rows):
            best = (0, -1)
            for s in range(max(0, h - hi), h - lo + 1):
                n = 0
                while h + n < len(own) and own[s + n] == own[h + n]:
                    n += 1
                best = max(best, (n, s))
            if best[0]:
                out.append((h, k, best[1], best[0]))
    return out


# Relations.


def edges(copies: DataFrame, sym: DataFrame, f: Code | str, g: Code | str) -> DataFrame:
    """All priced edges (seq_id, i, j, kind, dist, len, sym, bits) from prev_occurrence's rows and the symbols."""
    f, g = code(f), code(g)
    copy = copies.select("seq_id", "i", (F.col("i") + F.col("len")).alias("j"), F.lit("copy").alias("kind"), "dist", "len", F.lit(None).cast("int").alias("sym"), (f.column(F.col("dist")) + g.column(F.col("len"))).cast("long").alias("bits"))
    literal = sym.select("seq_id", "i", (F.col("i") + 1).alias("j"), F.lit("literal").alias("kind"), F.lit(0).alias("dist"), F.lit(1).alias("len"), F.col("s").cast("int").alias("sym"), (F.lit(f.bits(0)) + g.column(F.col("s"))).cast("long").alias("bits"))
    return copy.unionByName(literal)


def prune_edges(priced: DataFrame, f: Code | str, g: Code | str, rule: str = "right") -> DataFrame:
    """The maximal edges of a relation; literals stay. ``left`` is the mirrored rule for prefix-complete dictionaries."""
    copies, literals = priced.filter("kind = 'copy'"), priced.filter("kind <> 'copy'")
    if rule == "left":
        cheaper = F.min("bits").over(Window.partitionBy("seq_id", "j").orderBy("i").rowsBetween(Window.unboundedPreceding, -1))
        return copies.withColumn("__b", cheaper).filter("__b is null or bits < __b").drop("__b").unionByName(literals)
    f, g = code(f), code(g)
    after = Window.partitionBy("seq_id", "i").orderBy("j")
    by_d = F.lead(f.column(F.col("dist"))).over(after) > f.column(F.col("dist"))
    by_l = F.lead(g.column(F.col("len"))).over(after) > g.column(F.col("len"))
    by_cost = F.lead("bits").over(after) > F.col("bits")
    keep = {"d": by_d, "l": by_l, "right": by_d | by_l, "cost": by_cost}[rule]
    return copies.withColumn("__k", F.coalesce(keep, F.lit(True))).filter("__k").drop("__k").unionByName(literals)
