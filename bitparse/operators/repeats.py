"""Repeats of a sequence: suffix order, common prefixes, earlier occurrences. Arrays here; relations at the end."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def _doubled(syms: np.ndarray) -> list[np.ndarray]:
    """The ranks of all suffixes by their first 1, 2, 4, ... symbols, up to where all differ; equal ones have the rank of the first.

    A round sorts only the suffixes that do not differ yet, and these stand in order of their last rank.
    """
    n, out, step = len(syms), [], 1
    order = np.argsort(syms, kind="stable")
    new = np.concatenate(([True], syms[order[1:]] != syms[order[:-1]]))
    rank = np.empty(n, np.int32)
    rank[order] = np.maximum.accumulate(np.where(new, np.arange(n), 0))
    while True:
        out.append(rank)
        at = np.flatnonzero(~(new & np.append(new[1:], True)))
        if not len(at):
            return out
        own = order[at]
        key = rank[own] * np.int64(n + 1)
        more = np.flatnonzero(own + step < n)
        key[more] += rank[own[more] + step] + np.int64(1)
        by = np.argsort(key, kind="stable")
        own, key = own[by], key[by]
        order[at], new[at] = own, np.concatenate(([True], key[1:] != key[:-1]))
        rank = rank.copy()
        rank[own] = np.maximum.accumulate(np.where(new[at], at, 0))
        step *= 2


def suffix_ranks(syms: np.ndarray) -> np.ndarray:
    """The rank of each suffix, by doubling the length that is compared."""
    return _doubled(syms)[-1].astype(np.int64) if len(syms) else np.zeros(0, np.int64)


def ranks_and_lcp(syms: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The same, and of each rank the common prefix with the rank before it, by the ranks of the doublings."""
    n = len(syms)
    if not n:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    every = _doubled(syms)
    rank = every[-1].astype(np.int64)
    order = np.empty(n, np.int64)
    order[rank] = np.arange(n)
    a, b, common = order[1:].copy(), order[:-1].copy(), np.zeros(n, np.int64)
    for k in range(len(every) - 2, -1, -1):
        inside = np.flatnonzero(np.maximum(a, b) < n)
        same = inside[every[k][a[inside]] == every[k][b[inside]]]
        common[same + 1] += 1 << k
        a[same] += 1 << k
        b[same] += 1 << k
    return rank, common


def lcp(syms: np.ndarray, rank: np.ndarray) -> np.ndarray:
    """Of each rank the common prefix with the rank before it; 0 for the first."""
    n = len(syms)
    order = np.empty(n, np.int64)
    order[rank] = np.arange(n)
    own, places, before, out, h = syms.tolist(), rank.tolist(), order.tolist(), [0] * n, 0
    for i in range(n):
        if places[i] == 0:
            h = 0
            continue
        j = before[places[i] - 1]
        while i + h < n and j + h < n and own[i + h] == own[j + h]:
            h += 1
        out[places[i]] = h
        h = max(0, h - 1)
    return np.array(out, np.int64)


def minima(values: np.ndarray) -> np.ndarray:
    """Row k: of each place the least of 2^k values from there on, as one array; n log n, for short sequences."""
    rows, step = [values.astype(np.int32)], 1
    while 2 * step <= len(values):
        more = rows[-1].copy()
        np.minimum(rows[-1][:-step], rows[-1][step:], out=more[:-step])
        rows.append(more)
        step *= 2
    return np.concatenate(rows)


def levels(syms: np.ndarray, most_edges: int | None = None, window: int | None = None) -> Iterator[tuple[int, np.ndarray, np.ndarray]] | None:
    """For each length L the positions with an earlier copy of their L symbols, and the distance to the right-most one.

    The work is the number of such pairs; positions drop out as soon as they have no partner left.
    """
    n = len(syms)
    symbols = np.unique(syms, return_inverse=True)[1].astype(np.int64)
    at, group, length, total = np.arange(n), symbols.copy(), 1, 0
    while len(at):
        order = np.argsort(group, kind="stable")  # rows of a group stand in order of position
        at, group = at[order], group[order]
        same = np.concatenate(([False], group[1:] == group[:-1]))
        gap = np.zeros(len(at), np.int64)
        gap[1:] = at[1:] - at[:-1]
        near = same if window is None else same & (gap <= window)
        if near.any():
            total += int(near.sum())
            if most_edges is not None and total > most_edges:
                raise OverflowError("more edges than allowed")
            yield length, at[near], gap[near]
        partner = same | np.concatenate((same[1:], [False]))
        alive = partner & (at + length < n)
        at = at[alive]
        number = np.cumsum(~same)[alive]
        group = number * n + symbols[at + length]
        length += 1


def longest_repeat(syms: np.ndarray) -> int:
    return int(ranks_and_lcp(syms)[1].max(initial=0))


# Relations. A sequence relation has seq_id, n and syms; sym has seq_id, i (from 1) and s.


def grams(sym: DataFrame) -> DataFrame:
    """(seq_id, i, len, gram) of every substring of the sequences: quadratic in their length, for short ones.

    The gram is the array of symbols, so no separator can be mistaken for one.
    """
    own = sym.groupBy("seq_id").agg(F.array_sort(F.collect_list(F.struct("i", "s"))).alias("a"))
    flat = own.select("seq_id", F.transform("a", lambda x: x["s"]).alias("syms"))
    start = flat.select("seq_id", "syms", F.explode(F.sequence(F.lit(1), F.size("syms"))).alias("i"))
    return start.select("seq_id", "i", F.explode(F.sequence(F.lit(1), F.size("syms") - F.col("i") + 1)).alias("len"), "syms").select("seq_id", "i", "len", F.slice("syms", F.col("i"), F.col("len")).alias("gram"))


def prev_occurrence(gram_rows: DataFrame) -> DataFrame:
    """(seq_id, i, len, dist): the distance to the right-most earlier copy of each substring that has one."""
    before = F.lag("i").over(Window.partitionBy("seq_id", "len", "gram").orderBy("i"))
    return gram_rows.select("seq_id", "i", "len", (F.col("i") - before).alias("dist")).filter("dist is not null")


def longest_prev_match(copies: DataFrame) -> DataFrame:
    """(seq_id, i, len, dist) of the longest earlier match of each position that has one."""
    return copies.groupBy("seq_id", "i").agg(F.max_by(F.struct("len", "dist"), "len").alias("m")).select("seq_id", "i", "m.len", "m.dist")


def suffix_order(seq: DataFrame) -> DataFrame:
    """(seq_id, i, rank, lcp) of all suffixes, ranks from 1, lcp with the rank before."""
    suffix = seq.filter("n > 0").select("seq_id", "syms", F.explode(F.sequence(F.lit(1), F.col("n"))).alias("i"))
    suffix = suffix.select("seq_id", "i", F.slice("syms", F.col("i"), F.size("syms")).alias("suffix"))
    own = Window.partitionBy("seq_id").orderBy("suffix")
    placed = suffix.select("seq_id", "i", "suffix", F.row_number().over(own).alias("rank"), F.lag("suffix").over(own).alias("before"))
    first = F.array_position(F.zip_with("suffix", "before", lambda a, b: ~F.coalesce(a == b, F.lit(False))), True)
    lcp_col = F.when(F.col("before").isNull(), 0).otherwise(first - 1)
    return placed.select("seq_id", "i", "rank", lcp_col.cast("long").alias("lcp"))
