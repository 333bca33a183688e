"""Shortest paths over the graph of parsing steps, in order of position; and the same as expressions."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bitparse.operators.stars import Star


def relax(n: int, literal: np.ndarray, star: Star, cost: np.ndarray) -> tuple[list[int], list[int], list[int]]:
    """Best cost of each position, and the start and edge (-1 for a literal) of the step that reaches it.

    Ties keep the step found first: of equal costs the one that starts earliest.
    """
    far = 1 << 62
    best, start, edge = [far] * (n + 1), [0] * (n + 1), [-1] * (n + 1)
    best[0] = 0
    ptr = np.searchsorted(star.i, np.arange(n + 1)).tolist()
    ends, costs, lits = (star.i + star.length).tolist(), cost.tolist(), literal.tolist()
    at = ptr[0] if n else 0
    for i in range(n):
        here = best[i]
        c = here + lits[i]
        if c < best[i + 1]:
            best[i + 1], start[i + 1], edge[i + 1] = c, i, -1
        stop = ptr[i + 1]
        while at < stop:
            j = ends[at]
            c = here + costs[at]
            if c < best[j]:
                best[j], start[j], edge[j] = c, i, at
            at += 1
    return best, start, edge


def together(sizes: np.ndarray, number: np.ndarray, start: np.ndarray, length: np.ndarray, cost: np.ndarray, few: int = 8) -> list[int]:
    """The costs of the best paths of several sequences (sizes: their lengths) over edges of which no two of a sequence have start and
    end in common. All sequences go on by one position at a time; when only ``few`` are left they go on edge by edge."""
    order = np.argsort(-sizes, kind="stable")
    rank, cells = np.empty(len(sizes), np.int64), np.concatenate(([0], np.cumsum(sizes[order] + 1)))
    rank[order] = np.arange(len(sizes))
    base = cells[:-1][rank]
    most = int(sizes.max(initial=0))
    by = np.argsort(start.astype(np.uint16 if most <= 1 << 16 else np.int64), kind="stable")
    source = (base[number] + start)[by]
    target, cost = source + length[by], cost[by]
    ptr = np.concatenate(([0], np.cumsum(np.bincount(start, minlength=most)))).tolist()
    best = np.full(int(cells[-1]), 1 << 62)
    best[cells[:-1]] = 0
    lone = int(sizes[order[few]]) if len(sizes) > few else 0  # from here on at most few sequences are left
    for i in range(lone):
        part = slice(ptr[i], ptr[i + 1])
        to = target[part]
        best[to] = np.minimum(best.take(to), best.take(source[part]) + cost[part])
    if lone < most:
        front = int(cells[min(few, len(sizes))])
        own = best[:front].tolist()
        for a, b, c in zip(source[ptr[lone] :].tolist(), target[ptr[lone] :].tolist(), cost[ptr[lone] :].tolist(), strict=True):
            c += own[a]
            if c < own[b]:
                own[b] = c
        best[:front] = own
    return best[base + sizes].tolist()


def together_counted(sizes: np.ndarray, number: np.ndarray, start: np.ndarray, length: np.ndarray, cost: np.ndarray, few: int = 8) -> list[tuple[int, int]]:
    """The same with the numbers of steps of the best paths; of equal costs the step that starts earliest counts, as in ``Path``."""
    order = np.argsort(-sizes, kind="stable")
    rank, cells = np.empty(len(sizes), np.int64), np.concatenate(([0], np.cumsum(sizes[order] + 1)))
    rank[order] = np.arange(len(sizes))
    base = cells[:-1][rank]
    most = int(sizes.max(initial=0))
    by = np.argsort(start.astype(np.uint16) if most <= 1 << 16 else start, kind="stable")
    source = (base.take(number) + start).take(by)
    target, cost = source + length.take(by), cost.take(by)
    ptr = np.concatenate(([0], np.cumsum(np.bincount(start, minlength=most)))).tolist()
    best, steps = np.full(int(cells[-1]), 1 << 62), np.zeros(int(cells[-1]), np.int32)
    best[cells[:-1]] = 0
    lone = int(sizes[order[few]]) if len(sizes) > few else 0  # from here on at most few sequences are left
    for i in range(lone):
        part = slice(ptr[i], ptr[i + 1])
        to, begin = target[part], source[part]
        c = best.take(begin) + cost[part]
        less = np.flatnonzero(c < best.take(to))
        to = to.take(less)
        best[to] = c.take(less)
        steps[to] = steps.take(begin.take(less)) + 1
    if lone < most:
        front = int(cells[min(few, len(sizes))])
        own, made = best[:front].tolist(), steps[:front].tolist()
        for a, b, c in zip(source[ptr[lone] :].tolist(), target[ptr[lone] :].tolist(), cost[ptr[lone] :].tolist(), strict=True):
            c += own[a]
            if c < own[b]:
                own[b], made[b] = c, made[a] + 1
        best[:front], steps[:front] = own, made
    return list(zip(best[base + sizes].tolist(), steps[base + sizes].tolist(), strict=True))


class Path:
    """The same for steps that come range by range and are not kept: costs, and of each position the step that reaches it."""

    def __init__(self, n: int, literal: np.ndarray):
        self.best, self.start, self.dist = [1 << 62] * (n + 1), [0] * (n + 1), [0] * (n + 1)
        self.best[0] = 0
        self.literal = literal.tolist()

    def add(self, a: int, b: int, star: Star, cost: np.ndarray) -> None:
        """The copies that start at a..b-1, in order of start."""
        best, begin, far, lits = self.best, self.start, self.dist, self.literal
        ptr = np.searchsorted(star.i, np.arange(a, b + 1)).tolist()
        ends, costs, dists = (star.i + star.length).tolist(), cost.tolist(), star.dist.tolist()
        at = 0
        for i in range(a, b):
            here = best[i]
            c = here + lits[i]
            if c < best[i + 1]:
                best[i + 1], begin[i + 1], far[i + 1] = c, i, 0
            stop = ptr[i - a + 1]
            while at < stop:
                j = ends[at]
                c = here + costs[at]
                if c < best[j]:
                    best[j], begin[j], far[j] = c, i, dists[at]
                at += 1

    def steps(self) -> list[tuple[int, int, int]]:
        """(start, length, distance) of the steps of the best path, in order; distance 0 for a literal."""
        out, j = [], len(self.best) - 1
        while j:
            out.append((self.start[j], j - self.start[j], self.dist[j]))
            j = self.start[j]
        return out[::-1]


def backtrace(n: int, start: list[int], edge: list[int]) -> list[tuple[int, int, int]]:
    """(start, end, edge) of the steps of the best path, in order."""
    out, j = [], n
    while j:
        out.append((start[j], j, edge[j]))
        j = start[j]
    return out[::-1]


def adjacency(priced: DataFrame) -> DataFrame:
    """(seq_id, back): for each end position, in order, the steps (i, bits) that lead there."""
    steps = priced.groupBy("seq_id", "j").agg(F.collect_list(F.struct(F.col("i").cast("int").alias("i"), F.col("bits").cast("long").alias("bits"))).alias("steps"))
    return steps.groupBy("seq_id").agg(F.array_sort(F.collect_list(F.struct("j", "steps"))).alias("a")).select("seq_id", F.transform("a", lambda x: x["steps"]).alias("back"))


def fold(back: Column) -> Column:
    """The costs of positions 1 to n + 1, from each position's backward star; inside Catalyst, for short sequences."""
    return F.aggregate(back, F.array(F.lit(0).cast("long")), lambda costs, steps: F.concat(costs, F.array(F.array_min(F.transform(steps, lambda e: F.element_at(costs, e["i"]) + e["bits"])))))


def fold_costs(priced: DataFrame) -> DataFrame:
    """(seq_id, bits): the optimum of each sequence whose priced edges these are."""
    return adjacency(priced).select("seq_id", F.element_at(fold(F.col("back")), -1).alias("bits"))


def recursive_sql(edges: str) -> str:
    """The same as recursive SQL over a relation of edges (seq_id, i, j, bits): one round a position."""
    return f"""
    with recursive back as (select seq_id, j, array_agg(named_struct('i', i, 'bits', bits)) as steps from {edges} group by seq_id, j),
    walk(seq_id, j, costs) as (
      select distinct seq_id, cast(1 as int), array(cast(0 as bigint)) from back
      union all
      select w.seq_id, w.j + 1, array_append(w.costs, array_min(transform(b.steps, e -> element_at(w.costs, e.i) + e.bits)))
      from walk w join back b on b.seq_id = w.seq_id and b.j = w.j + 1)
    select seq_id, max_by(element_at(costs, -1), j) as bits from walk group by seq_id"""
