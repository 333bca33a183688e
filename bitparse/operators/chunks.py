"""Long sequences in chunks: with forced cuts at the seams (bounded loss), exact by carrying the frontier, or on line."""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bitparse.functions.codes import Code, code
from bitparse.operators import blocks, parsers, repeats, shortest, stars
from bitparse.operators.stars import Pricer, Star


def split(seq: DataFrame, chunk: int, history: int, ahead: int = 0) -> DataFrame:
    """(seq_id, n, c, held, own, syms): chunk c with ``held`` symbols before it, ``own`` of its own and up to ``ahead`` after."""
    size = F.size("syms")
    each = seq.filter(size > 0).select("seq_id", "n", "syms", F.explode(F.sequence(F.lit(0), F.floor((size - 1) / chunk).cast("int"))).alias("c"))
    first = F.col("c") * chunk
    held = F.least(first, F.lit(history))
    own = F.least(F.lit(chunk), size - first)
    return each.select("seq_id", "n", "c", held.alias("held"), own.alias("own"), F.slice("syms", first - held + 1, held + own + F.least(F.lit(ahead), size - first - own)).alias("syms"))


def _star(syms: np.ndarray, held: int, f: Pricer, g: Pricer, window: int, most: int | None = None, own: int | None = None) -> tuple[Star, np.ndarray]:
    """The pruned copies that start after the held symbols, moved to start at 0, and their costs."""
    parts = []
    for n, at, gap in repeats.levels(syms, window=window):
        if most is not None and n > most:
            break
        inside = (at >= held) & (at < held + (own if own is not None else len(syms)))
        parts.append((at[inside] - held, np.full(int(inside.sum()), n), gap[inside]))
    none = np.zeros(0, np.int64)
    star = stars._ordered(*(np.concatenate(x) for x in zip(*parts, strict=True))) if parts else Star(none, none, none)
    star = stars.prune(star, f, g)
    return star, f(star.dist) + g(star.length)


def chunk_parse(syms: np.ndarray, held: int, f: Code, g: Code, window: int) -> tuple[int, list[tuple[int, int, int]]]:
    """Bits and steps (start, length, distance) of the symbols after the held ones, by copies from at most ``window`` back."""
    n = len(syms) - held
    price_f, price_g = Pricer(f, max(window, len(syms), 1)), Pricer(g, int(max(len(syms), syms.max(initial=0), 1)))
    star, cost = _star(syms, held, price_f, price_g, window)
    literal = price_f(np.zeros(n, np.int64)) + price_g(syms[held:])
    best, start, edge = shortest.relax(n, literal, star, cost)
    return best[n], [(i, j - i, int(star.dist[e]) if e >= 0 else 0) for i, j, e in shortest.backtrace(n, start, edge)]


class Online:
    """The optimum with copies from at most ``window`` back and of at most ``most`` symbols, over symbols that come in parts.

    After each part the best paths to all positions are known that a later step may start from: the end, and the starts of
    copies that reach it. Where these paths meet, what lies before is final and given out; only the ``window``
    symbols before that place and those after it are kept, about window + most + the part.
    """

    def __init__(self, window: int, most: int, f: Code | str = "gamma", g: Code | str = "gamma", state: tuple | None = None):
        self.window, self.most, self.f, self.g = window, most, code(f), code(g)
        self.held, self.waiting, self.at = state or (np.zeros(0, np.int64), np.zeros(0, np.int64), 0)

    @property
    def state(self) -> tuple:
        return self.held, self.waiting, self.at

    def feed(self, syms: np.ndarray, last: bool = False) -> list[tuple[int, int, int, int, int]]:
        """(start from 0, length, distance, symbol or -1, bits) of the phrases that are final now; all of them with ``last``."""
        syms = np.asarray(syms, np.int64)
        own, skip = parsers.Sequence(np.concatenate([self.held, self.waiting, syms]), self.f, self.g, self.window), len(self.held)
        n = own.n - skip
        if not n:
            return []
        star = own.edges()
        inside = star.i >= skip
        star = Star(star.i[inside] - skip, np.minimum(star.length[inside], self.most), star.dist[inside])
        cost, literal = own.f(star.dist) + own.g(star.length), own.literal[skip:]
        best, start, edge = shortest.relax(n, literal, star, cost)
        open_ends = {n}
        if not last:
            reach = np.flatnonzero((star.i + star.length == n) & (star.length < self.most))
            open_ends.update(star.i[reach].tolist())
        heap = [-v for v in open_ends]
        heapq.heapify(heap)
        while len(heap) > 1:  # the paths back from all of them, the farthest first
            v = start[-heapq.heappop(heap)]
            if v not in open_ends:
                open_ends.add(v)
                heapq.heappush(heap, -v)
        done = -heap[0]
        out, j = [], done
        while j:
            i, e = start[j], edge[j]
            out.append((self.at + i, j - i, int(star.dist[e]) if e >= 0 else 0, -1 if e >= 0 else int(own.syms[skip + i]), int(cost[e] if e >= 0 else literal[i])))
            j = i
        self.held, self.waiting, self.at = own.syms[max(0, skip + done - self.window) : skip + done], own.syms[skip + done :], self.at + done
        return out[::-1]


def online(parts: DataFrame, window: int, most: int, f: Code | str = "gamma", g: Code | str = "gamma") -> DataFrame:
    """(seq_id, start from 1, len, kind, dist, sym, bits): the phrases of sequences whose symbols stand in rows (seq_id, c, syms),
    in order of c. No row or task ever holds a whole sequence; symbols are shuffled once, steps never."""
    names = code(f).name, code(g).name
    columns = ["seq_id", "start", "len", "kind", "dist", "sym", "bits"]

    def rows(key: int, found: list) -> pa.RecordBatch:
        start, size, dist, sym, bits = (np.array(x, np.int64) for x in (zip(*found, strict=True) if found else [()] * 5))
        kind = np.where(dist > 0, "copy", "literal")
        return pa.RecordBatch.from_arrays([pa.array([key] * len(found), pa.int64()), pa.array(start + 1), pa.array(size.astype(np.int32)), pa.array(kind.tolist(), pa.string()), pa.array(dist.astype(np.int32)), pa.array(sym.astype(np.int32), mask=sym < 0), pa.array(bits)], columns)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, own = None, None
        for batch in batches:
            for k, syms in zip(batch["seq_id"].to_pylist(), batch["syms"], strict=True):
                if own is None or k != key:
                    if own is not None:
                        yield rows(key, own.feed(np.zeros(0, np.int64), last=True))
                    key, own = k, Online(window, most, *names)
                if syms.is_valid:
                    yield rows(key, own.feed(syms.values.to_numpy(zero_copy_only=False)))
        if own is not None:
            yield rows(key, own.feed(np.zeros(0, np.int64), last=True))

    dealt = parts.select("seq_id", "c", "syms").repartition("seq_id").sortWithinPartitions("seq_id", "c")
    return dealt.select("seq_id", "syms").mapInArrow(run, "seq_id long, start long, len int, kind string, dist int, sym int, bits long")


def cut_bits(own: parsers.Sequence, chunk: int) -> int:
    """Bits of the optimum of the sequence in its window with a cut at each seam: no copy runs past the end of its chunk.

    By the copies of all lengths where these are listed, else by the longest ones of each plateau, made block by block.
    """
    path, monotone = shortest.Path(own.n, own.literal), own.f.code.monotone and own.g.code.monotone
    if own.listed is None:
        try:
            own.star("auto" if monotone else "full")
        except OverflowError:
            pass
    if own.listed is not None:
        keep = np.flatnonzero(own.listed.i % chunk + own.listed.length <= chunk)
        star = Star(own.listed.i[keep], own.listed.length[keep], own.listed.dist[keep])
        path.add(0, own.n, *own.worth(stars.prune(star, own.f, own.g) if monotone else star))
    else:
        for a, b, i, length, dist in blocks.stream(own.syms, own.f.code, own.window, own=own.suffixes):
            path.add(a, b, *own.worth(stars.split_lengths(Star(i, np.minimum(length, chunk - i % chunk), dist), own.f, own.g)))
    return path.best[own.n]


def seams(seq: DataFrame, chunk: int, window: int, f: Code | str = "gamma", g: Code | str = "gamma", whole: bool = False) -> DataFrame:
    """(seq_id, n, bits, seams, allowance): the windowed optimum with a cut at each seam, and by how much it may exceed
    the optimum without: the dearest step for each seam. With ``whole`` that optimum too, from the same steps."""
    f, g = code(f), code(g)
    names = f.name, g.name
    columns = ["seq_id", "n", "bits", "seams"] + ["whole"] * whole

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codes = code(names[0]), code(names[1])
        for batch in batches:
            rows = []
            for key, x in zip(batch["seq_id"].to_pylist(), batch["syms"], strict=True):
                if not x.is_valid or not len(x):
                    continue
                own = parsers.Sequence(x.values.to_numpy(zero_copy_only=False), *codes, window)
                best = own.fewest_bits() if whole else 0
                rows.append((key, own.n, cut_bits(own, chunk), (own.n - 1) // chunk, best))
            yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], pa.int32() if k == 1 else pa.int64()) for k in range(len(columns))], columns)

    own = seq.select(F.col("seq_id").cast("long").alias("seq_id"), "syms").mapInArrow(kernel, "seq_id long, n int, bits long, seams long" + ", whole long" * whole)
    dearest: Column = f.column(F.lit(window)) + g.column(F.col("n"))
    return own.select("seq_id", "n", "bits", "seams", (F.col("seams") * dearest).alias("allowance"), *(["whole"] * whole))


def exact(seq: DataFrame, chunk: int, window: int, most: int, f: Code | str = "gamma", g: Code | str = "gamma") -> DataFrame:
    """(seq_id, n, bits): the optimum with copies from at most ``window`` back and of at most ``most`` symbols. Steps are found
    chunk by chunk, in parallel; then the frontier of costs goes through each sequence's chunks in order."""
    names = code(f).name, code(g).name
    kind = "seq_id long, c int, own int, lit array<bigint>, i array<bigint>, len array<bigint>, cost array<bigint>"

    def steps(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own_f, own_g = code(names[0]), code(names[1])
        for batch in batches:
            for k in range(batch.num_rows):
                syms, held, own = np.array(batch["syms"][k].as_py(), np.int64), batch["held"][k].as_py(), batch["own"][k].as_py()
                price_f, price_g = Pricer(own_f, max(1, min(window, len(syms)))), Pricer(own_g, int(max(min(most, len(syms)), syms.max(initial=0), 1)))
                star, cost = _star(syms, held, price_f, price_g, window, most, own)
                literal = price_f(np.zeros(own, np.int64)) + price_g(syms[held : held + own])
                yield pa.RecordBatch.from_arrays([batch["seq_id"].slice(k, 1), batch["c"].slice(k, 1), pa.array([own], pa.int32()), *(pa.array([x], pa.list_(pa.int64())) for x in (literal, star.i, star.length, cost))], ["seq_id", "c", "own", "lit", "i", "len", "cost"])

    def walk(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, front, n, out = None, [0], 0, []

        def row():
            return pa.RecordBatch.from_arrays([pa.array([at], pa.int64()), pa.array([n], pa.int32()), pa.array([front[0]], pa.int64())], ["seq_id", "n", "bits"])

        for batch in batches:
            for k in range(batch.num_rows):
                key, own = batch["seq_id"][k].as_py(), batch["own"][k].as_py()
                if key != at:
                    if at is not None:
                        yield row()
                    at, front, n = key, [0], 0
                lit, i, length, cost = (batch[c][k].as_py() for c in ("lit", "i", "len", "cost"))
                reach = max(map(sum, zip(i, length, strict=True)), default=0)
                costs = front + [1 << 62] * (max(own, reach) + 1 - len(front))
                e = 0
                for p in range(own):
                    here = costs[p]
                    costs[p + 1] = min(costs[p + 1], here + lit[p])
                    while e < len(i) and i[e] == p:
                        j = p + length[e]
                        costs[j] = min(costs[j], here + cost[e])
                        e += 1
                front, n = costs[own:], n + own
        if at is not None:
            yield row()

    parts = split(seq, chunk, window, most).select("seq_id", F.col("c").cast("int").alias("c"), F.col("held").cast("int").alias("held"), F.col("own").cast("int").alias("own"), F.col("syms").cast("array<bigint>").alias("syms"))
    found = parts.mapInArrow(steps, kind)
    return found.repartition("seq_id").sortWithinPartitions("seq_id", "c").mapInArrow(walk, "seq_id long, n int, bits long")
