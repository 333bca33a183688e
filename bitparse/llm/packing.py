"""Packing of documents into windows by non-negative least squares.

A document of n tokens gives n // window whole windows and a remainder. Combinations of at most
three remainders that fill a window exactly are enumerated: all pairs, and triples of two frequent
lengths with the third that is missing. Non-negative least squares, by coordinate descent, finds
how often each is used so that the histogram of remainders is met best; the repeats are rounded.
Remainders left over are packed greedily, one after another, cut where a window is full; the
last window is cut into sequences of powers of two. So nothing is padded, and only leftovers are cut.

The plan depends on the histogram of remainders alone, which has a row for each length under the
window. Ranks within a length come from groups of about GROUP rows, so no length, however frequent,
has to be in one task.

Defined results: a null or empty text has its end id alone; repeated rows are packed each by
itself; no rows give no pieces.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from bitparse.llm import tokens
from bitparse.llm.common import store, table

WINDOW, FREQUENT, SWEEPS, GROUP = 2048, 96, 40, 500
PIECES = "start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


def combinations(hist: np.ndarray, window: int = WINDOW) -> list[tuple[int, ...]]:
    """Combinations of two or three present lengths that fill a window."""
    out = {(a, window - a) for a in range(1, window // 2 + 1) if hist[a] and hist[window - a]}
    often = [int(k) for k in np.argsort(-hist, kind="stable")[:FREQUENT] if hist[k]]
    for i, a in enumerate(often):
        for b in often[i:]:
            c = window - a - b
            if c > 0 and hist[c]:
                out.add(tuple(sorted((a, b, c))))
    return sorted(out)


def repeats(hist: np.ndarray, combos: list[tuple[int, ...]], sweeps: int = SWEEPS) -> np.ndarray:
    """Least-squares repeat counts, not negative, rounded and kept within the histogram."""
    left, x = hist.astype(float).copy(), np.zeros(len(combos))
    columns = [[(b, c.count(b)) for b in sorted(set(c))] for c in combos]
    norms = [sum(m * m for _, m in col) for col in columns]
    for _ in range(sweeps):
        moved = 0.0
        for j, col in enumerate(columns):
            step = max(-x[j], sum(m * left[b] for b, m in col) / norms[j])
            if step:
                x[j] += step
                moved = max(moved, abs(step))
                for b, m in col:
                    left[b] -= m * step
        if moved < 0.25:
            break
    have, out = hist.astype(np.int64).copy(), np.zeros(len(combos), np.int64)
    # rounded down first; then the largest fractions take what they can still have
    for most, order in ((np.floor(x), np.argsort(-x, kind="stable")), (np.full(len(x), np.inf), np.argsort(np.floor(x) - x, kind="stable"))):
        for j in order:
            n = int(min([most[j], *(int(have[b]) // m for b, m in columns[j])]))
            out[j] += n
            for b, m in columns[j]:
                have[b] -= m * n
    return out


@dataclass
class Plan:
    """Where the document of each remainder and rank goes; its size is bounded by the window."""

    window: int
    key: np.ndarray  # remainder << 40 | first rank, ascending: slots of combinations
    sequence: np.ndarray  # of the slot's first rank
    offset: np.ndarray
    planned: np.ndarray  # ranks of each remainder that combinations take
    position: np.ndarray  # of each remainder's first leftover, in the run of leftovers
    first: int  # sequence of the first leftover
    total: int  # tokens left over
    whole: int  # sequence of the first whole window

    @property
    def tail(self) -> list[int]:
        """Ends of the last sequences, all powers of two long, in the run of leftovers."""
        at, ends = self.total - self.total % self.window, []
        for k in range(self.window.bit_length() - 1, -1, -1):
            if self.total % self.window >> k & 1:
                at += 1 << k
                ends.append(at)
        return ends

    def place(self, remainder: int, rank: int) -> list[tuple[int, int, int]]:
        """(sequence, offset, length) of the pieces of a remainder."""
        if rank < self.planned[remainder]:
            k = int(np.searchsorted(self.key, (remainder << 40) + rank, "right")) - 1
            return [(int(self.sequence[k]) + rank - (int(self.key[k]) & ((1 << 40) - 1)), int(self.offset[k]), remainder)]
        at, out = int(self.position[remainder]) + (rank - int(self.planned[remainder])) * remainder, []
        stop, full = at + remainder, self.total - self.total % self.window
        while at < stop:
            if at < full:
                sequence, begin, end = at // self.window, at - at % self.window, at - at % self.window + self.window
            else:
                k = next(k for k, e in enumerate(self.tail) if e > at)
                sequence, begin, end = full // self.window + k, ([full] + self.tail)[k], self.tail[k]
            out.append((self.first + sequence, at - begin, min(end, stop) - at))
            at += out[-1][2]
        return out


def plan(hist: np.ndarray, window: int = WINDOW) -> Plan:
    """hist: the number of documents by remainder, 0 to window - 1."""
    hist = hist.copy()
    hist[0] = 0
    combos = combinations(hist, window)
    slots, planned, sequence = [], np.zeros(window, np.int64), 0
    for combo, n in zip(combos, repeats(hist, combos).tolist(), strict=True):
        at = 0
        for length in combo if n else ():
            slots.append(((length << 40) + int(planned[length]), sequence, at))
            planned[length] += n
            at += length
        sequence += n
    slots.sort()
    size = (hist - planned) * np.arange(window)
    position = np.cumsum(size) - size
    total = int(size.sum())
    made = Plan(window, np.array([s[0] for s in slots], np.int64), np.array([s[1] for s in slots], np.int64), np.array([s[2] for s in slots], np.int64), planned, position, sequence, total, 0)
    made.whole = sequence + total // window + len(made.tail)
    return made


def pack(ids: DataFrame, keep: tuple[str, ...] = ("doc_id",), window: int = WINDOW) -> DataFrame:
    """Pieces of stored rows (kept columns, rid, ids, n): the kept columns and PIECES. rid is unique."""
    spark = ids.sparkSession
    sized = ids.withColumn("r", (F.col("n") % window).cast("int")).withColumn("w", F.expr(f"n div {window}"))
    rows = sized.groupBy("r").agg(F.count("*").alias("c"), F.sum("w").alias("w")).collect()  # at most a row for each length
    hist, wholes = np.zeros(window, np.int64), np.zeros(window, np.int64)
    for x in rows:
        hist[x["r"]], wholes[x["r"]] = x["c"], x["w"]
    made = plan(hist, window)
    whole_base = made.whole + np.cumsum(wholes) - wholes
    groups = spark.createDataFrame([(k, int(-(-hist[k] // GROUP)), int(whole_base[k])) for k in range(window) if hist[k]], "r int, groups int, base long")
    dealt = sized.join(F.broadcast(groups), "r").withColumn("g", F.pmod(F.xxhash64("rid"), F.col("groups")).cast("int"))
    own = dealt.groupBy("r", "g").agg(F.count("*").alias("c"), F.sum("w").alias("gw"))
    before = Window.partitionBy("r").orderBy("g").rowsBetween(Window.unboundedPreceding, -1)
    offsets = own.select("r", "g", F.coalesce(F.sum("c").over(before), F.lit(0)).alias("rank0"), F.coalesce(F.sum("gw").over(before), F.lit(0)).alias("whole0"))
    inside = Window.partitionBy("r", "g").orderBy("rid")
    ranked = dealt.select(*keep, "r", "g", "ids", "n", "base", (F.row_number().over(inside) - 1).alias("rank"), F.coalesce(F.sum("w").over(inside.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("w"))
    placed = ranked.join(offsets, ["r", "g"]).select(*keep, "r", "ids", "n", (F.col("rank") + F.col("rank0")).alias("rank"), (F.col("base") + F.col("whole0") + F.col("w")).alias("whole"))
    shared = spark.sparkContext.broadcast(made)
    schema = T.StructType([*ids.select(*keep).schema, *T.StructType.fromDDL(PIECES)])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at, out = [], []
            columns = (batch[k].to_pylist() for k in ("r", "rank", "whole", "ids"))
            for k, (r, rank, whole, raw) in enumerate(zip(*columns, strict=True)):
                own = np.frombuffer(raw, np.uint16)
                pieces = [(whole + j, 0, window) for j in range(len(own) // window)] + (shared.value.place(r, rank) if r else [])
                start = 0
                for sequence, offset, length in pieces:
                    at.append(k)
                    out.append((start, length, tokens.crc(own[start : start + length]), len(own), sequence, offset))
                    start += length
            made = np.array(out, np.int64).reshape(-1, 6)
            taken = batch.select(list(keep)).take(pa.array(at, pa.int64()))
            yield pa.RecordBatch.from_arrays([*taken.columns, *(pa.array(made[:, j]) for j in range(6))], schema.names)

    return placed.mapInArrow(run, schema)


def pack_documents(docs: DataFrame, path: str | None = None, window: int = WINDOW, hold: bool = True) -> DataFrame:
    """Pieces of documents (doc_id, text): doc_id and PIECES."""
    own = docs.select("doc_id", "text", F.monotonically_increasing_id().alias("rid"))
    return pack(store(tokens.tokenize(own, path, keep=("doc_id", "rid"), hold=hold), "ids"), window=window)


def op4_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(table(spark, sf_dir, "documents"))
