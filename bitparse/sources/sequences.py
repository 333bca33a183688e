"""Sequences (seq_id, n, syms) from tables, and their alphabets."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def _counted(df: DataFrame) -> DataFrame:
    return df.select("seq_id", F.size("syms").alias("n"), "syms")


def code_points(text: Column) -> Column:
    return F.transform(F.filter(F.split(text, ""), lambda c: c != ""), lambda c: F.ascii(c))


def utf8_bytes(text: Column) -> Column:
    digits = F.regexp_extract_all(F.hex(F.encode(text, "UTF-8")), F.lit("(..)"), F.lit(1))
    return F.transform(digits, lambda d: F.conv(d, 16, 10).cast("int"))


def from_text(df: DataFrame, key: str, text: str, unit: str = "codepoint") -> DataFrame:
    """A sequence of code points or of UTF-8 bytes; a null text is empty. No shuffle.

    By Arrow batches: splitting a text into an array of strings costs more than all of its parse.
    """
    if unit not in ("codepoint", "byte"):
        raise ValueError(unit)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            own = [t or "" for t in batch["text"].to_pylist()]
            lo = 0
            while lo < len(own):  # about a million characters at a time
                hi, size = lo, 0
                while hi < len(own) and (hi == lo or size + len(own[hi]) <= 1 << 20):
                    size += len(own[hi])
                    hi += 1
                raw = [t.encode("utf-32-le" if unit == "codepoint" else "utf-8", "surrogatepass") for t in own[lo:hi]]
                syms = np.frombuffer(b"".join(raw), np.int32 if unit == "codepoint" else np.uint8).astype(np.int32)
                ends = np.concatenate(([0], np.cumsum([len(r) // (4 if unit == "codepoint" else 1) for r in raw]))).astype(np.int32)
                yield pa.RecordBatch.from_arrays([batch["key"].slice(lo, hi - lo), pa.array(np.diff(ends)), pa.ListArray.from_arrays(pa.array(ends), pa.array(syms))], ["seq_id", "n", "syms"])
                lo = hi

    return df.select(F.col(key).cast("long").alias("key"), F.col(text).alias("text")).mapInArrow(run, "seq_id long, n int, syms array<int>")


def from_events(df: DataFrame, key: str, order: list[str], symbol: Column) -> DataFrame:
    """A sequence for each key, its symbols (integers) in a total order: one shuffle by key."""
    rows = F.array_sort(F.collect_list(F.struct(*order, symbol.cast("int").alias("__s"))))
    own = df.groupBy(F.col(key).cast("long").alias("seq_id")).agg(rows.alias("rows"))
    return _counted(own.select("seq_id", F.transform("rows", lambda r: r["__s"]).alias("syms")))


def from_vectors(df: DataFrame, key: str, vector: str, levels: int = 16) -> DataFrame:
    """A sequence of quantised components of vectors in -1..1; levels from 1."""
    level = lambda x: (F.least(F.lit(levels - 1), F.greatest(F.lit(0), F.floor((x.cast("double") + 1) * (levels / 2)))) + 1).cast("int")
    return _counted(df.select(F.col(key).cast("long").alias("seq_id"), F.transform(vector, level).alias("syms")))


def explode(seq: DataFrame) -> DataFrame:
    """(seq_id, i from 1, s)."""
    return seq.select("seq_id", F.posexplode("syms").alias("i", "s")).select("seq_id", (F.col("i") + 1).alias("i"), "s")


def alphabet(seq: DataFrame) -> DataFrame:
    """(symbol, rank, count): the symbols of all sequences, ranked from 1; counts are summed before the shuffle."""
    own = explode(seq).groupBy(F.col("s").alias("symbol")).agg(F.count("*").alias("count"))
    # one row a symbol: as many as there are code points or keys, not as the data
    return own.select("symbol", F.row_number().over(Window.orderBy("symbol")).cast("long").alias("rank"), "count")


def remap(seq: DataFrame, scope: str = "global") -> DataFrame:
    """Symbols as ranks from 1: over all sequences, or over each (``sequence``), which needs no shuffle."""
    if scope == "sequence":
        own = F.array_sort(F.array_distinct("syms"))
        ranks = F.map_from_arrays(own, F.sequence(F.lit(1), F.size(own)))
        mapped = F.when(F.col("n") > 0, F.transform("syms", lambda s: F.element_at(ranks, s).cast("int"))).otherwise(F.col("syms"))
        return seq.select("seq_id", "n", mapped.alias("syms"))
    ranked = alphabet(seq).select(F.col("symbol").alias("s"), F.col("rank").cast("int").alias("rank"))
    joined = explode(seq).join(ranked, "s")
    back = joined.groupBy("seq_id").agg(F.array_sort(F.collect_list(F.struct("i", "rank"))).alias("a"))
    return seq.select("seq_id", "n").join(back, "seq_id", "left").select("seq_id", "n", F.coalesce(F.transform("a", lambda x: x["rank"]), F.array().cast("array<int>")).alias("syms"))


def to_text(seq: DataFrame) -> DataFrame:
    """(seq_id, text) of sequences of code points."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [x.values.to_numpy(zero_copy_only=False).astype("<u4").tobytes().decode("utf-32-le", "replace") if x.is_valid else None for x in batch["syms"]]
            yield pa.RecordBatch.from_arrays([batch["seq_id"], pa.array(texts, pa.string())], ["seq_id", "text"])

    return seq.select(F.col("seq_id").cast("long").alias("seq_id"), "syms").mapInArrow(run, "seq_id long, text string")
