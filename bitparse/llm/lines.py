"""Line dedup by a suffix array over line ids.

A text is its sequence of lines. Lines that occur once in all texts cannot be part of a repeated
run and leave at once. The others get ranks, and prefix doubling makes, for k = 0, 1, 2, ..., the
ranks of all runs of 2^k lines that occur more than once: the order of suffixes by their first 2^k
lines, with equal ranks for a common prefix. Runs of which there is one leave again, so each round
sorts less. Two ranks of runs of 2^k lines, at a run's start and at its end, name a run of any
length from 2^k to 2^(k+1): equal names are one interval of suffixes with that common prefix.

A repeated run counts from MIN_WORDS words on. It is the union of its shortest such parts: for each
line the shortest run of that many words that begins there, and the one that ends there. An
interval of such parts is kept where it occurs first, by doc_id and line, and deleted elsewhere;
the unions of what is deleted are the later copies of maximal repeated runs. Every distinct line
stays somewhere, as its first occurrence is no later copy.

Defined results: a null text stays null; lines are cut at line feeds and compared without white
space around them; blank lines neither count nor break a run, and a text of which only blank lines
would stay becomes empty; rows with equal doc_id and text are one document and get the same result;
null doc_ids come first; all columns of the rows are kept.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from bitparse.llm.common import as_bytes, fresh, giving_back, store, table

MIN_WORDS = 50
_LINES = "o long, h long, l int, a long, b long, tf int, tb int"


def line_rows(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """A row for each line that is not blank: its document (o, h), number l, 128-bit id (a, b), and the lines
    of the shortest run of min_words words that begins (tf) and ends (tb) there, 0 if there is none."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (whole.slice(lo, 256) for whole in batches for lo in range(0, whole.num_rows, 256)):
            at, out, numbers = [], [], []
            for k, raw in enumerate(as_bytes(batch["text"])):
                own = [x for x in map(bytes.strip, raw.split(b"\n")) if x]
                if not own:
                    continue
                total = np.concatenate(([0], np.cumsum([len(x.split()) for x in own])))
                first = np.arange(len(own))
                end = np.searchsorted(total, total[:-1] + min_words)
                start = np.searchsorted(total, total[1:] - min_words, "right") - 1
                tf = np.where(end <= len(own), end - first, 0)
                tb = np.where(total[1:] >= min_words, first - start + 1, 0)
                numbers.append(np.stack([first, tf, tb], axis=1))
                at += [k] * len(own)
                out += [xxhash.xxh3_128_digest(x) for x in own]
            if at:
                ids = np.frombuffer(b"".join(out), ">i8").astype(np.int64).reshape(-1, 2)
                n = np.concatenate(numbers).astype(np.int32)
                rows = batch.select(["o", "h"]).take(pa.array(at))
                yield pa.RecordBatch.from_arrays([*rows.columns, pa.array(n[:, 0]), pa.array(ids[:, 0]), pa.array(ids[:, 1]), pa.array(n[:, 1]), pa.array(n[:, 2])], ["o", "h", "l", "a", "b", "tf", "tb"])

    return docs.filter("text is not null").select(*_key(), "text").mapInArrow(giving_back(run), _LINES)


def _key() -> tuple:
    """A document's place in the order, and a hash that tells apart rows with one doc_id."""
    return F.coalesce(F.col("doc_id").cast("long"), F.lit(-(1 << 63))).alias("o"), F.xxhash64("doc_id", "text").alias("h")


def ranked(rows: DataFrame, by: tuple[str, str]) -> DataFrame:
    """The repeated values of two columns and ``r``, their rank in order: a distributed sort, then numbers from each part's offset."""
    often = rows.groupBy(*by).agg(F.count("*").alias("n")).filter("n > 1").select(*by)
    parts = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))

    def number(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at = 0
        for batch in batches:
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(np.arange(at, at + batch.num_rows))], [*by, "at"])
            at += batch.num_rows

    kinds = ", ".join(f"{c} long" for c in by)
    numbered = store(often.repartitionByRange(parts, *by).sortWithinPartitions(*by).mapInArrow(number, f"{kinds}, at long").withColumn("part", F.spark_partition_id()), "ranks")
    sizes = {r["part"]: r["count"] for r in numbered.groupBy("part").count().collect()}  # one row a partition
    starts, total = [], 0
    for k in sorted(sizes):
        starts.append((k, total))
        total += sizes[k]
    offsets = rows.sparkSession.createDataFrame(starts, "part int, base long")
    return numbered.join(F.broadcast(offsets), "part").select(*by, (F.col("at") + F.col("base")).alias("r"))


def later_copies(lines: DataFrame) -> DataFrame:
    """Spans (o, h, s, t), t lines from line s on, that occur earlier too. lines: stored rows of line_rows."""
    runs = store(lines.join(ranked(lines, ("a", "b")), ["a", "b"]).select("o", "h", "l", "r", "tf", "tb"), "suffixes")
    forward = runs.filter("tf > 0").select("o", "h", F.col("l").alias("s"), F.col("tf").alias("t"))
    backward = runs.filter("tb > 0").select("o", "h", (F.col("l") - F.col("tb") + 1).alias("s"), F.col("tb").alias("t"))
    windows = store(forward.unionByName(backward).distinct(), "windows")
    longest = windows.agg(F.max("t")).first()[0] or 0
    level, k, out = runs.select("o", "h", "l", "r"), 0, []
    while 1 << k <= longest:
        own = windows.filter((F.col("t") >= 1 << k) & (F.col("t") < 2 << k))
        at_start = level.select("o", "h", F.col("l").alias("s"), F.col("r").alias("r1"))
        at_end = level.select("o", "h", F.col("l").alias("e"), F.col("r").alias("r2"))
        named = own.join(at_start, ["o", "h", "s"]).withColumn("e", F.col("s") + F.col("t") - (1 << k)).join(at_end, ["o", "h", "e"]) if k else own.join(at_start, ["o", "h", "s"]).withColumn("r2", F.col("r1"))
        named = store(named.select("o", "h", "s", "t", "r1", "r2"), "named")
        # stored, so that the join below deals both sides anew and a run that very many texts share can be split
        first = store(named.groupBy("t", "r1", "r2").agg(F.min(F.struct("o", "h", "s")).alias("first"), F.count("*").alias("n")).filter("n > 1"), "first")
        out.append(named.join(first, ["t", "r1", "r2"]).filter(F.struct("o", "h", "s") > F.col("first")).select("o", "h", "s", "t"))
        k += 1
        if 1 << k > longest:
            break
        second = level.select("o", "h", (F.col("l") - (1 << (k - 1))).cast("int").alias("l"), F.col("r").alias("r2"))
        both = store(level.withColumnRenamed("r", "r1").join(second, ["o", "h", "l"]), "pairs")
        level = store(both.join(ranked(both, ("r1", "r2")), ["r1", "r2"]).select("o", "h", "l", "r"), "suffixes")
        if level.isEmpty():
            break
    spans = out[0]
    for more in out[1:]:
        spans = spans.unionByName(more)
    return spans


def dedup(docs: DataFrame, min_words: int = MIN_WORDS, removed: str = "n_removed") -> DataFrame:
    """The rows with later copies of repeated line runs deleted from text, and under ``removed`` the lines that went."""
    lines = store(line_rows(docs, min_words), "lines")
    spans = later_copies(lines) if not lines.isEmpty() else lines.select("o", "h", F.col("l").alias("s"), F.col("tf").alias("t"))
    o, h, away = fresh(docs, "o"), fresh(docs, "h"), fresh(docs, "gone")
    gone = spans.groupBy(F.col("o").alias(o), F.col("h").alias(h)).agg(F.collect_set(F.struct("s", "t")).alias(away))
    joined = docs.withColumns(dict(zip((o, h), _key(), strict=True))).join(gone.hint("shuffle_hash"), [o, h], "left").select(*docs.columns, away)
    schema, columns = T.StructType([*docs.schema, T.StructField(removed, T.LongType())]), docs.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (whole.slice(lo, 256) for whole in batches for lo in range(0, whole.num_rows, 256)):
            went = np.zeros(batch.num_rows, np.int64)
            touched = [k for k, x in enumerate(batch[away].is_valid().to_pylist()) if x]
            texts = batch["text"]
            if touched:
                raw = as_bytes(texts)
                for k in touched:
                    raw[k], went[k] = without(raw[k], [(x["s"], x["t"]) for x in batch[away][k].as_py()])
                texts = pa.array(raw, pa.binary()).cast(texts.type)
            yield pa.RecordBatch.from_arrays([*(texts if c == "text" else batch[c] for c in columns), pa.array(went)], schema.names)

    return joined.mapInArrow(giving_back(run), schema)


def without(raw: bytes, spans: list[tuple[int, int]]) -> tuple[bytes, int]:
    """A text without some spans of its lines that are not blank, and the number of lines that went."""
    gone = {k for s, t in spans for k in range(s, s + t)}
    kept, at = [], 0
    for line in raw.split(b"\n"):
        blank = not line.strip()
        if blank or at not in gone:
            kept.append(line)
        at += not blank
    return (b"\n".join(kept) if at > len(gone) else b""), len(gone)


def op9_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dedup(table(spark, sf_dir, "documents").select("doc_id", "text"))
