"""SimHash near-duplicates by a segment-popcount embedding.

A fingerprint maps to the bit counts of its 32 two-bit segments. The Manhattan distance of two such
vectors never exceeds the Hamming distance of the fingerprints. Counts are kept as 0, 01 and 11, so
that the Manhattan distance of two vectors is the number of their differing bits. The segments are cut into g groups;
of vectors within distance 4 at least g - 4 groups are equal, so a grid of unit cells over every
choice of g - 4 groups brings each such pair together (for g of 5, five cells a fingerprint). In a
cell, vectors are ordered by their sum and joined over the range of sums within 4; of these pairs
those within 4 by Manhattan distance are kept, and the exact Hamming distance decides. g grows with the number of fingerprints; every g is exact.

Equal fingerprints are one node from the start, cells over BLOCK members are dealt as pairs of
blocks, and a task gives at most one edge for each of its members, so neither copies nor dense
groups make quadratic output.

Defined results: a null text, an empty one and one of white space have fingerprint zero; rows that
repeat are linked like any others; extra columns are not read. doc_id may be null: such a row has
a fingerprint and joins a component, whose id is its smallest doc_id that is not null.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from bitparse.llm.common import as_bytes, fresh, store, table
from bitparse.llm.components import components, forest

BITS, SEED, BLOCK = 64, 42, 20_000
_EVEN = 0x5555555555555555


def fingerprint(raw: bytes | None, words: int = 4) -> int:
    """The unsigned fingerprint of a text in UTF-8."""
    own = raw.lower().split() if raw else ()
    if not own:
        return 0
    plain, n = b" ".join(own), len(own)
    ends = np.cumsum(np.fromiter(map(len, own), np.int64, n) + 1) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))
    digest = xxhash.xxh64_intdigest
    total = max(1, n - words + 1)
    counts = np.zeros(BITS, np.int64)
    for lo in range(0, total, 1 << 15):
        hi = min(total, lo + (1 << 15))
        span = zip(starts[lo:hi].tolist(), ends[[n - 1]].tolist() if n < words else ends[lo + words - 1 : hi + words - 1].tolist(), strict=True)
        h = np.array([digest(plain[a:b], SEED) for a, b in span], np.uint64)
        counts += np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int32)
    return sum(1 << int(k) for k in np.flatnonzero(2 * counts > total))


def fingerprints(df: DataFrame, text: str = "text", keep: tuple[str, ...] = ("doc_id",), words: int = 4) -> DataFrame:
    """The kept columns and ``fp``, the fingerprint as a signed 64-bit integer."""
    body = fresh(df, "body")
    own = df.select(*keep, F.col(text).alias(body))
    schema = T.StructType([*own.drop(body).schema, T.StructField("fp", T.LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fps = np.array([fingerprint(x, words) for x in as_bytes(batch[body])], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([*(batch[k] for k in keep), pa.array(fps)], [*keep, "fp"])

    return own.mapInArrow(run, schema)


def segment_counts(fp: Column) -> Column:
    """The bit counts of the 32 two-bit segments, each in its own two bits as 0, 01 or 11."""
    even = F.lit(_EVEN)
    low, high = fp.bitwiseAND(even), F.shiftrightunsigned(fp, 1).bitwiseAND(even)
    return low.bitwiseOR(high).bitwiseOR(F.shiftleft(low.bitwiseAND(high), 1))


def embedded(fp: np.ndarray) -> np.ndarray:
    """The same for arrays."""
    low, high = fp & np.uint64(_EVEN), (fp >> np.uint64(1)) & np.uint64(_EVEN)
    return low | high | ((low & high) << np.uint64(1))


def grid(n: int, distance: int = 4) -> list[int]:
    """Masks of the cells' segments, for n distinct fingerprints: the cheapest number of groups for that many."""
    best = None
    for g in range(distance + 1, distance + 6):
        cut = [round(k * 32 / g) for k in range(g + 1)]
        groups = [sum(3 << (2 * s) for s in range(lo, hi)) for lo, hi in zip(cut, cut[1:], strict=False)]
        masks = [sum(c) for c in combinations(groups, g - distance)]
        cost = sum(n * 2e-6 + n * n / 2 * 0.375 ** (m.bit_count() / 2) * 3e-9 for m in masks)
        if best is None or cost < best[0]:
            best = cost, masks
    return best[1]


def _near(batches: Iterator[pa.RecordBatch], distance: int) -> Iterator[pa.RecordBatch]:
    parts = [b for b in batches if b.num_rows]
    if not parts:
        return
    whole = pa.Table.from_batches(parts)
    key = whole["key"].to_numpy()
    fp = whole["fp"].to_numpy().view(np.uint64)
    ones = np.bitwise_count(fp).astype(np.int8)
    order = np.lexsort((fp, ones, key))
    key, fp, ones = key[order], fp[order], ones[order]
    vector = embedded(fp)
    at, step, found, kept = np.arange(len(fp)), 1, [], 0
    label = np.arange(len(fp))
    while True:
        at = at[at + step < len(fp)]
        at = at[(key[at] == key[at + step]) & (ones[at + step] - ones[at] <= distance)]
        if not len(at):
            break
        near = at[np.bitwise_count(vector[at] ^ vector[at + step]) <= distance]  # Manhattan
        near = near[np.bitwise_count(fp[near] ^ fp[near + step]) <= distance]
        found.append((near, near + step))
        kept += len(near)
        if kept > 1_000_000:
            label = forest(len(fp), *(np.concatenate(x) for x in zip(*found, (np.arange(len(fp)), label), strict=True)))
            found, kept = [], 0
        step += 1
    label = forest(len(fp), *(np.concatenate(x) for x in zip(*found, (np.arange(len(fp)), label), strict=True)))
    a, b = fp.view(np.int64), fp[label].view(np.int64)
    edges = np.unique(np.stack([a[a != b], b[a != b]], axis=1), axis=0)
    yield pa.RecordBatch.from_arrays([pa.array(edges[:, 0]), pa.array(edges[:, 1])], ["a", "b"])


def near_edges(distinct: DataFrame, n: int, distance: int = 4) -> DataFrame:
    """Edges (a, b) between fingerprints ``fp`` that connect whatever pairs within the distance connect."""
    masks = grid(n, distance)
    counts = segment_counts(F.col("fp"))
    signed = lambda m: m - (1 << 64) if m >> 63 else m
    keys = F.array(*(F.xxhash64(F.lit(k), counts.bitwiseAND(F.lit(signed(m)))) for k, m in enumerate(masks)))
    cells = distinct.select("fp", F.explode(keys).alias("cell"))
    hot = cells.groupBy("cell").count().filter(F.col("count") > BLOCK).select("cell", F.ceil(F.col("count") / BLOCK).cast("int").alias("k"))
    dealt = cells.join(hot, "cell", "left").withColumn("k", F.coalesce("k", F.lit(1))).withColumn("own", F.pmod(F.hash("fp"), F.col("k")))
    pairs = dealt.select("fp", "cell", "own", F.explode(F.sequence(F.lit(0), F.col("k") - 1)).alias("other"))
    keyed = pairs.select("fp", F.xxhash64("cell", F.least("own", "other"), F.greatest("own", "other")).alias("key"))
    tasks = max(1, -(-n * len(masks) // 400_000), int(distinct.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    return keyed.repartition(tasks, "key").mapInArrow(lambda batches: _near(batches, distance), "a long, b long")


def _grouped(own: DataFrame, key: Column, distance: int) -> DataFrame:
    """(fp, least) of stored rows with ``fp``: the smallest key in the component of each fingerprint."""
    nodes = store(own.groupBy("fp").agg(F.min(key).alias("least")), "nodes")
    roots = components(near_edges(nodes, nodes.count(), distance))
    named = nodes.join(roots.withColumnRenamed("id", "fp"), "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    return named.drop("least").join(named.groupBy("root").agg(F.min("least").alias("least")), "root").select("fp", "least")


def near_duplicates(df: DataFrame, text: str = "text", key: str = "doc_id", words: int = 4, distance: int = 4) -> DataFrame:
    """(key, fp, component_id) of every row; the component is named by its smallest key."""
    own = store(fingerprints(df, text, (key,), words), "fingerprints")
    return own.join(_grouped(own, F.col(key), distance), "fp").select(key, "fp", F.col("least").alias("component_id"))


def keep_one(docs: DataFrame, words: int = 4, distance: int = 4) -> DataFrame:
    """One row of each component, that of the smallest doc_id; of rows equal in doc_id and text one."""
    of, mark = F.xxhash64("doc_id", "text"), fresh(docs, "of")
    own = store(fingerprints(docs.select("doc_id", "text", of.alias("of")), keep=("doc_id", "of"), words=words), "fingerprints")
    best = _grouped(own, F.struct("doc_id", "of"), distance).select(F.col("least.of").alias("of")).distinct()
    kept = docs.withColumn(mark, of).join(best.withColumnRenamed("of", mark).hint("shuffle_hash"), mark, "left_semi")
    repeated = own.groupBy("of").agg(F.count("*").alias("n")).filter("n > 1").select(F.col("of").alias(mark))
    if repeated.isEmpty():
        return kept.drop(mark)
    once = kept.join(repeated, mark, "left_anti")
    return once.unionByName(kept.join(repeated, mark, "left_semi").dropDuplicates([mark])).select(*docs.columns)


def op7_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_duplicates(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return found.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")
