"""Token-id files coded by a canonical Huffman code of limited length.

Code lengths come from the counts of all ids (package-merge, at most LIMIT bits), so the lengths
alone give the code. A file is a row of a Parquet container: a range of documents in order of
their key, and a payload that holds all that a reader needs:

    magic, version, number of ids, documents and blocks, size of the packed header;
    the packed header: the code length of each id, the documents' keys (with a mark for null) and
    numbers of ids; the bit offset of each block's start (checkpoints); the bits, most significant first.

A block holds BLOCK ids, so blocks can be decoded by themselves; the decoder works through all
blocks of a payload at once, with a table from the next LIMIT bits to id and length. The columns
beside the payload (first and last key, number of ids) only let a reader skip files.

Defined results: a null text is empty, and every document has at least its end id; rows with one
doc_id are all kept, in any order among themselves; null ids come first; no rows give no files.
"""

from __future__ import annotations

import struct
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from bitparse.llm import tokens
from bitparse.llm.common import running, shared_dir, store, table

LIMIT, BLOCK, PIECE, PER_FILE, MOST_RUNS, MOST_FILES = 18, 512, 1 << 16, 2_000_000, 64, 500_000
_HEAD = struct.Struct("<4sHQQII")
_MAGIC = b"CHUF"


def code_lengths(counts: dict[int, int], limit: int = LIMIT) -> dict[int, int]:
    """Optimal code lengths of at most ``limit`` bits: package-merge, in levels of sorted packages."""
    ids = sorted(counts, key=lambda k: (counts[k], k))
    if len(ids) < 2:
        return {k: 1 for k in ids}
    if len(ids) > 1 << limit:
        raise ValueError("more ids than codes of that length")
    weight = np.array([counts[k] for k in ids], np.float64)
    # each level: sorted weights, and which of them are single ids
    levels, current = [], weight
    single = np.ones(len(ids), bool)
    for _ in range(limit - 1):
        levels.append(single)
        pairs = current[: len(current) // 2 * 2].reshape(-1, 2).sum(axis=1)
        merged = np.concatenate([weight, pairs])
        order = np.argsort(merged, kind="stable")
        current, single = merged[order], order < len(weight)
    levels.append(single)
    length, take = np.zeros(len(ids), np.int64), 2 * len(ids) - 2
    for single in reversed(levels):
        n = int(single[:take].sum())
        length[:n] += 1  # singles are taken in order of weight
        take = 2 * (take - n)
    return {k: int(n) for k, n in zip(ids, length, strict=True)}


class Code:
    """Canonical codes: by length, then by id."""

    def __init__(self, lengths: dict[int, int]):
        self.lengths = lengths
        self.width = max(lengths.values(), default=1)
        size = max(lengths, default=0) + 1
        self.length, self.code = np.zeros(size, np.uint8), np.zeros(size, np.uint64)
        self.ids, self.bits = np.zeros(1 << self.width, np.uint16), np.zeros(1 << self.width, np.uint8)
        code, last = 0, 0
        for k, n in sorted(lengths.items(), key=lambda x: (x[1], x[0])):
            code <<= n - last
            last = n
            self.length[k], self.code[k] = n, code
            lo = code << (self.width - n)
            self.ids[lo : lo + (1 << (self.width - n))], self.bits[lo : lo + (1 << (self.width - n))] = k, n
            code += 1

    def encode(self, ids: np.ndarray) -> tuple[int, bytes]:
        """The number of blocks, and their checkpoints and bits: pieces of whole blocks, small enough for the
        processor's cache, each from a word of 32 bits on."""
        n, at, offsets, words = len(ids), 0, [], []
        for lo in range(0, n, PIECE):
            start, own = self._piece(ids[lo : lo + PIECE])
            offsets.append(start[::BLOCK] + 32 * at)
            words.append(own)
            at += len(own)
        words.append(np.zeros(1, np.uint32))  # so that every look ahead stays inside
        starts = np.concatenate([*offsets, np.zeros(0, np.int64)]).astype("<u8")
        return len(starts), starts.tobytes() + np.concatenate(words).astype(">u4").tobytes()

    def _piece(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The bit where each id begins, and the words."""
        size = self.length[ids].astype(np.int64)
        end = np.cumsum(size)
        start = end - size
        word = start >> 5
        wide = self.code[ids] << (64 - (start & 31) - size).astype(np.uint64)
        out = np.zeros((int(end[-1]) >> 5) + 2, np.uint64)
        first = np.flatnonzero(np.concatenate(([True], word[1:] != word[:-1])))
        out[word[first]] += np.add.reduceat(wide >> np.uint64(32), first)
        out[word[first] + 1] += np.add.reduceat(wide & np.uint64(0xFFFFFFFF), first)
        return start, out.astype(np.uint32)

    def decode(self, body: memoryview, n: int, blocks: int) -> np.ndarray:
        at = np.frombuffer(body, "<u8", blocks).astype(np.int64)
        bits = np.frombuffer(body, ">u4", -1, 8 * blocks).astype(np.uint64)
        pairs = (bits[:-1] << np.uint64(32)) | bits[1:]
        out = np.zeros((BLOCK, blocks), np.uint16)
        shift, mask = np.uint64(64 - self.width), np.uint64((1 << self.width) - 1)
        full, last = blocks, n - (blocks - 1) * BLOCK if blocks else 0
        for k in range(min(n, BLOCK)):
            if k == last:
                full, at = blocks - 1, at[:-1]
            look = ((pairs[at >> 5] >> (shift - (at & 31).astype(np.uint64))) & mask).astype(np.int64)
            out[k, :full] = self.ids[look]
            at = at + self.bits[look]
        return out.T.reshape(-1)[:n]


def to_file(code: Code, ids: np.ndarray, keys: list[int | None], counts: list[int]) -> bytes:
    """A file of documents whose ids stand one after another."""
    lengths = np.zeros(max(code.lengths, default=-1) + 1, np.uint8)
    lengths[list(code.lengths)] = list(code.lengths.values())
    known = np.array([k is not None for k in keys], np.uint8)
    head = zlib.compress(struct.pack("<I", len(lengths)) + lengths.tobytes() + known.tobytes() + np.array([k or 0 for k in keys], "<i8").tobytes() + np.array(counts, "<u8").tobytes(), 1)
    blocks, body = code.encode(ids)
    return _HEAD.pack(_MAGIC, 2, len(ids), len(keys), blocks, len(head)) + head + body


class Reader:
    """Reads files; the code is kept, as those of one set share it."""

    def __init__(self):
        self.raw, self.code = None, None

    def __call__(self, payload: bytes) -> tuple[np.ndarray, list[int | None], np.ndarray]:
        """Ids, keys and the documents' numbers of ids."""
        magic, version, n, docs, blocks, size = _HEAD.unpack_from(payload)
        if magic != _MAGIC or version != 2:
            raise ValueError("not a token file of this format")
        head = zlib.decompress(payload[_HEAD.size : _HEAD.size + size])
        (kinds,) = struct.unpack_from("<I", head)
        raw, at = head[4 : 4 + kinds], 4 + kinds
        if raw != self.raw:
            self.raw, self.code = raw, Code({k: x for k, x in enumerate(raw) if x})
        known = np.frombuffer(head, np.uint8, docs, at)
        keys = np.frombuffer(head, "<i8", docs, at + docs).tolist()
        counts = np.frombuffer(head, "<u8", docs, at + 9 * docs).astype(np.int64)
        return self.code.decode(memoryview(payload)[_HEAD.size + size :], n, blocks), [k if ok else None for k, ok in zip(keys, known, strict=True)], counts


def count_ids(ids: DataFrame) -> DataFrame:
    """(id, count) over all rows, from the tallies of the partitions."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(1 << 16, np.int64)
        for batch in batches:
            for x in batch["tally"].to_pylist():
                total += np.frombuffer(x, "<i8")
        own = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(own), pa.array(total[own])], ["id", "n"])

    return ids.select("tally").filter("tally is not null").mapInArrow(run, "id long, n long").groupBy("id").agg(F.sum("n").alias("count"))


def in_order(ids: DataFrame, key: str) -> bool:
    """Whether the stored rows, as scans deal them out, are runs of ascending keys that do not overlap."""

    def runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out: list[list] = []
        for batch in batches:
            for k in batch["k"].to_pylist():
                if k is None:
                    out += [[0, 1 << 62]] * (MOST_RUNS + 1)  # nulls have no place in a run
                elif out and out[-1][1] <= k:
                    out[-1][1] = k
                else:
                    out.append([k, k])
                if len(out) > MOST_RUNS:  # not in order: two rows that overlap say so
                    out = [[-(1 << 62), 1 << 62]] * 2
                    break
        yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in out], pa.int64()), pa.array([r[1] for r in out], pa.int64())], ["first", "last"])

    found = ids.filter("tally is null").select(F.col(key).cast("long").alias("k")).mapInArrow(runs, "first long, last long")
    return _apart(store(found, "runs"))


def _apart(found: DataFrame) -> bool:
    before = running(found.select("first", "last"), ["first", "last"], "last", "before", most=True)
    return before.filter("before > first or first is null").isEmpty()


def write(ids: DataFrame, path: str | None = None, key: str = "doc_id") -> str:
    """Writes stored rows of key, ids, n and tally as files in key order under ``path`` (or a new one in the shared folder), and returns it.

    Rows that already stand in order, as in a table written in order, are encoded where they stand;
    others are dealt out by ranges of keys and sorted first.
    """
    spark = ids.sparkSession
    path = path or f"{shared_dir(spark)}/token-files-{uuid.uuid4().hex}"
    lengths = code_lengths({r["id"]: r["count"] for r in count_ids(ids).collect()})  # bounded by the vocabulary
    code = spark.sparkContext.broadcast(Code(lengths))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, held, size, number = [], [], 0, 0

        def flush():
            whole = np.frombuffer(b"".join(held), np.uint16)
            known = [k for k in keys if k is not None]
            return pa.RecordBatch.from_arrays(
                [pa.array([number], pa.int64()), pa.array([min(known, default=None)], pa.int64()), pa.array([max(known, default=None)], pa.int64()), pa.array([len(whole)], pa.int64()), pa.array([to_file(code.value, whole, keys, [len(x) // 2 for x in held])], pa.binary())],
                ["file", "first", "last", "n_ids", "payload"],
            )

        for batch in batches:
            for k, x in zip(batch["k"].to_pylist(), batch["ids"].to_pylist(), strict=True):
                if held and (size >= PER_FILE or (k is None) != (keys[-1] is None) or k is not None and k < keys[-1]):
                    yield flush()
                    keys, held, size, number = [], [], 0, number + 1
                keys.append(k)
                held.append(x)
                size += len(x) // 2
        if held:
            yield flush()

    rows = ids.filter("tally is null").select(F.col(key).cast("long").alias("k"), "ids")

    def files(dealt: DataFrame) -> DataFrame:
        made = dealt.mapInArrow(run, "file long, first long, last long, n_ids long, payload binary")
        made.withColumn("shard", F.spark_partition_id().cast("long")).write.mode("overwrite").parquet(path)
        return spark.read.parquet(path)

    if in_order(ids, key) and _apart(files(rows)):
        return path
    total = ids.agg(F.sum("n")).first()[0] or 0
    parts = max(1, -(-total // PER_FILE), min(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-total // 100_000)))
    files(rows.repartitionByRange(parts, "k").sortWithinPartitions("k"))
    return path


def read(spark: SparkSession, path: str, with_ids: bool = True) -> DataFrame:
    """(key, start, n_tokens, ids_crc32 and, unless left out, ids) of each document, from the files under ``path`` alone."""
    files = spark.read.parquet(path)
    starts = running(files.select("first", "last", "shard", "file", "n_ids"), ["first", "last", "shard", "file"], "n_ids", "before").select("shard", "file", F.coalesce("before", F.lit(0)).alias("before"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        open_file = Reader()
        for batch in batches:
            for payload, before in zip(batch["payload"], batch["before"].to_pylist(), strict=True):
                ids, keys, counts = open_file(payload.as_py())
                ends = np.cumsum(counts)
                cut = list(zip((ends - counts).tolist(), ends.tolist(), strict=True))
                crcs = pa.array([tokens.crc(ids[a:b]) for a, b in cut], pa.int64())
                columns = [pa.array(keys, pa.int64()), pa.array(before + ends - counts), pa.array(counts), crcs]
                if with_ids:
                    columns.append(pa.array([ids[a:b].tobytes() for a, b in cut], pa.binary()))
                yield pa.RecordBatch.from_arrays(columns, names)

    schema = "key long, start long, n_tokens long, ids_crc32 long" + ", ids binary" * with_ids
    names = ["key", "start", "n_tokens", "ids_crc32"] + ["ids"] * with_ids
    small = files.select("file").limit(MOST_FILES + 1).count() <= MOST_FILES
    located = files.join(F.broadcast(starts) if small else starts, ["shard", "file"])
    return located.select("payload", "before").mapInArrow(run, schema)


def op10_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    ids = store(tokens.tokenize(table(spark, sf_dir, "documents").select("doc_id", "text"), tally=True), "ids")
    return read(spark, write(ids), with_ids=False).select(F.col("key").alias("doc_id"), "start", "n_tokens", "ids_crc32")
