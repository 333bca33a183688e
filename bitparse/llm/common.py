"""Pieces that the operators of this package share: shared storage, Arrow batches and row keys."""

from __future__ import annotations

import atexit
import contextlib
import ctypes
import shutil
import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

RANGE = 20_000
_own: dict[str, str] = {}
_stored: list[str] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or in local mode, where it is unset, a folder of our own."""
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if spark.sparkContext.master.split("[")[0] != "local":
        raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
    if "dir" not in _own:
        _own["dir"] = tempfile.mkdtemp(prefix="bitparse-")
        atexit.register(shutil.rmtree, _own["dir"], True)
    return "file://" + _own["dir"]


def store(df: DataFrame, name: str, dictionary: bool = True) -> DataFrame:
    """Cut the lineage: write df to the shared folder and read it back. Survives lost executors.

    Without ``dictionary`` no column is tried for repeated values, which costs time for hashes.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.option("parquet.enable.dictionary", str(dictionary).lower()).parquet(path)
    _stored.append(path)
    return spark.read.schema(df.schema).parquet(path)


def fresh(df: DataFrame, name: str) -> str:
    """``name``, or a longer one where df has a column of that name."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def with_text(df: DataFrame, keep: tuple[str, ...], text: str) -> tuple[DataFrame, str, T.StructType]:
    """The kept columns and the text, once, under a name that no column has unless it is kept; that name; and the schema of the kept columns."""
    kept = df.select(*keep)
    if text in keep:
        return kept, text, kept.schema
    body = fresh(kept, "body")
    return df.select(*keep, F.col(text).alias(body)), body, kept.schema


def running(df: DataFrame, order: list[str], value: str, name: str, most: bool = False) -> DataFrame:
    """Stored rows with ``name``: the sum (or with ``most`` the greatest) of ``value`` over all rows that stand before them, null before the first.

    Ranges of the order of about RANGE rows are totalled side by side; only a row a range comes to the driver. df is read twice.
    """
    spark, schema = df.sparkSession, df.schema
    parts = 1 + df.count() // RANGE

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = None
        for batch in batches:
            out = []
            for x in batch[value].to_pylist():
                out.append(total)
                total = x if total is None else max(total, x) if most else total + x
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(out, pa.int64())], [*batch.schema.names, "before"])

    kind = T.StructType([*schema, T.StructField("before", T.LongType())])
    part = fresh(df, "part_")
    sorted_rows = df.repartitionByRange(parts, *order).sortWithinPartitions(*order)
    counted = store(sorted_rows.mapInArrow(run, kind).withColumn(part, F.spark_partition_id()), name)
    ends = counted.groupBy(part).agg((F.max(value) if most else F.sum(value)).alias("n")).collect()  # a row a range
    at, total = [], None
    for r in sorted(ends, key=lambda r: r[part]):
        at.append((r[part], total))
        total = r["n"] if total is None else max(total, r["n"]) if most else total + r["n"]
    bases = F.broadcast(spark.createDataFrame(at, f"{part} int, base long"))
    own = F.greatest("before", "base") if most else F.when(F.col("before").isNull() & F.col("base").isNull(), None).otherwise(F.coalesce("before", F.lit(0)) + F.coalesce("base", F.lit(0)))
    return counted.join(bases, part).select(*df.columns, own.alias(name))


def forget(spark: SparkSession) -> None:
    """Deletes all that ``store`` has written in this session. Results that were not read yet can't be read after that."""
    for path in _stored:
        target = spark._jvm.org.apache.hadoop.fs.Path(path)
        target.getFileSystem(spark._jsc.hadoopConfiguration()).delete(target, True)
    _stored.clear()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def give_back() -> None:
    """Gives memory that this worker has freed back to the machine: Arrow and the C library keep it else, as long as the worker lives."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(AttributeError, OSError):  # only some C libraries can
        ctypes.CDLL(None).malloc_trim(0)


def giving_back(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """The same kernel, and what it held is given back after each partition."""

    def own(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from run(batches)
        give_back()

    return own


def as_bytes(column: pa.Array) -> list[bytes | None]:
    """The UTF-8 bytes of a string column, without decoding."""
    kind = pa.large_binary() if pa.types.is_large_string(column.type) else pa.binary()
    return column.cast(kind).to_pylist()


def chunks(sizes: list[int], most: int) -> Iterator[tuple[int, int]]:
    """Ranges of consecutive rows of about ``most`` bytes each; a longer row makes a range alone."""
    lo = total = 0
    for k, n in enumerate(sizes):
        if k > lo and total + n > most:
            yield lo, k
            lo, total = k, 0
        total += n
    if lo < len(sizes):
        yield lo, len(sizes)


def words_of(text: Column) -> Column:
    """The number of words between ASCII white space."""
    return F.size(F.filter(F.split(text, r"[\x20\x09-\x0D]+"), lambda w: w != ""))
