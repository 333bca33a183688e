"""Reading texts from files of several kinds, and writing parses and payloads."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

FORMATS = ("parquet", "orc", "json", "csv", "text", "binaryFile")


def read_texts(spark: SparkSession, path: str, kind: str = "parquet", key: str = "id", text: str = "text", schema: str | None = None) -> DataFrame:
    """(seq_key, text): columns of tables; lines of text files; whole files with their bytes read as UTF-8."""
    if kind not in FORMATS:
        raise ValueError(f"no format {kind!r}")
    if kind == "text":
        return spark.read.text(path).select(F.xxhash64(F.input_file_name(), F.col("value")).alias("seq_key"), F.col("value").alias("text"))
    if kind == "binaryFile":
        return spark.read.format(kind).load(path).select(F.xxhash64("path").alias("seq_key"), F.decode("content", "UTF-8").alias("text"))
    reader = spark.read.option("header", True) if kind == "csv" else spark.read
    df = (reader.schema(schema) if schema else reader).format(kind).load(path)
    return df.select(F.col(key).cast("long").alias("seq_key"), F.col(text).alias("text"))


def write_parses(parse: DataFrame, path: str, buckets: int = 64, mode: str = "error") -> None:
    """Parses in Parquet, a folder for each bucket of sequences, so that one sequence is found in one of them."""
    parse.withColumn("bucket", F.pmod(F.hash("seq_id"), F.lit(buckets))).repartition("bucket").write.mode(mode).partitionBy("bucket").parquet(path)


def read_parse(spark: SparkSession, path: str, seq_id: int, buckets: int = 64) -> DataFrame:
    """The parses of one sequence; other buckets are pruned."""
    own = spark.range(1).select(F.pmod(F.hash(F.lit(seq_id).cast("long")), F.lit(buckets)).alias("b")).first().b
    return spark.read.parquet(path).filter((F.col("bucket") == own) & (F.col("seq_id") == seq_id)).drop("bucket")


def write_batches(stream: DataFrame, path: str, checkpoint: str, each: Callable[[DataFrame], DataFrame] = lambda df: df) -> StreamingQuery:
    """Parses each micro-batch and writes it in a folder of its number, so a batch that is run again replaces itself."""

    def put(df: DataFrame, number: int) -> None:
        each(df).write.mode("overwrite").parquet(f"{path}/batch={number}")

    return stream.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
