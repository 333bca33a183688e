"""The methods as SQL functions: register(spark) adds scalar, aggregate and table functions and a data source."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.functions import AnalyzeArgument, AnalyzeResult
from pyspark.sql.types import IntegerType, LongType, StringType, StructType

from bitparse.functions.codes import code
from bitparse.operators import parsers, stars


def _sequence(text: str | None, f: str, g: str) -> parsers.Sequence:
    return parsers.Sequence(np.array([ord(c) for c in text or ""], np.int64), code(f), code(g))


def _bits(parser: str):
    def run(text: pd.Series, f: pd.Series, g: pd.Series) -> pd.Series:
        made = [_sequence(*x) for x in zip(text, f, g, strict=True)]
        return pd.Series([s.total(parsers.PARSERS[parser](s)) for s in made], dtype="int64")

    return F.pandas_udf(run, LongType())


def _bits_agg(i: pd.Series, s: pd.Series) -> int:
    order = np.argsort(i.to_numpy())
    own = parsers.Sequence(s.to_numpy()[order].astype(np.int64), code("gamma"), code("gamma"))
    return own.total(own.optimal())


class Phrases:
    """lz_phrases(text, f, g[, parser]): the phrases of a text."""

    @staticmethod
    def analyze(text: AnalyzeArgument, f: AnalyzeArgument, g: AnalyzeArgument, parser: AnalyzeArgument | None = None) -> AnalyzeResult:
        if not isinstance(text.dataType, StringType):
            raise ValueError("lz_phrases takes a text")
        return AnalyzeResult(StructType().add("k", IntegerType()).add("start", IntegerType()).add("len", IntegerType()).add("kind", StringType()).add("dist", IntegerType()).add("bits", LongType()))

    def eval(self, text: str, f: str, g: str, parser: str = "optimal") -> Iterator[tuple]:
        own = _sequence(text, f, g)
        parse = parsers.PARSERS[parser](own)
        for k, (p, b) in enumerate(zip(parse, own.prices(parse), strict=True), 1):
            yield k, p[0] + 1, p[1], p[2], p[3], int(b)


class Edges:
    """lz_edges(text): the copies of the full graph."""

    def eval(self, text: str) -> Iterator[tuple[int, int, int]]:
        star = stars.full(np.array([ord(c) for c in text or ""], np.int64))
        for i, n, d in zip(star.i.tolist(), star.length.tolist(), star.dist.tolist(), strict=True):
            yield i + 1, n, d


class _Part(InputPartition):
    def __init__(self, l: int):  # noqa: E741
        self.l = l


class _FamilyReader(DataSourceReader):
    def __init__(self, options: dict):
        self.least, self.most = int(options.get("least", 2)), int(options.get("most", 9))

    def partitions(self) -> list[InputPartition]:
        return [_Part(k) for k in range(self.least, self.most + 1)]

    def read(self, partition: _Part) -> Iterator[tuple]:
        n = partition.l
        yield n, "b" + "a" * n + "c" * (1 << n) + "".join("b" + "a" * k for k in range(1, n + 1))


class BadFamily(DataSource):
    """spark.read.format("bad_family").option("most", 9): the strings on which greedy parsing is poor."""

    @classmethod
    def name(cls) -> str:
        return "bad_family"

    def schema(self) -> str:
        return "l int, text string"

    def reader(self, schema: StructType) -> DataSourceReader:
        return _FamilyReader(self.options)


def register(spark: SparkSession) -> None:
    for name in ("optimal", "greedy", "lazy", "fewest", "length_only"):
        spark.udf.register(f"lz_{name}_bits", _bits(name))
    spark.udf.register("lz_bits_agg", F.pandas_udf(_bits_agg, LongType()))
    spark.udtf.register("lz_phrases", F.udtf(Phrases))
    spark.udtf.register("lz_edges", F.udtf(Edges, returnType="i int, len int, dist int"))
    spark.dataSource.register(BadFamily)
