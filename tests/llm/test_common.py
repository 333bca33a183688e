"""Shared storage, and the queries that have SQL."""

import os
import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).parents[1]))
import oracle  # noqa: E402

from bitparse.llm import common, queries  # noqa: E402


@pytest.mark.parametrize("name", sorted(queries.ORACLE_SQL))
def test_same_as_sql(spark, name):
    small = "/root/testdata/sf0.01"
    assert not oracle.compare(spark, oracle.connect(small), name, small, queries.QUERIES[name], queries.ORACLE_SQL[name])


def test_store_and_forget(spark):
    out = common.store(spark.range(5), "numbers")
    path = common._stored[-1].removeprefix("file://")
    assert out.count() == 5 and os.path.isdir(path)
    common.forget(spark)
    assert not os.path.isdir(path)
    assert common.store(spark.range(0), "none").count() == 0


@pytest.mark.parametrize("size", [7, 20_000])
def test_running_totals(spark, monkeypatch, size):
    monkeypatch.setattr(common, "RANGE", size)
    rows = [(k * 7 % 50, k, "x") for k in range(50)]
    df = spark.createDataFrame(rows, "k long, n long, part_ string")
    got = {r.k: (r.sums, r.part_) for r in common.running(df, ["k"], "n", "sums").collect()}
    tops = {r.k: r.tops for r in common.running(df, ["k"], "n", "tops", most=True).collect()}
    total, top = None, None
    for k, n, _ in sorted(rows):
        assert got[k] == (total, "x") and tops[k] == top
        total, top = (total or 0) + n, n if top is None else max(top, n)
    assert common.running(df.limit(0), ["k"], "n", "sums").count() == 0


def test_chunks():
    assert list(common.chunks([5, 5, 20, 1, 1], 10)) == [(0, 2), (2, 3), (3, 5)]
    assert list(common.chunks([], 10)) == []
