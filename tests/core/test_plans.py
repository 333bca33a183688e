"""Routes, shared copies, files, and what the plans read."""

import pytest
from pyspark.sql import functions as F

from bitparse.functions import codes
from bitparse.operators import parsers
from bitparse.plans import route
from bitparse.sources import files, sequences
from bitparse.workloads import tables

SMALL = "/root/testdata/sf0.001"


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_routes_agree(spark):
    seq = sequences.from_text(spark.createDataFrame([(1, "abab" * 5), (2, "abc" * 40), (3, "xyz" * 200), (4, ""), (5, "a")], "id long, t string"), "id", "t")
    got = {r.seq_id: r for r in route.optimal_bits(seq, window=1000, fold=24, chunked=300, chunk=50, most=600).collect()}
    want = {r.seq_id: r.bits for r in parsers.optimal(seq, window=1000).collect()}
    assert {k: r.bits for k, r in got.items()} == want
    assert {k: r.route for k, r in got.items()} == {1: "fold", 2: "kernel", 3: "chunks", 4: "kernel", 5: "fold"}
    with pytest.raises(ValueError):
        route.optimal_bits(seq, chunked=300)
    assert [route.strategy("fixed8", "fixed8"), route.strategy("gamma", "rice2"), route.strategy("gamma", codes.static_entropy({1: 1, 2: 9}))] == ["greedy", "pruned", "full"]


def test_copies_are_parsed_once(spark):
    seq = tables.documents(spark, SMALL)
    twice = seq.unionByName(seq.withColumn("seq_id", F.col("seq_id") + 100_000))
    seen = []

    def parse(df):
        seen.append(df.count())
        return parsers.optimal(df).select("seq_id", "bits")

    got = {r.seq_id: r.bits for r in route.share_copies(twice, parse).collect()}
    want = {r.seq_id: r.bits for r in parsers.optimal(seq).collect()}
    assert got == {**want, **{k + 100_000: b for k, b in want.items()}} and seen[0] <= len(want)


def test_scans_read_two_columns_and_parsing_does_not_shuffle(spark):
    text = plan(parsers.optimal(sequences.from_text(tables.read(spark, SMALL, "documents"), "doc_id", "text")))
    assert "Exchange" not in text and "ReadSchema: struct<doc_id:bigint,text:string>" in text
    filtered = plan(parsers.optimal(sequences.from_text(tables.read(spark, SMALL, "documents").filter("lang = 'en'"), "doc_id", "text")))
    assert "EqualTo(lang,en)" in filtered


def test_files(spark, tmp_path):
    rows = [(1, "abcabc"), (2, "é\nx"), (3, "")]
    df = spark.createDataFrame(rows, "id long, text string")
    for kind in ("parquet", "orc", "json"):
        df.write.format(kind).save(f"{tmp_path}/{kind}")
        assert sorted((r.seq_key, r.text) for r in files.read_texts(spark, f"{tmp_path}/{kind}", kind).collect()) == rows
    df.limit(1).write.option("header", True).csv(f"{tmp_path}/csv")
    assert files.read_texts(spark, f"{tmp_path}/csv", "csv").first().text == "abcabc"
    (tmp_path / "raw").mkdir()
    (tmp_path / "raw" / "a.bin").write_bytes("é ok".encode())
    assert files.read_texts(spark, f"{tmp_path}/raw", "binaryFile").first().text == "é ok"
    assert files.read_texts(spark, f"{tmp_path}/raw", "text").first().text == "é ok"
    with pytest.raises(ValueError):
        files.read_texts(spark, "x", "xml")
    parse = parsers.optimal(sequences.from_text(df, "id", "text"))
    files.write_parses(parse, f"{tmp_path}/parses", 8)
    assert files.read_parse(spark, f"{tmp_path}/parses", 1, 8).first().bits == {r.seq_id: r.bits for r in parse.collect()}[1]


def test_stream_to_files(spark, tmp_path):
    tables.read(spark, SMALL, "documents").select("doc_id", "text").write.parquet(f"{tmp_path}/in")
    stream = spark.readStream.schema("doc_id long, text string").parquet(f"{tmp_path}/in")
    query = files.write_batches(stream, f"{tmp_path}/out", f"{tmp_path}/cp", lambda df: parsers.optimal(sequences.from_text(df, "doc_id", "text")).drop("counters"))
    query.awaitTermination()
    want = {r.seq_id: r.bits for r in parsers.optimal(tables.documents(spark, SMALL)).collect()}
    assert {r.seq_id: r.bits for r in spark.read.parquet(f"{tmp_path}/out").collect()} == want
