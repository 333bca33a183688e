"""The pipeline's stages on planted cases, and the guard of the entry."""

import corpus_pipeline
from pyspark.sql import functions as F


def test_stages_on_planted_cases(spark, tmp_path):
    base = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    bench = spark.read.parquet("/root/testdata/sf0.001/benchmark.parquet")
    docs = base.dropDuplicates(["text"]).collect()
    item = max((r.text for r in bench.collect()), key=len)
    passage = " ".join(f"unique{k}" for k in range(60))
    first, second = docs[0], docs[1]
    planted = [
        (9001, first.text, "en", "p"), (9002, first.text.replace(" the ", " the\t", 1), "en", "p"),  # copies
        (9003, item, "en", "p"), (9004, second.text + "\n" + passage, "en", "p"), (9005, docs[2].text + "\n" + passage + "\nown words here", "en", "p"),
        (9006, "12345 --- 678", "en", "p"), (9007, None, None, "p"), (9008, "", "en", "p"), (9008, "", "en", "p"),
    ]
    more = spark.createDataFrame([(*p, len(p[1] or "")) for p in planted], base.schema)
    for name, df in (("documents", base.unionByName(more)), ("benchmark", bench)):
        df.write.parquet(f"{tmp_path}/{name}.parquet")
    docs_in = spark.read.parquet(f"{tmp_path}/documents.parquet")
    seen = docs_in
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = corpus_pipeline.store(stage(spark, seen, str(tmp_path)), name)
        assert out.columns == docs_in.columns
        before, after = {r.doc_id: r for r in seen.collect()}, {r.doc_id: r for r in out.collect()}
        if name == "language_id":
            assert set(before) - set(after) == {9006, 9007, 9008}
        elif name == "line_dedup":
            assert set(before) == set(after)
            assert passage in after[9004].text and passage not in after[9005].text and after[9005].text.endswith("own words here")
            assert after[9005].n_chars == len(after[9005].text)
        elif name == "near_dedup":
            assert first.doc_id in after and 9001 not in after
        else:
            assert 9003 not in after and 9004 in after
        assert out.count() == len(after)
        seen = out
    pieces = corpus_pipeline.run(spark, str(tmp_path))
    assert {r.doc_id for r in pieces.select("doc_id").distinct().collect()} == {r.doc_id for r in seen.select("doc_id").collect()}


def test_columns_of_any_name_and_odd_rows_pass_every_stage(spark, tmp_path):
    names = ["said", "score", "removed", "n_words", "n_hit", "items", "body", "marks", "named", "of", "o", "h", "gone", "rid", "ids", "n", "__text", "__of", "__gone", "part", "start", "length"]
    text = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").first().text
    rows = [(k, t, "en", *range(len(names))) for k, t in enumerate([text, text, "", None, " \n ", "word " * 200_000, text + "\n" + text])] + [(None, text, None, *range(len(names)))]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, " + ", ".join(f"{c} long" for c in names))
    spark.read.parquet("/root/testdata/sf0.001/benchmark.parquet").write.parquet(f"{tmp_path}/benchmark.parquet")
    for seen in (docs, docs.limit(0)):
        for name, stage in corpus_pipeline.STAGES[:-1]:
            out = corpus_pipeline.store(stage(spark, seen, str(tmp_path)), name)
            assert out.columns == docs.columns
            assert all(tuple(r)[3:] == tuple(range(len(names))) for r in out.collect())
            seen = out
        pieces = corpus_pipeline.STAGES[-1][1](spark, seen, str(tmp_path))
        assert {r.doc_id for r in pieces.collect()} == {r.doc_id for r in seen.collect()}


def test_repeated_rows_leave_one(spark):
    df = spark.createDataFrame([(1, "a b c d e"), (1, "a b c d e"), (1, "other words are here now"), (2, "a b c d e"), (None, "a b c d e")], "doc_id long, text string")
    kept = corpus_pipeline.near_dedup(spark, df.withColumn("score", F.lit(1)), "")
    assert kept.count() == 2 and kept.columns == ["doc_id", "text", "score"]


def test_registered():
    import __spark_entry__ as entry

    names = set(entry.queries())
    assert "pipeline" in names and all(sum(n.startswith(f"op{k}_") for n in names) == 1 for k in range(1, 11))
