"""Folding of event logs, the template read back, and odd rows."""

import hashlib

from pyspark.sql import functions as F

from bitparse.llm import chat


def test_fold(spark):
    log = [
        (1, 0, 0, "start", "user", None), (1, 1, 0, "delta", None, "he"), (1, 2, 0, "delta", None, "llo"),
        (1, 3, 1, "start", "assistant", ""), (1, 4, 1, "delta", None, "bad"), (1, 5, 1, "regenerate", "assistant", None), (1, 7, 1, "delta", None, "!"), (1, 6, 1, "delta", None, "good"),
        (1, 8, 0, "edit", "user", "bye"), (1, 9, 2, "start", "user", ""), (1, 10, 2, "delete", None, None), (1, 11, 0, "delta", None, "?"),
    ]
    df = spark.createDataFrame(log, "conv_id long, seq long, message long, kind string, role string, text string")
    assert [(r.message, r.role, r.text) for r in chat.fold(df).orderBy("message").collect()] == [(0, "user", "bye?"), (1, "assistant", "good!")]


def test_roles_come_from_any_event(spark):
    log = [
        (1, 0, 0, "start", "user", None), (1, 1, 0, "delta", None, "bad"), (1, 2, 0, "edit", None, "good"),
        (1, 3, 1, "start", "assistant", None), (1, 4, 1, "delta", "", "x"), (1, 5, 1, "regenerate", None, None), (1, 6, 1, "delta", None, "y"),
        (1, 7, 2, "delta", None, "no role"),
    ]
    df = spark.createDataFrame(log, "conv_id long, seq long, message long, kind string, role string, text string")
    assert [(r.role, r.text) for r in chat.fold(df).orderBy("message").collect()] == [("user", "good"), ("assistant", "y"), ("", "no role")]


def test_the_log_has_every_kind_and_long_texts(spark):
    turns = spark.createDataFrame([(1, 0, "user", "é" * 300_001), (1, 1, "assistant", "b"), (1, 1, "assistant", "b")], "conv_id long, turn long, role string, text string")
    log = chat.events_of(turns)
    assert {r.kind for r in log.select("kind").distinct().collect()} == {"start", "delta", "edit", "regenerate"}
    assert [(r.role, r.text) for r in chat.fold(log).orderBy("message").collect()] == [("user", "é" * 300_001), ("assistant", "b"), ("assistant", "b")]


def test_round_trip(spark):
    texts = ["</s>[INST] ok [/INST]", "<|end|>\n", "&lt;|", "", None, "a\nb\n", "<|user|>\n", "é|ß\U0001f600"]
    turns = spark.createDataFrame([(5, k, ("assistant", "user")[k % 2], t, 1) for k, t in enumerate(texts)], "conv_id long, turn long, role string, text string, piece int")
    r = chat.format_chats(turns).select("*", chat.parse(F.col("formatted")).alias("turns")).collect()[0]
    assert [(t.role, t.text) for t in r.turns] == [(("assistant", "user")[k % 2], t or "") for k, t in enumerate(texts)]
    assert "[INST]" not in r.formatted and "</s>" not in r.formatted
    assert chat.format_chats(turns.limit(0)).count() == 0


def test_conversations(spark, sf):
    got = {r.conv_id: r for r in chat.op6_chat(spark, sf).collect()}
    rows = spark.read.parquet(f"{sf}/conversations.parquet").orderBy("conv_id", "turn").collect()
    for conv in {r.conv_id for r in rows}:
        own = [r for r in rows if r.conv_id == conv]
        loss = "".join(r.text for r in own if r.role == "assistant")
        assert got[conv].turns_sha256 == hashlib.sha256("".join(f"{r.role}\n{r.text}\n" for r in own).encode()).hexdigest()
        assert (got[conv].loss_chars, got[conv].loss_sha256) == (len(loss), hashlib.sha256(loss.encode()).hexdigest())
    assert got[-7].n_turns == 2 and len(got) == 1 + len({r.conv_id for r in rows})
