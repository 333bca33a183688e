"""Ids against the library, Huffman codes, token files read back, and packing."""

import heapq
import random
import subprocess
import sys
import zlib
from pathlib import Path

import numpy as np
import pytest
from tokenizers import Tokenizer

from bitparse.llm import huffman, packing, tokens

TEXTS = [None, "", " \n", "Hello, World's 3rd  test!\x1c\x85\xa0x", "é é ́ ΑΣ Σ", "<|endoftext|> a<|startoftext|>b <|endoftext |>", "\x01 a\x01b", "w" * 300 + " " + "don't 12" * 20, "日本語 ​　ok", "ﬁ İ ǅ", "ÀÉ, ß. ÿ;; Don't It's? é́ x́, µ ª a.b a,b! <|endoftext|>."]


def want(text, tokenizer=Tokenizer.from_file(tokens.default_path())):
    return [*tokenizer.encode(text or "", add_special_tokens=False).ids, 1]


def crc(ids):
    return zlib.crc32(np.array(ids, "<u4").tobytes())


def test_ids_are_the_librarys(monkeypatch):
    monkeypatch.setattr(tokens, "KEPT_WORDS", 3)
    own = tokens.Encoder(tokens.default_path())
    for _ in range(3):
        for t in TEXTS:
            assert np.frombuffer(own.texts([t.encode() if t is not None else None])[0], np.uint16).tolist() == want(t)[:-1]


def test_odd_words_together():
    """Words of marks, digits, accents and special tokens, many in one text, against each alone."""
    rng, own = random.Random(6), tokens.Encoder(tokens.default_path())
    alphabet = ["a", "Z", "7", "é", "e\u0301", "\u0301", "'", "'s", "-", "…", "日", "ﬁ", "İ", "\u200b", "\u00a0", "\u2028", "<|endoftext|>", "<|", "|>", "😀", "ß", "Σ", "\x01", "\x85", "½"]
    words = ["".join(rng.choices(alphabet, k=rng.randrange(1, 7))).encode() for _ in range(20_000)]
    words = [w for w in {p for w in words for p in w.split()} if w]
    for lo in range(0, len(words), 50):
        text = " ".join(w.decode() for w in words[lo : lo + 50])
        assert np.frombuffer(own.texts([text.encode()])[0], np.uint16).tolist() == want(text)[:-1]


def plain_huffman(counts):
    heap = [(n, k, 0) for k, n in enumerate(counts)]
    heapq.heapify(heap)
    total, k = 0, len(counts)
    while len(heap) > 1:
        a, b = heapq.heappop(heap), heapq.heappop(heap)
        total += a[0] + b[0]
        k += 1
        heapq.heappush(heap, (a[0] + b[0], k, 0))
    return total


@pytest.mark.parametrize("n", [1, 2, 3, 17, 500])
def test_codes(n):
    rng = random.Random(n)
    counts = {k * 3: rng.randrange(1, 10 ** rng.randrange(1, 5)) for k in range(n)}
    free = huffman.code_lengths(counts, 40)
    assert sum(2.0**-x for x in free.values()) <= 1
    if n > 2:
        assert sum(counts[k] * x for k, x in free.items()) == plain_huffman(list(counts.values()))
    tight = huffman.code_lengths({k: 2**min(k, 40) for k in range(n)}, 10)
    assert max(tight.values()) <= 10 and sum(2.0**-x for x in tight.values()) <= 1
    code = huffman.Code(tight)
    for size in (0, 1, 5, 511, 512, 513, 65536, 65537, 140_000):
        ids = np.random.default_rng(size).integers(0, n, size).astype(np.uint16)
        back, keys, counts = huffman.Reader()(huffman.to_file(code, ids, [7, None], [size, 0]))
        assert (back == ids).all() and keys == [7, None] and counts.tolist() == [size, 0]


def test_token_files(spark, sf):
    docs = sorted((r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect())
    got = {r.doc_id: r for r in huffman.op10_token_files(spark, sf).collect()}
    start = 0
    for key, text in docs:
        ids = want(text)
        assert (got[key].start, got[key].n_tokens, got[key].ids_crc32) == (start, len(ids), crc(ids))
        start += len(ids)


def test_token_files_odd_rows(spark):
    rows = [(k // 2 if k < 9 else None, t) for k, t in enumerate(TEXTS)]
    df = spark.createDataFrame([(*r, "x") for r in rows], "doc_id long, text string, ids string")
    ids = huffman.store(tokens.tokenize(df, tally=True), "ids")
    got = huffman.read(spark, huffman.write(ids)).collect()
    assert sorted((r.key is None, r.key or 0, r.ids_crc32) for r in got) == sorted((k is None, k or 0, crc(want(t))) for k, t in rows)
    ends = sorted((r.start, r.n_tokens) for r in got)
    assert all(a + n == b for (a, n), (b, _) in zip(ends, ends[1:], strict=False)) and ends[0][0] == 0
    empty = huffman.store(tokens.tokenize(df.limit(0), tally=True), "ids")
    assert huffman.read(spark, huffman.write(empty)).count() == 0


def test_token_files_of_rows_in_any_order(spark, monkeypatch):
    monkeypatch.setattr(huffman, "PER_FILE", 40)
    rows = [(k, f"text {k} " * (k % 7)) for k in range(60)] + [(30, "again"), (59, "last")]
    want_rows = None
    for order in (sorted(rows), list(reversed(rows)), random.Random(1).sample(rows, len(rows))):
        df = spark.createDataFrame(order, "doc_id long, text string").repartition(1) if order == sorted(rows) else spark.createDataFrame(order, "doc_id long, text string")
        ids = huffman.store(tokens.tokenize(df, tally=True), "ids")
        got = sorted((r.key, r.n_tokens, r.ids_crc32) for r in huffman.read(spark, huffman.write(ids), with_ids=False).collect())
        assert want_rows is None or got == want_rows
        want_rows = got
        at = 0
        for r in huffman.read(spark, huffman.write(ids), with_ids=False).orderBy("start").collect():
            assert r.start == at
            at += r.n_tokens
    assert want_rows == sorted((k, len(want(t)), crc(want(t))) for k, t in rows)
    keys = huffman.read(spark, huffman.write(ids), with_ids=False).orderBy("start").collect()
    assert [r.key for r in keys] == sorted(r.key for r in keys)


def test_token_files_need_nothing_but_their_path(spark, tmp_path):
    """A process that knows the path alone, and no Spark, reads the ids."""
    rows = [(k, f"some text {k} " * k) for k in range(20)]
    ids = huffman.store(tokens.tokenize(spark.createDataFrame(rows, "doc_id long, text string"), tally=True), "ids")
    path = huffman.write(ids, f"file://{tmp_path}/files")
    code = """
import sys, pyarrow.parquet as pq
from bitparse.llm.huffman import Reader
for payload in pq.read_table(sys.argv[1])["payload"].to_pylist():
    ids, keys, counts = Reader()(payload)
    at = 0
    for k, n in zip(keys, counts):
        print(k, *ids[at : at + n])
        at += n
"""
    out = subprocess.run([sys.executable, "-c", code, path.removeprefix("file://")], capture_output=True, text=True, check=True, cwd=Path(__file__).parents[2]).stdout
    got = {int(line.split()[0]): [int(x) for x in line.split()[1:]] for line in out.splitlines()}
    assert got == {k: want(t) for k, t in rows}


def test_other_tokenizers_are_encoded_as_they_are():
    import public_tokenizers

    path = public_tokenizers.path("byte_bpe_50k.json")
    plain, own = Tokenizer.from_file(path), tokens.Encoder(path)
    for t in [*TEXTS, "Hello, World  x", "x" * 3000]:
        assert np.frombuffer(own.texts([t.encode() if t is not None else None])[0], np.uint16).tolist() == plain.encode(t or "", add_special_tokens=False).ids


def check_pieces(pieces, docs, window=2048):
    by_doc, by_sequence = {}, {}
    for p in pieces:
        by_doc.setdefault(p.doc_id, []).append(p)
        by_sequence.setdefault(p.sequence_id, []).append(p)
    for key, text in docs:
        ids, at = want(text), 0
        for p in sorted(by_doc.pop(key), key=lambda p: p.start):
            assert (p.start, p.doc_tokens, p.ids_crc32) == (at, len(ids), crc(ids[at : at + p.length])) and p.length > 0
            at += p.length
        assert at == len(ids)
    assert not by_doc
    padding = 0
    for own in by_sequence.values():
        at = 0
        for p in sorted(own, key=lambda p: p.offset):
            assert p.offset == at
            at += p.length
        assert at <= window
        padding += 0 if at & (at - 1) == 0 else window - at
    assert padding == 0
    assert sorted(by_sequence) == list(range(len(by_sequence)))


def test_packing(spark, sf):
    docs = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    check_pieces(packing.op4_packing(spark, sf).collect(), docs)


def test_packing_odd_rows(spark, monkeypatch):
    monkeypatch.setattr(packing, "GROUP", 2)
    rows = [*enumerate(TEXTS), *((20 + k, "a b c") for k in range(30)), (60, "a " * 2047), (61, "a " * 9000), (62, "a " * 2045), (63, "a " * 1023), (64, "a " * 1023)]
    df = spark.createDataFrame([(*r, 1) for r in rows], "doc_id long, text string, start int")
    check_pieces(packing.pack_documents(df).collect(), rows)
    assert packing.pack_documents(df.limit(0)).count() == 0
    twice = packing.pack_documents(spark.createDataFrame([(1, "a"), (1, "a"), (None, "b")], "doc_id long, text string")).collect()
    assert len(twice) == 3


def test_least_squares_uses_the_histogram():
    rng = np.random.default_rng(3)
    hist = np.zeros(2048, np.int64)
    for a in rng.integers(1, 1024, 200):
        hist[a] += 5
        hist[2048 - a] += 5
    made = packing.plan(hist)
    assert made.planned.sum() >= 0.9 * hist.sum() and (made.planned <= hist).all()
