"""Spans against the plain patterns of the contract, checksums, and odd rows."""

import hashlib
import re

import pytest

from bitparse.llm import pii

PLAIN = {
    "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+",
    "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
    "card": r"[0-9]([\x20-]?[0-9])+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}


def brute(text):
    found = []
    for order, (kind, pattern) in enumerate(PLAIN.items()):
        for m in re.finditer(pattern, text):
            digits = re.sub("[^0-9]", "", m[0])
            total = sum(int(c) if k % 2 == 0 else sum(divmod(2 * int(c), 10)) for k, c in enumerate(reversed(digits)))
            ok = {"email": True, "ip": kind != "ip" or all(int(p) <= 255 for p in m[0].split(".")), "card": 12 <= len(digits) <= 19 and total % 10 == 0, "phone": 9 <= len(digits) <= 15}[kind]
            if ok:
                found.append((m.start(), order, kind, m.end()))
    return [(k, s, e) for s, _, k, e in sorted(found)]


TEXTS = [
    "", "a@b", "a@b.co", "a@b@c.com", "x..@d.e-f.g..h", "a@b.co@c.com d@e.f", "1.2.3.4.5.6.7.8 256.1.1.1 001.002.003.004",
    "4111 1111 1111 1111 and 4111-1111-1111-1112", "+1 (743) 555-3824. +12 +1((((((2 +49 (0) 170 1234567 8", "é@é.com mé.x@mail.example.com é", "1" * 5000 + "." + "2" * 50, "@" * 300, "+1" * 200,
]


@pytest.mark.parametrize("text", TEXTS)
def test_plain(text):
    got = [(s["kind"], s["start"], s["end"]) for s in pii.spans_of(text) if s["kind"] in pii.BASE_KINDS]
    assert got == brute(text)


def test_added_spans():
    kinds = lambda t: [s["kind"] for s in pii.spans_of(t) if s["kind"] not in pii.BASE_KINDS]
    assert kinds("iban GB82 WEST 1234 5698 7654 32 here") == ["iban"]
    assert kinds("iban GB82 WEST 1234 5698 7654 33 here") == []
    assert kinds("IBAN DE89 3704 0044 0532 0130 00 BIC COBADEFF") == ["iban"] and kinds("GB82 WEST 1234 5698 7654 32 NOW") == ["iban"]
    assert kinds("DE89370400440532013000") == ["iban"] and kinds("DE893704004405320130001") == [] and kinds("DE89 3704  0044 0532 0130 00") == []
    assert kinds("xDE89370400440532013000 DE89 3704 " + "DE89 3704 0044 0532 0130 00") == ["iban"]
    assert kinds("ssn 123-45-6789") == ["ssn"] and kinds("code 123-45-6789") == []
    assert pii.spans_of(None) == []


def test_context_is_whole_words_outside_the_span():
    score = lambda t: [s["score"] for s in pii.spans_of(t)][0]
    assert score("ship 1.2.3.4") == score("1.2.3.4") < score("ip 1.2.3.4") == score("1.2.3.4 (host)")
    key = "AKIA" + "ABCDEFGH" * 2
    assert score(key) < score("secret " + key) and score("mail@mail.de") < score("mail to a@b.de")


def test_documents(spark, sf):
    rows = pii.op1_pii(spark, sf).collect()
    docs = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    assert len(rows) == len(docs)
    for r in rows:
        want = brute(docs[r.doc_id])
        assert r.base_sha256 == hashlib.sha256(",".join(f"{k}:{s}:{e}" for k, s, e in want).encode()).hexdigest()
        assert r.n_email == sum(k == "email" for k, *_ in want)


def test_odd_rows(spark):
    df = spark.createDataFrame([(1, None, "x"), (1, "a@b.co", "y"), (1, "a@b.co", "y"), (None, "", None)], "doc_id long, text string, spans string")
    assert sorted(r.n_email for r in pii.digest(pii.scan(df)).collect()) == [0, 0, 1, 1]
    assert pii.scan(df.limit(0)).count() == 0
    assert {r.text for r in pii.redact(df).collect()} == {None, "", "<email>"}
