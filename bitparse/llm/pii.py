"""Personal data: patterns propose spans, checksums confirm them, words nearby adjust their score.

Defined results: a null or empty text has no spans. Every row gives one row, so repeated rows
give repeated rows. Only the text column is scanned; other columns pass through ``scan`` unread.
Positions count code points, the end is exclusive. Work is linear in the text, also for very
long runs of digits or of letters: each pattern is anchored where a match can begin.
"""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from bitparse.llm.common import chunks, fresh, table

BASE_KINDS = ("email", "ip", "card", "phone")
KINDS = (*BASE_KINDS, "iban", "ssn", "secret")
SPANS = "spans array<struct<kind:string,start:bigint,end:bigint,score:double>>"
#: Score of a confirmed match, before the words nearby; a span is kept from THRESHOLD on.
SCORE = {"email": 0.9, "ip": 0.7, "card": 0.8, "phone": 0.6, "iban": 0.9, "ssn": 0.3, "secret": 0.5}
THRESHOLD, NEAR = 0.5, 40
#: Whole words before or after a span that speak for its kind.
CONTEXT = {
    "email": ("mail", "email", "e-mail", "contact"), "ip": ("ip", "address", "host"), "card": ("card", "visa", "credit", "payment"),
    "phone": ("phone", "call", "tel", "mobile"), "iban": ("iban", "account", "bank"),
    "ssn": ("ssn", "social security"), "secret": ("password", "secret", "token", "key"),
}
_CONTEXT = {kind: re.compile(rf"(?<![A-Za-z0-9])(?:{'|'.join(words)})(?![A-Za-z0-9])", re.IGNORECASE) for kind, words in CONTEXT.items()}
#: The length of an account number by its country.
IBAN_LENGTH = {
    "AD": 24, "AE": 23, "AL": 28, "AT": 20, "AZ": 28, "BA": 20, "BE": 16, "BG": 22, "BH": 22, "BR": 29, "BY": 28, "CH": 21, "CR": 22, "CY": 28, "CZ": 24,
    "DE": 22, "DK": 18, "DO": 28, "EE": 20, "EG": 29, "ES": 24, "FI": 18, "FO": 18, "FR": 27, "GB": 22, "GE": 22, "GI": 23, "GL": 18, "GR": 27, "GT": 28,
    "HR": 21, "HU": 28, "IE": 22, "IL": 23, "IQ": 23, "IS": 26, "IT": 27, "JO": 30, "KW": 30, "KZ": 20, "LB": 28, "LC": 32, "LI": 21, "LT": 20, "LU": 20,
    "LV": 21, "MC": 27, "MD": 24, "ME": 22, "MK": 19, "MR": 27, "MT": 31, "MU": 30, "NL": 18, "NO": 15, "PK": 24, "PL": 28, "PS": 29, "PT": 25, "QA": 29,
    "RO": 24, "RS": 22, "SA": 24, "SE": 24, "SI": 19, "SK": 24, "SM": 27, "TN": 24, "TR": 26, "UA": 29, "VA": 22, "VG": 24, "XK": 20,
}

_PLAIN_CAPITAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789")
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++")
_IP = re.compile(r"(?<![0-9])([0-9]++)\.([0-9]++)\.([0-9]++)\.([0-9]++)")
_CARD = re.compile(r"[0-9](?:[ -]?[0-9])++")
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
_IBAN = re.compile(r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?=(?: ?[A-Z0-9]){11})")
_SSN = re.compile(r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])")
_SECRET = re.compile(r"(?<![A-Za-z0-9])(?:AKIA[0-9A-Z]{16}|(?<=password=)[^\s]{8,64})(?![A-Za-z0-9])")
_NOT_DIGIT = re.compile(r"[^0-9]+")
_LUHN = [sum(divmod(2 * d, 10)) for d in range(10)]


def luhn(digits: str) -> bool:
    """Whether the last digit is the check digit of those before it."""
    own = [int(c) for c in digits]
    return (sum(own[-1::-2]) + sum(_LUHN[d] for d in own[-2::-2])) % 10 == 0


def mod97(account: str) -> bool:
    """Whether an account number, its first four characters moved to the end and letters read as 10 to 35, is 1 modulo 97."""
    plain = account.replace(" ", "")
    return int("".join(str(int(c, 36)) for c in plain[4:] + plain[:4])) % 97 == 1


def _emails(text: str) -> Iterator[tuple[int, int]]:
    end, at = 0, text.find("@")
    while at >= 0:
        start = at
        while start > end and text[start - 1] in _LOCAL:
            start -= 1
        if start < at and (m := _DOMAIN.match(text, at)):
            end = m.end()
            yield start, end
            at = text.find("@", end)
        else:
            end = at  # what stands before this sign can't begin a later match
            at = text.find("@", at + 1)


def _ibans(text: str) -> Iterator[tuple[int, int]]:
    """Account numbers of their country's length, in groups or not, whatever capitals follow behind a space."""
    end = 0
    for m in _IBAN.finditer(text):
        start = at = m.start()
        left = IBAN_LENGTH.get(m[0][:2], 0)
        if start < end or not left:
            continue
        while left and at < len(text):
            c = text[at]
            if c in _PLAIN_CAPITAL:
                left -= 1
            elif c != " " or text[at - 1] == " ":
                break
            at += 1
        if not left and not (at < len(text) and text[at].isascii() and text[at].isalnum()) and mod97(text[start:at]):
            end = at
            yield start, end


def _matches(pattern: re.Pattern, confirmed: Callable[[re.Match], bool]) -> Callable[[str], Iterator[tuple[int, int]]]:
    return lambda text: (m.span() for m in pattern.finditer(text) if confirmed(m))


def _small(part: str) -> bool:
    part = part.lstrip("0")
    return len(part) < 3 or (len(part) == 3 and part <= "255")


def _digits(m: re.Match) -> str:
    return _NOT_DIGIT.sub("", m[0])


_PROPOSE: dict[str, Callable[[str], Iterator[tuple[int, int]]]] = {
    "email": _emails,
    "ip": _matches(_IP, lambda m: all(map(_small, m.groups()))),
    "card": _matches(_CARD, lambda m: 12 <= len(d := _digits(m)) <= 19 and luhn(d)),
    "phone": _matches(_PHONE, lambda m: 9 <= len(_digits(m)) <= 15),
    "iban": _ibans,
    "ssn": _matches(_SSN, lambda m: m[0][:3] not in ("000", "666") and m[0][0] != "9"),
    "secret": _matches(_SECRET, lambda m: True),
}


def spans_of(text: str | None) -> list[dict]:
    """All kept spans of a text, by start and then by kind as listed."""
    if not text:
        return []
    found = []
    has_digit = any(c in text for c in "0123456789")
    for order, kind in enumerate(KINDS):
        if kind in ("ip", "card", "phone", "iban", "ssn") and not has_digit:
            continue
        for start, end in _PROPOSE[kind](text):
            near = _CONTEXT[kind].search(text, max(0, start - NEAR), start) or _CONTEXT[kind].search(text, end, end + NEAR)
            score = min(1.0, SCORE[kind] + 0.3 * bool(near))
            if score >= THRESHOLD or kind in BASE_KINDS:
                found.append((start, order, kind, end, score))
    return [{"kind": kind, "start": start, "end": end, "score": score} for start, _, kind, end, score in sorted(found)]


def scan(df: DataFrame, text: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The kept columns of each row and its spans (kind, start, end, score)."""
    body = fresh(df, "body")
    own = df.select(*keep, F.col(text).alias(body))
    schema = T.StructType([*own.drop(body).schema, *T.StructType.fromDDL(SPANS)])
    kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64()), ("score", pa.float64())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo, hi in chunks(pc.fill_null(pc.binary_length(batch[body]), 0).to_pylist(), 8 << 20):
                part = batch.slice(lo, hi - lo)
                spans = pa.array([spans_of(t) for t in part[body].to_pylist()], kind)
                yield pa.RecordBatch.from_arrays([*(part[k] for k in keep), spans], [*keep, "spans"])

    return own.mapInArrow(run, schema)


def redact(df: DataFrame, text: str = "text") -> DataFrame:
    """The rows with every span replaced by its kind in angle brackets; of overlapping spans the first counts."""

    def clean(value: str | None) -> str | None:
        if value is None:
            return None
        parts, end = [], 0
        for s in spans_of(value):
            if s["start"] >= end:
                parts += [value[end : s["start"]], f"<{s['kind']}>"]
                end = s["end"]
        return "".join(parts) + value[end:]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            k = batch.schema.get_field_index(text)
            yield batch.set_column(k, text, pa.array([clean(t) for t in batch[k].to_pylist()], batch.schema.field(k).type))

    return df.mapInArrow(run, df.schema)


def digest(found: DataFrame) -> DataFrame:
    """Counts and digests of the spans of each row."""
    joined = lambda spans: F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")
    base = F.filter("spans", lambda s: s["kind"].isin(*BASE_KINDS))
    of_kind = lambda kind: F.filter("spans", lambda s: s["kind"] == kind)
    counts = [F.size(of_kind(kind)).cast("long").alias(f"n_{kind}") for kind in BASE_KINDS]
    return found.select("doc_id", *counts, F.sha2(joined(base).cast("binary"), 256).alias("base_sha256"), joined(F.col("spans")).alias("spans"), F.array_max(F.transform("spans", lambda s: s["score"])).alias("max_score"))


def op1_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digest(scan(table(spark, sf_dir, "documents").select("doc_id", "text")))
