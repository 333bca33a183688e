"""Language identification by unigrams of pieces, summed over all segmentations.

A language gives each piece of a fixed public vocabulary a probability. A word's probability is
the sum, over all ways to cut it into pieces, of the product of their probabilities; a forward
pass over the word computes it. A text's is the product over its words. The piece probabilities
are fitted by expectation maximisation on the words of a bounded sample of labelled rows:
at most DOCS_PER_LANG rows and CHARS_PER_LANG characters of each language, the rows chosen by a
hash of their id. Prediction reads whole texts and nothing but texts.

Words are runs of letters, in lower case; a word of over LONGEST letters counts as words of that
length. Word scores are kept in a bounded table, so each distinct word is computed once or rarely.

Defined results: ``und`` with score 0 for a null text and one without a letter; every row gives a
row; no labelled row at all makes every prediction ``und``.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from bitparse.llm import tokens
from bitparse.llm.common import as_bytes, chunks, giving_back, table, with_text

DOCS_PER_LANG, CHARS_PER_LANG, ROUNDS, LONGEST, PLAIN_RANGE = 400, 2_000_000, 4, 48, 24
VOCABULARY = "piece_bpe_32k.model"
UNKNOWN, KEPT_WORDS, PART = 1e-7, 400_000, 1 << 20
_PRIME, _NONE = np.uint64(0x9E3779B97F4A7C15), np.zeros(0, np.uint64)
#: ASCII letters in lower case, bytes of other letters as they are, and a space for all else.
_PLAIN = bytes(c + 32 if 65 <= c <= 90 else c if 97 <= c <= 122 or c >= 128 else 32 for c in range(256))


def pieces(path: str) -> list[str]:
    """The vocabulary: pieces of letters of a public model in lower case, with the word mark as it stands there."""
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    own = {model.id_to_piece(k).lower() for k in range(model.get_piece_size())}
    return sorted(p for p in own if all(c.isalpha() or c == "▁" for c in p) and p.strip("▁"))


def letters(word: str) -> list[str]:
    """The words of letters that stand in a piece of text without ASCII white space."""
    out = "".join(c if c.isalpha() else " " for c in word.lower()).split()
    return [w[k : k + LONGEST] for w in out for k in range(0, len(w), LONGEST)]


def _codes(words: list[str]) -> np.ndarray:
    n = len(words[0]) + 1
    return np.frombuffer("".join("▁" + w for w in words).encode("utf-32-le"), np.uint32).reshape(-1, n).astype(np.uint64)


def _hashes(codes: np.ndarray) -> tuple[np.ndarray, list[np.uint64]]:
    """Prefix hashes of each row, and the powers that join them."""
    prefix = np.zeros((codes.shape[0], codes.shape[1] + 1), np.uint64)
    power = [np.uint64(1)]
    with np.errstate(over="ignore"):
        for k in range(codes.shape[1]):
            prefix[:, k + 1] = prefix[:, k] * _PRIME + codes[:, k] + np.uint64(1)
            power.append(power[-1] * _PRIME)
    return prefix, power


class Model:
    """Piece probabilities of each language. The last row is that of an unknown character."""

    def __init__(self, vocabulary: list[str], langs: list[str]):
        by_length: dict[int, list[str]] = {}
        for p in vocabulary:
            by_length.setdefault(len(p), []).append(p)
        self.longest, total = max(by_length, default=1), 0
        self.keys: dict[int, tuple[np.ndarray, int]] = {}  # of each length the sorted hashes, and the row of the first
        for n, ps in sorted(by_length.items()):
            own = np.unique(_hashes(np.frombuffer("".join(ps).encode("utf-32-le"), np.uint32).reshape(-1, n).astype(np.uint64))[0][:, -1])
            self.keys[n] = own, total
            total += len(own)
        self.langs = langs
        self.table = np.full((total + 1, len(langs)), 1 / (total + 1))

    def lattice(self, words: list[str]) -> list[tuple[int, int, np.ndarray, np.ndarray]]:
        """For words of one length: start, end, the words that have a piece there, and its row."""
        prefix, power = _hashes(_codes(words))
        n, out = prefix.shape[1] - 1, []
        everyone = np.arange(len(words))
        for end in range(1, n + 1):
            for start in range(max(0, end - self.longest), end):
                if end - start > 1 and end - start not in self.keys:
                    continue
                with np.errstate(over="ignore"):
                    h = prefix[:, end] - prefix[:, start] * power[end - start]
                keys, first = self.keys.get(end - start, (_NONE, 0))
                at = np.searchsorted(keys, h)
                at[at == len(keys)] = 0
                here = keys[at] == h if len(keys) else np.zeros(len(h), bool)
                if end - start == 1:
                    out.append((start, end, everyone, np.where(here, at + first, len(self.table) - 1)))
                elif here.any():
                    own = np.flatnonzero(here)
                    out.append((start, end, own, at[own] + first))
        return out

    def forward(self, words: list[str], edges: list) -> tuple[np.ndarray, np.ndarray]:
        """Scaled prefix sums, by position, word and language, and their logarithmic scale."""
        n = len(words[0]) + 1
        alpha = np.zeros((n + 1, len(words), len(self.langs)))
        alpha[0], scale, last = 1, np.zeros((len(words), len(self.langs))), 0
        for start, end, own, row in edges:
            if end != last and last and last % 12 == 0:
                most = alpha[max(0, last - self.longest) : last + 1].max(axis=0)
                alpha[max(0, last - self.longest) : last + 1] /= most
                scale += np.log(most)
            last = end
            alpha[end, own] += alpha[start, own] * self.table[row]
        return alpha, scale

    def log_probability(self, words: list[str]) -> np.ndarray:
        """Of each word, in any order and of any length: a row of the languages' log-probabilities."""
        out = np.zeros((len(words), len(self.langs)))
        by_length: dict[int, list[int]] = {}
        for k, w in enumerate(words):
            by_length.setdefault(len(w), []).append(k)
        for rows in by_length.values():
            for lo in range(0, len(rows), 4096):
                part = rows[lo : lo + 4096]
                own = [words[k] for k in part]
                alpha, scale = self.forward(own, self.lattice(own))
                out[part] = np.log(np.maximum(alpha[-1], 1e-300)) + scale
        return out

    def fit(self, counts: list[dict[str, int]], rounds: int = ROUNDS) -> Model:
        """Expectation maximisation, for each language on its own word counts."""
        every = sorted({w for c in counts for w in c}, key=len)
        groups: dict[int, list[str]] = {}
        for w in every:
            groups.setdefault(len(w), []).append(w)
        parts = [own[lo : lo + 4096] for own in groups.values() for lo in range(0, len(own), 4096)]
        for _ in range(rounds):
            expected = np.full_like(self.table, 1e-3)
            expected[-1] = 1e-2
            for own in parts:
                weight = np.array([[c.get(w, 0) for c in counts] for w in own], float)
                edges = self.lattice(own)
                # the least product of a long word needs the range of extended precision
                alpha = np.zeros((len(own[0]) + 2, len(own), len(self.langs)), np.float64 if len(own[0]) <= PLAIN_RANGE else np.longdouble)
                beta = np.zeros_like(alpha)
                alpha[0] = beta[-1] = 1
                for start, end, rows, piece in edges:
                    alpha[end, rows] += alpha[start, rows] * self.table[piece]
                for start, end, rows, piece in sorted(edges, key=lambda e: -e[0]):
                    beta[start, rows] += beta[end, rows] * self.table[piece]
                share = weight / np.maximum(alpha[-1], np.finfo(alpha.dtype).tiny)
                for start, end, rows, piece in edges:
                    np.add.at(expected, piece, alpha[start, rows] * self.table[piece] * beta[end, rows] * share[rows])
            self.table = np.maximum(expected / expected.sum(axis=0), UNKNOWN * 1e-2)
        return self


class Scorer:
    """Scores texts, with a bounded table of word scores."""

    def __init__(self, model: Model):
        self.model, self.known = model, {}
        self.rows = np.zeros((0, len(model.langs) + 1))

    def _learn(self, missing: list[bytes]) -> None:
        if len(self.known) + len(missing) > KEPT_WORDS:
            self.known, self.rows = {}, np.zeros((0, len(self.model.langs) + 1))
        parts = [letters(w.decode("utf-8", "replace")) for w in missing]
        flat = sorted({w for p in parts for w in p})
        at = {w: k for k, w in enumerate(flat)}
        log = self.model.log_probability(flat) if flat else np.zeros((0, len(self.model.langs)))
        new = np.zeros((len(missing), self.rows.shape[1]))
        for k, p in enumerate(parts):
            for w in p:
                new[k, :-1] += log[at[w]]
                new[k, -1] += len(w)
        self.known.update(zip(missing, range(len(self.rows), len(self.rows) + len(missing)), strict=True))
        self.rows = np.concatenate([self.rows, new])

    def _totals(self, plain: list[bytes]) -> list[np.ndarray]:
        """Of each piece of text the sum of its words' scores and letters."""
        split = [x.split() for x in plain]
        missing = set().union(*split).difference(self.known)
        if missing:
            if len(self.known) + len(missing) > KEPT_WORDS:  # all words of these texts have to be known at once
                missing = set().union(*split)
            self._learn(list(missing))
        out = []
        for own in split:
            total = np.zeros(self.rows.shape[1])
            for lo in range(0, len(own), 1 << 16):
                part = own[lo : lo + (1 << 16)]
                total += self.rows[np.fromiter(map(self.known.__getitem__, part), np.int64, len(part))].sum(axis=0)
            out.append(total)
        return out

    def texts(self, raw: list[bytes | None]) -> tuple[list[str], list[float]]:
        """Predictions and scores. Words are held of about PART bytes of text at a time, of longer texts piece by piece."""
        totals = []
        for lo, hi in chunks([len(x or b"") for x in raw], PART):
            plain = [x.translate(_PLAIN) if x else b"" for x in raw[lo:hi]]
            if len(plain) > 1 or len(plain[0]) <= PART:
                totals += self._totals(plain)
                continue
            total, at, text = np.zeros(self.rows.shape[1]), 0, plain[0]
            while at < len(text):
                end = text.find(b" ", at + PART)
                end = len(text) if end < 0 else end
                total = total + self._totals([text[at:end]])[0]
                at = end
            totals.append(total)
        langs, scores = [], []
        for total in totals:
            if not total[-1] or not self.model.langs:
                langs.append("und")
                scores.append(0.0)
                continue
            log = total[:-1] - total[:-1].max()
            k = int(np.argmax(log))
            langs.append(self.model.langs[k])
            scores.append(float(1 / np.exp(log).sum()))
        return langs, scores


def train(labelled: DataFrame, vocabulary: str | None = None) -> Model:
    """A model from rows of doc_id, text and lang, by a bounded sample of each language."""
    import public_tokenizers

    labelled = labelled.filter("lang is not null and text is not null")
    counts = {r["lang"]: r["count"] for r in labelled.groupBy("lang").count().collect()}
    langs = sorted(counts)
    vocabulary = pieces(vocabulary or public_tokenizers.path(VOCABULARY))
    if not langs:
        return Model([], [])
    share = F.create_map(*[x for k in langs for x in (F.lit(k), F.lit(min(1.0, 2 * DOCS_PER_LANG / counts[k]) * (1 << 31)))])
    draw = F.pmod(F.xxhash64(F.lit("langid"), F.col("doc_id")), F.lit(1 << 31))
    rows = labelled.filter(draw < share[F.col("lang")]).select("doc_id", "lang", "text", draw.alias("draw"))
    taken, own = {k: [0, 0] for k in langs}, {k: {} for k in langs}
    for r in rows.orderBy("draw", "doc_id", "text").toLocalIterator():
        used = taken[r["lang"]]
        if used[0] < DOCS_PER_LANG and used[1] < CHARS_PER_LANG:
            used[0] += 1
            used[1] += len(r["text"])
            for w in letters(r["text"]):
                own[r["lang"]][w] = own[r["lang"]].get(w, 0) + 1
    return Model(vocabulary, langs).fit([own[k] for k in langs])


def identify(df: DataFrame, model: Model, text: str = "text", keep: tuple[str, ...] = ("doc_id",), names: tuple[str, str] = ("lang_pred", "score")) -> DataFrame:
    """The kept columns, and the prediction and its score under ``names``."""
    own, body, kept = with_text(df, keep, text)
    schema = T.StructType([*kept, T.StructField(names[0], T.StringType()), T.StructField(names[1], T.DoubleType())])
    shared = df.sparkSession.sparkContext.broadcast(model)  # bounded by the vocabulary and the labels

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokens.release()
        scorer = Scorer(shared.value)
        for batch in batches:
            for lo in range(0, batch.num_rows, 256):
                part = batch.slice(lo, 256)
                langs, scores = scorer.texts(as_bytes(part[body]))
                yield pa.RecordBatch.from_arrays([*(part[k] for k in keep), pa.array(langs, pa.string()), pa.array(scores, pa.float64())], [*keep, *names])

    return own.mapInArrow(giving_back(run), schema)


def remainder(key: str = "doc_id"):
    return F.crc32(F.col(key).cast("string").cast("binary")) % 3


def op5_langid(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    model = train(docs.filter(remainder() != 1))
    return identify(docs, model).select("doc_id", F.coalesce(remainder() == 1, F.lit(False)).alias("held_out"), "lang_pred", "score")
