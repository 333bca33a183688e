"""Masked pseudo-likelihood of texts by a bidirectional window network, trained in numpy.

Every word of a text is masked in turn and predicted from the SIDE words on either side of it. The
hidden layer is tanh of the neighbours' vectors, each weighted by its place; the output is a tree of
three softmax levels over the places of the vocabulary. A text's score is the sum of the conditional
log-probabilities of all its words.

The vocabulary is the GROWTH * N^(1/3) most frequent words of the N words of all texts, so it grows with the
input and stays small enough to be broadcast (0.4 million words for 10^13). Every other word has the
place of its length in bytes, and there its own probability: SHARE of its share of all words of that
place, counted over all texts, and the rest by a model of spelling (pairs of neighbouring bytes,
counted over all texts). The counts are a distributed table that occurrences are joined to; the places'
probabilities and the spellings each sum to one.

Training takes every word of every text as a target once. Texts are dealt to shards of about SHARD
words by a hash of key and text, in ROUNDS rounds; in a round each shard trains from the same start, in
the order of its hashes, and the shards' parameters are averaged in fixed point. So the network
depends on the rows alone, not on how they lie in files or partitions.

Defined results: null texts and texts without a word have n_words 0 and score 0; every row gives a
row; with no texts at all there are no rows. Words are those of decontamination: lower-case ASCII
letters, digits and all characters outside ASCII.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from bitparse.llm.common import as_bytes, chunks, store, table
from bitparse.llm.decontaminate import Words

WIDTH, SIDE, BATCH, RATE, CHUNK, SUMS = 16, 2, 16_384, 0.2, 1 << 20, 4096
GROWTH, LENGTHS, SHARE, SHARD, ROUNDS, FIXED = 16, 16, 0.9, 2_000_000, 4, 1 << 24
MOST = 4.0
#: Bytes of words as symbols of spellings: 0 is the start, digits, letters, then bytes from 128 on.
_SYMBOL = np.zeros(256, np.uint16)
_SYMBOL[[*range(48, 58), *range(97, 123), *range(128, 256)]] = np.arange(1, 165)
SYMBOLS = 165


def pairs_of(plain: bytes) -> np.ndarray:
    """Of each byte the symbol before it, times SYMBOLS, and its own."""
    sym = _SYMBOL.take(np.frombuffer(plain, np.uint8))
    out = sym.copy()
    out[1:] += sym[:-1] * np.uint16(SYMBOLS)
    return out


@dataclass
class Vocabulary:
    """The places of frequent words, by hash, after those of the lengths of all others; and the spelling of words."""

    keys: np.ndarray  # sorted hashes
    places: np.ndarray
    spelling: np.ndarray  # log p(symbol | symbol before), flat
    longer: float  # how likely a word of LENGTHS bytes or more goes on
    words: int  # of all texts

    @staticmethod
    def of(frequent: list[int], pairs: np.ndarray, long_words: int, beyond: int, words: int) -> Vocabulary:
        own = np.array(frequent, np.int64).view(np.uint64)
        order = np.argsort(own)
        counts = pairs.reshape(SYMBOLS, SYMBOLS)[:, 1:] + 0.5
        log = np.zeros((SYMBOLS, SYMBOLS))
        log[:, 1:] = np.log(counts / counts.sum(axis=1, keepdims=True))
        return Vocabulary(own[order], (LENGTHS + np.arange(len(own), dtype=np.int32))[order], log.ravel(), (beyond + 0.5) / (beyond + long_words + 1), words)

    @property
    def size(self) -> int:
        return LENGTHS + len(self.keys)

    @property
    def kind(self) -> str:
        """How places are stored."""
        return "<u2" if self.size < 1 << 16 else "<u4"

    def __call__(self, words: Words) -> np.ndarray:
        """The place of each word."""
        out = np.minimum(words.ends - words.starts, LENGTHS).astype(np.int32) - 1
        if len(self.keys):
            at = np.minimum(np.searchsorted(self.keys, words.hash), len(self.keys) - 1)
            out = np.where(self.keys[at] == words.hash, self.places[at], out)
        return out

    def spelled(self, words: Words) -> np.ndarray:
        """log p(bytes | place of the length) of each word."""
        total = np.concatenate(([0.0], np.cumsum(self.spelling.take(pairs_of(words.plain)))))
        size = words.ends - words.starts
        tail = np.where(size >= LENGTHS, (size - LENGTHS) * np.log(self.longer) + np.log1p(-self.longer), 0.0)
        return total[words.ends] - total[words.starts] + tail


class Around:
    """The words around the places of some texts, with pads beyond the ends of each text."""

    def __init__(self, x: np.ndarray, text: np.ndarray, pad: int, side: int = SIDE):
        number = np.cumsum(np.concatenate(([0], text[1:] != text[:-1])))[: len(x)]
        self.side, self.at = side, np.arange(len(x)) + side * (number + 1)
        self.padded = np.full(len(x) + side * (int(number.max(initial=0)) + 2), pad, np.int32)
        self.padded[self.at] = x

    def __call__(self, at: np.ndarray) -> np.ndarray:
        """A row a place; in memory a column after the other."""
        own, out = self.at[at], np.empty((2 * self.side, len(at)), np.int32)
        for k, step in enumerate([*range(-self.side, 0), *range(1, self.side + 1)]):
            out[k] = self.padded.take(own + step)
        return out.T


def neighbours(x: np.ndarray, text: np.ndarray, at: np.ndarray, pad: int, side: int = SIDE) -> np.ndarray:
    """The words around each place ``at``, with pads beyond the ends of its text."""
    return Around(x, text, pad, side)(at)


def packed(sums: np.ndarray) -> bytes:
    """Integers byte by byte, the lowest of all first, so that the mostly equal high ones compress."""
    return sums.astype("<i8").view(np.uint8).reshape(-1, 8).T.tobytes()


def unpacked(raw: bytes) -> np.ndarray:
    return np.ascontiguousarray(np.frombuffer(raw, np.uint8).reshape(8, -1).T).view("<i8").ravel()


class Net:
    """The network for a vocabulary of ``size`` places; the pad is place ``size``."""

    def __init__(self, size: int, flat: np.ndarray | None = None, seen: np.ndarray | None = None, kind: type = np.float32):
        self.size, k = size, 2
        while k**3 < size:
            k += 1
        self.k = k
        shapes = {"vectors": (size + 1, WIDTH), "place": (2 * SIDE, WIDTH), "bias": (WIDTH,), "top": (1, k, WIDTH + 1), "middle": (k, k, WIDTH + 1), "leaf": (k * k, k, WIDTH + 1)}
        total = sum(int(np.prod(s)) for s in shapes.values())
        if flat is None:
            flat = np.random.default_rng(11).normal(0, 0.1, total)
        self.flat = flat.astype(kind)
        self.grads = np.zeros_like(self.flat)
        self.seen = np.full_like(self.flat, 1e-6) if seen is None else seen.astype(kind)
        self.p, self.g, at = {}, {}, 0
        for name, shape in shapes.items():
            n = int(np.prod(shape))
            self.p[name], self.g[name] = self.flat[at : at + n].reshape(shape), self.grads[at : at + n].reshape(shape)
            at += n

    def hidden(self, around: list[np.ndarray]) -> np.ndarray:
        """The hidden layer, and a one behind it for the levels' biases; around: the words of each place of the window."""
        vectors, n = self.p["vectors"], len(around[0])
        z = np.broadcast_to(self.p["bias"], (n, WIDTH)).copy()
        for own, place in zip(around, self.p["place"], strict=True):
            z += (vectors * place).take(own, axis=0) if n >= len(vectors) else vectors.take(own, axis=0) * place
        out = np.ones((n, WIDTH + 1), z.dtype)
        np.tanh(z, out=out[:, :-1])
        return out

    def _level(self, name: str, h: np.ndarray, node: np.ndarray, child: np.ndarray, dh: np.ndarray | None) -> np.ndarray:
        """log p(child | node) of rows sorted by node; with ``dh``, adds the gradients."""
        first = np.flatnonzero(np.concatenate(([True], node[1:] != node[:-1])))
        cuts = list(zip(node[first].tolist(), first.tolist(), [*first[1:].tolist(), len(node)], strict=True))
        weights, logits = self.p[name], np.empty((len(h), self.k), h.dtype)
        turned = weights.transpose(0, 2, 1)
        if len(h) >= turned.shape[0] * self.k:
            turned = np.ascontiguousarray(turned)  # products of few rows are faster so
        for n, lo, hi in cuts:
            np.dot(h[lo:hi], turned[n], out=logits[lo:hi])
        flat, at = logits.ravel(), np.arange(len(h)) * self.k + child
        own = flat.take(at)
        np.exp(logits, out=logits)
        total = logits @ np.ones(self.k, h.dtype)
        if dh is not None:
            logits /= total[:, None]
            flat[at] -= 1
            grads, sums, add = self.g[name], np.empty(weights.shape[1:], h.dtype), np.empty_like(dh)
            for n, lo, hi in cuts:
                part = logits[lo:hi]
                grads[n] += np.dot(part.T, h[lo:hi], out=sums)
                np.dot(part, weights[n], out=add[lo:hi])
            dh += add
        return own - np.log(total)

    def log_probability(self, around: np.ndarray, target: np.ndarray, learn: bool = False) -> np.ndarray:
        """log p(place | both sides) of each target; with ``learn``, adds the gradient of their sum's negative."""
        out = np.empty(len(target), self.flat.dtype)
        if not len(target):
            return out
        kind = np.uint16 if self.size < 1 << 16 else np.int64  # 16 bits sort by digits
        order = np.argsort(target.astype(kind), kind="stable")
        around, target = [own.take(order) for own in around.T], target.take(order).astype(np.int64)
        h = self.hidden(around)
        dh = np.zeros_like(h) if learn else None
        leaf, middle = target // self.k, target // self.k**2
        log = self._level("top", h, np.zeros_like(target), middle, dh)
        log += self._level("middle", h, middle, leaf % self.k, dh)
        log += self._level("leaf", h, leaf, target % self.k, dh)
        out[order] = log
        if learn:
            dz = dh * (1 - h * h)  # its last column, of the ones, is zero
            self.g["bias"] += dz.sum(axis=0)[:-1]
            for k, own in enumerate(around):
                by = np.argsort(own.astype(kind), kind="stable")
                at = own.take(by)
                first = np.flatnonzero(np.concatenate(([True], at[1:] != at[:-1])))
                word, sums = at[first], np.add.reduceat(dz.take(by, axis=0), first, axis=0)[:, :-1]  # a row a word that occurs there
                self.g["place"][k] += np.einsum("ij,ij->j", sums, self.p["vectors"][word])
                self.g["vectors"][word] += sums * self.p["place"][k]
        return out

    def step(self, n: int, rate: float = RATE) -> None:
        self.grads /= max(1, n)
        self.seen += self.grads * self.grads
        self.flat -= rate * self.grads / np.sqrt(self.seen)
        np.clip(self.flat, -MOST, MOST, out=self.flat)  # so that no exponential overflows
        self.grads[:] = 0

    def learn(self, texts: list[np.ndarray]) -> None:
        """One pass over all words of some texts, in an order that follows from their number."""
        x = np.concatenate(texts).astype(np.int32)
        text = np.repeat(np.arange(len(texts)), [len(t) for t in texts])
        own, batch = np.random.default_rng(len(x)).permutation(len(x)), BATCH * (1 + self.size // (1 << 14))
        around = Around(x, text, self.size)
        for lo in range(0, len(own), batch):
            at = own[lo : lo + batch]
            self.log_probability(around(at), x[at], learn=True)
            self.step(len(at))


def _word_chunks(batches: Iterator[pa.RecordBatch], column: str) -> Iterator[tuple[pa.RecordBatch, Words]]:
    for batch in batches:
        raw = as_bytes(batch[column])
        for lo, hi in chunks([len(t or b"") for t in raw], CHUNK):
            yield batch.slice(lo, hi - lo), Words(raw[lo:hi])


def vocabulary(texts: DataFrame, text: str = "text") -> tuple[Vocabulary, DataFrame]:
    """The vocabulary of all texts, and the stored (word, share): of each word outside it the share of all such words of its length."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, ...]] = []
        pairs, lengths = np.zeros(SYMBOLS * SYMBOLS, np.int64), np.zeros(2, np.int64)

        def merged():
            keys, n, size = (np.concatenate(x) for x in zip(*held, strict=True))
            own, first, at = np.unique(keys, return_index=True, return_inverse=True)
            return own, np.bincount(at, n, len(own)).astype(np.int64), size[first]

        def rows(kind, own, n, size):
            return pa.RecordBatch.from_arrays([pa.array(np.full(len(own), kind, np.int8)), pa.array(own.view(np.int64)), pa.array(n), pa.array(size.astype(np.int8))], ["kind", "word", "n", "size"])

        for _, words in _word_chunks(batches, text):
            pairs += np.bincount(pairs_of(words.plain), minlength=SYMBOLS * SYMBOLS)
            size = words.ends - words.starts
            lengths += ((size >= LENGTHS).sum(), np.maximum(size - LENGTHS, 0).sum())
            own, first, n = np.unique(words.hash, return_index=True, return_counts=True)
            held.append((own, n, np.minimum(size[first], LENGTHS)))
            if len(held) >= 16:
                held[:] = [merged()]
                if len(held[0][0]) > 1_000_000:
                    yield rows(0, *held[0])
                    held.clear()
        if held:
            yield rows(0, *merged())
            pairs[::SYMBOLS] = 0  # ends of words
            seen = np.flatnonzero(pairs)
            yield rows(1, seen, pairs[seen], np.zeros(len(seen)))
            yield rows(2, np.arange(2), lengths, np.zeros(2))

    counted = store(texts.select(text).mapInArrow(run, "kind byte, word long, n long, size byte").groupBy("kind", "word").agg(F.sum("n").alias("n"), F.min("size").alias("size")), "words")
    counts = counted.filter("kind = 0").select("word", "n", "size")
    totals = np.zeros(LENGTHS + 1)
    for r in counts.groupBy("size").agg(F.sum("n").alias("n")).collect():  # a row a length
        totals[r["size"]] = r["n"]
    words = int(totals.sum())
    frequent = counts.orderBy(F.desc("n"), "word").limit(int(GROWTH * words ** (1 / 3))).collect()  # the cube root of the words
    for r in frequent:
        totals[r["size"]] -= r["n"]
    pairs, lengths = np.zeros(SYMBOLS * SYMBOLS), np.zeros(2, np.int64)
    for r in counted.filter("kind > 0").collect():  # at most one row a pair of symbols
        (pairs if r["kind"] == 1 else lengths)[r["word"]] = r["n"]
    share = F.col("n") / F.element_at(F.array(*(F.lit(float(max(t, 1.0))) for t in totals[1:])), F.col("size").cast("int"))
    return Vocabulary.of([r["word"] for r in frequent], pairs, int(lengths[0]), int(lengths[1]), words), counts.select("word", share.alias("share"))


def encode(docs: DataFrame, words_of: Vocabulary, text: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """Stored rows: the kept columns as ``kept``, row, the hash ``deal``, n_words, ids (the places), and of words outside the vocabulary the hash and the spelling."""
    own = docs.select(F.struct(*keep).alias("kept"), F.xxhash64(*keep, text).alias("deal"), F.col(text).alias("body"))
    schema = T.StructType([*own.select("kept", "deal").schema, *T.StructType.fromDDL("n_words long, ids binary, rare array<long>, spelled array<float>")])
    shared = docs.sparkSession.sparkContext.broadcast(words_of)  # bounded by the vocabulary

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        places = shared.value
        for rows, words in _word_chunks(batches, "body"):
            x = places(words)
            other = np.flatnonzero(x < LENGTHS)
            spelled = places.spelled(words)[other].astype(np.float32)
            cut = pa.array(np.searchsorted(other, words.bounds).astype(np.int32))
            ids = [x[a:b].astype(places.kind).tobytes() for a, b in zip(words.bounds[:-1], words.bounds[1:], strict=True)]
            yield pa.RecordBatch.from_arrays([rows["kept"], rows["deal"], pa.array(np.diff(words.bounds)), pa.array(ids, pa.binary()), pa.ListArray.from_arrays(cut, pa.array(words.hash[other].view(np.int64))), pa.ListArray.from_arrays(cut, pa.array(spelled))], schema.names)

    return store(own.mapInArrow(run, schema).withColumn("row", F.monotonically_increasing_id()), "encoded", dictionary=False)


def train(encoded: DataFrame, words_of: Vocabulary) -> Net:
    """A network from all encoded texts."""
    spark = encoded.sparkSession
    size, kind_of, net = words_of.size, words_of.kind, Net(words_of.size)
    shards = max(1, round(words_of.words / SHARD))
    rounds = min(ROUNDS, shards)
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[int, list] = {}
        for batch in batches:
            for k, n, raw in zip(batch["k"].to_pylist(), batch["n"].to_pylist(), batch["sums"].to_pylist(), strict=True):
                own = total.setdefault(k, [0, 0])
                own[0] += n
                own[1] = own[1] + unpacked(raw)
        yield pa.RecordBatch.from_arrays([pa.array(list(total), pa.int32()), pa.array([v[0] for v in total.values()], pa.int64()), pa.array([packed(v[1]) for v in total.values()], pa.binary())], ["k", "n", "sums"])

    dealt = encoded.filter("n_words > 0").select(F.pmod("deal", F.lit(shards)).alias("shard"), F.xxhash64("deal", F.lit(1)).alias("place"), "ids")
    for k in range(rounds):
        shared = spark.sparkContext.broadcast((net.flat, net.seen))  # bounded by the vocabulary

        def learn(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            start, total, n, at, mine, held, size_held = shared.value, 0, 0, None, None, [], 0

            def close():
                if held:
                    mine.learn(held)
                return np.rint(np.concatenate([mine.flat, np.sqrt(mine.seen)]).astype(np.float64) * FIXED).astype(np.int64)

            for batch in batches:
                for shard, raw in zip(batch["shard"].to_pylist(), batch["ids"].to_pylist(), strict=True):
                    if shard != at:
                        if mine is not None:
                            total, n = total + close(), n + 1
                        at, mine, held, size_held = shard, Net(size, *start), [], 0
                    held.append(np.frombuffer(raw, kind_of))
                    size_held += len(held[-1])
                    if size_held >= 1 << 16:
                        mine.learn(held)
                        held, size_held = [], 0
            if mine is not None:
                total, n = total + close(), n + 1
                pieces = [packed(total[lo : lo + SUMS]) for lo in range(0, len(total), SUMS)]
                yield pa.RecordBatch.from_arrays([pa.array(range(len(pieces)), pa.int32()), pa.array([n] * len(pieces), pa.int64()), pa.array(pieces, pa.binary())], ["k", "n", "sums"])

        kind = "k int, n long, sums binary"
        own = dealt.filter(F.col("shard") % rounds == k).repartition(max(parts, min(shards // rounds + 1, 100_000)), "shard").sortWithinPartitions("shard", "place", "ids")
        rows = own.select("shard", "ids").mapInArrow(learn, kind).repartition(parts, "k").mapInArrow(add, kind).collect()  # one set of parameters
        shared.unpersist()
        if rows:
            mean = np.concatenate([unpacked(r["sums"]) / (r["n"] * float(FIXED)) for r in sorted(rows, key=lambda r: r["k"])])
            flat, root = np.split(mean.astype(np.float32), 2)
            net = Net(size, flat, np.maximum(root * root, 1e-6))
    return net


def score(encoded: DataFrame, shares: DataFrame, words_of: Vocabulary, net: Net) -> DataFrame:
    """Of encoded rows the kept columns, n_words and log_likelihood. shares: (word, share) of the corpus."""
    shared = encoded.sparkSession.sparkContext.broadcast((net.size, net.flat))
    kind_of = words_of.kind
    schema = T.StructType([*encoded.select("row", "kept", "n_words").schema, T.StructField("net", T.DoubleType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        mine = Net(*shared.value)
        for batch in batches:
            raw = batch["ids"].to_pylist()
            for lo, hi in chunks([len(x) for x in raw], 1 << 19):
                own = [np.frombuffer(x, kind_of) for x in raw[lo:hi]]
                x, sizes = np.concatenate(own).astype(np.int32), np.array([len(t) for t in own])
                text, ends = np.repeat(np.arange(len(own)), sizes), np.cumsum(sizes)
                around, log = Around(x, text, mine.size), np.zeros(len(x) + 1)
                for a in range(0, len(x), 1 << 15):
                    at = np.arange(a, min(len(x), a + (1 << 15)))
                    log[at] = mine.log_probability(around(at), x[at])
                total = np.add.reduceat(log, ends - sizes) if len(own) else np.zeros(0)
                total[sizes == 0] = 0
                part = batch.slice(lo, hi - lo)
                yield pa.RecordBatch.from_arrays([*(part[c] for c in ("row", "kept", "n_words")), pa.array(total)], schema.names)

    # vocabulary words are not looked up, so no word of the join is frequent
    rare = encoded.select("row", F.explode(F.arrays_zip("rare", "spelled")).alias("w")).select("row", F.col("w.rare").alias("word"), F.col("w.spelled").cast("double").alias("spelled"))
    known, guessed = F.log(SHARE * F.col("share")), F.col("spelled") + float(np.log(1 - SHARE))
    both = F.greatest(known, guessed) + F.log1p(F.exp(-F.abs(known - guessed)))
    looked = rare.join(shares.hint("shuffle_hash"), "word", "left").groupBy("row").agg(F.sum(F.when(known.isNull(), guessed).otherwise(both)).alias("rare"))
    found = encoded.select("row", "kept", "n_words", "ids").mapInArrow(run, schema).join(looked, "row", "left")
    return found.select("kept.*", "n_words", (F.col("net") + F.coalesce("rare", F.lit(0.0))).alias("log_likelihood"))


def op8_lm_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    words_of, shares = vocabulary(docs)
    encoded = encode(docs, words_of)
    found = score(encoded, shares, words_of, train(encoded, words_of))
    return found.withColumn("per_word", F.when(F.col("n_words") > 0, F.col("log_likelihood") / F.col("n_words")))
