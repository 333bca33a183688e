"""Benchmark decontamination by a prefix-filtered set join.

An item's windows are its runs of WINDOW words (a shorter item is one window). A window is the set
of its shingles of SHINGLE words. A text contains the window only if it contains every one of its
shingles, so one necessary prefix token, its rarest shingle, is enough to find all candidates:
shingles are counted over all texts, the windows are filed under their rarest shingle, and the
texts' shingles are looked up there. Length and position bounds discard candidates that would pass
the ends of a text; the words of the rest are compared exactly over the window.

Items are taken in blocks of about BLOCK_CHARS characters, held as flat arrays of about 20 bytes a
character, and broadcast. Up to AT_ONCE blocks are held by a worker and meet all texts in one pass;
with more of them hits are stored after each pass and the next one goes on.

Defined results: texts and items that are null or without a word have no windows; an item_id that
stands in several rows is one item; a null item_id reads as an empty string; every row of the
texts gives one row; other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from bitparse.llm.common import as_bytes, chunks, fresh, store, table, with_text

WINDOW, SHINGLE, BLOCK_CHARS, AT_ONCE, CHUNK = 13, 5, 2_000_000, 4, 1 << 20
#: Word bytes in lower case, zero for all others; bytes from 128 on belong to word characters.
_PLAIN = bytes(c + 32 if 65 <= c <= 90 else c if 48 <= c <= 57 or 97 <= c <= 122 or c >= 128 else 0 for c in range(256))
_BASE, _MIX, _JOIN = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)


def words_of(raw: bytes | None) -> list[bytes]:
    return [w for w in raw.translate(_PLAIN).split(b"\0") if w] if raw else []


@lru_cache(2)
def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    back = np.uint64(pow(int(_BASE), -1, 1 << 64))
    with np.errstate(over="ignore"):
        return tuple(np.concatenate((np.ones(1, np.uint64), np.cumprod(np.full(n, b, np.uint64)))) for b in (_BASE, back))


def _hashes(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    power, back = _powers(1 << max(20, len(buf).bit_length()))
    with np.errstate(over="ignore"):
        total = np.concatenate((np.zeros(1, np.uint64), np.cumsum((buf.astype(np.uint64) + np.uint64(1)) * power[: len(buf)])))
        h = (total[ends] - total[starts]) * back[starts]
        h = (h ^ (h >> np.uint64(29))) * _MIX
        return h ^ (h >> np.uint64(32))


class Words:
    """The words of several texts: where each begins and ends, its hash, and the texts' ranges of words."""

    def __init__(self, texts: list[bytes | None]):
        self.plain = b"\0".join((t or b"") for t in texts).translate(_PLAIN) + b"\0"
        buf = np.frombuffer(self.plain, np.uint8)
        inside = buf != 0
        self.starts = np.flatnonzero(inside & ~np.concatenate(([False], inside[:-1])))
        self.ends = np.flatnonzero(~inside & np.concatenate(([False], inside[:-1])))
        self.hash = np.zeros(len(self.starts), np.uint64)
        lo = 0
        while lo < len(self.starts):  # about CHUNK bytes at a time, whole words
            hi = max(lo + 1, int(np.searchsorted(self.ends, self.starts[lo] + CHUNK, "right")))
            self.hash[lo:hi] = _hashes(buf[self.starts[lo] : self.ends[hi - 1]], self.starts[lo:hi] - self.starts[lo], self.ends[lo:hi] - self.starts[lo])
            lo = hi
        begins = np.cumsum([0] + [len(t or b"") + 1 for t in texts])
        self.bounds = np.searchsorted(self.starts, begins)
        self.text = np.repeat(np.arange(len(texts)), np.diff(self.bounds))

    def shingles(self, q: int) -> np.ndarray:
        """Hashes of the runs of q words that begin at each word, also over the ends of texts."""
        n = max(0, len(self.hash) - q + 1)
        out = np.full(n, q, np.uint64)
        with np.errstate(over="ignore"):
            for k in range(q):
                out = (out ^ self.hash[k : k + n]) * _JOIN
                out ^= out >> np.uint64(31)
        return out

    def run(self, first: int, n: int) -> list[bytes]:
        return [w for w in self.plain[self.starts[first] : self.ends[first + n - 1]].split(b"\0") if w]


class Windows:
    """The distinct windows of some items, and their shingles, in flat arrays."""

    def __init__(self, items: list[tuple[str, bytes | None]], window: int = WINDOW, shingle: int = SHINGLE):
        self.names = sorted({item for item, _ in items})
        number = {item: k for k, item in enumerate(self.names)}
        self.text = words = Words([raw for _, raw in items])
        size = np.diff(words.bounds)
        each = np.where(size > 0, np.maximum(size - window + 1, 1), 0)
        item = np.repeat(np.arange(len(items)), each)
        start = np.arange(len(item)) - np.repeat(np.cumsum(each) - each, each) + words.bounds[item]
        length = np.minimum(size, window)[item]
        # equal windows become one: by a hash of the words, then word by word
        key = np.zeros(len(item), np.uint64)
        for n in np.unique(length).tolist():
            own = length == n
            key[own] = words.shingles(n)[start[own]] + np.uint64(n)
        _, first, same = np.unique(key, return_index=True, return_inverse=True)
        other = np.flatnonzero(first[same] != np.arange(len(item)))
        alike = self._equal(words, start[other], words, start[first[same[other]]], length[other]) & (length[other] == length[first[same[other]]])
        strange = other[~alike]  # equal hashes of different words: windows of their own
        same[strange] = len(first) + np.arange(len(strange))
        first = np.concatenate([first, strange])
        self.start, self.length = start[first], length[first]
        owner = np.array([number[i] for i, _ in items], np.int64)[item]
        pairs = np.unique(np.stack([same, owner], axis=1), axis=0) if len(item) else np.zeros((0, 2), np.int64)
        self.slot, self.owner = np.searchsorted(pairs[:, 0], np.arange(len(first) + 1)), pairs[:, 1].astype(np.int32)
        self.width = np.minimum(self.length, shingle)
        self.widths = np.unique(self.width).tolist()
        grams = [np.zeros(0, np.uint64)]
        for q in self.widths:
            own = words.shingles(q)
            grams += [own[s : s + int(n) - q + 1] for s, n in zip(*self._runs(q), strict=True)]
        self.keys = np.unique(np.concatenate(grams))

    def _runs(self, q: int) -> tuple[np.ndarray, np.ndarray]:
        """Where the words begin that windows of that shingle width cover without a gap, and how many they are."""
        own = np.flatnonzero(self.width == q)
        order = own[np.argsort(self.start[own])]
        begin, end = self.start[order], self.start[order] + self.length[order]
        fresh = np.concatenate(([True], begin[1:] != begin[:-1] + 1)) if len(order) else np.zeros(0, bool)
        at = np.flatnonzero(fresh)
        return begin[at], (np.maximum.reduceat(end, at) if len(at) else end[at]) - begin[at]

    @staticmethod
    def _equal(a: Words, at: np.ndarray, b: Words, to: np.ndarray, length: np.ndarray) -> np.ndarray:
        """Whether runs of words are equal: by the words' hashes, then by their bytes."""
        out = np.ones(len(at), bool)
        for k in range(int(length.max(initial=0))):
            own = np.flatnonzero(out & (length > k))
            out[own] = a.hash[at[own] + k] == b.hash[to[own] + k]
        for k in np.flatnonzero(out).tolist():
            i, j, n = int(at[k]), int(to[k]), int(length[k])
            out[k] = a.plain[a.starts[i] : a.ends[i + n - 1]] == b.plain[b.starts[j] : b.ends[j + n - 1]] or a.run(i, n) == b.run(j, n)
        return out

    def counted(self, words: Words) -> np.ndarray:
        """How often each of the keys stands in these texts."""
        total = np.zeros(len(self.keys), np.int64)
        for q in self.widths:
            own = words.shingles(q)
            at = np.searchsorted(self.keys, own)
            at[at == len(self.keys)] = 0
            if len(at):
                total += np.bincount(at[self.keys[at] == own], minlength=len(self.keys))
        return total

    def file(self, counts: np.ndarray) -> Windows:
        """Files each window under its rarest shingle."""
        gram, offset = np.zeros(len(self.start), np.uint64), np.zeros(len(self.start), np.int64)
        for q in self.widths:
            grams, own = self.text.shingles(q), np.flatnonzero(self.width == q)
            best = np.full(len(own), np.iinfo(np.int64).max)
            for k in range(int((self.length[own] - q).max(initial=0)) + 1):
                has = np.flatnonzero(self.length[own] >= q + k)
                here = grams[self.start[own[has]] + k]
                rarity = counts[np.searchsorted(self.keys, here)]
                better = (rarity < best[has]) | ((rarity == best[has]) & (here < gram[own[has]]))
                to = has[better]
                best[to], gram[own[to]], offset[own[to]] = rarity[better], here[better], k
        order = np.argsort(gram, kind="stable")
        self.prefix, first = np.unique(gram[order], return_index=True)
        self.slots = np.append(first, len(order))
        self.filed, self.offset = order.astype(np.int32), offset[order].astype(np.int16)
        return self

    def find(self, words: Words) -> tuple[np.ndarray, list[set[str]]]:
        """Which words stand in an occurrence of a window, and the items of each text that occur."""
        hit = np.zeros(len(words.hash) + 1, np.int64)
        items: list[set[str]] = [set() for _ in range(len(words.bounds) - 1)]
        for q in self.widths:
            grams = words.shingles(q)
            if not len(grams) or not len(self.prefix):
                continue
            slot = np.searchsorted(self.prefix, grams)
            slot[slot == len(self.prefix)] = 0
            at = np.flatnonzero(self.prefix[slot] == grams)
            slot = slot[at]
            each = self.slots[slot + 1] - self.slots[slot]
            place = np.repeat(at, each)
            row = np.arange(len(place)) - np.repeat(np.cumsum(each) - each, each) + np.repeat(self.slots[slot], each)
            window, start = self.filed[row], place - self.offset[row]
            length = self.length[window]
            fits = (self.width[window] == q) & (start >= 0)
            window, start, length, place = window[fits], start[fits], length[fits], place[fits]
            text = words.text[place]
            fits = (start >= words.bounds[text]) & (start + length <= words.bounds[text + 1])
            window, start, length, text = window[fits], start[fits], length[fits], text[fits]
            same = self._equal(words, start, self.text, self.start[window], length)
            window, start, length, text = window[same], start[same], length[same], text[same]
            np.add.at(hit, start, 1)
            np.add.at(hit, start + length, -1)
            for w, t in set(zip(window.tolist(), text.tolist(), strict=True)):
                items[t].update(self.names[k] for k in self.owner[self.slot[w] : self.slot[w + 1]].tolist())
        return np.cumsum(hit[:-1]) > 0, items


def blocks_of(items: DataFrame, window: int, shingle: int, block_chars: int) -> Iterator[Windows]:
    own = items.select(F.coalesce(F.col("item_id").cast("string"), F.lit("")).alias("item"), "text").filter("text is not null")
    chars = own.agg(F.sum(F.length("text"))).first()[0] or 0
    blocks = max(1, -(-chars // block_chars))
    for k in range(blocks):
        rows = own.filter(F.pmod(F.xxhash64("item", "text"), F.lit(blocks)) == k).collect()  # of a checked size
        yield Windows([(r["item"], r["text"].encode("utf-8", "replace")) for r in rows], window, shingle)


def decontaminate(docs: DataFrame, items: DataFrame, keep: tuple[str, ...] = ("doc_id",), window: int = WINDOW, shingle: int = SHINGLE, block_chars: int = BLOCK_CHARS, names: tuple[str, str, str] = ("n_words", "n_hit", "items")) -> DataFrame:
    """The kept columns and, under ``names``, each text's words, hit words and occurring items (sorted). items: item_id, text."""
    context = docs.sparkSession.sparkContext
    own, body, kept = with_text(docs, keep, "text")
    marks, found = fresh(docs, "marks"), T.StructType.fromDDL("{} long, {} long, {} array<string>".format(*names))
    rows = own.withColumns({marks: F.lit(None).cast("binary"), fresh(docs, "named"): F.lit(None).cast("array<string>")})
    between, columns = rows.schema, own.columns

    def meet(ready: list, last: bool):
        """A pass over the texts with some blocks; hits of earlier passes are bits by word."""

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                raw = as_bytes(batch[body])
                for lo, hi in chunks([len(t or b"") for t in raw], CHUNK):
                    words, part = Words(raw[lo:hi]), batch.slice(lo, hi - lo)
                    bounds = words.bounds.tolist()
                    hit, items = np.zeros(len(words.hash), bool), [set(x or ()) for x in part[len(between) - 1].to_pylist()]
                    for k, x in enumerate(part[marks].to_pylist()):
                        if x is not None:
                            hit[bounds[k] : bounds[k + 1]] = np.unpackbits(np.frombuffer(x, np.uint8), count=bounds[k + 1] - bounds[k]).view(bool)
                    for shared in ready:
                        more_hit, more = shared.value.find(words)
                        hit |= more_hit
                        for mine, x in zip(items, more, strict=True):
                            mine |= x
                    listed = pa.array([sorted(x) for x in items], pa.list_(pa.string()))
                    if last:
                        total = np.concatenate(([0], np.cumsum(hit)))
                        yield pa.RecordBatch.from_arrays([*(part[k] for k in keep), pa.array(np.diff(words.bounds)), pa.array(np.diff(total[words.bounds])), listed], [*kept.names, *found.names])
                    else:
                        bits = [np.packbits(hit[a:b]).tobytes() for a, b in zip(bounds, bounds[1:], strict=False)]
                        yield pa.RecordBatch.from_arrays([*(part[k] for k in columns), pa.array(bits, pa.binary()), listed], between.names)

        return run

    ready: list = []
    for part in blocks_of(items, window, shingle, block_chars):
        if len(ready) == AT_ONCE:
            rows, ready = store(rows.mapInArrow(meet(ready, False), between), "hits"), []
        shared = context.broadcast(part)  # of about 20 * block_chars bytes

        def count(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            mine = shared.value
            total = np.zeros(len(mine.keys), np.int64)
            for batch in batches:
                raw = as_bytes(batch[body])
                for lo, hi in chunks([len(t or b"") for t in raw], CHUNK):
                    total += mine.counted(Words(raw[lo:hi]))
            seen = np.flatnonzero(total)
            yield pa.RecordBatch.from_arrays([pa.array(seen), pa.array(total[seen])], ["k", "n"])

        seen = own.select(body).mapInArrow(count, "k long, n long").groupBy("k").agg(F.sum("n").alias("n")).toArrow()  # two numbers a shingle of the block
        counts = np.zeros(len(part.keys), np.int64)
        counts[seen["k"].to_numpy()] = seen["n"].to_numpy()
        ready.append(context.broadcast(part.file(counts)))
        shared.unpersist()
    return rows.mapInArrow(meet(ready, True), T.StructType([*kept, *found]))


def contaminated(n_words: str = "n_words", n_hit: str = "n_hit") -> Column:
    return (F.col(n_hit) > 0) & (20 * F.col(n_hit) >= F.col(n_words))


def op2_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontaminate(table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "benchmark"))
    return found.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ",").cast("binary"), 256).alias("items_sha256"), contaminated().alias("contaminated"))
