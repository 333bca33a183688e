"""What parses are used for: clustering, indexes, prediction, leaks; and batch twins of the streams."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from bitparse import streaming
from bitparse.functions.codes import code
from bitparse.operators import lz78, parsers, shortest, stars
from bitparse.sources import sequences
from bitparse.workloads import parsing, tables

QUERIES, ORACLE_SQL = {}, {}


def add(name, query, sql=None):
    QUERIES[name] = query
    if sql:
        ORACLE_SQL[name] = sql


def _points(v) -> np.ndarray:
    return np.frombuffer((v or "").encode("utf-32-le", "surrogatepass"), np.int32).astype(np.int64) if v is None or isinstance(v, str) else np.array(v, np.int64)


def sizes(docs):
    """docs: doc_id, text. (doc_id, text, bits): the bits of the optimum of each text."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = code("gamma")
        for batch in batches:
            for lo, hi in _runs([len(t or "") for t in batch["text"].to_pylist()]):
                part = batch.slice(lo, hi - lo)
                bits = parsers.fewest_totals([_points(t) for t in part["text"].to_pylist()], c, c)
                yield pa.RecordBatch.from_arrays([part["doc_id"], part["text"], pa.array(bits, pa.int64())], ["doc_id", "text", "bits"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(kernel, "doc_id long, text string, bits long")


def _runs(lengths: list[int]) -> Iterator[tuple[int, int]]:
    """Ranges of rows of about as many symbols as go together."""
    lo, size = 0, 0
    for k, n in enumerate(lengths):
        if k > lo and size + n > parsers.RACK:
            yield lo, k
            lo, size = k, 0
        size += n
    if lengths:
        yield lo, len(lengths)


def ncd(pairs):
    """pairs: a, b, x, y (arrays of symbols, or texts), and if they are known cx, cy. (a, b, cx, cy, cxy, distance): the normalised compression distance."""
    texts, known = pairs.schema["x"].dataType == T.StringType(), {"cx", "cy"} <= set(pairs.columns)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = code("gamma")
        for batch in batches:
            for lo, hi in _runs([len(x or "") + len(y or "") for x, y in zip(batch["x"].to_pylist(), batch["y"].to_pylist(), strict=True)]):
                part = batch.slice(lo, hi - lo)
                x, y = ([_points(v) for v in part[k].to_pylist()] for k in "xy")
                every = [np.concatenate(v) for v in zip(x, y, strict=True)]
                if known:
                    alone = [part[k].to_pylist() for k in ("cx", "cy")]
                    both = parsers.fewest_totals(every, c, c)
                else:
                    own = {v.tobytes(): k for k, v in enumerate([*x, *y])}  # each of equal ones once
                    bits = parsers.fewest_totals([*(([*x, *y])[k] for k in own.values()), *every], c, c)
                    found, both = dict(zip(own, bits, strict=False)), bits[len(own) :]
                    alone = [[found[v.tobytes()] for v in z] for z in (x, y)]
                distance = [(n - min(cx, cy)) / max(cx, cy, 1) for cx, cy, n in zip(*alone, both, strict=True)]
                yield pa.RecordBatch.from_arrays([part["a"], part["b"], *(pa.array(v, pa.int64()) for v in (*alone, both)), pa.array(distance, pa.float64())], ["a", "b", "cx", "cy", "cxy", "distance"])

    if not texts:
        pairs = pairs.withColumns({k: F.col(k).cast("array<bigint>") for k in "xy"})
    return pairs.select("a", "b", "x", "y", *(["cx", "cy"] if known else [])).mapInArrow(kernel, "a long, b long, cx long, cy long, cxy long, distance double")


#: Characters of a group of texts, of which a task holds two, and groups at least.
GROUP, GROUPS = 1 << 25, 12


def _ncd_near(s, d):
    """Each distinct text that shares a phrase with an earlier one, and the nearest of all those by NCD.

    All pairs of distinct texts that share a phrase are priced, as many as there are: phrases that stand in a share of all texts make
    them grow with the square of the texts. Of equal texts the one of the smallest id counts.
    """
    docs = tables.read(s, d, "documents").select("doc_id", "text")
    ids = docs.groupBy(F.sha2(F.col("text").cast("binary"), 256).alias("k")).agg(F.min("doc_id").alias("doc_id")).select("doc_id")
    own = docs.join(ids, "doc_id", "left_semi")
    phrases = _phrases(tables.spread(own), "doc_id", "text")
    pairs = phrases.withColumnRenamed("doc_id", "a").join(phrases.withColumnRenamed("doc_id", "b"), "phrase").filter("a > b").select("a", "b").distinct()
    total = docs.agg(F.sum(F.length("text"))).first()[0] or 0
    return ncd(_with_texts(pairs, sizes(tables.spread(own)), total)).groupBy("a").agg(F.min_by(F.struct("b", "distance"), F.struct("distance", "b")).alias("m")).select("a", "m.b", "m.distance")


def _with_texts(pairs, docs, total):
    """(a, b, x, y, cx, cy): the texts and sizes of pairs of ids. Texts are dealt to groups and pairs to pairs of groups, so that a text is sent
    twice for each group and not once for each pair; a task holds the texts of two groups."""
    s = docs.sparkSession
    n = max(GROUPS, -(-total // GROUP))
    parts = max(n * n, 4 * s.sparkContext.defaultParallelism)
    group = lambda key: F.pmod(F.xxhash64(key), F.lit(n))
    other = F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    sent = docs.withColumn("g", group("doc_id")).withColumn("h", other)
    sent = sent.withColumn("cell", F.explode(F.array_distinct(F.array(F.col("g") * n + F.col("h"), F.col("h") * n + F.col("g")))))
    rows = pairs.select((group("a") * n + group("b")).alias("cell"), "a", "b", F.lit(None).cast("string").alias("t"), F.lit(None).cast("long").alias("c"))
    rows = rows.unionByName(sent.select("cell", F.col("doc_id").alias("a"), F.lit(None).cast("long").alias("b"), F.col("text").alias("t"), F.col("bits").alias("c")))

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cell, held, out, size = None, {}, [], 0
        for batch in batches:
            for own, a, b, t, c in zip(*(batch[k].to_pylist() for k in ("cell", "a", "b", "t", "c")), strict=True):
                if own != cell:
                    cell, held = own, {}
                if b is None:  # texts come before the pairs
                    held[a] = t, c
                    continue
                (x, cx), (y, cy) = held[a], held[b]
                out.append((a, b, x, y, cx, cy))
                size += len(x or "") + len(y or "")
                if size >= parsers.RACK:
                    yield pa.RecordBatch.from_pylist([dict(zip(_PAIR.names, r, strict=True)) for r in out], _PAIR)
                    out, size = [], 0
        yield pa.RecordBatch.from_pylist([dict(zip(_PAIR.names, r, strict=True)) for r in out], _PAIR)

    return rows.repartition(parts, "cell").sortWithinPartitions("cell", F.col("b").asc_nulls_first(), "a").mapInArrow(kernel, "a long, b long, x string, y string, cx long, cy long")


_PAIR = pa.schema([("a", pa.int64()), ("b", pa.int64()), ("x", pa.string()), ("y", pa.string()), ("cx", pa.int64()), ("cy", pa.int64())])


#: Words of a phrase; an item of fewer words is one phrase.
PHRASE = 5


def _phrases(df, key, text, widths=None):
    """(key, phrase): the distinct runs of PHRASE words of each text, or of each of these numbers of words."""
    words = F.filter(F.split(F.lower(F.coalesce(F.col(text), F.lit(""))), r"[^\p{L}\p{N}]+"), lambda w: w != "")
    own = df.select(key, words.alias("w")).filter(F.size("w") > 0)
    width = F.array(F.least(F.size("w"), F.lit(PHRASE))) if widths is None else F.filter(F.lit(widths), lambda q: q <= F.size("w"))
    each = own.select(key, "w", F.explode(width).alias("q"))
    runs = F.transform(F.sequence(F.lit(1), F.size("w") - F.col("q") + 1), lambda k: F.array_join(F.slice("w", k, F.col("q")), " "))
    return each.select(key, F.explode(F.array_distinct(runs)).alias("phrase"))


add("ncd_near_copies", _ncd_near)


def bits_after(held: np.ndarray, syms: np.ndarray) -> int:
    """Bits of the optimum of syms where copies may also start in, and run on from, the held symbols before them."""
    c, n = code("gamma"), len(held)
    own = parsers.Sequence(np.concatenate([held, syms]), c, c)
    star = own.edges()
    inside = star.i >= n
    star = stars.Star(star.i[inside] - n, star.length[inside], star.dist[inside])
    return int(shortest.relax(len(syms), own.literal[n:], star, own.f(star.dist) + own.g(star.length))[0][len(syms)])


def _leak(s, d):
    """Bits of each document alone and with an item as the history before it, for all items it shares a phrase with."""
    items, docs = tables.read(s, d, "benchmark"), tables.read(s, d, "documents")
    own = _phrases(items, "item_id", "text")
    # numbers of words of short items: at most PHRASE of them
    widths = sorted(r["q"] for r in own.select(F.size(F.split("phrase", " ")).alias("q")).distinct().collect()) or [PHRASE]
    pairs = own.join(_phrases(tables.spread(docs), "doc_id", "text", widths), "phrase").select("doc_id", "item_id").distinct()
    # texts are joined, and made into symbols only where they are priced
    texts = pairs.join(items.select("item_id", F.col("text").alias("held")), "item_id").join(docs.select("doc_id", "text"), "doc_id")

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, bits = None, 0
        for batch in batches:
            alone, after = [], []
            for k in range(batch.num_rows):
                x, y = np.array(batch["held"][k].as_py(), np.int64), np.array(batch["text"][k].as_py(), np.int64)
                if last is None or not np.array_equal(last, y):
                    last, bits = y, bits_after(y[:0], y)
                alone.append(bits)
                after.append(bits_after(x, y))
            yield pa.RecordBatch.from_arrays([batch["item_id"], batch["doc_id"], pa.array(alone, pa.int64()), pa.array(after, pa.int64())], ["item_id", "doc_id", "alone", "after_item"])

    symbols = lambda text: sequences.code_points(F.col(text)).cast("array<bigint>").alias(text)
    parts = max(4 * s.sparkContext.defaultParallelism, int(s.conf.get("spark.sql.shuffle.partitions")))
    own = texts.repartition(parts).select(F.col("item_id").cast("long"), F.col("doc_id").cast("long"), symbols("held"), symbols("text"))
    found = own.mapInArrow(kernel, "item_id long, doc_id long, alone long, after_item long")
    return found.withColumn("saved", F.col("alone") - F.col("after_item"))


add("benchmark_leak_bits", _leak)


def _phrase_index(s, d):
    """Where phrases begin: for each document and bucket of 64 positions the first phrase and the bits before it."""
    parse = parsers.explode(parsers.greedy(tables.documents(s, d)))
    before = F.sum("bits").over(Window.partitionBy("seq_id").orderBy("k").rowsBetween(Window.unboundedPreceding, -1))
    own = parse.withColumn("offset", F.coalesce(before, F.lit(0))).withColumn("bucket", F.floor((F.col("start") - 1) / 64))
    return own.groupBy("seq_id", "bucket").agg(F.min("k").cast("long").alias("k"), F.min("start").cast("long").alias("start"), F.min("offset").alias("offset"))


add("phrase_index", _phrase_index)


def _prefetch(s, d):
    """The event type that followed most often after each pair of types, and how often it came true."""
    own = Window.partitionBy("user_id").orderBy("ts", "event_id")
    rows = tables.read(s, d, "events").select("user_id", "event_type", F.lag("event_type", 1).over(own).alias("p1"), F.lag("event_type", 2).over(own).alias("p2")).filter("p2 is not null")
    counts = rows.groupBy("p2", "p1", "event_type").agg(F.count("*").alias("n"))
    place = F.row_number().over(Window.partitionBy("p2", "p1").orderBy(F.desc("n"), "event_type"))
    total = F.sum("n").over(Window.partitionBy("p2", "p1"))
    return counts.select("p2", "p1", F.col("event_type").alias("next"), "n", total.alias("of"), place.alias("place")).filter("place = 1").drop("place")


add(
    "prefetch_next_symbol", _prefetch,
    "with r as (select event_type, lag(event_type, 1) over w as p1, lag(event_type, 2) over w as p2 from events window w as (partition by user_id order by ts, event_id)), c as (select p2, p1, event_type as next, count(*) as n from r where p2 is not null group by all), o as (select *, sum(n) over (partition by p2, p1)::bigint as of, row_number() over (partition by p2, p1 order by n desc, next) as place from c) select p2, p1, next, n, of from o where place = 1",
)

# Batch twins of the streams.


def _symbols(s, d):
    own = tables.ranked(tables.read(s, d, "events"), F.col("event_type"))
    return streaming.symbols(own, F.col("sym"))


add("stream_lz78_batch", lambda s, d: lz78.run(tables.events(s, d), ("greedy",)).select(F.col("seq_id").alias("key"), F.size(F.filter("parse", lambda p: p["sym"].isNotNull())).cast("long").alias("phrases")), "with g as (" + parsing._GROWN.replace("{sym}", tables.SYM["events"]) + ") select seq_id as key, count(*) filter (sym >= 0) as phrases from g group by seq_id")


def _windowed(span):
    return lambda s, d: streaming.window_bits(_symbols(s, d), span()).withColumns({"begins": F.unix_micros("begins"), "ends": F.unix_micros("ends")})


add("tumbling_bits", _windowed(lambda: F.window("ts", "7 days")))
add("sliding_bits", _windowed(lambda: F.window("ts", "10 days", "5 days")))
add("session_bits", _windowed(lambda: F.session_window("ts", "12 hours")))
add(
    "tumbling_counts", lambda s, d: _windowed(lambda: F.window("ts", "7 days"))(s, d).groupBy("begins").agg(F.count("*").alias("keys"), F.sum("n").alias("n")),
    "with w as (select user_id, (epoch_us(ts) // 604800000000) * 604800000000 as begins, count(*) as n from events group by all) select begins::bigint as begins, count(*) as keys, sum(n)::bigint as n from w group by begins",
)
add(
    "session_counts", lambda s, d: _windowed(lambda: F.session_window("ts", "12 hours"))(s, d).groupBy("key").agg(F.count("*").alias("sessions"), F.sum("n").alias("n")),
    "with g as (select user_id, ts, case when ts - lag(ts) over (partition by user_id order by ts) < interval 12 hours then 0 else 1 end as new from events) select user_id as key, sum(new)::bigint as sessions, count(*) as n from g group by user_id",
)
