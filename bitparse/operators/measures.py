"""Sizes, ratios, bounds and checks. Relations in, relations out."""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from bitparse.functions.codes import Code, code, n_plateaus, plateaus
from bitparse.operators import bits as bits_of
from bitparse.operators import parsers, repeats, stars


def totals(parse: DataFrame) -> DataFrame:
    """(seq_id, parser, n, bits, phrases) of parses."""
    return parse.select("seq_id", "parser", "n", "bits", F.col("counters")["phrases"].alias("phrases"))


def gap(seq: DataFrame, f: Code | str = "gamma", g: Code | str = "gamma", window: int | None = None) -> DataFrame:
    """(seq_id, n, greedy, optimal, ratio, bound, within): greedy against the optimum, and the bound on their ratio."""
    f, g = code(f), code(g)
    both = parsers.compare(seq, f, g, ("optimal", "greedy"), window).select("seq_id", "n", "greedy", "optimal")  # where they are not taken together, greedy parsing finds the steps made in this order
    bound = (f.column(F.col("n")) + g.column(F.col("n"))) / F.lit(f.bits(0) + g.bits(0))
    own = both.withColumn("ratio", F.when(F.col("optimal") > 0, F.col("greedy") / F.col("optimal"))).withColumn("bound", bound)
    return own.withColumn("within", F.coalesce(F.col("ratio") <= F.col("bound"), F.lit(True)))


def family_gap(gaps: DataFrame) -> DataFrame:
    """The ratio on the bad family against l / log2 l."""
    l = F.col("seq_id")  # noqa: E741
    return gaps.withColumn("shape", l / F.log2(l)).withColumn("normalised", F.col("ratio") / (l / F.log2(l)))


def degree(priced: DataFrame, f: Code | str, g: Code | str) -> DataFrame:
    """(seq_id, n_edges, max_degree, bound): edges, the largest forward star, and Q(f, n) + Q(g, n)."""
    names = code(f).name, code(g).name

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = batch["n"].to_numpy(zero_copy_only=False).astype(np.int64)
            most = int(n.max(initial=0))
            bound = sum(np.searchsorted(np.array([p[0] for p in plateaus(c, most, 1)], np.int64), n, "right") for c in names)
            yield pa.RecordBatch.from_arrays([batch["seq_id"], batch["n_edges"], batch["max_degree"], pa.array(bound, pa.int64())], ["seq_id", "n_edges", "max_degree", "bound"])

    by_start = priced.groupBy("seq_id", "i").agg(F.count("*").alias("d"))
    own = by_start.groupBy("seq_id").agg(F.sum("d").alias("n_edges"), F.max("d").alias("max_degree"), F.max("i").alias("n"))
    rows = own.select("seq_id", "n_edges", "max_degree", F.col("n").cast("long").alias("n"))
    return rows.mapInArrow(kernel, "seq_id long, n_edges long, max_degree long, bound long")


def contiguous(priced: DataFrame) -> DataFrame:
    """(seq_id, gaps): forward stars whose ends are not a contiguous range from i + 1 on."""
    star = priced.select("seq_id", "i", "j").distinct().groupBy("seq_id", "i").agg((F.max("j") - F.col("i") - F.count("*")).alias("missing"))
    return star.groupBy("seq_id").agg(F.sum(F.when(F.col("missing") != 0, 1).otherwise(0)).alias("gaps"))


def monotone(priced: DataFrame) -> DataFrame:
    """(seq_id, forward, backward): copies that cost less than a shorter one of the same start, or of the same end."""
    copies = priced.filter("kind = 'copy'")
    ahead = F.lag("bits").over(Window.partitionBy("seq_id", "i").orderBy("j"))
    behind = F.lag("bits").over(Window.partitionBy("seq_id", "j").orderBy(F.desc("i")))
    bad = copies.select("seq_id", (F.col("bits") < ahead).alias("f"), (F.col("bits") < behind).alias("b"))
    return bad.groupBy("seq_id").agg(F.sum(F.coalesce(F.col("f").cast("long"), F.lit(0))).alias("forward"), F.sum(F.coalesce(F.col("b").cast("long"), F.lit(0))).alias("backward"))


def completeness(phrases: DataFrame) -> DataFrame:
    """(prefix, suffix): phrases (arrays) of which the phrase without its last, or first, symbol is not in the dictionary."""
    own = phrases.select("phrase").distinct()
    longer = own.filter(F.size("phrase") > 1)
    short = own.select(F.col("phrase").alias("short"))
    lost = lambda p: longer.select(p.alias("short")).join(short, "short", "left_anti").agg(F.count("*").alias("n"))
    prefix = lost(F.slice("phrase", 1, F.size("phrase") - 1)).withColumnRenamed("n", "prefix")
    return prefix.join(lost(F.slice("phrase", 2, F.size("phrase"))).withColumnRenamed("n", "suffix"))


def star_recall(seq: DataFrame, f: Code | str = "gamma") -> DataFrame:
    """(seq_id, d_maximal, found, invalid): the d-maximal copies of the full graph, those among the block scheme's, and
    the block scheme's copies that are none."""
    name = code(f).name

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for k in range(batch.num_rows):
                syms = np.array(batch["syms"][k].as_py() or [], np.int64)
                price = stars.Pricer(name, max(1, len(syms)))
                full = stars.full(syms)
                want = stars.prune(full, price, price, "d")
                made = stars.block(syms, price)
                edges = {(i, n): d for i, n, d in zip(full.i.tolist(), full.length.tolist(), full.dist.tolist(), strict=True)}
                have = set(zip(made.i.tolist(), made.length.tolist(), price(made.dist).tolist(), strict=True))
                found = sum((i, n, b) in have for i, n, b in zip(want.i.tolist(), want.length.tolist(), price(want.dist).tolist(), strict=True))
                invalid = sum((i, n) not in edges or any(syms[i + x] != syms[i + x - d] for x in range(n)) for i, n, d in zip(made.i.tolist(), made.length.tolist(), made.dist.tolist(), strict=True))
                rows.append((batch["seq_id"][k].as_py(), len(want.i), found, invalid))
            yield pa.RecordBatch.from_arrays([pa.array([r[c] for r in rows], pa.int64()) for c in range(4)], ["seq_id", "d_maximal", "found", "invalid"])

    return seq.select("seq_id", "syms").mapInArrow(kernel, "seq_id long, d_maximal long, found long, invalid long")


def work(parse: DataFrame) -> DataFrame:
    """(seq_id, n, edges, visits, live_edges, visits_per_edge) of block parses: work a copy and edges in memory at once."""
    c = F.col("counters")
    return parse.select("seq_id", "n", c["edges"].alias("edges"), c["visits"].alias("visits"), c["live_edges"].alias("live_edges"), (c["visits"] / F.greatest(c["emitted"], F.lit(1))).alias("visits_per_edge"))


def longest_repeat(seq: DataFrame, g: Code | str = "gamma") -> DataFrame:
    """(seq_id, longest, q): the longest repeated substring, and how many codeword lengths g has up to there."""
    name = code(g).name

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            longest = [repeats.longest_repeat(np.array(x or [], np.int64)) for x in batch["syms"].to_pylist()]
            yield pa.RecordBatch.from_arrays([batch["seq_id"], pa.array(longest, pa.int64()), pa.array([n_plateaus(name, n) for n in longest], pa.int64())], ["seq_id", "longest", "q"])

    return seq.select("seq_id", "syms").mapInArrow(kernel, "seq_id long, longest long, q long")


def entropy(seq: DataFrame, k: int) -> DataFrame:
    """(seq_id, n, h, bits): the empirical entropy of order k, and n - k times it; n counts the symbols with a whole context.

    Contexts are counted where the sequence stands, so nothing is shuffled; sequences of at most k symbols have no row.
    """

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for key, x in zip(batch["seq_id"].to_pylist(), batch["syms"], strict=True):
                syms = x.values.to_numpy(zero_copy_only=False) if x.is_valid else np.zeros(0, np.int64)
                m = len(syms) - k
                if m <= 0:
                    continue
                own = np.unique(syms, return_inverse=True)[1].astype(np.int64)
                context, sigma = np.zeros(m, np.int64), int(own.max()) + 1
                for j in range(k):
                    context = np.unique(context * sigma + own[j : j + m], return_inverse=True)[1].astype(np.int64)
                pairs, count = np.unique(context * sigma + own[k:], return_counts=True)
                bits = float(-(count * np.log2(count / np.bincount(context)[pairs // sigma])).sum())
                rows.append((key, m, abs(bits) / m, abs(bits)))
            yield pa.RecordBatch.from_arrays([pa.array([r[c] for r in rows], kind) for c, kind in enumerate((pa.int64(), pa.int64(), pa.float64(), pa.float64()))], ["seq_id", "n", "h", "bits"])

    return seq.select(F.col("seq_id").cast("long").alias("seq_id"), "syms").mapInArrow(kernel, "seq_id long, n long, h double, bits double")


def redundancy(parse: DataFrame, seq: DataFrame, k: int = 0) -> DataFrame:
    """(seq_id, n, per_symbol, h, redundancy, term): bits a symbol against the entropy, and log log n / log n."""
    own = parse.select("seq_id", (F.col("bits") / F.col("n")).alias("per_symbol")).join(entropy(seq, k).select("seq_id", "h"), "seq_id").join(seq.select("seq_id", "n"), "seq_id")
    return own.select("seq_id", "n", "per_symbol", "h", (F.col("per_symbol") - F.col("h")).alias("redundancy"), F.when(F.col("n") > 2, F.log2(F.log2("n")) / F.log2("n")).alias("term"))


def ratio(parse: DataFrame, seq: DataFrame) -> DataFrame:
    """(seq_id, n, bits, per_symbol, ratio): against the same number of digits for every symbol."""
    size = seq.select("seq_id", F.greatest(F.ceil(F.log2(F.size(F.array_distinct("syms")))), F.lit(1)).alias("digits"))
    return parse.join(size, "seq_id").select("seq_id", "n", "bits", (F.col("bits") / F.col("n")).alias("per_symbol"), (F.col("bits") / (F.col("n") * F.col("digits"))).alias("ratio"))


def roundtrip(parse: DataFrame, seq: DataFrame) -> DataFrame:
    """(seq_id, nbits, same): the bits written, and whether decoding them gives the sequence."""
    encoded = bits_of.encode(parse)
    hashed = lambda df, name: df.select("seq_id", F.xxhash64(F.col("syms").cast("array<bigint>")).alias(name))
    return encoded.select("seq_id", "nbits").join(hashed(bits_of.decode(encoded), "back"), "seq_id").join(hashed(seq, "own"), "seq_id").select("seq_id", "nbits", (F.col("back") == F.col("own")).alias("same"))


def codec(df: DataFrame, key: str, text: str) -> DataFrame:
    """(seq_id, bits): a general-purpose codec's size, for reference."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch["seq_id"], pa.array([8 * len(zlib.compress((x or "").encode(), 9)) for x in batch["t"].to_pylist()], pa.int64())], ["seq_id", "bits"])

    return df.select(F.col(key).cast("long").alias("seq_id"), F.col(text).alias("t")).mapInArrow(kernel, "seq_id long, bits long")


def bwt_runs(seq: DataFrame) -> DataFrame:
    """(seq_id, n, runs, mtf_bits): runs of equal symbols in suffix order, and the order-0 size of its move-to-front ranks."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for key, x in zip(batch["seq_id"].to_pylist(), batch["syms"].to_pylist(), strict=True):
                syms = np.array(x or [], np.int64)
                order = np.argsort(repeats.suffix_ranks(syms))
                last = syms[order - 1] if len(syms) else syms
                front, ranks = sorted(set(syms.tolist())), []
                for s in last.tolist():
                    ranks.append(front.index(s))
                    front.insert(0, front.pop(ranks[-1]))
                counts = np.bincount(ranks) if ranks else np.zeros(0)
                counts = counts[counts > 0]
                rows.append((key, len(syms), int((last[1:] != last[:-1]).sum()) + (len(syms) > 0), float(-(counts * np.log2(counts / max(1, counts.sum()))).sum())))
            yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.int64()), pa.array([r[2] for r in rows], pa.int64()), pa.array([r[3] for r in rows], pa.float64())], ["seq_id", "n", "runs", "mtf_bits"])

    return seq.select("seq_id", "syms").mapInArrow(kernel, "seq_id long, n long, runs long, mtf_bits double")
