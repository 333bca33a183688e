"""How a collection is parsed: by length to the fold, the kernel or chunks; equal sequences once."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bitparse.functions.codes import Code, NotMonotone, code
from bitparse.operators import chunks, parsers, repeats, shortest, stars
from bitparse.sources import sequences

#: Symbols up to which the fold inside Catalyst is used, and from which a sequence goes in chunks.
FOLD, CHUNKED = 24, 1 << 20


def strategy(f: Code | str, g: Code | str) -> str:
    """greedy where equal-length codes make it optimal; pruned for monotone codes; else the full graph."""
    f, g = code(f), code(g)
    if f.name.startswith("fixed") and g.name.startswith("fixed"):
        return "greedy"
    return "pruned" if f.monotone and g.monotone else "full"


def optimal_bits(seq: DataFrame, f: Code | str = "gamma", g: Code | str = "gamma", window: int | None = None, fold: int = FOLD, chunked: int = CHUNKED, chunk: int = 1 << 16, most: int = 1 << 16) -> DataFrame:
    """(seq_id, n, bits, route). Sequences of over ``chunked`` symbols need a window; their copies have at most ``most`` symbols,
    so they are exact for that dictionary; all others are exact as they are."""
    if strategy(f, g) == "full":
        raise NotMonotone("routes are for monotone codes; use parsers.run(..., ('optimal_full',))")
    short, long = seq.filter((F.col("n") <= fold) & (F.col("n") > 0)), seq.filter(F.col("n") > chunked)
    middle = seq.filter((F.col("n") == 0) | F.col("n").isNull() | (F.col("n") > fold) & (F.col("n") <= chunked))
    out = parsers.run(middle, ("optimal",), f, g, window, phrases=False).select("seq_id", F.col("n").cast("long").alias("n"), "bits", F.lit("kernel").alias("route"))
    if fold:
        sym = sequences.explode(short)
        copies = repeats.prev_occurrence(repeats.grams(sym))
        near = copies.filter(F.col("dist") <= window) if window else copies
        priced = stars.prune_edges(stars.edges(near, sym, f, g), f, g)
        folded = shortest.fold_costs(priced).join(short.select("seq_id", F.col("n").cast("long").alias("n")), "seq_id")
        out = out.unionByName(folded.select("seq_id", "n", "bits", F.lit("fold").alias("route")))
    if window:
        phrases = chunks.online(chunks.split(long, chunk, 0), window, most, f, g)
        cut = phrases.groupBy("seq_id").agg(F.sum("len").alias("n"), F.sum("bits").alias("bits"))
        out = out.unionByName(cut.select("seq_id", "n", "bits", F.lit("chunks").alias("route")))
    elif not long.isEmpty():
        raise ValueError(f"sequences of over {chunked} symbols need a window")
    return out


def share_copies(seq: DataFrame, parse_distinct) -> DataFrame:
    """Parses equal sequences once: ``parse_distinct`` gets one of each and gives rows with seq_id; every sequence gets its rows.

    Worth its two shuffles where many sequences are copies. Sequences are told apart by 128 bits of hash and their length.
    """
    syms = F.col("syms").cast("array<bigint>")
    keyed = seq.withColumns({"__h": F.xxhash64(syms), "__k": F.xxhash64(F.lit(1), syms)})
    one = keyed.groupBy("__h", "__k", "n").agg(F.min("seq_id").alias("__one"))
    first = seq.join(one.select(F.col("__one").alias("seq_id")), "seq_id", "left_semi")
    made = parse_distinct(first).withColumnRenamed("seq_id", "__one")
    return keyed.select("seq_id", "__h", "__k", "n").join(one, ["__h", "__k", "n"]).select("seq_id", "__one").join(made, "__one").drop("__one")
