"""Strings on which greedy parsing is far from the optimum, and closed forms for them; and the extremes."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from bitparse.functions.codes import Code, code

A, B, C = 1, 2, 3


def bad_strings(spark: SparkSession, most: int, least: int = 2) -> DataFrame:
    """The strings of l = least..most."""
    return strings_of(spark.range(least, most + 1).withColumnRenamed("id", "seq_id"))


def strings_of(own: DataFrame) -> DataFrame:
    """(seq_id = l, n, syms) for rows of l as seq_id: b, l times a, 2^l times c, then b and k times a for k = 1..l."""
    part = lambda k: F.concat(F.array(F.lit(B)), F.array_repeat(F.lit(A), k.cast("int")))
    l = F.col("seq_id")  # noqa: E741
    tail = F.flatten(F.transform(F.sequence(F.lit(1), l.cast("int")), part))
    syms = F.concat(part(l), F.array_repeat(F.lit(C), F.call_function("shiftleft", F.lit(1), l.cast("int"))), tail)
    return own.select("seq_id", syms.alias("syms")).select("seq_id", F.size("syms").alias("n"), "syms")


def closed_forms(strings: DataFrame, f: Code | str = "gamma", g: Code | str = "gamma") -> DataFrame:
    """(seq_id, greedy_phrases, near_phrases, greedy_bits, near_bits): what greedy parsing and the parser that copies
    from the part just before give, as expressions. For l from 3 on."""
    f, g = code(f), code(g)
    l = F.col("seq_id").cast("int")  # noqa: E741
    literal = lambda s: F.lit(f.bits(0) + g.bits(s)).cast("long")
    copy = lambda d, n: f.column(d) + g.column(n)
    power = F.call_function("shiftleft", F.lit(1), l)
    add = lambda values: F.aggregate(values, F.lit(0).cast("long"), lambda a, x: a + x)
    head = literal(B) + literal(A) + copy(F.lit(1), l - 1) + literal(C) + copy(F.lit(1), power - 1)
    far = lambda k: copy(l + 1 + power + ((k - 1) * (k + 2) / 2).cast("int"), k + 1)
    near = lambda k: copy(k, k) + literal(A)
    return strings.select(
        "seq_id", "n", (l + 5).cast("long").alias("greedy_phrases"), (2 * l + 5).cast("long").alias("near_phrases"),
        (head + add(F.transform(F.sequence(F.lit(1), l), far))).alias("greedy_bits"), (head + literal(B) + literal(A) + add(F.transform(F.sequence(F.lit(2), l), near))).alias("near_bits"),
    )


def near_copy_parse(strings: DataFrame) -> DataFrame:
    """(seq_id, phrases): start, length and distance of the parser that copies each part from the one just before it."""
    l = F.col("seq_id").cast("int")  # noqa: E741
    step = lambda i, n, d: F.struct(i.cast("int").alias("start"), n.cast("int").alias("len"), d.cast("int").alias("dist"))
    one, power = F.lit(1), F.call_function("shiftleft", F.lit(1), l)
    base = l + 2 + power
    at = lambda k: base + ((k - 1) * (k + 2) / 2).cast("int")
    head = F.array(step(one, one, F.lit(0)), step(one + 1, one, F.lit(0)), step(one + 2, l - 1, one), step(l + 2, one, F.lit(0)), step(l + 3, power - 1, one), step(base, one, F.lit(0)), step(base + 1, one, F.lit(0)))
    rest = F.flatten(F.transform(F.sequence(F.lit(2), l), lambda k: F.array(step(at(k), k, k), step(at(k) + k, one, F.lit(0)))))
    return strings.select("seq_id", F.concat(head, rest).alias("phrases"))


def extremes(spark: SparkSession, n: int) -> DataFrame:
    """One symbol n times (seq_id 0), all distinct (1), and 16 symbols by a hash (2)."""
    every = F.sequence(F.lit(1), F.lit(n))
    kinds = [F.transform(every, lambda x: F.lit(1)), every, F.transform(every, lambda x: (F.pmod(F.xxhash64(x), F.lit(16)) + 1).cast("int"))]
    return spark.range(1).select(F.posexplode(F.array(*kinds)).alias("seq_id", "syms")).select(F.col("seq_id").cast("long").alias("seq_id"), F.size("syms").alias("n"), "syms")
