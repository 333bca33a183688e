"""Integer codes: lengths as Python numbers, as columns and as SQL, codewords, and plateaus of equal length.

Values start at 0. Codes of numbers from 1 on (gamma, delta, omega, Fibonacci) are used for x + 1.
"""

from __future__ import annotations

import heapq
from collections.abc import Callable, Iterable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

FIBONACCI = [1, 2]
while FIBONACCI[-1] < 1 << 40:
    FIBONACCI.append(FIBONACCI[-1] + FIBONACCI[-2])


class NotMonotone(ValueError):
    """A code whose lengths may fall was given to a method that needs lengths that never fall."""


class Reader:
    """Reads codewords from a string of 0 and 1."""

    def __init__(self, bits: str):
        self.bits, self.at = bits, 0

    def take(self, n: int) -> int:
        self.at += n
        return int(self.bits[self.at - n : self.at], 2) if n else 0

    def run(self, bit: str) -> int:
        """The number of equal bits here; passes them and the bit that ends them."""
        end = self.bits.index("1" if bit == "0" else "0", self.at)
        n, self.at = end - self.at, end + 1
        return n


@dataclass(frozen=True)
class Code:
    name: str
    bits: Callable[[int], int]
    column: Callable[[Column], Column] = field(compare=False)
    sql: Callable[[str], str] = field(compare=False)
    word: Callable[[int], str] = field(compare=False)
    read: Callable[[Reader], int] = field(compare=False)
    monotone: bool = True
    limit: int | None = None  # the largest value that has a codeword, if not all have

    def __reduce__(self):
        return by_name, (self.name,)


def _bin(y: int) -> str:
    return format(y, "b")


def _length(y: Column) -> Column:
    return F.length(F.bin(y)).cast("long")


def _gamma_word(y: int) -> str:
    return "0" * (y.bit_length() - 1) + _bin(y)


def _gamma_read(r: Reader) -> int:
    n = r.run("0")
    return (1 << n) | r.take(n)


def gamma() -> Code:
    return Code("gamma", lambda x: 2 * (x + 1).bit_length() - 1, lambda x: 2 * _length(x + 1) - 1, lambda x: f"(2 * length(bin({x} + 1)) - 1)", lambda x: _gamma_word(x + 1), lambda r: _gamma_read(r) - 1)


def delta() -> Code:
    def read(r: Reader) -> int:
        n = _gamma_read(r) - 1
        return ((1 << n) | r.take(n)) - 1

    return Code(
        "delta",
        lambda x: (n := (x + 1).bit_length()) - 1 + 2 * n.bit_length() - 1,
        lambda x: _length(x + 1) - 1 + 2 * _length(_length(x + 1)) - 1,
        lambda x: f"(length(bin({x} + 1)) - 1 + 2 * length(bin(length(bin({x} + 1)))) - 1)",
        lambda x: _gamma_word((x + 1).bit_length()) + _bin(x + 1)[1:],
        read,
    )


def omega() -> Code:
    def groups(y: int) -> str:
        out = "0"
        while y > 1:
            out, y = _bin(y) + out, y.bit_length() - 1
        return out

    def read(r: Reader) -> int:
        y = 1
        while r.bits[r.at] == "1":
            y = r.take(y + 1)
        r.at += 1
        return y - 1

    # the length follows from the number of binary digits alone
    by_digits = [len(groups(1 << (n - 1))) for n in range(1, 64)]
    case = "(case length(bin({x} + 1)) " + " ".join(f"when {n} then {b}" for n, b in enumerate(by_digits, 1)) + " end)"
    return Code("omega", lambda x: by_digits[(x + 1).bit_length() - 1], lambda x: F.element_at(F.lit(by_digits), _length(x + 1).cast("int")).cast("long"), lambda x: case.replace("{x}", x), lambda x: groups(x + 1), read)


def fibonacci() -> Code:
    def index(y: int) -> int:
        return sum(f <= y for f in FIBONACCI)

    def word(x: int) -> str:
        y, out = x + 1, []
        for f in reversed(FIBONACCI[: index(y)]):
            out.append("1" if f <= y else "0")
            y -= f if f <= y else 0
        return "".join(reversed(out)) + "1"

    def read(r: Reader) -> int:
        end = r.bits.index("11", r.at)
        y = sum(f for f, b in zip(FIBONACCI, r.bits[r.at : end + 1], strict=False) if b == "1")
        r.at = end + 2
        return y - 1

    case = lambda x: "(case " + " ".join(f"when {x} + 1 < {f} then {k + 1}" for k, f in enumerate(FIBONACCI) if k) + " end)"
    return Code("fibonacci", lambda x: index(x + 1) + 1, lambda x: (F.size(F.filter(F.lit(FIBONACCI), lambda f: f <= x + 1)) + 1).cast("long"), case, word, read)


def _grouped(name: str, payload: int) -> Code:
    """Groups of payload bits, each after a flag that is 1 if another group follows."""

    def count(x: int) -> int:
        return max(1, -(-x.bit_length() // payload))

    def word(x: int) -> str:
        n = count(x)
        return "".join(("1" if k else "0") + format(x >> (payload * k) & ((1 << payload) - 1), f"0{payload}b") for k in reversed(range(n)))

    def read(r: Reader) -> int:
        x, more = 0, 1
        while more:
            more = r.take(1)
            x = x << payload | r.take(payload)
        return x

    return Code(name, lambda x: (payload + 1) * count(x), lambda x: (payload + 1) * F.ceil(_length(x) / payload).cast("long"), lambda x: f"({payload + 1} * ((length(bin({x})) + {payload - 1}) // {payload}))", word, read)


def varbyte() -> Code:
    return _grouped("varbyte", 7)


def nibble() -> Code:
    return _grouped("nibble", 4)


def unary() -> Code:
    return Code("unary", lambda x: x + 1, lambda x: x.cast("long") + 1, lambda x: f"({x} + 1)", lambda x: "1" * x + "0", lambda r: r.run("1"))


def rice(k: int) -> Code:
    return Code(f"rice{k}", lambda x: (x >> k) + 1 + k, lambda x: F.shiftright(x, k).cast("long") + 1 + k, lambda x: f"(({x} >> {k}) + {1 + k})", lambda x: "1" * (x >> k) + "0" + (format(x & ((1 << k) - 1), f"0{k}b") if k else ""), lambda r: r.run("1") << k | r.take(k))


def _within(x: Column, lo: int, hi: int, bits: Column, name: str) -> Column:
    """``bits`` where the value has a codeword, null where it is null, and an error elsewhere."""
    return F.when(x.isNull(), F.lit(None).cast("long")).when(x.between(lo, hi), bits).otherwise(F.raise_error(F.lit(f"no codeword of {name} for this value")).cast("long"))


def fixed(b: int) -> Code:
    """b digits for every value below 2^b; larger values are refused."""

    def checked(x: int) -> int:
        if not 0 <= x < 1 << b:
            raise ValueError(f"fixed{b} has no codeword for {x}")
        return x

    return Code(f"fixed{b}", lambda x: b if checked(x) >= 0 else 0, lambda x: _within(x, 0, (1 << b) - 1, F.lit(b).cast("long"), f"fixed{b}"), lambda x: f"({b})", lambda x: format(checked(x), f"0{b}b"), lambda r: r.take(b), limit=(1 << b) - 1)


def table(plateaus: Iterable[tuple[int, int, int]], name: str | None = None) -> Code:
    """A code from plateaus (lo, hi, bits) that cover 0..n; codewords are canonical, in order of value, and values beyond n are refused."""
    rows = tuple(sorted(tuple(map(int, p)) for p in plateaus))
    if sum((hi - lo + 1) * 2.0**-b for lo, hi, b in rows) > 1 + 1e-12:
        raise ValueError("no prefix code has these lengths")
    starts, code, last = {}, 0, 0
    for lo, hi, b in sorted(rows, key=lambda p: (p[2], p[0])):
        code <<= b - last
        starts[lo], last = (code, hi, b), b
        code += hi - lo + 1

    def row(x: int) -> tuple[int, int, int]:
        for p in rows:
            if p[0] <= x <= p[1]:
                return p
        raise ValueError(f"the table has no codeword for {x}")

    def read(r: Reader) -> int:
        for lo, (first, hi, b) in sorted(starts.items(), key=lambda s: s[1][2]):
            own = int(r.bits[r.at : r.at + b] or "0", 2) - first
            if len(r.bits) >= r.at + b and 0 <= own <= hi - lo:
                r.at += b
                return lo + own
        raise ValueError("no codeword")

    def column(x: Column) -> Column:
        out = F.lit(None).cast("long")
        for lo, hi, b in reversed(rows):
            out = F.when(x.between(lo, hi), F.lit(b).cast("long")).otherwise(out)
        return _within(x, rows[0][0], rows[-1][1], out, "the table") if rows else out

    monotone = all(a[2] <= b[2] for a, b in zip(rows, rows[1:], strict=False))
    sql = lambda x: "(case " + " ".join(f"when {x} between {lo} and {hi} then {b}" for lo, hi, b in rows) + " end)"
    return Code(name or "table" + repr(rows), lambda x: row(x)[2], column, sql, lambda x: format(starts[row(x)[0]][0] + x - row(x)[0], f"0{row(x)[2]}b"), read, monotone, rows[-1][1] if rows else -1)


def table_of(plateaus_of: DataFrame) -> Code:
    """The same from rows (lo, hi, bits), of which there may be MOST_PLATEAUS."""
    rows = plateaus_of.select("lo", "hi", "bits").limit(MOST_PLATEAUS + 1).collect()
    if len(rows) > MOST_PLATEAUS:
        raise ValueError(f"over {MOST_PLATEAUS} plateaus")
    return table([tuple(r) for r in rows])


def deflate_like(classes: int = 30) -> Code:
    """Buckets of base and extra bits: five bits for the bucket; two buckets for each number of extra bits."""
    rows, lo = [], 0
    for k in range(classes):
        extra = max(0, k // 2 - 1)
        rows.append((lo, lo + (1 << extra) - 1, 5 + extra))
        lo += 1 << extra
    merged: list[list[int]] = []
    for a, b, bits in rows:
        if merged and merged[-1][2] == bits:
            merged[-1][1] = b
        else:
            merged.append([a, b, bits])
    return table([tuple(m) for m in merged], f"deflate{classes}")


def static_entropy(histogram: dict[int, int]) -> Code:
    """Huffman lengths of a histogram of values. Not monotone in general; values not seen escape to gamma."""
    counts = {**histogram, -1: 1}
    heap = [(n, k, (v,)) for k, (v, n) in enumerate(sorted(counts.items()))]
    heapq.heapify(heap)
    depth, serial = dict.fromkeys(counts, 0), len(heap)
    while len(heap) > 1:
        (a, _, x), (b, _, y) = heapq.heappop(heap), heapq.heappop(heap)
        for v in x + y:
            depth[v] += 1
        heapq.heappush(heap, (a + b, serial, x + y))
        serial += 1
    words, code, last = {}, 0, 0
    for v, b in sorted(depth.items(), key=lambda d: (d[1], d[0])):
        code <<= b - last
        words[v], last = format(code, f"0{b}b") if b else "", b
        code += 1
    back, escape = {w: v for v, w in words.items()}, gamma()

    def read(r: Reader) -> int:
        w = ""
        while w not in back:
            w += r.bits[r.at]
            r.at += 1
        return back[w] if back[w] >= 0 else escape.read(r)

    def column(x: Column) -> Column:
        known = F.create_map(*[F.lit(t) for v, b in depth.items() if v >= 0 for t in (v, b)]) if histogram else F.create_map(F.lit(-2), F.lit(0))
        return F.coalesce(known[x.cast("int")].cast("long"), depth[-1] + escape.column(x))

    name = "entropy" + repr(tuple(sorted(histogram.items())))
    monotone = False
    case = lambda x: "(case " + " ".join(f"when {x} = {v} then {b}" for v, b in depth.items() if v >= 0) + f" else {depth[-1]} + {escape.sql(x)} end)"
    return Code(name, lambda x: depth[x] if x in depth and x >= 0 else depth[-1] + escape.bits(x), column, case, lambda x: words[x] if x in words and x >= 0 else words[-1] + escape.word(x), read, monotone)


def by_name(name: str) -> Code:
    """A code by the name it bears, so that codes can be shipped and named in SQL."""
    plain = {"gamma": gamma, "delta": delta, "omega": omega, "fibonacci": fibonacci, "varbyte": varbyte, "nibble": nibble, "unary": unary}
    if name in plain:
        return plain[name]()
    for kind, make in (("rice", rice), ("fixed", fixed), ("deflate", deflate_like)):
        if name.startswith(kind) and name[len(kind) :].isdigit():
            return make(int(name[len(kind) :]))
    import ast

    if name.startswith("table("):
        return table(ast.literal_eval(name[5:]))
    if name.startswith("entropy"):
        return static_entropy(dict(ast.literal_eval(name[7:])))
    raise ValueError(f"no code {name!r}")


def code(named: Code | str) -> Code:
    return named if isinstance(named, Code) else by_name(named)


MOST_PLATEAUS = 10_000
STANDARD = ("gamma", "delta", "omega", "fibonacci", "varbyte", "nibble", "rice2", "unary", "fixed13")


def plateaus(named: Code | str, n: int, lo: int = 0) -> list[tuple[int, int, int]]:
    """(lo, hi, bits): the ranges of equal length over lo..n, by bisection."""
    own, out = code(named), []
    if not own.monotone:
        raise NotMonotone(own.name)
    n = n if own.limit is None else min(n, own.limit)
    while lo <= n:
        bits, hi, step = own.bits(lo), lo, 1
        while hi + step <= n and own.bits(hi + step) == bits:
            hi, step = hi + step, step * 2
        while step:
            if hi + step <= n and own.bits(hi + step) == bits:
                hi += step
            step //= 2
        out.append((lo, hi, bits))
        lo = hi + 1
    return out


def n_plateaus(named: Code | str, n: int) -> int:
    return len({p[2] for p in plateaus(named, n, 1)})


def lengths(spark: SparkSession, n: int, names: Iterable[str] = STANDARD) -> DataFrame:
    """(code, x, bits) for x in 0..n, all of it expressions over a range."""
    return lengths_of(spark.range(n + 1).withColumnRenamed("id", "x"), names)


def lengths_of(own: DataFrame, names: Iterable[str] = STANDARD) -> DataFrame:
    """The same for rows of x."""
    pairs = F.array(*(F.struct(F.lit(k).alias("code"), code(k).column(F.col("x")).alias("bits")) for k in names))
    return own.select("x", F.explode(pairs).alias("c")).select("c.code", "x", "c.bits")


def plateau_table(lengths_of: DataFrame) -> DataFrame:
    """(code, k, lo, hi, bits) from rows of ``lengths``."""
    from pyspark.sql import Window

    own = lengths_of.groupBy("code", "bits").agg(F.min("x").alias("lo"), F.max("x").alias("hi"))
    return own.select("code", F.row_number().over(Window.partitionBy("code").orderBy("lo")).cast("long").alias("k"), "lo", "hi", "bits")


def is_monotone(lengths_of: DataFrame) -> DataFrame:
    """(code, monotone): whether lengths never fall as x grows."""
    from pyspark.sql import Window

    before = F.lag("bits").over(Window.partitionBy("code").orderBy("x"))
    return lengths_of.select("code", (F.col("bits") < before).alias("falls")).groupBy("code").agg((~F.coalesce(F.bool_or("falls"), F.lit(False))).alias("monotone"))


def log_ratio(lengths_of: DataFrame) -> DataFrame:
    """(code, least, most): bits over log2(x + 1), for x from 1 on."""
    ratio = F.col("bits") / F.log2(F.col("x") + 1)
    return lengths_of.filter("x >= 1").groupBy("code").agg(F.round(F.min(ratio), 6).alias("least"), F.round(F.max(ratio), 6).alias("most"))
