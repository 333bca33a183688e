"""Parses as bits and back. A payload is n as a delta codeword, then f(d) and g(v) of each phrase, most significant bit first.

d = 0 marks a literal and v is its symbol; d > 0 copies v symbols from d back, one at a time, so that a
copy may overlap itself. A triple adds g(next symbol). nbits leaves out the header, so it equals the
bits of the parse.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

from bitparse.functions.codes import Code, Reader, code, delta

ENCODED = "seq_id long, n int, parser string, f string, g string, nbits long, payload binary"


def to_bits(n: int, phrases: list[dict], f: Code, g: Code) -> tuple[str, str]:
    """Header and body."""
    body = []
    for p in phrases:
        if p["kind"] == "triple":
            body += [f.word(p["dist"]), g.word(p["len"] - 1), g.word(p["next"])]
        else:
            body += [f.word(p["dist"]), g.word(p["sym"] if p["kind"] == "literal" else p["len"])]
    return delta().word(n), "".join(body)


def from_bits(bits: str, f: Code, g: Code, triple: bool = False) -> list[int]:
    r = Reader(bits)
    n, out = delta().read(r), []
    read_f, read_g = f.read, g.read
    while len(out) < n:
        d, v = read_f(r), read_g(r)
        if triple or d:
            if v <= d:
                out += out[len(out) - d : len(out) - d + v]
            else:  # it runs over itself
                out += (out[-d:] * (v // d + 1))[:v]
            if triple:
                out.append(read_g(r))
        else:
            out.append(v)
    return out


def _words(code: Code, values: np.ndarray) -> np.ndarray:
    """The codewords of values, each made once."""
    distinct, at = np.unique(values, return_inverse=True)
    return np.array([code.word(x) for x in distinct.tolist()] + [""], object)[at]


def _body(phrases: pa.StructArray, f: Code, g: Code) -> str:
    """The codewords of phrases in columns."""
    kind, size, dist, sym, after = (phrases.field(c) for c in ("kind", "len", "dist", "sym", "next"))
    size, triple = size.to_numpy(zero_copy_only=False), len(kind) and kind[0].as_py() == "triple"
    value = size - 1 if triple else np.where(pc.equal(kind, "literal").to_numpy(zero_copy_only=False), pc.fill_null(sym, 0).to_numpy(zero_copy_only=False), size)
    columns = [_words(f, dist.to_numpy(zero_copy_only=False)), _words(g, value)]
    if triple:
        columns.append(_words(g, after.to_numpy(zero_copy_only=False)))
    return "".join(np.stack(columns, axis=1).ravel().tolist())


def encode(parse: DataFrame) -> DataFrame:
    """Payloads of parses, under the codes that each was made for."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                row = {c: batch[c][k].as_py() for c in ("seq_id", "n", "parser", "f", "g")}
                body = _body(batch["phrases"][k].values, code(row["f"]), code(row["g"]))
                bits = delta().word(row["n"]) + body
                payload = int("1" + bits + "0" * (-len(bits) % 8), 2).to_bytes(1 + -(-len(bits) // 8), "big")[1:]
                yield pa.RecordBatch.from_pydict({**{c: [row[c]] for c in ("seq_id",)}, "n": pa.array([row["n"]], pa.int32()), "parser": [row["parser"]], "f": [row["f"]], "g": [row["g"]], "nbits": [len(body)], "payload": pa.array([payload], pa.binary())})

    return parse.select("seq_id", "n", "parser", "f", "g", "phrases").mapInArrow(run, ENCODED)


def of_phrases(phrases: DataFrame, f: Code | str = "gamma", g: Code | str = "gamma", per: int = 1 << 16) -> DataFrame:
    """(seq_id, part, payload): the payloads of phrases that stand in rows (seq_id, start, len, dist, sym), about ``per`` symbols each.

    For sequences that no row can hold: each payload is n of its part and the codewords, so parts are read one after another.
    """
    names = code(f).name, code(g).name

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, key, part, held, size = (code(names[0]), code(names[1])), None, 0, [], 0

        def close():
            head, body = to_bits(size, held, *own)
            bits = head + body
            return pa.RecordBatch.from_arrays([pa.array([key], pa.int64()), pa.array([part], pa.int64()), pa.array([int("1" + bits + "0" * (-len(bits) % 8), 2).to_bytes(1 + -(-len(bits) // 8), "big")[1:]], pa.binary())], ["seq_id", "part", "payload"])

        for batch in batches:
            for r in batch.to_pylist():
                if held and (r["seq_id"] != key or size >= per):
                    yield close()
                    part, held, size = (part + 1 if r["seq_id"] == key else 0), [], 0
                key = r["seq_id"]
                held.append({"kind": "copy" if r["dist"] else "literal", **r})
                size += r["len"]
        if held:
            yield close()

    dealt = phrases.select("seq_id", "start", "len", "dist", "sym").repartition("seq_id").sortWithinPartitions("seq_id", "start")
    return dealt.mapInArrow(run, "seq_id long, part long, payload binary")


def to_symbols(payloads: list[bytes], f: Code | str = "gamma", g: Code | str = "gamma") -> list[int]:
    """The symbols of one sequence from its parts in order; copies may reach back into earlier parts."""
    out: list[int] = []
    f, g = code(f), code(g)
    for raw in payloads:
        r = Reader(format(int.from_bytes(b"\1" + raw, "big"), "b")[1:])
        end = delta().read(r) + len(out)
        while len(out) < end:
            d, v = f.read(r), g.read(r)
            if not d:
                out.append(v)
            elif v <= d:
                out += out[len(out) - d : len(out) - d + v]
            else:
                own = out[-d:]
                out += (own * (v // d + 1))[:v]
    return out


def decode(encoded: DataFrame) -> DataFrame:
    """(seq_id, n, syms) from payloads."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                raw = batch["payload"][k].as_py()
                bits = format(int.from_bytes(b"\1" + raw, "big"), "b")[1:]
                syms = from_bits(bits, code(batch["f"][k].as_py()), code(batch["g"][k].as_py()), batch["parser"][k].as_py() == "greedy_triple")
                yield pa.RecordBatch.from_arrays([batch["seq_id"].slice(k, 1), pa.array([len(syms)], pa.int32()), pa.array([np.array(syms, np.int64)], pa.list_(pa.int64()))], ["seq_id", "n", "syms"])

    return encoded.mapInArrow(run, "seq_id long, n int, syms array<bigint>")
