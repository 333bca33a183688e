"""Streams of symbols: the growing dictionary and the windowed optimum by key, and parses of event-time windows."""

from __future__ import annotations

import pickle
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from bitparse.functions.codes import Code, code
from bitparse.operators import chunks, parsers

_ORDER = ["ts", "event_id"]


def _in_order(parts: Iterator[pd.DataFrame]) -> list:
    """The symbols of a trigger by (ts, event_id); None, which ends a sequence, stands for a null."""
    whole = pd.concat(list(parts))
    return [None if pd.isna(s) else int(s) for s in whole.sort_values(_ORDER)["s"].tolist()]


def lz78(stream: DataFrame) -> DataFrame:
    """Phrases (key, k, id, sym) as they are completed. stream: key, s, ts, event_id. State: the tree and the open phrase.

    Within a trigger symbols are put in order of (ts, event_id); a phrase that is still open is given when a
    row without a symbol ends the sequence, with which the key starts anew.
    """

    def step(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        child, node, k = pickle.loads(state.get[0]) if state.exists else ({}, 0, 0)
        out = []
        for s in _in_order(parts):
            if s is None:  # the end: the open phrase is a known one, without a symbol of its own
                if node:
                    k += 1
                    out.append((key[0], k, node, None))
                child, node, k = {}, 0, 0
                continue
            if (node, s) in child:
                node = child[node, s]
                continue
            child[node, s] = len(child) + 1
            k += 1
            out.append((key[0], k, node, s))
            node = 0
        state.update((pickle.dumps((child, node, k)),))
        made = pd.DataFrame(out, columns=["key", "k", "id", "sym"])
        yield made.astype({"sym": "Int64"})

    return stream.groupBy("key").applyInPandasWithState(step, "key long, k long, id long, sym long", "state binary", "append", GroupStateTimeout.NoTimeout)


def windowed_optimal(stream: DataFrame, window: int, most: int, f: Code | str = "gamma", g: Code | str = "gamma", idle: str | None = None) -> DataFrame:
    """Parts (key, start from 1, n, bits) of the windowed optimum as they become final: together they cover the sequence without a
    cut, and their bits add up to those of the batch. A row without a symbol ends a sequence; with ``idle`` (milliseconds as
    text) so does that long a time without rows. State: the last ``window`` symbols and those that are not final."""
    names = code(f).name, code(g).name

    def step(key: tuple, rows: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        own = chunks.Online(window, most, *names, pickle.loads(state.get[0]) if state.exists else None)
        out = []

        def give(found: list) -> None:
            if found:
                out.append((key[0], found[0][0] + 1, sum(p[1] for p in found), sum(p[4] for p in found)))

        symbols = [None] if state.hasTimedOut else _in_order(rows)
        while symbols:
            end = symbols.index(None) if None in symbols else len(symbols)
            give(own.feed(np.array(symbols[:end], np.int64), last=end < len(symbols)))
            if end < len(symbols):
                own = chunks.Online(window, most, *names)
            symbols = symbols[end + 1 :]
        if own.at or len(own.waiting):
            state.update((pickle.dumps(own.state),))
            if idle:
                state.setTimeoutDuration(int(idle))
        elif state.exists:
            state.remove()
        yield pd.DataFrame(out, columns=["key", "start", "n", "bits"])

    timeout = GroupStateTimeout.ProcessingTimeTimeout if idle else GroupStateTimeout.NoTimeout
    return stream.groupBy("key").applyInPandasWithState(step, "key long, start long, n long, bits long", "state binary", "append", timeout)


def window_bits(events: DataFrame, span: Column, f: Code | str = "gamma", g: Code | str = "gamma") -> DataFrame:
    """(key, begins, ends, n, bits): the optimum of each key's symbols in each window; ``span`` is window(...) or
    session_window(...) of ts. Works on batches and, with a watermark on ts, on streams."""
    own = events.groupBy(span.alias("w"), "key").agg(F.array_sort(F.collect_list(F.struct(*_ORDER, "s"))).alias("rows"))
    # the window's ends go through the parse in the sequence's own columns
    kind = own.select("key", F.col("w.start").alias("begins"), F.col("w.end").alias("ends"), F.transform("rows", lambda r: r["s"].cast("bigint")).alias("syms"))
    names = code(f).name, code(g).name

    def kernel(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        c = code(names[0]), code(names[1])
        for batch in batches:
            made = [parsers.Sequence(np.array(s, np.int64), *c) for s in batch["syms"]]
            yield batch[["key", "begins", "ends"]].assign(n=[s.n for s in made], bits=[s.total(s.optimal()) for s in made])

    return kind.mapInPandas(kernel, "key long, begins timestamp, ends timestamp, n long, bits long")


def symbols(events: DataFrame, symbol: Column) -> DataFrame:
    """key, s, ts and event_id of events by user."""
    return events.select(F.col("user_id").alias("key"), symbol.cast("long").alias("s"), F.col("ts").cast("timestamp").alias("ts"), "event_id")


def deduplicated(stream: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Repeated events go while the watermark still remembers them; later ones are dropped as late."""
    return stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])
