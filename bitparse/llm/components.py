"""Connected components by randomised contraction, all of it distributed.

Each round every node hooks onto the neighbour of smallest random priority, if that is smaller
than its own, and the edges are contracted. Priorities change with the round, so a path in id
order also shrinks by a constant factor. Only aggregates and equi-joins on node ids are used;
each round is written to the shared folder, so a lost executor costs no earlier round.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bitparse.llm.common import store


def components(edges: DataFrame) -> DataFrame:
    """(id, root) of every node of the edges (a, b). Repeated edges and loops do no harm; no edges give no rows."""
    edges = store(edges.select("a", "b").filter("a <> b"), "edges")
    maps: list[DataFrame] = []
    while not edges.isEmpty():
        rank = lambda v: F.struct(F.xxhash64(F.lit(len(maps)), v).alias("p"), v.alias("v"))
        both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        best = both.groupBy("a").agg(F.min(rank(F.col("b"))).alias("m"))
        hooked = store(best.select(F.col("a").alias("id"), F.least(F.col("m"), rank(F.col("a")))["v"].alias("root")), "hooks")
        maps.append(hooked)
        at_a, at_b = (hooked.select(F.col("id").alias(k), F.col("root").alias(f"r{k}")) for k in "ab")
        moved = edges.join(at_a, "a").join(at_b, "b").filter("ra <> rb")
        edges = store(moved.select(F.least("ra", "rb").alias("a"), F.greatest("ra", "rb").alias("b")).distinct(), "edges")
    if not maps:
        return edges.select(F.col("a").alias("id"), F.col("b").alias("root"))
    out = maps[-1]
    for earlier in reversed(maps[:-1]):
        later = out.select(F.col("id").alias("root"), F.col("root").alias("__root"))
        out = earlier.join(later, "root", "left").select("id", F.coalesce("__root", "root").alias("root"))
    return store(out, "roots")


def forest(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Of n local nodes with edges (a, b): the smallest node of each node's component."""
    label = np.arange(n)
    while True:
        low = np.minimum(label[a], label[b])
        if (label[a] == low).all() and (label[b] == low).all():
            return label
        np.minimum.at(label, label[a], low)
        np.minimum.at(label, label[b], low)
        while True:
            up = label[label]
            if (up == label).all():
                break
            label = up
