"""Embedding near-duplicates by product quantisation over inverted lists.

Equal vectors are one node from the start. Lists have two levels: the nearest of some coarse
centroids, then the nearest of the fine ones, which all coarse lists share, to what is left. There is
a list for about PER_LIST vectors, so lists grow with the input, while at most COARSE + FINE centroids
are broadcast. The residual is coded as one codeword for each of PARTS subspaces, and the length of
what the code misses is kept. A query goes to every list whose border at either level (the plane half
way between its centroid and the query's own) is within a margin of it. In a list, asymmetric distances are
sums of table look-ups; a candidate is a row whose look-up distance is at most the link radius plus
what its code misses, which no true neighbour exceeds. The cosine of every candidate is then computed
from the vectors in double precision, and that alone decides.

So quantisation loses nothing; only the margin can, where neither of two neighbours reaches the list
of the other: a pair counts for both once either finds it. The margin is MARGIN standard deviations of the part
that a step of the link radius in a random direction has along one axis; ``exact=True`` takes the
whole radius, which no neighbour can be beyond, at the cost of more probes. The quantisers are
fitted on a sample of at most SAMPLE vectors, chosen by a hash of their id; every row is indexed.

Lists over BLOCK members are dealt in blocks. A task gives counts of links and at most one edge for
each row it holds, never all pairs.

Defined results: vectors that are null, empty, zero, or that hold null, NaN or infinite components
link with nothing; vectors of different lengths never link; a null vec_id counts as a vector like
others, but names no component; rows with equal vec_id are told apart by their vectors only.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from bitparse.llm.common import store, table
from bitparse.llm.components import components, forest

COSINE, MARGIN, SAMPLE, PER_LIST, COARSE, FINE, PARTS, WORDS, BLOCK, QUERIES = 0.95, 3.0, 20_000, 1000, 256, 4096, 8, 256, 4096, 512
SMALL = 200_000  # lists up to which their sizes are broadcast


def unit(rows: np.ndarray) -> np.ndarray:
    """Rows of length one, in double precision, for any finite rows that are not zero."""
    rows = rows.astype(np.float64)
    rows = rows / np.abs(rows).max(axis=1, keepdims=True)
    return rows / np.sqrt((rows * rows).sum(axis=1, keepdims=True))


def squared(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.maximum((a * a).sum(axis=1)[:, None] + (b * b).sum(axis=1)[None, :] - 2 * a @ b.T, 0)


def k_means(rows: np.ndarray, k: int, rounds: int = 8, seed: int = 7) -> np.ndarray:
    centres = rows[np.random.default_rng(seed).permutation(len(rows))[:k]].copy()
    for _ in range(rounds):
        own = squared(rows, centres).argmin(axis=1)
        size = np.bincount(own, minlength=len(centres))
        total = np.zeros_like(centres)
        np.add.at(total, own, rows)
        centres[size > 0] = total[size > 0] / size[size > 0, None]
    return centres


@dataclass
class Index:
    """Coarse and fine centroids and, for each subspace, the codewords of residuals. List c * len(fine) + k is coarse c, fine k."""

    coarse: np.ndarray
    fine: np.ndarray
    cuts: list[int]
    words: list[np.ndarray]
    radius: float
    margin: float

    @staticmethod
    def fit(sample: np.ndarray, n: int, cosine: float = COSINE, margin: float = MARGIN, exact: bool = False) -> Index:
        rows, dims = unit(sample), sample.shape[1]
        lists = max(1, n // PER_LIST)
        coarse = k_means(rows, min(COARSE, len(rows), lists))
        residual = rows - coarse[squared(rows, coarse).argmin(axis=1)]
        most = min(FINE, len(rows), -(-lists // len(coarse)))
        fine = k_means(residual, most) if most > 1 else np.zeros((1, dims))
        residual = residual - fine[squared(residual, fine).argmin(axis=1)]
        cuts = sorted({round(k * dims / PARTS) for k in range(PARTS + 1)})
        words = [k_means(residual[:, a:b], min(WORDS, len(rows))) for a, b in zip(cuts, cuts[1:], strict=False)]
        radius = float(np.sqrt(2 - 2 * cosine))
        return Index(coarse, fine, cuts, words, radius, radius if exact else min(radius, margin * radius / np.sqrt(dims)))

    def centre(self, at: int) -> np.ndarray:
        return self.coarse[at // len(self.fine)] + self.fine[at % len(self.fine)]

    def _near(self, rows: np.ndarray, centres: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Of each row the nearest centre, and which centres' borders are within the margin."""
        far = squared(rows, centres)
        own = far.argmin(axis=1)
        apart = np.sqrt(squared(centres, centres))
        border = (far - far[np.arange(len(rows)), own][:, None]) / np.maximum(2 * apart[own], 1e-12)
        border[np.arange(len(rows)), own] = 0
        return own, border <= self.margin

    def assign(self, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, list[np.ndarray]]:
        """Of unit rows: the list, the codes, the length that the code misses, and the lists to probe, in order."""
        own, near = self._near(rows, self.coarse)
        row, at = np.nonzero(near)
        lists = own.astype(np.int64)
        owner, found = [], []
        for lo in range(0, len(row), 4096):
            r, c = row[lo : lo + 4096], at[lo : lo + 4096]
            fine, reached = self._near(rows[r] - self.coarse[c], self.fine)
            home = c == own[r]
            lists[r[home]] = c[home] * len(self.fine) + fine[home]
            k, f = np.nonzero(reached)
            owner.append(r[k])
            found.append(c[k] * len(self.fine) + f)
        owner, found = np.concatenate([*owner, np.zeros(0, np.int64)]), np.concatenate([*found, np.zeros(0, np.int64)])
        probes = np.split(found, np.searchsorted(owner, np.arange(1, len(rows))))
        residual = rows - self.coarse[own] - self.fine[lists % len(self.fine)]
        codes = np.zeros((len(rows), len(self.words)), np.uint8)
        for m, words in enumerate(self.words):
            codes[:, m] = squared(residual[:, self.cuts[m] : self.cuts[m + 1]], words).argmin(axis=1)
        return lists, codes, np.linalg.norm(residual - self.decoded(codes), axis=1), probes

    def decoded(self, codes: np.ndarray) -> np.ndarray:
        return np.concatenate([w[codes[:, m]] for m, w in enumerate(self.words)], axis=1)

    def candidates(self, queries: np.ndarray, at: int, codes: np.ndarray, miss: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Pairs (query, row) of one list whose look-up distance a link allows."""
        residual = queries - self.centre(at)
        near = np.zeros((len(queries), len(codes)), np.float32)
        for m, words in enumerate(self.words):
            near += squared(residual[:, self.cuts[m] : self.cuts[m + 1]], words).astype(np.float32)[:, codes[:, m]]
        return np.nonzero(near <= ((self.radius + miss + 1e-3) ** 2).astype(np.float32)[None, :])


def _matrix(column: pa.Array, dims: int) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).reshape(-1, dims)


def _links(batches: Iterator[pa.RecordBatch], index: Index, dims: int, cosine: float) -> Iterator[pa.RecordBatch]:
    """Rows sorted by list and block, the block's members (role 0) before its queries (role 1)."""
    members, key, done = None, None, []

    def flush(last: bool):
        """The links of the queries held so far with the members of their block."""
        if members is None or not done:
            return None
        ids, sizes, vectors, codes, miss, reach, own = members
        q_ids, q_vectors, q_sizes, q_lists = (np.concatenate(x) for x in zip(*done, strict=True))
        done.clear()
        a, b = index.candidates(q_vectors, own, codes, miss)
        close = np.empty(len(a), bool)
        for lo in range(0, len(a), 1 << 16):
            close[lo : lo + (1 << 16)] = np.einsum("ij,ij->i", q_vectors[a[lo : lo + (1 << 16)]], vectors[b[lo : lo + (1 << 16)]]) >= cosine
        a, b = a[close], b[close]
        a, b = a[q_ids[a] != ids[b]], b[q_ids[a] != ids[b]]
        nodes, at = np.unique(np.concatenate([q_ids, ids]), return_inverse=True)
        counts = np.zeros(len(nodes), np.int64)
        np.add.at(counts, at[: len(q_ids)][a], sizes[b])
        # a member that does not probe the query's list has no other way to this pair
        most = 1 + max(int(reach[:, 1].max(initial=0)), int(q_lists.max(initial=0)))
        known = reach[:, 0] * most + reach[:, 1]
        pair = b * most + q_lists[a]
        place = np.minimum(np.searchsorted(known, pair), max(0, len(known) - 1))
        alone = known[place] != pair if len(known) else np.ones(len(pair), bool)
        np.add.at(counts, at[len(q_ids) :][b[alone]], q_sizes[a[alone]])
        label = forest(len(nodes), at[: len(q_ids)][a], at[len(q_ids) :][b])
        roots = nodes[label]
        moved = nodes != roots
        linked = counts > 0
        kinds = np.concatenate([np.zeros(linked.sum(), np.int8), np.ones(moved.sum(), np.int8)])
        return pa.RecordBatch.from_arrays([pa.array(kinds, pa.int8()), pa.array(np.concatenate([nodes[linked], nodes[moved]])), pa.array(np.concatenate([counts[linked], roots[moved]]))], ["kind", "a", "b"])

    for batch in batches:
        rows = [(x["list"], x["block"]) for x in batch.select(["list", "block"]).to_pylist()]
        role = batch["role"].to_numpy()
        vectors = unit(_matrix(batch["v"], dims)) if batch.num_rows else None
        at = 0
        while at < len(rows):
            stop = at
            while stop < len(rows) and rows[stop] == rows[at] and role[stop] == role[at] and stop - at < QUERIES:
                stop += 1
            if rows[at] != key:
                if (out := flush(True)) is not None:
                    yield out
                key, members = rows[at], None
            part = batch.slice(at, stop - at)
            ids, sizes = part["node"].to_numpy(), part["n"].to_numpy()
            if role[at] == 0:
                codes = np.frombuffer(b"".join(part["codes"].to_pylist()), np.uint8).reshape(stop - at, -1)
                probes = part["probes"]
                before = len(members[0]) if members is not None else 0
                reach = np.stack([before + np.repeat(np.arange(stop - at), probes.value_lengths().to_numpy()), probes.flatten().to_numpy()], axis=1)
                own = (ids, sizes, vectors[at:stop], codes, part["miss"].to_numpy(), reach)
                members = (*own, key[0]) if members is None else (*(np.concatenate(x) for x in zip(members[:-1], own, strict=True)), key[0])
            elif members is not None:
                done.append((ids, vectors[at:stop], sizes, part["home"].to_numpy()))
                if sum(len(x[0]) for x in done) >= QUERIES and (out := flush(False)) is not None:
                    yield out
            at = stop
    if (out := flush(True)) is not None:
        yield out


def near_links(nodes: DataFrame, dims: int, cosine: float = COSINE, exact: bool = False) -> DataFrame:
    """Of stored rows (node, n, v), all vectors of one length: rows (kind, a, b), kind 0 for b links of node a, kind 1 for an edge."""
    spark = nodes.sparkSession
    n = nodes.count()
    draw = F.pmod(F.xxhash64(F.lit("sample"), "node"), F.lit(1 << 31))
    taken = nodes.filter(draw < min(1.0, 0.95 * SAMPLE / max(1, n)) * (1 << 31)).select("node", "v").orderBy("node").limit(SAMPLE).collect()
    if not taken:  # so few rows that the hash chose none
        taken = nodes.select("node", "v").orderBy("node").limit(SAMPLE).collect()
    index = Index.fit(np.array([r["v"] for r in taken], np.float64), n, cosine, exact=exact)
    shared = spark.sparkContext.broadcast(index)  # bounded by COARSE, FINE and WORDS

    def assign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, batch.num_rows, 2048):
                part = batch.slice(lo, 2048)
                own, codes, miss, probes = shared.value.assign(unit(_matrix(part["v"], dims)))
                yield pa.RecordBatch.from_arrays([part["node"], part["n"], part["v"], pa.array(own), pa.array([c.tobytes() for c in codes], pa.binary()), pa.array(miss), pa.array([p.tolist() for p in probes], pa.list_(pa.int64()))], ["node", "n", "v", "list", "codes", "miss", "probes"])

    kind = nodes.schema["v"].dataType.simpleString()
    indexed = store(nodes.select("node", "n", "v").mapInArrow(assign, f"node long, n long, v {kind}, list long, codes binary, miss double, probes array<long>"), "indexed")
    sizes = indexed.groupBy("list").count().select("list", F.ceil(F.col("count") / BLOCK).cast("int").alias("blocks"))
    blocks = F.broadcast(sizes) if len(index.coarse) * len(index.fine) <= SMALL else sizes
    members = indexed.join(blocks, "list").select("list", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int").alias("block"), F.lit(0).alias("role"), "node", "n", "v", "codes", "miss", "probes", F.lit(None).cast("long").alias("home"))
    probing = indexed.select("node", "n", "v", F.col("list").alias("home"), F.explode("probes").alias("list")).join(blocks, "list")
    queries = probing.select("list", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("block"), F.lit(1).alias("role"), "node", "n", "v", F.lit(None).cast("binary").alias("codes"), F.lit(None).cast("double").alias("miss"), F.lit(None).cast("array<long>").alias("probes"), "home")
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    dealt = members.unionByName(queries).repartition(max(parts, -(-n // BLOCK)), "list", "block").sortWithinPartitions("list", "block", "role")
    return dealt.mapInArrow(lambda batches: _links(batches, shared.value, dims, cosine), "kind byte, a long, b long")


def near_duplicates(vectors: DataFrame, cosine: float = COSINE, exact: bool = False) -> DataFrame:
    """(vec_id, n_links, component_id, kept) of rows (vec_id, embedding)."""
    v = F.col("embedding")
    valid = v.isNotNull() & ~F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))) & F.exists(v, lambda x: x != 0)
    keyed = vectors.select("vec_id", "embedding", F.coalesce(valid, F.lit(False)).alias("valid"))
    nonzero = F.transform(v, lambda x: F.when(x == 0, F.lit(0).cast(vectors.schema["embedding"].dataType.elementType)).otherwise(x))  # one zero
    rows = store(keyed.select("vec_id", "valid", F.when(F.col("valid"), nonzero).alias("v")).withColumn("h1", F.xxhash64("v")).withColumn("h2", F.xxhash64(F.lit(1), "v")), "vectors")
    same = rows.filter("valid").groupBy("h1", "h2").agg(F.min("vec_id").alias("least"), F.count("*").alias("n"), F.first("v").alias("v"))
    nodes = store(same.select("h1", "h2", "least", "n", "v", F.monotonically_increasing_id().alias("node")), "nodes")
    links = None
    for r in nodes.select(F.size("v").alias("dims")).distinct().orderBy("dims").collect():  # one row for each length of vectors
        own = near_links(nodes.filter(F.size("v") == r["dims"]), r["dims"], cosine, exact)
        links = own if links is None else links.unionByName(own)
    if links is None:
        return rows.select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"), F.lit(True).alias("kept"))
    links = store(links, "links")
    degree = links.filter("kind = 0").groupBy("a").agg(F.sum("b").alias("more")).withColumnRenamed("a", "node")
    roots = components(links.filter("kind = 1").select("a", "b")).withColumnRenamed("id", "node")
    known = nodes.select("node", "h1", "h2", "n", "least").join(degree, "node", "left").join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
    ids = known.groupBy("root").agg(F.min("least").alias("component_id"))
    known = known.join(ids, "root").select("h1", "h2", (F.coalesce("more", F.lit(0)) + F.col("n") - 1).alias("n_links"), "component_id")
    out = rows.join(known, ["h1", "h2"], "left")
    component = F.when(F.col("valid"), F.col("component_id")).otherwise(F.col("vec_id"))
    return out.select("vec_id", F.when(F.col("valid"), F.col("n_links")).otherwise(0).cast("long").alias("n_links"), component.alias("component_id"), F.coalesce(F.col("vec_id") == component, F.lit(False)).alias("kept"))


def op3_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "embeddings").select("vec_id", "embedding"))
