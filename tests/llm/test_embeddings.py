"""Links and components against all cosines, recall, and odd rows."""

import numpy as np
import pytest

from bitparse.llm import embeddings


def brute(ids, rows, cosine=0.95):
    u = rows.astype(np.float64)
    u = u / np.linalg.norm(u, axis=1, keepdims=True)
    links = (u @ u.T >= cosine) & ~np.eye(len(u), dtype=bool)
    component = np.array(ids)
    while True:
        new = np.minimum(component, np.where(links, component[None, :], np.iinfo(np.int64).max).min(axis=1))
        if (new == component).all():
            return links.sum(axis=1), component
        component = new


@pytest.mark.parametrize("name", ["sf0.001", "sf0.01"])
def test_tables(spark, name):
    rows = spark.read.parquet(f"/root/testdata/{name}/embeddings.parquet").select("vec_id", "embedding").collect()
    n, component = brute([r.vec_id for r in rows], np.array([r.embedding for r in rows], np.float32))
    got = {r.vec_id: r for r in embeddings.op3_embeddings(spark, f"/root/testdata/{name}").collect()}
    assert len(got) == len(rows)
    for r, k, c in zip(rows, n, component, strict=True):
        assert (got[r.vec_id].n_links, got[r.vec_id].component_id, got[r.vec_id].kept) == (k, c, c == r.vec_id)


@pytest.mark.parametrize("exact", [True, False])
@pytest.mark.parametrize("coarse", [256, 4])
def test_recall_and_blocks(spark, monkeypatch, exact, coarse):
    for name, value in (("BLOCK", 50), ("PER_LIST", 40), ("QUERIES", 16), ("COARSE", coarse)):
        monkeypatch.setattr(embeddings, name, value)
    rng = np.random.default_rng(2)
    base = rng.normal(size=(60, 24))
    rows = np.repeat(base, 8, axis=0) + rng.normal(size=(480, 24)) * rng.choice([0, 0.1, 0.2, 0.3], size=(480, 1))
    rows = np.concatenate([rows, base[:1] + 0.1 * rng.normal(size=(150, 24))])  # a dense group over several blocks
    df = spark.createDataFrame([(k, r.tolist()) for k, r in enumerate(rows)], "vec_id long, embedding array<double>")
    n, component = brute(list(range(len(rows))), rows)
    got = {r.vec_id: r for r in embeddings.near_duplicates(df, exact=exact).collect()}
    found = np.array([got[k].n_links for k in range(len(rows))])
    assert (found <= n).all() and found.sum() >= (n.sum() if exact else 0.95 * n.sum())
    if exact:
        assert [got[k].component_id for k in range(len(rows))] == component.tolist()


def test_lists_grow_and_few_are_probed():
    """Correlated vectors of 64 numbers with planted neighbours: recall by either side, and the share of lists probed."""
    rng = np.random.default_rng(5)
    base = rng.normal(size=(6000, 8)) @ rng.normal(size=(8, 64)) + 0.7 * rng.normal(size=(6000, 64))
    rows = np.concatenate([base, base[:3000] + 0.18 * np.linalg.norm(base[:3000], axis=1, keepdims=True) * rng.normal(size=(3000, 64)) / 8])
    u = embeddings.unit(rows)
    index = embeddings.Index.fit(rows, 1_000_000)
    lists, _, _, probes = index.assign(u)
    assert len(index.coarse) * len(index.fine) >= 1000 and (np.array([own in p for own, p in zip(lists, probes, strict=True)])).all()
    pairs = [(k, 6000 + k) for k in range(3000) if u[k] @ u[6000 + k] >= embeddings.COSINE]
    found = sum(lists[b] in probes[a] or lists[a] in probes[b] for a, b in pairs)
    assert len(pairs) > 2000 and found >= 0.95 * len(pairs)
    assert np.mean([len(p) for p in probes]) <= 0.1 * len(index.coarse) * len(index.fine)


def test_odd_rows(spark):
    one = [1.0, 2.0, 3.0]
    rows = [(1, None), (2, []), (3, [0.0, -0.0, 0.0]), (4, [1.0, None, 2.0]), (5, [float("nan"), 1.0, 1.0]), (6, [float("inf"), 1.0, 1.0]), (7, one), (8, one), (9, [2e200, 4e200, 6e200]), (10, [1.0, 2.0]), (11, [1e-300, 2e-300, 3e-300]), (8, one), (None, [9.0, -9.0, 1.0])]
    df = spark.createDataFrame([(*r, 5) for r in rows], "vec_id long, embedding array<double>, n int")
    got = sorted(((r.vec_id or 0, r.n_links, r.component_id, r.kept) for r in embeddings.near_duplicates(df).collect()), key=str)
    linked = [g for g in got if g[0] in (7, 8, 9, 11)]
    assert len(got) == len(rows) and len(linked) == 5 and all(g[1:3] == (4, 7) for g in linked)
    assert all(g[1] == 0 and g[2] == g[0] and g[3] for g in got if g[0] in range(1, 7) or g[0] == 10)
    assert embeddings.near_duplicates(df.limit(0)).count() == 0
    assert embeddings.near_duplicates(df.filter("vec_id < 7")).count() == 6
