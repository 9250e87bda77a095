"""Nearest vectors in tiles against whole rows."""

import numpy as np
import pandas as pd
import pytest

from balcut.sources import derive


@pytest.mark.parametrize(("n", "copies"), [(5, 1), (300, 1), (900, 30), (6000, 60)])
def test_tiles_give_the_nearest(n, copies):
    r = np.random.default_rng(n)
    m = np.tile(r.normal(size=(n // copies, 8)), (copies, 1))
    m /= np.linalg.norm(m, axis=1, keepdims=True)
    ids = np.sort(r.choice(10 * n, n, replace=False))
    q = r.choice(n, min(n, 100), replace=False)
    want = set()
    for v, row in zip(ids[q], np.round(m[q] @ m.T, derive.DIGITS), strict=True):
        row[ids == v] = -2
        want |= {(int(v), int(ids[i])) for i in np.lexsort((ids, -row))[: derive.NEAREST] if row[i] > -2}
    a, b, _ = derive._nearest(ids[q], m[q], ids, m, derive.NEAREST)
    assert len(a) == len(want) and set(zip(a.tolist(), b.tolist(), strict=True)) == want


def test_memory_of_many_vectors(spark, tmp_path, monkeypatch):
    """a batch of 10,000 queries met all vectors of a block in one array of doubles."""
    r = np.random.default_rng(2)
    pd.DataFrame({"vec_id": np.arange(6000), "embedding": list(r.normal(size=(6000, 4)).astype("float32")), "label": 0}).to_parquet(tmp_path / "embeddings.parquet")
    inner = derive._nearest
    monkeypatch.setattr(derive, "VECTORS_AT_ONCE", 2500)  # three blocks

    def watched(q_ids, q, ids, m, nearest):
        assert len(q_ids) <= derive.QUERIES_AT_ONCE
        return inner(q_ids, q, ids, m, nearest)

    monkeypatch.setattr(derive, "_nearest", watched)
    g = derive.embedding_knn(spark, str(tmp_path))
    got = {(x["u"], x["v"]) for x in g.edges.collect()}
    m = np.stack(pd.read_parquet(tmp_path / "embeddings.parquet").embedding).astype(float)
    m /= np.linalg.norm(m, axis=1, keepdims=True)
    sim = np.round(m @ m.T, derive.DIGITS)
    np.fill_diagonal(sim, -2)
    want = {(min(i, j), max(i, j)) for i, row in enumerate(sim) for j in np.lexsort((np.arange(6000), -row))[: derive.NEAREST].tolist()}
    assert got == want
