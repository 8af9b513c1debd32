"""Pairs of many axes are told apart by products of matrices and measured exactly."""

import numpy as np
import pytest

from spurline.operators import blocks as B
from spurline.operators import reach


@pytest.mark.parametrize("metric", ["euclidean", "angular"])
def test_least_edges_by_products(monkeypatch, metric):
    """before, all pairs were measured axis by axis."""
    rng = np.random.default_rng(6)
    x = np.concatenate([rng.normal(size=(60, 12)), np.repeat(rng.normal(size=(10, 12)), 4, axis=0)]) + 3
    x = x / np.sqrt((x * x).sum(1))[:, None] if metric == "angular" else x * 1000
    core, comp = np.sort(B.lengths(x, x, metric), axis=1)[:, 3], rng.integers(0, 3, len(x))
    i, b = np.arange(0, len(x), 2), rng.permutation(len(x))
    got = reach._least(x, core, comp, i, b, metric)
    monkeypatch.setattr(B, "by_product", lambda *a: False)
    want = reach._least(x, core, comp, i, b, metric)
    assert np.array_equal(got[1], want[1]) and np.array_equal(got[0], want[0])
    assert np.isinf(reach._least(x, core, comp * 0, i, b, metric)[1]).all()


@pytest.mark.parametrize("metric", ["euclidean", "angular"])
def test_neighbours_by_products(spark, metric):
    rng = np.random.default_rng(7)
    x = np.concatenate([rng.normal(size=(150, 12)), np.repeat(rng.normal(size=(10, 12)), 5, axis=0)])
    p = spark.createDataFrame([("a", i, v.tolist()) for i, v in enumerate(x)], "grp string, id long, x array<double>")
    rows = lambda: sorted((r.id, r.nbr, r.d, r["rank"]) for r in B.knn(p, 4, metric, size=40).collect())
    got = rows()
    every = B.lengths(*[(x / np.sqrt((x * x).sum(1))[:, None] if metric == "angular" else x)] * 2, metric)
    np.fill_diagonal(every, np.inf)
    most = np.sort(every, axis=1)[:, 3]
    assert len(got) == int((every <= most[:, None] * (1 + 1e-12)).sum())
    assert all(abs(every[a, b] - d) < 1e-12 for a, b, d, _ in got)
