"""The tree of one group in a task against all pairs; boxes are set small."""

import numpy as np
import pytest

from spurline import queries
from spurline.operators import blocks as B
from spurline.operators import grown
from spurline.operators import kernels as K
from spurline.operators.components import least_labels


@pytest.mark.parametrize("metric", ["euclidean", "manhattan", "chebyshev", "angular"])
def test_group_trees(monkeypatch, metric):
    monkeypatch.setattr(grown, "LEAF", 12)
    rng = np.random.default_rng(0)
    mixed = np.concatenate([rng.normal(size=(200, 2)), rng.normal(size=(120, 2)) * 0.01 + 50, rng.normal(size=(5, 2)) * 100, np.repeat([[1.0, 2.0]], 80, 0)])
    cases = [mixed, rng.integers(1, 9, size=(300, 2)).astype(float), np.repeat(rng.random((40, 3)) + 1, 7, 0), np.repeat(rng.random((3, 2)) + 1, 3, 0), np.ones((30, 2)), rng.normal(size=(200, 6))]
    for x in cases:
        if metric == "angular":
            x = x / np.sqrt((x * x).sum(1))[:, None]
        ids = rng.permutation(len(x)) * 3
        u, v, w, core = grown.group_tree(ids, x, 5, metric)
        d = B.lengths(x, x, metric)
        c = K.core_distances(d, 5)
        reach = np.maximum(d, np.maximum(c[:, None], c[None, :]))
        place = np.empty(ids.max() + 1, int)
        place[ids] = np.arange(len(ids))
        a, b = place[u], place[v]
        assert (core == c).all() and (reach[a, b] == w).all() and not least_labels(len(x), a, b).any()
        assert sorted(w.tolist()) == sorted(K.spanning_tree(reach)[:, 2].tolist())


def test_larger_groups_go_by_rounds(spark, monkeypatch):
    monkeypatch.setattr(grown, "TREE_POINTS", 50)
    rng = np.random.default_rng(1)
    p = spark.createDataFrame([(g, i, rng.random(2).tolist()) for g, n in (("a", 40), ("b", 90), ("c", 3)) for i in range(n)], "grp string, id long, x array<double>")
    tree, core = grown.reach_edges(p, 4)
    assert {r.grp: r["count"] for r in tree.groupBy("grp").count().collect()} == {"a": 39, "b": 89}
    assert {r.grp: r["count"] for r in core.groupBy("grp").count().collect()} == {"a": 40, "b": 90}


def test_profiles_are_one_tasks_tree(spark, monkeypatch):
    """no neighbour lists, which hold every pair of equal customers, and no pairs of blocks are stored."""
    from spurline import queries_more
    from spurline.operators import reach

    seen = []
    for module in (queries_more, B, grown, reach):
        def stored(df, tag, f=module.materialise):
            seen.append(tag)
            return f(df, tag)

        monkeypatch.setattr(module, "materialise", stored)
    queries.QUERIES["profile_tree_total"](spark, "/root/testdata/sf0.001").collect()
    assert "grown" in seen and not {"neighbours", "pairs"} & set(seen)


@pytest.mark.parametrize("more", [{}, {"push": True, "label_sides": True, "branch_persistence": 0.1}, {"with_tree_edges": False, "metric": "manhattan", "direction": "min"}])
def test_branches_without_matrices(monkeypatch, more):
    """the same rows as with matrices, also of many equal points and of ties."""
    from spurline.params import BranchParams
    from spurline.plans import clustering as C

    monkeypatch.setattr(grown, "LEAF", 20)
    rng = np.random.default_rng(3)
    arms = np.concatenate([np.linspace(0.1, 9, 90)[:, None] * [np.cos(a), np.sin(a)] + rng.normal(size=(90, 2)) * 0.05 for a in (0, 2.1, 4.2)])
    for x in (arms, np.repeat(arms, 3, 0), np.concatenate([arms, arms + 40, rng.random((30, 2)) * 60]), rng.integers(0, 12, size=(300, 2)).astype(float), np.ones((40, 2)), arms[:4]):
        p = BranchParams(min_samples=5, min_cluster_size=25, min_branch_size=12, allow_single_cluster=True, branch_selection="leaf", **more)
        m = K.density(x, p)
        want, got = K.combine(m, K.branches(x, m, p), p), K.combine(*C.branch_parts(x, p), p)
        for c in want:
            assert np.allclose(want[c], got[c], atol=1e-12), c


def test_groups_of_three_sizes(spark):
    from spurline.params import BranchParams
    from spurline.plans import clustering as C
    from spurline.runtime import table
    from spurline.sources import workloads as W

    x = W.star_points(table(spark, "/root/testdata/sf0.001", "orders")).where("sample < 2").select("grp", "id", "x")
    p = BranchParams(min_samples=5, min_cluster_size=25, min_branch_size=12, allow_single_cluster=True, branch_selection="leaf")
    rows = lambda **how: sorted((r.grp, r.id, r.label, r.cluster, r.branch, round(r.strength, 9), r.is_center) for r in C.branch_clusters(x, p, **how).collect())
    want = rows()
    assert rows(limit=0) == want and rows(limit=0, arrays=0) == want
