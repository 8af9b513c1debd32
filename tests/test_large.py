"""What goes by joins and bounded tasks against the kernels and brute force; sizes are set small, so that blocks, halves and rounds are many."""

import dataclasses

import numpy as np
import pytest

from spurline.operators import blocks as B
from spurline.operators import condense as C
from spurline.operators import kernels as K
from spurline.operators import reach as R
from spurline.operators.components import components
from spurline.operators.forest import spanning_forest
from spurline.params import BranchParams
from spurline.plans import clustering, large
from spurline.runtime import table
from spurline.sources import workloads as W


def frame(spark, groups):
    return spark.createDataFrame([(g, i, list(map(float, v))) for g, x in groups.items() for i, v in enumerate(x)], "grp string, id long, x array<double>")


def clouds():
    """Two dense far-off clusters, a spread, far outliers and many equal points; a grid of ties; too few points."""
    rng = np.random.default_rng(0)
    mixed = np.concatenate([rng.normal(size=(200, 2)), rng.normal(size=(120, 2)) * 0.01 + 50, rng.normal(size=(90, 2)) * 0.01 + 50.3, rng.normal(size=(5, 2)) * 100, np.repeat([[1.0, 2.0]], 80, 0)])
    return {"mixed": mixed, "ties": rng.integers(0, 7, size=(150, 2)).astype(float), "few": np.array([[float(i), 1.0] for i in range(4)])}


@pytest.mark.parametrize("metric", ["euclidean", "angular", "chebyshev"])
def test_neighbours(spark, metric):
    groups = clouds()
    if metric == "angular":  # parallel vectors are equal but for rounding, which engines do in their own ways
        groups = {"mixed": groups["mixed"][:415], "few": groups["few"]}
    got = {(r.grp, r.id, r.nbr, r["rank"]): r.d for r in B.knn(frame(spark, groups), 5, metric, size=48).collect()}
    want = {}
    for g, x in groups.items():
        y = x / np.linalg.norm(x, axis=1)[:, None] if metric == "angular" else x
        d = B.lengths(y, y, metric)
        np.fill_diagonal(d, np.inf)
        for i in range(len(x)):
            most = np.sort(d[i])[min(4, len(x) - 2)]
            want |= {(g, i, int(j), int(1 + (d[i] < d[i, j]).sum())): d[i, j] for j in np.flatnonzero(d[i] <= most)}
    assert got.keys() == want.keys()
    assert metric == "angular" or got == want
    assert all(got[k] == pytest.approx(want[k], abs=1e-12) for k in got)


def test_spanning_trees(spark):
    groups = clouds()
    tree = R.reach_tree(frame(spark, groups), 5, size=48)[0].collect()
    for g, x in groups.items():
        mine = [r for r in tree if r.grp == g]
        if g == "few":
            assert not mine
            continue
        d = K.distances(x)
        core = K.core_distances(d, 5)
        w = np.maximum(d, np.maximum(core[:, None], core[None, :]))
        assert sorted(r.w for r in mine) == sorted(K.spanning_tree(w)[:, 2].tolist())
        assert all(w[r.u, r.v] == r.w for r in mine)
        assert len({K_find(mine, i) for i in range(len(x))}) == 1


def K_find(edges, i):
    """The least point that edges lead to."""
    seen, todo = {i}, [i]
    near = K_find.cache.setdefault(id(edges), {})
    if not near:
        for r in edges:
            near.setdefault(r.u, []).append(r.v)
            near.setdefault(r.v, []).append(r.u)
    while todo:
        for j in near.get(todo.pop(), []):
            if j not in seen:
                seen.add(j)
                todo.append(j)
    return min(seen)


K_find.cache = {}


@pytest.mark.parametrize(("task", "least", "how", "root", "persistence"), [(12, 3, "eom", False, 0.0), (40, 5, "leaf", True, 0.2), (100_000, 5, "eom", True, 0.0)])
def test_condensing(spark, task, least, how, root, persistence):
    rng, cases, rows = np.random.default_rng(1), {}, []
    for g in range(12):
        n, ties = int(rng.integers(2, 120)), [0, 5, 20, 2][g % 4]
        u, v = np.arange(1, n), np.array([rng.integers(0, i) for i in range(1, n)], int)
        level = rng.integers(1, ties, size=n - 1).astype(float) if ties else rng.random(n - 1) + 0.1
        keep = rng.random(n - 1) > (0.05 if g % 3 == 0 else 0)
        cases[f"g{g}"] = (n, u[keep], v[keep], level[keep])
        rows += [(f"g{g}", int(min(a, b)), int(max(a, b)), float(x)) for a, b, x in zip(u[keep], v[keep], level[keep], strict=True)]
    vertices = spark.createDataFrame([(g, i) for g, c in cases.items() for i in range(c[0])], "grp string, id long")
    points, nodes = C.condense(spark.createDataFrame(rows, "grp string, u long, v long, level double"), least, task)
    got = {(r.grp, r.id): (r.label, r.strength) for r in C.flat_labels(vertices, points, C.pick(points, nodes, how, root, 0.0, persistence)).collect()}
    for g, (n, u, v, level) in cases.items():
        h = K.prune(K.hierarchy(n, u, v, level, least), persistence)
        chosen = K.select(h, how, root)
        label, strength = K.labels(h, chosen)
        if len(chosen) == 1 and h.parent[chosen[0]] < 0:
            label = np.zeros(n, int)
        assert [got[g, i] for i in range(n)] == [(int(a), pytest.approx(float(b), abs=1e-12)) for a, b in zip(label, strength, strict=True)]


BASE = BranchParams(min_samples=5, min_cluster_size=25, min_branch_size=12, allow_single_cluster=True, branch_selection="leaf")
SETTINGS = [BASE, dataclasses.replace(BASE, central_labels="geodesic", combine="product"), dataclasses.replace(BASE, eccentricity="geodesic", push=True), BranchParams(min_samples=5, min_cluster_size=8, cluster_selection="leaf", min_branch_size=4, branch_persistence=0.3, label_sides=True, smooth=1)]


@pytest.mark.parametrize("p", SETTINGS, ids=["core", "geodesic", "hops", "leaves"])
def test_branches_equal_the_kernel(spark, p):
    x = W.star_points(table(spark, "/root/testdata/sf0.001", "orders")).where("sample < 2").select("grp", "id", "x")
    x = x.unionByName(spark.createDataFrame([("0", 9001, [float("nan"), 1.0]), ("1", 9002, None), ("1", None, [1.0, 1.0])], "grp string, id long, x array<double>"))
    small = {(r.grp, r.id): r for r in clustering.branch_clusters(x, p).collect()}
    got = {(r.grp, r.id): r for r in clustering.branch_clusters(x, p, limit=0).collect()}
    assert len(small) == 600 and small.keys() == got.keys()
    for key, r in small.items():
        for a, b in zip(r, got[key], strict=True):
            assert a == (pytest.approx(b, abs=1e-9) if isinstance(b, float) else b), (key, r, got[key])


def test_memberships_and_trees_equal_the_kernel(spark):
    x = W.star_points(table(spark, "/root/testdata/sf0.001", "orders")).where("sample < 2").select("grp", "id", "x")
    pick = lambda df: {(r.grp, r.id, r.cluster, r.branch): (r.d_geo, r.p, r.weighted) for r in df.collect()}
    small, got = pick(clustering.memberships(x, BASE)), pick(clustering.memberships(x, BASE, limit=0))
    assert small.keys() == got.keys() and len(small) > 600
    assert all(got[k] == pytest.approx(v, abs=1e-9) for k, v in small.items())
    for which in ("cluster", "branch"):
        rows = lambda df: sorted((r.grp, r.cluster, round(r.birth, 9), round(r.top, 9), r.size, round(r.stability, 6), r.selected, r.x1 - r.x0 >= r.size) for r in df.collect())
        assert rows(clustering.condensed(x, BASE, which, limit=0)) == rows(clustering.condensed(x, BASE, which))


def test_signals_of_any_kind(spark):
    """A column as the signal: the geometric eccentricity given as one finds what the method finds; turned, its valleys."""
    x = W.star_points(table(spark, "/root/testdata/sf0.001", "orders"), n_r=0.0).where("sample = 0")
    own = large.density(x, BASE)
    members = own.labels.where("label >= 0").select("grp", "id", "label", "strength").withColumnRenamed("label", "cluster")
    value = large.signal(own, members, large.cluster_graph(own, members.drop("strength"), BASE), BASE).select("grp", "id", "value")
    want = {r.id: r.label for r in clustering.branch_clusters(x, BASE).collect()}
    assert {r.id: r.label for r in clustering.branches_by_signal(x, value, BASE).collect()} == want and len(set(want.values())) >= 3
    turned = clustering.branches_by_signal(x, value, dataclasses.replace(BASE, direction="min"))
    assert {r.label for r in turned.collect()} == {0}  # one valley, the centre


def test_many_edges_go_by_rounds(spark, monkeypatch):
    """Components and forests of more edges than a task takes are the same."""
    import importlib

    rng = np.random.default_rng(4)
    rows = [("g", int(min(a, b)), int(max(a, b)), float(w)) for a, b, w in zip(rng.integers(0, 80, 150), rng.integers(0, 80, 150), rng.random(150), strict=True) if a != b]
    df = spark.createDataFrame(rows, "grp string, u long, v long, w double")
    few = [sorted(map(tuple, f.collect())) for f in (components(df, keys=("grp",)), spanning_forest(df))]
    for name in ("components", "forest"):
        monkeypatch.setattr(importlib.import_module(f"spurline.operators.{name}"), "TASK_EDGES", 0)
    assert few == [sorted(map(tuple, f.collect())) for f in (components(df, keys=("grp",)), spanning_forest(df))]
