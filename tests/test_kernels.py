"""Kernels against definitions: contours at every level, all-pairs cuts, planted shapes, parameters."""

import dataclasses

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from spurline.operators import kernels as K
from spurline.params import BranchParams

clouds = st.lists(st.tuples(st.integers(0, 9), st.integers(0, 9)), min_size=2, max_size=40).map(lambda p: np.array(p, float))


def parts(n, edges):
    root = list(range(n))

    def find(a):
        while root[a] != a:
            a = root[a]
        return a

    for u, v in edges:
        root[max(find(u), find(v))] = min(find(u), find(v))
    return [find(i) for i in range(n)]


@given(clouds)
@settings(max_examples=60, deadline=None)
def test_tree_cuts_are_components(x):
    d = K.distances(x)
    t = K.spanning_tree(d)
    for r in np.unique(d):
        assert parts(len(x), [(int(u), int(v)) for u, v, w in t if w <= r]) == parts(len(x), zip(*np.nonzero(d <= r)))


@given(clouds, st.integers(2, 6), st.randoms())
@settings(max_examples=60, deadline=None)
def test_hierarchy_nodes_are_the_large_contour_components(x, least, rng):
    n, d = len(x), K.distances(x)
    u, v = np.nonzero(np.triu(d <= 2, 1))
    e = np.hypot(*(x - x.mean(0)).T)
    level = np.minimum(e[u], e[v])
    h = K.hierarchy(n, u, v, level, least)
    order = list(range(len(u)))
    rng.shuffle(order)
    g = K.hierarchy(n, u[order], v[order], level[order], least)
    assert (np.sort(h.exit_level) == np.sort(g.exit_level)).all() and sorted(h.size) == sorted(g.size) and sorted(h.birth) == sorted(g.birth)
    for at in np.unique(level):
        comp = parts(n, [(a, b) for a, b, w in zip(u, v, level) if w >= at])
        big = sum(comp.count(c) >= least for c in set(comp))
        alive = sum((b < at or p < 0) and t >= at for b, t, p in zip(h.birth, h.top(), h.parent))
        assert alive == big
    assert all(s >= least for s in h.size)


@given(clouds, st.integers(1, 5))
@settings(max_examples=60, deadline=None)
def test_graphs(x, k):
    if len(x) <= k:
        return
    m = K.density(x, BranchParams(min_samples=k, min_cluster_size=2, allow_single_cluster=True))
    members = np.arange(len(x))
    sets = {kind: set(zip(*K.graph(m, members, kind, False))) for kind in ("core", "full", "mutual")}
    lists = {(min(a, b), max(a, b)) for a in members for b in members if a != b and m.d[a, b] <= m.core[a]}
    assert sets["core"] == lists and sets["mutual"] <= sets["core"] <= sets["full"]
    assert len(set(parts(len(x), sets["full"]))) == 1
    assert max(m.reach[a, b] for a, b in sets["full"]) == m.tree[:, 2].max()


def star(n_r, arms=3, b=10.0, seed=0):
    rng = np.random.default_rng(seed)
    r = (1 + b) ** (np.arange(100) / 99) - 1
    a = np.repeat(np.arange(arms) * 2 * np.pi / arms, 100)
    return np.stack([np.tile(r, arms) * np.cos(a), np.tile(r, arms) * np.sin(a)], 1) + rng.normal(0, 1e-9 + n_r * b * 0.7 / 4, (100 * arms, 2)), np.repeat(np.arange(arms), 100)


P = BranchParams(min_samples=5, min_cluster_size=25, min_branch_size=12, allow_single_cluster=True, branch_selection="leaf")


@pytest.mark.parametrize("change", [{}, {"graph": "full"}, {"graph": "mutual"}, {"central_labels": "geodesic"}, {"combine": "product"}, {"eccentricity": "geodesic"}, {"eccentricity": "distance_sum"}, {"smooth": 1}, {"metric": "manhattan"}, {"branch_selection": "eom"}])
def test_star_arms(change):
    x, arm = star(0.05)
    p = dataclasses.replace(P, **change)
    m = K.density(x, p)
    got = K.combine(m, K.branches(x, m, p), p)
    assert (m.label == 0).all() and len(set(got["label"][~got["is_center"]])) == 3
    outer = np.arange(300) % 100 > 80
    assert all(len(set(got["label"][outer & (arm == a)])) == 1 for a in range(3))
    assert (got["strength"] >= 0).all() and (got["strength"] <= 1 + 1e-12).all()


def test_two_sides_collapse():
    x = np.stack([np.linspace(0, 10, 200), np.zeros(200)], 1)
    for sides, n in ((False, 1), (True, 2)):
        p = dataclasses.replace(P, label_sides=sides)
        m = K.density(x, p)
        got = K.combine(m, K.branches(x, m, p), p)
        assert len(set(got["label"][~got["is_center"]])) == n


def test_persistence_removes_weak_leaves():
    rng = np.random.default_rng(1)
    r, a = np.sqrt(rng.random(300)), rng.random(300) * 2 * np.pi
    x = np.stack([r * np.cos(a), r * np.sin(a)], 1)
    m = K.density(x, P)
    weak = dataclasses.replace(P, branch_persistence=0.5)
    assert not K.branches(x, m, weak)[0].split
    y, _ = star(0.05)
    my = K.density(y, P)
    assert K.branches(y, my, dataclasses.replace(P, branch_persistence=3.0))[0].split


def test_memberships_sum_to_one():
    x, _ = star(0.1)
    m = K.density(x, P)
    b = K.branches(x, m, P)[0]
    for t in (1e-3, 1.0, 1e6):
        soft = K.softmax_membership(b.d_geo, t)
        assert np.allclose(soft.sum(0), 1)
    assert np.allclose(soft[:, (b.d_geo > 0).all(0)], 1 / len(soft), atol=1e-3)
    near = K.softmax_membership(b.d_geo, 1e-4)
    assert (near.argmax(0) == b.d_geo.argmin(0)).mean() > 0.99


@pytest.mark.parametrize("x", [np.zeros((1, 2)), np.zeros((4, 2)), np.zeros((60, 2)), np.arange(40.0)[:, None]])
def test_odd_clouds(x):
    m = K.density(x, P)
    got = K.combine(m, K.branches(x, m, P), P)
    assert len(got["label"]) == len(x) and np.isfinite(got["strength"]).all()
    if len(x) <= 5:
        assert (got["label"] == -1).all()


def test_unknown_options_are_refused():
    with pytest.raises(ValueError):
        BranchParams(graph="other")


def test_forest_by_joins_equals_prim(spark):
    from spurline.operators.forest import spanning_forest

    rng = np.random.default_rng(3)
    d = K.distances(np.round(rng.normal(size=(40, 2)), 1))
    rows = [("a", i, j, float(d[i, j])) for i in range(40) for j in range(i + 1, 40)] + [("b", 0, 1, 2.0)]
    got = spanning_forest(spark.createDataFrame(rows, "grp string, u long, v long, w double")).collect()
    assert len(got) == 40 and np.allclose(sorted(r.w for r in got if r.grp == "a"), sorted(K.spanning_tree(d)[:, 2]))


def test_streams_equal_batches(spark, tmp_path):
    from spurline.runtime import table
    from spurline.streaming.windows import event_windows

    sf = "/root/testdata/sf0.001"
    batch = table(spark, sf, "events")
    batch.repartition(3).write.parquet(f"{tmp_path}/in")
    q = event_windows(spark.readStream.schema(batch.schema).option("maxFilesPerTrigger", 5).parquet(f"{tmp_path}/in"), late="3650 days").writeStream.outputMode("complete").format("memory").queryName("w").trigger(availableNow=True).start()
    q.awaitTermination(120)
    key = lambda df: sorted((str(r.start), r.event_type, r.n, round(r.total, 6)) for r in df.collect())
    assert key(spark.table("w")) == key(event_windows(batch))


@given(clouds, st.integers(2, 6))
@settings(max_examples=60, deadline=None)
def test_thinning_changes_no_hierarchy(x, least):
    n, d = len(x), K.distances(x)
    u, v = np.nonzero(np.triu(d <= 4, 1))
    e = np.hypot(*(x - x.mean(0)).T)
    level = np.minimum(e[u], e[v])
    a, b, cut = K.thinned(n, u, v, level)
    whole, thin = K.hierarchy(n, u, v, level, least), K.hierarchy(n, a, b, cut, least)
    assert len(a) < n and (whole.exit_level == thin.exit_level).all()
    assert sorted(zip(whole.size, whole.birth)) == sorted(zip(thin.size, thin.birth))
