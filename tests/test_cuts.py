"""Cuts at lengths without a tree, against the tree; tiles and pieces are set small."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from spurline import queries
from spurline.operators import cuts
from spurline.operators.components import components
from spurline.operators.reach import reach_tree


@pytest.mark.parametrize("dims", [1, 2, 3])
def test_cuts_equal_the_tree(spark, monkeypatch, dims):
    monkeypatch.setattr(cuts, "TILE_CELLS", 3), monkeypatch.setattr(cuts, "PAIRS", 40)
    rng = np.random.default_rng(dims)
    x = np.concatenate([rng.integers(-9, 9, size=(150, dims)), rng.integers(40, 44, size=(90, dims)), np.zeros((20, dims), int), [[900] * dims]]).astype(float)
    rows = [("a", i * 7, v.tolist()) for i, v in enumerate(x)] + [("b", i, [float(i)] * dims) for i in range(4)] + [("b", 9, [float("nan")] * dims)]
    p = spark.createDataFrame(rows, "grp string, id long, x array<double>")
    squares = [1, 2, 9]
    tree = reach_tree(p, 4)[0]
    got = {(r.grp, int(r.most), r.id): r.component for r in cuts.reach_cut(p, 4, squares).collect()}
    edges = {(r.grp, int(r.most)): r.edges for r in cuts.tree_edges_within(p, 4, squares).collect()}
    assert len(got) == 3 * (len(x) + 4)
    for s in squares:
        within = tree.where(F.rint(F.col("w") * F.col("w")) <= s)
        want = components(within.select("grp", "u", "v"), p.where("id is not null").select("grp", "id"), keys=("grp",)).collect()
        assert all(got[r.grp, s, r.id] == r.component for r in want if (r.grp, r.id) != ("b", 9))
        assert [edges[g, s] for g in "ab"] == [within.where(F.col("grp") == g).count() for g in "ab"]


@pytest.mark.parametrize("name", ["walk_tree_total", "walk_linkage_cut"])
def test_walks_go_without_neighbour_lists(spark, monkeypatch, name):
    """F16, F24: a few tables are stored, however many points; before, neighbours and a table or more for each step of each round."""
    from spurline import queries_more
    from spurline.operators import blocks, components, reach

    seen = []
    for module in (queries_more, blocks, components, cuts, reach):
        def stored(df, tag, f=module.materialise):
            seen.append(tag)
            return f(df, tag)

        monkeypatch.setattr(module, "materialise", stored)
    queries.QUERIES[name](spark, "/root/testdata/sf0.001").collect()
    assert "tiles" in seen and "neighbours" not in seen and len(seen) <= 6


def test_edges_within_are_of_a_whole_tree(spark, monkeypatch):
    """the edges that are counted are a tree's, with all that are longer; before, points less their components and no tree."""
    monkeypatch.setattr(cuts, "TILE_CELLS", 3)
    rng = np.random.default_rng(4)
    x = np.concatenate([rng.integers(-9, 9, size=(300, 2)), rng.integers(40, 44, size=(90, 2)), np.zeros((20, 2), int), [[900, 900], [900, 910]]]).astype(float)
    p = spark.createDataFrame([("a", i * 7, v.tolist()) for i, v in enumerate(x)] + [("b", i, [float(i), 0.0]) for i in range(4)], "grp string, id long, x array<double>")
    made = []

    def kept(*args, f=cuts.tile_tree):
        made.append(f(*args))
        return made[-1]

    monkeypatch.setattr(cuts, "tile_tree", kept)
    squares = [1, 4, 1_000_000]
    edges = {(r.grp, int(r.most)): r.edges for r in cuts.tree_edges_within(p, 4, squares[:2]).collect()}
    rows, want = made[0].collect(), reach_tree(p, 4)[0].collect()
    assert sorted(r.w for r in rows) == sorted(r.w for r in want) and len(rows) == len(x) - 1 == len({v for r in rows for v in (r.u, r.v)}) - 1
    assert [edges["a", s] for s in squares[:2]] == [sum(r.w * r.w <= s for r in rows) for s in squares[:2]] and edges["b", 1] == 0


@pytest.mark.parametrize("some", [4_096, 20])
def test_region_forests_hold_the_tree(monkeypatch, some):
    """Any points and lengths: the forests of overlapping regions together, finished, have the weights of the kernel's tree."""
    from spurline.operators import grown
    from spurline.operators import kernels as K
    from spurline.operators.components import least_labels
    from spurline.operators.forest import kept_edges
    from spurline.params import BranchParams

    monkeypatch.setattr(grown, "SOME", some)  # few: points far from all other components are left out at the end
    rng = np.random.default_rng(5)
    for n, k, most in ((6, 2, 1.0), (700, 4, 0.2), (900, 10, 0.05), (400, 5, 1e-9), (800, 3, 9.0)):
        x = np.round(rng.normal(size=(n, 2)), 2 if n % 3 else 9)
        sides = [(x[:, 0] >= a - most / 2) & (x[:, 0] <= b + most / 2) for a, b in ((-np.inf, 0), (0, np.inf))]
        parts, edges = [grown.region_forest(x, k, near, most) for near in sides], []
        for u, v, w, _ in parts:
            stays, name = grown.settled(n, u, v, w, sides[0] & sides[1])
            edges.append(np.stack([u, v, w, name[u], name[v], stays], 1))
            assert (name[u[stays]] == name[v[stays]]).all()
        edges = np.concatenate(edges)
        sure, rest = edges[edges[:, 5] == 1], edges[edges[:, 5] == 0]
        rest = rest[np.argsort(rest[:, 2], kind="stable")]
        rest = rest[kept_edges(n, rest[:, 3].astype(int), rest[:, 4].astype(int))]
        u, v, w = np.concatenate([sure, rest])[:, :3].T
        u, v = u.astype(int), v.astype(int)
        more = grown.joined_up(x, np.minimum(parts[0][3], parts[1][3]), k, least_labels(n, u, v))
        u, v, w = (np.concatenate(c) for c in zip((u, v, w), more, strict=True))
        want = K.metric_parts(x, BranchParams(min_samples=k))[3][:, 2]
        assert np.array_equal(np.sort(w), np.sort(want)) and len(kept_edges(n, u, v)) == n - 1
