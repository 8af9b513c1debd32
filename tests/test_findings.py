"""What larger tables showed: one test for each finding that was mended."""

import re

import numpy as np
import pytest

from spurline import queries, queries_graphs
from spurline.operators import baselines, components, neighbors, summaries

SMALL = "/root/testdata/sf0.001"


@pytest.fixture
def plans(spark, monkeypatch):
    """Physical plans of all that is stored, where the planner would broadcast whatever it can."""
    seen = []
    for module in (queries, queries_graphs, baselines, components, neighbors, summaries):
        def stored(df, tag, f=module.materialise):
            seen.append(df._jdf.queryExecution().executedPlan().toString())
            return f(df, tag)

        monkeypatch.setattr(module, "materialise", stored)
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "1g")
    yield seen
    spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


@pytest.mark.parametrize("name", [
    "anti_isolated_points", "semi_connected_points", "star_full_graph", "edge_set_ops", "star_component_grid", "star_level_sets", "star_nerve", "star_slice", "star_largest_component",
])
def test_points_are_not_broadcast(spark, plans, monkeypatch, name):
    monkeypatch.setattr(neighbors, "PAIR_POINTS", 0)  # as if all groups were large
    plans.append(queries.QUERIES[name](spark, SMALL)._jdf.queryExecution().executedPlan().toString())
    keys = [k for p in plans for k in re.findall(r"BroadcastHashJoin \[(.*?)\]", p)]
    assert not [k for k in keys if re.search(r"(^|, )(cell|id|u|v)#", k)]


def _tables(seen, kind):
    """How many tables of a kind were stored."""
    return sum(tag == kind for tag in seen)


@pytest.fixture
def tags(monkeypatch):
    """The tags of all that is stored."""
    from spurline.operators import blocks, measures

    seen = []
    for module in (queries, queries_graphs, baselines, components, neighbors, summaries, measures, blocks):
        def stored(df, tag, f=module.materialise):
            seen.append(tag)
            return f(df, tag)

        monkeypatch.setattr(module, "materialise", stored)
    return seen


def graph(spark):
    """Two chains with short cuts, a point apart, as (grp, u, v, w)."""
    rng = np.random.default_rng(3)
    rows = [(g, i, i + 1, float(rng.integers(1, 9))) for g in "ab" for i in range(40)] + [(g, i, i + 7, float(rng.integers(1, 40))) for g in "ab" for i in range(0, 30, 5)]
    return spark.createDataFrame([*rows, ("a", 100, 101, 1.0)], "grp string, u long, v long, w double")


def test_small_groups_paths_take_no_rounds(spark, tags, monkeypatch):
    from spurline.operators import measures

    roots = spark.createDataFrame([("a", 0), ("a", 33), ("b", 5), ("c", 1)], "grp string, root long")
    run = lambda: ({tuple(r) for r in measures.path_lengths(graph(spark), roots).collect()}, {tuple(r) for r in neighbors.hop_distances(graph(spark), roots).collect()})
    small = run()
    assert not _tables(tags, "paths") and not _tables(tags, "hops")
    monkeypatch.setattr(neighbors, "PATH_EDGES", 0)
    assert run() == small and _tables(tags, "paths") and len(small[0]) == len(small[1]) == 41 * 3 + 1


def test_pairs_of_small_groups_are_not_joined(spark, monkeypatch):
    rng = np.random.default_rng(4)
    p = spark.createDataFrame([(g, i, rng.normal(size=3).tolist()) for g in "ab" for i in range(30)], "grp string, id long, x array<double>")
    core = p.select("grp", "id", (queries.F.col("id") / 10.0).alias("core")).where("id <> 4")
    found = neighbors.reach_pairs(p, core)
    assert "CartesianProduct" not in (plan := found._jdf.queryExecution().executedPlan().toString()) and not re.search(r"Join \[grp#\d+\]", plan)
    small = {tuple(r) for r in found.collect()}
    monkeypatch.setattr(neighbors, "PAIR_POINTS", 0)
    assert {tuple(r) for r in neighbors.reach_pairs(p, core).collect()} == small and len(small) == 2 * 29 * 28 // 2


def test_components_and_forests_of_small_groups_take_no_rounds(spark, tags, monkeypatch):
    from spurline.operators import forest

    e = graph(spark).where("grp in ('a', 'b')").unionByName(graph(spark).where("grp = 'a' and u > 10").withColumn("grp", queries.F.lit("c")))
    run = lambda: ({tuple(r) for r in components.components(e.select("grp", "u", "v"), keys=("grp",)).collect()}, {tuple(r) for r in forest.spanning_forest(e).collect()}, {tuple(r) for r in forest.spanning_forest(e, True).collect()})
    at_once = run()
    for module in (components, forest):
        monkeypatch.setattr(module, "TASK_EDGES", 60)
    del tags[:]
    assert run() == at_once and not _tables(tags, "star")
    for module in (components, forest):
        monkeypatch.setattr(module, "TASK_EDGES", 40)  # two groups are large, one is small
    assert run() == at_once and _tables(tags, "star")


def test_near_pairs_and_sums_of_small_groups_are_not_joined(spark, monkeypatch):
    rng = np.random.default_rng(5)
    p = spark.createDataFrame([(g, i, rng.integers(0, 9, 2).astype(float).tolist()) for g in "ab" for i in range(40)], "grp string, id long, x array<double>")
    reach = spark.createDataFrame([("a", 2.0), ("b", 3.0)], "grp string, reach double")
    run = lambda: ({tuple(r) for r in summaries.radius_pairs(p, reach).collect()}, {(r.grp, r.id): round(r.value, 9) for r in baselines.distance_sums(p).collect()})
    assert "Join [grp" not in baselines.distance_sums(p)._jdf.queryExecution().executedPlan().toString()
    small = run()
    monkeypatch.setattr(neighbors, "PAIR_POINTS", 0)
    assert run() == small and len(small[1]) == 80


def test_shapes_of_the_grid_are_not_stored(spark, tags, monkeypatch):
    """one task holds a sample's shapes; its centroids are those of the joins."""
    from spurline import queries_more
    from spurline.plans import clustering, packs
    from spurline.runtime import table
    from spurline.sources import workloads

    def stored(df, tag, f=queries_more.materialise):
        tags.append(tag)
        return f(df, tag)

    monkeypatch.setattr(queries_more, "materialise", stored)
    queries.QUERIES["spread95_heatmap"](spark, SMALL).collect()
    assert set(tags) == {"centroids"}
    F, orders = queries.F, table(spark, SMALL, "orders").where("o_orderkey < 640")
    shapes = [queries._GRID[i] for i in (0, 37, 99)]
    p = workloads.star_grid(orders, shapes).withColumn("x", F.array(F.col("px").cast("double"), F.col("py").cast("double")))
    first = p.where("floor(id / 3) % 100 = 50").select("grp", F.col("arm").alias("label"), F.col("x").alias("c"))
    rows = baselines.kmeans(p, first, 2).join(p.select("grp", "id", "sample", "arm", "px", "py", "j_l", "j_n"), ["grp", "id"]).withColumn("strength", F.lit(1.0))
    found = packs.kmeans_centroids(workloads.star_packs(orders, shapes), 2).withColumn("j_l", F.get(F.array(*[F.lit(s[0]) for s in shapes]), "shape")).withColumn("j_n", F.get(F.array(*[F.lit(s[1]) for s in shapes]), "shape"))
    plain = lambda df: sorted((r.j_l, r.j_n, r.arm, round(r.spread, 3)) for r in df.collect())
    want = plain(clustering.centroid_spread(rows, ("j_l", "j_n"), "sample"))
    assert plain(clustering.arm_spread(found, ("j_l", "j_n"))) == want and len(want) == 18


def _grid_by_joins(spark):
    """Two samples and a part of one, in three shapes: as packs, and as points with their names."""
    from spurline.runtime import table
    from spurline.sources import workloads

    orders, shapes = table(spark, SMALL, "orders").where("o_orderkey < 640"), [queries._GRID[i] for i in (0, 37, 99)]
    names = queries.F.array(*[queries.F.lit(f"{a}/{b}") for a, b, _, _ in shapes])
    return workloads.star_packs(orders, shapes), workloads.star_grid(orders, shapes), lambda df: {r.k: r.v for r in df.select(queries.F.concat_ws("/", queries.F.get(names, "shape"), "sample", "setting").alias("k"), queries.F.round("ari", 9).alias("v")).collect()}


def _stored_only(spark, tags, monkeypatch, name, kind):
    """The query stores measures of clouds, and none of their points."""
    from spurline import queries_more
    from spurline.plans import packs
    from spurline.sources import workloads

    def stored(df, tag, f=queries_more.materialise):
        tags.append(tag)
        return f(df, tag)

    monkeypatch.setattr(queries_more, "materialise", stored)
    few = workloads.star_packs
    monkeypatch.setattr(workloads, "star_packs", lambda orders, shapes: few(orders.where("o_orderkey < 300"), shapes))
    monkeypatch.setattr(packs, "TOGETHER", 7)
    del tags[:]
    rows = queries.QUERIES[name](spark, SMALL).collect()
    assert set(tags) == {kind}
    return rows


def test_heatmap_scores_clouds_in_their_tasks(spark, tags, monkeypatch):
    """F21"""
    from spurline.plans import clustering, packs

    F, (packed, p, plain) = queries.F, _grid_by_joins(spark)
    first = p.where("floor(id / 3) % 100 = 50").select("grp", F.col("arm").alias("label"), F.col("x").alias("c"))
    runs = [clustering.branch_clusters(p, queries.BEST).select("grp", "id", "label"), clustering.density_clusters(p, queries.LEAF_DENSITY).select("grp", "id", "label"), baselines.kmeans(p, first, 6)]
    want = {f"{r.grp}/{i}": round(r.ari, 9) for i, found in enumerate(runs) for r in clustering.adjusted_rand(found.join(p.select("grp", "id", "arm"), ["grp", "id"]), "arm", "label", ("grp",)).collect()}
    assert plain(packs.method_scores(packed, queries.BEST, queries.LEAF_DENSITY, 6)) == want and len(want) == 3 * (3 + 3 + 2)
    assert len(_stored_only(spark, tags, monkeypatch, "star_heatmap", "scores")) == 1 + 3 + 30 + 300


def _settings_scored(spark, settings, branches):
    from spurline.plans import clustering, packs

    F, (packed, p, plain) = queries.F, _grid_by_joins(spark)
    found = clustering.branch_grid(p, settings) if branches else clustering.density_grid(p, settings)
    want = clustering.adjusted_rand(found.select("grp", "id", "setting", "label").join(p.select("grp", "id", "arm"), ["grp", "id"]), "arm", "label", ("grp", "setting"))
    assert plain(packs.grid_scores(packed, settings, branches)) == {f"{r.grp}/{r.setting}": round(r.ari, 9) for r in want.collect()}


def test_density_grid_scores_clouds_in_their_tasks(spark, tags, monkeypatch):
    """F20"""
    replace = queries.dataclasses.replace
    _settings_scored(spark, [replace(queries.LEAF_DENSITY, cluster_selection=s, min_cluster_size=m) for s in ("eom", "leaf") for m in (2, 8, 24)], False)
    assert len(_stored_only(spark, tags, monkeypatch, "star_density_grid", "scores")) == 24


def test_branch_grid_scores_clouds_in_their_tasks(spark, tags, monkeypatch):
    """F19"""
    replace = queries.dataclasses.replace
    _settings_scored(spark, [replace(queries.BEST, graph=g, branch_selection=s, min_branch_size=m) for g in ("full", "core") for s in ("eom", "leaf") for m in (2, 12)], True)
    assert len(_stored_only(spark, tags, monkeypatch, "star_branch_grid", "scores")) == 48


def test_spread_of_branches_is_found_in_their_tasks(spark, tags, monkeypatch):
    """F23"""
    from spurline.plans import clustering, packs

    F, (packed, p, _) = queries.F, _grid_by_joins(spark)
    rows = clustering.branch_clusters(p, queries.BEST).select("grp", "id", "label", "strength").join(p.drop("x"), ["grp", "id"])
    want = clustering.centroid_spread(rows, ("j_l", "j_n"), "sample")
    found = clustering.arm_spread(packs.branch_centroids(packed, queries.BEST), ("shape",))
    plain = lambda df: sorted((r.arm, round(r.spread, 3)) for r in df.collect())
    assert plain(found) == plain(want) and len(plain(found)) >= 18
    assert len(_stored_only(spark, tags, monkeypatch, "star_spread_heatmap", "centroids")) == 200
