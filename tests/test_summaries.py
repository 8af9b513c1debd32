"""Graph summaries, measures and stored models against small definitions."""

import dataclasses
from collections import Counter
from itertools import permutations

import numpy as np
import pytest
from comparing import same
from pyspark.sql import functions as F

from spurline import queries_graphs
from spurline.operators import kernels as K
from spurline.operators import measures as M
from spurline.operators import memberships as R
from spurline.operators import summaries as Y
from spurline.params import BranchParams
from spurline.plans import clustering as C
from spurline.plans import model as P
from spurline.queries import QUERIES
from spurline.sources import workloads as W

BEST = BranchParams(min_samples=5, min_cluster_size=25, min_branch_size=12, allow_single_cluster=True, branch_selection="leaf", central_labels="geodesic")
ORDERS = "/root/testdata/sf0.001/orders.parquet"


def cloud(spark, n=60, seed=3, grp="a"):
    x = np.random.default_rng(seed).integers(0, 12, (n, 2)).astype(float)
    return x, spark.createDataFrame([(grp, i, p.tolist()) for i, p in enumerate(x)], "grp string, id long, x array<double>")


def edges_of(spark, rows):
    return spark.createDataFrame([("a", int(u), int(v), float(w)) for u, v, w in rows], "grp string, u long, v long, w double")


def test_every_query_of_the_module_is_registered():
    names = [n for n, f in QUERIES.items() if f.__module__ == queries_graphs.__name__]
    assert len(names) > 35


def test_radius_pairs_with_ties_and_negative_cells(spark):
    x, p = cloud(spark)
    x = x - 6
    p = p.withColumn("x", F.transform("x", lambda v: v - 6))
    got = {(r.u, r.v) for r in Y.radius_pairs(p, spark.createDataFrame([("a", 2.0)], "grp string, reach double")).collect()}
    d = K.distances(x)
    assert got == {(i, j) for i in range(60) for j in range(i + 1, 60) if d[i, j] <= 2}


def test_full_graph_holds_the_core_graph(spark):
    x, p = cloud(spark)
    m = K.density(x, BranchParams(min_samples=3, min_cluster_size=5, allow_single_cluster=True))
    core = spark.createDataFrame([("a", i, float(c)) for i, c in enumerate(m.core)], "grp string, id long, core double")
    reach = float(m.tree[:, 2].max())
    got = {(r.u, r.v) for r in Y.graph_full(p, core, spark.createDataFrame([("a", reach)], "grp string, reach double")).collect()}
    assert got == set(zip(*(a.tolist() for a in K.graph(m, np.arange(60), "full", True)), strict=True))


def test_path_lengths_memberships_and_nearest_root(spark):
    x, _ = cloud(spark)
    d = K.distances(x)
    u, v = np.nonzero(np.triu((d <= 3) & (d > 0), 1))
    e = edges_of(spark, zip(u, v, d[u, v], strict=True))
    roots = [0, 7, 19]
    paths = M.path_lengths(e, spark.createDataFrame([("a", r) for r in roots], "grp string, root long")).cache()
    want = np.array([K.geodesics(60, u, v, d[u, v], r) for r in roots])
    got = np.full((3, 60), np.inf)
    for r in paths.collect():
        got[roots.index(r.root), r.id] = r.d_geo
    np.testing.assert_allclose(got, want)
    reached = np.isfinite(want).all(0)
    soft = K.softmax_membership(want, 0.5)
    for r in R.softmax(paths, 0.5).collect():
        if reached[r.id]:
            assert r.p == pytest.approx(soft[roots.index(r.root), r.id])
    for r in R.nearest_root(paths).collect():
        assert r.root == roots[int(want[:, r.id].argmin())]
    with pytest.raises(ValueError):
        R.softmax(paths, 0)


def test_lipschitz_matches_all_pairs_of_edges(spark):
    rng = np.random.default_rng(1)
    rows = [(u, v, rng.integers(0, 4), rng.random()) for u in range(12) for v in range(u + 1, 12) if rng.random() < 0.4]
    e = spark.createDataFrame([("a", u, v, float(w), float(s)) for u, v, w, s in rows], "grp string, u long, v long, w double, level double")
    want = max(abs(a[3] - b[3]) / a[2] for a in rows for b in rows if a[2] > 0 and {a[0], a[1]} & {b[0], b[1]})
    assert M.lipschitz(e).first().constant == pytest.approx(want)
    assert M.lipschitz(e.limit(0)).count() == 0


def test_graph_stats_of_a_group_without_edges(spark):
    _, p = cloud(spark, 4)
    got = {r.grp: r for r in M.graph_stats(edges_of(spark, [(0, 1, 2), (1, 2, 5)]), p.unionByName(p.withColumn("grp", F.lit("b")))).collect()}
    assert (got["a"].edges, got["a"].degree, got["a"].longest) == (2, 1.0, 5.0) and got["b"].edges == 0 and got["b"].longest is None


def test_scaling_fit_is_a_polynomial_fit(spark):
    rng = np.random.default_rng(5)
    n = 100 * 2.0 ** np.arange(9)
    s = 1e-6 * n**1.4 * np.exp(rng.normal(0, 0.1, 9))
    got = M.scaling_fit(spark.createDataFrame([("k", float(a), float(b)) for a, b in zip(n, s, strict=True)] + [("two", 1.0, 1.0), ("two", 2.0, 2.0)], "m string, n double, seconds double"), ("m",)).collect()
    x = np.log(n) - np.log(n).mean()
    bend, slope, base = np.polyfit(x, np.log(s), 2)
    design = np.stack([np.ones(9), x, x * x], 1)
    gap = np.log(s) - design @ [base, slope, bend]
    se = np.sqrt((gap @ gap / 6) * np.einsum("ij,jk,ik->i", design, np.linalg.inv(design.T @ design), design))
    for r in got:
        if r.m == "two":
            assert r.slope is None and r.low is None
            continue
        i = n.tolist().index(r.n)
        assert (r.slope, r.bend) == (pytest.approx(slope), pytest.approx(bend))
        assert r.high / r.fitted == pytest.approx(np.exp(1.96 * se[i])) and r.low < r.fitted


def test_bottleneck_against_all_matchings(spark):
    rng = np.random.default_rng(2)
    for n, m in ((0, 0), (0, 2), (1, 3), (3, 3), (2, 2)):
        p, q = (np.sort(rng.integers(0, 9, (k, 2)).astype(float), 1)[:, ::-1] for k in (n, m))
        best = 0.0 if n + m == 0 else np.inf
        for order in permutations(range(n + m)) if n + m else ():
            cost = [np.abs(p[i] - q[j]).max() if i < n and j < m else (p[i, 0] - p[i, 1]) / 2 if i < n else (q[j, 0] - q[j, 1]) / 2 if j < m else 0.0 for i, j in enumerate(order)]
            best = min(best, max(cost))
        assert M.matching_distance(p, q) == best
    t = spark.createDataFrame([("a", 5.0, 1.0), ("b", 3.0, 1.0)], "grp string, birth double, death double")
    assert {r.grp: r.distance for r in M.bottleneck(t, t.where("grp = 'a'")).collect()} == {"a": 0.0, "b": 1.0}


def test_nerve_of_a_ring_is_a_ring(spark):
    at = 2 * np.pi * np.arange(100) / 100
    p = spark.createDataFrame([("a", i, [float(np.cos(a)), float(np.sin(a))]) for i, a in enumerate(at)], "grp string, id long, x array<double>")
    near = Y.radius_pairs(p, spark.createDataFrame([("a", 0.1)], "grp string, reach double"))
    nodes, links = Y.nerve(p.select("grp", "id", F.get("x", F.lit(0)).alias("value")), near, 4, 0.4)
    assert nodes.count() == 6 and links.count() == 6
    flat = p.select("grp", "id", F.lit(1.0).alias("value"))
    assert Y.nerve(flat, near, 4, 0.4)[0].collect()[0].size == 100


def test_level_sets_of_a_path(spark):
    signal = spark.createDataFrame([("a", i, abs(i - 5) + 0.5) for i in range(11)], "grp string, id long, value double")
    nodes, links = Y.level_sets(signal, edges_of(spark, [(i, i + 1, 1) for i in range(10)]), 2.0)
    assert nodes.count() == 5 and links.count() == 4


def test_largest_component_ties_and_dense_part(spark):
    v = spark.createDataFrame([("a", i) for i in range(5)], "grp string, id long")
    assert {r.id for r in Y.largest_component(edges_of(spark, [(3, 4, 1), (0, 1, 1)]), v).collect()} == {0, 1}
    core = v.withColumn("core", F.col("id").cast("double"))
    assert {r.id for r in Y.dense_part(core, 0.5).collect()} == {0, 1, 2}


def test_compare_labels_and_center_batches(spark):
    a = spark.createDataFrame([("a", 0, 0), ("a", 1, 0), ("a", 2, 1)], "grp string, id long, label int")
    got = {(r.a, r.b): (r.n, r.share_a) for r in Y.compare_labels(a, a.where("id < 2")).collect()}
    assert got == {(0, 0): (2, 1.0), (1, -1): (1, 1.0)}
    p = spark.createDataFrame([("a", 0, [1.0, 2.0], "p"), ("a", 1, [3.0, 2.0], "p"), ("a", 2, [9.0, 9.0], None)], "grp string, id long, x array<double>, batch string")
    assert {r.id: r.x for r in Y.center_batches(p, "batch").collect()} == {0: [-1.0, 0.0], 1: [1.0, 0.0], 2: [0.0, 0.0]}


def test_model_gives_the_same_branches_and_survives_saving(spark, tmp_path):
    p = W.star_points(spark.read.parquet(ORDERS), W.lengths(5), W.noises(5))
    P.save_model(P.density_model(p, BEST), BEST, str(tmp_path / "m"))
    model, params = P.load_model(spark, str(tmp_path / "m"))
    assert params == BEST
    for q in (BEST, dataclasses.replace(BEST, graph="full", branch_selection="eom")):
        assert sorted(map(tuple, P.branches_of(model, q).collect())) == sorted(map(tuple, C.branch_clusters(p, q).collect()))
    assert P.density_model(p.limit(0), BEST).count() == 0


def test_shapes(spark):
    orders = spark.read.parquet(ORDERS)
    bar = W.shape_points(orders, "bar")
    one = C.branch_clusters(bar, BEST).groupBy("grp").agg(F.count_distinct("label").alias("n")).collect()
    two = C.branch_clusters(bar, dataclasses.replace(BEST, label_sides=True, central_labels="centre")).where("cluster >= 0").groupBy("grp").agg(F.count_distinct("branch").alias("n")).collect()
    assert {r.n for r in one} == {1} and all(r.n >= 2 for r in two)
    y = C.branch_clusters(W.shape_points(orders, "yshape"), BEST).where("label >= 0").groupBy("grp").agg(F.count_distinct("label").alias("n")).collect()
    assert {r.n for r in y} == {3}


@pytest.mark.parametrize("name", ["profile_points", "yshape_points", "edge_lipschitz"])
def test_larger_scale(spark, sf, name):
    from spurline.queries import ORACLES

    assert same(QUERIES[name](spark, sf), ORACLES[name], sf) > 0


def pair_counting_ari(a, b):
    pairs = lambda xs: sum(n * (n - 1) / 2 for n in Counter(xs).values())
    both, one, two, every = pairs(zip(a, b, strict=True)), pairs(a), pairs(b), len(a) * (len(a) - 1) / 2
    most, chance = (one + two) / 2, one * two / every
    return 1.0 if most == chance else (both - chance) / (most - chance)


@pytest.fixture(scope="module")
def late_orders(spark, tmp_path_factory):
    """Sixty orders of one sample, with keys behind the first thousands, and their hundred clouds."""
    d = tmp_path_factory.mktemp("late")
    spark.read.parquet(ORDERS).where("o_orderkey < 60").withColumn("o_orderkey", F.col("o_orderkey") + 3435).coalesce(1).write.parquet(f"{d}/orders.parquet")
    shapes = [(a, b, W.lengths(a), W.noises(b)) for a in range(10) for b in range(10)]
    clouds = {}
    for r in W.star_grid(spark.read.parquet(f"{d}/orders.parquet"), shapes).orderBy("grp", "id").collect():
        clouds.setdefault((r.j_l, r.j_n), []).append((r.arm, r.x))
    assert len(clouds) == 100
    return str(d), {k: ([arm for arm, _ in v], np.array([x for _, x in v])) for k, v in clouds.items()}


def test_star_heatmap_reads_every_order(spark, late_orders):
    d, clouds = late_orders
    got = {(r.method, r.j_l, r.j_n): (r.ari, r.clouds) for r in QUERIES["star_heatmap"](spark, d).collect()}
    dense = BranchParams(min_samples=5, min_cluster_size=8, cluster_selection="leaf")
    for (a, b), (arm, x) in clouds.items():
        m = K.density(x, BEST)
        assert got["branches", a, b] == (pytest.approx(pair_counting_ari(arm, K.combine(m, K.branches(x, m, BEST), BEST)["label"].tolist())), 1)
        assert got["density", a, b] == (pytest.approx(pair_counting_ari(arm, K.density(x, dense).label.tolist())), 1)
        assert got["kmeans", a, b][1] == 1
    assert got[None, None, None][1] == 300


def test_star_branch_grid_takes_every_order_and_shape(spark, late_orders):
    d, clouds = late_orders
    got = QUERIES["star_branch_grid"](spark, d).collect()
    assert len(got) == 48 and [-r.ari for r in got] == sorted(-r.ari for r in got)
    for r in [r for r in got if r.m_b in (2, 12, 24)]:
        p, every = dataclasses.replace(BEST, graph=r.graph, branch_selection=r.selection, min_branch_size=r.m_b), []
        for arm, x in clouds.values():
            m = K.density(x, p)
            every.append(pair_counting_ari(arm, K.combine(m, K.branches(x, m, p), p)["label"].tolist()))
        assert r.ari == pytest.approx(np.mean(every))


def test_star_density_grid(spark, late_orders):
    d, clouds = late_orders
    got = QUERIES["star_density_grid"](spark, d).collect()
    assert {(r.selection, r.m_c) for r in got} == {(s, m) for s in ("eom", "leaf") for m in range(2, 25, 2)} and len(got) == 24
    assert [-r.ari for r in got] == sorted(-r.ari for r in got)
    for r in [r for r in got if r.m_c in (2, 8, 24)]:
        p = BranchParams(min_samples=5, min_cluster_size=r.m_c, cluster_selection=r.selection)
        assert r.ari == pytest.approx(np.mean([pair_counting_ari(arm, K.density(x, p).label.tolist()) for arm, x in clouds.values()]))


@pytest.mark.parametrize("name", ["profile_branches", "walk_branches"])
def test_one_data_set_is_one_cloud(spark, tmp_path, name):
    """Labels of the whole cloud, as the kernel gives them without groups."""
    d = "/root/testdata/sf0.001"
    if name == "walk_branches":
        d = str(tmp_path)
        spark.read.parquet("/root/testdata/sf0.01/events.parquet").where("user_id < 30").coalesce(1).write.parquet(f"{d}/events.parquet")
        points, p = W.walk_points(spark.read.parquet(f"{d}/events.parquet")), BranchParams(min_samples=10, min_cluster_size=100, min_branch_size=20, allow_single_cluster=True)
    else:
        points, p = W.profile_points(spark.read.parquet(f"{d}/customer.parquet"), spark.read.parquet(ORDERS)), BranchParams(min_samples=5, min_cluster_size=100, min_branch_size=5, allow_single_cluster=True)
    rows = points.select("id", "x").orderBy("id").collect()
    x = np.array([r.x for r in rows])
    m = K.density(x, p)
    want = dict(zip([r.id for r in rows], K.combine(m, K.branches(x, m, p), p)["label"].tolist(), strict=True))
    got = QUERIES[name](spark, d).collect()
    assert len({r.grp for r in got}) == 1 and {r.id: r.label for r in got} == want


def test_layout_parts_components(spark):
    """Two triangles that overlap: ends of edges come to lie nearer to each other than the triangles do."""
    import numpy as np

    points = spark.createDataFrame([("a", i, [float(i // 3) + 0.1 * (i % 3), 0.5 * (i % 2), 1.0]) for i in range(6)], "grp string, id long, x array<double>")
    edges = spark.createDataFrame([("a", 0, 1), ("a", 1, 2), ("a", 0, 2), ("a", 3, 4), ("a", 4, 5), ("a", 3, 5)], "grp string, u long, v long")
    at = {r.id: np.array(r.x) for r in Y.layout(edges, points, 2, repulsion=1.0).collect()}
    assert len(at) == 6 and all(np.isfinite(x).all() for x in at.values())
    within = max(np.linalg.norm(at[i] - at[j]) for i, j in ((0, 1), (1, 2), (3, 4), (4, 5)))
    assert np.linalg.norm((at[0] + at[1] + at[2]) / 3 - (at[3] + at[4] + at[5]) / 3) > within / 2


def test_stability_of_samples(spark):
    rows = [("a", i, [float(i), float(i % 2)], int(i >= 10)) for i in range(20)] + [("b", 0, [0.0, 0.0], 0)]
    a = spark.createDataFrame(rows, "grp string, id long, x array<double>, label int")
    moved = spark.createDataFrame([(g, i, [x[0] + 0.2, x[1]], 7 - k) for g, i, x, k in rows if g == "a"], a.schema)
    got = {r.grp: (r.points, r.ari) for r in Y.sample_stability(a, moved).collect()}
    assert got == {"a": (20, 1.0)}


def test_timing_experiment(spark, tmp_path):
    """Two sizes, two methods; the cut-off stops the larger size; metrics of an event log."""
    import json

    from spurline import timing
    from spurline.runtime import table

    events = table(spark, "/root/testdata/sf0.001", "events")
    records = timing.run(spark, events, dimensions=(2,), starts=(2, 4), samples=1, methods=("kmeans", "density"), cut_off=0.0)
    assert [(r["n"], r["method"]) for r in records] == [(500, "kmeans"), (500, "density")]
    assert all(r["groups"] >= 1 and "error" not in r for r in records)
    got = timing.report(spark, records)
    assert got["times"].count() == 2 and got["overhead"].count() == 0
    log = tmp_path / "log"
    log.write_text("\n".join(map(json.dumps, [{"Event": "SparkListenerTaskEnd", "Task Metrics": {"Executor CPU Time": 2e9, "Shuffle Write Metrics": {"Shuffle Bytes Written": 5}, "Disk Bytes Spilled": 1}}, {"Event": "SparkListenerStageCompleted"}])))
    assert timing.spark_metrics(str(log)) == {"tasks": 1, "cpu_seconds": 2.0, "shuffle_written": 5, "shuffle_read": 0, "spilled": 1, "peak_task_memory": 0, "stages": 1}


def test_walk_clouds(spark):
    from spurline.runtime import table
    from spurline.sources.workloads import walk_cloud

    events = table(spark, "/root/testdata/sf0.001", "events")
    for dims, starts in ((2, 2), (8, 7), (16, 3)):
        rows = walk_cloud(events, dims, starts, sample=1).collect()
        assert len(rows) == len({r.id for r in rows}) == 250 * starts and {r.start for r in rows} == set(range(starts)) and all(len(r.x) == dims for r in rows)
