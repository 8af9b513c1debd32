"""Clusters and branches of groups of any size: the whole method as joins, windows and bounded array tasks."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from spurline.operators import baselines, measures
from spurline.operators import condense as C
from spurline.operators import kernels as K
from spurline.operators import neighbors as N
from spurline.operators.blocks import measurable
from spurline.operators.forest import spanning_forest
from spurline.operators.memberships import softmax
from spurline.operators.reach import reach_tree
from spurline.operators.summaries import graph_full
from spurline.params import BranchParams
from spurline.runtime import materialise


@dataclass
class DensityModel:
    """A clustering by density as tables, all by ``grp``: points ``id, x``; neighbours; core distances; spanning tree; points' exits and
    nodes of the condensed hierarchy; the nodes' selection; labels ``id, label, strength``."""

    points: DataFrame
    near: DataFrame
    core: DataFrame
    tree: DataFrame
    exits: DataFrame
    nodes: DataFrame
    picked: DataFrame
    labels: DataFrame


def density(points: DataFrame, p: BranchParams, task_edges: int = C.TASK_EDGES) -> DensityModel:
    """Points that hold nulls or other than finite numbers are left out; ids are distinct within a group."""
    points = materialise(measurable(points, p.metric), "points")
    tree, core, near = reach_tree(points, p.min_samples, p.metric)
    exits, nodes = C.condense(tree.select("grp", "u", "v", (1.0 / F.greatest("w", F.lit(K.MIN_GAP))).alias("level")), p.min_cluster_size, max(task_edges, p.min_cluster_size))
    picked = C.pick(exits, nodes, p.cluster_selection, p.allow_single_cluster, p.cluster_epsilon)
    return DensityModel(points, near, core, tree, exits, nodes, picked, materialise(C.flat_labels(points, exits, picked), "labels"))


def _mean(rows: DataFrame, keys: list[str]) -> DataFrame:
    """``(keys..., centre)``: the mean of ``x`` by ``strength``; plain where strengths are all zero."""
    axis = rows.select(*keys, "strength", F.posexplode("x").alias("axis", "value")).groupBy(*keys, "axis").agg(F.sum(F.col("value") * F.col("strength")).alias("s"), F.sum("strength").alias("w"), F.avg("value").alias("plain"))
    mean = F.when(F.col("w") > 0, F.col("s") / F.col("w")).otherwise(F.col("plain"))
    return axis.groupBy(*keys).agg(F.transform(F.array_sort(F.collect_list(F.struct("axis", mean.alias("m")))), lambda t: t["m"]).alias("centre"))


def distance_to(metric: str, a: F.Column, b: F.Column) -> F.Column:
    if metric == "angular":
        dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda s, t: s * t), F.lit(0.0), lambda s, t: s + t)
        return F.acos(F.least(F.greatest(dot(a, b) / F.greatest(F.sqrt(dot(a, a)) * F.sqrt(dot(b, b)), F.lit(1e-300)), F.lit(-1.0)), F.lit(1.0)))
    gaps = F.zip_with(a, b, lambda s, t: F.abs(s - t))
    if metric == "euclidean":
        return F.sqrt(N.squared(a, b))
    return F.aggregate(gaps, F.lit(0.0), (lambda s, g: s + g) if metric == "manhattan" else (lambda s, g: F.greatest(s, g)))


def cluster_graph(m: DensityModel, members: DataFrame, p: BranchParams) -> DataFrame:
    """``(grp, cluster, u, v, d, w)``, u < v: the approximation graph of each cluster among its ``members`` (``grp, id, cluster``)."""
    at = lambda e: members.select("grp", F.col("id").alias(e), F.col("cluster").alias(f"k_{e}"))
    inside = lambda e: e.join(at("u"), ["grp", "u"]).join(at("v"), ["grp", "v"]).where("k_u = k_v").withColumnRenamed("k_u", "cluster").drop("k_v")
    x = m.points.select("grp", "id", "x")
    tree = inside(m.tree.select("grp", "u", "v", "w"))
    if p.graph == "full":
        keyed = lambda df: df.withColumn("grp", F.concat_ws("\n", "grp", "cluster"))
        if p.metric not in ("euclidean", "manhattan"):
            raise ValueError("full graphs of large groups are found by cells, under Euclidean or Manhattan distance")
        reach = keyed(tree).groupBy("grp").agg(F.max("w").alias("reach"))
        mine = keyed(members.join(x, ["grp", "id"]))
        core = keyed(members.join(m.core, ["grp", "id"]))
        full = graph_full(mine, core.select("grp", "id", "core"), reach.where("reach > 0"))
        back = members.select("grp", "cluster").distinct().withColumn("key", F.concat_ws("\n", "grp", "cluster"))
        return full.withColumnRenamed("grp", "key").join(back, "key").select("grp", "cluster", "u", "v", "d", "w")
    lists = N.graph_core(m.near, m.core) if p.graph == "core" else N.mutual_reach(N.graph_mutual(m.near), m.core).drop("larger")
    edges = inside(lists.select("grp", "u", "v", "d", "w"))
    if p.with_tree_edges:
        more = tree.join(edges.select("grp", "u", "v"), ["grp", "u", "v"], "left_anti")
        more = more.join(x.select("grp", F.col("id").alias("u"), F.col("x").alias("a")), ["grp", "u"]).join(x.select("grp", F.col("id").alias("v"), F.col("x").alias("b")), ["grp", "v"])
        edges = edges.unionByName(more.select("grp", "cluster", "u", "v", distance_to(p.metric, F.col("a"), F.col("b")).alias("d"), "w"))
    return edges


def signal(m: DensityModel, members: DataFrame, edges: DataFrame, p: BranchParams) -> DataFrame:
    """``(grp, cluster, id, value)``: eccentricities, of a geometric, geodesic or distance-sum kind, smoothed, pushed and turned."""
    keys = ["grp", "cluster"]
    rows = materialise(members.join(m.points, ["grp", "id"]), "members")
    far = rows.join(_mean(rows, keys), keys).select(*keys, "id", "x", distance_to(p.metric, F.col("centre"), F.col("x")).alias("value"))
    keyed = lambda df: df.withColumn("grp", F.concat_ws("\n", *keys))
    if p.eccentricity == "distance_sum":
        if p.metric != "euclidean":
            raise ValueError("distance sums of large groups are Euclidean")
        sums = baselines.distance_sums(keyed(rows)).withColumnRenamed("grp", "key")
        far = rows.withColumn("key", F.concat_ws("\n", *keys)).join(sums, ["key", "id"]).select(*keys, "id", "x", "value")
    elif p.eccentricity == "geodesic":
        root = far.groupBy(*keys).agg(F.min_by("id", F.struct("value", "id")).alias("root"))
        hops = lambda roots: materialise(N.hop_distances(keyed(edges), keyed(roots).select("grp", "root")).select("grp", "id", "hops"), "hops")
        if p.root == "extremal":
            end = hops(root).groupBy("grp").agg(F.max_by("id", F.struct("hops", -F.col("id"))).alias("end"))
            root = root.withColumn("key", F.concat_ws("\n", *keys)).join(end.withColumnRenamed("grp", "key"), "key").select(*keys, F.col("end").alias("root"))
        found = hops(root).withColumnRenamed("grp", "key")
        far = far.withColumn("key", F.concat_ws("\n", *keys)).join(found, ["key", "id"], "left").select(*keys, "id", "x", F.coalesce(F.col("hops").cast("double"), F.lit(0.0)).alias("value"))
    elif p.eccentricity == "max_path":
        raise ValueError("longest paths from every point are for groups that the kernel takes; use landmarks (star_max_path)")
    out = far.drop("x")
    for _ in range(p.smooth):
        out = materialise(N.smooth_signal(edges.select("grp", "u", "v"), out.select("grp", "id", "value")).join(members.select("grp", "id", "cluster"), ["grp", "id"]), "smooth")
    if p.push:
        out = out.join(m.core, ["grp", "id"]).withColumn("value", F.col("value") + F.col("core")).drop("core")
    if p.direction == "min":
        out = out.withColumn("value", F.max("value").over(Window.partitionBy(*keys)) - F.col("value"))
    return materialise(out.select(*keys, "id", "value"), "signal")


@dataclass
class _BranchPass:
    """What the branch pass over a density model makes: members ``grp, id, cluster, strength``; graph; exits and nodes by cluster, with
    ``grp`` and ``cluster`` in one; clusters that are split ``grp, cluster, key, chosen``; their points ``grp, cluster, id, branch, bs, chosen``."""

    members: DataFrame
    edges: DataFrame
    exits: DataFrame
    nodes: DataFrame
    splits: DataFrame
    found: DataFrame


KEYS = ["grp", "cluster"]


def _keyed(df: DataFrame) -> DataFrame:
    return df.withColumn("grp", F.concat_ws("\n", *KEYS))


def _branch_pass(m: DensityModel, p: BranchParams, task_edges: int = C.TASK_EDGES, given: DataFrame | None = None) -> _BranchPass:
    members = m.labels.where("label >= 0").select("grp", "id", F.col("label").alias("cluster"), "strength")
    edges = materialise(cluster_graph(m, members.drop("strength"), p), "cluster-graph")
    if given is None:
        value = signal(m, members, edges, p)
    else:
        own = members.select(*KEYS, "id").join(given.select("grp", "id", F.col("value").cast("double").alias("value")), ["grp", "id"], "left")
        value = materialise(own.withColumn("value", F.coalesce("value", F.min("value").over(Window.partitionBy(*KEYS)), F.lit(0.0))), "signal")
    levels = N.level_edges(edges.select(*KEYS, "u", "v"), value.select("grp", "id", "value"))
    forest = spanning_forest(_keyed(levels).select("grp", "u", "v", F.col("level").alias("w")), maximum=True)
    exits, nodes = C.condense(forest.withColumnRenamed("w", "level"), p.branch_size, max(task_edges, p.branch_size))
    picked = C.pick(exits, nodes, p.branch_selection, False, 0.0, p.branch_persistence)
    names = members.select(*KEYS).distinct().withColumn("key", F.concat_ws("\n", *KEYS))
    counts = picked.groupBy(F.col("grp").alias("key")).agg(F.max("chosen").alias("chosen")).where(F.col("chosen") > (1 if p.label_sides else 2))
    splits = materialise(names.join(counts, "key"), "splits")
    found = C.flat_labels(_keyed(members), exits, picked).withColumnRenamed("grp", "key")
    found = found.join(splits, "key").select(*KEYS, "id", F.col("label").alias("branch"), F.col("strength").alias("bs"), "chosen")
    return _BranchPass(members, edges, exits, nodes, splits, materialise(found, "branches"))


def _root_paths(m: DensityModel, b: _BranchPass, p: BranchParams) -> DataFrame:
    """``(key, id, branch, d_geo)``: path lengths from the root of every branch, the point nearest to its mean by strength."""
    inner = b.found.where("branch >= 0").withColumnRenamed("bs", "strength").join(m.points, ["grp", "id"])
    centres = _mean(inner, [*KEYS, "branch"])
    near = inner.join(centres, [*KEYS, "branch"]).groupBy(*KEYS, "branch").agg(F.min_by("id", F.struct(N.squared(F.col("x"), F.col("centre")), "id")).alias("root"))
    near = materialise(near, "roots")
    length = {"distance": F.col("d"), "mreach": F.col("w"), "hops": F.lit(1.0)}[p.edge_length]
    paths = measures.path_lengths(_keyed(b.edges.join(b.splits, KEYS, "left_semi")).select("grp", "u", "v", length.alias("w")), _keyed(near).select("grp", "root"))
    return paths.join(_keyed(near).select("grp", "root", "branch"), ["grp", "root"]).select(F.col("grp").alias("key"), "id", "branch", "d_geo")


def branches(m: DensityModel, p: BranchParams, task_edges: int = C.TASK_EDGES, given: DataFrame | None = None) -> DataFrame:
    """RESULT rows of a density model; see :mod:`spurline.plans.clustering`. All clusters go through every step together.

    ``given`` (``grp, id, value``): any signal in place of the eccentricity; points without a value have the least of their cluster.
    """
    b = _branch_pass(m, p, task_edges, given)
    loose = F.col("branch") < 0
    if p.central_labels == "geodesic":
        nearest = _root_paths(m, b, p).groupBy("key", "id").agg(F.min_by("branch", F.struct("d_geo", "branch")).alias("nearest"))
        found = b.found.withColumn("key", F.concat_ws("\n", *KEYS)).join(nearest, ["key", "id"], "left").withColumn("k", F.when(loose, F.coalesce("nearest", F.lit(0))).otherwise(F.col("branch")))
    else:
        found = b.found.withColumn("k", F.when(loose, F.col("chosen")).otherwise(F.col("branch")))
    found = found.select("grp", "id", "k", F.when(loose, 0.0).otherwise(F.col("bs")).alias("bs"), loose.alias("loose"))
    rows = m.labels.withColumnRenamed("label", "cluster").join(found, ["grp", "id"], "left")
    joint = F.col("strength") * F.col("bs") if p.combine == "product" else (F.col("strength") + F.col("bs")) / 2
    rows = materialise(rows.select("grp", "id", F.coalesce(joint, "strength").alias("strength"), "cluster", F.col("strength").alias("cluster_strength"), F.coalesce("k", F.lit(0)).alias("branch"), F.coalesce("bs", F.lit(1.0)).alias("branch_strength"), F.coalesce("loose", F.lit(False)).alias("is_center")), "combined")
    number = rows.where("cluster >= 0").select("grp", "cluster", "branch").distinct().withColumn("label", (F.row_number().over(Window.partitionBy("grp").orderBy("cluster", "branch")) - 1).cast("int"))
    out = rows.join(number, ["grp", "cluster", "branch"], "left")
    return out.select("grp", "id", F.coalesce("label", F.lit(-1)).alias("label"), "strength", "cluster", "cluster_strength", "branch", "branch_strength", "is_center")


def memberships(m: DensityModel, p: BranchParams) -> DataFrame:
    """Softmax memberships of every point in each branch of its cluster, and weighted by its strength; a branch that no path reaches
    from a point counts nothing there, at an infinite length."""
    b = _branch_pass(m, p)
    every = b.found.select(*KEYS, "id").join(b.found.where("branch >= 0").select(*KEYS, "branch").distinct(), KEYS).withColumn("key", F.concat_ws("\n", *KEYS))
    paths = every.join(_root_paths(m, b, p), ["key", "id", "branch"], "left").withColumn("d_geo", F.coalesce("d_geo", F.lit(float("inf"))))
    soft = softmax(paths.select(F.col("key").alias("grp"), F.col("branch").alias("root"), "id", "d_geo"), p.temperature)
    rows = paths.join(soft.select(F.col("grp").alias("key"), "id", F.col("root").alias("branch"), "p"), ["key", "id", "branch"]).join(b.members, [*KEYS, "id"])
    return rows.select("grp", "id", "cluster", "branch", "d_geo", "p", (F.col("p") * F.col("strength")).alias("weighted"))


def condensed(m: DensityModel, p: BranchParams, which: str = "cluster") -> DataFrame:
    """Nodes of the cluster tree, or of all branch trees, as rows of :func:`spurline.plans.clustering.condensed`."""
    from spurline.plans.clustering import TREES, tree_rows

    if which == "cluster":
        how, allow, eps = p.cluster_selection, p.allow_single_cluster, p.cluster_epsilon
        return C.tree_table(m.exits, m.nodes, lambda t: tree_rows(t, K.select(t, how, allow, eps), -1), TREES)
    b = _branch_pass(m, p)
    how = p.branch_selection
    rows = C.tree_table(b.exits, b.nodes, lambda t: tree_rows(t, K.select(t, how, False), -1), TREES, p.branch_persistence).drop("cluster").withColumnRenamed("grp", "key")
    names = b.members.select(*KEYS).distinct().withColumn("key", F.concat_ws("\n", *KEYS))
    return rows.join(names, "key").select(*[f.split()[0] for f in TREES.split(", ")])
