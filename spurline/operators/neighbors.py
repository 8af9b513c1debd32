"""Core distances, neighbourhood graphs and paths as joins, for groups of any size; neighbours come from :mod:`spurline.operators.blocks`."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spurline.runtime import materialise, merged


def squared(a: F.Column, b: F.Column) -> F.Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)


def core_distance(neighbours: DataFrame, k: int) -> DataFrame:
    """``(grp, id, core)``: distance to the k-th nearest other point; points with fewer neighbours are left out."""
    return neighbours.groupBy("grp", "id").agg(F.max("d").alias("core"), F.count(F.lit(1)).alias("n")).where(F.col("n") >= k).drop("n")


def mutual_reach(edges: DataFrame, core: DataFrame) -> DataFrame:
    """``edges`` (``grp, u, v, d``) with ``w``, the mutual reachability."""
    cu, cv = (core.select("grp", F.col("id").alias(s), F.col("core").alias(f"core_{s}")) for s in "uv")
    return edges.join(merged(cu), ["grp", "u"]).join(merged(cv), ["grp", "v"]).select("grp", "u", "v", "d", F.greatest("d", "core_u", "core_v").alias("w"), F.greatest("core_u", "core_v").alias("larger"))


#: Points of a group whose pairs are formed by one task.
PAIR_POINTS = 2_000


def reach_pairs(points: DataFrame, core: DataFrame) -> DataFrame:
    """``(grp, u, v, w)``, u < v: all pairs of each group's points that have a core distance, with their mutual reachability. A group of
    over PAIR_POINTS points goes by joins; a smaller one is paired by one task, so that no pair is ever shuffled."""
    rows = points.select("grp", "id", "x").join(merged(core.select("grp", "id", "core")), ["grp", "id"])
    big = materialise(points.groupBy("grp").count().where(F.col("count") > PAIR_POINTS).select("grp"), "large-groups")

    def run(key, t):
        t = t.sort_by("id")
        ids, c = t.column("id").to_numpy(), t.column("core").to_numpy()
        x = t.column("x").combine_chunks()
        x = x.flatten().to_numpy(zero_copy_only=False).reshape(len(x), -1)
        u, v = np.triu_indices(len(ids), 1)
        fine = ids[u] < ids[v]  # a repeated id is no pair
        u, v = u[fine], v[fine]
        w = np.zeros(len(u))
        for axis in x.T:
            gap = axis[u] - axis[v]
            w += gap * gap
        w = np.maximum(np.sqrt(w), np.maximum(c[u], c[v]))
        return pa.table({"grp": pa.repeat(pa.scalar(key[0].as_py(), pa.string()), len(u)), "u": ids[u], "v": ids[v], "w": w})

    def grouped(r: DataFrame) -> DataFrame:
        tasks = int(r.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        return r.where("grp is not null").repartition(tasks, "grp").groupBy("grp").applyInArrow(run, "grp string, u long, v long, w double")

    if big.isEmpty():
        return grouped(rows)
    large = rows.join(big, "grp", "left_semi")
    a, b = (large.select("grp", F.col("id").alias(e), F.col("x").alias(f"x_{e}"), F.col("core").alias(f"c_{e}")) for e in "uv")
    joined = a.join(merged(b), "grp").where("u < v").select("grp", "u", "v", F.greatest(F.sqrt(squared(F.col("x_u"), F.col("x_v"))), "c_u", "c_v").alias("w"))
    return grouped(rows.join(big, "grp", "left_anti")).unionByName(joined)


def graph_core(neighbours: DataFrame, core: DataFrame) -> DataFrame:
    """``(grp, u, v, d, w)``, u < v: pairs whose mutual reachability is at most the larger of their core distances, which is
    what being in one of the two neighbour lists means."""
    pairs = neighbours.select("grp", F.least("id", "nbr").alias("u"), F.greatest("id", "nbr").alias("v"), "d").groupBy("grp", "u", "v").agg(F.min("d").alias("d"))
    return mutual_reach(pairs, core).where("w <= larger").drop("larger")


def graph_mutual(neighbours: DataFrame) -> DataFrame:
    """``(grp, u, v, d)``: pairs that are in each other's lists."""
    pairs = neighbours.select("grp", F.least("id", "nbr").alias("u"), F.greatest("id", "nbr").alias("v"), "d")
    return pairs.groupBy("grp", "u", "v").agg(F.min("d").alias("d"), F.count(F.lit(1)).alias("n")).where("n = 2").drop("n")


def level_edges(edges: DataFrame, signal: DataFrame) -> DataFrame:
    """``edges`` with ``level``, the smaller signal (``grp, id, value``) of their ends."""
    a, b = (signal.select("grp", F.col("id").alias(s), F.col("value").alias(f"e_{s}")) for s in "uv")
    return edges.join(merged(a), ["grp", "u"]).join(merged(b), ["grp", "v"]).withColumn("level", F.least("e_u", "e_v")).drop("e_u", "e_v")


def smooth_signal(edges: DataFrame, signal: DataFrame, rounds: int = 1) -> DataFrame:
    """``(grp, id, value)``: means over closed neighbourhoods, ``rounds`` times."""
    for _ in range(rounds):
        both = edges.select("grp", F.col("u").alias("id"), F.col("v").alias("o")).unionByName(edges.select("grp", F.col("v").alias("id"), F.col("u").alias("o"))).unionByName(signal.select("grp", "id", F.col("id").alias("o")))
        signal = both.join(signal.select("grp", F.col("id").alias("o"), "value"), ["grp", "o"]).groupBy("grp", "id").agg(F.avg("value").alias("value"))
    return signal


#: Edges of a group, and edges times roots, up to which its paths are found by one task.
PATH_EDGES, PATH_WORK = 50_000, 5_000_000


def paths_by_size(edges: DataFrame, roots: DataFrame, name: str, joined) -> DataFrame:
    """``(grp, root, id, name)``, the least sums of ``w`` along ``edges`` (``grp, u, v, w``) from each of ``roots``: small groups by a task
    each, and ``joined(edges, roots)`` for the others, if there are any. Sums are formed from the root on, in both."""
    work = edges.groupBy("grp").agg(F.count(F.lit(1)).alias("e")).join(merged(roots.groupBy("grp").agg(F.count(F.lit(1)).alias("r"))), "grp")
    big = materialise(work.where((F.col("e") > PATH_EDGES) | (F.col("e") * F.col("r") > PATH_WORK)).select("grp"), "large-groups")
    if big.isEmpty():
        return _paths_of_groups(edges, roots, name)
    few = _paths_of_groups(*(t.join(big, "grp", "left_anti") for t in (edges, roots)), name)
    return few.unionByName(joined(*(t.join(big, "grp", "left_semi") for t in (edges, roots))))


def _paths_of_groups(edges: DataFrame, roots: DataFrame, name: str) -> DataFrame:
    def run(key, e, r):
        ends = [e.column(c).to_numpy() for c in "uv"]
        root = r.column("root").to_numpy()
        ids, at = np.unique(np.concatenate([*ends, root]), return_inverse=True)
        n = len(ends[0])
        u, v = np.r_[at[:n], at[n : 2 * n]], np.r_[at[n : 2 * n], at[:n]]
        w = np.tile(e.column("w").to_numpy().astype(float), 2)
        order = np.argsort(v, kind="stable")
        u, v, w = u[order], v[order], w[order]
        first = np.flatnonzero(np.r_[True, v[1:] != v[:-1]][: len(v)])
        best = np.full((len(root), len(ids)), np.inf)
        best[np.arange(len(root)), at[2 * n :]] = 0.0
        for _ in range(len(ids) + 1 if len(first) else 0):
            new = np.minimum(best[:, v[first]], np.minimum.reduceat(best[:, u] + w, first, axis=1))
            if (new == best[:, v[first]]).all():
                break
            best[:, v[first]] = new
        else:
            if len(first):
                raise RuntimeError("paths are still getting shorter")
        a, b = np.nonzero(np.isfinite(best))
        return pa.table({"grp": pa.repeat(pa.scalar(key[0].as_py(), pa.string()), len(a)), "root": root[a], "id": ids[b], name: best[a, b]})

    side = lambda t, *c: t.where("grp is not null").select("grp", *c).groupBy("grp")
    return side(edges.where("u is not null and v is not null and w is not null"), "u", "v", "w").cogroup(side(roots.where("root is not null"), "root")).applyInArrow(run, f"grp string, root long, id long, {name} double")


def hop_distances(edges: DataFrame, roots: DataFrame, max_rounds: int = 10_000) -> DataFrame:
    """``(grp, root, id, hops)`` from each root (``grp, root``); unreachable points have no row. A large group goes by frontiers."""
    def joined(e, r):
        return _frontiers(e, r, max_rounds)

    found = paths_by_size(edges.select("grp", "u", "v", F.lit(1.0).alias("w")), roots, "hops", joined)
    return found.withColumn("hops", F.col("hops").cast("int"))


def _frontiers(edges: DataFrame, roots: DataFrame, max_rounds: int) -> DataFrame:
    both = materialise(edges.select("grp", "u", "v").unionByName(edges.select("grp", F.col("v").alias("u"), F.col("u").alias("v"))), "both")
    seen = frontier = materialise(roots.select("grp", "root", F.col("root").alias("id"), F.lit(0).alias("hops")), "hops")
    for i in range(1, max_rounds):
        step = frontier.select("grp", "root", F.col("id").alias("u")).join(both, ["grp", "u"]).select("grp", "root", F.col("v").alias("id")).distinct()
        frontier = materialise(step.join(seen.select("grp", "root", "id"), ["grp", "root", "id"], "left_anti").withColumn("hops", F.lit(i)), "hops")
        if frontier.isEmpty():
            return seen
        seen = seen.unionByName(frontier)
        if i % 8 == 0:
            seen = materialise(seen, "hops")
    raise RuntimeError("the frontier is still moving")
