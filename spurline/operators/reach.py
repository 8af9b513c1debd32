"""The spanning tree under mutual reachability for groups of any size: exact, without all pairs of a group.

The first edges need no search: among the k nearest of a point, one with a smaller core distance (or, of equal ones, a smaller id)
is as near under mutual reachability as any point can be, since no edge of a point is shorter than its core distance. That leaves
one component for each local minimum of the core distance. Then rounds: every component takes its shortest edge to another one. A
round knows an edge that each component can have, from the neighbour lists or between boxes; only blocks within that reach that are not
wholly in the same component are looked at. A total order of the edges (weight, smaller id, larger id) keeps the rounds free of cycles.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spurline.operators import blocks as B
from spurline.operators.components import components
from spurline.operators.neighbors import core_distance
from spurline.runtime import materialise


def pointer_edges(neighbours: DataFrame, core: DataFrame) -> DataFrame:
    """``(grp, u, v, w)``: each point's edge to that of its neighbours with the least core distance, where that is less than its own."""
    own = core.select("grp", "id", "core")
    other = core.select("grp", F.col("id").alias("nbr"), F.col("core").alias("c"))
    rows = neighbours.select("grp", "id", "nbr").join(own, ["grp", "id"]).join(other, ["grp", "nbr"])
    lower = rows.where((F.col("c") < F.col("core")) | ((F.col("c") == F.col("core")) & (F.col("nbr") < F.col("id"))))
    best = lower.groupBy("grp", "id").agg(F.min(F.struct("c", "nbr")).alias("p"), F.first("core").alias("w"))
    return best.select("grp", F.least("id", "p.nbr").alias("u"), F.greatest("id", "p.nbr").alias("v"), "w")


def _summary(members: DataFrame, tree: DataFrame) -> DataFrame:
    """The tree of boxes with the cores and components of the points below each node."""
    up = F.explode(F.expr("filter(transform(sequence(0, 15), i -> shiftright(block, 4 * i)), n -> n > 0)"))
    leaves = members.groupBy("grp", "block").agg(F.min("core").alias("c0"), F.max("core").alias("c1"), F.min("comp").alias("k0"), F.max("comp").alias("k1"))
    return tree.join(leaves.select("grp", up.alias("node"), "c0", "c1", "k0", "k1").groupBy("grp", "node").agg(F.min("c0").alias("c0"), F.max("c1").alias("c1"), F.min("k0").alias("k0"), F.max("k1").alias("k1")), ["grp", "node"])


def _reach_of_lonely(lonely: DataFrame, nodes: DataFrame, metric: str) -> DataFrame:
    """``(grp, comp, far)``: a length within which each component (``grp, comp, core, x`` of one point) has an edge: to the farthest corner
    of the best box that holds points of another, found level by level."""
    depth = nodes.agg(F.max(F.floor(F.log(float(B.FAN), F.col("node") + 0.5)))).first()[0] or 0
    front = lonely.select("grp", "comp", "core", F.col("x").alias("a_low"), F.col("x").alias("a_high")).join(nodes.where("node = 1"), "grp")
    best = None
    for i in range(int(depth) + 1):
        mixed = front.where("not (k0 = k1 and k0 = comp)").withColumn("upper", F.greatest(B.farthest_gap(metric), "c1", "core")).withColumn("lower", F.greatest(B.nearest_gap(metric), "c0", "core"))
        mixed = materialise(mixed, "lonely")
        here = mixed.groupBy("grp", "comp").agg(F.min("upper").alias("far"))
        best = here if best is None else materialise(best.unionByName(here).groupBy("grp", "comp").agg(F.min("far").alias("far")), "far")
        if i < depth:
            inner = mixed.join(best, ["grp", "comp"]).where("lower <= far and not leaf").select("grp", "comp", "core", "a_low", "a_high", F.col("node").alias("above"))
            front = inner.join(nodes.withColumnRenamed("parent", "above"), ["grp", "above"])
    return best


def _least(x: np.ndarray, core: np.ndarray, comp: np.ndarray, i: np.ndarray, b: np.ndarray, metric: str) -> tuple[np.ndarray, np.ndarray]:
    """For each of the points ``i`` the place in ``b`` of the first of those in other components with the least mutual reachability, and
    that; infinite where there are none."""
    if not B.by_product(x.shape[1], metric):
        w = np.maximum(np.maximum(B.lengths(x[i], x[b], metric), core[b][None, :]), core[i][:, None])
        w[comp[i][:, None] == comp[b][None, :]] = np.inf
        j = w.argmin(1)
        return j, w[np.arange(len(i)), j]
    angle = (lambda s: 2 * np.arcsin(np.minimum(np.sqrt(s) / 2, 1))) if metric == "angular" else np.sqrt
    s, room = B.squares(x[i], x[b])
    low = np.maximum(np.maximum(angle(np.maximum(s - room, 0)) * (1 - B.SLACK), core[b]), core[i][:, None])
    low[comp[i][:, None] == comp[b][None, :]] = np.inf
    at = low.argmin(1)
    bound = np.maximum(np.maximum(B.pair_lengths(x[i], x[b[at]], metric), core[b[at]]), core[i])  # of an edge that there is
    u, v = np.nonzero((low <= bound[:, None]) & np.isfinite(low))
    w = np.maximum(np.maximum(B.pair_lengths(x[i[u]], x[b[v]], metric), core[b[v]]), core[i[u]])
    order = np.lexsort((v, w, u))
    order = order[np.r_[True, u[order][1:] != u[order][:-1]][: len(u)]]
    j, least = np.zeros(len(i), int), np.full(len(i), np.inf)
    j[u[order]], least[u[order]] = v[order], w[order]
    return j, least


def _shortest(rows: DataFrame, metric: str) -> DataFrame:
    """``(grp, comp, w, u, v)``: of each task (``grp, key, part, own, id, x, core, comp, far``) the shortest edge that leaves each
    component, among points whose core distance is within its reach."""
    def run(key, t):
        mine = t.column("own").to_numpy(zero_copy_only=False).astype(bool)
        ids, core, comp, far = (t.column(c).to_numpy() for c in ("id", "core", "comp", "far"))
        x = B._vectors(t)
        a = np.flatnonzero(mine & (core <= far))
        b = np.flatnonzero(~mine & (core <= (far[a].max() if len(a) else -1)))
        b = b[np.argsort(ids[b], kind="stable")]  # of equal edges of a point, that to the smaller id comes first
        best: dict[int, tuple] = {}
        if len(b):
            for at in range(0, len(a), 256):
                i = a[at : at + 256]
                j, least = _least(x, core, comp, i, b, metric)
                for p in np.flatnonzero(least <= far[i]):
                    u, v = sorted((int(ids[i[p]]), int(ids[b[j[p]]])))
                    edge, c = (float(least[p]), u, v), int(comp[i[p]])
                    if c not in best or edge < best[c]:
                        best[c] = edge
        cs = list(best)
        return pa.table({"grp": pa.array([key[0].as_py()] * len(cs), pa.string()), "comp": pa.array(cs, pa.int64()), "w": pa.array([best[c][0] for c in cs], pa.float64()), "u": pa.array([best[c][1] for c in cs], pa.int64()), "v": pa.array([best[c][2] for c in cs], pa.int64())})

    return rows.repartition(B._tasks(rows), "grp", "key", "part").groupBy("grp", "key", "part").applyInArrow(run, "grp string, comp long, w double, u long, v long")


def reach_tree(points: DataFrame, k: int, metric: str = "euclidean", size: int = B.BLOCK_POINTS, max_rounds: int = 64) -> tuple[DataFrame, DataFrame, DataFrame]:
    """``(grp, u, v, w)``: the least spanning tree of each group's mutual reachabilities, with its core distances ``(grp, id, core)`` and
    neighbours. Ids are distinct within a group; points of groups with ``k`` points or fewer have no core distance and no edge.

    Ties are broken by ids, but any least tree has the same components at every level, which is all that hierarchies use.
    """
    placed, tree = B.split(B.embedded(points, metric), size)
    near = materialise(B.knn(points, k, metric, placed=(placed, tree)), "neighbours")
    core = materialise(core_distance(near, k), "core")
    pts = materialise(placed.join(core, ["grp", "id"]), "cored")
    first = materialise(pointer_edges(near, core), "pointers")
    found = [first]
    home = components(first.select("grp", "u", "v"), core.select("grp", "id"), keys=("grp",)).select("grp", "id", F.col("component").alias("comp"))
    members = materialise(pts.join(home, ["grp", "id"]), "members")
    ends = core.select("grp", "id", "core")
    listed = near.where("id < nbr").unionByName(near.where("id > nbr").select("grp", F.col("nbr").alias("id"), F.col("id").alias("nbr"), "d", "rank")).select("grp", F.col("id").alias("u"), F.col("nbr").alias("v"), "d").distinct()
    listed = listed.join(ends.withColumnsRenamed({"id": "u", "core": "a"}), ["grp", "u"]).join(ends.withColumnsRenamed({"id": "v", "core": "b"}), ["grp", "v"]).select("grp", "u", "v", F.greatest("d", "a", "b").alias("w"))
    for _ in range(max_rounds):
        live = members.groupBy("grp").agg((F.min("comp") != F.max("comp")).alias("more")).where("more").select("grp")
        members = materialise(members.join(live, "grp", "left_semi"), "members")
        if members.isEmpty():
            out = found[0]
            for part in found[1:]:
                out = out.unionByName(part)
            return materialise(out, "reach-tree"), core, near
        at = lambda e: members.select("grp", F.col("id").alias(e), F.col("comp").alias(f"k_{e}"))
        listed = materialise(listed.select("grp", "u", "v", "w").join(at("u"), ["grp", "u"]).join(at("v"), ["grp", "v"]).where("k_u <> k_v"), "listed")
        known = listed.select("grp", F.col("k_u").alias("comp"), "w").unionByName(listed.select("grp", F.col("k_v").alias("comp"), "w")).groupBy("grp", "comp").agg(F.min("w").alias("far"))
        nodes = materialise(_summary(members, tree), "nodes")
        deepest = members.groupBy("grp", "comp").agg(F.min(F.struct("core", "id", "x")).alias("p")).select("grp", "comp", "p.core", "p.x")
        lonely = materialise(deepest.join(known, ["grp", "comp"], "left_anti"), "lonely")
        far = materialise(known if lonely.isEmpty() else known.unionByName(_reach_of_lonely(lonely, nodes, metric)), "reach")
        rows = materialise(members.join(far, ["grp", "comp"]), "members")
        asks = rows.where("core <= far").groupBy("grp", F.col("block").alias("key")).agg((F.max("far") * (1 + B.SLACK)).alias("radius"))
        asks = asks.join(nodes.select("grp", F.col("node").alias("key"), F.col("low").alias("a_low"), F.col("high").alias("a_high"), F.when(F.col("k0") == F.col("k1"), F.col("k0")).alias("only")), ["grp", "key"])
        pairs = B.descend(asks, nodes, metric, F.expr("c0 <= radius and not coalesce(k0 = k1 and k0 = only, false)"))
        best = _shortest(B.pair_rows(pairs, rows, rows), metric).groupBy("grp", "comp").agg(F.min(F.struct("w", "u", "v")).alias("e"))
        picked = materialise(best.select("grp", "e.u", "e.v", "e.w").distinct(), "picked")
        found.append(picked)
        merged = components(picked.join(at("u"), ["grp", "u"]).join(at("v"), ["grp", "v"]).select("grp", F.col("k_u").alias("u"), F.col("k_v").alias("v")), keys=("grp",))
        members = materialise(members.join(merged.select("grp", F.col("id").alias("comp"), F.col("component").alias("new")), ["grp", "comp"], "left").withColumn("comp", F.coalesce("new", "comp")).drop("new"), "members")
    raise RuntimeError("the tree is still growing")
