"""Cost and accuracy measures of graphs, hierarchies and experiments."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from spurline.operators.neighbors import paths_by_size, squared
from spurline.runtime import materialise, merged

#: Pairs of one diagram that the matching takes.
DIAGRAM_PAIRS = 1_000


def graph_stats(edges: DataFrame, points: DataFrame) -> DataFrame:
    """``(grp, points, edges, degree, share, longest)``: edges (``grp, u, v, w``), mean degree, share of all pairs, largest weight."""
    n = points.groupBy("grp").agg(F.count(F.lit(1)).alias("points"))
    e = edges.groupBy("grp").agg(F.count(F.lit(1)).alias("edges"), F.max("w").alias("longest"))
    count = F.coalesce("edges", F.lit(0))
    return n.join(e, "grp", "left").select("grp", "points", count.alias("edges"), (2.0 * count / F.col("points")).alias("degree"), F.when(F.col("points") > 1, 2.0 * count / (F.col("points") * (F.col("points") - 1))).alias("share"), "longest")


def _ends(edges: DataFrame, *more: str) -> DataFrame:
    return edges.select("grp", F.col("u").alias("p"), *more).unionByName(edges.select("grp", F.col("v").alias("p"), *more))


def lipschitz(edges: DataFrame) -> DataFrame:
    """``(grp, constant)``: the largest change of ``level`` between edges that share an end, per unit of the ``w`` of one of them.

    Only the least and the greatest level at an end can give the largest change, so no pairs of edges are formed.
    Edges of weight zero take no part as the divisor.
    """
    range_ = _ends(edges, "level").groupBy("grp", "p").agg(F.min("level").alias("low"), F.max("level").alias("high"))
    at = _ends(edges.where("w > 0"), "level", "w").join(range_, ["grp", "p"])
    return at.groupBy("grp").agg(F.max(F.greatest(F.col("high") - F.col("level"), F.col("level") - F.col("low")) / F.col("w")).alias("constant"))


def path_lengths(edges: DataFrame, roots: DataFrame, max_rounds: int = 10_000) -> DataFrame:
    """``(grp, root, id, d_geo)``: shortest paths along ``edges`` (``grp, u, v, w``) from each of ``roots`` (``grp, root``).

    In a large group each round relaxes the edges of the points that came closer in the last one. Unreachable points have no row.
    """
    return paths_by_size(edges, roots, "d_geo", lambda e, r: _relaxed(e, r, max_rounds))


def _relaxed(edges: DataFrame, roots: DataFrame, max_rounds: int) -> DataFrame:
    both = materialise(edges.select("grp", "u", "v", "w").unionByName(edges.select("grp", F.col("v").alias("u"), F.col("u").alias("v"), "w")), "both")
    best = frontier = materialise(roots.select("grp", "root", F.col("root").alias("id"), F.lit(0.0).alias("d_geo")), "paths")
    for _ in range(max_rounds):
        step = frontier.select("grp", "root", F.col("id").alias("u"), "d_geo").join(both, ["grp", "u"])
        step = step.groupBy("grp", "root", F.col("v").alias("id")).agg(F.min(F.col("d_geo") + F.col("w")).alias("new"))
        both_sides = materialise(best.join(step, ["grp", "root", "id"], "full"), "paths")
        closer = F.col("new").isNotNull() & (F.col("d_geo").isNull() | (F.col("new") < F.col("d_geo")))
        frontier = both_sides.where(closer).select("grp", "root", "id", F.col("new").alias("d_geo"))
        best = both_sides.select("grp", "root", "id", F.least("d_geo", "new").alias("d_geo"))
        if frontier.isEmpty():
            return best
    raise RuntimeError("paths are still getting shorter")


def distortion(paths: DataFrame, points: DataFrame, at: tuple[float, ...] = (0.5, 0.95, 1.0)) -> DataFrame:
    """``(grp, pairs, q0, q1, ...)``: quantiles of path length over direct distance, for pairs at some distance."""
    x = points.select("grp", "id", "x")
    far = paths.join(merged(x), ["grp", "id"]).join(merged(x.select("grp", F.col("id").alias("root"), F.col("x").alias("y"))), ["grp", "root"])
    ratio = far.withColumn("d", F.sqrt(squared(F.col("x"), F.col("y")))).where("d > 0").select("grp", (F.col("d_geo") / F.col("d")).alias("ratio"))
    return ratio.groupBy("grp").agg(F.count(F.lit(1)).alias("pairs"), *[F.percentile("ratio", F.lit(q)).alias(f"q{i}") for i, q in enumerate(at)])


def scaling_fit(times: DataFrame, keys: tuple[str, ...], size: str = "n", seconds: str = "seconds", z: float = 1.96) -> DataFrame:
    """``(keys..., n, seconds, mean, slope, bend, fitted, low, high)``: least squares of ln seconds on x = ln size - mean and its square.

    ``slope`` is the power at the mean size, ``bend`` the coefficient of x squared; ``low`` and ``high`` bound the fitted
    seconds by ``z`` standard errors. Keys with fewer than four sizes have no band, with fewer than three no fit.
    """
    k = list(keys)
    t = times.select(*k, F.col(size).alias("n"), F.col(seconds).alias("seconds"), F.log(size).alias("lx"), F.log(seconds).alias("y"))
    mean = t.groupBy(*k).agg(F.avg("lx").alias("mean"))
    t = t.join(mean, k) if k else t.crossJoin(F.broadcast(mean))
    t = t.withColumn("x", F.col("lx") - F.col("mean"))
    x = F.col("x")
    sums = t.groupBy(*k).agg(F.count(F.lit(1)).alias("s0"), F.sum(x * x).alias("s2"), F.sum(x * x * x).alias("s3"), F.sum(x * x * x * x).alias("s4"), F.sum("y").alias("t0"), F.sum(x * F.col("y")).alias("t1"), F.sum(x * x * F.col("y")).alias("t2"))
    s0, s2, s3, s4, t0, t1, t2 = map(F.col, ("s0", "s2", "s3", "s4", "t0", "t1", "t2"))
    # The normal matrix is [[s0, 0, s2], [0, s2, s3], [s2, s3, s4]], as x has mean zero; these are its cofactors.
    c00, c01, c02, c11, c12, c22 = s2 * s4 - s3 * s3, s2 * s3, -s2 * s2, s0 * s4 - s2 * s2, -s0 * s3, s0 * s2
    det = s0 * c00 + s2 * c02
    sums = sums.withColumn("det", F.when((s0 >= 3) & (F.abs(det) > 1e-12), det))
    d = F.col("det")
    fit = sums.select(*k, "s0", *[(c / d).alias(n) for n, c in (("i00", c00), ("i01", c01), ("i02", c02), ("i11", c11), ("i12", c12), ("i22", c22))], ((c00 * t0 + c01 * t1 + c02 * t2) / d).alias("base"), ((c01 * t0 + c11 * t1 + c12 * t2) / d).alias("slope"), ((c02 * t0 + c12 * t1 + c22 * t2) / d).alias("bend"))
    t = (t.join(fit, k) if k else t.crossJoin(F.broadcast(fit))).withColumn("f", F.col("base") + F.col("slope") * x + F.col("bend") * x * x)
    w = Window.partitionBy(*k)
    gap = F.col("y") - F.col("f")
    t = t.withColumn("var", F.when(F.col("s0") > 3, F.sum(gap * gap).over(w) / (F.col("s0") - 3)))
    form = F.col("i00") + 2 * F.col("i01") * x + (2 * F.col("i02") + F.col("i11")) * x * x + 2 * F.col("i12") * x * x * x + F.col("i22") * x * x * x * x
    half = z * F.sqrt(F.col("var") * F.greatest(form, F.lit(0.0)))
    return t.select(*k, "n", "seconds", "mean", "slope", "bend", F.exp("f").alias("fitted"), F.exp(F.col("f") - half).alias("low"), F.exp(F.col("f") + half).alias("high"))


def select_params(scores: DataFrame, params: tuple[str, ...], ari: str = "ari", spread: str = "spread") -> DataFrame:
    """``(params..., ari, spread, place)``: settings by greatest mean ARI to two digits, then least mean spread, then the settings themselves."""
    means = scores.groupBy(*params).agg(F.avg(ari).alias("ari"), F.avg(spread).alias("spread"))
    return means.withColumn("place", F.row_number().over(Window.orderBy(F.desc(F.round("ari", 2)), "spread", *params)))


def tree_stats(tree: DataFrame) -> DataFrame:
    """``(grp, cluster, nodes, leaves, selected, longest, stability)`` of condensed trees."""
    kids = tree.select("grp", "cluster", F.col("parent").alias("node")).where("node >= 0").distinct().withColumn("inner", F.lit(True))
    return tree.join(kids, ["grp", "cluster", "node"], "left").groupBy("grp", "cluster").agg(F.count(F.lit(1)).alias("nodes"), F.count_if(F.col("inner").isNull()).alias("leaves"), F.count_if("selected").alias("selected"), F.max(F.col("top") - F.col("birth")).alias("longest"), F.sum("stability").alias("stability"))


def persistence_pairs(tree: DataFrame) -> DataFrame:
    """``(grp, birth, death)`` of every node of condensed trees, with the greatest level first met as birth."""
    return tree.select("grp", F.col("top").alias("birth"), F.col("birth").alias("death"))


def matching_distance(p: np.ndarray, q: np.ndarray) -> float:
    """Bottleneck distance of two diagrams (rows birth, death): the least worst move of a perfect matching, where any pair
    may also go to the diagonal."""
    n, m = len(p), len(q)
    if max(n, m) > DIAGRAM_PAIRS:
        raise ValueError(f"over {DIAGRAM_PAIRS} pairs in a diagram")
    if n + m == 0:
        return 0.0
    cost = np.zeros((n + m, n + m))
    own_p, own_q = (np.abs(r[:, 0] - r[:, 1]) / 2 if len(r) else np.empty(0) for r in (p, q))
    if n and m:
        cost[:n, :m] = np.abs(p[:, None, :] - q[None, :, :]).max(2)
    cost[:n, m:], cost[n:, :m] = own_p[:, None], own_q[None, :]
    levels = np.unique(cost)
    low, high = 0, len(levels) - 1
    while low < high:
        mid = (low + high) // 2
        low, high = (low, mid) if _perfect(cost <= levels[mid]) else (mid + 1, high)
    return float(levels[low])


def _perfect(ok: np.ndarray) -> bool:
    """Whether every row finds a column of its own, by augmenting paths found breadth first."""
    n = len(ok)
    row_of = np.full(n, -1)
    for start in range(n):
        came, todo, end = np.full(n, -1), [start], -1
        fresh = np.ones(n, bool)
        while todo and end < 0:
            r = todo.pop(0)
            for c in np.flatnonzero(ok[r] & fresh):
                fresh[c], came[c] = False, r
                if row_of[c] < 0:
                    end = c
                    break
                todo.append(int(row_of[c]))
        if end < 0:
            return False
        while end >= 0:
            r = came[end]
            before = np.flatnonzero(row_of == r)
            row_of[end] = r
            end = int(before[0]) if r != start else -1
            if end >= 0:
                row_of[end] = -1
    return True


def bottleneck(a: DataFrame, b: DataFrame) -> DataFrame:
    """``(grp, distance)`` between the diagrams (``grp, birth, death``) of each group; a side may lack a group."""
    def run(x: pd.DataFrame, y: pd.DataFrame) -> pd.DataFrame:
        grp = (x if len(x) else y)["grp"].iloc[0]
        return pd.DataFrame({"grp": [grp], "distance": [matching_distance(*(t[["birth", "death"]].to_numpy(float).reshape(-1, 2) for t in (x, y)))]})

    side = lambda t: t.select("grp", "birth", "death").groupBy("grp")
    return side(a).cogroup(side(b)).applyInPandas(run, "grp string, distance double")
