"""Balanced blocks of nearby points, and exact neighbours between them, for groups of any size, density and dimension.

Points are split at quantiles of their widest axis, again and again, until a block holds a bounded number of them. The blocks'
boxes form a shallow tree; who may have something to do with whom is found by walking it with joins, level by level, and only pairs of
blocks that are near enough are looked at, by array kernels over bounded numbers of points.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from spurline.runtime import materialise

#: Points of a block at most; parts that a split makes; other blocks that one task of a block looks at.
BLOCK_POINTS, FAN, OTHERS = 1_024, 16, 64
#: Room for rounding when boxes are compared with distances.
SLACK = 1e-9


def _unit(x: F.Column) -> F.Column:
    return F.transform(x, lambda v: v / F.sqrt(F.aggregate(x, F.lit(0.0), lambda s, e: s + e * e)))


def measurable(points: DataFrame, metric: str = "euclidean") -> DataFrame:
    """``(grp, id, x)`` of the points that have distances: not those without id, with a null vector, with nulls or other than finite
    numbers in it, or, under angles, of length zero."""
    fine = F.forall("x", lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf")))
    out = points.select("grp", "id", F.col("x").cast("array<double>").alias("x")).where(F.col("id").isNotNull() & F.coalesce(fine, F.lit(False)))
    return out.where(F.exists("x", lambda v: v != 0)) if metric == "angular" else out


def embedded(points: DataFrame, metric: str) -> DataFrame:
    """:func:`measurable` points, as unit vectors for angles."""
    out = measurable(points, metric)
    return out.withColumn("x", _unit(F.col("x"))) if metric == "angular" else out


def split(points: DataFrame, size: int = BLOCK_POINTS) -> tuple[DataFrame, DataFrame]:
    """``(grp, id, x, block)``, and the tree of boxes ``(grp, node, parent, low, high, points, leaf)``.

    Cuts are approximate quantiles; where most points share one value, or all are equal, they are dealt by a hash of their ids, so no
    block stays larger than ``size`` but for repeated ids. Each round is one aggregation over the points of overfull blocks.
    """
    placed = materialise(points.select("grp", "id", "x", F.lit(1).cast("long").alias("block")), "blocks")
    first = placed.select(F.size("x").alias("d")).first()
    dims = first.d if first else 0
    for _ in range(14):  # sixteen to the fifteenth fits the number of a block
        ends = [f(F.get("x", F.lit(i))).alias(f"{n}{i}") for i in range(dims) for n, f in (("l", F.min), ("h", F.max))]
        count = placed.groupBy("grp", "block").agg(F.count(F.lit(1)).alias("n"), *ends).where(F.col("n") > size)
        spans = F.array(*[F.col(f"h{i}") - F.col(f"l{i}") for i in range(dims)]) if dims else F.array(F.lit(0.0))
        full = materialise(count.select("grp", "block", "n", (F.array_position(spans, F.array_max(spans)) - 1).cast("int").alias("axis")), "overfull")
        if full.isEmpty():
            break
        rows = placed.join(full, ["grp", "block"])
        cuts = rows.groupBy("grp", "block").agg(F.percentile_approx(F.expr("get(x, axis)"), [i / FAN for i in range(1, FAN)], 2000).alias("cuts"))
        rows = rows.join(cuts, ["grp", "block"])
        dealt = F.expr(f"pmod(xxhash64(id, block), least({FAN}L, ceil(n / {float(size)}D * 1.5D)))")
        child = F.when(F.get("cuts", F.lit(0)) == F.get("cuts", F.lit(FAN - 2)), dealt).otherwise(F.expr("size(filter(cuts, c -> c < get(x, axis)))"))
        rows = rows.select("grp", "id", "x", (F.col("block") * FAN + child).cast("long").alias("block"))
        placed = materialise(placed.join(full.select("grp", "block"), ["grp", "block"], "left_anti").select("grp", "id", "x", "block").unionByName(rows), "blocks")
    return placed, box_tree(placed, dims)


def box_tree(placed: DataFrame, dims: int) -> DataFrame:
    low, high = (F.array(*[f(F.get(c, F.lit(i))) for i in range(dims)]) if dims else F.array().cast("array<double>") for c, f in (("low", F.min), ("high", F.max)))
    ends = [F.array(*[f(F.get("x", F.lit(i))) for i in range(dims)]).alias(n) if dims else F.array().cast("array<double>").alias(n) for n, f in (("low", F.min), ("high", F.max))]
    level = materialise(placed.groupBy("grp", F.col("block").alias("node")).agg(*ends, F.count(F.lit(1)).alias("points")).withColumn("leaf", F.lit(True)), "boxes")
    parts = [level]
    while not (level := level.where("node > 1")).isEmpty():
        # Blocks lie at different depths: a parent gathers children of its own depth only, so the deepest go first.
        deep = materialise(level.withColumn("deep", F.floor(F.log(float(FAN), F.col("node") + 0.5))), "deep")
        most = deep.agg(F.max("deep")).first()[0]
        up = deep.where(F.col("deep") == most).groupBy("grp", F.floor(F.col("node") / FAN).cast("long").alias("node")).agg(low.alias("low"), high.alias("high"), F.sum("points").alias("points"))
        made = materialise(up.withColumn("leaf", F.lit(False)), "boxes")
        parts.append(made)
        level = deep.where(F.col("deep") < most).drop("deep").unionByName(made)
    out = parts[0]
    for part in parts[1:]:
        out = out.unionByName(part)
    return materialise(out.withColumn("parent", F.floor(F.col("node") / FAN).cast("long")), "boxes")


def norm(gaps: F.Column, metric: str) -> F.Column:
    """Length of a vector of gaps; under angles, of the chord as an angle."""
    if metric == "manhattan":
        return F.aggregate(gaps, F.lit(0.0), lambda s, g: s + g)
    if metric == "chebyshev":
        return F.coalesce(F.array_max(gaps), F.lit(0.0))
    chord = F.sqrt(F.aggregate(gaps, F.lit(0.0), lambda s, g: s + g * g))
    return 2.0 * F.asin(F.least(chord / 2.0, F.lit(1.0))) if metric == "angular" else chord


def nearest_gap(metric: str) -> F.Column:
    """The least distance of two boxes, ``low, high`` and ``a_low, a_high``."""
    return norm(F.expr("zip_with(zip_with(a_low, high, (p, q) -> p - q), zip_with(low, a_high, (p, q) -> p - q), (p, q) -> greatest(p, q, 0D))"), metric)


def farthest_gap(metric: str) -> F.Column:
    return norm(F.expr("zip_with(zip_with(a_high, low, (p, q) -> abs(p - q)), zip_with(high, a_low, (p, q) -> abs(p - q)), (p, q) -> greatest(p, q))"), metric)


def descend(asks: DataFrame, tree: DataFrame, metric: str, keep: F.Column | None = None) -> DataFrame:
    """``(grp, key, node)``: the leaves whose boxes are within ``radius`` of each ask (``grp, key, a_low, a_high, radius`` and more),
    among nodes that fulfil ``keep`` all the way down."""
    depth = tree.agg(F.max(F.floor(F.log(float(FAN), F.col("node") + 0.5)))).first()[0] or 0
    carried, found = asks.columns, None
    front = asks.join(tree.where("node = 1"), "grp")
    for i in range(int(depth) + 1):
        hit = (front if keep is None else front.where(keep)).where(nearest_gap(metric) * (1 - SLACK) <= F.col("radius"))
        ends = hit.where("leaf").select("grp", "key", "node")
        found = ends if found is None else found.unionByName(ends)
        if i < depth:
            inner = hit.where("not leaf").select(*carried, F.col("node").alias("above"))
            front = inner.join(tree.withColumnRenamed("parent", "above"), ["grp", "above"]).drop("above")
    return found


def pair_rows(pairs: DataFrame, placed: DataFrame, own: DataFrame, others: int = OTHERS) -> DataFrame:
    """Rows for the tasks of pairs of blocks ``(grp, key, node)``: to each part of a block's others, ``part``, come the rows of those others
    and, with ``own`` true, the block's own rows. ``placed`` and ``own`` have ``grp, block`` and the same columns."""
    parts = F.ceil(F.count(F.lit(1)).over(Window.partitionBy("grp", "key")) / others)
    dealt = materialise(pairs.withColumn("part", F.pmod(F.xxhash64("node"), parts).cast("int")), "pairs")
    far = dealt.select("grp", "key", "part", F.col("node").alias("block")).join(placed, ["grp", "block"]).drop("block").withColumn("own", F.lit(False))
    near = dealt.select("grp", F.col("key").alias("block"), "part").distinct().join(own, ["grp", "block"]).withColumnRenamed("block", "key").withColumn("own", F.lit(True))
    return far.unionByName(near)


def lengths(a: np.ndarray, b: np.ndarray, metric: str) -> np.ndarray:
    """Distances of all rows of ``a`` to all of ``b``, axis by axis, so that both orders of a pair and all engines agree."""
    out = np.zeros((len(a), len(b)))
    for i in range(a.shape[1]):
        gap = np.abs(a[:, i, None] - b[None, :, i])
        if metric in ("euclidean", "angular"):
            out += gap * gap
        elif metric == "manhattan":
            out += gap
        else:
            np.maximum(out, gap, out=out)
    if metric == "angular":  # of unit vectors, from the chord: small angles keep their digits
        return 2 * np.arcsin(np.minimum(np.sqrt(out) / 2, 1))
    return np.sqrt(out) if metric == "euclidean" else out


def squares(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, float]:
    """Squares of the Euclidean distances of all rows of ``a`` to all of ``b`` by a product of matrices, and how far they can be off."""
    mid = a.mean(0)
    a, b = a - mid, b - mid
    aa, bb = (a * a).sum(1), (b * b).sum(1)
    return aa[:, None] + bb - 2 * (a @ b.T), 2e-15 * (a.shape[1] + 8) * (aa.max(initial=0) + bb.max(initial=0))


def pair_lengths(a: np.ndarray, b: np.ndarray, metric: str) -> np.ndarray:
    """Distances of the rows of ``a`` to those of ``b`` beside them, the same numbers as those of :func:`lengths`; Euclidean or angles."""
    out = np.zeros(len(a))
    for i in range(a.shape[1]):
        gap = np.abs(a[:, i] - b[:, i])
        out += gap * gap
    return 2 * np.arcsin(np.minimum(np.sqrt(out) / 2, 1)) if metric == "angular" else np.sqrt(out)


def by_product(dims: int, metric: str) -> bool:
    """Whether a product of matrices should tell which pairs are measured."""
    return dims >= 8 and metric in ("euclidean", "angular")


def _vectors(t: pa.Table, name: str = "x") -> np.ndarray:
    c = t.column(name).combine_chunks()
    return c.flatten().to_numpy(zero_copy_only=False).reshape(len(c), -1)


def _tasks(df: DataFrame) -> int:
    return int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))


def _knn_of_groups(points: DataFrame, k: int, metric: str) -> DataFrame:
    """:func:`knn` where every group is one task's work."""
    def near(key, t):
        x, ids, us, vs, ds = _vectors(t), t.column("id").to_numpy(), [], [], []
        for at in range(0, len(x), 256):
            d = lengths(x[at : at + 256], x, metric)
            d[ids[at : at + 256, None] == ids[None, :]] = np.inf
            most = np.partition(d, k - 1, axis=1)[:, k - 1 : k] if d.shape[1] > k else np.full((len(d), 1), np.inf)
            u, v = np.nonzero((d <= most) & np.isfinite(d))
            us.append(ids[at : at + 256][u]), vs.append(ids[v]), ds.append(d[u, v])
        u, v, d = (np.concatenate(c) for c in (us, vs, ds))
        order = np.lexsort((d, u))
        u, v, d = u[order], v[order], d[order]
        # The rank of an entry is one more than the entries of its point that are nearer: the place of the first as near as it is.
        place, new = np.arange(len(u)), np.r_[True, u[1:] != u[:-1]][: len(u)]
        tie = np.r_[True, (u[1:] != u[:-1]) | (d[1:] != d[:-1])][: len(u)]
        rank = np.maximum.accumulate(np.where(tie, place, 0)) - np.maximum.accumulate(np.where(new, place, 0)) + 1
        fine = rank <= k
        return pa.table({"grp": pa.repeat(pa.scalar(key[0].as_py(), pa.string()), int(fine.sum())), "id": u[fine], "nbr": v[fine], "d": d[fine], "rank": pa.array(rank[fine], pa.int32())})

    return points.repartition(_tasks(points), "grp").groupBy("grp").applyInArrow(near, "grp string, id long, nbr long, d double, rank int")


def knn(points: DataFrame, k: int, metric: str = "euclidean", size: int = BLOCK_POINTS, placed: tuple[DataFrame, DataFrame] | None = None) -> DataFrame:
    """``(grp, id, nbr, d, rank)``: neighbours of rank up to ``k`` (ties share a rank), other than the point itself; exact.

    A block's own points bound how far any of its points has to look; then each block meets the blocks within that reach. Groups
    with ``k`` points or fewer return all that there are. Rows of repeated ids are one point each, and not neighbours of each other.
    """
    if placed is None:
        p = embedded(points, metric).where("grp is not null")
        big = materialise(p.groupBy("grp").count().where(F.col("count") > size).select("grp"), "large-groups")
        if big.isEmpty():
            return _knn_of_groups(p, k, metric)
        few = _knn_of_groups(p.join(big, "grp", "left_anti"), k, metric)
        return few.unionByName(knn(points, k, metric, size, split(p.join(big, "grp", "left_semi"), size)))
    placed, tree = placed

    def reach(key, t):
        x, far = _vectors(t), np.inf
        if len(x) > k:
            far = max(float(np.partition(lengths(x[i : i + 256], x, metric), k, axis=1)[:, k].max()) for i in range(0, len(x), 256))
        return pa.table({"grp": pa.array([key[0].as_py()], pa.string()), "block": [key[1].as_py()], "far": [far]})

    own = placed.repartition(_tasks(placed), "grp", "block").groupBy("grp", "block").applyInArrow(reach, "grp string, block long, far double")
    boxes = tree.where("leaf").select("grp", F.col("node").alias("block"), F.col("low").alias("a_low"), F.col("high").alias("a_high"))
    asks = materialise(own.join(boxes, ["grp", "block"]), "reach")
    short = asks.where(F.col("far") == float("inf"))  # too few points of its own: as far as the smallest box around it that has enough
    if not short.isEmpty():
        wide = tree.where(F.col("points") > k).select("grp", F.col("node").alias("above"), F.col("low").alias("a_low"), F.col("high").alias("a_high"), "low", "high").select("grp", "above", farthest_gap(metric).alias("wide"))
        above = short.select("grp", "block", F.explode(F.expr(f"transform(sequence(0, 15), i -> shiftright(block, {int(math.log2(FAN))} * i))")).alias("above")).where("above > 0").join(wide, ["grp", "above"]).groupBy("grp", "block").agg(F.min("wide").alias("wide"))
        asks = asks.join(above, ["grp", "block"], "left").withColumn("far", F.least("far", F.coalesce("wide", F.lit(float("inf"))))).drop("wide")
    pairs = descend(asks.select("grp", F.col("block").alias("key"), "a_low", "a_high", (F.col("far") * (1 + SLACK)).alias("radius")), tree, metric)
    fields = "grp string, id long, nbr long, d double"

    def near(key, t):
        mine = t.column("own").to_numpy(zero_copy_only=False).astype(bool)
        x, ids = _vectors(t), t.column("id").to_numpy()
        a, b, us, vs, ds = x[mine], x[~mine], [], [], []
        ia, ib = ids[mine], ids[~mine]
        for at in range(0, len(a), 256):
            if by_product(a.shape[1], metric) and len(b) > k:
                s, room = squares(a[at : at + 256], b)
                s[ia[at : at + 256, None] == ib[None, :]] = np.inf
                u, v = np.nonzero(s <= np.partition(s, k - 1, axis=1)[:, k - 1 : k] + 2 * room)
                other = ia[at + u] != ib[v]
                u, v = u[other], v[other]
                us.append(ia[at + u]), vs.append(ib[v]), ds.append(pair_lengths(a[at + u], b[v], metric))
                continue
            d = lengths(a[at : at + 256], b, metric)
            d[ia[at : at + 256, None] == ib[None, :]] = np.inf
            most = np.partition(d, k - 1, axis=1)[:, k - 1 : k] if d.shape[1] > k else np.full((len(d), 1), np.inf)
            u, v = np.nonzero((d <= most) & np.isfinite(d))
            us.append(ia[at : at + 256][u]), vs.append(ib[v]), ds.append(d[u, v])
        cat = lambda xs, kind: np.concatenate(xs) if xs else np.empty(0, kind)
        u = cat(us, np.int64)
        return pa.table({"grp": pa.array([key[0].as_py()] * len(u), pa.string()), "id": u, "nbr": cat(vs, np.int64), "d": cat(ds, float)})

    rows = pair_rows(pairs, placed, placed)
    found = rows.repartition(_tasks(rows), "grp", "key", "part").groupBy("grp", "key", "part").applyInArrow(near, fields)
    return found.withColumn("rank", F.rank().over(Window.partitionBy("grp", "id").orderBy("d"))).where(F.col("rank") <= k)
