"""Neighbouring methods and preparations: radius graphs, slices, covers, level sets, skeletons, components, projections."""

from __future__ import annotations

from itertools import product

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spurline.operators.baselines import kmeans
from spurline.operators.components import components
from spurline.operators.forest import spanning_forest
from spurline.operators.neighbors import mutual_reach, squared
from spurline.runtime import fresh, materialise, merged

#: Centres that a skeleton compares with each other.
SKELETON_CENTRES = 2_000


def radius_pairs(points: DataFrame, reach: DataFrame, axes: int = 2) -> DataFrame:
    """``(grp, u, v, d)``, u < v: pairs within the ``reach`` (``grp, reach``, positive) of their group. A group of over PAIR_POINTS points
    goes by an equi-join on cells of that side over the first ``axes`` axes, a smaller one through one task."""
    from spurline.operators import neighbors

    rows = points.select("grp", "id", "x").where("grp is not null and id is not null and x is not null").join(reach, "grp")
    big = materialise(points.groupBy("grp").count().where(F.col("count") > neighbors.PAIR_POINTS).select("grp"), "large-groups")
    if big.isEmpty():
        return _pairs_of_groups(rows)
    p = rows.join(big, "grp", "left_semi")
    cell = [F.floor(F.get("x", F.lit(i)) / F.col("reach")).cast("long") for i in range(axes)]
    near = F.explode(F.array(*[F.array(*[c + o for c, o in zip(cell, off, strict=True)]) for off in product((-1, 0, 1), repeat=axes)]))
    asked = p.select("grp", F.col("id").alias("u"), F.col("x").alias("a"), "reach", near.alias("cell"))
    held = p.select("grp", F.col("id").alias("v"), F.col("x").alias("b"), F.array(*cell).alias("cell"))
    d = F.sqrt(squared(F.col("a"), F.col("b")))
    joined = asked.join(merged(held), ["grp", "cell"]).where("u < v").withColumn("d", d).where("d <= reach").select("grp", "u", "v", "d")
    return _pairs_of_groups(rows.join(big, "grp", "left_anti")).unionByName(joined)


def _pairs_of_groups(rows: DataFrame) -> DataFrame:
    """:func:`radius_pairs` of ``rows`` (``grp, id, x, reach``) where every group is one task's work."""
    import numpy as np
    import pyarrow as pa

    from spurline.operators.blocks import lengths

    def run(key, t):
        ids, x = t.column("id").to_numpy(), t.column("x").combine_chunks()
        x = x.flatten().to_numpy(zero_copy_only=False).reshape(len(x), -1)
        us, vs, ds = [], [], []
        for at in range(0, len(ids), 256):
            d = lengths(x[at : at + 256], x, "euclidean")
            u, v = np.nonzero((d <= t.column("reach")[0].as_py()) & (ids[at : at + 256, None] < ids[None, :]))
            us.append(ids[at : at + 256][u]), vs.append(ids[v]), ds.append(d[u, v])
        u, v, d = (np.concatenate(c) for c in (us, vs, ds))
        return pa.table({"grp": pa.repeat(pa.scalar(key[0].as_py(), pa.string()), len(u)), "u": u, "v": v, "d": d})

    tasks = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    typed = rows.select("grp", F.col("id").cast("long").alias("id"), F.col("x").cast("array<double>").alias("x"), F.col("reach").cast("double").alias("reach"))
    return typed.repartition(tasks, "grp").groupBy("grp").applyInArrow(run, "grp string, u long, v long, d double")


def graph_full(points: DataFrame, core: DataFrame, reach: DataFrame, axes: int = 2) -> DataFrame:
    """``(grp, u, v, d, w)``: all pairs whose mutual reachability is at most the group's ``reach``, the longest edge of its spanning tree."""
    edges = mutual_reach(radius_pairs(points, reach, axes), core).drop("larger")
    return edges.join(reach, "grp").where("w <= reach").drop("reach")


def slice_times(signal: DataFrame, edges: DataFrame, slope: float, offset: float) -> tuple[DataFrame, DataFrame]:
    """When points (``grp, id, t``) and edges (``grp, u, v, w``) appear along a line through the two-parameter filtration: at time t
    the radius is t and the threshold of the signal is ``offset - slope * t``."""
    if slope <= 0:
        raise ValueError("the slope must be positive")
    born = signal.select("grp", "id", F.greatest((offset - F.col("value")) / slope, F.lit(0.0)).alias("t"))
    a, b = (born.select("grp", F.col("id").alias(e), F.col("t").alias(f"t_{e}")) for e in "uv")
    return born, edges.join(merged(a), ["grp", "u"]).join(merged(b), ["grp", "v"]).select("grp", "u", "v", F.greatest("d", "t_u", "t_v").alias("w"))


def slice_components(signal: DataFrame, edges: DataFrame, slope: float, offset: float, times: list[float]) -> DataFrame:
    """``(grp, at, components)`` along the line: one spanning forest gives every time's count, points born less edges of the forest."""
    born, timed = slice_times(signal, edges, slope, offset)
    change = born.select("grp", "t", F.lit(1).alias("by")).unionByName(spanning_forest(timed).select("grp", F.col("w").alias("t"), F.lit(-1).alias("by")))
    at = F.explode(F.array(*[F.lit(float(t)) for t in times]))
    return change.select("grp", "t", "by", at.alias("at")).groupBy("grp", "at").agg(F.sum(F.when(F.col("t") <= F.col("at"), F.col("by")).otherwise(0)).alias("components"))


def nerve(lens: DataFrame, edges: DataFrame, bins: int, overlap: float) -> tuple[DataFrame, DataFrame]:
    """Cover and nerve: nodes ``(grp, bin, component, size)`` and links ``(grp, bin, component, other, shared)`` to the next bins.

    ``lens`` (``grp, id, value``) is cut into ``bins`` equal intervals, each widened by ``overlap`` (below 1) of its length in all; a node
    is a component of ``edges`` (``grp, u, v``) inside an interval, a link is shared points. Groups of one value have one bin.
    """
    if bins < 1 or not 0 <= overlap < 1:
        raise ValueError("at least one bin, and an overlap below 1")
    span = lens.groupBy("grp").agg(F.min("value").alias("low"), ((F.max("value") - F.min("value")) / bins).alias("wide"))
    at = (F.col("value") - F.col("low")) / F.col("wide")
    first, last = (F.least(F.greatest(F.floor(at + s * overlap / 2), F.lit(0)), F.lit(bins - 1)) for s in (-1, 1))
    inside = lens.join(span, "grp").select("grp", "id", F.explode(F.when(F.col("wide") > 0, F.sequence(first, last)).otherwise(F.array(F.lit(0).cast("long")))).alias("bin"))
    inside = materialise(inside, "cover")
    ends = edges.select("grp", "u", "v").join(merged(inside.withColumnRenamed("id", "u")), ["grp", "u"]).join(merged(inside.withColumnRenamed("id", "v")), ["grp", "bin", "v"])
    home = materialise(components(ends.select("grp", "bin", "u", "v"), inside, keys=("grp", "bin")), "nerve")
    nodes = home.groupBy("grp", "bin", "component").agg(F.count(F.lit(1)).alias("size"))
    other = home.select("grp", "id", (F.col("bin") - 1).alias("bin"), F.col("component").alias("other"))
    return nodes, home.join(merged(other), ["grp", "id", "bin"]).groupBy("grp", "bin", "component", "other").agg(F.count(F.lit(1)).alias("shared"))


def level_sets(signal: DataFrame, edges: DataFrame, width: float) -> tuple[DataFrame, DataFrame]:
    """Level-set graph: nodes ``(grp, band, component, size)`` of bands of the signal, links ``(grp, a, b, edges)`` between nodes, each
    named by its least point."""
    band = signal.select("grp", "id", F.floor(F.col("value") / width).alias("band"))
    a, b = (band.select("grp", F.col("id").alias(e), F.col("band").alias(f"band_{e}")) for e in "uv")
    placed = edges.select("grp", "u", "v").join(merged(a), ["grp", "u"]).join(merged(b), ["grp", "v"])
    home = materialise(components(placed.where("band_u = band_v").select("grp", F.col("band_u").alias("band"), "u", "v"), band, keys=("grp", "band")), "bands")
    at = lambda e, n: home.select("grp", F.col("id").alias(e), F.col("component").alias(n))
    links = placed.where("band_u <> band_v").join(merged(at("u", "cu")), ["grp", "u"]).join(merged(at("v", "cv")), ["grp", "v"])
    return home.groupBy("grp", "band", "component").agg(F.count(F.lit(1)).alias("size")), links.groupBy("grp", F.least("cu", "cv").alias("a"), F.greatest("cu", "cv").alias("b")).agg(F.count(F.lit(1)).alias("edges"))


def centroid_skeleton(points: DataFrame, centres: DataFrame, rounds: int = 10) -> DataFrame:
    """``(grp, u, v, w)``: the spanning tree of kMeans centres, as pairs of their labels. Groups have few centres; more raise."""
    found = kmeans(points, centres, rounds).join(points.select("grp", "id", "x"), ["grp", "id"])
    axis = found.select("grp", "label", F.posexplode("x").alias("axis", "value")).groupBy("grp", "label", "axis").agg(F.avg("value").alias("m"))
    c = materialise(axis.groupBy("grp", "label").agg(F.transform(F.array_sort(F.collect_list(F.struct("axis", "m"))), lambda s: s["m"]).alias("x")), "skeleton")
    most = c.groupBy("grp").count().agg(F.max("count")).first()[0] or 0
    if most > SKELETON_CENTRES:
        raise ValueError(f"{most} centres in a group; at most {SKELETON_CENTRES} are compared")
    pairs = c.select("grp", F.col("label").alias("u"), F.col("x").alias("a")).join(c.select("grp", F.col("label").alias("v"), F.col("x").alias("b")), "grp").where("u < v")
    return spanning_forest(pairs.select("grp", "u", "v", F.sqrt(squared(F.col("a"), F.col("b"))).alias("w")))


def dense_part(core: DataFrame, keep: float) -> DataFrame:
    """``(grp, id)``: the share ``keep`` of each group's points with the least core distances (and those that tie with the last)."""
    cut = core.groupBy("grp").agg(F.percentile("core", F.lit(keep)).alias("cut"))
    return core.join(cut, "grp").where("core <= cut").select("grp", "id")


def largest_component(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """``(grp, id)``: the points of each group's largest component, of equal ones that with the least point."""
    home = materialise(components(edges.select("grp", "u", "v"), vertices, keys=("grp",)), "home")
    sizes = home.groupBy("grp", "component").agg(F.count(F.lit(1)).alias("n"))
    best = sizes.groupBy("grp").agg(F.max_by("component", F.struct("n", -F.col("component"))).alias("component"))
    return home.join(best, ["grp", "component"], "left_semi").select("grp", "id")


def compare_labels(a: DataFrame, b: DataFrame) -> DataFrame:
    """``(grp, a, b, n, share_a, share_b)``: how the groups of two labelings (``grp, id, label``) overlap; points in one only count as -1 in the other."""
    both = a.select("grp", "id", F.col("label").alias("a")).join(b.select("grp", "id", F.col("label").alias("b")), ["grp", "id"], "full").na.fill(-1, ["a", "b"])
    cell = both.groupBy("grp", "a", "b").agg(F.count(F.lit(1)).alias("n"))
    side = lambda c: cell.groupBy("grp", c).agg(F.sum("n").alias(f"n_{c}"))
    return cell.join(side("a"), ["grp", "a"]).join(side("b"), ["grp", "b"]).select("grp", "a", "b", "n", (F.col("n") / F.col("n_a")).alias("share_a"), (F.col("n") / F.col("n_b")).alias("share_b"))


def label_adjacency(labels: DataFrame, edges: DataFrame) -> DataFrame:
    """``(grp, a, b, edges, level)``: groups that touch, over how many edges (``grp, u, v, level``), and the strongest level of those."""
    at = lambda e, n: labels.select("grp", F.col("id").alias(e), F.col("label").alias(n))
    e = edges.join(at("u", "a"), ["grp", "u"]).join(at("v", "b"), ["grp", "v"]).where("a <> b")
    return e.groupBy("grp", F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).agg(F.count(F.lit(1)).alias("edges"), F.max("level").alias("level"))


def center_batches(points: DataFrame, batch: str) -> DataFrame:
    """``points`` with the mean of their batch taken from ``x``; a null batch is a batch."""
    means = points.select("grp", batch, F.posexplode("x").alias("axis", "v")).groupBy("grp", batch, "axis").agg(F.avg("v").alias("m")).groupBy("grp", batch).agg(F.transform(F.array_sort(F.collect_list(F.struct("axis", "m"))), lambda s: s["m"]).alias("_m"))
    p, m = points.alias("p"), means.alias("m")
    joined = p.join(m, (F.col("p.grp") == F.col("m.grp")) & F.col(f"p.{batch}").eqNullSafe(F.col(f"m.{batch}")))
    return joined.select("p.*", "_m").withColumn("x", F.zip_with("x", "_m", lambda a, b: a - b)).drop("_m")


def pca(points: DataFrame, dims: int) -> DataFrame:
    """``points`` with ``x`` on its ``dims`` strongest principal components (all groups together)."""
    from pyspark.ml.feature import PCA
    from pyspark.ml.functions import array_to_vector, vector_to_array

    v, low = fresh("v", points), fresh("low", points)
    rows = points.withColumn(v, array_to_vector("x"))
    return PCA(k=dims, inputCol=v, outputCol=low).fit(rows).transform(rows).withColumn("x", vector_to_array(low)).drop(v, low)


def gaussian_mixture(points: DataFrame, k: int, seed: int = 1) -> DataFrame:
    """``points`` with ``label`` and ``p``, the probabilities of a mixture of ``k`` Gaussians."""
    from pyspark.ml.clustering import GaussianMixture
    from pyspark.ml.functions import array_to_vector, vector_to_array

    v, q = fresh("v", points), fresh("q", points)
    rows = points.withColumn(v, array_to_vector("x"))
    found = GaussianMixture(k=k, seed=seed, featuresCol=v, predictionCol="label", probabilityCol=q).fit(rows).transform(rows)
    return found.withColumn("p", vector_to_array(q)).drop(v, q)


#: Points of a group that a layout by forces takes.
LAYOUT_POINTS = 5_000


def layout(edges: DataFrame, points: DataFrame, dims: int = 2, repulsion: float = 1.0, rounds: int = 100) -> DataFrame:
    """``(grp, id, x)``: a layout of each group's graph (``grp, u, v``) from where ``points`` (``grp, id, x``) are: edges pull, all points
    push each other away by ``repulsion`` over the squared distance, less and less each round. One group is one task, of at most
    LAYOUT_POINTS points; larger raise. Points lie on their first ``dims`` axes at first, equal ones apart on a fixed spiral."""
    import numpy as np
    import pyarrow as pa

    def run(key, p, e):
        n = len(p)
        if n > LAYOUT_POINTS:
            raise ValueError(f"a layout of {n} points; at most {LAYOUT_POINTS}")
        if not n:
            return pa.table({"grp": pa.array([], pa.string()), "id": pa.array([], pa.int64()), "x": pa.array([], pa.list_(pa.float64()))})
        order = np.argsort(p.column("id").to_numpy(), kind="stable")
        ids = p.column("id").to_numpy()[order]
        raw = p.column("x").combine_chunks()
        raw = raw.flatten().to_numpy(zero_copy_only=False).reshape(n, -1)[order, :dims]
        x = np.zeros((n, dims))
        x[:, : raw.shape[1]] = raw
        x = (x - x.mean(0)) / max(float(x.std()), 1e-12)
        angle = np.arange(n) * 2.399963229728653  # the golden angle
        x[:, 0] += 1e-3 * np.cos(angle)
        x[:, -1] += 1e-3 * np.sin(angle)
        ends = [e.column(c).to_numpy() for c in "uv"]
        u, v = (np.searchsorted(ids, c, side="right") - 1 for c in ends)
        inside = (u >= 0) & (v >= 0) & (ids[u] == ends[0]) & (ids[v] == ends[1])
        u, v = u[inside], v[inside]
        for r in range(rounds):
            force = np.zeros_like(x)
            for at in range(0, n, 512):
                gaps = [x[at : at + 512, None, i] - x[None, :, i] for i in range(dims)]
                far = sum(g * g for g in gaps)
                push = np.divide(repulsion / n, np.maximum(far, 1e-4, out=far), out=far)
                for i, g in enumerate(gaps):
                    force[at : at + 512, i] = np.einsum("ij,ij->i", g, push)
            pull = x[v] - x[u]
            for i in range(dims):
                force[:, i] += np.bincount(u, pull[:, i], n) - np.bincount(v, pull[:, i], n)
            step = 0.1 * (1 - r / rounds)
            size = np.linalg.norm(force, axis=1, keepdims=True)
            x += step * force / np.maximum(size, 1.0)
        return pa.table({"grp": pa.repeat(pa.scalar(key[0].as_py(), pa.string()), n), "id": ids, "x": pa.ListArray.from_arrays(pa.array(np.arange(0, n * dims + 1, dims), pa.int32()), x.ravel())})

    side = lambda df, *c: df.select("grp", *c).groupBy("grp")
    return side(points, "id", "x").cogroup(side(edges.where("u is not null and v is not null"), "u", "v")).applyInArrow(run, "grp string, id long, x array<double>")


def sample_stability(a: DataFrame, b: DataFrame) -> DataFrame:
    """``(grp, points, ari)``: how alike two labelled samples of one shape are (``grp, id, x, label``): every point of ``a`` takes the label
    of the point of ``b`` nearest to it (ties to the smaller id), and the labels are compared. Both sides of a group go to one task."""
    import numpy as np
    import pandas as pd

    from spurline.plans.clustering import KERNEL_POINTS, adjusted_rand

    def run(p: pd.DataFrame, q: pd.DataFrame) -> pd.DataFrame:
        if max(len(p), len(q)) > KERNEL_POINTS:
            raise ValueError(f"samples of over {KERNEL_POINTS} points")
        if not len(p) or not len(q):
            return pd.DataFrame({"grp": pd.Series([], dtype=object), "own": pd.Series([], dtype="int32"), "other": pd.Series([], dtype="int32")})
        q = q.sort_values("id", kind="stable")
        x, y = (np.array(t["x"].tolist(), float) for t in (p, q))
        near = [int(((y - v) ** 2).sum(1).argmin()) for v in x]
        return pd.DataFrame({"grp": p["grp"].iloc[0], "own": p["label"].to_numpy(), "other": q["label"].to_numpy()[near]})

    side = lambda df: df.select("grp", "id", "x", "label").groupBy("grp")
    both = materialise(side(a).cogroup(side(b)).applyInPandas(run, "grp string, own int, other int"), "samples")
    return both.groupBy("grp").agg(F.count(F.lit(1)).alias("points")).join(adjusted_rand(both, "own", "other", ("grp",)), "grp")
