"""The methods that the branch-aware clustering is compared with."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spurline.operators import neighbors
from spurline.operators.blocks import lengths
from spurline.operators.components import components
from spurline.operators.neighbors import squared
from spurline.runtime import fresh, materialise, merged


def kmeans(points: DataFrame, centres: DataFrame, rounds: int = 10) -> DataFrame:
    """``(grp, id, label)`` after ``rounds`` of Lloyd's steps from ``centres`` (``grp, label, c array<double>``); ties to the smaller label.

    A centre that loses all points is gone. Centres are k rows a group; each step is one join on ``grp`` and two aggregations.
    """
    base = materialise(points.select("grp", "id", "x"), "points")
    for i in range(rounds + 1):
        near = base.join(centres, "grp").groupBy("grp", "id").agg(F.min_by("label", F.struct(squared(F.col("x"), F.col("c")), F.col("label"))).alias("label"))
        if i == rounds:
            return near
        parts = base.join(near, ["grp", "id"]).select("grp", "label", F.posexplode("x").alias("axis", "value"))
        means = parts.groupBy("grp", "label", "axis").agg(F.avg("value").alias("m"))
        centres = materialise(means.groupBy("grp", "label").agg(F.transform(F.array_sort(F.collect_list(F.struct("axis", "m"))), lambda s: s["m"]).alias("c")), "centres")
    return near


def kmeans_ml(points: DataFrame, k: int, seed: int = 1) -> DataFrame:
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    v = fresh("v", points)
    rows = points.withColumn(v, array_to_vector("x"))
    return KMeans(k=k, seed=seed, featuresCol=v, predictionCol="label").fit(rows).transform(rows).drop(v)


def _sums_of_groups(points: DataFrame) -> DataFrame:
    """:func:`distance_sums` where every group is one task's work."""
    def run(key, t):
        x = t.column("x").combine_chunks()
        x = x.flatten().to_numpy(zero_copy_only=False).reshape(len(x), -1)
        return pa.table({"grp": pa.repeat(pa.scalar(key[0].as_py(), pa.string()), len(x)), "id": t.column("id"), "value": lengths(x, x, "euclidean").sum(1)})

    tasks = int(points.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return points.select("grp", "id", "x").where("grp is not null and x is not null").repartition(tasks, "grp").groupBy("grp").applyInArrow(run, "grp string, id long, value double")


def distance_sums(points: DataFrame, against: DataFrame | None = None) -> DataFrame:
    """``(grp, id, value)``: sum of distances to all points of the group, or to ``against``, a sample of it that
    bounds the work. Without it the work is quadratic in a group, which is this baseline's nature: use it on groups of some thousands."""
    if against is None:
        big = materialise(points.groupBy("grp").count().where(F.col("count") > neighbors.PAIR_POINTS).select("grp"), "large-groups")
        if big.isEmpty():
            return _sums_of_groups(points)
        return _sums_of_groups(points.join(big, "grp", "left_anti")).unionByName(distance_sums(points.join(big, "grp", "left_semi"), points.join(big, "grp", "left_semi")))
    other = (against if against is not None else points).select("grp", F.col("x").alias("y"))
    return points.select("grp", "id", "x").join(other, "grp").groupBy("grp", "id").agg(F.sum(F.sqrt(squared(F.col("x"), F.col("y")))).alias("value"))


def core_removal(signal: DataFrame, edges: DataFrame, threshold: float, radius: float) -> DataFrame:
    """``(grp, id, component)``: points whose signal is at least ``threshold``, joined by edges (``grp, u, v, d``) up to ``radius``."""
    kept = signal.where(F.col("value") >= threshold).select("grp", "id")
    inside = edges.where(F.col("d") <= radius)
    for end in "uv":
        inside = inside.join(merged(kept.withColumnRenamed("id", end)), ["grp", end], "left_semi")
    return components(inside.select("grp", "u", "v"), kept, keys=("grp",))


def component_grid(signal: DataFrame, edges: DataFrame, thresholds: list[float], radii: list[float]) -> DataFrame:
    """``(grp, e_index, r_index, components)``: two-parameter filtration, all grid cells in one keyed run."""
    cells = [(i, j, float(e), float(r)) for i, e in enumerate(thresholds) for j, r in enumerate(radii)]
    grid = F.explode(F.array(*[F.struct(F.lit(i).alias("e_index"), F.lit(j).alias("r_index"), F.lit(e).alias("e"), F.lit(r).alias("r")) for i, j, e, r in cells]))
    at = ["grp", "e_index", "r_index"]
    kept = signal.select("grp", "id", "value", grid.alias("g")).where("value >= g.e").select("grp", "g.e_index", "g.r_index", "id")
    inside = edges.select("grp", "u", "v", "d", grid.alias("g")).where("d <= g.r").select("grp", "g.e_index", "g.r_index", "u", "v")
    for end in "uv":
        inside = inside.join(merged(kept.withColumnRenamed("id", end)), [*at, end], "left_semi")
    return components(inside, kept, keys=tuple(at)).groupBy(*at).agg(F.countDistinct("component").alias("components"))
