"""Nearest roots and softmax memberships from path lengths, as aggregates and windows of any size."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def nearest_root(paths: DataFrame) -> DataFrame:
    """``(grp, id, root)`` of ``paths`` (``grp, root, id, d_geo``): the root with the shortest path, of equal ones the smallest."""
    return paths.groupBy("grp", "id").agg(F.min_by("root", F.struct("d_geo", "root")).alias("root"))


def softmax(paths: DataFrame, t: float = 1.0) -> DataFrame:
    """``(grp, id, root, p)``: softmax of 1 / (path length * t) over the roots that a point reaches. A point at a root belongs to it
    wholly; roots at one point share it equally."""
    if t <= 0:
        raise ValueError("the temperature must be positive")
    w = Window.partitionBy("grp", "id")
    c = F.when(F.col("d_geo") > 0, 1.0 / F.col("d_geo") / t)
    rows = paths.withColumn("c", c).withColumn("roots", F.count_if(F.col("d_geo") == 0).over(w)).withColumn("e", F.exp(F.col("c") - F.max("c").over(w)))
    p = F.when(F.col("roots") > 0, F.when(F.col("d_geo") == 0, 1.0 / F.col("roots")).otherwise(0.0)).otherwise(F.col("e") / F.sum("e").over(w))
    return rows.select("grp", "id", "root", p.alias("p"))
