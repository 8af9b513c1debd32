"""Functions for SQL: distances, mean vectors, and the whole method as a table function."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession

from spurline.operators import kernels as K
from spurline.params import BranchParams

_RESULT = "id long, label int, strength double, cluster int, cluster_strength double, branch int, branch_strength double, is_center boolean"


def vector_distance(a: pd.Series, b: pd.Series, metric: pd.Series) -> pd.Series:
    """The distance of two vectors under ``euclidean``, ``manhattan``, ``chebyshev`` or ``angular``; null where a vector is null, holds
    nulls, is of another length, or has no angle."""
    def one(x, y, m):
        if x is None or y is None or len(x) != len(y) or m is None:
            return None
        pair = np.array([x, y], float)
        if np.isnan(pair).any() or m == "angular" and not np.abs(pair).sum(1).all():
            return None
        return float(K.distances(pair, m)[0, 1])

    return pd.Series([one(*r) for r in zip(a, b, metric, strict=True)], dtype="float64")


def vector_mean(x: pd.Series) -> list[float]:
    """The mean of the vectors of a group that are not null."""
    rows = [v for v in x if v is not None]
    return np.mean(np.array(rows, float), axis=0).tolist() if rows else []


class Branches:
    """``branches(TABLE(points) PARTITION BY (grp), min_samples, min_cluster_size, min_branch_size)``: RESULT rows of one group, a row of
    ``points`` having ``id`` and ``x``. One group is one task, of at most as many points as the kernels take; points without distances are left out."""

    def __init__(self):
        self.rows: list[tuple[int, list[float]]] = []
        self.sizes = (5, 25, 25)

    def eval(self, row, min_samples: int, min_cluster_size: int, min_branch_size: int):
        from spurline.plans.clustering import KERNEL_POINTS

        self.sizes = (min_samples, min_cluster_size, min_branch_size)
        if row["id"] is not None and row["x"] is not None and all(v is not None and np.isfinite(v) for v in row["x"]):
            self.rows.append((row["id"], row["x"]))
        if len(self.rows) > KERNEL_POINTS:
            raise ValueError(f"over {KERNEL_POINTS} points in a group; use branch_clusters")

    def terminate(self) -> Iterator[tuple]:
        if not self.rows:
            return
        k, m_c, m_b = self.sizes
        p = BranchParams(min_samples=k, min_cluster_size=m_c, min_branch_size=m_b, allow_single_cluster=True, branch_selection="leaf")
        ids, x = zip(*sorted(self.rows), strict=True)
        x = np.array(x, float)
        m = K.density(x, p)
        got = K.combine(m, K.branches(x, m, p), p)
        for i, own in enumerate(ids):
            yield (own, *(got[c][i].item() for c in ("label", "strength", "cluster", "cluster_strength", "branch", "branch_strength", "is_center")))


def register(spark: SparkSession) -> None:
    """Make ``vector_distance``, ``vector_mean`` and ``branches`` known to SQL."""
    from pyspark.sql.functions import PandasUDFType, pandas_udf, udtf

    spark.udf.register("vector_distance", pandas_udf(vector_distance, "double"))
    spark.udf.register("vector_mean", pandas_udf(vector_mean, "array<double>", PandasUDFType.GROUPED_AGG))
    spark.udtf.register("branches", udtf(Branches, returnType=_RESULT))
