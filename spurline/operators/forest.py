"""Spanning forests by rounds of joins; each round at least halves the components that have an edge left."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spurline.operators.components import TASK_EDGES, Union, components, least_labels
from spurline.runtime import materialise


def _in_a_task(edges: DataFrame) -> DataFrame:
    """The forest of at most TASK_EDGES edges (``grp, a, b, o, u, v, w``), by one task."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = [r for batch in batches for r in zip(*(c.to_pylist() for c in batch.columns), strict=True)]
        sets, out = {}, []
        for grp, a, b, o, u, v, w in sorted(rows, key=lambda r: (r[3], r[4], r[5])):
            if sets.setdefault(grp, Union()).join(a, b):
                out.append((grp, u, v, w))
        columns = list(zip(*out, strict=True)) or [()] * 4
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, (pa.string(), pa.int64(), pa.int64(), pa.float64()), strict=True)], names=["grp", "u", "v", "w"])

    return edges.select("grp", "a", "b", "o", "u", "v", "w").coalesce(1).mapInArrow(run, "grp string, u long, v long, w double")


def kept_edges(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Places of the edges ``a``, ``b`` between vertices 0 to n - 1 that make their forest; of edges, the first go before the others."""
    left, many, taken = np.arange(len(a)), len(a), []
    while (apart := a != b).any():
        a, b, left = a[apart], b[apart], left[apart]
        best = np.full(n, many)
        for end in (a, b):  # edges are in order, so that of each component's the first is its best
            c, first = np.unique(end, return_index=True)
            best[c] = np.minimum(best[c], left[first])
        chosen = np.unique(best[best < many])
        taken.append(chosen)
        place = np.searchsorted(left, chosen)
        home = least_labels(n, a[place], b[place])
        a, b = home[a], home[b]
    return np.concatenate(taken) if taken else np.empty(0, int)


def _by_groups(edges: DataFrame) -> DataFrame:
    """Forests where each group, of at most TASK_EDGES edges (``grp, o, u, v, w``), is one task's work."""
    def run(key, t):
        u, v, o, w = (t.column(c).to_numpy() for c in "uvow")
        order = np.lexsort((v, u, o))
        u, v, w = u[order], v[order], w[order]
        ids, at = np.unique(np.concatenate([u, v]), return_inverse=True)
        kept = kept_edges(len(ids), at[: len(u)], at[len(u) :])
        return pa.table({"grp": pa.repeat(pa.scalar(key[0].as_py(), pa.string()), len(kept)), "u": u[kept], "v": v[kept], "w": w[kept]})

    tasks = int(edges.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return edges.select("grp", "o", "u", "v", "w").repartition(tasks, "grp").groupBy("grp").applyInArrow(run, "grp string, u long, v long, w double")


def spanning_forest(edges: DataFrame, maximum: bool = False, max_rounds: int = 64) -> DataFrame:
    """``(grp, u, v, w)``: the least (or greatest) spanning forest of ``edges`` (``grp, u, v, w``, u < v), unique under (w, u, v).

    Every round, each component takes its best edge, components joined by these are contracted, and of the edges between two
    components only the best stays. Once few edges are left one task ends it.
    """
    w = F.col("w").cast("double")
    left = materialise(edges.select("grp", "u", "v", w.alias("w"), (-w if maximum else w).alias("o"), F.col("u").alias("a"), F.col("v").alias("b")), "forest")
    found = []
    if left.count() > TASK_EDGES:
        fine = ["grp", "o", "u", "v", "w"]
        sizes = left.groupBy("grp").count()
        small = materialise(sizes.where(F.col("count") <= TASK_EDGES).select("grp"), "small-groups")
        if not small.isEmpty():
            found.append(_by_groups(left.select(*fine).join(small, "grp", "left_semi")))
            left = materialise(left.join(small, "grp", "left_anti"), "forest")
    for _ in range(max_rounds):
        if left.count() <= TASK_EDGES:
            found.append(_in_a_task(left))
            break
        ends = left.select("grp", F.col("a").alias("c"), "o", "u", "v", "w", "a", "b").unionByName(left.select("grp", F.col("b").alias("c"), "o", "u", "v", "w", "a", "b"))
        best = materialise(ends.groupBy("grp", "c").agg(F.min(F.struct("o", "u", "v", "w", "a", "b")).alias("e")).select("grp", "e.*").distinct(), "best")
        found.append(best.select("grp", "u", "v", "w"))
        home = materialise(components(best.select("grp", F.col("a").alias("u"), F.col("b").alias("v")), keys=("grp",)), "home")
        for end in "ab":
            left = left.join(home.select("grp", F.col("id").alias(end), F.col("component").alias("new")), ["grp", end], "left").withColumn(end, F.coalesce("new", end)).drop("new")
        left = left.where("a <> b").groupBy("grp", F.least("a", "b").alias("x"), F.greatest("a", "b").alias("y")).agg(F.min(F.struct("o", "u", "v", "w")).alias("e"))
        left = materialise(left.select("grp", "e.*", F.col("x").alias("a"), F.col("y").alias("b")), "forest")
    else:
        raise RuntimeError("the forest is still growing")
    out = found[0]
    for part in found[1:]:
        out = out.unionByName(part)
    return materialise(out, "forest")
