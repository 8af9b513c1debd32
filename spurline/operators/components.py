"""Connected components by alternating star contractions, for graphs of any size and shape."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spurline.runtime import materialise, merged

#: Edges that one task joins up in one go, instead of rounds of joins.
TASK_EDGES = 100_000


class Union:
    """Disjoint sets of anything hashable; a set's root is the first of it that was met, or what :meth:`join` made it."""

    def __init__(self):
        self.up: dict = {}

    def find(self, x):
        up = self.up
        up.setdefault(x, x)
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    def join(self, x, y) -> bool:
        """Whether x and y were apart; the smaller root stays."""
        x, y = self.find(x), self.find(y)
        if x == y:
            return False
        self.up[max(x, y)] = min(x, y)
        return True


def _in_a_task(graph: DataFrame, k: list[str]) -> DataFrame:
    """Components of at most TASK_EDGES edges, by one task."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sets: dict[tuple, Union] = {}
        for batch in batches:
            for *key, u, v in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                sets.setdefault(tuple(key), Union()).join(u, v)
        rows = [(*key, x, own.find(x)) for key, own in sets.items() for x in list(own.up)]
        columns = list(zip(*rows, strict=True)) or [()] * (len(k) + 2)
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, kinds, strict=True)], names=[*k, "id", "component"])

    from pyspark.sql.pandas.types import to_arrow_type

    rows = graph.select(*k, "u", "v")
    kinds = [to_arrow_type(f.dataType) for f in rows.schema]
    kinds[-1] = kinds[-2]
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields[: len(k)]), *(f"{n} {rows.schema['u'].dataType.simpleString()}" for n in ("id", "component"))])
    return rows.coalesce(1).mapInArrow(run, schema)


def least_labels(n: int, u: np.ndarray, v: np.ndarray) -> np.ndarray:
    """Of vertices 0 to n - 1, the least one that each can reach over the edges ``u``, ``v``."""
    label = np.arange(n)
    while True:
        a, b = label[u], label[v]
        apart = a != b
        if not apart.any():
            return label
        u, v, a, b = u[apart], v[apart], a[apart], b[apart]
        np.minimum.at(label, np.maximum(a, b), np.minimum(a, b))
        while (label != label[label]).any():
            label = label[label]


def _by_groups(graph: DataFrame, k: list[str]) -> DataFrame:
    """Components where each graph, of at most TASK_EDGES edges, is one task's work."""
    from pyspark.sql.pandas.types import to_arrow_type

    kinds = [to_arrow_type(graph.schema[c].dataType) for c in k]

    def run(key, t):
        ids, at = np.unique(np.concatenate([t.column(c).to_numpy() for c in "uv"]), return_inverse=True)
        home = ids[least_labels(len(ids), at[: t.num_rows], at[t.num_rows :])]
        own = {c: pa.repeat(pa.scalar(x.as_py(), kind), len(ids)) for c, x, kind in zip(k, key, kinds, strict=True)}
        return pa.table({**own, "id": ids, "component": home})

    schema = ", ".join([*(f"`{c}` {graph.schema[c].dataType.simpleString()}" for c in k), "id long, component long"])
    tasks = int(graph.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return graph.select(*k, "u", "v").repartition(tasks, *k).groupBy(*k).applyInArrow(run, schema)


def _symmetric(edges: DataFrame) -> DataFrame:
    return edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v"), *[c for c in edges.columns if c not in ("u", "v")]))


def _star(edges: DataFrame, keys: list[str], large: bool) -> DataFrame:
    """One contraction. ``large`` ties each larger neighbour of a node to the least of its neighbourhood;
    otherwise each smaller neighbour, and the node itself, are tied to the least."""
    both = _symmetric(edges) if large else edges.select(*keys, F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    least = both.groupBy(*keys, "u").agg(F.min("v").alias("m")).withColumn("m", F.least("u", "m"))
    tied = both.join(merged(least), [*keys, "u"])
    if large:
        out = tied.where(F.col("v") > F.col("u")).select(*keys, F.col("v").alias("u"), F.col("m").alias("v"))
    else:
        out = tied.select(*keys, F.col("v").alias("u"), F.col("m").alias("v")).unionByName(least.select(*keys, "u", F.col("m").alias("v")))
    return out.where("u <> v").distinct()


def components(edges: DataFrame, vertices: DataFrame | None = None, keys: tuple[str, ...] = (), max_rounds: int = 60) -> DataFrame:
    """``(keys..., id, component)``: each vertex with the least id it can reach.

    ``edges`` has ``u`` and ``v`` (and the ``keys`` that separate graphs); loops, repeats and null ends are
    ignored. With ``vertices`` (``keys..., id``) lonely vertices get a row too; without, only ends of edges.
    Graphs of at most TASK_EDGES edges are one task's work each; larger ones go by rounds.
    A round costs two aggregations and two joins; every round is written to the shared folder. The number of
    rounds grows with the logarithm of the longest path. No task ever holds a component of more than TASK_EDGES edges.
    """
    k = list(keys)
    graph = materialise(edges.where("u is not null and v is not null and u <> v").select(*k, F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "edges")
    few = graph.count() <= TASK_EDGES
    if not few and k and {graph.schema[c].dataType.simpleString() for c in "uv"} == {"bigint"}:
        big = materialise(graph.groupBy(*k).count().where(F.col("count") > TASK_EDGES).select(*k), "large-groups")
        if big.isEmpty():
            found = _by_groups(graph, k)
        else:
            found = _by_groups(graph.join(big, k, "left_anti"), k).unionByName(_rounds(graph.join(big, k, "left_semi"), k, max_rounds))
        return _with_lonely(found, vertices, k)
    return _with_lonely(_in_a_task(graph, k) if few else _rounds(graph, k, max_rounds), vertices, k)


def _rounds(graph: DataFrame, k: list[str], max_rounds: int) -> DataFrame:
    """Components of graphs of any size, by contractions."""
    seen = None
    for _ in range(max_rounds):
        now = graph.agg(F.count(F.lit(1)), F.sum(F.xxhash64(*k, "u", "v").cast("decimal(38,0)"))).first()
        if tuple(now) == seen or not now[0]:
            break
        seen = tuple(now)
        graph = materialise(_star(_star(graph, k, True), k, False), "star")
    else:
        raise RuntimeError(f"components are still moving after {max_rounds} rounds")
    roots = graph.select(*k, F.col("v").alias("id"), F.col("v").alias("component")).distinct()
    return graph.select(*k, F.col("u").alias("id"), F.col("v").alias("component")).unionByName(roots)


def _with_lonely(found: DataFrame, vertices: DataFrame | None, k: list[str]) -> DataFrame:
    if vertices is None:
        return found
    return vertices.select(*k, "id").join(merged(found), [*k, "id"], "left").withColumn("component", F.coalesce("component", "id"))
