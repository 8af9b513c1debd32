"""Clusterings as DataFrame plans: one grouped kernel run for all groups, however many data sets they are."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spurline.operators import grown
from spurline.operators import kernels as K
from spurline.operators.blocks import _vectors as vectors
from spurline.operators.blocks import measurable
from spurline.operators.forest import kept_edges
from spurline.params import BranchParams
from spurline.runtime import materialise

RESULT = "grp string, id long, label int, strength double, cluster int, cluster_strength double, branch int, branch_strength double, is_center boolean"
#: Points of one group that the kernels take: their distance matrices are square. Larger groups go by joins, with the same rows.
KERNEL_POINTS = 4_000


def _points(pdf: pd.DataFrame) -> tuple[pd.DataFrame, np.ndarray]:
    if len(pdf) > KERNEL_POINTS:
        raise ValueError(f"a group of {len(pdf)} points is over the kernel's {KERNEL_POINTS}")
    pdf = pdf.sort_values("id", kind="stable")
    return pdf, np.array(pdf["x"].tolist(), float).reshape(len(pdf), -1)


def per_group(points: DataFrame, schema: str, make, metric: str = "euclidean") -> DataFrame:
    """``make(x, ids)`` returns columns for each group ``grp`` of ``points`` (``grp, id, x``); points without distances are left out.

    The number of partitions is given, so that few bytes with much work are not put together in one task at run time.
    """
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        grp = pdf["grp"].iloc[0]
        pdf, x = _points(pdf)
        return pd.DataFrame({"grp": grp, **make(x, pdf["id"].to_numpy())})

    return spread(points, metric).groupBy("grp").applyInPandas(run, schema)


def spread(points: DataFrame, metric: str = "euclidean") -> DataFrame:
    return measurable(points, metric).repartition(int(points.sparkSession.conf.get("spark.sql.shuffle.partitions")), "grp")


def by_size(points: DataFrame, limit: int, small, large) -> DataFrame:
    """``small`` of the groups with at most ``limit`` points, and ``large`` of the others, if there are any."""
    big = materialise(points.groupBy("grp").count().where(F.col("count") > limit).select("grp"), "large-groups")
    if big.isEmpty():
        return small(points)
    return small(points.join(big, "grp", "left_anti")).unionByName(large(points.join(big, "grp", "left_semi")))


def branch_clusters(points: DataFrame, p: BranchParams = BranchParams(), limit: int = KERNEL_POINTS, arrays: int = grown.TREE_POINTS) -> DataFrame:
    """RESULT rows: density clusters, branches inside them, and both combined. A group of up to ``limit`` points goes through one task and
    its matrices; one of up to ``arrays`` points through one task without matrices, where the settings allow it; a larger one through joins
    and bounded tasks (:mod:`spurline.plans.large`). All give the same rows."""
    def joined(rows: DataFrame) -> DataFrame:
        from spurline.plans import large

        return large.branches(large.density(rows, p), p)

    def more(rows: DataFrame) -> DataFrame:
        dims = rows.select(F.max(F.size("x"))).first()[0] or 1
        most = min(arrays, grown.TREE_NUMBERS // max(dims, 1)) if in_arrays(p) else 0
        return by_size(rows, most, lambda part: _branch_arrays(part, p), joined) if most > 0 else joined(rows)

    return by_size(points, limit, lambda rows: _branch_kernel(rows, p), more)


def in_arrays(p: BranchParams) -> bool:
    """Whether the branch pass needs no path and no mean along edges, so that of equal points the edges to one of them are enough."""
    return p.graph == "core" and p.eccentricity == "geometric" and p.smooth == 0 and p.central_labels == "centre"


def _branch_arrays(points: DataFrame, p: BranchParams) -> DataFrame:
    """:func:`_branch_kernel` without matrices."""
    def run(key, t):
        t = t.sort_by("id")
        ids, x = t.column("id").to_numpy(), vectors(t)
        got = {"id": ids, **K.combine(*branch_parts(x, p), p)}
        kinds = {f.split()[0]: {"string": pa.string(), "long": pa.int64(), "int": pa.int32(), "double": pa.float64(), "boolean": pa.bool_()}[f.split()[1]] for f in RESULT.split(", ")}
        return pa.table({"grp": pa.repeat(pa.scalar(key[0].as_py(), pa.string()), len(ids)), **{c: pa.array(got[c], kind) for c, kind in kinds.items() if c != "grp"}})

    return spread(points, p.metric).groupBy("grp").applyInArrow(run, RESULT)


def branch_parts(x: np.ndarray, p: BranchParams) -> tuple[K.Density, list[K.Branches]]:
    """The density model, without its matrices, and the branches of one group; see :func:`in_arrays`."""
    n, k = len(x), p.min_samples
    if n <= k:
        return K.Density(None, np.full(n, np.inf), None, np.empty((0, 3)), K.Tree(), np.full(n, -1), np.zeros(n)), []
    at = x / np.sqrt((x * x).sum(1))[:, None] if p.metric == "angular" else x
    u, v, w, core, a, b = grown.group_graph(at, k, p.metric, True)
    if p.with_tree_edges:
        a, b = np.concatenate([a, u]), np.concatenate([b, v])
    h = K.hierarchy(n, u, v, 1 / np.maximum(w, K.MIN_GAP), p.min_cluster_size)
    del u, v, w
    chosen = K.select(h, p.cluster_selection, p.allow_single_cluster, p.cluster_epsilon)
    label, strength = K.labels(h, chosen)
    if len(chosen) == 1 and h.parent[chosen[0]] < 0 and p.cluster_epsilon == 0:
        label = np.zeros(n, int)
    m, out, place = K.Density(None, core, None, np.empty((0, 3)), h, label, strength), [], np.empty(n, int)
    by = np.argsort(label, kind="stable")
    inside = (label[a] == label[b]) & (label[a] >= 0)
    a, b = a[inside], b[inside]
    edges = np.argsort(label[a], kind="stable")
    a, b = a[edges], b[edges]
    many = int(label.max(initial=-1)) + 1
    cuts, ends = np.searchsorted(label[by], np.arange(many + 1)), np.searchsorted(label[a], np.arange(many + 1))
    for c in range(many):
        members = by[cuts[c] : cuts[c + 1]]
        place[members] = np.arange(len(members))
        s, t = place[a[ends[c] : ends[c + 1]]], place[b[ends[c] : ends[c + 1]]]
        e = K.eccentricity(x, m, members, s, t, p)
        level = np.minimum(e[s], e[t])
        order = np.argsort(-level, kind="stable")
        kept = order[kept_edges(len(members), s[order], t[order])]
        tree = K.prune(K.hierarchy(len(members), s[kept], t[kept], level[kept], p.branch_size), p.branch_persistence)
        found = K.select(tree, p.branch_selection, False)
        out.append(K.Branches(members, e, s, t, tree, *K.labels(tree, found), len(found) > (1 if p.label_sides else 2)))
    return m, out


def _branch_kernel(points: DataFrame, p: BranchParams) -> DataFrame:
    def make(x, ids):
        m = K.density(x, p)
        return {"id": ids, **K.combine(m, K.branches(x, m, p), p)}

    return per_group(points, RESULT, make, p.metric)


def branches_by_signal(points: DataFrame, signal: DataFrame, p: BranchParams = BranchParams()) -> DataFrame:
    """RESULT rows where ``signal`` (``grp, id, value``) stands in place of the eccentricity: branches are its peaks (``direction`` "min":
    its valleys) in each cluster. Points without a value have the least of their cluster. Groups of any size."""
    from spurline.plans import large

    given = signal.withColumn("value", -F.col("value")) if p.direction == "min" else signal
    return large.branches(large.density(points, p), p, given=given)


def branch_grid(points: DataFrame, settings: list[BranchParams]) -> DataFrame:
    """RESULT rows for many settings, with their place in the list as ``setting``: settings that share the density
    parameters share one density run in each group."""
    def make(x, ids):
        known, out = {}, []
        for i, p in enumerate(settings):
            key = (p.min_samples, p.min_cluster_size, p.allow_single_cluster, p.cluster_selection, p.cluster_epsilon, p.metric)
            if key not in known:
                known[key] = K.density(x, p), {}
            m, common = known[key]
            out.append(pd.DataFrame({"id": ids, "setting": i, **K.combine(m, K.branches(x, m, p, common), p)}))
        return {c: pd.concat(out)[c].to_numpy() for c in out[0].columns}

    return per_group(points, RESULT + ", setting int", make)


def density_clusters(points: DataFrame, p: BranchParams = BranchParams(), limit: int = KERNEL_POINTS) -> DataFrame:
    """``(grp, id, label, strength, core)`` of groups of any size; see :func:`branch_clusters`."""
    def make(x, ids):
        m = K.density(x, p)
        return {"id": ids, "label": m.label, "strength": m.strength, "core": m.core}

    def joined(rows: DataFrame) -> DataFrame:
        from spurline.plans import large

        m = large.density(rows, p)
        return m.labels.join(m.core, ["grp", "id"], "left").select("grp", "id", "label", "strength", F.coalesce("core", F.lit(float("inf"))).alias("core"))

    return by_size(points, limit, lambda rows: per_group(rows, "grp string, id long, label int, strength double, core double", make, p.metric), joined)


def density_grid(points: DataFrame, settings: list[BranchParams]) -> DataFrame:
    """``(grp, id, label, setting)`` of the density clusters under many settings, with their place in the list."""
    def make(x, ids):
        parts = {(p.min_samples, p.metric): p for p in settings}
        parts = {k: K.metric_parts(x, p) for k, p in parts.items()}
        out = [pd.DataFrame({"id": ids, "label": K.density(x, p, parts[p.min_samples, p.metric]).label, "setting": i}) for i, p in enumerate(settings)]
        return {c: pd.concat(out)[c].to_numpy() for c in out[0].columns}

    return per_group(points, "grp string, id long, label int, setting int", make)


MEMBERSHIPS = "grp string, id long, cluster int, branch int, d_geo double, p double, weighted double"


def memberships(points: DataFrame, p: BranchParams = BranchParams(), limit: int = KERNEL_POINTS) -> DataFrame:
    """``(grp, id, cluster, branch, d_geo, p, weighted)``: softmax memberships of every point in each branch of its cluster. Groups of any
    size; see :func:`branch_clusters`."""
    def make(x, ids):
        m, out = K.density(x, p), []
        for c, b in enumerate(K.branches(x, m, p)):
            if b.split:
                soft = K.softmax_membership(b.d_geo, p.temperature)
                for k in range(len(soft)):
                    out.append(pd.DataFrame({"id": ids[b.members], "cluster": c, "branch": k, "d_geo": b.d_geo[k], "p": soft[k], "weighted": soft[k] * m.strength[b.members]}))
        got = pd.concat(out) if out else pd.DataFrame({k: [] for k in ("id", "cluster", "branch", "d_geo", "p", "weighted")})
        return {c: got[c].to_numpy() for c in got.columns}

    def joined(rows: DataFrame) -> DataFrame:
        from spurline.plans import large

        return large.memberships(large.density(rows, p), p)

    return by_size(points, limit, lambda rows: per_group(rows, MEMBERSHIPS, make, p.metric), joined)


TREES = "grp string, cluster int, node int, parent int, birth double, top double, size long, stability double, selected boolean, x0 double, x1 double"


def tree_rows(tree: K.Tree, chosen: list[int], cluster: int) -> pd.DataFrame:
    """A tree's nodes; x0 and x1 are an icicle's sides: a node is as wide as its points, or as its children beside each other."""
    n, kids, own = len(tree.parent), tree.children(), set(chosen)
    x0, x1, at = [0.0] * n, [0.0] * n, 0.0
    for root in (i for i, p in enumerate(tree.parent) if p < 0):
        todo = [(root, False)]
        while todo:  # children from left to right, then their parent
            i, done = todo.pop()
            if done:
                x1[i] = max(at, x0[i] + tree.size[i])
                at = x1[i]
            else:
                x0[i] = at
                todo.append((i, True))
                todo += [(k, False) for k in reversed(kids[i])]
    return pd.DataFrame({"cluster": cluster, "node": range(n), "parent": tree.parent, "birth": tree.birth, "top": tree.top(), "size": tree.size, "stability": tree.stability(), "selected": [i in own for i in range(n)], "x0": x0, "x1": x1})


def condensed(points: DataFrame, p: BranchParams = BranchParams(), which: str = "cluster", limit: int = KERNEL_POINTS) -> DataFrame:
    """Nodes of the cluster tree or of all branch trees: ``(grp, cluster, node, parent, birth, top, size, stability, selected, x0, x1)``;
    x0 and x1 are an icicle's sides, leaves beside each other by node. Groups of any size; their nodes may be numbered otherwise."""
    def make(x, ids):
        m = K.density(x, p)
        if which == "cluster":
            out = [tree_rows(m.hierarchy, K.select(m.hierarchy, p.cluster_selection, p.allow_single_cluster, p.cluster_epsilon), -1)]
        else:
            out = [tree_rows(b.tree, K.select(b.tree, p.branch_selection, False), c) for c, b in enumerate(K.branches(x, m, p))]
        got = pd.concat(out) if out else tree_rows(K.Tree(), [], -1)
        return {c: got[c].to_numpy() for c in got.columns}

    def joined(rows: DataFrame) -> DataFrame:
        from spurline.plans import large

        return large.condensed(large.density(rows, p), p, which)

    return by_size(points, limit, lambda rows: per_group(rows, TREES, make, p.metric), joined)


def single_linkage_cut(points: DataFrame, at: float) -> DataFrame:
    """The quadratic exact baseline: plain single linkage, cut at a distance; a component has its least id."""
    def make(x, ids):
        t = K.spanning_tree(K.distances(x)) if len(x) else np.empty((0, 3))
        root = list(range(len(ids)))

        def find(a):
            while root[a] != a:
                a = root[a]
            return a

        for u, v, w in t:
            if w <= at:
                a, b = sorted((find(int(u)), find(int(v))))
                root[b] = a
        return {"id": ids, "component": ids[[find(i) for i in range(len(ids))]]}

    return per_group(points, "grp string, id long, component long", make)


def adjusted_rand(df: DataFrame, truth: str, label: str, keys: tuple[str, ...] = ()) -> DataFrame:
    """Adjusted Rand index from the contingency table, a row for each combination of ``keys``; noise is one ordinary label.
    Two partitions that leave nothing to chance (all in one, or all apart) agree wholly: 1."""
    k = list(keys)
    cell = df.groupBy(*k, truth, label).agg(F.count(F.lit(1)).cast("double").alias("n"))
    pairs = lambda n: n * (n - 1) / 2
    key = k or [F.lit(0).alias("_k")]
    names = k or ["_k"]
    inner = cell.groupBy(*key).agg(F.sum(pairs(F.col("n"))).alias("both"), F.sum("n").alias("total"))
    side = lambda c, name: cell.groupBy(*key, c).agg(F.sum("n").alias("n")).groupBy(*names).agg(F.sum(pairs(F.col("n"))).alias(name))
    joined = inner.join(side(truth, "by_truth"), names).join(side(label, "by_label"), names)
    chance = F.col("by_truth") * F.col("by_label") / pairs(F.col("total"))
    most = (F.col("by_truth") + F.col("by_label")) / 2
    return joined.select(*k, F.when(most == chance, 1.0).otherwise((F.col("both") - chance) / (most - chance)).alias("ari"))


def centroid_spread(result: DataFrame, keys: tuple[str, ...], sample: str) -> DataFrame:
    """``(keys..., arm, spread)``: distance of every predicted centroid to the mean of those nearest to the same true centroid.

    ``result``: ``keys..., sample, arm, label, strength, px, py``; noise is no group. Centroids are weighted by strength.
    """
    k = list(keys)
    true = result.groupBy(*k, sample, "arm").agg(F.avg("px").alias("tx"), F.avg("py").alias("ty"))
    weight = F.sum("strength")
    found = result.where("label >= 0").groupBy(*k, sample, "label").agg((F.sum(F.col("px") * F.col("strength")) / weight).alias("cx"), (F.sum(F.col("py") * F.col("strength")) / weight).alias("cy"))
    gap = F.hypot(F.col("cx") - F.col("tx"), F.col("cy") - F.col("ty"))
    near = found.join(true, [*k, sample]).groupBy(*k, sample, "label", "cx", "cy").agg(F.min_by("arm", F.struct(gap, "arm")).alias("arm"))
    return arm_spread(near, keys)


def arm_spread(near: DataFrame, keys: tuple[str, ...]) -> DataFrame:
    """``(keys..., arm, spread)`` of centroids ``keys..., arm, cx, cy`` that know their nearest true one."""
    k = list(keys)
    mean = near.groupBy(*k, "arm").agg(F.avg("cx").alias("mx"), F.avg("cy").alias("my"))
    return near.join(mean, [*k, "arm"]).select(*k, "arm", F.hypot(F.col("cx") - F.col("mx"), F.col("cy") - F.col("my")).alias("spread"))
