"""The spanning tree under mutual reachability of one group of up to a million points, as one task's work in arrays: exact, without all pairs.

Equal points count as one with their number, so copies cost nothing. The others lie in small boxes; a point's neighbours are looked for
in boxes within what is known so far. Components then take their shortest edges in rounds. An edge is known to be the shortest if no point
could have a shorter one: each point keeps a length below which it has no edge to leave by, which only points that could still matter look
beyond. The greatest component of a round waits for the others, so its many inner points never look.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spurline.operators import blocks as B
from spurline.operators.components import least_labels
from spurline.operators.reach import reach_tree
from spurline.runtime import materialise

#: Points, and numbers in their vectors, of a group that one task takes; points of a box; points that are looked at together;
#: points beyond the nearest that are measured exactly; points outside the greatest component, and points that bound how far they look.
TREE_POINTS, TREE_NUMBERS, LEAF, BATCH, SPARE, MANY, SOME = 1_000_000, 16_000_000, 256, 8_192, 6, 50_000, 4_096


def _split(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """An order of the points, and where boxes begin and end in it."""
    order, ends, todo = np.arange(len(x)), [0], [(0, len(x))]
    while todo:
        a, b = todo.pop()
        if b - a <= LEAF:
            ends.append(b)
            continue
        part, mid = order[a:b], (b - a) // 2
        at = x[part]
        axis = int((at.max(0) - at.min(0)).argmax())
        order[a:b] = part[np.argpartition(at[:, axis], mid)]
        todo += [(a + mid, b), (a, a + mid)]
    return order, np.array(ends)


class _Boxes:
    def __init__(self, x: np.ndarray, ends: np.ndarray, metric: str):
        self.x, self.ends, self.metric = x, ends, metric
        self.low, self.high = np.minimum.reduceat(x, ends[:-1]), np.maximum.reduceat(x, ends[:-1])

    def gap(self, a: np.ndarray, low: np.ndarray, high: np.ndarray) -> np.ndarray:
        """The least distance of the points ``a`` to each of the boxes, with room for rounding; points are boxes too."""
        g = np.maximum(np.maximum(low - a.max(0), a.min(0) - high), 0)
        if self.metric == "manhattan":
            d = g.sum(1)
        elif self.metric == "chebyshev":
            d = g.max(1, initial=0)
        else:
            d = np.sqrt((g * g).sum(1))
        return (2 * np.arcsin(np.minimum(d / 2, 1)) if self.metric == "angular" else d) * (1 - B.SLACK)

    def members(self, leaves: np.ndarray) -> np.ndarray:
        n = self.ends[leaves + 1] - self.ends[leaves]
        return np.arange(n.sum()) + np.repeat(self.ends[leaves] - (np.cumsum(n) - n), n)


def _nearest(box: _Boxes, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Places and distances of the ``k`` nearest others of every point, nearest first."""
    x, n = box.x, len(box.x)
    nbr, dist = np.empty((n, k), np.int32), np.empty((n, k))

    def exact(rows: np.ndarray, others: np.ndarray) -> None:
        d = B.lengths(x[rows], x[others], box.metric)
        d[rows[:, None] == others[None, :]] = np.inf
        near = np.argpartition(d, k - 1, axis=1)[:, :k] if d.shape[1] > k else np.broadcast_to(np.arange(d.shape[1]), d.shape)
        d = np.take_along_axis(d, near, 1)
        order = np.argsort(d, axis=1, kind="stable")
        nbr[rows], dist[rows] = others[np.take_along_axis(near, order, 1)], np.take_along_axis(d, order, 1)

    def take(rows: np.ndarray, others: np.ndarray) -> np.ndarray:
        """Squares by a product of matrices tell which points come into question, differences how far they are; rows of which the
        product can't tell go by differences alone."""
        if box.metric not in ("euclidean", "angular") or len(others) <= 4 * (k + SPARE):
            exact(rows, others)
            return dist[rows, -1]
        mid = x[rows].mean(0)
        a, b = x[rows] - mid, x[others] - mid
        aa, bb = (a * a).sum(1), (b * b).sum(1)
        s = aa[:, None] + bb - 2 * (a @ b.T)
        room = 1e-15 * (x.shape[1] + 8) * (aa.max() + bb.max())
        s[rows[:, None] == others[None, :]] = np.inf
        near = np.argpartition(s, k + SPARE, axis=1)[:, : k + SPARE + 1]
        least = np.take_along_axis(s, near[:, -1:], 1)[:, 0] - room  # none of the others is nearer
        near = near[:, :-1]
        d = np.zeros(near.shape)
        for axis in x.T:
            gap = axis[rows][:, None] - axis[others[near]]
            d += gap * gap
        order = np.argsort(d, axis=1, kind="stable")[:, :k]
        square = np.take_along_axis(d, order, 1)
        d = np.sqrt(square)
        nbr[rows], dist[rows] = others[np.take_along_axis(near, order, 1)], 2 * np.arcsin(np.minimum(d / 2, 1)) if box.metric == "angular" else d
        unsure = np.flatnonzero(~(square[:, -1] < least))
        if len(unsure):
            exact(rows[unsure], others)
        return dist[rows, -1]

    for i in range(len(box.ends) - 1):
        rows = np.arange(box.ends[i], box.ends[i + 1])
        gaps = box.gap(x[rows], box.low, box.high)
        by = np.argsort(gaps, kind="stable")
        few = int(np.searchsorted(np.cumsum((box.ends[1:] - box.ends[:-1])[by]), 2 * k + LEAF)) + 1
        if few >= len(by):
            take(rows, np.arange(n))
            continue
        far = take(rows, box.members(by[:few]))
        for part in np.array_split(np.argsort(far), 4):
            if len(part):
                a, most = rows[part], far[part].max()
                others = box.members(np.flatnonzero(box.gap(x[a], box.low, box.high) <= most))
                take(a, others[box.gap(x[a], x[others], x[others]) <= most])
    return nbr, dist


def _edges_out(box: _Boxes, core: np.ndarray, comp: np.ndarray, asks: np.ndarray, far: np.ndarray, below: np.ndarray) -> list[tuple]:
    """Edges ``(u, v, w)`` by which the points ``asks`` leave their components within ``far``, which falls as shorter ones are found;
    ``below`` is told how far each has looked in vain."""
    x, out = box.x, []
    first = box.ends[:-1]
    c0, k0, k1 = np.minimum.reduceat(core, first), np.minimum.reduceat(comp, first), np.maximum.reduceat(comp, first)
    leaf = np.searchsorted(box.ends, asks, side="right") - 1
    for p in np.split(asks, np.flatnonzero(np.diff(leaf)) + 1) if len(asks) else []:
        own = comp[p]
        single = own[0] if (own == own[0]).all() else -1
        gaps = np.maximum(box.gap(x[p], box.low, box.high), c0)
        hit = np.flatnonzero((gaps <= far[own].max()) & ~((k0 == k1) & (k0 == single)))
        hit = hit[np.argsort(gaps[hit], kind="stable")]
        best, at, step = np.full(len(p), np.inf), 0, 2
        while at < len(hit) and gaps[hit[at]] <= (most := far[own].max()):
            q = box.members(hit[at : at + step])
            at, step = at + step, min(2 * step, max(1, BATCH // LEAF))
            q = q[(core[q] <= most) & (comp[q] != single)]
            q = q[box.gap(x[p], x[q], x[q]) <= most]
            if not len(q):
                continue
            w = np.maximum(np.maximum(B.lengths(x[p], x[q], box.metric), core[q]), core[p][:, None])
            w[own[:, None] == comp[q]] = np.inf
            j = w.argmin(1)
            least = w[np.arange(len(p)), j]
            best = np.minimum(best, least)
            found = np.flatnonzero(least <= far[own])
            found = found[np.isfinite(least[found])]
            out.append((p[found], q[j[found]], least[found]))
            np.minimum.at(far, own[found], least[found])
        below[p] = np.maximum(below[p], np.minimum(best, far[own]))
    return out


def _grow(box: _Boxes, core: np.ndarray, u: np.ndarray, v: np.ndarray, w: np.ndarray, below: np.ndarray, comp: np.ndarray | None = None, most: float = np.inf) -> tuple[np.ndarray, ...]:
    """The least spanning tree, from edges that are known; no point has an unknown one shorter than its ``below``. ``comp`` are components
    that are already joined, by their edges that are not given again; of edges longer than ``most`` there are none."""
    n, taken = len(core), []
    comp = np.arange(n) if comp is None else comp
    while True:
        _, comp = np.unique(comp, return_inverse=True)
        many = int(comp.max(initial=-1)) + 1
        if many <= 1:
            return tuple(np.concatenate(c) for c in zip(*taken, strict=True)) if taken else (u[:0], v[:0], w[:0])
        apart = comp[u] != comp[v]
        u, v, w = u[apart], v[apart], w[apart]
        waits = np.bincount(comp, minlength=many).argmax()
        far, unknown = np.full(many, most), np.ones(many, bool)
        for end in (u, v):
            np.minimum.at(far, comp[end], w)
            unknown[comp[end]] = False
        deep = np.lexsort((core, comp))  # a component with no known edge looks from its deepest point first
        deep = deep[np.r_[True, np.diff(comp[deep]) > 0]]
        more = []
        for asks in (np.sort(deep[unknown & (below[deep] < far) & (np.arange(many) != waits)]), None):
            if asks is None:
                asks = np.flatnonzero((below < far[comp]) & (comp != waits))
            more += _edges_out(box, core, comp, asks, far, below)
        if more:
            u, v, w = (np.concatenate([old, *new]) for old, new in zip((u, v, w), zip(*more, strict=True), strict=True))
        order = np.lexsort((np.maximum(u, v), np.minimum(u, v), w))
        u, v, w = u[order], v[order], w[order]
        best = np.full(many, len(u))
        place = np.arange(len(u))
        for end in (u, v):  # of several, the last that is written stays: the first in order
            mine = np.full(many, len(u))
            mine[comp[end][::-1]] = place[::-1]
            best = np.minimum(best, mine)
        best[waits] = len(u)
        e = np.unique(best[best < len(u)])
        if not len(e):
            return tuple(np.concatenate(c) for c in zip(*taken, strict=True)) if taken else (u[:0], v[:0], w[:0])
        pair = np.sort(np.stack([comp[u[e]], comp[v[e]]]), axis=0)
        e = e[np.unique(pair, axis=1, return_index=True)[1]]  # one edge joins two components, if both took one of equal weight
        taken.append((u[e], v[e], w[e]))
        comp = least_labels(many, comp[u[e]], comp[v[e]])[comp]


def _core_pairs(box: _Boxes, core: np.ndarray, nbr: np.ndarray, dist: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Pairs u < v of points of which one is within the other's core distance; lists that end within it are looked up again."""
    n = len(core)
    full = (dist[:, -1] <= core) if nbr.shape[1] < n - 1 else np.zeros(n, bool)
    u, at = np.nonzero((dist <= core[:, None]) & ~full[:, None])
    us, vs = [u], [nbr[u, at].astype(int)]
    asks = np.flatnonzero(full)
    leaf = np.searchsorted(box.ends, asks, side="right") - 1
    for p in np.split(asks, np.flatnonzero(np.diff(leaf)) + 1) if len(asks) else []:
        q = box.members(np.flatnonzero(box.gap(box.x[p], box.low, box.high) <= core[p].max()))
        i, j = np.nonzero(B.lengths(box.x[p], box.x[q], box.metric) <= core[p][:, None])
        us.append(p[i]), vs.append(q[j])
    u, v = np.concatenate(us), np.concatenate(vs)
    both = np.unique(np.minimum(u, v) * n + np.maximum(u, v))
    u, v = both // n, both % n
    return u[u != v], v[u != v]


def group_graph(x: np.ndarray, k: int, metric: str = "euclidean", graph: bool = False, tree: bool = True) -> tuple[np.ndarray, ...]:
    """Places and weights ``u, v, w`` of the tree's edges, the core distances, and with ``graph`` the places ``a, b`` of pairs that are within
    the core distance of one of them; of equal points, only pairs with the first one. Without ``tree``
    its edges are missing. For more than ``k`` points."""
    none = np.empty(0, np.int64)
    by = np.lexsort((np.arange(len(x)), *x.T))
    new = np.r_[True, (x[by][1:] != x[by][:-1]).any(1)]
    of = np.empty(len(x), int)
    of[by] = np.cumsum(new) - 1
    rep, count = by[new], np.bincount(of)
    order, ends = _split(x[rep])
    rep, count, place = rep[order], count[order], np.argsort(order)
    of = place[of]
    n = len(rep)
    box = _Boxes(np.ascontiguousarray(x[rep]), ends, metric)
    a = b = none
    if n == 1:
        core, (u, v, w) = np.zeros(1), (none, none, np.empty(0))
    else:
        nbr, dist = _nearest(box, min(2 * k, n - 1))
        reached = count[:, None] - 1 + np.cumsum(count[nbr], axis=1)
        core = np.where(count > k, 0.0, dist[np.arange(n), (reached >= k).argmax(1)])
        if graph:
            a, b = _core_pairs(box, core, nbr, dist)
        u, v = np.repeat(np.arange(n, dtype=np.int32), nbr.shape[1]), nbr.ravel()
        w = np.maximum(dist.ravel(), np.maximum(core[u], core[v]))
        keep = (u < v) | ~(nbr[v] == u[:, None]).any(1)  # each pair once
        below = np.maximum(core, dist[:, -1] if nbr.shape[1] < n - 1 else np.inf)
        del nbr, dist
        u, v, w = _grow(box, core, u[keep], v[keep], w[keep], below) if tree else (none, none, np.empty(0))
    twins = np.flatnonzero(rep[of] != np.arange(len(x)))
    ends = lambda i, j: (np.concatenate([rep[i], rep[of[twins]]]), np.concatenate([rep[j], twins]))
    return *ends(u, v), np.concatenate([w, core[of[twins]]]), core[of], *(ends(a, b) if graph else (a, b))


def region_forest(x: np.ndarray, k: int, near: np.ndarray, most: float) -> tuple[np.ndarray, ...]:
    """Places and weights ``u, v, w`` of a least spanning forest of the points that are ``near``, of Euclidean mutual reachabilities up to
    ``most``, and the core distances, infinite where they are greater. The other points, at least all around, only count as neighbours."""
    none = np.empty(0, np.int64)
    if len(x) <= k:
        return none, none, np.empty(0), np.full(len(x), np.inf)
    by = np.lexsort((np.arange(len(x)), *x.T))
    new = np.r_[True, (x[by][1:] != x[by][:-1]).any(1)]
    of = np.empty(len(x), int)
    of[by] = np.cumsum(new) - 1
    rep, count = by[new], np.bincount(of)
    order, ends = _split(x[rep])
    rep, count, place = rep[order], count[order], np.argsort(order)
    of, n = place[of], len(rep)
    if n == 1:
        core, u, v, w = np.zeros(1), none, none, np.empty(0)
        kept = near[rep]
    else:
        nbr, dist = _nearest(_Boxes(np.ascontiguousarray(x[rep]), ends, "euclidean"), min(2 * k, n - 1))
        reached = count[:, None] - 1 + np.cumsum(count[nbr], axis=1)
        core = np.where(count > k, 0.0, dist[np.arange(n), (reached >= k).argmax(1)])
        kept = near[rep] & (core <= most)
        at, to = np.flatnonzero(kept), np.cumsum(kept) - 1
        fine = kept[nbr] & kept[:, None] & (dist <= most)
        below = np.maximum(core, dist[:, -1] if nbr.shape[1] < n - 1 else np.inf)[at]
        u, j = np.nonzero(fine)
        v, w = nbr[u, j].astype(np.int64), dist[u, j]
        del nbr, dist, reached, fine, j
        w = np.maximum(w, np.maximum(core[u], core[v]))
        short = w <= most
        u, v, w = to[u[short]], to[v[short]], w[short]
        _, one = np.unique(np.minimum(u, v) * len(at) + np.maximum(u, v), return_index=True)
        if len(at):
            box = _Boxes(np.ascontiguousarray(x[rep[at]]), np.unique(np.r_[0, np.cumsum(kept)][ends]), "euclidean")
            u, v, w = _grow(box, core[at], u[one], v[one], w[one], below, None, most)
            u, v = at[u], at[v]
    twins = np.flatnonzero((rep[of] != np.arange(len(x))) & kept[of])
    own = np.where(core <= most, core, np.inf)
    return np.concatenate([rep[u], rep[of[twins]]]), np.concatenate([rep[v], twins]), np.concatenate([w, core[of[twins]]]), own[of]


def settled(n: int, u: np.ndarray, v: np.ndarray, w: np.ndarray, shared: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Which edges of a least forest over ``n`` points stay in it whatever edges other forests add between points that are ``shared``, and for
    each point one that it is joined to by them: the shared one, if there is any. Components without a shared point take their shortest edge
    until there are none; no edge from elsewhere leaves them."""
    order = np.argsort(w, kind="stable")
    a, b, left, many = u[order], v[order], np.arange(len(u)), len(u)
    home, open_, stays = np.arange(n), shared.copy(), np.zeros(many, bool)
    while (apart := a != b).any():
        a, b, left = a[apart], b[apart], left[apart]
        best = np.full(n, many)
        for end in (a, b):
            c, first = np.unique(end, return_index=True)
            best[c] = np.minimum(best[c], left[first])
        best[open_] = many
        chosen = np.unique(best[best < many])
        if not len(chosen):
            break
        stays[order[chosen]] = True
        place = np.searchsorted(left, chosen)
        to = least_labels(n, a[place], b[place])
        a, b, home = to[a], to[b], to[home]
        held, open_ = to[open_], np.zeros(n, bool)
        open_[held] = True
    name = np.arange(n)
    name[home[shared]] = np.flatnonzero(shared)
    return stays, name[home]


def joined_up(x: np.ndarray, core: np.ndarray, k: int, home: np.ndarray) -> tuple[np.ndarray, ...]:
    """Places and weights ``u, v, w`` of the edges by which a least spanning tree of Euclidean mutual reachabilities joins the components
    ``home``, which it has at some length. Core distances that are greater than it are infinite and found here."""
    none, at = np.empty(0, np.int64), _around(x, core, k, home)
    x, core, home = x[at], core[at], home[at]
    order, ends = _split(x)
    box, core, home = _Boxes(np.ascontiguousarray(x[order]), ends, "euclidean"), core[order], home[order]
    asks = np.flatnonzero(np.isinf(core))
    for rows in np.array_split(asks, max(1, len(asks) // 64)):
        if len(rows):
            core[rows] = _core_of(box, rows, k)
    u, v, w = _grow(box, core, none, none, np.empty(0), core.copy(), home)
    return at[order[u]], at[order[v]], w


def _around(x: np.ndarray, core: np.ndarray, k: int, home: np.ndarray) -> np.ndarray:
    """The points that edges between components, and unknown core distances, can have to do with: all but those of the greatest component
    that are too far from the others. Some points bound how far each of the others has to look."""
    few = np.flatnonzero(home != np.bincount(home).argmax())
    if len(few) > MANY or len(x) <= 4 * SOME or k >= SOME:
        return np.arange(len(x))
    few = few[np.argsort(home[few], kind="stable")]
    some = np.arange(0, len(x), len(x) // SOME)
    inside = some[home[some] == np.bincount(home).argmax()]
    inside = inside[np.isfinite(core[inside])]
    if not len(inside) or not len(few):
        return np.arange(len(x))
    most, far = core[few].copy(), np.empty(len(few))
    for i in range(0, len(few), 256):
        rows = few[i : i + 256]
        d = B.lengths(x[rows], x[some], "euclidean")
        most[i : i + 256] = np.where(np.isinf(core[rows]), np.partition(d, k, axis=1)[:, k], core[rows])
        far[i : i + 256] = np.maximum(np.maximum(B.lengths(x[rows], x[inside], "euclidean"), core[inside]).min(1), most[i : i + 256])
    first = np.flatnonzero(np.r_[True, np.diff(home[few]) != 0])
    reach = np.maximum(np.minimum.reduceat(far, first), np.maximum.reduceat(most, first)) * (1 + B.SLACK)
    low, high = np.minimum.reduceat(x[few], first) - reach[:, None], np.maximum.reduceat(x[few], first) + reach[:, None]
    by = np.argsort(x[:, 0], kind="stable")
    a, b = np.searchsorted(x[:, 0], low[:, 0], sorter=by), np.searchsorted(x[:, 0], high[:, 0], side="right", sorter=by)
    kept = np.zeros(len(x), bool)
    kept[few] = True
    for c in range(len(first)):
        part = by[a[c] : b[c]]
        kept[part[((x[part] >= low[c]) & (x[part] <= high[c])).all(1)]] = True
    return np.flatnonzero(kept)


def _core_of(box: _Boxes, rows: np.ndarray, k: int) -> np.ndarray:
    """Distances to the k-th nearest others of a few points that lie beside each other."""
    gaps = box.gap(box.x[rows], box.low, box.high)
    by, sizes = np.argsort(gaps, kind="stable"), box.ends[1:] - box.ends[:-1]
    few = int(np.searchsorted(np.cumsum(sizes[by]), k + len(rows))) + 1
    for _ in range(2):  # what some boxes say bounds which others count
        others = box.members(by[:few])
        d = np.empty((len(rows), k + 1))
        for i, r in enumerate(rows):
            d[i] = np.partition(B.lengths(box.x[r : r + 1], box.x[others], box.metric)[0], k)[: k + 1]
        most = d.max(1)
        few = max(few, int(np.searchsorted(gaps[by], most.max(), side="right")))
    return most


def group_tree(ids: np.ndarray, x: np.ndarray, k: int, metric: str = "euclidean") -> tuple[np.ndarray, ...]:
    """``u, v, w`` of the tree's edges between ids, and the core distances in the order of ``ids``; no edges for ``k`` points or fewer."""
    if len(ids) <= k:
        none = np.empty(0, np.int64)
        return none, none, np.empty(0), np.full(len(ids), np.inf)
    u, v, w, core, _, _ = group_graph(x, k, metric)
    return np.minimum(ids[u], ids[v]), np.maximum(ids[u], ids[v]), w, core


def reach_edges(points: DataFrame, k: int, metric: str = "euclidean") -> tuple[DataFrame, DataFrame]:
    """Tree and core distances of :func:`spurline.operators.reach.reach_tree`: a group that one task can take is one task's work, a larger
    one goes by its rounds."""
    p = materialise(B.embedded(points, metric).where("grp is not null"), "embedded")
    sizes = p.groupBy("grp").agg(F.count(F.lit(1)).alias("n"), F.max(F.size("x")).alias("d"))
    big = materialise(sizes.where((F.col("n") > TREE_POINTS) | (F.col("n") * F.col("d") > TREE_NUMBERS)).select("grp"), "large-groups")

    def run(key, t):
        ids = t.column("id").to_numpy()
        u, v, w, core = group_tree(ids, B._vectors(t), k, metric)
        fine = np.isfinite(core)
        return pa.table({"grp": pa.repeat(pa.scalar(key[0].as_py(), pa.string()), len(u) + int(fine.sum())), "u": np.concatenate([u, ids[fine]]), "v": pa.concat_arrays([pa.array(v, pa.int64()), pa.nulls(int(fine.sum()), pa.int64())]), "w": np.concatenate([w, core[fine]])})

    few = p if big.isEmpty() else p.join(big, "grp", "left_anti")
    made = materialise(few.repartition(B._tasks(p), "grp").groupBy("grp").applyInArrow(run, "grp string, u long, v long, w double"), "grown")
    tree, core = made.where("v is not null"), made.where("v is null").select("grp", F.col("u").alias("id"), F.col("w").alias("core"))
    if few is p:
        return tree, core
    more, cores, _ = reach_tree(points.join(big, "grp", "left_semi"), k, metric)
    return tree.unionByName(more.select("grp", "u", "v", "w")), core.unionByName(cores.select("grp", "id", "core"))
