"""NumPy kernels for one group of points that fits a task: distances, trees, hierarchies, selection, labels.

One routine, :func:`hierarchy`, serves both passes: over 1 / mutual reachability for density, and over eccentricity for
branches. It takes all edges of one level together, so equal levels give one node however edges are ordered.
"""

from __future__ import annotations

import heapq
from dataclasses import dataclass, field

import numpy as np

MIN_GAP = 1e-12
#: Edges a point from which a graph is thinned to a spanning forest, by array steps, before its edges are walked.
DENSE = 12


def distances(x: np.ndarray, metric: str = "euclidean") -> np.ndarray:
    if metric == "angular":
        size = np.linalg.norm(x, axis=1)
        if (size == 0).any():
            raise ValueError("a zero vector has no angle")
        y = x / size[:, None]
        d = np.arccos(np.clip(y @ y.T, -1, 1))
        np.fill_diagonal(d, 0)
        return d
    if metric == "euclidean" and 0 < x.shape[1] < 8:  # so few squares are summed one after the other in either way
        out = np.zeros((len(x), len(x)))
        for axis in x.T:
            gap = axis[:, None] - axis
            out += gap * gap
        return np.sqrt(out)
    gap = lambda i: np.abs(x - x[i])
    one = {"euclidean": lambda g: np.sqrt((g * g).sum(1)), "manhattan": lambda g: g.sum(1), "chebyshev": lambda g: g.max(1)}[metric]
    return np.stack([one(gap(i)) for i in range(len(x))]) if len(x) else np.empty((0, 0))


def distances_to(a: np.ndarray, x: np.ndarray, metric: str) -> np.ndarray:
    """Distances of all rows of ``x`` to ``a``, as :func:`distances` finds them; not for angles."""
    gap = np.abs(x - a)
    return {"euclidean": lambda: np.sqrt((gap * gap).sum(1)), "manhattan": lambda: gap.sum(1), "chebyshev": lambda: gap.max(1)}[metric]()


def core_distances(d: np.ndarray, k: int) -> np.ndarray:
    """Distance to the k-th nearest other point; infinite if there are fewer."""
    n = len(d)
    if n <= k:
        return np.full(n, np.inf)
    return np.partition(d + np.diag(np.full(n, -1.0)), k, axis=1)[:, k]  # the point itself sorts first


def spanning_tree(w: np.ndarray) -> np.ndarray:
    """Prim's tree of a full weight matrix: rows (u, v, weight)."""
    n = len(w)
    best, near, out = w[0].copy(), np.zeros(n, int), []
    todo = np.ones(n, bool)
    todo[0] = False
    for _ in range(n - 1):
        v = int(np.where(todo, best, np.inf).argmin())
        out.append((near[v], v, best[v]))
        todo[v] = False
        closer = todo & (w[v] < best)
        best[closer], near[closer] = w[v][closer], v
    return np.array(out).reshape(-1, 3)


@dataclass
class Tree:
    """A condensed hierarchy. Levels fall from leaves to roots; a node is born where it parts from its parent."""

    parent: list[int] = field(default_factory=list)  # -1: root
    birth: list[float] = field(default_factory=list)
    size: list[int] = field(default_factory=list)
    exit_node: np.ndarray = field(default_factory=lambda: np.empty(0, int))  # where each point leaves; -1: never in a node
    exit_level: np.ndarray = field(default_factory=lambda: np.empty(0))

    def children(self) -> list[list[int]]:
        out: list[list[int]] = [[] for _ in self.parent]
        for c, p in enumerate(self.parent):
            if p >= 0:
                out[p].append(c)
        return out

    def stability(self) -> np.ndarray:
        out = np.zeros(len(self.parent))
        inside = self.exit_node >= 0
        birth = np.array(self.birth)
        np.add.at(out, self.exit_node[inside], self.exit_level[inside] - birth[self.exit_node[inside]])
        for c, p in enumerate(self.parent):
            if p >= 0:
                out[p] += self.size[c] * (birth[c] - birth[p])
        return out

    def top(self) -> np.ndarray:
        """The largest level at which anything leaves each node directly."""
        out = np.array(self.birth, float)
        inside = self.exit_node >= 0
        np.maximum.at(out, self.exit_node[inside], self.exit_level[inside])
        for c, p in enumerate(self.parent):
            if p >= 0:
                out[p] = max(out[p], self.birth[c])
        return out


def thinned(n: int, u: np.ndarray, v: np.ndarray, level: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """A greatest spanning forest of the edges: at every level it has the same components."""
    w = np.full((n, n), 1.0)
    rank = np.unique(-level, return_inverse=True)[1] / (len(level) + 1)  # below 1, which stands for no edge
    np.minimum.at(w, (u, v), rank), np.minimum.at(w, (v, u), rank)
    full = np.full((n, n), -np.inf)
    np.maximum.at(full, (u, v), level), np.maximum.at(full, (v, u), level)
    t = spanning_tree(w)
    a, b = (t[t[:, 2] < 1, i].astype(int) for i in (0, 1))
    return a, b, full[a, b]


def hierarchy(n: int, u: np.ndarray, v: np.ndarray, level: np.ndarray, least: int) -> Tree:
    """Fused linkage and condensing: levels are taken from high to low, all edges of a level at once."""
    if n > 1 and len(u) > DENSE * n:
        u, v, level = thinned(n, u, v, level)
    tree, root = Tree(exit_node=np.full(n, -1), exit_level=np.zeros(n)), list(range(n))
    size, node, loose = [1] * n, [-1] * n, {i: [i] for i in range(n)}

    def find(a: int) -> int:
        while root[a] != a:
            root[a] = root[root[a]]
            a = root[a]
        return a

    order = np.argsort(-level, kind="stable")
    us, vs, levels = np.asarray(u)[order].tolist(), np.asarray(v)[order].tolist(), level[order].tolist()
    at, last = 0, len(levels)
    while at < last:
        lv, stop = levels[at], at
        meet: dict[int, set[int]] = {}
        while stop < last and levels[stop] == lv:
            a, b = find(us[stop]), find(vs[stop])
            stop += 1
            if a != b:
                a, b = (a, b) if size[a] >= size[b] else (b, a)
                both, other = meet.pop(a, {a}), meet.pop(b, {b})
                both, other = (both, other) if len(both) >= len(other) else (other, both)
                both |= other
                root[b] = a
                meet[a] = both
        at = stop
        for top, parts in meet.items():
            total = sum(size[p] for p in parts)
            nodes = [node[p] for p in sorted(parts) if node[p] >= 0]
            points = [x for p in parts if node[p] < 0 for x in loose.pop(p)]
            own = -1
            if not nodes and total < least:
                loose[top] = points
            else:
                if len(nodes) == 1:
                    own = nodes[0]
                else:
                    own = len(tree.parent)
                    tree.parent.append(-1), tree.birth.append(0.0), tree.size.append(0)
                    for c in nodes:
                        tree.parent[c], tree.birth[c] = own, lv
                if len(points) == 1:
                    tree.exit_node[points[0]], tree.exit_level[points[0]] = own, lv
                elif points:
                    tree.exit_node[points], tree.exit_level[points] = own, lv
                tree.size[own] = total
            size[top], node[top] = total, own
    return tree


def prune(tree: Tree, persistence: float) -> Tree:
    """Merge leaves whose range of levels is not above ``persistence`` into their parents until none is left."""
    if persistence <= 0:
        return tree
    while True:
        top, kids = tree.top(), tree.children()
        short = [c for c, p in enumerate(tree.parent) if p >= 0 and not kids[c] and top[c] - tree.birth[c] <= persistence]
        if not short:
            return tree
        c = min(short, key=lambda c: (top[c] - tree.birth[c], c))
        p = tree.parent[c]
        inside = tree.exit_node == c
        tree.exit_level[inside] = tree.birth[c]
        rest = [k for k in kids[p] if k != c]
        into = {c: p}
        if len(rest) == 1:  # a lone child goes on as its parent
            into[rest[0]] = p
        tree.exit_node = np.array([into.get(int(x), int(x)) for x in tree.exit_node])
        keep = [i for i in range(len(tree.parent)) if i not in into]
        new = {old: i for i, old in enumerate(keep)}
        parents = [into.get(tree.parent[i], tree.parent[i]) for i in keep]
        tree = Tree([new.get(x, -1) for x in parents], [tree.birth[i] for i in keep], [tree.size[i] for i in keep], np.array([new.get(int(x), -1) for x in tree.exit_node]), tree.exit_level)


def select(tree: Tree, how: str, allow_root: bool, epsilon: float = 0.0) -> list[int]:
    """Selected nodes. Excess of mass keeps a parent whose stability is at least its selected descendants' sum. ``epsilon``
    (a distance) climbs from nodes that were born above level 1 / epsilon."""
    kids = tree.children()
    can = lambda i: allow_root or tree.parent[i] >= 0
    if how == "leaf":
        chosen = [i for i in range(len(tree.parent)) if not kids[i] and can(i)]
    else:
        own, best, pick = tree.stability(), {}, {}
        for i in range(len(tree.parent)):  # children have smaller numbers than their parents, save after pruning
            for j in ([i] if all(k in best for k in kids[i]) else _below(i, kids)):
                below = sum(best[k] for k in kids[j])
                pick[j] = can(j) and (not kids[j] or own[j] >= below)
                best[j] = own[j] if pick[j] else below
        chosen, todo = [], [i for i, p in enumerate(tree.parent) if p < 0]
        while todo:
            i = todo.pop()
            if pick[i]:
                chosen.append(i)
            else:
                todo += kids[i]
    if epsilon > 0:
        up = set()
        for i in chosen:
            while tree.birth[i] > 1 / epsilon and tree.parent[i] >= 0 and can(tree.parent[i]):
                i = tree.parent[i]
            up.add(i)
        chosen = [i for i in up if not any(_inside(tree, i, j) for j in up if j != i)]
    return sorted(chosen)


def _below(i: int, kids: list[list[int]]) -> list[int]:
    out, todo = [], [i]
    while todo:
        out.append(j := todo.pop())
        todo += kids[j]
    return out[::-1]


def _inside(tree: Tree, i: int, j: int) -> bool:
    while i >= 0:
        i = tree.parent[i]
        if i == j:
            return True
    return False


def labels(tree: Tree, chosen: list[int]) -> tuple[np.ndarray, np.ndarray]:
    """Labels numbered by each group's smallest member, -1 for noise; strengths in 0..1."""
    home, top = {-1: -1, **{c: c for c in chosen}}, tree.top()
    for i in range(len(tree.parent)):
        way, j = [], i
        while j not in home:
            way.append(j)
            j = tree.parent[j]
        home.update(dict.fromkeys(way, home[j]))
    at = np.array([home[x] for x in tree.exit_node.tolist()], int)
    number: dict[int, int] = {}
    for x in at.tolist():
        if x >= 0:
            number.setdefault(x, len(number))
    cap = np.where(at >= 0, np.append(top, 1.0)[at], 1.0)
    strength = np.where(at >= 0, np.minimum(tree.exit_level, cap) / np.where(cap > 0, cap, 1.0), 0.0)
    return np.array([number.get(x, -1) for x in at.tolist()], int), strength


@dataclass
class Density:
    d: np.ndarray
    core: np.ndarray
    reach: np.ndarray
    tree: np.ndarray
    hierarchy: Tree
    label: np.ndarray
    strength: np.ndarray


def metric_parts(x: np.ndarray, p) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Distances, core distances, mutual reachability, and its spanning tree, which is empty for fewer than k + 1 points."""
    d = distances(x, p.metric)
    core = core_distances(d, p.min_samples)
    reach = np.maximum(d, np.maximum(core[:, None], core[None, :]))
    return d, core, reach, spanning_tree(reach) if len(x) > p.min_samples else np.empty((0, 3))


def metric_parts_of_many(x: np.ndarray, p) -> list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """:func:`metric_parts` of clouds of equal size (clouds by points by axes), whose trees grow at the same time."""
    parts = [(d := distances(c, p.metric), k := core_distances(d, p.min_samples), np.maximum(d, np.maximum(k[:, None], k[None, :]))) for c in x]
    if not parts or x.shape[1] <= p.min_samples:
        return [(*t, np.empty((0, 3))) for t in parts]
    w, (many, n) = np.stack([r for _, _, r in parts]), x.shape[:2]
    each = np.arange(many)
    best, near, out = w[:, 0].copy(), np.zeros((many, n), int), np.empty((many, n - 1, 3))
    best[:, 0] = np.inf  # infinite: in the tree; core distances are finite here
    done = np.zeros((many, n), bool)
    done[:, 0] = True
    for i in range(n - 1):
        v = best.argmin(1)
        out[:, i, 0], out[:, i, 1], out[:, i, 2] = near[each, v], v, best[each, v]
        best[each, v], done[each, v] = np.inf, True
        row = w[each, v]
        closer = ~done & (row < best)
        np.copyto(best, row, where=closer)
        np.copyto(near, np.broadcast_to(v[:, None], near.shape), where=closer)
    return [(*t, tree) for t, tree in zip(parts, out, strict=True)]


def density(x: np.ndarray, p, known: tuple | None = None, trees: dict | None = None) -> Density:
    """The base clustering of one group; fewer than k + 1 points are all noise. ``known``: what :func:`metric_parts` or
    :func:`metric_parts_of_many` say of these points with the same metric and number of neighbours. ``trees`` keeps their hierarchies."""
    n = len(x)
    d, core, reach, t = known or metric_parts(x, p)
    if n <= p.min_samples:
        return Density(d, core, reach, t, Tree(exit_node=np.full(n, -1), exit_level=np.zeros(n)), np.full(n, -1), np.zeros(n))
    h = None if trees is None else trees.get(p.min_cluster_size)
    if h is None:
        h = hierarchy(n, t[:, 0].astype(int), t[:, 1].astype(int), 1 / np.maximum(t[:, 2], MIN_GAP), p.min_cluster_size)
    if trees is not None:
        trees[p.min_cluster_size] = h
    chosen = select(h, p.cluster_selection, p.allow_single_cluster, p.cluster_epsilon)
    label, strength = labels(h, chosen)
    if len(chosen) == 1 and h.parent[chosen[0]] < 0 and p.cluster_epsilon == 0:
        label = np.zeros(n, int)
    return Density(d, core, reach, t, h, label, strength)


def adjacency(n: int, u: np.ndarray, v: np.ndarray, length: np.ndarray) -> list[list[tuple[int, float]]]:
    near: list[list[tuple[int, float]]] = [[] for _ in range(n)]
    for a, b, w in zip(u.tolist(), v.tolist(), length.tolist(), strict=True):
        near[a].append((b, w))
        near[b].append((a, w))
    return near


def geodesics(n: int, u: np.ndarray, v: np.ndarray, length: np.ndarray, start: int) -> np.ndarray:
    return walked(adjacency(n, u, v, length), start)


def walked(near: list[list[tuple[int, float]]], start: int) -> np.ndarray:
    """Path lengths from ``start``."""
    out, todo = [np.inf] * len(near), [(0.0, start)]
    out[start] = 0.0
    while todo:
        w, a = heapq.heappop(todo)
        if w > out[a]:
            continue
        for b, x in near[a]:
            if w + x < out[b]:
                out[b] = w + x
                heapq.heappush(todo, (w + x, b))
    return np.array(out)


def graph(m: Density, members: np.ndarray, kind: str, with_tree: bool) -> tuple[np.ndarray, np.ndarray]:
    """Edges among a cluster's members, as positions in ``members``, the smaller first."""
    d, c = m.reach[np.ix_(members, members)], m.core[members]
    place = np.full(len(m.core), -1)
    place[members] = np.arange(len(members))
    ends = place[m.tree[:, :2].astype(int)].reshape(-1, 2)
    own = np.column_stack([ends, m.tree[:, 2]])[(ends >= 0).all(1)]
    plain = m.d[np.ix_(members, members)]
    if kind == "full":
        ok = d <= (own[:, 2].max() if len(own) else -1)
    elif kind == "mutual":
        ok = plain <= np.minimum(c[:, None], c[None, :])
    else:
        ok = d <= np.maximum(c[:, None], c[None, :])
    if with_tree and kind != "full":
        ok[own[:, 0].astype(int), own[:, 1].astype(int)] = True
    ok |= ok.T
    return np.nonzero(np.triu(ok, 1))


def eccentricity(x: np.ndarray, m: Density, members: np.ndarray, u: np.ndarray, v: np.ndarray, p) -> np.ndarray:
    w, y, n = m.strength[members], x[members], len(members)
    centre = (y * w[:, None]).sum(0) / w.sum() if w.sum() > 0 else y.mean(0)
    if p.metric == "angular":
        cos = (y @ centre) / np.maximum(np.linalg.norm(y, axis=1) * np.linalg.norm(centre), 1e-300)
        e = np.arccos(np.clip(cos, -1, 1))
    else:
        e = distances_to(centre, y, p.metric)
    if p.eccentricity != "geometric":
        d = m.d[np.ix_(members, members)]
        if p.eccentricity == "distance_sum":
            e = d.sum(1)
        else:
            hops = np.ones(len(u))
            if p.eccentricity == "max_path":
                far = np.array([geodesics(n, u, v, m.reach[members[u], members[v]], i) for i in range(n)])
                e = np.where(np.isfinite(far), far, 0).max(1)
            else:
                root = int(e.argmin())
                if p.root == "extremal":
                    root = int(np.nan_to_num(geodesics(n, u, v, hops, root), posinf=-1).argmax())
                e = geodesics(n, u, v, hops, root)
                e[~np.isfinite(e)] = 0
    for _ in range(p.smooth):
        total, count = e.copy(), np.ones(n)
        np.add.at(total, u, e[v]), np.add.at(total, v, e[u])
        np.add.at(count, u, 1), np.add.at(count, v, 1)
        e = total / count
    if p.push:
        e = e + m.core[members]
    return -e + e.max() if p.direction == "min" else e


@dataclass
class Branches:
    members: np.ndarray
    e: np.ndarray
    u: np.ndarray
    v: np.ndarray
    tree: Tree
    label: np.ndarray
    strength: np.ndarray
    split: bool
    d_geo: np.ndarray | None = None


def branches(x: np.ndarray, m: Density, p, known: dict | None = None) -> list[Branches]:
    """The branch pass over every cluster of a density model; the model is not run again. ``known`` keeps what passes with other settings
    over the same model have in common."""
    known, out = {} if known is None else known, []

    def once(key: tuple, make):
        if key not in known:
            known[key] = make()
        return known[key]

    for c in range(m.label.max(initial=-1) + 1):
        members = once(("members", c), lambda: np.flatnonzero(m.label == c))
        n, by = len(members), (c, p.graph, p.with_tree_edges)
        u, v = once(("graph", by), lambda: graph(m, members, p.graph, p.with_tree_edges))
        of = (by, p.eccentricity, p.root, p.direction, p.smooth, p.push)
        e = once(("signal", of), lambda: eccentricity(x, m, members, u, v, p))

        def levels():
            level = np.minimum(e[u], e[v])
            return thinned(n, u, v, level) if n > 1 and len(u) > DENSE * n else (u, v, level)

        forest = once(("levels", of), levels)
        h = once(("tree", of, p.branch_size, p.branch_persistence), lambda: prune(hierarchy(n, *forest, p.branch_size), p.branch_persistence))
        chosen = select(h, p.branch_selection, False)
        label, strength = labels(h, chosen)
        split = len(chosen) > (1 if p.label_sides else 2)
        b = Branches(members, e, u, v, h, label, strength, split)
        if split:
            length = {"distance": m.d, "mreach": m.reach}[p.edge_length][members[u], members[v]] if p.edge_length != "hops" else np.ones(len(u))
            roots = []
            for k in range(len(chosen)):
                y, w = x[members][label == k], strength[label == k]
                centre = (y * w[:, None]).sum(0) / w.sum() if w.sum() > 0 else y.mean(0)
                roots.append(int(np.flatnonzero(label == k)[((y - centre) ** 2).sum(1).argmin()]))
            near = once(("near", by, p.edge_length), lambda: adjacency(n, u, v, length))
            b.d_geo = np.array([once(("paths", by, p.edge_length, r), lambda: walked(near, r)) for r in roots])
        out.append(b)
    return out


def softmax_membership(d_geo: np.ndarray, t: float) -> np.ndarray:
    """Rows: branches, columns: points. A root belongs wholly to its branch; roots at one point share equally."""
    with np.errstate(divide="ignore"):
        c = 1 / d_geo / t
    at_root = np.isinf(c)
    c = np.where(at_root.any(0), np.where(at_root, 0.0, -np.inf), c)
    e = np.exp(c - c.max(0))
    return e / e.sum(0)


def combine(m: Density, parts: list[Branches], p) -> dict[str, np.ndarray]:
    """Cluster and branch labels as one, centre points last in their cluster."""
    n = len(m.label)
    branch, bs, centre, strength = np.zeros(n, int), np.ones(n), np.zeros(n, bool), m.strength.copy()
    for b in parts:
        if not b.split:
            continue
        k = b.label.copy()
        loose = k < 0
        if p.central_labels == "geodesic":
            k[loose] = b.d_geo[:, loose].argmin(0)
        else:
            k[loose] = b.label.max() + 1
        own = np.where(loose, 0.0, b.strength)
        branch[b.members], bs[b.members], centre[b.members] = k, own, loose
        s = m.strength[b.members]
        strength[b.members] = s * own if p.combine == "product" else (s + own) / 2
    pairs = sorted({(c, k) for c, k in zip(m.label.tolist(), branch.tolist(), strict=True) if c >= 0})
    number = {x: i for i, x in enumerate(pairs)}
    return {"label": np.array([number.get(x, -1) for x in zip(m.label.tolist(), branch.tolist(), strict=True)], int), "strength": strength, "cluster": m.label, "cluster_strength": m.strength, "branch": branch, "branch_strength": bs, "is_center": centre}
