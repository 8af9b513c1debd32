"""What is linked under mutual reachability within given lengths, and the least spanning tree of few axes, by tiles: exact, for dense groups.

A least spanning tree that is cut at a length has the components of all pairs within it; these go without a tree (:func:`reach_cut`). Cells so small that their points are all within
the length of each other are linked as wholes, so a dense spot is a few cells, whatever it holds. Tiles of cells are bounded tasks that know
the points around them; they tell how their cells hang together, and the tiles are joined by the least point of each cell at their sides.
"""

from __future__ import annotations

import math
from itertools import product

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spurline.operators import blocks as B
from spurline.operators import grown
from spurline.operators.components import components, least_labels
from spurline.operators.forest import kept_edges
from spurline.operators.reach import reach_tree
from spurline.runtime import materialise, merged

#: Cells of the greatest length along a tile's side; pairs of points that are looked at together.
TILE_CELLS, PAIRS = 16, 2_000_000
TOLD = "grp string, most double, kind int, a long, b long"
POINT, SIDE = 0, 1
#: Rows of a tile: edges u, v of the tree; edges that may be, between what the points a and b stand for; points u with their core
#: distances w, and which point a stands for them.
TREE, OPEN, OWN = 0, 1, 2
TILE = "grp string, kind int, u long, v long, w double, a long, b long, x array<double>"
EDGES = "grp string, u long, v long, w double"


def _cells(code: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of sorted codes: the distinct ones, where they begin and how many each has."""
    start = np.flatnonzero(np.r_[True, code[1:] != code[:-1]]) if len(code) else np.empty(0, int)
    return code[start], start, np.diff(np.r_[start, len(code)])


def _within(x: np.ndarray, square: float, a: tuple, b: tuple):
    """``(pair, i, j)`` of the points i and j of pairs of runs (starts, sizes) that are within the length, some pairs at a time."""
    (a0, na), (b0, nb) = a, b
    per = np.maximum(1, PAIRS // np.maximum(nb, 1))
    cut = np.repeat(np.arange(len(na)), -(-na // per))  # runs of too many pairs are taken in pieces
    piece = np.arange(len(cut)) - np.searchsorted(cut, cut)
    a0, na = a0[cut] + piece * per[cut], np.minimum(na[cut] - piece * per[cut], per[cut])
    total = np.cumsum(na * nb[cut])
    at = 0
    while at < len(cut):
        stop = max(at + 1, int(np.searchsorted(total, (total[at - 1] if at else 0) + PAIRS, side="right")))
        p = cut[at:stop]
        n = na[at:stop] * nb[p]
        of = np.repeat(np.arange(len(p)), n)
        place = np.arange(len(of)) - np.repeat(np.cumsum(n) - n, n)
        i, j = a0[at:stop][of] + place // nb[p][of], b0[p][of] + place % nb[p][of]
        d = np.zeros(len(of))
        for axis in x.T:
            gap = axis[i] - axis[j]
            d += gap * gap
        near = d <= square
        yield p[of[near]], i[near], j[near]
        at = stop


def tile_links(ids: np.ndarray, x: np.ndarray, tile: np.ndarray, side: float, square: float, k: int) -> tuple[np.ndarray, ...]:
    """For the tile whose number along each axis is ``tile``: its points with k others within the length, the label of each, and
    ``(least point, label)`` of cells that another tile can see. ``x`` holds at least all points around the tile."""
    dims, length = x.shape[1], math.sqrt(square)
    m = math.ceil(side * math.sqrt(dims) / length * (1 + 1e-9))
    edge = side / m
    ring = int(length / edge) + 1
    rel = np.floor(x / edge).astype(np.int64) - tile * m
    seen = ((rel >= -2 * ring) & (rel < m + 2 * ring)).all(1)
    ids, x, rel = ids[seen], x[seen], rel[seen]
    radix = (m + 6 * ring) ** np.arange(dims)
    code = (rel + 3 * ring) @ radix
    order = np.lexsort((ids, code))
    ids, x, rel, code = ids[order], x[order], rel[order], code[order]
    offsets = [np.array(o) for o in product(range(-ring, ring + 1), repeat=dims)]
    gap = lambda o: float((np.maximum(np.abs(o) - 1, 0) ** 2).sum() * edge * edge)
    offsets = sorted((o for o in offsets if gap(o) <= square * (1 + 1e-9)), key=lambda o: (gap(o), np.abs(o).sum()))

    def beside(cells: np.ndarray, known: np.ndarray, o: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        want = cells + int(o @ radix)
        place = np.minimum(np.searchsorted(known, want), max(len(known) - 1, 0))
        hit = known[place] == want if len(known) else np.zeros(len(cells), bool)
        return np.flatnonzero(hit), place[hit]

    near = ((rel >= -ring) & (rel < m + ring)).all(1)
    cell, start, size = _cells(code)
    found = np.repeat(np.where(size > k, k + 1, 0), size)  # a cell of over k points: each has k others
    asks = np.flatnonzero((size <= k) & near[start])
    for o in offsets:
        if not len(asks):
            break
        a, b = beside(cell[asks], cell, o)
        a = asks[a]
        for _, i, _ in _within(x, square, (start[a], size[a]), (start[b], size[b])):
            found += np.bincount(i, minlength=len(found))
        asks = asks[np.minimum.reduceat(found, start)[asks] <= k]
    core = near & (found > k)
    ids, x, rel, code = ids[core], x[core], rel[core], code[core]
    if not len(ids):
        return ids, ids, ids, ids
    cell, start, size = _cells(code)
    own, least = ((rel >= 0) & (rel < m)).all(1)[start], ids[start]
    label, us, vs = np.arange(len(cell)), [], []
    for o in offsets:
        if tuple(o) <= (0,) * dims:
            continue
        a, b = beside(cell, cell, o)
        open_ = (own[a] | own[b]) & (label[a] != label[b])
        a, b = a[open_], b[open_]
        for most in (8, None):  # a few points of each mostly show the link; all are looked at where they don't
            ends = [(start[c], size[c] if most is None else np.minimum(size[c], most)) for c in (a, b)]
            linked = np.zeros(len(a), bool)
            for p, _, _ in _within(x, square, *ends):
                linked[p] = True
            us.append(a[linked]), vs.append(b[linked])
            a, b = a[~linked], b[~linked]
        label = least_labels(len(cell), np.concatenate(us), np.concatenate(vs))
    name = np.full(len(cell), np.iinfo(np.int64).max)
    np.minimum.at(name, label, least)
    name = name[label]
    inner = ((rel >= ring) & (rel < m - ring)).all(1)[start]
    alive = np.zeros(len(cell), bool)
    alive[label[own]] = True
    told = ~inner & alive[label]
    mine = np.repeat(own, size)
    return ids[mine], np.repeat(name, size)[mine], least[told], name[told]


def _tiles(p: DataFrame, dims: int, side: float, halo: float) -> tuple[DataFrame, list[str]]:
    """The points, once for each tile that they are in or no further than ``halo`` from, with the tile's number along each axis."""
    rows, keys = p, [f"t{i}" for i in range(dims)]
    for i, t in enumerate(keys):
        at = F.get("x", F.lit(i))
        rows = rows.withColumn(t, F.explode(F.sequence(F.floor((at - halo) / side).cast("long"), F.floor((at + halo) / side).cast("long"))))
    return rows.repartition(8 * B._tasks(rows), "grp", *keys), keys


def _dims(p: DataFrame) -> int:
    first = p.select(F.size("x").alias("d")).first()
    return first.d if first else 1


def _told(points: DataFrame, k: int, squares: list[float]) -> DataFrame:
    """TOLD rows of all tiles: the points and their labels, and cells at the sides."""
    p = B.measurable(points).where("grp is not null")
    dims = _dims(p)
    side = TILE_CELLS * math.sqrt(max(squares) / dims)
    halo = 2 * max(math.sqrt(s) + side / math.ceil(side * math.sqrt(dims) / math.sqrt(s) * (1 + 1e-9)) for s in squares) * (1 + 1e-6)
    rows, keys = _tiles(p, dims, side, halo)

    def run(key, t):
        ids, x, tile = t.column("id").to_numpy(), B._vectors(t), np.array([c.as_py() for c in key[1:]])
        out = [[] for _ in range(4)]
        for square in squares:
            mine, label, least, name = tile_links(ids, x, tile, side, square, k)
            for kind, a, b in ((POINT, mine, label), (SIDE, least, name)):
                for c, v in zip(out, (np.full(len(a), float(square)), np.full(len(a), kind, np.int32), a, b), strict=True):
                    c.append(v)
        cols = [np.concatenate(c) for c in out]
        return pa.table({"grp": pa.repeat(pa.scalar(key[0].as_py(), pa.string()), len(cols[0])), "most": cols[0], "kind": cols[1], "a": cols[2], "b": cols[3]})

    return materialise(rows.groupBy("grp", *keys).applyInArrow(run, TOLD), "tiles")


def _homes(told: DataFrame) -> DataFrame:
    sides = told.where(F.col("kind") == SIDE).select("grp", "most", F.col("a").alias("u"), F.col("b").alias("v"))
    return materialise(components(sides, keys=("grp", "most")).select("grp", "most", F.col("id").alias("b"), "component"), "homes")


def reach_cut(points: DataFrame, k: int, squares: list[float]) -> DataFrame:
    """``(grp, most, id, component)``: for each of ``squares`` (lengths, squared) the least point to which each point of ``points`` is linked
    over mutual reachabilities within the length; Euclidean, of few axes. A task holds a tile, TILE_CELLS cells of the greatest length."""
    told = _told(points, k, squares)
    mine = told.where(F.col("kind") == POINT).select("grp", "most", F.col("a").alias("id"), "b")
    found = mine.join(_homes(told), ["grp", "most", "b"], "left").select("grp", "most", "id", F.coalesce("component", "b").alias("component"))
    every = B.measurable(points).select("grp", "id", F.explode(F.array(*[F.lit(float(s)) for s in squares])).alias("most"))
    return every.join(merged(found), ["grp", "most", "id"], "left").select("grp", "most", "id", F.coalesce("component", "id").alias("component"))


def tile_tree(points: DataFrame, k: int, length: float) -> DataFrame:
    """``(grp, u, v, w)``: the whole least spanning tree of each group's mutual reachabilities; Euclidean, of few axes, the same weights as
    :func:`spurline.operators.reach.reach_tree`. A tile is a task that grows a least forest of all edges up to ``length`` whose middle can
    be in it; at every level the tiles' forests together link what all edges link, so the group's tree is among their edges. Most of them no
    other tile can replace; one task takes the tree from the rest, and one, for groups of up to TREE_NUMBERS numbers, finds the edges
    beyond ``length`` between components that are left. Larger groups go by rounds."""
    p = B.measurable(points).where("grp is not null")
    dims = _dims(p)
    side = TILE_CELLS * length / math.sqrt(dims)
    seen = length * (1 + 1e-6)
    sizes = {r.grp: r["count"] for r in p.groupBy("grp").count().collect()}
    big = [g for g, n in sizes.items() if n * dims > grown.TREE_NUMBERS]
    few = p.where(~F.col("grp").isin(big)) if big else p
    rows, keys = _tiles(few, dims, side, 1.5 * seen)

    def grow(key, t):
        t = t.sort_by("id")
        ids, x, low = t.column("id").to_numpy(), B._vectors(t), np.array([c.as_py() for c in key[1:]]) * side
        near = ((x >= low - seen / 2) & (x <= low + side + seen / 2)).all(1)
        inner = ((x > low + 0.501 * seen) & (x < low + side - 0.501 * seen)).all(1)
        u, v, w, core = grown.region_forest(x, k, near, length)
        stays, name = grown.settled(len(ids), u, v, w, near & ~inner)
        own = np.flatnonzero((np.floor(x / side) * side == low).all(1))
        u, v = np.minimum(ids[u], ids[v]), np.maximum(ids[u], ids[v])
        home, sizes = ids[name], [int(stays.sum()), int((~stays).sum()), len(own)]
        none = [pa.nulls(n, pa.int64()) for n in sizes]
        left = np.searchsorted(ids, u[~stays]), np.searchsorted(ids, v[~stays])
        cols = {
            "u": [u[stays], u[~stays], ids[own]], "v": [v[stays], v[~stays], none[2]], "w": [w[stays], w[~stays], core[own]],
            "a": [none[0], home[left[0]], home[own]], "b": [none[0], home[left[1]], none[2]],
        }
        cols = {c: pa.concat_arrays([x if isinstance(x, pa.Array) else pa.array(x) for x in parts]) for c, parts in cols.items()}
        places = pa.ListArray.from_arrays(pa.array(np.arange(0, len(own) * dims + 1, dims), pa.int32()), x[own].ravel())
        return pa.table({
            "grp": pa.repeat(pa.scalar(key[0].as_py(), pa.string()), sum(sizes)), "kind": np.repeat(np.array([TREE, OPEN, OWN], np.int32), sizes), **cols,
            "x": pa.concat_arrays([pa.nulls(sizes[0] + sizes[1], places.type), places]),
        })

    told = materialise(rows.groupBy("grp", *keys).applyInArrow(grow, TILE), "tiles")

    def choose(key, t):
        u, v, w, a, b = (t.column(c).to_numpy() for c in "uvwab")
        order = np.lexsort((v, u, w))
        at, place = np.unique(np.concatenate([a, b]), return_inverse=True)
        kept = order[kept_edges(len(at), place[: len(a)][order], place[len(a) :][order])]
        return pa.table({"grp": pa.repeat(pa.scalar(key[0].as_py(), pa.string()), len(kept)), "u": u[kept], "v": v[kept], "w": w[kept], "a": a[kept], "b": b[kept]})

    chosen = materialise(told.where(F.col("kind") == OPEN).select("grp", "u", "v", "w", "a", "b").groupBy("grp").applyInArrow(choose, EDGES + ", a long, b long"), "chosen")
    tree = told.where(F.col("kind") == TREE).select("grp", "u", "v", "w").unionByName(chosen.select("grp", "u", "v", "w"))
    edges = {r.grp: r["count"] for r in tree.groupBy("grp").count().collect()}
    apart = [g for g, n in sizes.items() if g not in big and n > k and edges.get(g, 0) < n - 1]
    if apart:
        def join(key, t, e):
            ids = t.column("u").to_numpy()
            by = np.argsort(ids, kind="stable")
            at = lambda c: by[np.searchsorted(ids, c.to_numpy(), sorter=by)]
            home = least_labels(len(ids), at(e.column("a")), at(e.column("b")))[at(t.column("a"))]
            u, v, w = grown.joined_up(B._vectors(t), t.column("w").to_numpy(), k, home)
            return _edge_rows(key[0], np.minimum(ids[u], ids[v]), np.maximum(ids[u], ids[v]), w)

        own = told.where(F.col("kind") == OWN).where(F.col("grp").isin(apart)).select("grp", "u", "w", "a", "x")
        tree = tree.unionByName(materialise(own.groupBy("grp").cogroup(chosen.select("grp", "a", "b").groupBy("grp")).applyInArrow(
            lambda key, t, e: join(key, t, e) if len(t) else _edge_rows(key[0], *[np.empty(0, np.int64)] * 2, np.empty(0)), EDGES), "joined"))
    return tree.unionByName(reach_tree(p.where(F.col("grp").isin(big)), k)[0].select("grp", "u", "v", "w")) if big else tree


def _edge_rows(grp: pa.Scalar, u, v, w) -> pa.Table:
    return pa.table({"grp": pa.repeat(pa.scalar(grp.as_py(), pa.string()), len(u)), "u": u, "v": v, "w": w})


def tree_edges_within(points: DataFrame, k: int, squares: list[float]) -> DataFrame:
    """``(grp, most, edges)``: how many edges of a least spanning tree of mutual reachabilities are within each of ``squares`` (lengths,
    squared). See :func:`tile_tree`."""
    at = lambda df, *c: df.select("grp", *c, F.explode(F.array(*[F.lit(float(s)) for s in squares])).alias("most"))
    found = at(tile_tree(points, k, math.sqrt(max(squares))), "w").groupBy("grp", "most").agg(F.count_if(F.col("w") <= F.sqrt("most")).alias("edges"))
    every = at(B.measurable(points).select("grp").distinct())
    return every.join(found, ["grp", "most"], "left").select("grp", "most", F.coalesce("edges", F.lit(0)).alias("edges"))
