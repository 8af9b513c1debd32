"""The condensed hierarchy of a forest of any size, and labels from it, as joins around bounded array tasks.

Linkage by levels needs only this of what lies above a level: which points are together, and how many. A component of at least the
least size is some node, whichever; a smaller one is a set of points that will leave together. So a forest is halved at the median of
its levels: each component of the upper half is a problem of its own, and the lower half is one problem whose vertices are those
components. Both go on independently, level by level of the halving, until problems are small enough for a task. Components are
named by their least point and their size, which no other component shares, so what tasks say of each other's components fits together
by equi-joins. All edges of one level are taken together; a problem of a single level needs no task at all.
"""

from __future__ import annotations

from collections.abc import Iterator

import heapq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from spurline.operators import kernels as K
from spurline.operators.components import components
from spurline.runtime import materialise

#: Edges of a problem that one task takes, and nodes of one condensed tree that one task selects from.
TASK_EDGES, TASK_NODES = 100_000, 5_000_000
EVENTS = "grp string, kind string, c long, s long, node_c long, node_s long, level double, size long"
KEY = ["grp", "q", "comp"]


class _Events:
    """Columns of EVENTS for one group at a time."""

    def __init__(self):
        self.rows: list[tuple] = []

    def add(self, *row) -> None:
        self.rows.append(row)

    def batch(self) -> pa.RecordBatch:
        kinds = [pa.string(), pa.string(), *[pa.int64()] * 4, pa.float64(), pa.int64()]
        columns = list(zip(*self.rows, strict=True)) or [()] * 8
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, kinds, strict=True)], names=[f.split()[0] for f in EVENTS.split(", ")])


def walk(groups: list, problem: np.ndarray, a: np.ndarray, sa: np.ndarray, b: np.ndarray, sb: np.ndarray, level: np.ndarray, least: int) -> _Events:
    """What happens in the problems (numbers into ``groups``) when their edges are taken from high levels to low:

    ``exit``: the points of component (c, s) leave in a node at a level; ``part``: component (c, s) ends as part of another that is too
    small for a node; ``born``: node (c, s) parts from its parent; ``top``: component (c, s) ends in a node.
    """
    ends = np.rec.fromarrays([np.concatenate([problem, problem]), np.concatenate([a, b])], names="p,v")
    found, first, place = np.unique(ends, return_index=True, return_inverse=True)
    size = np.concatenate([sa, sb])[first].tolist()
    name, of, n = found.v.tolist(), found.p.tolist(), len(found)
    ia, ib = place[: len(a)], place[len(a) :]
    root, low, own_size = list(range(n)), list(name), list(size)
    node = [(name[i], size[i]) if size[i] >= least else None for i in range(n)]
    loose = {i: [i] for i in range(n) if node[i] is None}
    out = _Events()

    def find(x: int) -> int:
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    order = np.argsort(-level, kind="stable")
    cuts = np.flatnonzero(np.diff(level[order])) + 1
    for span in np.split(order, cuts) if len(order) else []:
        lv, meet = float(level[span[0]]), {}
        for e in span.tolist():
            x, y = find(int(ia[e])), find(int(ib[e]))
            if x != y:
                x, y = (x, y) if own_size[x] >= own_size[y] else (y, x)
                both = meet.pop(x, {x}) | meet.pop(y, {y})
                root[y] = x
                meet[x] = both
        for top, parts in meet.items():
            total, least_id = sum(own_size[p] for p in parts), min(low[p] for p in parts)
            carriers = [p for p in parts if node[p] is not None]
            points = [x for p in parts if node[p] is None for x in loose.pop(p)]
            grp, own = groups[of[top]], None
            if not carriers and total < least:
                loose[top] = points
            else:
                own = node[carriers[0]] if len(carriers) == 1 else (least_id, total)
                if len(carriers) > 1:
                    for p in carriers:
                        out.add(grp, "born", *node[p], *own, lv, own_size[p])
                for x in points:
                    out.add(grp, "exit", name[x], size[x], *own, lv, None)
            own_size[top], low[top], node[top] = total, least_id, own
    for i in range(n):
        if root[i] == i:
            grp = groups[of[i]]
            if node[i] is None:
                for x in loose[i]:
                    out.add(grp, "part", name[x], size[x], low[i], own_size[i], None, None)
            else:
                out.add(grp, "top", low[i], own_size[i], *node[i], None, None)
    return out


def _walk_tasks(edges: DataFrame, least: int) -> DataFrame:
    """Events of whole problems; many small ones go through one walk together."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.Table] = []

        def done(t: pa.Table) -> pa.RecordBatch:
            cols = {c: t.column(c).to_numpy() for c in ("q", "comp", "a", "sa", "b", "sb", "level")}
            grp = t.column("grp").to_pylist()
            new = np.ones(len(grp), bool)
            new[1:] = (cols["q"][1:] != cols["q"][:-1]) | (cols["comp"][1:] != cols["comp"][:-1]) | np.array([x != y for x, y in zip(grp, grp[1:], strict=False)], bool)
            problem = np.cumsum(new) - 1
            names = [grp[i] for i in np.flatnonzero(new)]
            return walk(names, problem, cols["a"], cols["sa"], cols["b"], cols["sb"], cols["level"], least).batch()

        for batch in batches:
            held.append(pa.Table.from_batches([batch]))
            t = pa.concat_tables(held)
            if len(t) >= TASK_EDGES // 4:  # all but the last problem, which may go on in the next batch
                last = tuple(t.column(c)[len(t) - 1].as_py() for c in KEY)
                same = np.logical_and.reduce([np.array([x == y for x in t.column(c).to_pylist()]) for c, y in zip(KEY, last, strict=True)])
                cut = int(np.flatnonzero(same)[0])
                if cut:
                    yield done(t.slice(0, cut))
                held = [t.slice(cut)]
        if held and sum(map(len, held)):
            yield done(pa.concat_tables(held))

    rows = edges.repartition(int(edges.sparkSession.conf.get("spark.sql.shuffle.partitions")), *KEY).sortWithinPartitions(*KEY)
    return rows.select(*KEY, "a", "sa", "b", "sb", "level").mapInArrow(run, EVENTS)


def _vertices(edges: DataFrame) -> DataFrame:
    return edges.select(*KEY, F.col("a").alias("v"), F.col("sa").alias("s")).unionByName(edges.select(*KEY, F.col("b").alias("v"), F.col("sb").alias("s"))).distinct()


def _one_level(edges: DataFrame, least: int) -> DataFrame:
    """Events of problems whose edges all have one level: all vertices meet at once. They have at least ``least`` points."""
    total = _vertices(edges).groupBy(*KEY).agg(F.sum("s").alias("total"), F.count_if(F.col("s") >= least).alias("carriers"), F.max(F.when(F.col("s") >= least, F.struct("v", "s"))).alias("one"))
    lv = edges.groupBy(*KEY).agg(F.max("level").alias("level"))
    own = F.when(F.col("carriers") == 1, F.col("one")).otherwise(F.struct(F.col("comp").alias("v"), F.col("total").alias("s")))
    total = total.join(lv, KEY).withColumn("own", own)
    v = _vertices(edges).join(total, KEY)
    row = lambda kind, c, s, level, size: [F.col("grp"), F.lit(kind).alias("kind"), c.alias("c"), s.alias("s"), F.col("own.v").alias("node_c"), F.col("own.s").alias("node_s"), level.cast("double").alias("level"), size.cast("long").alias("size")]
    exits = v.where(F.col("s") < least).select(*row("exit", F.col("v"), F.col("s"), F.col("level"), F.lit(None)))
    born = v.where((F.col("s") >= least) & (F.col("carriers") > 1)).select(*row("born", F.col("v"), F.col("s"), F.col("level"), F.col("s")))
    return exits.unionByName(born).unionByName(total.select(*row("top", F.col("comp"), F.col("total"), F.lit(None), F.lit(None))))


def _resolved(pointers: DataFrame, max_rounds: int = 64) -> DataFrame:
    """``(grp, c, s, node_c, node_s)`` with every pointer at its end, by jumping."""
    now = materialise(pointers.select("grp", "c", "s", "node_c", "node_s"), "pointers")
    for _ in range(max_rounds):
        ahead = now.where("c <> node_c or s <> node_s").select("grp", F.col("c").alias("node_c"), F.col("s").alias("node_s"), F.col("node_c").alias("next_c"), F.col("node_s").alias("next_s"))
        new = materialise(now.join(ahead, ["grp", "node_c", "node_s"], "left").select("grp", "c", "s", F.coalesce("next_c", "node_c").alias("node_c"), F.coalesce("next_s", "node_s").alias("node_s"), F.col("next_c").isNotNull().alias("moved")), "pointers")
        now = new.drop("moved")
        if new.where("moved").isEmpty():
            return now
    raise RuntimeError("pointers do not end")


def condense(edges: DataFrame, least: int, task_edges: int = TASK_EDGES) -> tuple[DataFrame, DataFrame]:
    """Points ``(grp, id, node_c, node_s, level)`` that leave in a node, and nodes ``(grp, node_c, node_s, parent_c, parent_s, birth, size)``
    of the condensed hierarchy of a forest (``grp, u, v, level``); roots have no parent and birth 0. ``grp`` is not null."""
    if task_edges < least:
        raise ValueError("a task must take at least as many edges as a node has points")
    base = materialise(edges.select("grp", "u", "v", "level"), "forest")
    home = components(base.select("grp", "u", "v"), keys=("grp",))
    left = base.join(home.select("grp", F.col("id").alias("u"), F.col("component").alias("comp")), ["grp", "u"]).select("grp", F.lit(1).cast("long").alias("q"), "comp", F.col("u").alias("a"), F.lit(1).cast("long").alias("sa"), F.col("v").alias("b"), F.lit(1).cast("long").alias("sb"), "level")
    left, events = materialise(left, "problems"), []
    for _ in range(62):
        stats = left.groupBy(*KEY).agg(F.count(F.lit(1)).alias("n"), F.min("level").alias("lo"), F.max("level").alias("hi"), F.percentile_approx("level", 0.5, 1000).alias("mid"))
        big = materialise(stats.where(F.col("n") > task_edges).drop("n"), "big")
        if big.isEmpty():
            events.append(_walk_tasks(left, least))
            break
        events.append(materialise(_walk_tasks(left.join(big, KEY, "left_anti"), least), "events"))
        rows = left.join(big, KEY)
        events.append(materialise(_one_level(rows.where("lo = hi").select(*left.columns), least), "events"))
        rows = rows.where("lo < hi").withColumn("upper", F.when(F.col("mid") == F.col("lo"), F.col("level") > F.col("lo")).otherwise(F.col("level") >= F.col("mid")))
        rows = materialise(rows.select(*left.columns, "upper"), "halves")
        upper = rows.where("upper").drop("upper")
        inside = components(upper.select(*KEY, F.col("a").alias("u"), F.col("b").alias("v")), keys=tuple(KEY)).select(*KEY, F.col("id").alias("v"), F.col("component").alias("c"))
        inside = materialise(inside, "inside")
        sizes = _vertices(upper).join(inside, [*KEY, "v"]).groupBy(*KEY, "c").agg(F.sum("s").alias("cs"))
        named = materialise(inside.join(sizes, [*KEY, "c"]), "inside")
        above = upper.join(inside.withColumnRenamed("v", "a"), [*KEY, "a"]).select("grp", (F.col("q") * 2).alias("q"), F.col("c").alias("comp"), "a", "sa", "b", "sb", "level")
        below = rows.where("not upper").drop("upper")
        for end, s in (("a", "sa"), ("b", "sb")):
            below = below.join(named.withColumnRenamed("v", end), [*KEY, end], "left").withColumn(end, F.coalesce("c", end)).withColumn(s, F.coalesce("cs", s)).select(*left.columns)
        left = materialise(above.unionByName(below.withColumn("q", F.col("q") * 2 + 1)), "problems")
    else:
        raise RuntimeError("levels are still being halved")
    every = events[0]
    for part in events[1:]:
        every = every.unionByName(part)
    every = materialise(every, "events")
    tops = _resolved(every.where("kind = 'top'"))
    ahead = tops.select("grp", F.col("c").alias("node_c"), F.col("s").alias("node_s"), F.col("node_c").alias("t_c"), F.col("node_s").alias("t_s"))
    at = lambda df: df.join(ahead, ["grp", "node_c", "node_s"], "left").withColumn("node_c", F.coalesce("t_c", "node_c")).withColumn("node_s", F.coalesce("t_s", "node_s")).drop("t_c", "t_s")
    exits = at(every.where("kind = 'exit'").select("grp", "c", "s", "node_c", "node_s", "level"))
    parts = every.where("kind = 'part' and (c <> node_c or s <> node_s)")
    ends = _resolved(parts).where("s = 1").select("grp", F.col("c").alias("id"), F.col("node_c").alias("c"), F.col("node_s").alias("s"))
    direct = exits.where("s = 1").select("grp", F.col("c").alias("id"), "node_c", "node_s", "level")
    points = materialise(direct.unionByName(ends.join(exits.where("s > 1"), ["grp", "c", "s"]).select("grp", "id", "node_c", "node_s", "level")), "exits")
    children = at(every.where("kind = 'born'").select("grp", F.col("node_c").alias("parent_c"), F.col("node_s").alias("parent_s"), F.col("c").alias("node_c"), F.col("s").alias("node_s"), F.col("level").alias("birth"), "size"))
    roots = tops.groupBy("grp", "node_c", "node_s").agg(F.max("s").alias("size")).join(children, ["grp", "node_c", "node_s"], "left_anti")
    none = F.lit(None).cast("long")
    nodes = children.select("grp", "node_c", "node_s", "parent_c", "parent_s", "birth", "size").unionByName(roots.select("grp", "node_c", "node_s", none.alias("parent_c"), none.alias("parent_s"), F.lit(0.0).alias("birth"), "size"))
    return points, materialise(nodes, "nodes")


class SummedTree(K.Tree):
    """A condensed tree that knows of its points only how many leave in each node, the sum of their levels and the greatest."""

    def __init__(self, parent, birth, size, count, total, most):
        super().__init__(list(parent), list(birth), list(size))
        self.count, self.total, self.most = list(count), list(total), list(most)

    def stability(self) -> np.ndarray:
        out = np.array(self.total, float) - np.array(self.count, float) * np.array(self.birth, float)
        for c, p in enumerate(self.parent):
            if p >= 0:
                out[p] += self.size[c] * (self.birth[c] - self.birth[p])
        return out

    def top(self) -> np.ndarray:
        out = np.maximum(np.array(self.birth, float), np.array(self.most, float))
        for c, p in enumerate(self.parent):
            if p >= 0:
                out[p] = max(out[p], self.birth[c])
        return out

    def pruned(self, persistence: float) -> tuple[SummedTree, list[int], np.ndarray]:
        """Leaves whose range is not above ``persistence`` merged into their parents, the least range first; for each old node, its
        new one, and the level at which its points leave at most."""
        n = len(self.parent)
        kids, into, cap = [set(k) for k in self.children()], list(range(n)), np.full(n, np.inf)
        parent, count, total, most = list(self.parent), list(self.count), list(self.total), list(self.most)
        span = lambda i: max([most[i], self.birth[i], *(self.birth[k] for k in kids[i])]) - self.birth[i]
        todo = [(span(i), i) for i in range(n) if not kids[i] and parent[i] >= 0]
        heapq.heapify(todo)
        gone = set()
        while persistence > 0 and todo:
            r, c = heapq.heappop(todo)
            if c in gone or kids[c] or r > persistence:
                continue
            p = parent[c]
            into[c], cap[c] = p, self.birth[c]
            count[p], total[p] = count[p] + count[c], total[p] + count[c] * self.birth[c]
            most[p] = max(most[p], self.birth[c]) if count[c] else most[p]
            gone.add(c)
            kids[p].discard(c)
            if len(kids[p]) == 1:
                (k,) = kids[p]
                into[k], kids[p] = p, kids[k]
                for x in kids[p]:
                    parent[x] = p
                count[p], total[p], most[p] = count[p] + count[k], total[p] + total[k], max(most[p], most[k])
                gone.add(k)
            if not kids[p] and parent[p] >= 0:
                heapq.heappush(todo, (span(p), p))
        keep = [i for i in range(n) if i not in gone]
        new = {old: i for i, old in enumerate(keep)}
        for i in reversed(range(n)):  # parents come after their children
            if into[i] != i:
                cap[i] = min(cap[i], cap[into[i]])
        home = list(range(n))
        for i in reversed(range(n)):
            home[i] = home[into[i]] if into[i] != i else i
        out = SummedTree([new.get(parent[i], -1) for i in keep], [self.birth[i] for i in keep], [self.size[i] for i in keep], [count[i] for i in keep], [total[i] for i in keep], [most[i] for i in keep])
        return out, [new[h] for h in home], cap


def _with_counts(points: DataFrame, nodes: DataFrame) -> DataFrame:
    told = points.groupBy("grp", "node_c", "node_s").agg(F.count(F.lit(1)).alias("n"), F.sum("level").alias("total"), F.max("level").alias("most"))
    return nodes.join(told, ["grp", "node_c", "node_s"], "left")


def _tree_of(pdf):
    """The rows of one group's nodes, children before their parents, and their tree."""
    if len(pdf) > TASK_NODES:
        raise ValueError(f"{len(pdf)} nodes in a tree; at most {TASK_NODES} are selected from")
    pdf = pdf.sort_values(["birth", "size", "node_c"], ascending=[False, True, True], kind="stable").reset_index(drop=True)
    place = {x: i for i, x in enumerate(zip(pdf["node_c"], pdf["node_s"], strict=True))}
    parent = [place.get((c, s), -1) for c, s in zip(pdf["parent_c"], pdf["parent_s"], strict=True)]
    return pdf, SummedTree(parent, pdf["birth"], pdf["size"].astype(int), pdf["n"].fillna(0).astype(int), pdf["total"].fillna(0.0), pdf["most"].fillna(-np.inf))


def tree_table(points: DataFrame, nodes: DataFrame, make, schema: str, persistence: float = 0.0) -> DataFrame:
    """``make(tree)``'s columns for each group's tree, after pruning; see :func:`pick` for its bound."""
    import pandas as pd

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        grp = pdf["grp"].iloc[0]
        return make(_tree_of(pdf)[1].pruned(persistence)[0]).assign(grp=grp)

    return _with_counts(points, nodes).groupBy("grp").applyInPandas(run, schema)


PICKED = "grp string, node_c long, node_s long, home_c long, home_s long, top double, cap double, chosen int, whole boolean"


def pick(points: DataFrame, nodes: DataFrame, how: str, allow_root: bool, epsilon: float = 0.0, persistence: float = 0.0) -> DataFrame:
    """PICKED rows, one for each node: the selected node it belongs to (null: none), that node's greatest level, the level at which the
    node's points leave at most, how many nodes its group selects, and whether that is the root alone.

    One task takes the nodes of one group, which are fewer than its points over half the least size; over TASK_NODES raise.
    """
    def run(key, t):
        pdf = t.to_pandas()
        pdf, whole_tree = _tree_of(pdf)
        tree, home, cap = whole_tree.pruned(persistence)
        chosen = K.select(tree, how, allow_root, epsilon)
        top, at = tree.top(), [-1] * len(tree.parent)
        own, kids = set(chosen), tree.children()
        todo = [(i, -1) for i, p in enumerate(tree.parent) if p < 0]
        while todo:
            i, h = todo.pop()
            at[i] = i if i in own else h
            todo += [(k, at[i]) for k in kids[i]]
        back = {}
        for old, new in enumerate(home):  # of the nodes that became one, the last is its oldest, which names it
            back[new] = old
        whole = len(chosen) == 1 and tree.parent[chosen[0]] < 0 and epsilon == 0
        named = [back[at[h]] if at[h] >= 0 else None for h in home]
        c, s = pdf["node_c"].tolist(), pdf["node_s"].tolist()
        none = lambda x, of: None if x is None else of[x]
        return pa.table({"grp": pa.array([key[0].as_py()] * len(pdf), pa.string()), "node_c": pa.array(c, pa.int64()), "node_s": pa.array(s, pa.int64()), "home_c": pa.array([none(x, c) for x in named], pa.int64()), "home_s": pa.array([none(x, s) for x in named], pa.int64()), "top": pa.array([float(top[at[h]]) if at[h] >= 0 else None for h in home], pa.float64()), "cap": pa.array(cap, pa.float64()), "chosen": pa.array([len(chosen)] * len(pdf), pa.int32()), "whole": pa.array([whole] * len(pdf), pa.bool_())})

    return materialise(_with_counts(points, nodes).groupBy("grp").applyInArrow(run, PICKED), "picked")


def flat_labels(vertices: DataFrame, points: DataFrame, picked: DataFrame) -> DataFrame:
    """``(grp, id, label, strength)`` of all ``vertices`` (``grp, id``): labels numbered by their least point, -1 and strength 0 for
    those outside; where the root alone is selected every point of the group has label 0."""
    rows = points.join(picked, ["grp", "node_c", "node_s"]).where("home_c is not null")
    level = F.least("level", "cap", "top")
    rows = materialise(rows.select("grp", "id", "home_c", "home_s", (level / F.when(F.col("top") > 0, F.col("top")).otherwise(1.0)).alias("strength")), "homes")
    first = rows.groupBy("grp", "home_c", "home_s").agg(F.min("id").alias("first"))
    number = first.withColumn("label", (F.row_number().over(Window.partitionBy("grp").orderBy("first")) - 1).cast("int")).drop("first")
    whole = picked.where("whole").select("grp").distinct().withColumn("whole", F.lit(0))
    found = rows.join(number, ["grp", "home_c", "home_s"]).select("grp", "id", "label", "strength")
    out = vertices.select("grp", "id").join(found, ["grp", "id"], "left").join(whole, "grp", "left")
    return out.select("grp", "id", F.coalesce("whole", "label", F.lit(-1)).cast("int").alias("label"), F.coalesce("strength", F.lit(0.0)).alias("strength"))
