"""Registered queries and their DuckDB SQL, side by side."""

from __future__ import annotations

import dataclasses

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from spurline.operators import baselines as B
from spurline.operators import kernels as K
from spurline.operators import neighbors as N
from spurline.operators import summaries as Y
from spurline.operators.blocks import knn
from spurline.operators.components import components
from spurline.operators.forest import spanning_forest
from spurline.params import BranchParams
from spurline.plans import clustering as C
from spurline.plans import packs as G
from spurline.runtime import materialise, merged, table
from spurline.sources import workloads as W
from spurline.streaming import windows as S

QUERIES, ORACLES = {}, {}
BEST = BranchParams(min_samples=5, min_cluster_size=25, min_branch_size=12, allow_single_cluster=True, branch_selection="leaf", central_labels="geodesic")
LEAF_DENSITY = BranchParams(min_samples=5, min_cluster_size=8, cluster_selection="leaf")
STAR_SQL = W.star_sql()
PAIRS = f"s AS MATERIALIZED ({STAR_SQL}), pairs AS MATERIALIZED (SELECT a.id AS id, b.id AS nbr, (a.px - b.px) * (a.px - b.px) + (a.py - b.py) * (a.py - b.py) AS d2 FROM s a JOIN s b ON a.sample = b.sample AND a.id <> b.id), ranked AS (SELECT *, rank() OVER (PARTITION BY id ORDER BY d2) AS rank FROM pairs), knn AS MATERIALIZED (SELECT * FROM ranked WHERE rank <= 5), core AS MATERIALIZED (SELECT id, max(d2) AS c2 FROM knn GROUP BY id)"
CORE_SQL = "graph AS MATERIALIZED (SELECT p.id AS u, p.nbr AS v, p.d2 FROM pairs p JOIN core a ON a.id = p.id JOIN core b ON b.id = p.nbr WHERE p.id < p.nbr AND p.d2 <= greatest(a.c2, b.c2))"


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


def star(spark: SparkSession, d: str) -> DataFrame:
    """All samples of the star, coordinates in whole units, so that squared distances are exact."""
    return W.star_points(table(spark, d, "orders")).withColumn("x", F.array(F.col("px").cast("double"), F.col("py").cast("double")))


def star_nn(spark: SparkSession, d: str) -> DataFrame:
    return materialise(knn(star(spark, d), 5), "star-knn")


def exact(d: F.Column) -> F.Column:
    return F.rint(d * d).cast("long")


@query(W.star_sql())
def star_points(spark, d):
    return W.star_points(table(spark, d, "orders")).select("id", "sample", "arm", "px", "py")


_GRID = [(a, b, W.lengths(a), W.noises(b)) for a in range(10) for b in range(10)]


@query("SELECT CAST(a AS INTEGER) AS j_l, CAST(b AS INTEGER) AS j_n, CAST(o_orderkey // 300 AS BIGINT) AS sample, count(*) AS n FROM orders, range(10) t(a), range(10) r(b) GROUP BY ALL")
def star_grid_sizes(spark, d):
    return W.star_grid(table(spark, d, "orders"), _GRID).groupBy("j_l", "j_n", "sample").agg(F.count(F.lit(1)).alias("n"))


@query(W.walk_sql())
def walk_points(spark, d):
    return W.walk_points(table(spark, d, "events")).select("user_id", "step", "start", "p0", "p1")


@query(f"SELECT start, count(*) AS n, min(p0) AS low0, max(p0) AS high0, min(p7) AS low7, max(p7) AS high7 FROM ({W.walk_sql(8)}) GROUP BY start")
def walk_extent(spark, d):
    return W.walk_points(table(spark, d, "events"), 8).groupBy("start").agg(F.count(F.lit(1)).alias("n"), *[f(c).alias(f"{n}{c[1]}") for c in ("p0", "p7") for n, f in (("low", F.min), ("high", F.max))])


@query("SELECT vec_id, i - 1 AS axis, round(CAST(embedding[i] AS DOUBLE), 6) AS value FROM embeddings, range(1, 65) t(i)")
def embedding_long(spark, d):
    return table(spark, d, "embeddings").select("vec_id", F.posexplode("embedding").alias("axis", "v")).select("vec_id", F.col("axis").cast("long").alias("axis"), F.round(F.col("v").cast("double"), 6).alias("value"))


@query(f"WITH {PAIRS} SELECT id, nbr, d2, rank FROM knn")
def star_knn(spark, d):
    return star_nn(spark, d).select("id", "nbr", exact(F.col("d")).alias("d2"), F.col("rank").cast("long").alias("rank"))


@query(f"WITH s AS (SELECT user_id * 50 + step AS id, p0, p1 FROM ({W.walk_sql()})), ranked AS (SELECT a.id AS id, b.id AS nbr, (a.p0 - b.p0) * (a.p0 - b.p0) + (a.p1 - b.p1) * (a.p1 - b.p1) AS d2, rank() OVER (PARTITION BY a.id ORDER BY (a.p0 - b.p0) * (a.p0 - b.p0) + (a.p1 - b.p1) * (a.p1 - b.p1)) AS rank FROM s a, s b WHERE a.id <> b.id) SELECT id, nbr, CAST(d2 AS BIGINT) AS d2 FROM ranked WHERE rank <= 10")
def walk_knn(spark, d):
    pts = materialise(W.walk_points(table(spark, d, "events")).withColumn("x", F.array(F.col("p0").cast("double"), F.col("p1").cast("double"))), "walk")
    return knn(pts, 10).select("id", "nbr", exact(F.col("d")).alias("d2"))


@query(f"WITH {PAIRS} SELECT id, c2 FROM core")
def star_core(spark, d):
    """Core distances, squared: whole numbers."""
    return N.core_distance(star_nn(spark, d), 5).select("id", exact(F.col("core")).alias("c2"))


@query(f"WITH {PAIRS} SELECT p.id AS u, p.nbr AS v, greatest(p.d2, a.c2, b.c2) AS w2 FROM pairs p JOIN core a ON a.id = p.id JOIN core b ON b.id = p.nbr WHERE p.id < p.nbr")
def star_reach_edges(spark, d):
    return N.reach_pairs(star(spark, d), N.core_distance(star_nn(spark, d), 5)).select("u", "v", exact(F.col("w")).alias("w2"))


@query(f"WITH {PAIRS}, {CORE_SQL} SELECT u, v, d2 FROM graph")
def star_core_graph(spark, d):
    nn = star_nn(spark, d)
    return N.graph_core(nn, N.core_distance(nn, 5)).select("u", "v", exact(F.col("d")).alias("d2"))


@query(f"WITH {PAIRS} SELECT DISTINCT least(id, nbr) AS u, greatest(id, nbr) AS v FROM knn")
def star_core_graph_lists(spark, d):
    return star_nn(spark, d).select(F.least("id", "nbr").alias("u"), F.greatest("id", "nbr").alias("v")).distinct()


@query(f"WITH {PAIRS} SELECT a.id AS u, a.nbr AS v FROM knn a JOIN knn b ON a.id = b.nbr AND a.nbr = b.id WHERE a.id < a.nbr")
def star_mutual_graph(spark, d):
    return N.graph_mutual(star_nn(spark, d)).select("u", "v")


@query(f"WITH {PAIRS}, {CORE_SQL}, m AS (SELECT a.id AS u, a.nbr AS v, a.d2 FROM knn a JOIN knn b ON a.id = b.nbr AND a.nbr = b.id WHERE a.id < a.nbr) SELECT 'core' AS kind, count(*) AS edges, round(2.0 * count(*) / (SELECT count(*) FROM s), 6) AS degree FROM graph UNION ALL SELECT 'mutual', count(*), round(2.0 * count(*) / (SELECT count(*) FROM s), 6) FROM m")
def star_graph_stats(spark, d):
    nn = star_nn(spark, d)
    both = N.graph_core(nn, N.core_distance(nn, 5)).select(F.lit("core").alias("kind")).unionByName(N.graph_mutual(nn).select(F.lit("mutual").alias("kind")))
    size = star(spark, d).agg(F.count(F.lit(1)).alias("n"))  # one row
    return both.groupBy("kind").agg(F.count(F.lit(1)).alias("edges")).join(size).select("kind", "edges", F.round(2.0 * F.col("edges") / F.col("n"), 6).alias("degree"))


_SIGNAL = "e AS (SELECT id, sample, sqrt((px - mx) * (px - mx) + (py - my) * (py - my)) / 1e4 AS value FROM s JOIN (SELECT sample, avg(px) AS mx, avg(py) AS my FROM s GROUP BY sample) USING (sample))"


def _signal(spark, d) -> DataFrame:
    p = star(spark, d)
    m = p.groupBy("grp").agg(F.avg("px").alias("mx"), F.avg("py").alias("my"))
    return materialise(p.join(m, "grp").select("grp", "id", (F.sqrt((F.col("px") - F.col("mx")) * (F.col("px") - F.col("mx")) + (F.col("py") - F.col("my")) * (F.col("py") - F.col("my"))) / 1e4).alias("value")), "signal")


def _core_graph(spark, d) -> DataFrame:
    nn = star_nn(spark, d)
    return materialise(N.graph_core(nn, N.core_distance(nn, 5)), "core-graph")


@query(f"WITH s AS ({STAR_SQL}), {_SIGNAL} SELECT id, round(value, 6) AS e FROM e")
def star_unit_eccentricity(spark, d):
    return _signal(spark, d).select("id", F.round("value", 6).alias("e"))


@query(f"WITH {PAIRS}, {CORE_SQL}, {_SIGNAL} SELECT u, v, round(least(a.value, b.value), 6) AS level FROM graph JOIN e a ON a.id = u JOIN e b ON b.id = v")
def star_edge_levels(spark, d):
    return N.level_edges(_core_graph(spark, d), _signal(spark, d)).select("u", "v", F.round("level", 6).alias("level"))


@query(f"WITH RECURSIVE {PAIRS}, {CORE_SQL}, {_SIGNAL}, t(threshold) AS (VALUES (2.0::DOUBLE), (5.0::DOUBLE), (10.0::DOUBLE)), n AS (SELECT threshold, id FROM e, t WHERE value >= threshold), links AS (SELECT u, v FROM graph UNION ALL SELECT v, u FROM graph), r(threshold, a, b) AS (SELECT threshold, id, id FROM n UNION SELECT r.threshold, r.a, links.v FROM r JOIN links ON links.u = r.b JOIN n ON n.id = links.v AND n.threshold = r.threshold) SELECT threshold, a AS id, min(b) AS component FROM r GROUP BY threshold, a")
def star_contours(spark, d):
    at = F.explode(F.array(*[F.lit(x) for x in (2.0, 5.0, 10.0)]))
    points = _signal(spark, d).select("id", "value", at.alias("threshold")).where("value >= threshold")
    edges = N.level_edges(_core_graph(spark, d), _signal(spark, d)).select("u", "v", "level", at.alias("threshold")).where("level >= threshold")
    return components(edges.select("threshold", "u", "v"), points.select("threshold", "id"), keys=("threshold",))


@query(f"WITH RECURSIVE {PAIRS}, {CORE_SQL}, links AS (SELECT u, v FROM graph UNION ALL SELECT v, u FROM graph), r(root, id, hops) AS (SELECT id, id, 0 FROM s WHERE id % 300 >= 297 UNION SELECT r.root, links.v, r.hops + 1 FROM r JOIN links ON links.u = r.id WHERE r.hops < 120) SELECT root, id, min(hops) AS hops FROM r GROUP BY root, id")
def star_hop_distances(spark, d):
    """Hops from the ends of the three arms of each sample."""
    g = _core_graph(spark, d)
    roots = star(spark, d).where("id % 300 >= 297").select("grp", F.col("id").alias("root"))
    return N.hop_distances(g, roots).select("root", "id", "hops")


@query(f"WITH {PAIRS}, {CORE_SQL}, {_SIGNAL}, near AS (SELECT u AS id, v AS o FROM graph UNION ALL SELECT v, u FROM graph UNION ALL SELECT id, id FROM e) SELECT near.id, round(avg(value), 6) AS value FROM near JOIN e ON e.id = near.o GROUP BY near.id")
def star_smoothed(spark, d):
    return N.smooth_signal(_core_graph(spark, d), _signal(spark, d)).select("id", F.round("value", 6).alias("value"))


@query(f"WITH {PAIRS}, {_SIGNAL} SELECT id, round(value + sqrt(c2) / 1e4, 6) AS value FROM e JOIN core USING (id)")
def star_pushed(spark, d):
    return _signal(spark, d).join(N.core_distance(star_nn(spark, d), 5), ["grp", "id"]).select("id", F.round(F.col("value") + F.col("core") / 1e4, 6).alias("value"))


@query(f"WITH {PAIRS} SELECT id, round(sum(sqrt(d2)) / 1e4, 4) AS total FROM pairs GROUP BY id")
def star_distance_sum(spark, d):
    return B.distance_sums(star(spark, d)).select("id", F.round(F.col("value") / 1e4, 4).alias("total"))


_LINKS = "links AS (SELECT id AS u, nbr AS v FROM pairs WHERE d2 <= 9000000)"


@query(f"WITH RECURSIVE {PAIRS}, {_LINKS}, r(a, b) AS (SELECT id, id FROM s UNION SELECT r.a, links.v FROM r JOIN links ON links.u = r.b) SELECT a AS id, min(b) AS component FROM r GROUP BY a")
def star_single_linkage_cut(spark, d):
    return C.single_linkage_cut(star(spark, d), 3000.0).select("id", "component")


def _pair_edges(p: DataFrame, radius: float) -> DataFrame:
    return Y.radius_pairs(p, p.select("grp").distinct().withColumn("reach", F.lit(radius)))


_SUMS = "t AS (SELECT id, sum(sqrt(d2)) / 1e4 AS total FROM pairs GROUP BY id)"


@query(f"WITH RECURSIVE {PAIRS}, {_SUMS}, n AS (SELECT id FROM t WHERE total >= 2000), links AS (SELECT id AS u, nbr AS v FROM pairs WHERE d2 <= 225000000), r(a, b) AS (SELECT id, id FROM n UNION SELECT r.a, links.v FROM r JOIN links ON links.u = r.b JOIN n ON n.id = links.v) SELECT a AS id, min(b) AS component FROM r GROUP BY a")
def star_core_removal(spark, d):
    p = star(spark, d)
    sums = B.distance_sums(p).select("grp", "id", (F.col("value") / 1e4).alias("value"))
    return B.core_removal(sums, _pair_edges(p, 15000.0), 2000.0, 15000.0).select("id", "component")


@query(f"WITH RECURSIVE {PAIRS}, {_SUMS}, g(e_index, r_index, e, r) AS (VALUES (0, 0, 0, 5000), (0, 1, 0, 15000), (1, 0, 2000, 5000), (1, 1, 2000, 15000)), n AS (SELECT e_index, r_index, r, id FROM t, g WHERE total >= e), c(e_index, r_index, r, a, b) AS (SELECT e_index, r_index, r, id, id FROM n UNION SELECT c.e_index, c.r_index, c.r, c.a, p.nbr FROM c JOIN pairs p ON p.id = c.b AND p.d2 <= c.r * c.r JOIN n ON n.id = p.nbr AND n.e_index = c.e_index AND n.r_index = c.r_index) SELECT CAST(sample AS VARCHAR) AS grp, e_index, r_index, count(DISTINCT m) AS components FROM (SELECT e_index, r_index, a, min(b) AS m FROM c GROUP BY ALL) JOIN s ON s.id = a GROUP BY ALL")
def star_component_grid(spark, d):
    p = star(spark, d)
    sums = B.distance_sums(p).select("grp", "id", (F.col("value") / 1e4).alias("value"))
    return B.component_grid(sums, _pair_edges(p, 15000.0), [0.0, 2000.0], [5000.0, 15000.0])


def _kmeans_sql(rounds: int) -> str:
    out = f"WITH s AS ({W.star_sql()}), c0 AS (SELECT sample, arm AS label, px::DOUBLE AS cx, py::DOUBLE AS cy FROM s WHERE (id // 3) % 100 = 50)"
    for i in range(rounds + 1):
        out += f", n{i} AS (SELECT s.id, s.sample, s.arm, s.px, s.py, arg_min(label, (((px - cx) * (px - cx) + (py - cy) * (py - cy)), label)) AS label FROM s JOIN c{i} USING (sample) GROUP BY ALL), c{i + 1} AS (SELECT sample, label, avg(px) AS cx, avg(py) AS cy FROM n{i} GROUP BY sample, label)"
    return out


def _kmeans(spark, d, rounds: int = 4) -> DataFrame:
    p = materialise(W.star_points(table(spark, d, "orders")).withColumn("x", F.array(F.col("px").cast("double"), F.col("py").cast("double"))), "stars")
    first = p.where("floor(id / 3) % 100 = 50").select("grp", F.col("arm").alias("label"), F.col("x").alias("c"))
    return B.kmeans(p, first, rounds).join(p.select("grp", "id", "sample", "arm", "px", "py"), ["grp", "id"])


@query(_kmeans_sql(4) + " SELECT id, label FROM n4")
def star_kmeans_rounds(spark, d):
    return _kmeans(spark, d).select("id", "label")


_ARI = """, cell AS (SELECT {k}, {t} AS t, {l} AS l, count(*) AS n FROM {src} GROUP BY ALL), a AS (SELECT {k}, sum(n * (n - 1) / 2.0) AS agreed, sum(n) AS total FROM cell GROUP BY {k}), bt AS (SELECT {k}, sum(n * (n - 1) / 2.0) AS x FROM (SELECT {k}, t, sum(n) AS n FROM cell GROUP BY ALL) GROUP BY {k}), bl AS (SELECT {k}, sum(n * (n - 1) / 2.0) AS y FROM (SELECT {k}, l, sum(n) AS n FROM cell GROUP BY ALL) GROUP BY {k})
SELECT {out}round(CAST(CASE WHEN (x + y) / 2 = x * y / (total * (total - 1) / 2.0) THEN 1 ELSE (agreed - x * y / (total * (total - 1) / 2.0)) / ((x + y) / 2 - x * y / (total * (total - 1) / 2.0)) END AS DOUBLE), 6) AS ari FROM a JOIN bt USING ({k}) JOIN bl USING ({k})"""


@query(_kmeans_sql(4) + _ARI.format(k="sample", t="arm", l="label", src="n4", out="sample, "))
def star_kmeans_ari(spark, d):
    return C.adjusted_rand(_kmeans(spark, d), "arm", "label", ("sample",)).select("sample", F.round("ari", 6).alias("ari"))


@query("WITH o AS (SELECT 0 AS k, o_orderstatus, o_orderpriority FROM orders)" + _ARI.format(k="k", t="o_orderstatus", l="o_orderpriority", src="o", out=""))
def ari_by_status(spark, d):
    return C.adjusted_rand(table(spark, d, "orders"), "o_orderstatus", "o_orderpriority").select(F.round("ari", 6).alias("ari"))


@query(_kmeans_sql(4) + ", tr AS (SELECT sample, arm, avg(px) AS tx, avg(py) AS ty FROM n4 GROUP BY ALL), near AS (SELECT c5.sample, label, cx, cy, arg_min(arm, (sqrt((cx - tx) * (cx - tx) + (cy - ty) * (cy - ty)), arm)) AS arm FROM c5 JOIN tr USING (sample) GROUP BY ALL), m AS (SELECT arm, avg(cx) AS mx, avg(cy) AS my FROM near GROUP BY arm) SELECT arm, count(*) AS groups, round(quantile_cont(sqrt((cx - mx) * (cx - mx) + (cy - my) * (cy - my)), 0.95) / 1e4, 4) AS spread95 FROM near JOIN m USING (arm) GROUP BY arm")
def spread_of_kmeans(spark, d):
    rows = _kmeans(spark, d).withColumn("strength", F.lit(1.0))
    return C.centroid_spread(rows, (), "sample").groupBy("arm").agg(F.count(F.lit(1)).alias("groups"), F.round(F.expr("percentile(spread, 0.95)") / 1e4, 4).alias("spread95"))


@query("SELECT CAST(o_orderkey // 300 AS BIGINT) AS sample, 3 AS found FROM orders GROUP BY 1 HAVING count(*) = 300")
def star_branches_truth(spark, d):
    """Without noise the planted truth is three branches in each sample."""
    p = W.star_points(table(spark, d, "orders"), n_r=0.0)
    return C.branch_clusters(p, BEST).where("label >= 0").groupBy("grp").agg(F.countDistinct("label").cast("int").alias("found")).select(F.col("grp").cast("long").alias("sample"), "found")


@query()
def star_worked(spark, d):
    """The worked cloud: flagship."""
    return C.branch_clusters(W.star_points(table(spark, d, "orders"), W.lengths(5), W.noises(5)), BEST)


@query()
def star_density(spark, d):
    return C.density_clusters(W.star_points(table(spark, d, "orders"), W.lengths(5), W.noises(5)), LEAF_DENSITY)


@query()
def star_heatmap(spark, d):
    """Mean ARI by length, noise and method over all samples of each of the hundred shapes, with margins."""
    found = G.method_scores(W.star_packs(table(spark, d, "orders"), _GRID), BEST, LEAF_DENSITY, 6)
    shapes = F.array(*[F.struct(F.lit(a).alias("j_l"), F.lit(b).alias("j_n")) for a, b, _, _ in _GRID])
    methods = F.array(*[F.lit(m) for m in ("branches", "density", "kmeans")])
    out = materialise(found, "scores").select(F.get(methods, F.col("setting")).alias("method"), F.get(shapes, F.col("shape")).alias("g"), "ari").select("method", "g.*", "ari")
    return out.rollup("method", "j_l", "j_n").agg(F.avg("ari").alias("ari"), F.count(F.lit(1)).alias("clouds"))


def _best_settings(spark, d, settings: list[BranchParams], branches: bool, names: list[F.Column]) -> DataFrame:
    found = materialise(G.grid_scores(W.star_packs(table(spark, d, "orders"), _GRID), settings, branches), "scores")
    return found.groupBy("setting").agg(F.avg("ari").alias("ari")).select("setting", F.get(F.array(*names), F.col("setting")).alias("p"), "ari").select("setting", "p.*", "ari").orderBy(F.desc("ari"), "setting")


@query()
def star_branch_grid(spark, d):
    """The parameter grid of the branch pass over all samples of the hundred shapes, best setting first by mean ARI."""
    settings = [dataclasses.replace(BEST, graph=g, branch_selection=s, min_branch_size=m) for g in ("full", "core") for s in ("eom", "leaf") for m in range(2, 25, 2)]
    return _best_settings(spark, d, settings, True, [F.struct(F.lit(s.graph).alias("graph"), F.lit(s.branch_selection).alias("selection"), F.lit(s.min_branch_size).alias("m_b")) for s in settings])


@query()
def star_density_grid(spark, d):
    """The parameter grid of the density baseline over all samples of the hundred shapes, best setting first by mean ARI."""
    settings = [dataclasses.replace(LEAF_DENSITY, cluster_selection=s, min_cluster_size=m) for s in ("eom", "leaf") for m in range(2, 25, 2)]
    return _best_settings(spark, d, settings, False, [F.struct(F.lit(s.cluster_selection).alias("selection"), F.lit(s.min_cluster_size).alias("m_c")) for s in settings])


@query()
def star_memberships_full(spark, d):
    return C.memberships(W.star_points(table(spark, d, "orders")), BEST)


@query()
def branch_tree(spark, d):
    return C.condensed(W.star_points(table(spark, d, "orders")), BEST, "branch")


@query()
def cluster_tree(spark, d):
    return C.condensed(W.star_points(table(spark, d, "orders")), LEAF_DENSITY, "cluster")


@query()
def star_label_adjacency(spark, d):
    """Which groups of a sample touch, over how many edges, and the strongest level of those."""
    p = star(spark, d)
    found = materialise(C.branch_clusters(p, BEST).select("grp", "id", "label"), "labels")
    return Y.label_adjacency(found, N.level_edges(_core_graph(spark, d), _signal(spark, d)))


@query()
def star_core_forest(spark, d):
    """Spanning forest of the core graph under mutual reachability, by joins alone."""
    return spanning_forest(_core_graph(spark, d).select("grp", "u", "v", "w")).select("u", "v", "w")


@query()
def walk_branches(spark, d):
    """All walks as one cloud."""
    return C.branch_clusters(W.walk_points(table(spark, d, "events")), BranchParams(min_samples=10, min_cluster_size=100, min_branch_size=20, allow_single_cluster=True))


@query()
def horseshoe_branches(spark, d):
    return C.branch_clusters(W.horseshoe_points(table(spark, d, "customer")), BranchParams(min_samples=5, min_cluster_size=100, min_branch_size=5, allow_single_cluster=True))


@query()
def tree_branches(spark, d):
    return C.branch_clusters(W.tree_points(table(spark, d, "orders")), BranchParams(min_samples=3, min_cluster_size=500, min_branch_size=50, allow_single_cluster=True, branch_selection="leaf"))


@query("SELECT o_orderstatus AS status, o_orderpriority AS priority, count(*) AS n FROM orders GROUP BY ROLLUP (1, 2)")
def rollup_groups(spark, d):
    return table(spark, d, "orders").rollup(F.col("o_orderstatus").alias("status"), F.col("o_orderpriority").alias("priority")).agg(F.count(F.lit(1)).alias("n"))


@query("SELECT o_orderstatus AS status, o_orderpriority AS priority, count(*) AS n FROM orders GROUP BY CUBE (1, 2)")
def cube_groups(spark, d):
    return table(spark, d, "orders").cube(F.col("o_orderstatus").alias("status"), F.col("o_orderpriority").alias("priority")).agg(F.count(F.lit(1)).alias("n"))


@query("SELECT date_trunc('day', ts) AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY ALL")
def daily_windows(spark, d):
    return S.event_windows(table(spark, d, "events")).select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", "n", F.round("total", 4).alias("total"))


@query("WITH g AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER w + INTERVAL 30 MINUTE OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS opens FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(opens) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM g) SELECT user_id, min(ts) AS start, count(*) AS n FROM s GROUP BY user_id, k")
def session_windows(spark, d):
    return S.sessions(table(spark, d, "events")).select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), "n")


@query("SELECT CAST(json_extract_string(props, '$.k') AS INTEGER) AS k, count(*) AS n FROM events GROUP BY 1")
def json_props(spark, d):
    return table(spark, d, "events").groupBy(F.from_json("props", "k int")["k"].alias("k")).agg(F.count(F.lit(1)).alias("n"))


@query("SELECT min(doc_id) AS first, count(*) AS copies FROM documents WHERE text IS NOT NULL GROUP BY text HAVING count(*) > 1")
def duplicate_texts(spark, d):
    return table(spark, d, "documents").where("text is not null").groupBy(F.sha2("text", 256).alias("h")).agg(F.min("doc_id").alias("first"), F.count(F.lit(1)).alias("copies")).where("copies > 1").drop("h")


@query("SELECT event_id, o_orderkey FROM (SELECT event_id, o_orderkey, row_number() OVER (PARTITION BY event_id ORDER BY o_orderdate DESC, o_orderkey DESC) AS r FROM events JOIN orders ON o_custkey = user_id AND o_orderdate <= ts) WHERE r = 1")
def asof_order_before_event(spark, d):
    """Both tables in one, by user and time: the last order not after an event, without forming the earlier ones."""
    o = table(spark, d, "orders").select(F.col("o_custkey").alias("user_id"), F.col("o_orderdate").alias("ts"), F.lit(None).cast("long").alias("event_id"), "o_orderkey")
    both = table(spark, d, "events").where("user_id is not null").select("user_id", "ts", "event_id", F.lit(None).cast("long").alias("o_orderkey")).unionByName(o)
    w = Window.partitionBy("user_id").orderBy("ts", F.col("event_id").isNotNull(), "o_orderkey").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("o_orderkey", F.last("o_orderkey", ignorenulls=True).over(w)).where("event_id is not null and o_orderkey is not null").select("event_id", "o_orderkey")


@query(f"WITH {PAIRS} SELECT s.id FROM s WHERE NOT EXISTS (SELECT 1 FROM pairs p WHERE p.id = s.id AND d2 <= 1000000)")
def anti_isolated_points(spark, d):
    near = _pair_edges(star(spark, d), 1000.0)
    ends = near.select(F.col("u").alias("id")).unionByName(near.select(F.col("v").alias("id")))
    return star(spark, d).select("id").join(merged(ends), "id", "left_anti")


@query("SELECT c_custkey, o_orderkey, CAST(place AS INTEGER) AS place FROM (SELECT c_custkey, o_orderkey, row_number() OVER (PARTITION BY c_custkey ORDER BY o_totalprice DESC, o_orderkey) AS place FROM customer JOIN orders ON o_custkey = c_custkey) WHERE place <= 3")
def top_orders(spark, d):
    """A report of the three largest orders of each customer."""
    w = Window.partitionBy("c_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return table(spark, d, "customer").join(table(spark, d, "orders"), F.col("o_custkey") == F.col("c_custkey")).select("c_custkey", "o_orderkey", F.row_number().over(w).alias("place")).where("place <= 3")
