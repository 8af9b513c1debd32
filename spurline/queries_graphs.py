"""More registered queries: shapes, graphs, summaries, measures, models, relational surface."""

from __future__ import annotations

import dataclasses

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spurline.operators import baselines as B
from spurline.operators import measures as M
from spurline.operators import memberships as R
from spurline.operators import neighbors as N
from spurline.operators import summaries as Y
from spurline.operators.blocks import knn
from spurline.params import BranchParams
from spurline.plans import clustering as C
from spurline.plans import model as P
from spurline.queries import _SIGNAL, _SUMS, BEST, CORE_SQL, LEAF_DENSITY, PAIRS, _core_graph, _signal, exact, query, star, star_nn
from spurline.runtime import materialise, merged, table
from spurline.sources import workloads as W
from spurline.streaming import windows as S

_WALKED = f"WITH RECURSIVE {PAIRS}, {CORE_SQL}, links AS (SELECT u, v FROM graph UNION ALL SELECT v, u FROM graph), far(root, id, hops) AS (SELECT id, id, 0 FROM s WHERE id % 300 >= {{first}} UNION SELECT far.root, links.v, far.hops + 1 FROM far JOIN links ON links.u = far.id WHERE far.hops < 299), h AS (SELECT root, id, min(hops) AS hops FROM far GROUP BY ALL)"
_REACHED = "c(k, id, component) USING KEY (k, id) AS (SELECT k, id, id FROM n UNION SELECT l.k, l.v, min(c.component) FROM c JOIN l ON l.k = c.k AND l.u = c.id JOIN recurring.c AS o ON o.k = l.k AND o.id = l.v WHERE c.component < o.component GROUP BY l.k, l.v)"


def _shape(name: str):
    def run(spark, d):
        return W.shape_points(table(spark, d, "orders"), name).select("id", "sample", "part", "px", "py")

    run.__name__ = f"{name}_points"
    return query(W.shape_sql(name))(run)


ushape_points, yshape_points, bar_points, unequal_points = map(_shape, ("ushape", "yshape", "bar", "unequal"))


@query(W.PROFILE_SQL)
def profile_points(spark, d):
    p = W.profile_points(table(spark, d, "customer"), table(spark, d, "orders"))
    return p.select("id", *[(F.round(F.get("x", F.lit(i)), 5) + 0.0).alias(f"z{i}") for i in range(5)])


@query(f"WITH {PAIRS} SELECT p.id AS u, p.nbr AS v, p.d2 FROM pairs p JOIN core a ON a.id = p.id JOIN core b ON b.id = p.nbr WHERE p.id < p.nbr AND greatest(p.d2, a.c2, b.c2) <= 36000000")
def star_full_graph(spark, d):
    """Pairs whose mutual reachability is at most a stated length."""
    p = star(spark, d)
    reach = p.select("grp").distinct().withColumn("reach", F.lit(6000.0))
    return Y.graph_full(p, N.core_distance(star_nn(spark, d), 5), reach).select("u", "v", exact(F.col("d")).alias("d2"))


@query(f"WITH {PAIRS}, {CORE_SQL}, f AS (SELECT p.id AS u, p.nbr AS v FROM pairs p JOIN core a ON a.id = p.id JOIN core b ON b.id = p.nbr WHERE p.id < p.nbr AND greatest(p.d2, a.c2, b.c2) <= 36000000), g AS (SELECT u, v FROM graph) SELECT 'both' AS part, count(*) AS edges FROM (SELECT * FROM g INTERSECT SELECT * FROM f) UNION ALL SELECT 'core', count(*) FROM (SELECT * FROM g EXCEPT SELECT * FROM f) UNION ALL SELECT 'full', count(*) FROM (SELECT * FROM f EXCEPT SELECT * FROM g)")
def edge_set_ops(spark, d):
    full, core = star_full_graph(spark, d).select("u", "v"), _core_graph(spark, d).select("u", "v")
    count = lambda df, name: df.agg(F.count(F.lit(1)).alias("edges")).select(F.lit(name).alias("part"), "edges")
    return count(core.intersect(full), "both").unionByName(count(core.exceptAll(full), "core")).unionByName(count(full.exceptAll(core), "full"))


def _hops(spark, d, first: int) -> DataFrame:
    roots = star(spark, d).where(F.col("id") % 300 >= first).select("grp", F.col("id").alias("root"))
    return N.hop_distances(_core_graph(spark, d), roots).withColumn("d_geo", F.col("hops").cast("double"))


@query(_WALKED.format(first=290) + " SELECT id, max(hops) AS far FROM h GROUP BY id")
def star_max_path(spark, d):
    """The longest of the shortest paths to ten landmarks of the sample."""
    return _hops(spark, d, 290).groupBy("id").agg(F.max("hops").alias("far"))


@query(_WALKED.format(first=297) + " SELECT id, arg_min(root, (hops, root)) AS root FROM h GROUP BY id")
def star_nearest_root(spark, d):
    return R.nearest_root(_hops(spark, d, 297)).select("id", "root")


@query(_WALKED.format(first=297) + ", z AS (SELECT *, count(*) FILTER (hops = 0) OVER (PARTITION BY id) AS zeros FROM h) SELECT id, root, round(CASE WHEN zeros > 0 THEN CASE WHEN hops = 0 THEN 1.0::DOUBLE / zeros ELSE 0 END ELSE exp(1.0::DOUBLE / nullif(hops, 0)) / sum(exp(1.0::DOUBLE / nullif(hops, 0))) OVER (PARTITION BY id) END, 6) AS p FROM z")
def star_membership(spark, d):
    return R.softmax(_hops(spark, d, 297)).select("id", "root", F.round("p", 6).alias("p"))


@query(f"WITH {PAIRS}, {CORE_SQL}, {_SIGNAL}, l AS MATERIALIZED (SELECT u, v, least(a.value, b.value) AS level, sqrt(greatest(d2, x.c2, y.c2)) / 1e4 AS w FROM graph JOIN e a ON a.id = u JOIN e b ON b.id = v JOIN core x ON x.id = u JOIN core y ON y.id = v), m AS (SELECT u AS p, level, w FROM l UNION ALL SELECT v, level, w FROM l) SELECT CAST(sample AS VARCHAR) AS grp, round(max(abs(f.level - g.level) / f.w), 6) AS constant FROM m f JOIN m g USING (p) JOIN s ON s.id = p WHERE f.w > 0 GROUP BY sample")
def edge_lipschitz(spark, d):
    e = N.level_edges(_core_graph(spark, d), _signal(spark, d)).withColumn("w", F.col("w") / 1e4)
    return M.lipschitz(e).select("grp", F.round("constant", 6).alias("constant"))


@query("""WITH t AS (SELECT o_orderstatus AS status, ln(o_orderkey + 1) AS lx, ln(o_totalprice) AS y FROM orders), c AS (SELECT status, lx - avg(lx) OVER (PARTITION BY status) AS x, y FROM t),
 s AS (SELECT status, count(*) AS s0, sum(x * x) AS s2, sum(x * x * x) AS s3, sum(x * x * x * x) AS s4, sum(y) AS t0, sum(x * y) AS t1, sum(x * x * y) AS t2 FROM c GROUP BY status),
 f AS (SELECT *, (t2 - s2 * t0 / s0 - s3 * t1 / s2) / (s4 - s2 * s2 / s0 - s3 * s3 / s2) AS bend FROM s)
SELECT status, round((t1 - s3 * bend) / s2, 5) + 0.0 AS slope, round(bend, 5) + 0.0 AS bend, s0 AS sizes FROM f""")
def scaling_fit(spark, d):
    """The fit of run times to sizes, over order keys as sizes and prices as seconds."""
    rows = table(spark, d, "orders").select(F.col("o_orderstatus").alias("status"), (F.col("o_orderkey") + 1).cast("double").alias("n"), F.col("o_totalprice").cast("double").alias("seconds"))
    fit = M.scaling_fit(rows, ("status",))
    return fit.groupBy("status").agg((F.round(F.first("slope"), 5) + 0.0).alias("slope"), (F.round(F.first("bend"), 5) + 0.0).alias("bend"), F.count(F.lit(1)).alias("sizes"))


def _near(spark, d) -> tuple[DataFrame, DataFrame]:
    """The signal, and pairs within 1.5, in the signal's unit."""
    p = star(spark, d)
    pairs = Y.radius_pairs(p, p.select("grp").distinct().withColumn("reach", F.lit(15000.0)))
    return _signal(spark, d), materialise(pairs.withColumn("d", F.col("d") / 1e4), "near")


@query(f"WITH RECURSIVE {PAIRS}, {_SIGNAL}, t(k) AS (VALUES (0.25::DOUBLE), (0.5::DOUBLE), (1.0::DOUBLE), (1.5::DOUBLE)), n AS (SELECT k, id FROM e, t WHERE greatest((12 - value) / 10, 0) <= k), l AS MATERIALIZED (SELECT k, pairs.id AS u, nbr AS v FROM pairs, t JOIN n USING (k) JOIN n o USING (k) WHERE n.id = pairs.id AND o.id = nbr AND sqrt(d2) / 1e4 <= k), {_REACHED} SELECT CAST(sample AS VARCHAR) AS grp, k AS at, count(DISTINCT component) AS components FROM c JOIN s USING (id) GROUP BY sample, k")
def star_slice(spark, d):
    """One line through the two-parameter filtration."""
    signal, near = _near(spark, d)
    got = Y.slice_components(signal, near, 10.0, 12.0, [0.25, 0.5, 1.0, 1.5])
    return got.where("components > 0").select("grp", "at", "components")


@query(f"WITH RECURSIVE {PAIRS}, {_SIGNAL}, span AS (SELECT sample, min(value) AS low, (max(value) - min(value)) / 6 AS wide FROM e GROUP BY sample), n AS (SELECT k, id FROM e JOIN span USING (sample), range(6) t(k) WHERE k BETWEEN greatest(floor((value - low) / wide - 0.15), 0) AND least(floor((value - low) / wide + 0.15), 5) OR (k = 5 AND floor((value - low) / wide - 0.15) >= 5)), l AS MATERIALIZED (SELECT n.k, pairs.id AS u, nbr AS v FROM pairs JOIN n ON n.id = pairs.id JOIN n o ON o.id = nbr AND o.k = n.k WHERE sqrt(d2) / 1e4 <= 1.5), {_REACHED} SELECT k AS bin, component, count(*) AS size FROM c GROUP BY ALL")
def star_nerve(spark, d):
    return Y.nerve(*_near(spark, d), bins=6, overlap=0.3)[0].select("bin", "component", "size")


@query(f"WITH RECURSIVE {PAIRS}, {_SIGNAL}, n AS (SELECT CAST(floor(value / 3) AS BIGINT) AS k, id FROM e), l AS MATERIALIZED (SELECT n.k, pairs.id AS u, nbr AS v FROM pairs JOIN n ON n.id = pairs.id JOIN n o ON o.id = nbr AND o.k = n.k WHERE sqrt(d2) / 1e4 <= 1.5), {_REACHED} SELECT k AS band, component, count(*) AS size FROM c GROUP BY ALL")
def star_level_sets(spark, d):
    return Y.level_sets(*_near(spark, d), width=3.0)[0].select("band", "component", "size")


@query(f"WITH RECURSIVE {PAIRS}, cut AS (SELECT sample, quantile_cont(sqrt(c2), 0.84) AS most FROM core JOIN s USING (id) GROUP BY sample), n AS (SELECT 0 AS k, id FROM core JOIN s USING (id) JOIN cut USING (sample) WHERE c2 <= most ** 2 * (1 + 1e-12)), l AS MATERIALIZED (SELECT 0 AS k, id AS u, nbr AS v FROM pairs WHERE d2 <= 25000000 AND id IN (SELECT id FROM n) AND nbr IN (SELECT id FROM n)), {_REACHED}, z AS (SELECT component FROM (SELECT sample, component, count(*) AS m FROM c JOIN s USING (id) GROUP BY ALL) QUALIFY row_number() OVER (PARTITION BY sample ORDER BY m DESC, component) = 1) SELECT id FROM c JOIN z USING (component)")
def star_largest_component(spark, d):
    p = star(spark, d)
    kept = materialise(Y.dense_part(N.core_distance(star_nn(spark, d), 5), 0.84), "dense")
    near = Y.radius_pairs(p.join(merged(kept), ["grp", "id"], "left_semi"), p.select("grp").distinct().withColumn("reach", F.lit(5000.0)))
    return Y.largest_component(near, kept).select("id")


@query()
def star_skeleton(spark, d):
    p = W.star_points(table(spark, d, "orders"))
    first = p.where("floor(id / 3) % 20 = 10").select("grp", (F.col("id") % 300).cast("int").alias("label"), F.col("x").alias("c"))
    return Y.centroid_skeleton(p, first, 3)


@query()
def star_model_branches(spark, d):
    """The branch pass over a stored density model; the same rows as from one run."""
    model = materialise(P.density_model(W.star_points(table(spark, d, "orders"), W.lengths(5), W.noises(5)), BEST), "model")
    return P.branches_of(model, BEST)


@query()
def star_bottleneck(spark, d):
    """How far each sample's branch trees are from those of the noiseless shape."""
    orders = table(spark, d, "orders")
    a, b = (M.persistence_pairs(C.condensed(W.star_points(orders, n_r=n), BEST, "branch")) for n in (0.0, W.noises(3)))
    return M.bottleneck(a, b)


@query()
def star_tree_stats(spark, d):
    return M.tree_stats(C.condensed(W.star_points(table(spark, d, "orders")), BEST, "branch"))


@query()
def star_distortion(spark, d):
    """Path length along the core graph over direct distance, from three landmarks of each sample."""
    p, g = star(spark, d), _core_graph(spark, d)
    roots = p.where("id % 300 >= 297").select("grp", F.col("id").alias("root"))
    return M.distortion(M.path_lengths(g.select("grp", "u", "v", F.col("d").alias("w")), roots), p)


@query()
def star_compare_labels(spark, d):
    """Branches of each sample beside its density clusters."""
    p = materialise(W.star_points(table(spark, d, "orders")), "stars")
    return Y.compare_labels(C.branch_clusters(p, BEST), C.density_clusters(p, LEAF_DENSITY))


@query()
def star_select_params(spark, d):
    """Branch sizes by mean ARI, then mean spread, over samples of the star."""
    p = materialise(W.star_points(table(spark, d, "orders")), "stars")
    settings = [dataclasses.replace(BEST, min_branch_size=m) for m in (6, 12, 24)]
    found = materialise(C.branch_grid(p, settings).join(p.select("grp", "id", "sample", "arm", "px", "py"), ["grp", "id"]), "found")
    ari = C.adjusted_rand(found, "arm", "label", ("setting", "sample")).groupBy("setting").agg(F.avg("ari").alias("ari"))
    spread = C.centroid_spread(found, ("setting",), "sample").groupBy("setting").agg(F.expr("percentile(spread, 0.95)").alias("spread"))
    return M.select_params(ari.join(spread, "setting"), ("setting",))


def _branches_of_shape(name: str, **more):
    def run(spark, d):
        return C.branch_clusters(W.shape_points(table(spark, d, "orders"), name), dataclasses.replace(BEST, **more))

    run.__name__ = f"{name}_branches" + "".join(f"_{v}" for v in more.values() if isinstance(v, str)) + ("_sides" if more.get("label_sides") else "")
    return query()(run)


ushape_branches, ushape_geodesic = _branches_of_shape("ushape"), _branches_of_shape("ushape", eccentricity="geodesic", root="extremal")
yshape_branches, unequal_branches = _branches_of_shape("yshape"), _branches_of_shape("unequal")
bar_branches, bar_sides = _branches_of_shape("bar"), _branches_of_shape("bar", label_sides=True)


@query()
def profile_branches(spark, d):
    """All customers as one cloud."""
    p = W.profile_points(table(spark, d, "customer"), table(spark, d, "orders")).withColumn("grp", F.lit("profiles"))
    return C.branch_clusters(p, BranchParams(min_samples=5, min_cluster_size=100, min_branch_size=5, allow_single_cluster=True))


@query()
def atlas_branches(spark, d):
    """Components, the densest part, its largest piece, three components, branches."""
    raw = Y.center_batches(W.embedding_points(table(spark, d, "embeddings")).withColumn("batch", F.pmod("id", F.lit(3))), "batch")
    p = materialise(Y.pca(raw, 50), "atlas")
    core = C.density_clusters(p, BranchParams(min_samples=5, min_cluster_size=50, metric="angular")).select("grp", "id", "core")
    kept = materialise(Y.dense_part(core, 0.84), "atlas-dense")
    nn = materialise(knn(p.join(kept, ["grp", "id"], "left_semi"), 30, "angular"), "atlas-knn")
    piece = Y.largest_component(nn.select("grp", F.col("id").alias("u"), F.col("nbr").alias("v")), kept)
    low = Y.pca(p.join(piece, ["grp", "id"], "left_semi"), 3)
    return C.branch_clusters(low, BranchParams(min_samples=3, min_cluster_size=100, min_branch_size=20, allow_single_cluster=True, branch_selection="leaf"))


@query()
def walk_mixture(spark, d):
    """Walk points as a mixture of Gaussians."""
    return Y.gaussian_mixture(W.walk_points(table(spark, d, "events")), 5).select("id", "label", "p")


@query()
def walk_kmeans_ml(spark, d):
    return B.kmeans_ml(W.walk_points(table(spark, d, "events")), 5).select("id", "label")


@query("SELECT time_bucket(INTERVAL 6 HOUR, ts) - k * INTERVAL 6 HOUR AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events, range(4) t(k) GROUP BY ALL")
def sliding_windows(spark, d):
    return S.event_windows(table(spark, d, "events"), "1 day", "6 hours").select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", "n", F.round("total", 4).alias("total"))


@query("SELECT o_orderstatus AS status, o_orderpriority AS priority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority))")
def grouping_sets_groups(spark, d):
    o = table(spark, d, "orders").select(F.col("o_orderstatus").alias("status"), F.col("o_orderpriority").alias("priority"))
    return o.groupingSets([["status"], ["priority"]], "status", "priority").agg(F.count(F.lit(1)).alias("n"))


@query(f"WITH {PAIRS} SELECT DISTINCT id FROM pairs WHERE d2 <= 1000000")
def semi_connected_points(spark, d):
    p = star(spark, d)
    near = Y.radius_pairs(p, p.select("grp").distinct().withColumn("reach", F.lit(1000.0)))
    return p.select("id").join(merged(near.select(F.explode(F.array("u", "v")).alias("id"))), "id", "left_semi")


@query("SELECT page_id, CAST(len(regexp_extract_all(lower(regexp_replace(html, '<[^>]*>', ' ', 'g')), '[a-z0-9]+')) AS BIGINT) AS tokens FROM pages")
def page_tokens(spark, d):
    text = F.lower(F.regexp_replace("html", "<[^>]*>", " "))
    return table(spark, d, "pages").select("page_id", F.when(F.col("html").isNotNull(), F.size(F.regexp_extract_all(text, F.lit("[a-z0-9]+"), F.lit(0)))).cast("long").alias("tokens"))


@query("SELECT lang, source, count(*) AS docs, count(quality) AS labelled, round(avg(quality), 6) AS quality, round(avg(toxic), 6) AS toxic FROM documents LEFT JOIN labels USING (doc_id) GROUP BY ALL")
def group_profile(spark, d):
    docs = table(spark, d, "documents").select("doc_id", "lang", "source").join(table(spark, d, "labels"), "doc_id", "left")
    return docs.groupBy("lang", "source").agg(F.count(F.lit(1)).alias("docs"), F.count("quality").alias("labelled"), F.round(F.avg("quality"), 6).alias("quality"), F.round(F.avg("toxic"), 6).alias("toxic"))
