import numpy as np
import pytest

from spurline.functions import register
from spurline.params import BranchParams
from spurline.plans.clustering import branch_clusters
from spurline.runtime import table
from spurline.sources.workloads import star_points


def test_sql_functions(spark):
    register(spark)
    spark.createDataFrame([(1, [0.0, 3.0]), (1, [4.0, 0.0]), (1, None), (2, [1.0, 1.0])], "k int, x array<double>").createOrReplaceTempView("vecs")
    got = spark.sql("SELECT vector_distance(array(0D, 3D), array(4D, 0D), m) AS d FROM VALUES ('euclidean'), ('manhattan'), ('chebyshev'), ('angular') t(m)").collect()
    assert sorted(r.d for r in got) == pytest.approx([np.pi / 2, 4, 5, 7])
    assert spark.sql("SELECT vector_distance(array(0D), array(1D, 2D), 'euclidean') IS NULL AND vector_distance(array(0D), array(1D), 'angular') IS NULL AS n").first().n
    assert {r.k: r.m for r in spark.sql("SELECT k, vector_mean(x) AS m FROM vecs GROUP BY k").collect()} == {1: [2.0, 1.5], 2: [1.0, 1.0]}


def test_table_function(spark):
    register(spark)
    p = star_points(table(spark, "/root/testdata/sf0.001", "orders"))
    p.createOrReplaceTempView("star")
    got = spark.sql("SELECT * FROM branches(TABLE(SELECT grp, id, x FROM star UNION ALL SELECT '0', 9999, array(double('NaN'), 1D)) PARTITION BY (grp), 5, 25, 12)").collect()
    want = branch_clusters(p, BranchParams(min_samples=5, min_cluster_size=25, min_branch_size=12, allow_single_cluster=True, branch_selection="leaf")).drop("grp").collect()
    assert sorted(map(tuple, got)) == sorted(map(tuple, want))
