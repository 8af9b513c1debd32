"""The run-time experiment: random walks in 2, 8 and 16 dimensions, growing numbers of starts, five methods, a cut-off.

``python -m spurline.timing --out FILE`` writes one JSON line for each run and prints a table, the scaling fit and the overhead of the
branch pass. ``spark_metrics`` sums what Spark's event log says of a run.
"""

from __future__ import annotations

import argparse
import json
import os
import time

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from spurline.operators import baselines, measures
from spurline.params import BranchParams
from spurline.plans import clustering as C
from spurline.runtime import clean, materialise, table
from spurline.sources.workloads import walk_cloud

#: Fixed values of the experiment: dimensions, numbers of starts, settings, seconds after which larger sizes are skipped.
DIMENSIONS = (2, 8, 16)
STARTS = tuple(round(2 * 400 ** (j / 9)) for j in range(10))
SETTING = BranchParams(min_samples=10, min_cluster_size=100, min_branch_size=20, allow_single_cluster=True)
CUT_OFF = 80.0


def _kmeans(points: DataFrame, starts: int) -> DataFrame:
    """One centre for each start: the first point of its first walk; ten rounds."""
    w = Window.partitionBy("start").orderBy("id")
    first = points.withColumn("r", F.row_number().over(w)).where("r = 1").select("grp", F.col("start").cast("int").alias("label"), F.col("x").alias("c"))
    return baselines.kmeans(points, materialise(first, "first"), 10)


METHODS = {
    "kmeans": _kmeans,
    "density": lambda p, c: C.density_clusters(p, SETTING),
    "branches core": lambda p, c: C.branch_clusters(p, SETTING),
    "branches full": lambda p, c: C.branch_clusters(p, BranchParams(**{**SETTING.__dict__, "graph": "full"})),
    "single linkage": lambda p, c: C.single_linkage_cut(p, 0.1),
}


def run(spark: SparkSession, events: DataFrame, dimensions=DIMENSIONS, starts=STARTS, samples: int = 10, methods=tuple(METHODS), cut_off: float = CUT_OFF) -> list[dict]:
    """A record for each run: ``dims, starts, sample, n, method, seconds, groups``; each method once on each cloud. After the first run of a
    method over ``cut_off`` seconds its larger clouds of that dimension are skipped; errors are recorded and end it too."""
    out, over = [], set()
    for dims in dimensions:
        for c in starts:
            for sample in range(samples):
                cloud = materialise(walk_cloud(events, dims, c, sample), "cloud")
                n = cloud.count()
                for name in methods:
                    if (dims, name) in over:
                        continue
                    began, record = time.time(), {"dims": dims, "starts": c, "sample": sample, "n": n, "method": name}
                    try:
                        found = METHODS[name](cloud, c)
                        label = "label" if "label" in found.columns else "component"
                        record["groups"] = found.where(F.col(label) >= 0).select(label).distinct().count()
                    except Exception as e:  # a method that cannot take the size is part of the result
                        record["error"] = str(e).splitlines()[0][:200]
                    record["seconds"] = round(time.time() - began, 3)
                    out.append(record)
                    if record["seconds"] > cut_off or "error" in record:
                        over.add((dims, name))
    return out


def report(spark: SparkSession, records: list[dict]) -> dict[str, DataFrame]:
    """``times`` (mean seconds and groups by dimension, size and method), ``fit`` (quadratic scaling with its band) and ``overhead`` (the
    branch methods' seconds over those of density)."""
    rows = spark.createDataFrame([(r["dims"], r["starts"], r["n"], r["method"], r["seconds"], r.get("groups")) for r in records if "error" not in r], "dims int, starts int, n long, method string, seconds double, groups long")
    means = rows.groupBy("dims", "n", "method").agg(F.avg("seconds").alias("seconds"), F.avg("groups").alias("groups"))
    base = means.where("method = 'density'").select("dims", "n", F.col("seconds").alias("base"))
    overhead = means.where("method like 'branches%'").join(base, ["dims", "n"]).select("dims", "n", "method", (F.col("seconds") / F.col("base")).alias("overhead"))
    fit = measures.scaling_fit(means.withColumn("key", F.concat_ws("/", "dims", "method")), ("key",))
    return {"times": means, "fit": fit, "overhead": overhead}


def spark_metrics(event_log: str) -> dict[str, float]:
    """Sums over the tasks of an uncompressed event log: tasks, CPU seconds, shuffle and spill bytes, greatest memory of a task, stages."""
    out = {"tasks": 0, "cpu_seconds": 0.0, "shuffle_written": 0, "shuffle_read": 0, "spilled": 0, "peak_task_memory": 0, "stages": 0}
    with open(event_log, encoding="utf-8") as f:
        for line in f:
            e = json.loads(line)
            if e.get("Event") == "SparkListenerStageCompleted":
                out["stages"] += 1
            m = e.get("Task Metrics") if e.get("Event") == "SparkListenerTaskEnd" else None
            if m:
                read = m.get("Shuffle Read Metrics", {})
                out["tasks"] += 1
                out["cpu_seconds"] += m.get("Executor CPU Time", 0) / 1e9
                out["shuffle_written"] += m.get("Shuffle Write Metrics", {}).get("Shuffle Bytes Written", 0)
                out["shuffle_read"] += read.get("Remote Bytes Read", 0) + read.get("Local Bytes Read", 0)
                out["spilled"] += m.get("Disk Bytes Spilled", 0)
                out["peak_task_memory"] = max(out["peak_task_memory"], m.get("Peak Execution Memory", 0))
    return out


def main() -> None:
    a = argparse.ArgumentParser(description=__doc__)
    a.add_argument("--data", default=os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"))
    a.add_argument("--dims", type=int, nargs="+", default=list(DIMENSIONS))
    a.add_argument("--starts", type=int, nargs="+", default=list(STARTS))
    a.add_argument("--samples", type=int, default=10)
    a.add_argument("--methods", nargs="+", default=list(METHODS))
    a.add_argument("--cut-off", type=float, default=CUT_OFF)
    a.add_argument("--out")
    args = a.parse_args()
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.ui.enabled", "false").config("spark.driver.memory", "12g").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    records = run(spark, table(spark, args.data, "events"), args.dims, args.starts, args.samples, args.methods, args.cut_off)
    if args.out:
        with open(args.out, "w", encoding="utf-8") as f:
            f.writelines(json.dumps(r) + "\n" for r in records)
    for r in records:
        print(json.dumps(r))
    got = report(spark, records)
    got["overhead"].orderBy("dims", "n", "method").show(100, truncate=False)
    got["fit"].select("key", "slope", "bend").distinct().orderBy("key").show(100, truncate=False)
    clean(spark)


if __name__ == "__main__":
    main()
