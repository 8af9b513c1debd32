"""Streams against the batch form of the same rows."""

from pyspark.sql import Window
from pyspark.sql import functions as F

from spurline.sources.workloads import walk_step
from spurline.streaming import windows as S

EVENTS = "/root/testdata/sf0.001/events.parquet"


def stream(spark, tmp_path):
    """The events as five files in order of time, one a batch."""
    rows = spark.read.parquet(EVENTS).withColumn("part", F.ntile(5).over(Window.orderBy("ts", "event_id")))
    for i in range(1, 6):
        rows.where(F.col("part") == i).drop("part").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    return spark.readStream.schema(rows.drop("part").schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))


def drain(df, tmp_path, name, mode):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", str(tmp_path / "state")).trigger(availableNow=True).start()
    try:
        q.awaitTermination(120)
    finally:
        q.stop()


def test_walk_positions(spark, tmp_path):
    drain(S.walk_positions(stream(spark, tmp_path), 20), tmp_path, "walks", "append")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    rows = spark.read.parquet(EVENTS).where("user_id is not null").withColumn("step", F.row_number().over(w)).where("step <= 20").withColumn("size", walk_step())
    at = [F.sum(F.when(F.col("event_id") % 2 == i, F.col("size")).otherwise(0)).over(w).alias(f"p{i}") for i in range(2)]
    want = rows.select("user_id", "step", *at)
    assert sorted(map(tuple, spark.table("walks").collect())) == sorted(map(tuple, want.collect()))


def test_windows(spark, tmp_path):
    drain(S.event_windows(stream(spark, tmp_path), late="1 day"), tmp_path, "days", "update")
    last = spark.table("days").groupBy("start", "event_type").agg(F.max("n").alias("n"))
    want = S.event_windows(spark.read.parquet(EVENTS)).select("start", "event_type", "n")
    assert sorted(map(tuple, last.collect())) == sorted(map(tuple, want.collect()))
