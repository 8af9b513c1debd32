"""Where intermediate tables go, and how lineage is cut so that lost executors do no harm."""

from __future__ import annotations

import re
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder for intermediate tables: below ``spark.checkpoint.dir``, which all executors share.

    Only in plain local mode, where driver and executors are one process, a folder of our own stands in
    when the setting is absent; on a cluster an absent setting is an error.
    """
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        found = "/tmp/checkpoints"
    return f"{found.rstrip('/')}/spurline"


def materialise(df: DataFrame, tag: str) -> DataFrame:
    """Write ``df`` as Parquet to the shared folder and read it back: the plan behind it is not run again,
    and a lost executor costs no more than the rereading of its files. :func:`clean` deletes them all."""
    path = f"{shared_dir(df.sparkSession)}/{df.sparkSession.sparkContext.applicationId}/{tag}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def merged(df: DataFrame) -> DataFrame:
    """``df`` as a side of a join that grows with the points: sorted and merged, never collected by the driver to be broadcast. The
    planner's guess of a size follows compressed files and narrow columns, so it is far too small for rows with arrays."""
    return df.hint("merge")


def fresh(name: str, df: DataFrame) -> str:
    """A column name that ``df`` does not have."""
    while name.lower() in {c.lower() for c in df.columns}:
        name += "_"
    return name


def clean(spark: SparkSession) -> None:
    """Delete what this application has written with :func:`materialise`; frames built on it can no longer be read."""
    folder = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{shared_dir(spark)}/{spark.sparkContext.applicationId}")
    folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(folder, True)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
