"""The folder that driver and executors share: checkpoints, and tables written on the way."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F


def shared_top(spark: SparkSession) -> str:
    """The session's spark.checkpoint.dir, or the folder that its context checkpoints to. A session without either gets a
    temporary folder if it runs on this machine alone, and an error if it doesn't: executors elsewhere couldn't read it."""
    if top := spark.conf.get("spark.checkpoint.dir", None):
        return top.rstrip("/")
    sc = spark.sparkContext
    held = sc._jsc.sc().getCheckpointDir()
    if held.isDefined():
        return held.get().rstrip("/")
    if not sc.master.startswith("local") or sc.master.startswith("local-cluster"):
        raise RuntimeError("no shared folder: set spark.checkpoint.dir to one that driver and executors reach")
    top = tempfile.mkdtemp(prefix="pathframe-")
    sc.setCheckpointDir(top)
    return top


def checkpointed(df: DataFrame) -> DataFrame:
    """df checkpointed in the shared folder, under new column identities: a checkpoint keeps those of its plan with what
    the plan knew of them (such as a filter), and a join with another part of that plan would apply that to both sides."""
    spark = df.sparkSession
    top = shared_top(spark)
    if spark.sparkContext._jsc.sc().getCheckpointDir().isEmpty():
        spark.sparkContext.setCheckpointDir(top)
    df = df.checkpoint()
    return df.select(*[F.col(f"`{c}`").alias(c) for c in df.columns])


def written(df: DataFrame, **measures: Column) -> tuple[DataFrame, dict]:
    """df written once as Parquet in the shared folder and read again, with aggregates taken on the way, in the same job.

    Lineage is cut, later reads take only their columns, and Spark knows the size. A checkpoint would run df twice and
    count it in a third job.
    """
    spark, seen = df.sparkSession, Observation()
    path = f"{shared_top(spark)}/round-{uuid.uuid4().hex}"
    schema = df.schema
    (df.observe(seen, *[c.alias(k) for k, c in measures.items()]) if measures else df).write.parquet(path)
    return spark.read.schema(schema).parquet(path), dict(seen.get) if measures else {}
