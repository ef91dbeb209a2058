"""What modules need of the session: a shared folder for intermediate tables."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_path(spark: SparkSession, name: str) -> str:
    """A new path in the folder that driver and executors share; deleted when the JVM ends.

    That is spark.checkpoint.dir, or the context's checkpoint folder. On one machine the warehouse's
    folder will do; a cluster without a shared folder is an error.
    """
    sc = spark.sparkContext
    base = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if base is None:
        if not sc.master.startswith("local") or sc.master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        base = f"{spark.conf.get('spark.sql.warehouse.dir').rstrip('/')}/contrast-scratch"
    path = f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex}"
    jvm_path = sc._jvm.org.apache.hadoop.fs.Path(path)
    jvm_path.getFileSystem(sc._jsc.hadoopConfiguration()).deleteOnExit(jvm_path)
    return path


def settled(df: DataFrame, name: str) -> DataFrame:
    """The same rows, written and read again: computed once, with a short plan, safe from lost executors."""
    df.write.parquet(path := shared_path(df.sparkSession, name))
    return df.sparkSession.read.schema(df.schema).parquet(path)


#: Rows of a side that is sent to all tasks; more are joined or dealt out.
FEW = 100_000


def few(df: DataFrame, most: int = FEW) -> bool:
    """Whether a table has so few rows that it can be sent to all tasks; counts no further than that."""
    return df.limit(most + 1).count() <= most
