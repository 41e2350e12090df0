"""Tables in the shared folder, for results that rounds build on."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``, which driver and executors share.

    A temporary folder takes its place where it is unset on one machine; on a cluster that is an error.
    """
    there = spark.conf.get("spark.checkpoint.dir", None)
    java = spark.sparkContext._jsc.sc().getCheckpointDir()
    if not there and java.isDefined():
        there = java.get()
    if not there:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="shared_"))
        there = spark.sparkContext._jsc.sc().getCheckpointDir().get()
    return there.rstrip("/")


def written(df: DataFrame, what: str) -> DataFrame:
    """``df`` written and read again: lineage ends here, and lost executors cost nothing before it."""
    path = f"{shared_dir(df.sparkSession)}/{what}_{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def bucketed(df: DataFrame, what: str, key: str, buckets: int) -> DataFrame:
    """``df`` written once in files by the key's hash, as a table: joins on the key don't move it again."""
    name = f"{what}_{uuid.uuid4().hex}"
    df.write.format("parquet").bucketBy(buckets, key).sortBy(key).option("path", f"{shared_dir(df.sparkSession)}/{name}").saveAsTable(name)
    return df.sparkSession.table(name)
