"""What the text operators share: the shared folder, tables written there, row batches."""

from __future__ import annotations

import os
import tempfile
import uuid
from collections.abc import Iterator
from functools import lru_cache
from weakref import WeakKeyDictionary

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows of an Arrow batch that are turned into Python objects at once.
SLICE = 256


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``.

    Only where it is unset (tests, one machine) a temporary folder takes its place.
    """
    there = spark.conf.get("spark.checkpoint.dir", None)
    if not there:
        java = spark.sparkContext._jsc.sc().getCheckpointDir()
        there = java.get() if java.isDefined() else None
    if not there:
        there = tempfile.mkdtemp(prefix="shared_")
        spark.sparkContext.setCheckpointDir(there)
        java = spark.sparkContext._jsc.sc().getCheckpointDir()
        there = java.get()
    return there.rstrip("/")


def fresh_path(spark: SparkSession, what: str) -> str:
    return f"{shared_dir(spark)}/{what}_{uuid.uuid4().hex}"


def local(path: str) -> str:
    """The path as this machine opens it; shared folders are mounted, so a file scheme is dropped."""
    if path.startswith("file:"):
        return "/" + path[5:].lstrip("/")
    if "://" in path:
        raise ValueError(f"the shared folder {path} cannot be mapped into memory; mount it and name it as file://")
    return path


@lru_cache(maxsize=8192)
def mapped(path: str, kind: str) -> np.ndarray:
    """A file of numbers, mapped into memory."""
    return np.memmap(path, kind, "r") if os.path.getsize(path) else np.zeros(0, kind)


_PATHS: WeakKeyDictionary[DataFrame, str] = WeakKeyDictionary()


def written(df: DataFrame, what: str, compression: str = "zstd", shrink: int = 1) -> DataFrame:
    """``df`` written to the shared folder and read again: cuts lineage, survives lost executors.

    ``shrink``: for tables much smaller than the data, a file for so many shuffle partitions.
    """
    spark = df.sparkSession
    path = fresh_path(spark, what)
    if shrink > 1:
        df = df.coalesce(max(1, int(spark.conf.get("spark.sql.shuffle.partitions")) // shrink))
    df.write.option("compression", compression).parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    _PATHS[out] = path
    return out


def discard(*tables: DataFrame) -> None:
    """Deletes the files of tables that ``written`` gave and nothing will read again."""
    for df in tables:
        if path := _PATHS.pop(df, None):
            spark = df.sparkSession
            at = spark._jvm.org.apache.hadoop.fs.Path(path)
            at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def slices(batches: Iterator[pa.RecordBatch], rows: int = SLICE) -> Iterator[pa.RecordBatch]:
    """The batches, cut so that few rows at a time become Python objects."""
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)


def column(df: DataFrame, name: str, kind: str) -> F.Column:
    """The column if the frame has it, else nulls of that kind."""
    return F.col(f"`{name}`").cast(kind) if name in df.columns else F.lit(None).cast(kind)


#: Ids up to which a table is broadcast in an anti-join.
BROADCAST_IDS = 1_000_000


def without(docs: DataFrame, gone: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """``docs`` without the rows whose id is in ``gone``; rows without an id stay."""
    gone = written(gone.select(id_col).where(F.col(id_col).isNotNull()).distinct(), "gone")
    if gone.count() <= BROADCAST_IDS:
        gone = F.broadcast(gone)
    return docs.join(gone, id_col, "left_anti").select(*docs.columns)
