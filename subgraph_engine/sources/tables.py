"""The given tables, read from Parquet, and graphs as files of adjacency or edge lines."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceWriter, InputPartition, WriterCommitMessage

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def load_edges_text(spark: SparkSession, path: str, sep: str = r"\s+", comment: str = "#") -> DataFrame:
    """``src, dst`` from lines of two ids."""
    parts = F.split(F.trim("value"), sep)
    lines = spark.read.text(path).where(~F.col("value").startswith(comment) & (F.trim("value") != ""))
    return lines.select(parts[0].cast("long").alias("src"), parts[1].cast("long").alias("dst"))


def load_adjacency_text(spark: SparkSession, path: str, sep: str = "\t", item_sep: str = " ") -> DataFrame:
    """``id, nbrs`` from lines of an id, a tab and its neighbours."""
    parts = F.split("value", sep)
    ids = F.filter(F.split(F.coalesce(F.get(parts, F.lit(1)), F.lit("")), item_sep), lambda x: x != "")
    return spark.read.text(path).where("value <> ''").select(parts[0].cast("long").alias("id"), F.array_sort(F.transform(ids, lambda x: x.cast("long"))).alias("nbrs"))


def save_adjacency_text(adjacency: DataFrame, path: str, sep: str = "\t", item_sep: str = " ") -> None:
    line = F.concat_ws(sep, F.col("id").cast("string"), F.array_join(F.transform("nbrs", lambda x: x.cast("string")), item_sep))
    adjacency.select(line.alias("value")).write.mode("overwrite").text(path)


class AdjacencySource(DataSource):
    """``spark.read.format("adjacency")``: labelled adjacency lines ``id|label|n:label:edgelabel,...``.

    Reads one file for each partition; writes one file for each task, named when the task commits.
    Paths are of folders that all machines mount.
    """

    @classmethod
    def name(cls) -> str:
        return "adjacency"

    def schema(self) -> str:
        return "id long, label string, nbrs array<struct<id:long,label:string,elabel:string>>"

    def reader(self, schema) -> AdjacencyReader:
        return AdjacencyReader(self.options["path"])

    def writer(self, schema, overwrite: bool) -> AdjacencyWriter:
        return AdjacencyWriter(self.options["path"], overwrite)


class AdjacencyReader(DataSourceReader):
    def __init__(self, path: str) -> None:
        self.path = path

    def partitions(self) -> list[InputPartition]:
        import os

        files = sorted(f for f in os.listdir(self.path) if f.startswith("part-"))
        return [InputPartition(f"{self.path}/{f}") for f in files] or [InputPartition("")]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        if not partition.value:
            return
        with open(partition.value, encoding="utf-8") as lines:
            for line in lines:
                i, label, rest = line.rstrip("\n").split("|")
                items = [x.split(":") for x in rest.split(",") if x]
                yield int(i), label or None, [(int(a), b or None, c or None) for a, b, c in items]


class AdjacencyWriter(DataSourceWriter):
    def __init__(self, path: str, overwrite: bool) -> None:
        self.path, self.overwrite = path, overwrite

    def write(self, iterator: Iterator) -> WriterCommitMessage:
        import os
        import uuid

        os.makedirs(self.path, exist_ok=True)
        draft = f"{self.path}/_draft-{uuid.uuid4().hex}"
        with open(draft, "w", encoding="utf-8") as out:
            for row in iterator:
                items = ",".join(f"{n['id']}:{n['label'] or ''}:{n['elabel'] or ''}" for n in row["nbrs"] or [])
                out.write(f"{row['id']}|{row['label'] or ''}|{items}\n")
        return _Draft(draft)

    def commit(self, messages) -> None:
        import os

        if self.overwrite:
            for f in os.listdir(self.path):
                if f.startswith("part-"):
                    os.remove(f"{self.path}/{f}")
        for k, m in enumerate(m for m in messages if m is not None):
            os.replace(m.path, f"{self.path}/part-{k:05d}")

    def abort(self, messages) -> None:
        import contextlib
        import os

        for m in messages:
            if m is not None:
                with contextlib.suppress(OSError):
                    os.remove(m.path)


class _Draft(WriterCommitMessage):
    def __init__(self, path: str) -> None:
        self.path = path
