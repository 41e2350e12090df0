"""Streams over files: replays of the events, windows, joins, and triangles as edges arrive.

Watermarks bound all state: keys of the stateful operator are (type, time bucket) pairs whose
timers clear them once the watermark has passed.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterable, Iterator
from itertools import combinations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from subgraph_engine.plans.store import shared_dir
from subgraph_engine.sources.tables import load

EVENT = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def fresh(spark: SparkSession, what: str) -> str:
    return f"{shared_dir(spark)}/{what}_{uuid.uuid4().hex}"


def events(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))


def replay(spark: SparkSession, rows: DataFrame, files: int = 4, late: DataFrame | None = None, again: bool = False) -> DataFrame:
    """A file stream of the events in order of time; then a late file, or the first file again."""
    path = fresh(spark, "replay")
    bounds = rows.select(F.unix_micros("ts").alias("t")).approxQuantile("t", [k / files for k in range(1, files)], 0.001)
    part = sum(((F.unix_micros("ts") > F.lit(int(b))).cast("int") for b in bounds), F.lit(0))
    names = [f.split()[0] for f in EVENT.split(", ")]
    for k in range(files):
        rows.where(part == k).select(*names).coalesce(1).write.mode("append").parquet(path)
    if again:
        rows.where(part == 0).select(*names).coalesce(1).write.mode("append").parquet(path)
    if late is not None:
        late.select(*names).coalesce(1).write.mode("append").parquet(path)
    return spark.readStream.schema(EVENT).option("maxFilesPerTrigger", 1).parquet(path)


def drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a stream over all that is there and reads its sink."""
    spark, out = stream.sparkSession, fresh(stream.sparkSession, "sink")
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", fresh(spark, "state")).trigger(availableNow=True)
    writer.format("parquet").option("path", out).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def tumbling(stream: DataFrame, delay: str = "1 hour", width: str = "1 day", slide: str | None = None) -> DataFrame:
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return stream.withWatermark("ts", delay).groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sessions(stream: DataFrame, gap: str = "6 hours", delay: str = "1 hour") -> DataFrame:
    s = stream.withWatermark("ts", delay).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return s.select("user_id", F.col("w.start").alias("start"), "n")


def deduplicated(stream: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Each event id once: repeats within the delay by state that the watermark clears, later ones as late rows."""
    return stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def interval_join(stream: DataFrame, other: DataFrame, minutes: int = 10) -> DataFrame:
    """Pairs of users with events of one type within some minutes; both sides have a watermark."""
    a = stream.withWatermark("ts", "1 hour").select(F.col("event_id").alias("first"), F.col("user_id").alias("src"), "event_type", F.col("ts").alias("ta"))
    b = other.withWatermark("ts", "1 hour").select(F.col("event_id").alias("second"), F.col("user_id").alias("dst"), F.col("event_type").alias("other"), F.col("ts").alias("tb"))
    near = F.expr(f"tb >= ta and tb <= ta + interval {minutes} minutes")
    return a.join(b, (F.col("event_type") == F.col("other")) & near & (F.col("src") < F.col("dst"))).select("first", "second")


TRIANGLE = T.StructType([T.StructField("event_type", T.StringType()), T.StructField("bucket", T.LongType()), *(T.StructField(f"v{k}", T.LongType()) for k in (1, 2, 3))])
_STATE = T.StructType([T.StructField("users", T.ArrayType(T.LongType()))])


#: Triangles that are held at once.
ROWS = 10_000


def closed(users: list[int], arriving: Iterable[int]) -> Iterator[list[tuple[int, ...]]]:
    """The triangles that arriving users close with those before, ROWS at a time; ``users`` grows by the new ones."""
    seen, out = set(users), []
    for u in arriving:
        if u in seen:
            continue
        seen.add(u)
        for pair in combinations(users, 2):
            out.append(tuple(sorted((*pair, u))))
            if len(out) == ROWS:
                yield out
                out = []
        users.append(u)
    if out:
        yield out


def new_triangles(stream: DataFrame, seconds: int = 600, delay: str = "1 hour") -> DataFrame:
    """Triangles of users that meet in a (type, bucket), each given once, when its last user turns up.

    Users of a bucket all meet, so a new user closes one triangle with each two users before.
    """

    def grow(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        users = [int(u) for u in state.get[0]] if state.exists else []
        for rows in closed(users, (u for frame in frames for u in frame["user_id"].tolist())):
            yield pd.DataFrame([(*key, *r) for r in rows], columns=["event_type", "bucket", "v1", "v2", "v3"])
        state.update((users,))
        state.setTimeoutTimestamp(max((int(key[1]) + 1) * seconds * 1000, int(state.getCurrentWatermarkMs()) + 1))

    rows = stream.withWatermark("ts", delay).withColumn("bucket", F.floor(F.unix_seconds("ts") / seconds))
    return rows.groupBy("event_type", "bucket").applyInPandasWithState(grow, TRIANGLE, _STATE, "append", GroupStateTimeout.EventTimeTimeout)


def incremental_triangles(edges: DataFrame, batches: int = 3) -> tuple[int, list[int]]:
    """Triangles counted as edges arrive in batches; each counts when its last edge does.

    Every batch joins its new edges with old and new ones; the stored edges grow by a folder a batch, which a
    batch that runs again writes over.
    """
    spark = edges.sparkSession
    path, store = fresh(spark, "edges"), fresh(spark, "stored")
    for k in range(batches):
        edges.where(F.pmod(F.xxhash64("src", "dst"), F.lit(batches)) == k).coalesce(1).write.mode("append").parquet(path)
    spark.createDataFrame([], "src long, dst long").write.parquet(f"{store}/batch=-1")
    found: dict[int, int] = {}

    def step(new: DataFrame, batch: int) -> None:
        s = new.sparkSession
        old = s.read.schema("src long, dst long, batch long").parquet(store).where(F.col("batch") != batch)
        fresh_edges = new.select("src", "dst").withColumn("new", F.lit(1)).persist()
        every = old.select("src", "dst", F.lit(0).alias("new")).union(fresh_edges).persist()
        # a triangle with a new edge: find it from that one of its new edges that comes first
        a, b, c = (every.toDF(x, y, n) for x, y, n in (("v1", "v2", "n1"), ("v2", "v3", "n2"), ("v1", "v3", "n3")))
        tri = a.join(b, "v2").join(c, ["v1", "v3"]).where("n1 + n2 + n3 > 0")
        found[batch] = tri.count()
        fresh_edges.select("src", "dst").write.mode("overwrite").parquet(f"{store}/batch={batch}")
        every.unpersist()
        fresh_edges.unpersist()

    stream = spark.readStream.schema("src long, dst long").option("maxFilesPerTrigger", 1).parquet(path)
    stream.writeStream.foreachBatch(step).option("checkpointLocation", fresh(spark, "state")).trigger(availableNow=True).start().awaitTermination()
    return sum(found.values()), [found[k] for k in sorted(found)]
