"""Streaming queries over replayed events; each equals a query over the whole table, which is its SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from subgraph_engine.sources.builders import co_user
from subgraph_engine.sources.tables import load
from subgraph_engine.streaming import replays as R

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}

#: What a watermark of an hour closes: windows that end at least an hour before the last event.
_LAST = "(SELECT max(ts) FROM events)"
_DAYS = "SELECT date_trunc('day', ts) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2"


def stream(name: str, sql: str | None = None):
    def register(f):
        QUERIES[f"stream_{name}"] = f
        if sql is not None:
            SQL[f"stream_{name}"] = sql
        return f

    return register


@stream("tumbling", f"SELECT * FROM ({_DAYS}) WHERE start + INTERVAL 1 DAY <= {_LAST} - INTERVAL 1 HOUR")
def tumbling(spark, sf):
    """Finished days by type; the last day waits for its watermark."""
    return _naive(R.drained(R.tumbling(R.replay(spark, R.events(spark, sf)))))


def _naive(df: DataFrame) -> DataFrame:
    return df.withColumn("start", F.col("start").cast("timestamp_ntz"))


@stream("sliding", f"SELECT start, event_type, count(*) AS n FROM (SELECT unnest([date_trunc('hour', ts) - INTERVAL 1 HOUR, date_trunc('hour', ts)]) AS start, event_type FROM events) WHERE start + INTERVAL 2 HOUR <= {_LAST} - INTERVAL 1 HOUR GROUP BY 1, 2")
def sliding(spark, sf):
    return _naive(R.drained(R.tumbling(R.replay(spark, R.events(spark, sf)), width="2 hours", slide="1 hour")))


@stream("session", f"WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events), s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, fresh DESC) AS k FROM g), w AS (SELECT user_id, k, min(ts) AS start, max(ts) AS last, count(*) AS n FROM s GROUP BY 1, 2) SELECT user_id, start, n FROM w WHERE last + INTERVAL 6 HOUR <= {_LAST} - INTERVAL 1 HOUR")
def session(spark, sf):
    return _naive(R.drained(R.sessions(R.replay(spark, R.events(spark, sf)))))


@stream("late", f"SELECT * FROM ({_DAYS}) WHERE start + INTERVAL 1 DAY <= {_LAST} - INTERVAL 1 HOUR")
def late(spark, sf):
    """A file of copies of the first events comes at the end: days that are closed must not change."""
    ev = R.events(spark, sf)
    first = ev.agg(F.min("ts").alias("m")).first()["m"]
    old = ev.where(F.col("ts") < F.lit(first) + F.expr("interval 1 day"))
    return _naive(R.drained(R.tumbling(R.replay(spark, ev, late=old))))


@stream("dedup", "SELECT event_id, user_id FROM events")
def dedup(spark, sf):
    """The last events come twice in one file and once more after it, and the first file comes again."""
    ev = R.events(spark, sf)
    late = ev.agg(F.max("ts").alias("m")).first()["m"]
    near = ev.where(F.col("ts") >= F.lit(late) - F.expr("interval 30 minutes"))
    got = R.deduplicated(R.replay(spark, ev.unionByName(near), late=near, again=True))
    return R.drained(got.select("event_id", "user_id"))


@stream("static_join", "SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey")
def static_join(spark, sf):
    customers = load(spark, sf, "customer").select("c_custkey", "c_mktsegment")
    joined = R.replay(spark, R.events(spark, sf)).join(customers, F.col("user_id") == F.col("c_custkey"))
    return R.drained(joined.select("event_id", "c_mktsegment"))


@stream("stream_join", "SELECT a.event_id AS first, b.event_id AS second FROM events a JOIN events b ON a.event_type = b.event_type AND a.user_id < b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE")
def stream_join(spark, sf):
    ev = R.events(spark, sf)
    return R.drained(R.interval_join(R.replay(spark, ev), R.replay(spark, ev)))


@stream("stateful", "WITH b AS (SELECT DISTINCT user_id, event_type, epoch_us(ts) // 600000000 AS bucket FROM events) SELECT x.event_type, x.bucket, x.user_id AS v1, y.user_id AS v2, z.user_id AS v3 FROM b x JOIN b y USING (event_type, bucket) JOIN b z USING (event_type, bucket) WHERE x.user_id < y.user_id AND y.user_id < z.user_id")
def stateful(spark, sf):
    """Triangles of each type and bucket, as their users turn up."""
    return R.drained(R.new_triangles(R.replay(spark, R.events(spark, sf))))


_CO_USER = "e AS (SELECT DISTINCT a.user_id AS src, b.user_id AS dst FROM (SELECT DISTINCT user_id, event_type, epoch_us(ts) // 600000000 AS k FROM events) a JOIN (SELECT DISTINCT user_id, event_type, epoch_us(ts) // 600000000 AS k FROM events) b ON a.event_type = b.event_type AND a.k = b.k AND a.user_id < b.user_id)"


@stream("foreach_batch", f"WITH {_CO_USER} SELECT count(*) AS triangles FROM e a JOIN e b ON a.dst = b.src JOIN e c ON c.src = a.src AND c.dst = b.dst")
def foreach_batch(spark, sf):
    total, _ = R.incremental_triangles(co_user(spark, sf))
    return spark.createDataFrame([(total,)], "triangles long")
