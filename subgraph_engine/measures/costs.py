"""Cost measures over the tasks of a method: what is pulled, cached, queued, copied and how evenly."""

from __future__ import annotations

from time import perf_counter

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from subgraph_engine.functions.models import LruCache, OrderedQueue, StreamQueue
from subgraph_engine.operators.graph import PropertyGraph, forward_adjacency
from subgraph_engine.operators.triangles import TriangleProgram, triangle_count
from subgraph_engine.plans.queue import minhash_key, order_columns, owner_of, queued, remote
from subgraph_engine.plans.store import written


def triangle_requests(g: PropertyGraph) -> DataFrame:
    """``root, pulls`` of the triangle program's seeds, the standard trace of the measures."""
    return TriangleProgram().seed(forward_adjacency(g)).select("root", "pulls")


def pull_stats(tasks: DataFrame, workers: int, batch: int, kind: str = "lsh", arrival: str = "id", values: int = 4) -> DataFrame:
    """``total, remote, fetched``: requests, those of other owners, and distinct ones of a batch."""
    rows = queued(tasks, workers, kind, values, arrival, batch)
    wanted = rows.select("worker", "batch_no", F.explode("remote").alias("want"))
    fetched = wanted.distinct().agg(F.count("*").alias("fetched"))
    sums = rows.agg(F.coalesce(F.sum(F.size("pulls").cast("long")), F.lit(0)).alias("total"), F.coalesce(F.sum(F.size("remote").cast("long")), F.lit(0)).alias("remote"))
    return sums.crossJoin(fetched)  # one row each


def reply_sizes(g: PropertyGraph) -> DataFrame:
    """``policy, items``: list items of all replies to the triangle requests, whole or cut."""
    asked = triangle_requests(g).select(F.explode("pulls").alias("id"))
    degree = g.symmetric().groupBy("id").agg(F.count("*").alias("whole"), F.sum((F.col("nbr") > F.col("id")).cast("long")).alias("forward"))
    sums = asked.join(degree, "id").agg(F.coalesce(F.sum("whole"), F.lit(0)).alias("whole"), F.coalesce(F.sum("forward"), F.lit(0)).alias("forward"))
    return sums.select(F.explode(F.array(F.struct(F.lit("whole").alias("policy"), F.col("whole").alias("items")), F.struct(F.lit("forward").alias("policy"), F.col("forward").alias("items"))))).select("col.policy", "col.items")


def redundancy(tasks: DataFrame, workers: int) -> DataFrame:
    """``copies, distinct_vertices``: vertex copies if each task keeps its own, and distinct ones of a worker."""
    wanted = tasks.select(owner_of(F.col("root"), workers).alias("worker"), F.explode("pulls").alias("want"))
    return wanted.agg(F.count("*").alias("copies"), F.countDistinct("worker", "want").alias("distinct_vertices"))


def _traces(tasks: DataFrame, workers: int, kind: str, arrival: str) -> DataFrame:
    rows = tasks.withColumn("worker", owner_of(F.col("root"), workers)).withColumn("remote", remote(F.col("pulls"), F.col("root"), workers))
    rows = rows.select("*", *minhash_key(F.col("remote")))
    place = F.row_number().over(Window.partitionBy("worker").orderBy(*order_columns(kind, 4, arrival)))
    return rows.select("worker", place.alias("place"), "root", "remote", *[f"k{k}" for k in range(1, 5)])


def cache_stats(tasks: DataFrame, workers: int, capacity: int, batch: int = 1000, kind: str = "lsh", arrival: str = "id") -> DataFrame:
    """``worker, hits, misses, evictions, peak`` of a replay through a worker's cache, batch by batch."""

    def replay(table: pa.Table) -> pa.Table:
        table = table.sort_by("place")
        cache = LruCache(capacity)
        wants = table["remote"].to_pylist()
        for at in range(0, len(wants), batch):
            cache.batch(v for w in wants[at : at + batch] for v in w)
        return pa.table({"worker": table["worker"][:1], "hits": pa.array([cache.hits]), "misses": pa.array([cache.misses]), "evictions": pa.array([cache.evictions]), "peak": pa.array([cache.peak])})

    return _traces(tasks, workers, kind, arrival).groupBy("worker").applyInArrow(replay, "worker long, hits long, misses long, evictions long, peak long")


def queue_io(tasks: DataFrame, workers: int, kind: str = "lsh", file_capacity: int = 100, buffer_capacity: int = 1000, passes: int = 2) -> DataFrame:
    """``worker, tasks, reads, writes``: files read and written by a worker's queue over a whole run.

    Seeds are built in bulk; each task that is taken comes back ``passes - 1`` times, with its key.
    """

    def run(table: pa.Table) -> pa.Table:
        table = table.sort_by("place")
        keys = list(zip(*([x if x is not None else -1 for x in table[f"k{k}"].to_pylist()] for k in range(1, 5)), strict=True))
        own = list(enumerate(keys))
        queue = OrderedQueue(file_capacity, buffer_capacity) if kind == "lsh" else StreamQueue(file_capacity)
        if kind == "lsh":
            queue.bulk_build((k, t) for t, k in own)
        else:
            for t, k in own:
                queue.put(k, t)
        left = {t: passes for t, _ in own}
        while taken := queue.take():
            for key, t in taken:
                left[t] -= 1
                if left[t]:
                    queue.put(key, t)
        return pa.table({"worker": table["worker"][:1], "tasks": pa.array([len(own)]), "reads": pa.array([queue.reads]), "writes": pa.array([queue.writes])})

    return _traces(tasks, workers, kind, "id").groupBy("worker").applyInArrow(run, "worker long, tasks long, reads long, writes long")


def memory_stats(g: PropertyGraph, workers: int, batch: int = 1000, kind: str = "lsh") -> DataFrame:
    """``worker, peak_vertices, peak_items, share``: most distinct vertices and list items of a batch,
    and the even share of all items (average degree times vertices over workers)."""
    rows = queued(triangle_requests(g), workers, kind, batch=batch)
    degree = g.symmetric().groupBy("id").agg(F.count("*").alias("degree"))
    wanted = rows.select("worker", "batch_no", F.explode("pulls").alias("id")).distinct().join(degree, "id")
    batches = wanted.groupBy("worker", "batch_no").agg(F.count("*").alias("vertices"), F.sum("degree").alias("items"))
    share = 2 * g.edges.count() / workers
    return batches.groupBy("worker").agg(F.max("vertices").alias("peak_vertices"), F.max("items").alias("peak_items")).withColumn("share", F.lit(share))


def task_costs(g: PropertyGraph) -> DataFrame:
    """``root, size, items, cost``: a piece's vertices, its list items, and the checks that it takes."""
    forward = forward_adjacency(g)
    pieces = forward.select(F.col("id").alias("root"), F.size("nbrs").alias("n"), F.explode("nbrs").alias("id"))
    lists = forward.select("id", F.size("nbrs").alias("d"))
    sums = pieces.join(lists, "id", "left").groupBy("root").agg(F.first("n").cast("long").alias("size"), F.coalesce(F.sum("d"), F.lit(0)).cast("long").alias("items"))
    return sums.withColumn("cost", F.col("items") + F.col("size") * (F.col("size") - 1) / 2)


#: Rows that one step of ``nth_least`` takes to the driver at most.
STEPS = 1000


def nth_least(values: DataFrame, column: str, n: int) -> int:
    """The ``n``-th least (from 1) of a column of whole numbers, exactly.

    The range is cut into equal steps that are counted, and the one with the n-th is cut again, so each pass
    sends a bounded histogram to the driver and the values are never sorted.
    """
    least, most = values.agg(F.min(column), F.max(column)).first()
    while least < most:
        width = (most - least) // STEPS + 1
        step = F.expr(f"({column} - {least}L) div {width}L")
        for at, count in sorted(map(tuple, values.where(F.col(column).between(least, most)).groupBy(step.alias("at")).count().collect())):
            if n <= count:
                break
            n -= count
        least, most = least + at * width, min(most, least + at * width + width - 1)
    return least


def skew_stats(g: PropertyGraph) -> DataFrame:
    """``tasks, most, mean, p99`` of the tasks' costs; p99 is the cost that 99 of 100 tasks don't exceed, as one of them has it."""
    twice = F.round(F.col("cost") * 2).cast("long").alias("twice")  # costs are multiples of a half
    costs = written(task_costs(g).select("cost", twice), "costs")
    tasks = costs.count()
    p99 = nth_least(costs, "twice", -(-99 * tasks // 100)) / 2 if tasks else None
    return costs.agg(F.count("*").alias("tasks"), F.max("cost").alias("most"), F.avg("cost").alias("mean"), F.lit(p99).cast("double").alias("p99"))


def balance(costs: DataFrame, bins: int) -> DataFrame:
    """``root, cost, bin``: costs dealt out so that no bin has much more than the mean.

    Tasks go in order of cost, to the bins forth and back; within an order of magnitude the sums
    stay equal up to the largest task. The order is by range, so no worker sorts all.
    """
    level = F.floor(F.log2(F.col("cost") + 1)).cast("int").alias("level")
    rows = costs.select("root", "cost", level, (F.conv(F.substring(F.md5(F.col("root").cast("string").cast("binary")), 1, 2), 16, 10).cast("int") % 64).alias("lane"))
    place = F.row_number().over(Window.partitionBy("level", "lane").orderBy(F.desc("cost"), "root"))
    turn = F.pmod(place - 1 + F.col("lane") + F.col("level"), F.lit(2 * bins))
    return rows.select("root", "cost", F.when(turn < bins, turn).otherwise(2 * bins - 1 - turn).cast("int").alias("bin"))


def fit_costs(seen: DataFrame) -> tuple[float, float]:
    """Slope and intercept of measured seconds over estimated cost (``cost, seconds``)."""
    r = seen.agg(F.regr_slope("seconds", "cost").alias("a"), F.regr_intercept("seconds", "cost").alias("b")).first()
    return r["a"], r["b"]


def timed(run, *args, **kwargs) -> tuple[object, float]:
    """What ``run`` returns and the seconds that it took."""
    began = perf_counter()
    out = run(*args, **kwargs)
    return out, perf_counter() - began


def queue_overhead(g: PropertyGraph, workers: int, batch: int = 1000) -> list[tuple[str, float, int]]:
    """(order, seconds of keys and sorting, vertices fetched) for hashed keys and both arrival orders."""
    tasks = written(triangle_requests(g), "requests")
    out = []
    for kind, arrival in (("lsh", "id"), ("stream", "id"), ("stream", "hash")):
        got, s = timed(lambda kind=kind, arrival=arrival: pull_stats(tasks, workers, batch, kind, arrival).first())
        out.append((f"{kind}_{arrival}" if kind == "stream" else kind, s, got["fetched"]))
    return out


def choose(g: PropertyGraph, app: str, light: float = 5e7) -> str:
    """``join`` for triangle counting whose list checks are few, else ``tasks``: searches keep no candidates."""
    if app != "triangles":
        return "tasks"
    checks = task_costs(g).agg(F.sum("items").alias("n")).first()["n"] or 0
    return "join" if checks < light else "tasks"


def same_rows(a: DataFrame, b: DataFrame) -> int:
    """Rows that only one of two frames has, with repeats."""
    return a.exceptAll(b).count() + b.exceptAll(a).count()


def answers(graphs: dict[str, PropertyGraph]) -> DataFrame:
    """``graph, vertices, edges, triangles`` of some graphs."""
    out = None
    for name, g in graphs.items():
        row = triangle_count(g).select(F.lit(name).alias("graph"), F.lit(g.ids().count()).alias("vertices"), F.lit(g.edges.count()).alias("edges"), "triangles")
        out = row if out is None else out.unionByName(row)
    return out
