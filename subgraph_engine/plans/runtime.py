"""Runs task programs: order, batch, pull with sharing, step, fold; in rounds.

The adjacency frame is built once and stored in buckets by id, so seeds and the replies of all rounds
read it and no round moves it again. A round is one Spark job over the waiting tasks. Requests are made
distinct within a batch before they meet the lists, which travel in chunks of bounded length, and each
batch's tasks are searched beside its vertices in one grouped map. Batches are bounded by the items that
they fetch and by a share of all estimated cost, so that no task of Spark's gets much more than others.
Within a round a task goes on as long as what it asks for is in its batch. Results and waiting
tasks go to the shared folder; only counts and the aggregate come to the driver.
"""

from __future__ import annotations

import pickle
from collections.abc import Callable
from dataclasses import dataclass, field
from functools import reduce
from time import perf_counter
from typing import Any
from weakref import WeakSet

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from subgraph_engine.plans.program import Task, TaskProgram
from subgraph_engine.plans.queue import plan_batches, weights
from subgraph_engine.plans.store import bucketed, written


@dataclass(frozen=True)
class RunConfig:
    """``share=False`` gives each task its own copies of what it pulls, for comparison.

    ``item_capacity`` bounds the list items of a batch; ``balance`` says how many batches, by estimated cost,
    each of the ``parts`` gets at least (0: as many as the other bounds make).
    """

    batch_capacity: int = 1000
    cache_capacity: int = 1_000_000
    item_capacity: int = 5_000_000
    balance: int = 2
    queue: str = "lsh"
    minhash_values: int = 4
    share: bool = True
    rounds: int = 50
    parts: int | None = None
    trace: bool = False  # keep each step's time


@dataclass
class RunResult:
    results: DataFrame  # root, members
    value: int | None
    metrics: dict[str, int] = field(default_factory=dict)
    trace: DataFrame | None = None  # root, seconds of each step


class RoundsExceeded(RuntimeError):
    pass


OUT = "kind string, root long, iteration int, value long, members array<long>, state binary, pulls array<long>"


#: Items of a list that travel in one row.
CHUNK = 1 << 16


def _chunks(reply: DataFrame) -> DataFrame:
    """``id, part, nbrs``: lists of more than CHUNK items in several rows. Rows stay in their buckets."""
    whole = F.array(F.struct(F.lit(0).alias("part"), F.col("nbrs").alias("nbrs")))
    last = F.floor((F.size("nbrs") - 1) / CHUNK).cast("int")
    parts = F.transform(F.sequence(F.lit(0), last), lambda k: F.struct(k.alias("part"), F.slice("nbrs", k * CHUNK + 1, F.lit(CHUNK)).alias("nbrs")))
    return reply.select("id", F.explode(F.when(F.size("nbrs") <= CHUNK, whole).otherwise(parts)).alias("at")).select("id", "at.part", "at.nbrs")


def _store(vertices: pa.Table) -> dict[int, list]:
    """The lists by id, their chunks joined in order."""
    ids, parts, lists = (vertices[c].to_pylist() for c in ("id", "part", "nbrs"))
    out = {u: x for u, k, x in zip(ids, parts, lists, strict=True) if k == 0}
    for u, k, x in sorted((u, k, x) for u, k, x in zip(ids, parts, lists, strict=True) if k):
        out[u] += x
    return out


def _kernel(program: TaskProgram, shared: dict[str, Any], trace: bool = False):
    """The grouped map's function of a batch's tasks and its vertices."""

    def run(tasks: pa.Table, vertices: pa.Table) -> pa.Table:
        store = _store(vertices) if vertices.num_rows else {}
        own_shared = dict(shared)  # what a step leaves there is for the tasks after it in the batch
        out: list[tuple] = []
        nodes, value, done = 0, None, 0

        def fold(x: int | None) -> None:
            nonlocal value
            if x is not None:
                value = x if value is None else (value + x if program.aggregate == "sum" else max(value, x))

        for root, own, pulls, state, iteration in zip(*(tasks[c].to_pylist() for c in ("root", "own", "pulls", "state", "iteration")), strict=True):
            own, state = pickle.loads(state) if state else (own or [], None)
            waiting = [Task(root, own, pulls or [], state, iteration)]
            while waiting:
                task = waiting.pop()
                missing = [u for u in task.pulls if u not in store]
                if missing and task.iteration > iteration:  # asked for just now: to the next round
                    out.append(("task", task.root, task.iteration, None, None, pickle.dumps((task.own, task.state)), task.pulls))
                    continue
                began = perf_counter()
                got = program.step(task, [(u, store[u]) for u in task.pulls if u in store], own_shared)
                if trace:
                    out.append(("trace", task.root, task.iteration, int((perf_counter() - began) * 1e6), None, None, None))
                nodes += got.nodes
                fold(got.value)
                out += [("result", task.root, 0, None, m, None, None) for m in got.results]
                out += [("task", t.root, task.iteration + 1, None, None, pickle.dumps((t.own, t.state)), t.pulls) for t in got.spawned]
                if got.pulls is not None:
                    waiting.append(Task(task.root, task.own, got.pulls, got.state, task.iteration + 1))
                else:
                    done += 1
        if value is not None:
            out.append(("value", 0, 0, value, None, None, None))
        out += [("nodes", 0, 0, nodes, None, None, None), ("done", 0, 0, done, None, None, None), ("fetched", 0, 0, len(store), None, None, None)]
        out.append(("items", 0, 0, sum(len(x or ()) for x in store.values()), None, None, None))
        kinds = (pa.string(), pa.int64(), pa.int32(), pa.int64(), pa.list_(pa.int64()), pa.binary(), pa.list_(pa.int64()))
        names = ["kind", "root", "iteration", "value", "members", "state", "pulls"]
        return pa.table({n: pa.array(c, k) for n, c, k in zip(names, zip(*out, strict=True), kinds, strict=True)})

    return run


_STORED: WeakSet[DataFrame] = WeakSet()


def stored(adjacency: DataFrame, parts: int | None = None) -> DataFrame:
    """The adjacency in buckets by id, for one run or several."""
    if adjacency in _STORED:
        return adjacency
    parts = parts or int(adjacency.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    out = bucketed(adjacency, "adjacency", "id", parts)
    _STORED.add(out)
    return out


def run_program(adjacency: DataFrame, program: TaskProgram, config: RunConfig = RunConfig(), shared: dict[str, Any] | None = None, seeds: Callable[[DataFrame], DataFrame] | None = None) -> RunResult:
    """Runs a program over an adjacency frame (``id, nbrs`` and whatever ``seed`` and ``reply`` need).

    ``seeds`` may replace the program's own. A frame that ``stored`` gave is used as it is.
    """
    spark = adjacency.sparkSession
    parts = config.parts or int(spark.conf.get("spark.sql.shuffle.partitions"))
    adjacency = stored(adjacency, parts)
    seeds = program.seed(adjacency) if seeds is None else seeds(adjacency)
    reply = _chunks(program.reply(adjacency))
    lists, _ = weights(adjacency)
    cost = seeds.agg(F.sum(F.size("pulls") * lists.mean + F.size("own") * (F.size("own") - 1.0) / 2)).first()[0] if config.balance else None
    bounds = {"item_capacity": config.item_capacity, "cost_capacity": cost / (parts * config.balance) if cost else None, "lists": lists}
    tasks = seeds.select("root", F.col("root").alias("task_id"), "own", "pulls", F.lit(None).cast("binary").alias("state"), F.lit(1).alias("iteration"))
    kept: list[DataFrame] = []
    totals: dict[str, int] = {}
    traces: list[DataFrame] = []
    value, kernel = None, _kernel(program, shared or {}, config.trace)
    for number in range(1, config.rounds + 1):
        batched = plan_batches(tasks, parts, config.queue, config.minhash_values, config.batch_capacity if config.share else 1, config.cache_capacity, **bounds)
        batched = written(batched, "tasks")
        wanted = batched.select(F.col("batch").alias("of"), F.explode("pulls").alias("id")).distinct()
        vertices = wanted.join(reply, "id").select("of", "id", "part", "nbrs")
        grouped = batched.groupBy("batch").cogroup(vertices.groupBy("of"))
        out = written(grouped.applyInArrow(kernel, OUT), "round")
        sums = {r["kind"]: r for r in out.groupBy("kind").agg(F.count("*").alias("n"), F.sum("value").alias("sum"), F.max("value").alias("max")).collect()}
        for kind in ("nodes", "done", "fetched", "items"):
            totals[kind] = totals.get(kind, 0) + (sums[kind]["sum"] if kind in sums else 0)
        totals["batches"] = totals.get("batches", 0) + (sums["done"]["n"] if "done" in sums else 0)
        totals["rounds"] = number
        if "value" in sums:
            x = sums["value"]["sum" if program.aggregate == "sum" else "max"]
            value = x if value is None else (value + x if program.aggregate == "sum" else max(value, x))
        if config.trace:
            traces.append(out.where("kind = 'trace'").select("root", (F.col("value") / 1e6).alias("seconds")))
        if "result" in sums:
            kept.append(out.where("kind = 'result'").select("root", "members"))
        if "task" not in sums:
            break
        if number == config.rounds:
            raise RoundsExceeded(f"{sums['task']['n']} tasks wait after {number} rounds")
        own = F.array().cast(tasks.schema["own"].dataType)
        waiting = out.where("kind = 'task'")
        task_id = F.xxhash64("root", "iteration", "state", "pulls")
        tasks = waiting.select("root", task_id.alias("task_id"), own.alias("own"), "pulls", "state", "iteration")
    results = kept[0] if kept else spark.createDataFrame([], "root long, members array<long>")
    for more in kept[1:]:
        results = results.unionByName(more)
    seconds = reduce(DataFrame.unionByName, traces).groupBy("root").agg(F.sum("seconds").alias("seconds")) if traces else None
    return RunResult(results, value, totals, seconds)
