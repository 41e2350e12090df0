"""Order of waiting tasks, and batches of them.

The key of a task is a few min-hash values of what it will fetch from other owners, so tasks with
overlapping requests come to stand beside each other and a batch fetches fewer distinct vertices.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field

import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: The prime and the (a, b) of the hash functions (a u + b) mod prime.
PRIME = 2**31 - 1
HASHES = ((1103515245, 12345), (48271, 1013904223), (69621, 7), (16807, 99991))


def owner_of(vertex: Column, workers: int) -> Column:
    return F.pmod(vertex, F.lit(workers))


def remote(pulls: Column, root: Column, workers: int) -> Column:
    """The requested ids that another worker than the root's owns."""
    return F.filter(pulls, lambda u: owner_of(u, workers) != owner_of(root, workers))


def minhash_key(ids: Column, values: int = 4) -> list[Column]:
    """``k1``.. of an array of ids; null for an empty one, which has nothing to fetch."""
    def least(k: int) -> Column:
        a, b = HASHES[k % len(HASHES)]
        a += 2 * (k // len(HASHES))
        return F.array_min(F.transform(ids, lambda u: F.pmod(F.pmod(u, F.lit(PRIME)) * a + b, F.lit(PRIME))))

    return [least(k).alias(f"k{k + 1}") for k in range(values)]


def order_columns(kind: str, values: int = 4, arrival: str = "id") -> list[Column]:
    """What tasks are sorted by: ``lsh``, or ``stream`` in order of ids or of their hashes."""
    if kind == "lsh":
        return [F.col(f"k{k + 1}").asc_nulls_first() for k in range(values)] + [F.col("root").asc()]
    if kind == "stream":
        return [F.col("root").asc()] if arrival == "id" else [F.md5(F.col("root").cast("string").cast("binary")).asc(), F.col("root").asc()]
    raise ValueError(kind)


def queued(tasks: DataFrame, workers: int, kind: str = "lsh", values: int = 4, arrival: str = "id", batch: int = 1000) -> DataFrame:
    """Adds ``worker``, the keys and ``batch_no``: runs of ``batch`` tasks of one worker in queue order.

    For cost measures with a given number of logical workers; ``plan_batches`` is what runs tasks.
    """
    keyed = tasks.withColumn("worker", owner_of(F.col("root"), workers)).withColumn("remote", remote(F.col("pulls"), F.col("root"), workers))
    keyed = keyed.select("*", *minhash_key(F.col("remote"), values))
    place = F.row_number().over(Window.partitionBy("worker").orderBy(*order_columns(kind, values, arrival)))
    return keyed.withColumn("batch_no", F.floor((place - 1) / batch).cast("long"))


@dataclass(frozen=True)
class Weights:
    """How long lists are: those of ids with the longest, and the mean of the others."""

    heavy: dict[int, int] = field(default_factory=dict)
    mean: float = 1.0

    def of(self, ids: Iterable[int]) -> float:
        return sum(self.heavy.get(u, self.mean) for u in ids)


#: Ids whose list has more than a share of one in so many of all items are heavy; there are no more of them.
HEAVY = 100_000


def weights(adjacency: DataFrame) -> tuple[Weights, int]:
    """The weights of an adjacency frame, and all its items; at most HEAVY ids come to the driver."""
    size = F.size("nbrs").cast("long")
    n, items, most = adjacency.agg(F.count("*"), F.coalesce(F.sum(size), F.lit(0)), F.coalesce(F.max(size), F.lit(0))).first()
    mean = items / max(n, 1)
    least = max(items / HEAVY, 4 * mean, 1000)
    if most <= least:
        return Weights({}, mean), items
    return Weights({r["id"]: r["n"] for r in adjacency.select("id", F.size("nbrs").alias("n")).where(F.col("n") > least).collect()}, mean), items


def plan_batches(tasks: DataFrame, parts: int, kind: str = "lsh", values: int = 4, batch_capacity: int = 1000, cache_capacity: int = 1_000_000, item_capacity: int | None = None, cost_capacity: float | None = None, lists: Weights | None = None) -> DataFrame:
    """Adds ``batch``: stretches of the ordered tasks, bounded in tasks and in what they fetch.

    Bounds are on distinct ids, on the items of their lists (by ``lists``), and on the tasks' estimated
    cost: the items that a task pulls and the pairs of its own list. A task that alone goes beyond has a
    batch to itself. Tasks are range partitioned by key, so no worker sorts more than its share.
    """
    keyed = tasks.select("*", *minhash_key(F.col("pulls"), values)) if kind == "lsh" else tasks
    columns = [F.col(f"k{k + 1}") for k in range(values)] if kind == "lsh" else []
    ordered = keyed.repartitionByRange(parts, *columns, "root", "task_id").sortWithinPartitions(*columns, "root", "task_id").select(*tasks.columns)
    pulls_at, own_at = tasks.columns.index("pulls"), tasks.columns.index("own")
    sizes = lists or Weights()

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, number, n, items, cost, wanted = TaskContext.get().partitionId(), 0, 0, 0.0, 0.0, set()
        for rows in batches:
            numbers = []
            owned = pc.fill_null(pc.list_value_length(rows.column(own_at)), 0).to_pylist()
            for pulls, own in zip(rows.column(pulls_at).to_pylist(), owned, strict=True):
                pulls = pulls or []
                new = [u for u in pulls if u not in wanted]
                more, work = sizes.of(new), sizes.of(pulls) + own * (own - 1) / 2
                full = n == batch_capacity or len(wanted) + len(new) > cache_capacity
                if n and (full or (item_capacity and items + more > item_capacity) or (cost_capacity and cost + work > cost_capacity)):
                    number, n, items, cost, wanted = number + 1, 0, 0.0, 0.0, set()
                    new, more = pulls, sizes.of(pulls)
                wanted.update(new)
                n, items, cost = n + 1, items + more, cost + work
                numbers.append(part << 32 | number)
            yield pa.RecordBatch.from_arrays([*rows.columns, pa.array(numbers, pa.int64())], names=[*rows.schema.names, "batch"])

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in tasks.schema.fields)
    return ordered.mapInArrow(cut, f"{fields}, batch bigint")
