"""Dense graphs of what meets in groups, as rows of bits in the shared folder.

Where a vertex meets a large share of all others, a bit for each takes less than a list, and what two vertices
share is found 64 vertices at once. No pair is a row of a table: each vertex marks the members of its groups.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from subgraph_engine.plans.lists import Lists, _folder, flat, mapped_edges
from subgraph_engine.plans.store import written

#: Stretches of rows, as each leaves out the bits before it; and rows that are copied at once.
STRETCHES, COPIED = 32, 64

_SEEN: dict[str, np.ndarray] = {}


def numbered(rows: DataFrame, item: str, *group: str) -> DataFrame:
    """``id, grp``: each item and the number of a group that it is in, once."""
    rows = written(rows.select(item, *group).dropna().distinct(), "groups")
    groups = written(rows.select(*group).distinct().withColumn("grp", F.monotonically_increasing_id()), "numbers")
    return rows.join(groups, list(group)).select(F.col(item).cast("long").alias("id"), "grp")


def dense(rows: DataFrame) -> bool:
    """Whether a bit for each two items of ``id, grp`` takes less than lists of all that meet, four bytes an item."""
    n = rows.select("id").distinct().count()
    met = rows.groupBy("grp").count().agg(F.sum(F.col("count").cast("double") * (F.col("count") - 1))).first()[0] or 0
    return n * n / 8 <= 4 * met


def set_places(words: np.ndarray) -> np.ndarray:
    """The places of the bits that are set."""
    return np.flatnonzero(np.unpackbits(words.view(np.uint8), bitorder="little"))


def shared_bits(copies: np.ndarray, tiled: np.ndarray) -> int:
    """Bits set in both of two arrays of one shape, without an array for them."""
    if not copies.size:
        return 0
    both = [pa.py_buffer(x.reshape(-1)) for x in (tiled, copies)]  # set and valid
    return pa.Array.from_buffers(pa.bool_(), copies.size * 64, both).true_count


class Room:
    """Memory that copies are made in, again and again, as new memory costs as much as a copy."""

    def __init__(self, words: int) -> None:
        self.words, self.used = np.empty(words, np.uint64), 0

    def take(self, rows: int, width: int) -> np.ndarray:
        at, self.used = self.used, self.used + rows * width
        return self.words[at : self.used].reshape(rows, width)

    def left(self) -> int:
        return len(self.words) - self.used

    def free(self) -> None:
        self.used = 0


class Marks:
    """``own``: the groups of each vertex, ``groups``: the places of their members. A place is a vertex's rank by id.

    ``parts``: first place, first word and path of each stretch of rows, whose bits are of larger places only with ``up``.
    """

    def __init__(self, own: Lists, groups: Lists, n: int, up: bool) -> None:
        self.own, self.groups, self.n, self.up = own, groups, n, up
        self.width = -(-n // 64)
        self.parts: list[tuple[int, int, str]] = []
        self.ends: list[int] = []

    @staticmethod
    def of(rows: DataFrame, up: bool = True) -> Marks:
        """From ``id, grp``: vertices are next to each other that meet in a group."""
        rows, spark = written(rows, "met"), rows.sparkSession
        own = mapped_edges(rows.select("id", F.col("grp").alias("nbr")))

        def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                at = np.searchsorted(every(own), batch.column(0).to_numpy())
                yield pa.RecordBatch.from_arrays([batch.column(1), pa.array(at)], names=["id", "nbr"])

        g = Marks(own, mapped_edges(rows.select("id", "grp").mapInArrow(place, "id long, nbr long")), len(every(own)), up)
        k = min(max(STRETCHES, int(spark.conf.get("spark.sql.shuffle.partitions"))), g.n)
        cuts = [g.n * x // k for x in range(k + 1)] if k else []
        path = _folder(rows)

        def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            import os

            os.makedirs(path, exist_ok=True)
            for batch in batches:
                for first, end in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                    name, begin = f"{path}/{uuid.uuid4().hex}", first // 64 if up else 0
                    out = np.lib.format.open_memmap(f"{name}.bits.npy", "w+", np.uint64, (end - first, g.width - begin))
                    lengths = np.zeros(end - first, np.int64)
                    for p in range(first, end):
                        found = g.around(p, up)
                        out[p - first], lengths[p - first] = found[begin:], int(np.bitwise_count(found).sum())
                    out.flush()
                    del out
                    np.save(f"{name}.lengths.npy", lengths)
                    yield pa.RecordBatch.from_arrays([pa.array([first]), pa.array([begin]), pa.array([name])], names=["first", "begin", "path"])

        if k:
            stretches = spark.createDataFrame(list(zip(cuts, cuts[1:], strict=False)), "first long, last long").repartitionByRange(k, "first")
            g.parts = sorted(tuple(r) for r in stretches.mapInArrow(write, "first long, begin long, path string").collect())
            g.ends = [p[0] for p in g.parts[1:]] + [g.n]
        return g

    def around(self, p: int, up: bool = False) -> np.ndarray:
        """The words of a vertex's neighbours, all or larger ones, from the members of its groups."""
        flags = np.zeros(self.width * 64, bool)
        for _, items, begin, end in self.groups._places(self.own.of(int(every(self.own)[p]))):
            flags[flat(items, begin, end)] = True
        flags[0 if up else p : p + 1] = False
        return np.packbits(flags, bitorder="little").view(np.uint64)

    def some(self, first: int) -> np.ndarray:
        """The words of all places from one on."""
        flags = np.zeros(self.width * 64, bool)
        flags[first : self.n] = True
        return np.packbits(flags, bitorder="little").view(np.uint64)

    def row(self, p: int) -> np.ndarray:
        """The stored words of a vertex, from the first one on."""
        k = int(np.searchsorted(self.ends, p, "right"))
        first, begin, path = self.parts[k]
        out = np.zeros(self.width, np.uint64)
        out[begin:] = _read(f"{path}.bits.npy")[p - first]
        return out

    def copies(self, places: np.ndarray, room: Room) -> Iterator[tuple[int, int, int, np.ndarray]]:
        """The rows of some places (ascending), some at once: how many, their first word, how long their lists are in all, and copies of their words."""
        cuts = np.searchsorted(places, self.ends).tolist()
        for (first, begin, path), a, b in zip(self.parts, [0, *cuts], cuts, strict=False):
            if a < b:
                bits, at = _read(f"{path}.bits.npy"), places[a:b] - first
                sizes = np.add.reduceat(_read(f"{path}.lengths.npy")[at], range(0, b - a, COPIED)).tolist()
                for k, size in zip(range(0, b - a, COPIED), sizes, strict=True):
                    some = at[k : k + COPIED]
                    yield len(some), begin, size, bits.take(some, 0, room.take(len(some), bits.shape[1]), "clip")

    def inside(self, places: np.ndarray, words: np.ndarray, room: Room | None = None) -> int:
        """How many bits the rows of some places share with some words, in all."""
        total, tiled, at, room = 0, None, -1, room or Room(COPIED * self.width)
        for n, begin, _, copies in self.copies(places, room):
            if begin != at or len(tiled) < n:
                at, tiled = begin, np.tile(words[begin:], (n, 1))
            total += shared_bits(copies, tiled[:n])
            room.free()
        return total

    def marked(self, ids: DataFrame) -> np.ndarray:
        """The words of some vertices' ids (a column ``id``); ids without a place are left out."""

        def mark(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            flags, known = np.zeros(self.width * 64, bool), every(self.own)
            for batch in batches:
                x = batch.column(0).to_numpy()
                at = np.searchsorted(known, x)
                flags[at[(at < len(known)) & (known[np.minimum(at, len(known) - 1)] == x)]] = True
            yield pa.RecordBatch.from_arrays([pa.array([np.packbits(flags, bitorder="little").tobytes()], pa.binary())], names=["words"])

        out = np.zeros(self.width, np.uint64)
        if self.n:
            for row in ids.select("id").mapInArrow(mark, "words binary").toLocalIterator():
                out |= np.frombuffer(row["words"], np.uint64)
        return out

    def ids(self) -> np.ndarray:
        return every(self.own)

    def dealt(self) -> DataFrame:
        """``place``: of all vertices, dealt by hash."""
        spark = SparkSession.active()
        return spark.range(self.n).withColumnRenamed("id", "place").repartition(int(spark.conf.get("spark.sql.shuffle.partitions")), "place")

    def each(self, search: Callable[[int], tuple], fields: str) -> DataFrame:
        """Rows of numbers, one for each vertex."""
        names = [f.split()[0] for f in fields.split(", ")]

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                found = [search(p) for p in batch.column(0).to_pylist()]
                yield pa.RecordBatch.from_arrays([pa.array([x[k] for x in found], pa.int64()) for k in range(len(names))], names=names)

        return self.dealt().mapInArrow(run, fields)


def every(lists: Lists) -> np.ndarray:
    """The ids of all lists, ascending; each process reads them once."""
    if not lists.parts:
        return np.empty(0, np.int64)
    name = lists.parts[0][1]
    if name not in _SEEN:
        _SEEN[name] = np.concatenate([np.load(f"{path}.ids.npy") for _, path in lists.parts])
    return _SEEN[name]


def _read(path: str) -> np.ndarray:
    if path not in _SEEN:
        _SEEN[path] = np.asarray(np.load(path, mmap_mode="r"))
    return _SEEN[path]
