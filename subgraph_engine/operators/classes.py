"""Vertices that no other one tells apart, taken as one.

Two vertices with the same neighbours and each other are in the same maximal cliques, and cliques with one of them
are also with the other. A class of such vertices stands in the graph as its least member; what is counted or
listed there has its members put back. Each vertex may be a class of its own.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from subgraph_engine.functions.kernels import Piece
from subgraph_engine.operators.graph import PropertyGraph
from subgraph_engine.plans.lists import Lists, mapped, mapped_edges, mapped_met, placed
from subgraph_engine.plans.store import written


@dataclass(frozen=True)
class Near:
    """What tasks look up. ``lists``: the neighbours of each class, only larger ones with ``up``; ``members``: those of classes that have several."""

    lists: Lists
    members: Lists
    up: bool = False

    def larger(self, v: int) -> np.ndarray:
        own = self.lists.of(v)
        return own if self.up else own[np.searchsorted(own, v, "right") :]

    def sizes(self, ids: np.ndarray) -> np.ndarray:
        return np.maximum(self.members.lengths(ids), 1) if self.members.parts else np.ones(len(ids), np.int64)

    def size(self, v: int) -> int:
        return max(len(self.members.of(v)), 1) if self.members.parts else 1

    def larger_ones(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The larger neighbours of several classes, one list after the other, and how long each is."""
        items, lengths = self.lists.gathered(ids)
        if self.up or not len(items):
            return items, lengths
        row = np.repeat(np.arange(len(ids)), lengths)
        kept = items > ids[row]
        return items[kept], np.bincount(row[kept], minlength=len(ids))

    def piece(self, ids: np.ndarray) -> Piece:
        """The graph between some classes (ascending), from the lists of all neighbours."""
        some = max(BLOCK // max(len(ids), 1), 1)
        rows = [x for k in range(0, len(ids), some) for x in bit_rows(ids, *self.lists.gathered(ids[k : k + some]))]
        return Piece(ids.tolist(), rows, place={v: k for k, v in enumerate(ids.tolist())})

    def closed(self, own: np.ndarray, items: np.ndarray, lengths: np.ndarray) -> int:
        """Pairs of vertices of two of the classes ``own``, where ``items`` has lists of these of some ``lengths``."""
        at = placed(items, own)
        if not self.members.parts:
            return int(np.count_nonzero(at >= 0))
        sizes = self.sizes(own)
        return int((np.repeat(sizes, lengths)[at >= 0] * sizes[at[at >= 0]]).sum())

    def triangles(self, root: int, own: np.ndarray, inside: int) -> int:
        """Triangles whose least class is ``root``: with three, two or one of its members. ``own``: its larger neighbours;
        ``inside``: the pairs of vertices of two of these that are next to each other."""
        n, sizes = self.size(root), self.sizes(own)
        once, twice = int(sizes.sum()), int((sizes * (sizes - 1) // 2).sum())
        return n * (n - 1) * (n - 2) // 6 + n * (n - 1) // 2 * once + n * (twice + inside)


#: Marks of a piece that are made at once.
BLOCK = 1 << 23


def bit_rows(ids: np.ndarray, items: np.ndarray, lengths: np.ndarray) -> list[int]:
    """Of each list, the places of its items among some ids as a bit set."""
    at = placed(items, ids)
    width = -(-len(ids) // 8)
    inside = np.zeros((len(lengths), width * 8), bool)
    found = np.flatnonzero(at >= 0)
    inside[np.searchsorted(np.cumsum(lengths), found, "right"), at[found]] = True
    packed = np.packbits(inside, bitorder="little").tobytes()
    return [int.from_bytes(packed[k * width : (k + 1) * width], "little") for k in range(len(lengths))]


@dataclass(frozen=True)
class Classes:
    """``graph``: edges and ids of the least members."""

    graph: PropertyGraph
    near: Near

    @staticmethod
    def of(g: PropertyGraph | Classes, up: bool = False) -> Classes:
        """Each vertex with an edge alone (with a larger neighbour, with ``up``); classes stay as they are."""
        if isinstance(g, Classes):
            return g
        rows = g.edges.select(F.col("src").alias("id"), F.col("dst").alias("nbr")) if up else g.symmetric()
        return Classes(PropertyGraph(g.edges, written(rows.select("id").distinct(), "ids")), Near(mapped_edges(rows), Lists([]), up))

    @staticmethod
    def made(edges: DataFrame, members: DataFrame) -> Classes:
        """From the edges of least members, and ``id, nbrs``: the members of each class. One alone without an edge is not in the graph."""
        edges = written(edges, "class_edges")
        rows, several = PropertyGraph(edges).symmetric(), members.where(F.size("nbrs") > 1)
        ids = written(rows.select("id").union(several.select("id")).distinct(), "ids")
        return Classes(PropertyGraph(edges, ids), Near(mapped_edges(rows), mapped(several)))

    @staticmethod
    def met(edges: DataFrame, rows: DataFrame, item: str, group: str, up: bool = False) -> Classes:
        """Each item that meets another (a larger one, with ``up``) in a group alone; ``edges`` are only read by who asks for them."""
        lists = mapped_met(rows, item, group, up)
        return Classes(PropertyGraph(edges, written(lists.ids(rows.sparkSession), "ids")), Near(lists, Lists([]), up))

    def each(self, search: Callable[[int], tuple], fields: str) -> DataFrame:
        """Rows of numbers, one for each class."""
        names = [f.split()[0] for f in fields.split(", ")]

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                found = [search(v) for v in batch.column(0).to_pylist()]
                yield pa.RecordBatch.from_arrays([pa.array([x[k] for x in found], pa.int64()) for k in range(len(names))], names=names)

        return self.dealt().mapInArrow(run, fields)

    def dealt(self) -> DataFrame:
        """The ids, dealt by hash."""
        return self.graph.ids().repartition(int(self.graph.edges.sparkSession.conf.get("spark.sql.shuffle.partitions")), "id")

    def expanded(self, rows: DataFrame) -> DataFrame:
        """``root, members`` with the members of the classes in place of their least ones, ascending."""
        lists = self.near.members

        def put(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                roots, found = batch.column(0).to_pylist(), batch.column(1).to_pylist()
                for k in range(0, len(roots), 1000):
                    full = [sorted(u for v in m for u in (lists.of(v).tolist() or [v])) for m in found[k : k + 1000]]
                    yield pa.RecordBatch.from_arrays([pa.array(roots[k : k + 1000], pa.int64()), pa.array(full, pa.list_(pa.int64()))], names=["root", "members"])

        return rows.select("root", "members").mapInArrow(put, "root long, members array<long>") if lists.parts else rows
