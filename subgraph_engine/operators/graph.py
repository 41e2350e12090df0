"""The graph and its adjacency as frames, and helpers on them."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from typing import TYPE_CHECKING

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from subgraph_engine.plans.lists import Lists, mapped
from subgraph_engine.plans.marks import COPIED, Marks, Room, set_places
from subgraph_engine.plans.store import written

if TYPE_CHECKING:
    from subgraph_engine.operators.classes import Classes


@dataclass(frozen=True)
class PropertyGraph:
    """``edges``: src, dst (and weight, elabel); undirected edges come once with src < dst, directed ones from src to dst.

    ``vertices``: id and label, or None where labels don't matter; then vertices are the edges' ends.
    """

    edges: DataFrame
    vertices: DataFrame | None = None
    directed: bool = False

    def validate(self) -> PropertyGraph:
        """Raises if ids are null, edges loop, repeat or are not in order, or labels are missing."""
        e = self.edges
        order = F.lit(False) if self.directed else F.col("src") > F.col("dst")
        bad = e.where(F.col("src").isNull() | F.col("dst").isNull() | (F.col("src") == F.col("dst")) | order)
        if not bad.isEmpty():
            raise ValueError(f"edges with null ends, loops or out of order: {bad.limit(3).collect()}")
        keys = ["src", "dst", *(["elabel"] if "elabel" in e.columns else [])]
        if not e.groupBy(*keys).count().where("count > 1").isEmpty():
            raise ValueError("repeated edges")
        if self.vertices is not None:
            ends = e.select(F.explode(F.array("src", "dst")).alias("id"))
            if not ends.join(self.vertices.where("label is not null"), "id", "left_anti").isEmpty():
                raise ValueError("vertices without a label")
        return self

    @staticmethod
    def canonical(pairs: DataFrame, vertices: DataFrame | None = None) -> PropertyGraph:
        """From any pairs: loops and repeats go, ends are put in order."""
        e = pairs.where("src is not null and dst is not null and src <> dst")
        return PropertyGraph(e.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).distinct(), vertices)

    def undirected(self) -> PropertyGraph:
        """Each pair once whatever its directions; itself if it has none."""
        return PropertyGraph.canonical(self.edges.select("src", "dst"), self.vertices) if self.directed else self

    def reversed(self) -> PropertyGraph:
        """All directed edges turned around."""
        if not self.directed:
            return self
        others = [c for c in self.edges.columns if c not in ("src", "dst")]
        return PropertyGraph(self.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), *others), self.vertices, True)

    def ids(self) -> DataFrame:
        return self.vertices.select("id") if self.vertices is not None else self.edges.select(F.explode(F.array("src", "dst")).alias("id")).distinct()

    def symmetric(self) -> DataFrame:
        """``id, nbr``: each edge from both of its ends."""
        ends = F.explode(F.array(F.struct(F.col("src").alias("id"), F.col("dst").alias("nbr")), F.struct(F.col("dst").alias("id"), F.col("src").alias("nbr"))))
        return self.edges.select(ends).select("col.id", "col.nbr")


def encode_ids(pairs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Edges of any type as edges of numbers, and the table ``id, name``; numbers follow the names' hashes."""
    names = pairs.select(F.explode(F.array("src", "dst")).alias("name")).distinct()
    table = written(names.select(F.xxhash64("name").alias("id"), "name"), "ids")
    if not table.groupBy("id").count().where("count > 1").isEmpty():
        raise ValueError("two names have one hash")
    return pairs.select(F.xxhash64("src").alias("src"), F.xxhash64("dst").alias("dst")), table


def forward_adjacency(g: PropertyGraph, orient: str = "id") -> DataFrame:
    """``id, nbrs``: each vertex's larger neighbours, ascending; by id, or by (degree, id).

    With ``orient="degree"`` "larger" is by (degree, id), which bounds a list by the square root of
    twice the edges, hubs included; lists are still sorted by id, so their last one isn't the largest.
    """
    e = g.edges.select("src", "dst")
    if orient == "degree":
        degree = g.symmetric().groupBy("id").agg(F.count("*").alias("d"))
        a, b = degree.toDF("src", "ds"), degree.toDF("dst", "dd")
        swap = F.struct("ds", "src") > F.struct("dd", "dst")
        ranked = e.join(a, "src").join(b, "dst")
        e = ranked.select(F.when(swap, F.col("dst")).otherwise(F.col("src")).alias("src"), F.when(swap, F.col("src")).otherwise(F.col("dst")).alias("dst"))
    elif orient != "id":
        raise ValueError(orient)
    return e.groupBy(F.col("src").alias("id")).agg(F.array_sort(F.collect_list("dst")).alias("nbrs"))


def adjacency(g: PropertyGraph) -> DataFrame:
    """``id, nbrs``: all neighbours, ascending."""
    return g.symmetric().groupBy("id").agg(F.array_sort(F.collect_list("nbr")).alias("nbrs"))


def arc_adjacency(g: PropertyGraph, direction: str = "out") -> DataFrame:
    """``id, nbrs`` of a directed graph: where each vertex's edges lead (``out``) or come from (``in``), ascending."""
    a, b = {"out": ("src", "dst"), "in": ("dst", "src")}[direction]
    return g.edges.groupBy(F.col(a).alias("id")).agg(F.array_sort(F.collect_set(b)).alias("nbrs"))


def peeled(g: PropertyGraph, k: int, passes: int = 2) -> PropertyGraph:
    """The graph after some passes that drop vertices with fewer than ``k`` neighbours; it holds the k-core."""
    edges = g.edges.select("src", "dst")
    for _ in range(passes):
        strong = PropertyGraph(edges).symmetric().groupBy("id").agg(F.count("*").alias("d")).where(F.col("d") >= k).select("id")
        edges = written(edges.join(strong.withColumnRenamed("id", "src"), "src", "left_semi").join(strong.withColumnRenamed("id", "dst"), "dst", "left_semi").select("src", "dst"), "peeled")
    return PropertyGraph(edges)


def attach_neighbor_labels(g: PropertyGraph) -> DataFrame:
    """``id, label, nbrs``: items carry the neighbour's label and the edge's, sorted by id.

    ``out`` says of a directed edge whether it leads to the neighbour; it is null for others.
    """
    if g.vertices is None:
        raise ValueError("the graph has no labels")
    e = g.edges if "elabel" in g.edges.columns else g.edges.withColumn("elabel", F.lit(None).cast("string"))
    out = [F.lit(x if g.directed else None).cast("boolean").alias("out") for x in (True, False)]
    ends = F.explode(F.array(F.struct(F.col("src").alias("id"), F.col("dst").alias("nbr"), out[0]), F.struct(F.col("dst").alias("id"), F.col("src").alias("nbr"), out[1])))
    both = e.select("elabel", ends).select("col.id", "col.nbr", "elabel", "col.out")
    labels = g.vertices.select(F.col("id").alias("nbr"), F.col("label").alias("nlabel"))
    items = both.join(labels, "nbr").groupBy("id").agg(F.array_sort(F.collect_list(F.struct(F.col("nbr").alias("id"), F.col("nlabel").alias("label"), "elabel", "out"))).alias("nbrs"))
    return items.join(g.vertices.select("id", "label"), "id").select("id", "label", "nbrs")


def with_letters(edges: DataFrame, label: Column) -> PropertyGraph:
    """The edges' ends with a label computed from the id (a column of ``id``)."""
    ids = edges.select(F.explode(F.array("src", "dst")).alias("id")).distinct()
    return PropertyGraph(edges.select("src", "dst"), ids.select("id", label.alias("label")))


def ego_pieces(g: PropertyGraph | Classes | Marks, hops: int = 1, forward: bool = False) -> DataFrame:
    """``root, members``: each vertex with those within ``hops`` steps, only larger ones with ``forward``.

    Forward steps go through larger vertices only. Beyond the first hop the lists are looked up in the shared
    folder, so paths are never rows: each root takes its members' lists together by itself.
    """
    if isinstance(g, Marks):
        return _pieces_of_bits(g, hops, forward)
    if not isinstance(g, PropertyGraph):
        return _pieces_of_lists(g.graph.ids(), g.near.lists, hops, forward)
    near = adjacency(g).select("id", F.array_distinct("nbrs").alias("nbrs"))  # both arcs of a directed pair give one neighbour
    if hops == 1:
        own = F.filter("nbrs", lambda u: u > F.col("id")) if forward else F.col("nbrs")
        return near.select(F.col("id").alias("root"), own.alias("members")).where(F.size("members") > 0)
    near = written(near, "adjacency")
    return _pieces_of_lists(near.select("id"), mapped(near), hops, forward)


def _pieces_of_bits(g: Marks, hops: int, forward: bool) -> DataFrame:
    """From rows of all bits: a root's rows are taken together until all vertices are in, as no other can add any then."""
    if g.up:
        raise ValueError("pieces need the rows of all bits")

    def reach(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for root in batch.column(0).to_pylist():
                wanted = g.some(root + 1 if forward else 0)
                wanted[root // 64] &= ~(np.uint64(1) << np.uint64(root % 64))
                edge = members = g.row(root) & wanted
                for _ in range(hops - 1):
                    known, room = members.copy(), Room(COPIED * g.width)
                    for _, _, _, rows in g.copies(set_places(edge), room):
                        known |= np.bitwise_or.reduce(rows, axis=0) & wanted
                        room.free()
                        if np.array_equal(known, wanted):
                            break
                    edge, members = known & ~members, known
                found = g.ids()[set_places(members)]
                if len(found):
                    yield pa.RecordBatch.from_arrays([pa.array(g.ids()[root : root + 1]), pa.array([found], pa.list_(pa.int64()))], names=["root", "members"])

    return g.dealt().mapInArrow(reach, "root long, members array<long>")


def _pieces_of_lists(ids: DataFrame, lists: Lists, hops: int, forward: bool) -> DataFrame:
    def reach(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for root in batch.column(0).to_pylist():
                members = lists.of(root)
                edge = members = members[members > root] if forward else members
                for _ in range(hops - 1):
                    known = np.union1d(members, lists.union(edge.tolist()))
                    known = known[known > root] if forward else known[known != root]
                    edge = np.setdiff1d(known, members, assume_unique=True)
                    members = known
                if len(members):
                    yield pa.RecordBatch.from_arrays([pa.array([root], pa.int64()), pa.array([members], pa.list_(pa.int64()))], names=["root", "members"])

    ids = ids.repartition(int(ids.sparkSession.conf.get("spark.sql.shuffle.partitions")), "id")
    return ids.mapInArrow(reach, "root long, members array<long>")


def degree_histogram(g: PropertyGraph) -> DataFrame:
    degree = g.symmetric().groupBy("id").agg(F.count("*").alias("degree"))
    return degree.groupBy("degree").agg(F.count("*").alias("vertices"))


def k_hop(g: PropertyGraph, root: int, hops: int) -> DataFrame:
    """``id, hop``: vertices within ``hops`` steps of the root and their least distance."""
    step = g.symmetric()
    seen = written(step.sparkSession.createDataFrame([(root, 0)], "id long, hop int"), "hops")
    edge = seen
    for k in range(1, hops + 1):
        edge = edge.select("id").join(step, "id").select(F.col("nbr").alias("id")).distinct().join(seen.select("id"), "id", "left_anti").select("id", F.lit(k).alias("hop"))
        edge = written(edge, "hop")
        seen = seen.unionByName(edge)
    return seen


def connected_components(g: PropertyGraph, rounds: int = 60) -> DataFrame:
    """``id, component``: the least vertex that each can reach; by star contraction."""
    links = written(g.edges.select(F.col("dst").alias("a"), F.col("src").alias("b")).distinct(), "links")
    before = None
    for _ in range(rounds):
        now = links.agg(F.count("*").alias("n"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")).alias("h")).first()
        if now == before:
            break
        before = now
        both = links.select(F.explode(F.array(F.struct("a", "b"), F.struct(F.col("b").alias("a"), F.col("a").alias("b"))))).select("col.a", "col.b")
        least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
        large = both.join(least, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b"))
        least = large.groupBy("a").agg(F.min("b").alias("m"))
        ends = F.explode(F.array(F.struct(F.col("a").alias("a"), F.col("m").alias("b")), F.struct(F.col("b").alias("a"), F.col("m").alias("b"))))
        links = written(large.join(least, "a").select(ends).select("col.a", "col.b").where("a <> b").distinct(), "links")
    else:
        raise RuntimeError("components did not settle")
    ends = F.explode(F.array(F.struct(F.col("a").alias("id"), F.col("b").alias("component")), F.struct(F.col("b").alias("id"), F.col("b").alias("component"))))
    return links.select(ends).select("col.id", "col.component").distinct()


def k_core(g: PropertyGraph, k: int, rounds: int = 200, last: bool = False) -> DataFrame:
    """``src, dst``: the edges of the largest subgraph in which every vertex has ``k`` neighbours or more.

    Each round drops all weaker vertices at once. If none stays, there is no such subgraph and no edge;
    ``last`` then gives the edges that the last round but one left, which are no core.
    """
    edges, n = written(g.edges.select("src", "dst"), "core"), -1
    before = edges
    for _ in range(rounds):
        m = edges.count()
        if m == n:
            return edges
        if last and not m:
            return before
        n, before = m, edges
        weak = PropertyGraph(edges).symmetric().groupBy("id").agg(F.count("*").alias("d")).where(F.col("d") < k).select("id")
        edges = edges.join(weak.withColumnRenamed("id", "src"), "src", "left_anti").join(weak.withColumnRenamed("id", "dst"), "dst", "left_anti")
        edges = written(edges.select("src", "dst"), "core")
    raise RuntimeError("the core did not settle")


def densest_subgraph(g: PropertyGraph, eps: float = 0.1) -> tuple[float, DataFrame]:
    """A density (edges / vertices) and the vertices that reach it, at least 1 / (2 (1 + eps)) of the best.

    Each pass drops all vertices of degree up to 2 (1 + eps) times the density, so passes grow with
    the logarithm of the vertices only.
    """
    edges = written(g.edges.select("src", "dst"), "dense")
    best, kept = 0.0, None
    while True:
        degree = written(PropertyGraph(edges).symmetric().groupBy("id").agg(F.count("*").alias("d")), "degree")
        n, m = degree.count(), edges.count()
        if not n:
            break
        density = m / n
        if density > best or kept is None:
            best, kept = density, degree.select("id")
        strong = degree.where(F.col("d") > 2 * (1 + eps) * density).select("id")
        edges = edges.join(strong.withColumnRenamed("id", "src"), "src", "left_semi").join(strong.withColumnRenamed("id", "dst"), "dst", "left_semi")
        edges = written(edges.select("src", "dst"), "dense")
    if kept is None:
        kept = edges.select(F.col("src").alias("id"))
    return best, kept
