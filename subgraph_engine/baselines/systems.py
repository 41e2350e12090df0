"""What the task engine is compared with, each with the same local searches and the same graphs.

* ``serial``: the whole graph in one process.
* ``level_sync``: embeddings of k vertices from those of k - 1, all of a level materialised.
* ``vertex_centric``: messages between vertices in supersteps; a vertex holds its ego net in a frame.
* ``materialized``: tasks' subgraphs are built and packed first, with copies of their own.
* ``twig_join`` and ``path_explore``: labelled matching by joins of acyclic parts, and by
  exploring along a path whose cycle a join closes.
* ``ego_cliques``: pieces that overlap, so that each clique turns up once for each member.

Each returns its answer and what it materialised or sent.
"""

from __future__ import annotations

from bisect import bisect_right
from time import perf_counter

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from subgraph_engine.baselines.budget import within
from subgraph_engine.functions.kernels import FIVE, Piece, QueryGraph, bits, choices, cliques_of_classes, heaviest_clique, largest_clique, match, maximal_cliques, product
from subgraph_engine.operators.classes import Classes, bit_rows
from subgraph_engine.operators.graph import PropertyGraph
from subgraph_engine.plans.lists import contained, mapped
from subgraph_engine.plans.marks import COPIED, Marks, Room, set_places, shared_bits
from subgraph_engine.plans.store import written

APPS = ("triangles", "maximum_clique", "maximal_cliques", "matches")


def _solve(neighbours: dict[int, list[int]], labels: dict[int, str], app: str, query: QueryGraph) -> int:
    """One process's answer over a whole graph."""
    piece = Piece.of(neighbours)
    if app == "triangles":
        rows = piece.rows
        total = 0
        for k, row in enumerate(rows):
            larger = row & (-1 << (k + 1))
            for j in range(k + 1, len(rows)):
                if larger >> j & 1:
                    total += (larger & rows[j] & (-1 << (j + 1))).bit_count()
        return total
    if app == "maximum_clique":
        return largest_clique(piece, (1 << len(piece.ids)) - 1).bit_count()
    if app == "maximal_cliques":
        return sum(1 for _ in maximal_cliques(piece, 0, (1 << len(piece.ids)) - 1, 0)) if piece.ids else 0
    if app == "matches":
        near = {v: set(ns) for v, ns in neighbours.items()}
        by = {q: [v for v in near if labels.get(v) == name] for q, name in query.labels.items()}
        total = 0
        for root in by[1]:
            total += sum(1 for _ in match(query, by | {1: [root]}, lambda _, a, __, b: b in near[a], 1))
        return total
    raise ValueError(app)


def serial(g: PropertyGraph, app: str, query: QueryGraph = FIVE, most_edges: int | None = 5_000_000) -> int:
    """One task takes all; it fails beyond ``most_edges``."""
    within("edges", "serial", g.edges.count(), most_edges)
    rows = g.symmetric()
    if g.vertices is not None:
        rows = rows.join(g.vertices.select("id", "label"), "id")
    else:
        rows = rows.withColumn("label", F.lit(None).cast("string"))

    def run(table: pa.Table) -> pa.Table:
        lists: dict[int, list[int]] = {}
        labels: dict[int, str] = {}
        for v, u, label in zip(table["id"].to_pylist(), table["nbr"].to_pylist(), table["label"].to_pylist(), strict=True):
            lists.setdefault(v, []).append(u)
            labels[v] = label
        return pa.table({"n": pa.array([_solve(lists, labels, app, query)], pa.int64())})

    got = rows.withColumn("all", F.lit(1)).groupBy("all").applyInArrow(run, "n long").collect()
    return got[0]["n"] if got else 0


def level_sync(g: PropertyGraph | Classes, app: str, max_rows: int | None = None, levels: int = 64) -> tuple[int, list[int]]:
    """The answer and the cliques of each level; fails if a level has more than ``max_rows`` rows.

    A row has a clique's vertices only; what may come next is found anew from the lists. Of classes, each level has
    those of their cliques, and the sizes are of the vertices' cliques.
    """
    c = Classes.of(g)
    near = c.near

    def first(batches):
        for batch in batches:
            ids = batch.column(0)
            alone = [not len(near.lists.of(v)) for v in ids.to_pylist()]
            members = pa.ListArray.from_arrays(pa.array(np.arange(len(ids) + 1), pa.int32()), ids)
            yield pa.RecordBatch.from_arrays([members, pa.array(alone, pa.bool_())], names=["members", "maximal"])

    def grown(k):
        def run(batches):
            root = piece = None
            for batch in batches:
                rows = pc.list_flatten(batch.column(0)).to_numpy().reshape(-1, k)
                for at in range(0, len(rows), 1000):
                    some, counts, last, maximal = rows[at : at + 1000], [], [], []
                    for members in some.tolist():
                        if members[0] != root:
                            root = members[0]
                            piece = near.piece(near.lists.of(root))
                        places = [piece.place[v] for v in members[1:]]
                        common = (1 << len(piece.ids)) - 1
                        for j in places:
                            common &= piece.rows[j]
                        least = places[-1] + 1 if places else bisect_right(piece.ids, root)
                        n = 0
                        for j in bits(common >> least << least):
                            last.append(piece.ids[j])
                            maximal.append(not common & piece.rows[j])
                            n += 1
                        counts.append(n)
                    out = np.column_stack([np.repeat(some, counts, axis=0), np.array(last, np.int64)])
                    ends = pa.array(np.arange(len(out) + 1) * (k + 1), pa.int32())
                    yield pa.RecordBatch.from_arrays([pa.ListArray.from_arrays(ends, pa.array(out.ravel())), pa.array(maximal, pa.bool_())], names=["members", "maximal"])

        return run

    def kinds(k):
        def run(batches):
            for batch in batches:
                ids, which = np.unique(pc.list_flatten(batch.column(0)).to_numpy(), return_inverse=True)
                found, n = np.unique(np.sort(near.sizes(ids)[which].reshape(-1, k), axis=1), axis=0, return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(list(found), pa.list_(pa.int64())), pa.array(n, pa.int64())], names=["sizes", "n"])

        return run

    schema = "members array<long>, maximal boolean"
    level = c.dealt().mapInArrow(first, schema)
    sizes: list[int] = []  # by the number of vertices, from one on
    total, k = 0, 1
    while k <= levels:
        level = written(level, "level")
        n = level.count()
        within("rows", f"level {k}", n, max_rows)
        if not near.members.parts:
            sizes.append(n)
        elif n:
            for row in level.select("members").mapInArrow(kinds(k), "sizes array<long>, n long").groupBy("sizes").agg(F.sum("n").alias("n")).collect():
                ways = [1]
                for m in row["sizes"]:
                    ways = product([*ways, *[0] * m], [0, *choices(m, m)[1:]])
                sizes += [0] * (len(ways) - 1 - len(sizes))
                for j, x in enumerate(ways[1:]):
                    sizes[j] += row["n"] * x
        else:
            sizes.append(0)
        if app == "triangles" and k == 3:
            return sizes[2] if len(sizes) > 2 else 0, sizes[:3]
        if app == "maximal_cliques":
            total += level.where("maximal").count()
        if not n:
            break
        level = level.select("members").mapInArrow(grown(k), schema)
        k += 1
    if near.members.parts and app == "triangles":
        return sizes[2] if len(sizes) > 2 else 0, sizes[:3]
    return (total if app == "maximal_cliques" else sum(x > 0 for x in sizes)), sizes


def vertex_centric(g: PropertyGraph | Classes, app: str, frame_limit: int | None = None) -> tuple[int, int]:
    """The answer and the messages sent; fails if a vertex's ego net has more items than ``frame_limit``.

    Messages are lists read from the shared folder by who gets them, so none is a row.
    """
    if app == "triangles":
        c = Classes.of(g, up=True)
        near = c.near
        if near.members.parts:
            raise ValueError("messages of triangles are counted by vertices")

        def check(root: int) -> tuple[int, int]:
            # superstep 1: a vertex tells each larger neighbour of those beyond it; superstep 2: it checks them
            own = near.larger(root)
            return near.closed(own, *near.larger_ones(own)), len(own) * (len(own) - 1) // 2

        got = c.each(check, "found long, said long").agg(F.sum("found").alias("found"), F.sum("said").alias("said")).first()
        return got["found"] or 0, got["said"] or 0
    if app != "maximal_cliques":
        raise ValueError(app)
    c = Classes.of(g)
    near, known = c.near, {}

    def degree(v: int) -> int:
        if v not in known:
            known[v] = int(near.sizes(near.lists.of(v)).sum()) + near.size(v) - 1
        return known[v]

    def frame(root: int) -> tuple[int, int]:
        own, n = near.lists.of(root), near.size(root)
        items = sum(m * degree(u) for u, m in zip(own.tolist(), near.sizes(own).tolist(), strict=True)) + (n - 1) * degree(root)
        return items, n * items

    largest = c.each(frame, "items long, sent long").agg(F.max("items").alias("m"), F.sum("sent").alias("n")).first()
    within("frame", "ego net", largest["m"] or 0, frame_limit)

    def search(root: int) -> tuple[int]:
        piece = near.piece(near.lists.of(root))
        k = bisect_right(piece.ids, root)
        smaller = (1 << k) - 1
        return (sum(1 for _ in maximal_cliques(piece, 0, (1 << len(piece.ids)) - 1 & ~smaller, smaller)),)

    return c.each(search, "n long").agg(F.sum("n").alias("n")).first()["n"] or 0, largest["n"] or 0


def materialized(g: PropertyGraph | Classes | Marks, app: str, bin_items: int = 100_000) -> dict[str, float]:
    """The answer, the copies made, and the tasks' seconds of construction and of mining apart.

    Subgraphs are built with copies of their own and packed; a bin that is full is mined and dropped.
    """
    if isinstance(g, Marks):
        return _materialized_marks(g, app, bin_items)
    c = Classes.of(g, up=True)
    near = c.near

    def mined(root: int, own: np.ndarray, items: np.ndarray, lengths: np.ndarray) -> int:
        if app == "triangles":
            return near.triangles(root, own, near.closed(own, items, lengths))
        rows = bit_rows(own, items, lengths)
        for k, row in enumerate(rows):
            for j in bits(row >> k << k):
                rows[j] |= 1 << k
        return near.size(root) + heaviest_clique(Piece(own.tolist(), rows), (1 << len(own)) - 1, near.sizes(own).tolist())

    def run(batches):
        packed: list[tuple] = []
        size, began = 0, perf_counter()

        def mine() -> pa.RecordBatch:
            nonlocal size, began
            built = perf_counter()
            values = [mined(*x) for x in packed]
            row = (sum(values) if app == "triangles" else max(values), sum(len(x[3]) for x in packed), size, built - began, perf_counter() - built)
            packed.clear()
            size, began = 0, perf_counter()
            return pa.RecordBatch.from_arrays([pa.array([x]) for x in row], names=["n", "copies", "items", "build_s", "mine_s"])

        for batch in batches:
            for root in batch.column(0).to_pylist():
                own = near.larger(root).copy()
                packed.append((root, own, *near.larger_ones(own)))
                size += len(packed[-1][2]) + len(own)
                if size >= bin_items:
                    yield mine()
        if packed:
            yield mine()

    fold = F.sum("n") if app == "triangles" else F.max("n")
    got = c.dealt().mapInArrow(run, "n long, copies long, items long, build_s double, mine_s double").agg(fold.alias("value"), *[F.sum(x).alias(x) for x in ("copies", "items", "build_s", "mine_s")], F.count("*").alias("bins")).first()
    return {k: got[k] or 0 for k in ("value", "copies", "items", "bins", "build_s", "mine_s")}


def _materialized_marks(g: Marks, app: str, bin_items: int) -> dict[str, float]:
    """The same of rows of bits: a subgraph's rows may fill several bins, as triangles are found row by row."""
    if app != "triangles":
        raise ValueError(app)

    def run(batches):
        for batch in batches:
            packed, room = [], Room(max(1 << 17, 2 * COPIED * g.width))
            value = copies = items = bins = size = 0
            began, build_s, mine_s = perf_counter(), 0.0, 0.0

            def mine() -> None:
                nonlocal value, items, bins, size, began, build_s, mine_s
                built = perf_counter()
                value += sum(shared_bits(rows, tiled) for rows, tiled in packed)
                packed.clear()
                room.free()
                items, bins, size = items + size, bins + 1, 0
                build_s += built - began
                began = perf_counter()
                mine_s += began - built

            for root in batch.column(0).to_pylist():
                words, at, tiled = g.row(root), -1, None
                own = set_places(words)
                size += len(own)
                for n, begin, lengths, rows in g.copies(own, room):
                    if begin != at or len(tiled) < len(rows):
                        at, tiled = begin, np.tile(words[begin:], (len(rows), 1))
                    packed.append((rows, tiled[: len(rows)]))
                    copies, size = copies + n, size + lengths
                    if size >= bin_items or room.left() < COPIED * g.width:
                        mine()
            if packed:
                mine()
            yield pa.RecordBatch.from_arrays([pa.array([x]) for x in (value, copies, items, bins, build_s, mine_s)], names=["value", "copies", "items", "bins", "build_s", "mine_s"])

    names = ("value", "copies", "items", "bins", "build_s", "mine_s")
    got = g.dealt().mapInArrow(run, "value long, copies long, items long, bins long, build_s double, mine_s double").agg(*[F.sum(x).alias(x) for x in names]).first()
    return {k: got[k] or 0 for k in names}


def _labelled(g: PropertyGraph) -> DataFrame:
    """``a, la, b, lb``: each edge from both ends with both labels."""
    labels = g.vertices.select("id", "label")
    both = g.symmetric().toDF("a", "b")
    return both.join(labels.toDF("a", "la"), "a").join(labels.toDF("b", "lb"), "b")


def twig_join(g: PropertyGraph, injective: bool = True) -> tuple[DataFrame, dict[str, int]]:
    """``k1..k5`` of the five-vertex pattern, and the rows of each twig.

    Twigs: the c-vertex with an a- and two b-neighbours; the a-vertex with a b-neighbour; the last b-vertex with a d-neighbour.
    """
    e = written(_labelled(g), "labelled")

    def side(x: str, y: str, kx: str, ky: str) -> DataFrame:
        return e.where((F.col("la") == x) & (F.col("lb") == y)).select(F.col("a").alias(kx), F.col("b").alias(ky))

    star = side("c", "a", "k2", "k1").join(side("c", "b", "k2", "k3"), "k2").join(side("c", "b", "k2", "k4"), "k2")
    if injective:
        star = star.where("k3 <> k4")
    star, bar, tail = written(star, "twig"), written(side("a", "b", "k1", "k3"), "twig"), written(side("b", "d", "k4", "k5"), "twig")
    joined = star.join(bar, ["k1", "k3"]).join(tail, "k4").select("k1", "k2", "k3", "k4", "k5")
    return joined, {"star": star.count(), "bar": bar.count(), "tail": tail.count()}


def path_explore(g: PropertyGraph | Classes | Marks, labelled: DataFrame | None = None) -> dict[str, int]:
    """Paths b - a - c explored by labels alone, and those that the edge back to the b-vertex closes; no path is a row.

    ``labelled``: ``id, member, label`` where vertices are classes. A class is next to itself.
    """
    if isinstance(g, Marks):
        words = {x: g.marked(labelled.where(F.col("label") == x)) for x in "abc"}

        def follow(v: int) -> tuple[int, int]:
            if not int(words["a"][v // 64]) >> v % 64 & 1:
                return 0, 0
            near = g.around(v)
            before, after = near & words["b"], near & words["c"]
            b, c = set_places(before), set_places(after)
            return len(b) * len(c), g.inside(b, after) + g.inside(c, before)  # an edge is in the row of its smaller end

        got = g.each(follow, "paths long, closed long").agg(F.sum("paths").alias("paths"), F.sum("closed").alias("closed")).first()
        return {"paths": got["paths"] or 0, "closed": got["closed"] or 0}
    if labelled is None:
        labelled = g.vertices.select("id", F.col("id").alias("member"), "label")
    c = Classes.of(g)
    lists = c.near.lists
    kinds = {x: mapped(labelled.where(F.col("label") == x).groupBy("id").agg(F.array_sort(F.collect_list("member")).alias("nbrs"))) for x in "abc"}

    def around(v: int) -> np.ndarray:
        return np.union1d(lists.of(v), [v])

    def explore(v: int) -> tuple[int, int]:
        n = len(kinds["a"].of(v))
        if not n:
            return 0, 0
        near = around(v)
        before, after = kinds["b"].lengths(near), kinds["c"].lengths(near)
        closed = sum(int(before[k]) * int(after[contained(near, around(int(near[k])))].sum()) for k in np.flatnonzero(before))
        return n * int(before.sum()) * int(after.sum()), n * closed

    got = c.each(explore, "paths long, closed long").agg(F.sum("paths").alias("paths"), F.sum("closed").alias("closed")).first()
    return {"paths": got["paths"] or 0, "closed": got["closed"] or 0}


def ego_cliques(g: PropertyGraph | Classes | Marks, size: int) -> tuple[int, int]:
    """How often a clique of ``size`` turns up in overlapping ego nets, and how many distinct ones there are.

    Each net has all cliques around its vertex; those where that is the least one are the distinct ones.
    """
    if isinstance(g, Marks):
        if size != 3 or not g.up:
            raise ValueError("nets of marks have cliques of three")

        def net(root: int) -> tuple[int, int]:
            # each pair of the net by its smaller end; those beyond the root have both ends beyond it
            words = g.around(root)
            own = set_places(words)
            k = int(np.searchsorted(own, root))
            firsts = g.inside(own[k:], words)
            return g.inside(own[:k], words) + firsts, firsts

        got = g.each(net, "found long, firsts long").agg(F.sum("found").alias("found"), F.sum("firsts").alias("firsts")).first()
        return got["found"] or 0, got["firsts"] or 0
    c = Classes.of(g)
    near = c.near

    def search(root: int) -> tuple[int, int]:
        own, n = near.lists.of(root), near.size(root)
        piece, sizes = near.piece(own), near.sizes(own).tolist()
        every, smaller = (1 << len(own)) - 1, (1 << bisect_right(piece.ids, root)) - 1
        found = n * cliques_of_classes(piece, every, sizes, choices(n - 1, size - 1), size - 1)
        return found, cliques_of_classes(piece, every & ~smaller, sizes, [0, *choices(n, size)[1:]], size)

    got = c.each(search, "found long, firsts long").agg(F.sum("found").alias("found"), F.sum("firsts").alias("firsts")).first()
    return got["found"] or 0, got["firsts"] or 0
