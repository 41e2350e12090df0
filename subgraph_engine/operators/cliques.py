"""Cliques: the largest, all largest, all maximal ones, all of one size; and the output modes."""

from __future__ import annotations

import heapq
from bisect import bisect_right
from collections.abc import Callable
from typing import Any

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from subgraph_engine.functions.kernels import Piece, bits, cliques_of_size, count_maximal, greedy_clique, largest_clique, maximal_cliques
from subgraph_engine.operators.classes import Classes
from subgraph_engine.operators.graph import PropertyGraph, adjacency, forward_adjacency
from subgraph_engine.plans.program import StepOutcome, Task, TaskProgram
from subgraph_engine.plans.runtime import RunConfig, RunResult, run_program, stored


def _piece(root: int, own: list[int], frontier: list[tuple[int, list[int]]]) -> Piece:
    return Piece.of({root: own, **{u: [] for u in own}, **dict(frontier)})


class MaxCliqueProgram(TaskProgram):
    """Each root searches its larger neighbours for a clique above the best size known.

    ``max_piece``: larger pieces become one task for each next vertex, up to ``max_depth`` times.
    """

    aggregate = "max"

    def __init__(self, max_piece: int | None = None, max_depth: int = 1, bound: str = "color", sync: bool = True) -> None:
        self.max_piece, self.max_depth, self.bound, self.sync = max_piece, max_depth, bound, sync

    def seed(self, adjacency: DataFrame) -> DataFrame:
        return adjacency.select(F.col("id").alias("root"), F.col("nbrs").alias("own"), F.col("nbrs").alias("pulls"))

    def step(self, task, frontier, shared) -> StepOutcome:
        if task.state is None:
            piece, fixed, depth = _piece(task.root, task.own, frontier), [task.root], 0
            within = piece.mask(task.own)
        else:
            fixed, lists, depth = task.state
            piece = Piece.of(lists)
            within = (1 << len(piece.ids)) - 1
        best = shared.get("best", 0) if self.sync else 0
        if self.max_piece and within.bit_count() > self.max_piece and depth < self.max_depth:
            spawned = []
            for k in bits(within):
                larger = within & piece.rows[k] & (-1 << (k + 1))
                if len(fixed) + 1 + larger.bit_count() > best:
                    lists = {piece.ids[j]: [piece.ids[i] for i in bits(piece.rows[j] & larger)] for j in bits(larger)}
                    spawned.append(Task(task.root, [], [], ([*fixed, piece.ids[k]], lists, depth + 1)))
            return StepOutcome(value=len(fixed), spawned=spawned, nodes=1)
        floor = max(best - len(fixed), 0)
        found = largest_clique(piece, within, floor, self.bound)
        size = len(fixed) + found.bit_count()
        if found and self.sync:
            shared["best"] = max(best, size)  # tasks that follow in this batch prune by it
        return StepOutcome(value=size, nodes=piece.nodes)


#: Roots that are searched first, greedily, for a bound.
FIRST_ROOTS = 64


class GreedyCliqueProgram(MaxCliqueProgram):
    """One clique of each root: always the candidate with most candidates beside it."""

    def step(self, task, frontier, shared) -> StepOutcome:
        piece = _piece(task.root, task.own, frontier)
        return StepOutcome(value=1 + greedy_clique(piece, piece.mask(task.own)).bit_count(), nodes=1)


def greedy_bound(forward: DataFrame, roots: int = FIRST_ROOTS, config: RunConfig = RunConfig()) -> RunResult:
    """The size of the largest of some greedy cliques, of the roots with most larger neighbours."""
    first = lambda lists: GreedyCliqueProgram().seed(lists.orderBy(F.desc(F.size("nbrs")), "id").limit(roots))
    return run_program(forward, GreedyCliqueProgram(), config, seeds=first)


def maximum_clique(g: PropertyGraph, sync: str = "periodic", bound: str = "color", config: RunConfig = RunConfig(), max_piece: int | None = None, max_depth: int = 1, orient: str = "id") -> RunResult:
    """The size of a largest clique (``value``).

    ``sync``: ``periodic`` starts from a greedy bound, then searches the roots with most larger neighbours and
    hands what it finds to the rest, of which roots that can't beat it are dropped before they pull; ``final``
    shares the best size only among the tasks of a batch; ``none`` not at all.
    """
    forward = stored(forward_adjacency(g, orient), config.parts)
    program = MaxCliqueProgram(max_piece, max_depth, bound, sync != "none")
    if forward.isEmpty():
        return RunResult(g.edges.sparkSession.createDataFrame([], "root long, members array<long>"), 0, {"waves": 0})
    if sync != "periodic":
        got = run_program(forward, program, config, {"best": 0})
        got.value = max(got.value or 0, 1)
        return got
    runs = [greedy_bound(forward, config=config)]
    best = max(1, runs[0].value or 0)
    runs.append(run_program(forward, program, config, {"best": best}, lambda lists: program.seed(lists.where(F.size("nbrs") + 1 > best))))
    best = max(best, runs[1].value or 0)
    return RunResult(runs[1].results, best, {k: sum(r.metrics.get(k, 0) for r in runs) for k in runs[1].metrics} | {"waves": 2, "greedy": runs[0].value or 0})


class CliqueListProgram(TaskProgram):
    """All cliques of ``size`` vertices, each in the piece of its least vertex."""

    def __init__(self, size: int) -> None:
        self.size = size

    def seed(self, adjacency: DataFrame) -> DataFrame:
        own = adjacency.where(F.size("nbrs") >= self.size - 1)
        return own.select(F.col("id").alias("root"), F.col("nbrs").alias("own"), F.col("nbrs").alias("pulls"))

    def step(self, task, frontier, shared) -> StepOutcome:
        piece = _piece(task.root, task.own, frontier)
        got = cliques_of_size(piece, piece.mask(task.own), self.size - 1)
        if shared.get("count"):
            return StepOutcome(value=sum(1 for _ in got), nodes=piece.nodes)
        return StepOutcome(results=[[task.root, *piece.members(c)] for c in got], nodes=piece.nodes)


def k_cliques(g: PropertyGraph, size: int, count: bool = False, config: RunConfig = RunConfig()) -> RunResult:
    return run_program(forward_adjacency(g), CliqueListProgram(size), config, {"count": count})


def maximum_cliques(g: PropertyGraph, config: RunConfig = RunConfig()) -> DataFrame:
    """``root, members`` of all largest cliques: the size first, then all cliques of that size."""
    size = maximum_clique(g, config=config).value
    return k_cliques(g, size, config=config).results


class MaximalCliqueProgram(TaskProgram):
    """Maximal cliques whose least vertex is the root.

    The root's smaller neighbours stay beside the search as vertices that must not extend a
    clique, so lists come whole: a forward list would hide the edges to them.
    """

    def __init__(self, least: int = 1, mode: str = "list", top: int = 0, score: Callable[[list[int]], float] | None = None, max_piece: int | None = None) -> None:
        self.least, self.mode, self.top, self.score, self.max_piece = least, mode, top, score, max_piece

    def seed(self, adjacency: DataFrame) -> DataFrame:
        return adjacency.select(F.col("id").alias("root"), F.col("nbrs").alias("own"), F.filter("nbrs", lambda u: u > F.col("id")).alias("pulls"))

    def step(self, task, frontier, shared: dict[str, Any]) -> StepOutcome:
        if task.state is None:
            near = set(task.own)
            piece = Piece.of({task.root: task.own, **{u: [] for u in task.own}, **{u: [w for w in nbrs if w in near] for u, nbrs in frontier}})
            start = 1 << piece.place[task.root]
            larger, smaller = piece.mask(u for u in task.own if u > task.root), piece.mask(u for u in task.own if u < task.root)
            if self.max_piece and larger.bit_count() > self.max_piece:
                return StepOutcome(spawned=self._split(task.root, piece, larger, smaller), nodes=1)
        else:
            lists, clique, some, others = task.state
            piece = Piece.of(lists)
            start, larger, smaller = piece.mask(clique), piece.mask(some), piece.mask(others)
        got = (c for c in maximal_cliques(piece, start, larger, smaller) if c.bit_count() >= self.least)
        if self.mode == "count":
            return StepOutcome(value=sum(1 for _ in got), nodes=piece.nodes)
        if self.mode == "histogram":
            sizes: dict[int, int] = {}
            for c in got:
                sizes[c.bit_count()] = sizes.get(c.bit_count(), 0) + 1
            return StepOutcome(results=[[k, n] for k, n in sizes.items()], nodes=piece.nodes)
        found = [piece.members(c) for c in got]
        if self.mode == "topk":
            found = heapq.nsmallest(self.top, found, key=lambda m: (-(self.score or len)(m), m))
        return StepOutcome(results=found, nodes=piece.nodes)


    @staticmethod
    def _split(root: int, piece: Piece, larger: int, smaller: int) -> list[Task]:
        """The first level of the search as tasks of their own, each with its part of the piece."""
        out = []
        pivot = max(bits(larger | smaller), key=lambda k: (larger & piece.rows[k]).bit_count())
        for k in bits(larger & ~piece.rows[pivot]):
            row = piece.rows[k]
            some, others = larger & row, smaller & row
            inside = some | others | 1 << k | 1 << piece.place[root]
            lists = {piece.ids[a]: piece.members(piece.rows[a] & inside & (-1 << (a + 1))) for a in bits(inside)}
            out.append(Task(root, [], [], (lists, [root, piece.ids[k]], piece.members(some), piece.members(others))))
            larger, smaller = larger & ~(1 << k), smaller | 1 << k
        return out


def _with_isolated(g: PropertyGraph) -> DataFrame:
    lists = adjacency(g)
    if g.vertices is None:
        return lists
    return g.vertices.select("id").join(lists, "id", "left").select("id", F.coalesce("nbrs", F.array().cast("array<bigint>")).alias("nbrs"))


def maximal_clique_run(g: PropertyGraph, least: int = 1, mode: str = "list", top: int = 0, score: Callable[[list[int]], float] | None = None, config: RunConfig = RunConfig(), max_piece: int | None = None) -> RunResult:
    """``mode``: list, count, histogram or topk; isolated vertices count where the graph names its vertices.

    ``max_piece``: roots with more larger neighbours become a task for each branch of the search's first level.
    """
    return run_program(_with_isolated(g), MaximalCliqueProgram(least, mode, top, score, max_piece), config)


def count_maximal_cliques(g: PropertyGraph | Classes) -> int:
    """How many maximal cliques there are, each found from its least vertex by looked-up lists; vertices without an edge count where classes name them."""
    c = Classes.of(g)
    near = c.near

    def search(root: int) -> tuple[int]:
        piece = near.piece(near.lists.of(root))
        smaller = (1 << bisect_right(piece.ids, root)) - 1
        return (count_maximal(piece, (1 << len(piece.ids)) - 1 & ~smaller, smaller),)

    return c.each(search, "n long").agg(F.sum("n").alias("n")).first()["n"] or 0


def clique_histogram(g: PropertyGraph, config: RunConfig = RunConfig()) -> DataFrame:
    """``size, cliques``: maximal cliques by size; pieces send counts, not cliques."""
    rows = maximal_clique_run(g, mode="histogram", config=config).results
    return rows.select(F.get("members", F.lit(0)).alias("size"), F.get("members", F.lit(1)).alias("n")).groupBy("size").agg(F.sum("n").alias("cliques"))


def largest_by(rows: DataFrame, k: int, score: F.Column | None = None) -> DataFrame:
    """The ``k`` results with the highest score (their size by default), ties to the smaller members."""
    return rows.withColumn("score", score if score is not None else F.size("members").cast("double")).orderBy(F.desc("score"), "members").limit(k)
