"""Quasi-cliques: sets in which every member has a fraction of the others as neighbours."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from subgraph_engine.functions.kernels import Piece, bits, quasi_cliques, reach_two
from subgraph_engine.operators.cliques import largest_by
from subgraph_engine.operators.graph import PropertyGraph, adjacency, peeled
from subgraph_engine.plans.program import StepOutcome, Task, TaskProgram
from subgraph_engine.plans.runtime import RunConfig, RunResult, run_program

MODES = ("all", "maximal", "largest", "count", "topk")


class QuasiCliqueProgram(TaskProgram):
    """Two rounds of pulls reach all vertices above the root within two steps through such vertices.

    Members of a set with the root as its least vertex are at most two steps apart inside the set,
    so the piece of the root holds the set. A vertex between the root and its neighbour counts too,
    so lists are cut by the root only in the task. ``max_piece``: larger pieces become one task for each
    second vertex, with what is left of the piece.
    """

    def __init__(self, num: int, den: int, least: int, most: int | None, mode: str = "all", top: int = 0, max_piece: int | None = None) -> None:
        if 2 * num < den:
            raise ValueError("the fraction must be a half at least")
        if mode not in MODES:
            raise ValueError(mode)
        if mode == "maximal" and most is not None:
            raise ValueError("sets under a bound on sizes are not maximal")
        self.num, self.den, self.least, self.most, self.mode, self.top, self.max_piece = num, den, least, most, mode, top, max_piece

    def seed(self, adjacency: DataFrame) -> DataFrame:
        larger = F.filter("nbrs", lambda u: u > F.col("id"))
        return adjacency.select(F.col("id").alias("root"), larger.alias("own"), larger.alias("pulls")).where(F.size("own") > 0)

    def _split(self, root: int, piece: Piece) -> list[Task]:
        """One task for each second vertex, in order; later ones may not take earlier ones again."""
        out, two, k = [], reach_two(piece), piece.place[root]
        for j in bits(two[k] & (-1 << (k + 1))):
            rest = two[k] & two[j] & (-1 << (j + 1))
            inside = rest | 1 << k | 1 << j
            lists = {piece.ids[a]: piece.members(piece.rows[a] & inside & (-1 << (a + 1))) for a in bits(inside)}
            out.append(Task(root, [], [], (lists, piece.ids[j])))
        return out

    def step(self, task, frontier, shared) -> StepOutcome:
        lists, second = task.state or ({}, None)
        lists = dict(lists) | {u: [w for w in nbrs if w > task.root] for u, nbrs in frontier}
        if task.state is None:
            near = set(task.own)
            more = sorted({w for nbrs in lists.values() for w in nbrs} - near)
            if more:
                return StepOutcome(pulls=more, state=(lists, None))
        piece = Piece.of(lists if second is not None else {task.root: task.own, **lists})
        if second is None and self.max_piece and len(piece.ids) > self.max_piece and self.least > 1:
            return StepOutcome(spawned=self._split(task.root, piece), nodes=1)
        restart = None
        if second is not None:
            members = piece.mask((task.root, second))
            restart = members, ((1 << len(piece.ids)) - 1) & ~members & (-1 << (piece.place[second] + 1))
        least = max(self.least, shared.get("best", 0)) if self.mode == "largest" else self.least
        got = quasi_cliques(piece, task.root, self.num, self.den, least, self.most, self.mode == "largest", self.mode == "maximal", restart)
        if self.mode == "count":
            return StepOutcome(value=sum(1 for _ in got), nodes=piece.nodes)
        found = [piece.members(s) for s in got]
        if self.mode == "largest":
            most = max(map(len, found), default=0)
            shared["best"] = max(shared.get("best", 0), most)
            found = [s for s in found if len(s) == most]
        if self.mode == "topk":
            found = sorted(found, key=lambda m: (-len(m), m))[: self.top]
        return StepOutcome(results=found, nodes=piece.nodes)


def quasi_run(g: PropertyGraph, gamma: tuple[int, int] = (1, 2), min_size: int = 4, max_size: int | None = None, mode: str = "all", top: int = 0, config: RunConfig = RunConfig(), max_piece: int | None = None) -> RunResult:
    """Runs the search; vertices with fewer neighbours than the smallest set asks for go before."""
    num, den = gamma
    needed = -(-num * (min_size - 1) // den)
    if needed > 1:
        g = peeled(g, needed)
    return run_program(adjacency(g), QuasiCliqueProgram(num, den, min_size, max_size, mode, top, max_piece), config)


def quasi_clique_sets(g: PropertyGraph, gamma: tuple[int, int] = (1, 2), min_size: int = 4, max_size: int | None = None, output: str = "all", config: RunConfig = RunConfig(), max_piece: int | None = None, top: int = 0) -> DataFrame:
    """``root, members``; output ``all``, ``maximal`` (no set holds it), ``largest`` or ``topk`` by size.

    The fraction is a pair of integers, so thresholds are exact. ``quasi_run`` with ``count`` only counts.
    """
    found = quasi_run(g, gamma, min_size, max_size, output, top, config, max_piece).results
    if output == "largest":
        most = found.agg(F.max(F.size("members")).alias("most"))
        return found.join(F.broadcast(most), F.size("members") == F.col("most")).drop("most")
    if output == "topk":
        return largest_by(found, top).select("root", "members")
    if output != "maximal":
        return found
    # a set that holds another also holds its first member and its last
    pairs = F.explode(F.flatten(F.transform("members", lambda x: F.transform(F.filter("members", lambda y: y >= x), lambda y: F.struct(x.alias("first"), y.alias("last"))))))
    large = found.where(F.size("members") > min_size).select(pairs.alias("ends"), F.col("members").alias("outer")).select("ends.first", "ends.last", "outer")
    small = found.select("root", "members", F.array_min("members").alias("first"), F.array_max("members").alias("last"))
    inside = (F.size("outer") > F.size("members")) & (F.size(F.array_except("members", "outer")) == 0)
    return small.alias("s").join(large.alias("l"), (F.col("s.first") == F.col("l.first")) & (F.col("s.last") == F.col("l.last")) & inside, "left_anti").select("root", "members")
