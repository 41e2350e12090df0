"""Labelled graph matching by tasks: grow the neighbourhood of a root, then search it locally."""

from __future__ import annotations

import heapq
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from subgraph_engine.functions.kernels import FIVE, QueryGraph, match
from subgraph_engine.operators.graph import PropertyGraph, attach_neighbor_labels
from subgraph_engine.plans.lists import Lists
from subgraph_engine.plans.program import StepOutcome, Task, TaskProgram
from subgraph_engine.plans.runtime import RunConfig, RunResult, run_program


@dataclass(frozen=True)
class MatchPlan:
    """Where to start and what each round pulls: the labels of the pattern's layers."""

    query: QueryGraph
    root: int
    layers: tuple[frozenset[int], ...]
    pulled: int  # layers that are pulled

    @staticmethod
    def of(query: QueryGraph, root: int | None = None, frequency: dict[str, int] | None = None) -> MatchPlan:
        """Without a root: the vertex with the fewest layers, then the rarest label, then the least number."""
        if root is None:
            root = min(query.labels, key=lambda q: (len(query.layers(q)), (frequency or {}).get(query.labels[q], 0), q))
        layers = tuple(frozenset(x) for x in query.layers(root))
        last = layers[-1]
        inside = any(a in last and b in last for a, b, *_ in query.edges)
        return MatchPlan(query, root, layers, len(layers) - 1 if inside else len(layers) - 2)


def _of_labels(labels: list[str]) -> F.Column:
    return F.filter("nbrs", lambda x: x["label"].isin(labels))


class MatchProgram(TaskProgram):
    """Lists hold (id, label, elabel); replies keep the items that the pattern can use.

    ``rules``: for the five-vertex pattern, the case rules that drop c-vertices and b-candidates
    after the first pull. The edge between a c-vertex and its b-neighbours beside the a-vertex is
    kept from that pull, and b-candidates outside are those not adjacent to the a-vertex.

    ``directed``: a query edge (i, j) stands for one from i to j. ``max_piece``: a root with more candidates
    for the vertex that is placed next becomes several tasks, each with a share of them. ``top``: each task
    gives only its best by ``score``.
    """

    def __init__(self, plan: MatchPlan, injective: bool = True, count: bool = False, rules: bool = False, directed: bool = False, max_piece: int | None = None, top: int = 0, score: Callable[[list[int]], float] | None = None) -> None:
        if rules and plan.query != FIVE:
            raise ValueError("the case rules are those of the five-vertex pattern")
        self.plan, self.injective, self.count, self.rules, self.directed = plan, injective, count, rules, directed
        self.max_piece, self.top, self.score = max_piece, top, score
        self.arcs = directed or any(len(e) > 2 for e in plan.query.edges)  # whether edges matter beyond being there

    def _labels(self, layer: int) -> list[str]:
        return sorted({self.plan.query.labels[q] for q in self.plan.layers[layer]})

    def seed(self, adjacency: DataFrame) -> DataFrame:
        query, root = self.plan.query, self.plan.root
        rows = adjacency.where(F.col("label") == query.labels[root])
        for label in sorted({query.labels[q] for q in query.neighbours(root)}):
            rows = rows.where(F.array_contains(F.transform("nbrs", lambda x: x["label"]), label))
        wanted = F.filter("nbrs", lambda x: x["label"].isin(self._labels(1))) if len(self.plan.layers) > 1 else F.col("nbrs")
        pulls = F.transform(wanted, lambda x: x["id"]) if self.plan.pulled > 0 else F.array().cast("array<bigint>")
        return rows.select(F.col("id").alias("root"), F.filter("nbrs", lambda x: x["label"].isin(sorted(set(query.labels.values())))).alias("own"), pulls.alias("pulls"))

    def reply(self, adjacency: DataFrame) -> DataFrame:
        """Items towards the same or later layers; edges back are known from the layer before."""
        query, layer = self.plan.query, {q: k for k, own in enumerate(self.plan.layers) for q in own}
        used: dict[str, set[str]] = {}
        for q, label in query.labels.items():
            used.setdefault(label, set()).update(query.labels[n] for n in query.neighbours(q) if layer[n] >= layer[q])
        items = F.array().cast(adjacency.schema["nbrs"].dataType)
        for label, kept in sorted(used.items()):
            if kept:
                items = F.when(F.col("label") == label, _of_labels(sorted(kept))).otherwise(items)
        return adjacency.where(F.col("label").isin(sorted(used))).select("id", items.alias("nbrs"))

    def _pruned(self, own: dict[int, str], lists: dict[int, dict[int, str]]) -> tuple[dict[int, dict[int, str]], list[int]]:
        """The lists without c-vertices that no match can use, and the b-vertices that may stand fourth."""
        beside = {u for u, label in own.items() if label == "b"}
        kept, fourth = dict(lists), set()
        for c in [u for u, label in own.items() if label == "c" and u in lists]:
            near = {u for u, label in lists[c].items() if label == "b"}
            inner, outer = near & beside, near - beside
            if not inner or (self.injective and len(inner) == 1 and not outer):
                del kept[c]
            elif self.injective and len(inner) == 1:
                fourth |= outer
            else:
                fourth |= near
        return kept, sorted(fourth)

    def _known(self, arcs: dict[tuple[int, int], set], u: int, items: list) -> dict[int, str]:
        """The items' labels; the labels of the edges go to ``arcs``, by where these begin and end."""
        for x in items if self.arcs else ():
            if x["out"] is not None or x["elabel"] is not None:
                arcs.setdefault((x["id"], u) if x["out"] is False else (u, x["id"]), set()).add(x["elabel"])
        return {x["id"]: x["label"] for x in items}

    def step(self, task, frontier, shared) -> StepOutcome:
        query, plan = self.plan.query, self.plan
        lists, arcs, given = task.state or ({}, {}, None)
        if not lists:
            lists = {task.root: self._known(arcs, task.root, task.own)}
        own = lists[task.root]
        for u, items in frontier:
            lists[u] = self._known(arcs, u, items)
        if given is None and task.iteration < plan.pulled:
            if self.rules:
                lists, more = self._pruned(own, lists)
                more = [u for u in more if u not in lists]
            else:
                wanted = set(self._labels(task.iteration + 1))
                more = sorted({u for items in lists.values() for u, label in items.items() if label in wanted} - lists.keys())
            if more:
                return StepOutcome(pulls=more, state=(lists, arcs, None))
        labels = {u: label for items in lists.values() for u, label in items.items()}
        candidates = {q: sorted(u for u, label in labels.items() if label == name) for q, name in query.labels.items()}
        candidates[plan.root] = [task.root]
        if self.rules:  # the fourth vertex needs a d-neighbour
            candidates[4] = [u for u in candidates[4] if "d" in lists.get(u, {}).values()]
        following = query.order(plan.root)[1] if len(query.labels) > 1 else plan.root
        if given is not None:
            candidates[following] = given
        elif self.max_piece and len(candidates[following]) > self.max_piece:
            some = candidates[following]
            parts = [some[k : k + self.max_piece] for k in range(0, len(some), self.max_piece)]
            return StepOutcome(spawned=[Task(task.root, [], [], (lists, arcs, part), task.iteration) for part in parts], nodes=1)
        wants: dict[tuple[int, int], list] = {}
        for i, j, *rest in query.edges:
            wants.setdefault((i, j), []).append((False, *rest))
            wants.setdefault((j, i), []).append((True, *rest))

        def joined(q1: int, a: int, q2: int, b: int) -> bool:
            if b not in lists.get(a, ()) and a not in lists.get(b, ()):
                return False
            if not self.arcs:
                return True
            for turned, *label in wants[q1, q2]:
                there = arcs.get((b, a) if turned else (a, b), ())
                if not self.directed:
                    there = {*there, *arcs.get((a, b) if turned else (b, a), ())}
                if (label and label[0] not in there) or (self.directed and not there):
                    return False
            return True

        found = match(query, candidates, joined, plan.root, self.injective)
        if self.count:
            nodes = sum(1 for _ in found)
            return StepOutcome(value=nodes, nodes=nodes)
        rows = ([m[q] for q in sorted(query.labels)] for m in found)
        if self.top:
            rows = heapq.nsmallest(self.top, rows, key=lambda m: (-(self.score or sum)(m), m))
        results = list(rows)
        return StepOutcome(results=results, nodes=len(results))


def match_run(g: PropertyGraph, query: QueryGraph = FIVE, root: int | None = None, injective: bool = True, count: bool = False, rules: bool = False, config: RunConfig = RunConfig(), max_piece: int | None = None, top: int = 0, score: Callable[[list[int]], float] | None = None) -> RunResult:
    """Runs a matching; without ``root``, the plan looks at the frequency of labels. Edges of a directed graph keep their direction."""
    if rules and g.directed:
        raise ValueError("the case rules are for undirected graphs")
    lists = attach_neighbor_labels(g)
    frequency = None
    if root is None and not rules:
        frequency = {r["label"]: r["n"] for r in g.vertices.where(F.col("label").isin(sorted(set(query.labels.values())))).groupBy("label").agg(F.count("*").alias("n")).collect()}
    plan = MatchPlan.of(query, 1 if rules else root, frequency)
    return run_program(lists, MatchProgram(plan, injective, count, rules, g.directed, max_piece, top, score), config)


#: Partial matches that are extended at once.
ROWS = 1_000_000


#: What is placed next, and from which of those before it: by lists that must all have it.
Step = tuple[int | str, list[tuple[int | str, Lists]]]


def _extended(got: dict[int | str, np.ndarray], steps: list[Step], wanted: list[int | str], most: int) -> Iterator[dict[int | str, np.ndarray]]:
    """Partial matches (an array for each place) with the next places filled, ``most`` at once; only ``wanted`` ones at the end.

    Each is extended by the shortest list of those before the next one, and the others must have what is found.
    """
    if not steps:
        yield got
        return
    (q, sources), rest = steps[0], steps[1:]
    needed = {*wanted, *(n for _, own in rest for n, _ in own)}
    lengths = np.array([near.lengths(got[n]) for n, near in sources])
    shortest = lengths.argmin(axis=0)
    for which, (n, near) in enumerate(sources):
        rows = np.flatnonzero(shortest == which)
        ends = np.cumsum(lengths[which][rows])
        at = 0
        while at < len(rows):  # so many that their lists are bounded together, but one at least
            to = max(int(np.searchsorted(ends, (ends[at - 1] if at else 0) + most, "right")), at + 1)
            some = rows[at:to]
            items, sizes = near.gathered(got[n][some])
            row = np.repeat(some, sizes)
            for m, other in sources:
                if other is not near:
                    kept = np.flatnonzero(other.having(got[m][row], items))
                    row, items = row[kept], items[kept]
            new = {v: x[row] for v, x in got.items() if v in needed} | {q: items}
            if len(new[q]):
                yield from _extended(new, rest, wanted, most)
            at = to


def _steps(query: QueryGraph, root: int, lists: dict[tuple[int, int], Lists]) -> list[Step]:
    if len(set(query.labels.values())) < len(query.labels):
        raise ValueError("labels must differ")
    order = query.order(root)
    return [(q, [(n, lists[n, q]) for n in order[:k] if n in query.neighbours(q)]) for k, q in enumerate(order) if k]


def _dealt(roots: DataFrame) -> DataFrame:
    return roots.select("id").repartition(int(roots.sparkSession.conf.get("spark.sql.shuffle.partitions")), "id")


def count_looked_up(query: QueryGraph, root: int, roots: DataFrame, lists: dict[tuple[int, int], Lists]) -> int:
    """How many matches of a pattern whose labels all differ, from a root's candidates (``id``) on; none is a row of Spark's.

    ``lists[i, j]``: of each candidate for i, those for j that it is joined to.
    """
    steps, most = _steps(query, root, lists), ROWS

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = sum(len(x[root]) for x in _extended({root: batch.column(0).to_numpy()}, steps, [root], most))
            yield pa.RecordBatch.from_arrays([pa.array([n], pa.int64())], names=["n"])

    return _dealt(roots).mapInArrow(run, "n long").agg(F.sum("n").alias("n")).first()["n"] or 0


def rows_looked_up(query: QueryGraph, root: int, roots: DataFrame, lists: dict[tuple[int, int], Lists], members: dict[int, Lists]) -> DataFrame:
    """``k1``, ``k2``..: the matches of ``count_looked_up`` among classes, each with all ``members[q]`` of its class for q.

    Tasks give them as they find them, so only who reads them stores any.
    """
    places = sorted(query.labels)
    steps, most = _steps(query, root, lists) + [(f"k{q}", [(q, members[q])]) for q in places], ROWS

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for found in _extended({root: batch.column(0).to_numpy()}, steps, [f"k{q}" for q in places], most):
                yield pa.RecordBatch.from_arrays([pa.array(found[f"k{q}"]) for q in places], names=[f"k{q}" for q in places])

    return _dealt(roots).mapInArrow(run, ", ".join(f"k{q} long" for q in places))


def match_rows(result: RunResult, query: QueryGraph = FIVE) -> DataFrame:
    """``k1``, ``k2``..: one column for each query vertex."""
    return result.results.select(*[F.get("members", F.lit(k)).alias(f"k{q}") for k, q in enumerate(sorted(query.labels))])
