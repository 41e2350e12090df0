"""What a user writes: how tasks start, what a pulled vertex shows, and what a task does with it."""

from __future__ import annotations

from dataclasses import dataclass, field
from typing import Any

from pyspark.sql import DataFrame


@dataclass
class Task:
    """root, the root's own list, what it asked for last (in order), its state, and which iteration this is."""

    root: int
    own: list
    pulls: list[int]
    state: Any = None
    iteration: int = 1


@dataclass
class StepOutcome:
    """Results, a contribution to the aggregate, and either nothing more or new requests or tasks."""

    results: list[list[int]] = field(default_factory=list)
    value: int | None = None
    pulls: list[int] | None = None  # to go on with, in the next iteration
    state: Any = None
    spawned: list[Task] = field(default_factory=list)
    nodes: int = 0


class TaskProgram:
    """A program runs in rounds; a step must depend on its arguments only, as Spark may run it again.

    ``seed`` gives ``root, own, pulls`` from an adjacency frame; ``reply`` cuts the lists before
    they travel; ``step`` gets the task, its frontier (pulled lists in the order asked for), and the
    values shared by the driver, where it may leave bounds for the tasks that follow in its batch.
    ``aggregate`` is how values fold: sum or max.
    """

    aggregate = "sum"

    def seed(self, adjacency: DataFrame) -> DataFrame:
        raise NotImplementedError

    def reply(self, adjacency: DataFrame) -> DataFrame:
        """All of each list."""
        return adjacency.select("id", "nbrs")

    def step(self, task: Task, frontier: list[tuple[int, list]], shared: dict[str, Any]) -> StepOutcome:
        raise NotImplementedError
