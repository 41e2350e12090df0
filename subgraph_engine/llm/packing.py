"""Packing token sequences into windows of a fixed capacity by minimum bin slack.

1. Each document is encoded and closed by one end id; its ids go to a table in the shared
   folder, with the length that is left beyond full windows and the rank among the documents
   of its partition with that length.
2. The histogram of these lengths (at most ``capacity`` numbers, whatever the corpus) goes to
   the driver. A window takes the longest length left; a bitset of reachable sums over the
   rest shows how close to the capacity it can come, and backtracking gives the counts of each
   length. The same counts serve as many windows as the histogram holds. If no set of lengths
   ends at the capacity, one more document is cut to fill the window and its rest goes back.
3. Ranks become places: a length's documents in order of partition and rank follow the plan's
   ranges. Only the plan, whose size the capacity bounds, goes to the executors.

Only the last window can have slack. Null text counts as empty, so it is the end id alone.
Repeated rows are packed once each. An empty table gives an empty result.
"""

from __future__ import annotations

import zlib
from bisect import bisect_right
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from subgraph_engine.llm.bpe import codec
from subgraph_engine.llm.common import slices, written

#: Rows of (partition, length) offsets that are broadcast; beyond, they are joined by a shuffle.
BROADCAST_ROWS = 400_000


@dataclass
class Plan:
    """Where the items of each length go, by ranges of their ranks.

    ranges[length]: starts and (count for each window or 0 for a cut, taken length, first
    window, offset in the window, first rank of the rest).
    """

    capacity: int
    windows: int = 0
    slack: int = 0
    starts: dict[int, list[int]] = field(default_factory=dict)
    steps: dict[int, list[tuple[int, int, int, int, int]]] = field(default_factory=dict)

    def _add(self, length: int, start: int, step: tuple[int, int, int, int, int]) -> None:
        self.starts.setdefault(length, []).append(start)
        self.steps.setdefault(length, []).append(step)

    def pieces(self, length: int, rank: int) -> Iterator[tuple[int, int, int, int]]:
        """(start, length, window, offset) of the pieces of one item."""
        at = 0
        while length:
            k = bisect_right(self.starts[length], rank) - 1
            count, taken, window, offset, rest = self.steps[length][k]
            k = rank - self.starts[length][k]
            if count:
                yield at, length, window + k // count, offset + k % count * length
                return
            yield at, taken, window + k, offset
            at, length, rank = at + taken, length - taken, rest + k


def closest(counts: dict[int, int], room: int) -> dict[int, int]:
    """How many of each length come closest to ``room`` from below; longer ones first."""
    reach, full, history = 1, (1 << (room + 1)) - 1, []
    for length in sorted((x for x, n in counts.items() if n and x <= room), reverse=True):
        left, step = min(counts[length], room // length), 1
        while left:
            many = min(step, left)
            history.append((length, many, reach))
            reach |= (reach << (length * many)) & full
            left, step = left - many, step * 2
        if reach >> room & 1:
            break
    total, used = reach.bit_length() - 1, {}
    for length, many, before in reversed(history):
        if not before >> total & 1:
            used[length] = used.get(length, 0) + many
            total -= length * many
    return used


def plan_windows(histogram: dict[int, int], capacity: int) -> Plan:
    """The plan for items of these lengths (1 to capacity)."""
    plan = Plan(capacity)
    left = {k: n for k, n in histogram.items() if n and k}
    size = dict(left)  # items that ever had a length: the next free rank
    taken = dict.fromkeys(left, 0)
    while left:
        longest = max(left)
        rest = left | {longest: left[longest] - 1}
        used = closest(rest, capacity - longest)
        used[longest] = used.get(longest, 0) + 1
        slack = capacity - sum(k * n for k, n in used.items())
        over = {k: n - used.get(k, 0) for k, n in left.items() if n > used.get(k, 0)}
        cut = max(over, key=lambda k: (over[k], k)) if slack and over else 0
        times = min(left[k] // (n + (k == cut)) for k, n in used.items())
        if cut:
            times = min(times, left[cut] // (used.get(cut, 0) + 1))
        offset = 0
        for k in sorted(used, reverse=True):
            plan._add(k, taken[k], (used[k], k, plan.windows, offset, 0))
            taken[k] += used[k] * times
            left[k] -= used[k] * times
            offset += used[k] * k
        if cut:
            short = cut - slack
            plan._add(cut, taken[cut], (0, slack, plan.windows, offset, size.get(short, 0)))
            taken[cut] += times
            left[cut] -= times
            taken.setdefault(short, 0)
            size[short] = size.get(short, 0) + times
            left[short] = left.get(short, 0) + times
        else:
            plan.slack += slack * times
        plan.windows += times
        left = {k: n for k, n in left.items() if n}
    return plan


def encoded_items(docs: DataFrame, path: str, capacity: int, end_id: int) -> DataFrame:
    """Each document's ids with the end, and its place among those of its partition."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, part, full, ranks = codec(path), TaskContext.get().partitionId(), 0, [0] * capacity
        end = end_id.to_bytes(4, "little")
        narrow = len(own.pieces) <= 1 << 16
        for batch in slices(batches):
            out: list[list] = [[], [], [], [], []]
            for text in batch.column(1).to_pylist():
                ids = own.encode(text) + end
                n = len(ids) // 4
                length = n % capacity
                for values, x in zip(out, (n, np.frombuffer(ids, "<u4").astype("<u2").tobytes() if narrow else ids, full, length, ranks[length]), strict=True):
                    values.append(x)
                full += n // capacity
                ranks[length] += 1
            kinds = (pa.int64(), pa.binary(), pa.int64(), pa.int32(), pa.int64())
            columns = [pa.array(x, k) for x, k in zip(out, kinds, strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([part] * batch.num_rows, pa.int32()), *columns], names=["doc_id", "part", "doc_tokens", "ids", "full_rank", "item_length", "item_rank"])

    return docs.mapInArrow(rows, "doc_id long, part int, doc_tokens long, ids binary, full_rank long, item_length int, item_rank long")


def pack(docs: DataFrame, path: str, capacity: int = 2048, end_id: int = 1, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False) -> DataFrame:
    """All documents in sequences of ``capacity`` ids.

    A row for each piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset;
    ``with_ids`` adds the piece's ids as an array.
    """
    picked = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    items = written(encoded_items(picked, path, capacity, end_id), "packing_items")
    counted = items.groupBy("part", "item_length").agg(F.count("*").alias("n"), F.sum(F.expr(f"doc_tokens div {capacity}")).alias("full"))
    counted = written(counted, "packing_counts")
    histogram = {r["item_length"]: r["n"] for r in counted.groupBy("item_length").agg(F.sum("n").alias("n")).collect()}
    histogram.pop(0, None)
    plan = plan_windows(histogram, capacity)

    before = Window.rowsBetween(Window.unboundedPreceding, -1)
    fulls = counted.groupBy("part").agg(F.sum("full").alias("full"))
    fulls = fulls.select("part", F.coalesce(F.sum("full").over(before.orderBy("part")), F.lit(0)).alias("full_before"))
    offsets = counted.select("part", "item_length", F.coalesce(F.sum("n").over(before.partitionBy("item_length").orderBy("part")), F.lit(0)).alias("rank_before"))
    offsets = written(offsets.join(fulls, "part"), "packing_offsets")
    if offsets.count() <= BROADCAST_ROWS:
        offsets = F.broadcast(offsets)
    placed = items.join(offsets, ["part", "item_length"])

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            out: list[list] = [[] for _ in range(8)]
            for doc, n, ids, full, length, rank in zip(*(batch.column(x).to_pylist() for x in ("doc_id", "doc_tokens", "ids", "full", "item_length", "item_rank")), strict=True):
                ids = np.frombuffer(ids, "<u2" if len(ids) == 2 * n else "<u4").astype("<u4")
                whole = n // capacity
                pieces = [(k * capacity, capacity, plan.windows + full + k, 0) for k in range(whole)]
                pieces += [(whole * capacity + a, b, c, d) for a, b, c, d in plan.pieces(length, rank)]
                for start, size, window, offset in pieces:
                    own = ids[start : start + size]
                    for values, x in zip(out, (doc, start, size, zlib.crc32(own), n, window, offset, own if with_ids else None), strict=True):
                        values.append(x)
            columns = [pa.array(x, pa.int64()) for x in out[:7]]
            names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]
            if with_ids:
                columns.append(pa.array(out[7], pa.list_(pa.int32())))
                names.append("ids")
            yield pa.RecordBatch.from_arrays(columns, names=names)

    ready = placed.select("doc_id", "doc_tokens", "ids", (F.col("full_rank") + F.col("full_before")).alias("full"), "item_length", (F.col("item_rank") + F.col("rank_before")).alias("item_rank"))
    return ready.mapInArrow(rows, "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long" + (", ids array<int>" if with_ids else ""))
