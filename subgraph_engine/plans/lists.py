"""Adjacency lists as mapped arrays in the shared folder, for what needs the lists of both ends of many edges.

A join would move a list with each edge; here each list is stored once, and workers look lists up by id.
The shared folder must be mounted on all machines.
"""

from __future__ import annotations

import uuid
from bisect import bisect_right
from collections.abc import Callable, Iterator
from urllib.parse import urlparse

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from subgraph_engine.plans.store import shared_dir

#: Most ids between the ends of a list that is marked in an array; others are met by binary search.
MARKS = 1 << 20

#: How often each vertex stands in a row where its list is marked, on average.
RUN = 200

_OPEN: dict[str, tuple[np.ndarray, np.ndarray, np.ndarray]] = {}


class Lists:
    """``parts``: (least id, folder and name of the arrays) of each stored stretch of ids."""

    def __init__(self, parts: list[tuple[int, str]]) -> None:
        self.parts = sorted(parts)
        self.starts = [p[0] for p in self.parts]
        self.last: tuple = (None, None, 0, None)  # the vertex that was asked about last, its list, the list's first id, marks from there on

    def of(self, v: int) -> np.ndarray:
        """The list of ``v``, ascending; empty if it has none."""
        k = bisect_right(self.starts, v) - 1
        if k >= 0:
            path = self.parts[k][1]
            if path not in _OPEN:
                _OPEN[path] = tuple(np.asarray(np.load(f"{path}.{x}.npy", mmap_mode="r")) for x in ("ids", "ends", "items"))
            ids, ends, items = _OPEN[path]
            at = int(np.searchsorted(ids, v))
            if at < len(ids) and ids[at] == v:
                return items[ends[at] : ends[at + 1]].astype(np.int64, copy=False)
        return np.empty(0, np.int64)

    def ids(self, spark: SparkSession) -> DataFrame:
        """``id``: of all lists, read where they are stored."""

        def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for path in batch.column(0).to_pylist():
                    ids = np.load(f"{path}.ids.npy", mmap_mode="r")
                    for k in range(0, len(ids), 100_000):
                        yield pa.RecordBatch.from_arrays([pa.array(np.array(ids[k : k + 100_000]))], names=["id"])

        return spark.createDataFrame([(path,) for _, path in self.parts], "path string").mapInArrow(read, "id long")

    def _places(self, ids: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
        """Of each part that has some of the ids: which ones, its items, and where their lists begin and end."""
        part = np.searchsorted(self.starts, ids, "right") - 1
        first, last = (int(part.min()), int(part.max())) if len(part) else (-1, -1)
        for k in [first] if first == last else np.unique(part).tolist():
            if k < 0:
                continue
            where = np.arange(len(ids)) if first == last else np.flatnonzero(part == k)
            self.of(self.starts[k])  # opens the part
            known, ends, items = _OPEN[self.parts[k][1]]
            some = ids[where]
            at = np.minimum(np.searchsorted(known, some), len(known) - 1)
            begin = ends[at].astype(np.int64)
            yield where, items, begin, np.where(known[at] == some, ends[at + 1], begin)

    def lengths(self, ids: np.ndarray) -> np.ndarray:
        """How long the lists of many vertices are."""
        out = np.zeros(len(ids), np.int64)
        for where, _, begin, end in self._places(ids):
            out[where] = end - begin
        return out

    def gathered(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The lists of many vertices, one after the other, and how long each is."""
        lengths, found = np.zeros(len(ids), np.int64), []
        for where, items, begin, end in self._places(ids):
            lengths[where] = end - begin
            found.append((where, flat(items, begin, end)))
        if len(found) == 1 and len(found[0][0]) == len(ids):
            return found[0][1].astype(np.int64, copy=False), lengths
        out, starts = np.empty(int(lengths.sum()), np.int64), np.cumsum(lengths) - lengths
        for where, some in found:
            out[_spread(starts[where], lengths[where])] = some
        return out, lengths

    def having(self, ids: np.ndarray, others: np.ndarray) -> np.ndarray:
        """Whether the list of each vertex has the other id beside it; quickest where a vertex stands many times in a row."""
        out = np.zeros(len(ids), bool)
        cuts = np.flatnonzero(ids[1:] != ids[:-1]) + 1
        if len(ids) >= RUN * (len(cuts) + 1):
            cuts = [0, *cuts.tolist(), len(ids)]
            for a, b in zip(cuts, cuts[1:], strict=False):
                out[a:b] = marked(others[a:b], self.of(int(ids[a])))
            return out
        for where, items, low, high in self._places(ids):
            if not len(items):
                continue
            want, end = others[where], high
            for _ in range(int((high - low).max()).bit_length()):
                middle = (low + high) // 2
                less = (low < high) & (items[np.minimum(middle, len(items) - 1)] < want)
                low, high = np.where(less, middle + 1, low), np.where(less, high, middle)
            out[where] = (low < end) & (items[np.minimum(low, len(items) - 1)] == want)
        return out

    def shared(self, u: int, v: int) -> int:
        """How many ids the lists of two vertices share; quickest if ``u`` is often that of the call before."""
        if self.last[0] != u:
            own, marks = self.of(u), None
            if len(own) and own[-1] - own[0] < MARKS:
                marks = np.zeros(own[-1] - own[0] + 1, bool)
                marks[own - own[0]] = True
            self.last = (u, own, int(own[0]) if len(own) else 0, marks)
        _, own, first, marks = self.last
        other = self.of(v)
        if marks is None:
            return shared_size(own, other)
        other = other[np.searchsorted(other, first) : np.searchsorted(other, first + len(marks))]
        return int(np.count_nonzero(marks[other - first]))

    def union(self, ids: list[int]) -> np.ndarray:
        """All ids in the lists of some vertices, ascending."""
        found = [x for x in map(self.of, ids) if len(x)]
        if not found:
            return np.empty(0, np.int64)
        first, last = min(int(x[0]) for x in found), max(int(x[-1]) for x in found)
        if last - first < MARKS:
            marks = np.zeros(last - first + 1, bool)
            for x in found:
                marks[x - first] = True
            return np.flatnonzero(marks) + first
        known = found[0]
        for x in found[1:]:
            new = x[~contained(x, known)]
            known = np.union1d(known, new) if len(new) else known
        return known


def _folder(df: DataFrame) -> str:
    top = shared_dir(df.sparkSession)
    if ":" in top and not top.startswith("file:"):
        raise ValueError(f"lists are mapped from a mounted folder, which {top} is not")
    return f"{urlparse(top).path}/lists_{uuid.uuid4().hex}"


def _save(path: str, keys: np.ndarray, ends: np.ndarray, items: np.ndarray) -> pa.RecordBatch:
    import os

    os.makedirs(path, exist_ok=True)
    name = f"{path}/{uuid.uuid4().hex}"
    np.save(f"{name}.ids.npy", keys)
    np.save(f"{name}.ends.npy", ends.astype(np.int32) if len(items) < 1 << 31 else ends)
    small = len(items) and -(1 << 31) <= int(items.min()) and int(items.max()) < 1 << 31
    np.save(f"{name}.items.npy", items.astype(np.int32) if small else items)
    return pa.RecordBatch.from_arrays([pa.array([int(keys[0])]), pa.array([name])], names=["least", "path"])


def mapped(adjacency: DataFrame) -> Lists:
    """Stores ``id, nbrs`` (ids once each, lists ascending)."""
    path = _folder(adjacency)

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, sizes, items = [], [], []
        for b in batches:
            ids.append(b.column(0).to_numpy())
            sizes.append(pc.list_value_length(b.column(1)).to_numpy())
            items.append(pc.list_flatten(b.column(1)).to_numpy())
        if sum(map(len, ids)):
            yield _save(path, np.concatenate(ids), np.concatenate([[0], np.cumsum(np.concatenate(sizes), dtype=np.int64)]), np.concatenate(items))

    rows = adjacency.select("id", "nbrs").repartitionByRange("id").sortWithinPartitions("id")
    return Lists([tuple(r) for r in rows.mapInArrow(write, "least long, path string").collect()])


def _distinct(ids: np.ndarray, items: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Pairs in order, each once."""
    if not len(ids):
        return ids, items
    least, first = int(items.min()), int(ids.min())
    width = int(items.max()) - least + 1
    if width * (int(ids.max()) - first + 1) < 1 << 62:
        key = np.unique((ids - first) * width + (items - least))
        return key // width + first, key % width + least
    order = np.lexsort((items, ids))
    ids, items = ids[order], items[order]
    new = np.concatenate([[True], (ids[1:] != ids[:-1]) | (items[1:] != items[:-1])])
    return ids[new], items[new]


#: Rows that a task packs at once, and ids that each task gives for the bounds of stretches.
PACKED, GIVEN = 2_000_000, 1_000


def _narrow(x: np.ndarray) -> bytes:
    """Numbers from 0 on, in as many bytes as the largest needs, all first bytes first."""
    width = max((int(x.max()).bit_length() + 7) // 8, 1)
    return bytes([width]) + x.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :width].T.tobytes()


def _wide(data: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """What ``_narrow`` had, and the bytes after it."""
    width, out = int(data[0]), np.zeros((n, 8), np.uint8)
    out[:, :width] = data[1 : 1 + n * width].reshape(width, n).T
    return out.view("<u8")[:, 0], data[1 + n * width :]


def pack(ids: np.ndarray, items: np.ndarray) -> bytes:
    """Pairs in the order of their ids as bytes: steps between ids, and items from the least one on."""
    ids, items, least = ids.view(np.uint64), items.view(np.uint64), items.min().view(np.uint64)
    head = np.array([len(ids), ids[0], least], "<u8").tobytes()
    return head + _narrow(np.diff(ids, prepend=ids[:1])) + _narrow(items - least)


def unpack(data: bytes | pa.Buffer) -> tuple[np.ndarray, np.ndarray]:
    (n, first, least), rest = np.frombuffer(data, "<u8", 3), np.frombuffer(data, np.uint8, offset=24)
    steps, rest = _wide(rest, int(n))
    return (np.cumsum(steps, dtype=np.uint64) + first).view(np.int64), (_wide(rest, int(n))[0] + least).view(np.int64)


def _moved(rows: DataFrame) -> DataFrame:
    """``part, packed``: ``id, nbr`` rows by stretches of ids, those of a stretch in one task; ``_received`` reads them.

    A few ids of each task say where stretches begin, which is only how tasks are balanced. A packed row takes about
    half as much of the disk as a row of Spark's.
    """
    parts, most = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")), PACKED

    def some(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found, n = [], 0
        for batch in batches:
            ids, n = batch.column(0).to_numpy(), n + batch.num_rows
            found.append(ids[:: max(len(ids) // 64, 1)])
        ids = np.sort(np.concatenate(found)) if found else np.empty(0, np.int64)
        ids = ids[:: max(len(ids) // GIVEN, 1)]
        if len(ids):
            yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(np.full(len(ids), n / len(ids)))], names=["id", "weight"])

    given = sorted(map(tuple, rows.select("id").mapInArrow(some, "id long, weight double").collect()))
    weight = np.cumsum([w for _, w in given])
    bounds = np.unique([given[int(np.searchsorted(weight, weight[-1] * k / parts))][0] for k in range(1, parts)]) if given else np.empty(0)
    bounds = bounds.astype(np.int64)

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0

        def packed() -> pa.RecordBatch:
            ids, items = _distinct(*(np.concatenate([x[k] for x in held]) for k in range(2)))
            at = np.concatenate([[0], np.searchsorted(ids, bounds), [len(ids)]]).tolist()
            which = [k for k in range(len(at) - 1) if at[k] < at[k + 1]]
            data = [pack(ids[at[k] : at[k + 1]], items[at[k] : at[k + 1]]) for k in which]
            return pa.RecordBatch.from_arrays([pa.array(which, pa.int32()), pa.array(data, pa.binary())], names=["part", "packed"])

        for batch in batches:
            if batch.num_rows:
                held.append((batch.column(0).to_numpy(), batch.column(1).to_numpy()))
                n += batch.num_rows
            if n >= most:
                yield packed()
                held, n = [], 0
        if n:
            yield packed()

    return rows.select("id", "nbr").mapInArrow(send, "part int, packed binary").repartition(parts, "part")


def _received(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Ids and items of each stretch that a task has, in order and each pair once."""
    found: dict[int, list] = {}
    for batch in batches:
        for part, data in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
            found.setdefault(part, []).append(unpack(data.as_buffer()))
    while found:
        some = found.pop(min(found))
        yield _distinct(*(np.concatenate([x[k] for x in some]) for k in range(2)))


def _ends(ids: np.ndarray) -> np.ndarray:
    """Where each id's rows begin, and where the last one's end."""
    return np.append(np.flatnonzero(np.concatenate([[True], ids[1:] != ids[:-1]])), len(ids)).astype(np.int64)


def mapped_edges(edges: DataFrame) -> Lists:
    """Stores the lists of ``id, nbr`` rows, repeats once; rows move once, and no list is a row."""
    path = _folder(edges)

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for ids, items in _received(batches):
            ends = _ends(ids)
            yield _save(path, ids[ends[:-1]], ends, items)

    return Lists([tuple(r) for r in _moved(edges.select("id", "nbr")).mapInArrow(write, "least long, path string").collect()])


#: Items of groups that are taken together at once, but for an item that meets more by itself.
MET = 2_000_000


def _met(path: str, ids: np.ndarray, sizes: np.ndarray, some: Callable[[slice], tuple[np.ndarray, np.ndarray]], most: int) -> Iterator[pa.RecordBatch]:
    """Saves the lists of ids (in order, repeated) that get items by their rows, ``sizes`` at most; from ``most`` at once.

    ``some``: of a slice of the rows, which of them each item comes by, and the items.
    """
    ends, before = _ends(ids), np.concatenate([[0], np.cumsum(sizes)])
    found, k = [], 0
    while k < len(ends) - 1:
        to = max(int(np.searchsorted(before[ends], before[ends[k]] + most, "right")) - 1, k + 1)
        roots = np.repeat(np.arange(k, to), np.diff(ends[k : to + 1]))
        row, items = some(slice(ends[k], ends[to]))
        own, items = _distinct(roots[row], items)
        if len(own):
            at = _ends(own)
            found.append((ids[ends[own[at[:-1]]]], np.diff(at), items))
        k = to
    if found:
        keys, lengths, items = (np.concatenate([x[j] for x in found]) for j in range(3))
        yield _save(path, keys, np.concatenate([[0], np.cumsum(lengths)]), items)


def mapped_met(rows: DataFrame, item: str, group: str, up: bool = False) -> Lists:
    """Stores the lists of those that each item meets in a group, only larger ones with ``up``; no pair is a row.

    Rows move twice: to the groups' lists, which are stored too, and to the items, which look them up.
    """
    path, most = _folder(rows), MET
    rows = rows.select(F.col(item).cast("long").alias("id"), F.col(group).cast("long").alias("nbr")).dropna()
    groups = mapped_edges(rows.select(F.col("nbr").alias("id"), F.col("id").alias("nbr")))

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for ids, own in _received(batches):

            def some(rows: slice, ids: np.ndarray = ids, own: np.ndarray = own) -> tuple[np.ndarray, np.ndarray]:
                items, lengths = groups.gathered(own[rows])
                row = np.repeat(np.arange(len(lengths)), lengths)
                kept = items > ids[rows][row] if up else items != ids[rows][row]
                return row[kept], items[kept]

            yield from _met(path, ids, groups.lengths(own), some, most)

    return Lists([tuple(r) for r in _moved(rows).mapInArrow(write, "least long, path string").collect()])


def mapped_before(rows: DataFrame, others: DataFrame) -> Lists:
    """Stores of each id of ``rows`` the ids of ``others`` that have a larger ``at`` in a group; no pair is a row.

    Both: ``id, grp, at``, numbers without nulls. An id may get itself.
    """
    path, most = _folder(rows), MET
    groups = others.groupBy(F.col("grp").alias("id")).agg(F.sort_array(F.collect_list(F.struct("id", "at"))).alias("found"))
    items, ats = (mapped(groups.select("id", F.col(f"found.{k}").alias("nbrs"))) for k in ("id", "at"))

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [[c.to_numpy() for c in b.columns] for b in batches if b.num_rows]
        if not held:
            return
        ids, own, at = (np.concatenate([x[k] for x in held]) for k in range(3))

        def some(rows: slice) -> tuple[np.ndarray, np.ndarray]:
            found, lengths = items.gathered(own[rows])
            row = np.repeat(np.arange(len(lengths)), lengths)
            kept = ats.gathered(own[rows])[0] > at[rows][row]
            return row[kept], found[kept]

        yield from _met(path, ids, items.lengths(own), some, most)

    dealt = rows.select("id", "grp", "at").repartitionByRange("id").sortWithinPartitions("id")
    return Lists([tuple(r) for r in dealt.mapInArrow(write, "least long, path string").collect()])


def contained(some: np.ndarray, among: np.ndarray) -> np.ndarray:
    """Which ids of one ascending list another one has."""
    if not len(among):
        return np.zeros(len(some), bool)
    at = np.searchsorted(among, some)
    at[at == len(among)] = 0
    return among[at] == some


def _spread(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The places from each start on, as many as its size."""
    return np.repeat(starts - (np.cumsum(sizes) - sizes), sizes) + np.arange(int(sizes.sum()))


def flat(items: np.ndarray, begin: np.ndarray, end: np.ndarray) -> np.ndarray:
    """Some stretches of an array, one after the other; short ones without a step of Python's for each."""
    if int((end - begin).sum()) < 64 * len(begin):
        return items[_spread(begin, end - begin)]
    return np.concatenate([items[a:b] for a, b in zip(begin.tolist(), end.tolist(), strict=True)]) if len(begin) else items[:0]


def marked(some: np.ndarray, among: np.ndarray) -> np.ndarray:
    """Which of some ids an ascending list has; by marks if its ends are not too far apart."""
    if not len(among) or int(among[-1]) - int(among[0]) >= min(MARKS, 256 * len(some)):
        return contained(some, among)
    width = int(among[-1] - among[0]) + 1
    marks = np.zeros(width + 1, bool)  # the last one is of all others
    marks[among - among[0]] = True
    return marks[np.minimum((some - among[0]).view(np.uint64), width)] & (some >= among[0])


def placed(some: np.ndarray, among: np.ndarray) -> np.ndarray:
    """Where each of some ids is in an ascending list; -1 for those that it hasn't."""
    if not len(among) or among[-1] - among[0] >= MARKS:
        return np.where(contained(some, among), np.searchsorted(among, some), -1)
    width = int(among[-1] - among[0]) + 1
    marks = np.full(width + 1, -1, np.int32)  # the last one is of all others
    marks[among - among[0]] = np.arange(len(among))
    return marks[np.minimum((some - among[0]).view(np.uint64), width)]


def shared_size(a: np.ndarray, b: np.ndarray) -> int:
    """How many ids two ascending lists share."""
    return int(np.count_nonzero(contained(b, a) if len(a) > len(b) else contained(a, b)))
