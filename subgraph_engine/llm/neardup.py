"""Near-duplicates at a Jaccard similarity, found by an LSH forest and confirmed on whole sets.

A document's set is its distinct shingles of five words. Documents with equal sets form a class;
only one of each class goes on.

1. ``TREES`` sorted orders of min-hash values: each order sorts the classes by ``DEPTH`` values of
   the signature, and a class's candidates are its neighbours with a common prefix of at least
   ``LEAST`` values. How deep the prefix goes follows from how crowded the region is, and the
   number of candidates is linear in the rows however large a group is.
2. Candidates whose signatures agree in too few places can't be similar enough and are dropped;
   what remains connects classes to regions. Where neighbours were dropped inside a run with a
   common prefix, the run's other pairs across regions are compared too, in blocks.
3. Each region's sets are built again from the texts and compared exactly: first with a leader,
   then those that the leader doesn't link with all others, through an inverted index of shingles.
   Large regions go in blocks of bounded size.

A pair at the threshold misses every common prefix with a probability of about
``(1 - 0.75^LEAST)^TREES`` = 5e-6; all links that are found are exact.

Nulls and texts without words have empty sets and no links. Texts of any length. Repeated rows are
one class. Rows without an id keep their set size, have a null component and are kept.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from subgraph_engine.llm.common import discard, slices, written
from subgraph_engine.llm.components import components
from subgraph_engine.llm.hashing import blocks, mix, word_hashes

WORDS = 5
#: Values of a signature, orders, values of an order, and the least common prefix.
VALUES, TREES, DEPTH, LEAST = 128, 32, 8, 4
#: Standard deviations by which a signature may fall short of the threshold.
SLACK = 5.0
#: Sets of a block that are compared with all others before it has a main component.
LEADERS = 8
#: Classes of a run that are compared at once, shingles of a region that are, rows up to which a table is broadcast.
RUN_BLOCK, SET_BLOCK, BROADCAST_ROWS = 2048, 2_000_000, 1_000_000

_FACTORS = mix(np.arange(1, WORDS + 1, dtype="<u8") << np.uint64(32)) | np.uint64(1)
_SEEDS = mix(np.arange(1, VALUES + 1, dtype="<u8") << np.uint64(24)) | np.uint64(1)


def shingles(words: np.ndarray) -> np.ndarray:
    """The sorted distinct shingles of a document's word hashes."""
    n = len(words)
    if not n:
        return words
    if n < WORDS:
        return mix(np.array([np.add.reduce(words * _FACTORS[:n]) + np.uint64(n)], "<u8"))
    total = words[: n - WORDS + 1] * _FACTORS[0]
    for k in range(1, WORDS):
        total = total + words[k : n - WORDS + 1 + k] * _FACTORS[k]
    return np.unique(mix(total))


def signature(own: np.ndarray) -> np.ndarray:
    """The least value of each of VALUES hash functions."""
    out = np.empty(VALUES, "<u4")
    for at in range(0, VALUES, 16):
        seeds = _SEEDS[at : at + 16, None]
        out[at : at + 16] = np.min([((own[k : k + 4096] * seeds) >> np.uint64(32)).min(1) for k in range(0, len(own), 4096)], 0)
    return out


def _class(own: np.ndarray) -> int:
    """A 63-bit name of a set: two sums of its mixed members, mixed."""
    sums = np.array([np.add.reduce(mix(own)), np.bitwise_xor.reduce(mix(own + np.uint64(1))), len(own)], "<u8")
    return int(mix(np.add.reduce(sums * _FACTORS[:3], keepdims=True))[0] >> np.uint64(1))


def sets(docs: DataFrame, signed: bool) -> DataFrame:
    """``doc_id, n_shingles, class`` and the signature, or the set itself (binary)."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in blocks(batch, 1):
                hashes, at = word_hashes(part.column(1))
                n, names, data = [], [], []
                for a, b in zip(at[:-1], at[1:], strict=True):
                    own = shingles(hashes[a:b])
                    n.append(len(own))
                    names.append(_class(own) if len(own) else None)
                    data.append((signature(own) if signed else own).tobytes() if len(own) else None)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(n, pa.int64()), pa.array(names, pa.int64()), pa.array(data, pa.binary())], names=["doc_id", "n_shingles", "class", "data"])

    return docs.mapInArrow(rows, "doc_id long, n_shingles long, class long, data binary")


def _needed(threshold: float) -> int:
    """Places in which signatures at the threshold agree at least, but for SLACK deviations."""
    return int(VALUES * threshold - SLACK * (VALUES * threshold * (1 - threshold)) ** 0.5)


def forest_neighbours(classes: DataFrame, parts: int) -> DataFrame:
    """``run, a, b``, written: neighbours in each sorted order; run names the order and the common prefix."""

    def trees(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, 1000):
            if not batch.num_rows:
                continue
            values = np.stack([np.frombuffer(x, "<u4") for x in batch.column("data").to_pylist()])
            order = (np.arange(TREES)[:, None] * LEAST + np.arange(DEPTH)) % VALUES
            keys = values[:, order].astype(">u4")  # rows x trees x depth, ordered as bytes
            raw, width = keys.tobytes(), 4 * DEPTH
            names = ["tree", "key", "class"]
            tree = pa.array(np.tile(np.arange(TREES, dtype="<i4"), batch.num_rows))
            key = pa.array([raw[k : k + width] for k in range(0, len(raw), width)], pa.binary())
            yield pa.RecordBatch.from_arrays([tree, key, pa.array(np.repeat(batch.column("class").to_numpy(), TREES))], names=names)

    def neighbours(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        first = last = None
        for batch in batches:
            n = batch.num_rows
            if not n:
                continue
            tree, own = batch.column("tree").to_numpy(), batch.column("class").to_numpy()
            keys = batch.column("key").to_pylist()
            heads = [k[: 4 * LEAST] for k in keys]
            out = []
            if first is None:
                first = (int(tree[0]), heads[0], int(own[0]))
            elif last[:2] == (int(tree[0]), heads[0]):
                out.append((last[2], int(own[0]), *last[:2]))
            out += [(int(own[k - 1]), int(own[k]), int(tree[k]), heads[k]) for k in range(1, n) if heads[k] == heads[k - 1] and tree[k] == tree[k - 1]]
            last = (int(tree[-1]), heads[-1], int(own[-1]))
            if out:
                a, b, t, h = zip(*out, strict=True)
                yield pa.RecordBatch.from_arrays([pa.array(["pair"] * len(out)), pa.array(t, pa.int32()), pa.array(h, pa.binary()), pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["kind", "tree", "head", "a", "b"])
        if first is not None:
            ends = [("first", *first), ("last", *last)]
            kind, t, h, a = zip(*ends, strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(kind), pa.array(t, pa.int32()), pa.array(h, pa.binary()), pa.array(a, pa.int64()), pa.array(a, pa.int64())], names=["kind", "tree", "head", "a", "b"])

    spread = classes.select("class", "data").mapInArrow(trees, "tree int, key binary, class long")
    ordered = spread.repartitionByRange(parts, "tree", "key", "class").sortWithinPartitions("tree", "key", "class")
    found = written(ordered.mapInArrow(neighbours, "kind string, tree int, head binary, a long, b long").withColumn("part", F.spark_partition_id()), "forest")
    # where one partition ends and the next begins: two rows for each partition
    ends = sorted((r["part"], r["kind"] == "last", r["tree"], bytes(r["head"]), r["a"]) for r in found.where("kind <> 'pair'").collect())
    across = [(x[2], bytearray(x[3]), x[4], y[4]) for x, y in zip(ends, ends[1:], strict=False) if x[0] != y[0] and x[2:4] == y[2:4]]
    pairs = found.where("kind = 'pair'").select("tree", "head", "a", "b")
    if across:
        pairs = pairs.union(found.sparkSession.createDataFrame(across, "tree int, head binary, a long, b long"))
    out = written(pairs.select(F.xxhash64("tree", "head").alias("run"), "a", "b"), "neighbours", shrink=4)
    discard(found)
    return out


def _agreeing(pairs: DataFrame, classes: DataFrame, needed: int) -> DataFrame:
    """``a, b, near``: whether the signatures of distinct pairs agree in enough places."""
    own = classes.select("class", "data", "n_shingles")
    joined = pairs.join(own.toDF("a", "x", "nx"), "a").join(own.toDF("b", "y", "ny"), "b")

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                x, y = (np.frombuffer(b"".join(batch.column(c).to_pylist()), "<u4").reshape(-1, VALUES) for c in ("x", "y"))
                near = (x == y).sum(1) >= needed
                yield pa.RecordBatch.from_arrays([batch.column("a"), batch.column("b"), pa.array(near)], names=["a", "b", "near"])

    return joined.select("a", "b", "x", "y").mapInArrow(rows, "a long, b long, near boolean")


def _looked_up(table: DataFrame, what: str) -> DataFrame:
    """A table of groups, stored; broadcast if its rows are few, so that hot groups aren't gathered to join it."""
    table = written(table, what, shrink=16)
    return F.broadcast(table) if table.count() <= BROADCAST_ROWS else table


def _block(blocks: F.Column) -> F.Column:
    """One of a group's blocks by the class's hash, alike in size and without an order over the group."""
    return F.pmod(F.xxhash64("class"), blocks).cast("int")


def _dealt(rows: DataFrame, every: F.Column, asking: F.Column) -> DataFrame:
    """Each row goes to the pairs of blocks ``i, j`` where it is needed: in i if it asks, in j to be compared with.

    A row that asks goes to all blocks; blocks where none asks meet none.
    """
    asks = F.when(F.col("asks"), F.transform(every, lambda j: F.struct(F.col("block").alias("i"), j.alias("j"), F.lit(True).alias("asks")))).otherwise(F.array())
    there = F.transform(asking, lambda i: F.struct(i.alias("i"), F.col("block").alias("j"), F.lit(False).alias("asks")))
    return rows.withColumn("at", F.explode(F.concat(asks, there))).drop("asks").select("*", "at.i", "at.j", "at.asks")


def _across_regions(broken: DataFrame, classes: DataFrame, needed: int) -> DataFrame:
    """``a, b``: of runs with more than one region, agreeing pairs across regions that connect these.

    ``broken`` has ``run, class, region``; members of the run's smaller regions are compared with all.
    """
    sizes = broken.groupBy("run", "region").agg(F.count("*").alias("n"))
    most = sizes.groupBy("run").agg(F.max(F.struct("n", "region"))["region"].alias("main"), F.count("*").alias("regions"), F.ceil(F.sum("n") / RUN_BLOCK).cast("int").alias("blocks"))
    most = most.where("regions > 1").drop("regions")
    rows = broken.join(_looked_up(most, "main_regions"), "run").withColumn("asks", F.col("region") != F.col("main"))
    rows = written(rows.withColumn("block", _block(F.col("blocks"))), "runs", shrink=4)
    asking = rows.where("asks").groupBy("run").agg(F.collect_set("block").alias("asking"))
    rows = rows.join(_looked_up(asking, "asking"), "run").join(classes.select("class", "data"), "class")
    rows = _dealt(rows, F.sequence(F.lit(0), F.col("blocks") - 1), F.col("asking")).select("run", "i", "j", "asks", "class", "region", "data")

    def compare(table: pa.Table) -> pa.Table:
        x, y = table.filter(table["asks"]), table.filter(pc.invert(table["asks"]))
        xs, ys = (np.frombuffer(b"".join(t["data"].to_pylist()), "<u4").reshape(-1, VALUES) for t in (x, y))
        own, other, others = x["region"].to_numpy(), y["region"].to_numpy(), y["class"].to_pylist()
        done: set[tuple[int, int]] = set()
        out = []
        for k, name in enumerate(x["class"].to_pylist()):
            free = np.flatnonzero(other != own[k])
            for j in free[(ys[free] == xs[k]).sum(1) >= needed]:
                if (pair := (int(own[k]), int(other[j]))) not in done:
                    done.add(pair)
                    out.append((name, others[j]))
        return pa.table({"a": pa.array([a for a, _ in out], pa.int64()), "b": pa.array([b for _, b in out], pa.int64())})

    return rows.groupBy("run", "i", "j").applyInArrow(compare, "a long, b long").distinct()


class _Sets:
    """An inverted index over some sets."""

    def __init__(self, own: list[np.ndarray]) -> None:
        self.sizes = np.array([len(x) for x in own], "<i8")
        every = np.concatenate(own)
        self.values, at = np.unique(every, return_inverse=True)
        order = np.argsort(at, kind="stable")
        self.docs = np.repeat(np.arange(len(own), dtype="<i4"), self.sizes)[order]
        self.starts = np.searchsorted(at[order], np.arange(len(self.values) + 1))

    def linked(self, x: np.ndarray, num: int, den: int) -> np.ndarray:
        """The sets whose similarity with ``x`` is num / den or more."""
        at = np.minimum(np.searchsorted(self.values, x), len(self.values) - 1)
        at = at[self.values[at] == x]
        a, n = self.starts[at], self.starts[at + 1] - self.starts[at]
        if not n.sum():
            return np.zeros(0, "<i8")
        each = np.repeat(a - np.concatenate([[0], np.cumsum(n)[:-1]]), n) + np.arange(n.sum())
        shared = np.bincount(self.docs[each], minlength=len(self.sizes))
        return np.flatnonzero(den * shared >= num * (self.sizes + len(x) - shared))


def _read(column: pa.ChunkedArray) -> list[np.ndarray]:
    return [np.frombuffer(x, "<u8") for x in column.to_pylist()]


def region_links(members: DataFrame, regions: DataFrame, num: int, den: int) -> DataFrame:
    """``a, b``: links that connect all classes of a region that are linked, directly or by others.

    ``members`` has ``class, region, data``, ``regions`` the same classes with ``n_shingles``; sets of a region
    with more than SET_BLOCK shingles go in blocks.
    """
    sums = regions.groupBy("region").agg(F.min("class").alias("leader"), F.sum("n_shingles").alias("n"))
    large = written(sums.where(F.col("n") > SET_BLOCK).select("region", "leader", F.ceil(F.col("n") / SET_BLOCK).cast("int").alias("blocks")), "large_regions", shrink=16)
    if any_large := not large.isEmpty():
        known = F.broadcast(large) if large.count() <= BROADCAST_ROWS else large
        rows = members.join(known, "region", "left")
    else:
        rows = members.select("*", F.lit(None).cast("long").alias("leader"), F.lit(None).cast("int").alias("blocks"))
    rows = rows.withColumn("block", F.coalesce(_block(F.col("blocks")), F.lit(0)))

    def within(table: pa.Table) -> pa.Table:
        names, own, leader = table["class"].to_pylist(), _read(table["data"]), table["leader"][0].as_py()
        order = sorted(range(len(names)), key=lambda k: (names[k] != leader, names[k]))
        names, own = [names[k] for k in order], [own[k] for k in order]
        out, index, root = [], _Sets(own), np.arange(len(own))

        def ask(k: int) -> None:
            for j in index.linked(own[k], num, den):
                if root[j] != root[k]:
                    out.append((names[k], names[j]))
                    root[root == max(root[j], root[k])] = min(root[j], root[k])

        asked = set(range(0, len(own), -(-len(own) // LEADERS)))
        for k in sorted(asked):
            ask(k)
        main = int(np.bincount(root).argmax())
        for k in range(len(own)):  # a link has an end outside the main component or joins what is joined already
            if k not in asked and root[k] != root[main]:
                ask(k)
        return pa.table({"a": pa.array([a for a, _ in out], pa.int64()), "b": pa.array([b for _, b in out], pa.int64())})

    # the leader joins every block, so that what it links is one component throughout
    at = F.when(F.col("class") == F.col("leader"), F.sequence(F.lit(0), F.col("blocks") - 1)).otherwise(F.array("block"))
    spread = rows.withColumn("block", F.explode(at)).select("region", "block", "class", "data", "leader")
    links = written(spread.groupBy("region", "block").applyInArrow(within, "a long, b long"), "links_within", shrink=8)
    if not any_large:
        return links

    roots = components(links)
    rows = rows.where("leader is not null").join(roots.withColumnRenamed("v", "class"), "class", "left").withColumn("root", F.coalesce("root", "class"))
    rows = written(rows, "regions")
    main = rows.groupBy("region", "root").agg(F.count("*").alias("n")).groupBy("region").agg(F.max(F.struct("n", "root"))["root"].alias("main"))
    rows = rows.join(_looked_up(main, "main_components"), "region").withColumn("asks", F.col("root") != F.col("main"))
    asking = rows.where("asks").groupBy("region").agg(F.collect_set("block").alias("asking"))
    rows = _dealt(rows.join(_looked_up(asking, "asking"), "region"), F.sequence(F.lit(0), F.col("blocks") - 1), F.col("asking")).where("i <> j")
    rows = rows.select("region", "i", "j", "asks", "class", "data", "root")

    def between(table: pa.Table) -> pa.Table:
        x, y = table.filter(table["asks"]), table.filter(pc.invert(table["asks"]))
        out, done = [], set()
        if x.num_rows and y.num_rows:
            index, names, roots = _Sets(_read(y["data"])), y["class"].to_pylist(), y["root"].to_pylist()
            for name, root, own in zip(x["class"].to_pylist(), x["root"].to_pylist(), _read(x["data"]), strict=True):
                for j in index.linked(own, num, den):
                    if roots[j] != root and (root, roots[j]) not in done:
                        done.add((root, roots[j]))
                        out.append((name, names[j]))
        return pa.table({"a": pa.array([a for a, _ in out], pa.int64()), "b": pa.array([b for _, b in out], pa.int64())})

    more = rows.groupBy("region", "i", "j").applyInArrow(between, "a long, b long")
    return links.union(written(more, "links_between", shrink=8))


def near_duplicates(docs: DataFrame, num: int = 75, den: int = 100, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, n_shingles, component_id, kept``, a row for each row of ``docs``."""
    spark = docs.sparkSession
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    picked = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    every = written(sets(picked, True), "signatures")
    grouped = every.where("class is not null").groupBy("class").agg(F.min("doc_id").alias("doc_id"), F.first("n_shingles").alias("n_shingles"), F.first("data").alias("data"))
    classes = written(grouped.where("doc_id is not null"), "classes")

    needed = _needed(num / den)
    runs = forest_neighbours(classes, parts)
    pairs = runs.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    judged = written(_agreeing(pairs, classes, needed), "judged", shrink=4)
    near = judged.where("near").select("a", "b")
    regions = written(components(near), "regions", shrink=8)

    far = judged.where("not near").select("a", "b")
    split = runs.select("run", F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).join(far, ["a", "b"], "left_semi").select("run").distinct()
    long_runs = runs.groupBy("run").agg(F.count("*").alias("n")).where("n > 1").join(split, "run", "left_semi").select("run")
    members = runs.join(_looked_up(long_runs, "split_runs"), "run", "left_semi")
    members = members.select("run", F.explode(F.array("a", "b")).alias("class")).distinct()
    broken = members.join(regions.toDF("class", "region"), "class", "left").withColumn("region", F.coalesce("region", "class"))
    near = near.union(written(_across_regions(broken, classes, needed), "across", shrink=8))

    regions = written(components(near), "regions", shrink=8)
    discard(runs)
    wanted = regions.toDF("class", "region").join(classes.select("class", "doc_id", "n_shingles"), "class")
    wanted = written(wanted, "wanted", shrink=4)
    if wanted.count() <= BROADCAST_ROWS:
        texts = picked.join(F.broadcast(wanted.select("doc_id").distinct()), "doc_id", "left_semi")
    else:
        texts = picked.join(wanted.select("doc_id").distinct(), "doc_id", "left_semi")
    members = sets(texts, False).select("class", "data").dropDuplicates(["class"]).join(wanted.select("class", "region"), "class")
    roots = components(region_links(members, wanted.select("class", "region", "n_shingles"), num, den))
    firsts = roots.toDF("class", "root").join(classes.select("class", "doc_id"), "class")
    firsts = firsts.join(firsts.groupBy("root").agg(F.min("doc_id").alias("component")), "root").select("class", "component")
    known = classes.select("class", "doc_id").join(firsts, "class", "left").select("class", F.coalesce("component", "doc_id").alias("component"))
    out = every.drop("data").join(known, "class", "left")
    component = F.when(F.col("doc_id").isNotNull(), F.coalesce("component", "doc_id"))
    return out.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(component == F.col("doc_id"), F.lit(True)).alias("kept"))
