"""Rows of bits against the joined edges, and methods that read them; no pair is a row."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from subgraph_engine.baselines import systems
from subgraph_engine.operators.classes import Classes
from subgraph_engine.operators.graph import PropertyGraph, ego_pieces
from subgraph_engine.operators.triangles import triangle_count
from subgraph_engine.plans.marks import Marks, Room, dense, numbered, set_places, shared_bits
from subgraph_engine.plans.store import written
from subgraph_engine.sources import builders
from subgraph_engine.workloads import graphs

SF = "/root/testdata/sf0.001"


def met(spark, items=150, seed=1):
    """The edges, and ``id, grp``: no two items alike, wide ids, repeats, nulls and items that meet nobody."""
    rng = random.Random(seed)
    rows = [(rng.choice([1, 10**10]) * v - 7, rng.choice("xyz"), rng.randrange(8)) for v in range(items) for _ in range(3)]
    rows += rows[:20] + [(5, "alone", 1), (None, "x", 1), (6, None, 1), (6, "x", None)]
    df = spark.createDataFrame(rows, "item long, kind string, at long").repartition(3)
    edges = written(builders.pairs_of(df, "item", "kind", "at").select("src", "dst").distinct(), "edges")
    return PropertyGraph(edges), written(numbered(df, "item", "kind", "at"), "numbered")


@pytest.mark.parametrize("up", [True, False])
@pytest.mark.parametrize("items", [1, 30, 150])
def test_rows_of_bits(spark, items, up):
    g, rows = met(spark, items)
    near = {}
    for a, b in map(tuple, g.edges.collect()):
        near.setdefault(a, set()).add(b)
        near.setdefault(b, set()).add(a)
    m = Marks.of(rows, up)
    ids = m.ids().tolist()
    assert ids == sorted({r["id"] for r in rows.collect()}) and set(near) <= set(ids)
    every = [sorted(near.get(v, set())) for v in ids]
    assert [[ids[k] for k in set_places(m.around(p))] for p in range(m.n)] == every
    assert [[ids[k] for k in set_places(m.row(p))] for p in range(m.n)] == [[u for u in own if u > v or not up] for v, own in zip(ids, every, strict=True)]
    some = np.arange(0, m.n, 2)
    lengths = [len(set_places(m.row(p))) for p in some]
    assert sum(x[2] for x in m.copies(some, Room(m.n * m.width))) == sum(lengths) == sum(int(np.bitwise_count(x[3]).sum()) for x in m.copies(some, Room(m.n * m.width)))
    assert set_places(m.marked(spark.createDataFrame([(v,) for v in [*ids[::3], -1000, 10**15]], "id long"))).tolist() == list(range(0, m.n, 3))


def test_bits_in_both():
    rng = np.random.default_rng(1)
    a, b = (rng.integers(0, 1 << 63, (5, 3), np.uint64) for _ in range(2))
    assert shared_bits(a, b) == int(np.bitwise_count(a & b).sum()) and shared_bits(a[:0], b[:0]) == 0


def test_few_that_meet_are_lists(spark):
    """A bit for each two vertices would take more; one group of all is dense."""
    pairs = spark.range(5000).select("id", F.floor(F.col("id") / 2).alias("grp"))
    assert not dense(pairs) and dense(pairs.withColumn("grp", F.lit(1)))


@pytest.mark.parametrize("is_dense", [True, False])
def test_materialised_bits(spark, monkeypatch, is_dense):
    """No edge is a row of a table, and rows of a root may be in several bins."""
    g, rows = met(spark)
    want, m = systems.serial(g, "triangles"), Marks.of(rows)
    got = [systems.materialized(m, "triangles", bins) for bins in (1, 100_000)]
    listed = systems.materialized(g, "triangles")
    assert {x["value"] for x in got} == {want} and {x["copies"] for x in got} == {listed["copies"]} and got[0]["items"] == listed["items"]
    assert got[0]["bins"] > got[1]["bins"] > 0
    monkeypatch.setattr(builders, "pairs_of", lambda *a: pytest.fail("pairs are made") if is_dense else rows.selectExpr("id AS src", "id AS dst"))
    monkeypatch.setattr(graphs, "dense", lambda rows: is_dense)
    found = graphs.meeting_users(spark, SF)
    assert isinstance(found, Marks if is_dense else Classes)
    monkeypatch.undo()
    assert systems.materialized(found, "triangles")["value"] == systems.serial(graphs.graph(spark, SF, "co_user"), "triangles") > 0


def test_wedges_of_bits(spark):
    g, rows = met(spark)
    got = triangle_count(Marks.of(rows), "wedge")
    assert "Join" not in got._jdf.queryExecution().executedPlan().toString() and got.first()[0] == systems.serial(g, "triangles") > 0
    assert triangle_count(Marks.of(rows.limit(0)), "wedge").first()[0] == 0


def test_nets_of_bits(spark):
    g, rows = met(spark)
    want = systems.serial(g, "triangles")
    assert systems.ego_cliques(Marks.of(rows), 3) == systems.ego_cliques(g, 3) == (3 * want, want)


def test_paths_of_bits(spark):
    g, rows = met(spark)
    label = F.element_at(F.array(*map(F.lit, "abcd")), (F.pmod("id", F.lit(4)) + 1).cast("int"))
    labelled = rows.select("id").distinct().select("id", label.alias("label"))
    want = systems.path_explore(PropertyGraph(g.edges, g.ids().select("id", label.alias("label"))))
    assert want["closed"] and systems.path_explore(Marks.of(rows), labelled) == want


@pytest.mark.parametrize("forward", [True, False])
@pytest.mark.parametrize("hops", [1, 2, 3])
def test_pieces_of_bits(spark, hops, forward):
    g, rows = met(spark, 40)
    got = ego_pieces(Marks.of(rows, up=False), hops, forward)
    assert dict(map(tuple, got.collect())) == dict(map(tuple, ego_pieces(g, hops, forward).collect())) != {}


@pytest.mark.parametrize("name", ["base_materialized", "tri_count_co_user_wedge", "base_ego_cliques", "base_path", "ego_two_forward"])
def test_users_are_no_pairs(spark, monkeypatch, name):
    want = sorted(map(tuple, PLAIN[name](graphs.lettered(spark, SF, "co_user"))))
    monkeypatch.setattr(builders, "pairs_of", lambda *a: pytest.fail("pairs are made"))
    assert sorted(map(tuple, graphs.QUERIES[name](spark, SF).collect())) == want


PLAIN = {
    "base_materialized": lambda g: [(systems.serial(g, "triangles"),)], "tri_count_co_user_wedge": lambda g: [(systems.serial(g, "triangles"),)],
    "base_ego_cliques": lambda g: [(3 * (n := systems.serial(g, "triangles")), n)], "base_path": lambda g: [tuple(systems.path_explore(g).values())],
    "ego_two_forward": lambda g: [(r["root"], len(r["members"])) for r in ego_pieces(g, 2, True).collect()],
}
