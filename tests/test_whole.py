"""Queries answer for all of their input: no cap on sizes, no subset of ids."""

import itertools

import pytest

from subgraph_engine.functions.kernels import Piece, quasi_cliques
from subgraph_engine.operators.graph import PropertyGraph
from subgraph_engine.workloads import graphs, relational


@pytest.mark.parametrize("name", ["quasi_maximal", "quasi_largest"])
def test_quasi_cliques_of_any_size(spark, monkeypatch, name):
    edges = [*itertools.combinations(range(1, 11), 2), (10, 11)]
    monkeypatch.setattr(graphs, "graph", lambda *_: PropertyGraph(spark.createDataFrame(edges, "src long, dst long")))
    assert [r["members"] for r in graphs.QUERIES[name](spark, "").collect()] == ["1,2,3,4,5,6,7,8,9,10"]


def test_all_largest_sets_are_given():
    def edge(u, v):
        return (u * 7 + v * 3) % 5 < 3

    piece = Piece.of({u: [v for v in range(12) if v > u and edge(u, v)] for u in range(12)})
    for root in range(12):
        every = list(quasi_cliques(piece, root, 3, 5, 4))
        top = max((m.bit_count() for m in every), default=0)
        found = list(quasi_cliques(piece, root, 3, 5, 4, largest=True))
        assert {m for m in found if m.bit_count() == top} == {m for m in every if m.bit_count() == top}


def test_range_join_of_all_lines_and_parts(spark):
    sf = "/root/testdata/sf0.001"
    lines = spark.read.parquet(f"{sf}/lineitem.parquet").select("l_orderkey", "l_linenumber", "l_extendedprice").collect()
    parts = spark.read.parquet(f"{sf}/part.parquet").select("p_partkey", "p_retailprice").collect()
    prices = [(round(float(p) * 100), k) for k, p in parts]
    want = sorted((o, n, k) for o, n, x in lines for p, k in prices if abs(round(float(x) * 100) - p) <= 500)
    assert sorted(map(tuple, relational.QUERIES["op_join_range"](spark, sf).collect())) == want
    assert any(o >= 400 for o, _, _ in want) and any(k >= 100 for _, _, k in want)


@pytest.mark.parametrize("how", ["left", "right", "full"])
def test_outer_joins_of_all_customers(spark, how):
    sf = "/root/testdata/sf0.01"
    nations = dict(spark.read.parquet(f"{sf}/customer.parquet").select("c_custkey", "c_nationkey").collect())
    got = relational.QUERIES[f"op_join_{how}"](spark, sf).collect()
    assert any(nations.get(r["c_custkey"], 0) >= 12 for r in got)
    assert how == "left" or any(r["c_custkey"] is None for r in got)
    assert how == "right" or any(r["o_orderkey"] is None for r in got)
