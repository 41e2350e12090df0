"""Cases that a reviewer's findings named; each failed before."""

import itertools
import random
import re
import tracemalloc

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from subgraph_engine.baselines import systems
from subgraph_engine.measures import costs
from subgraph_engine.operators import classes, cliques, matching, triangles
from subgraph_engine.operators.classes import Classes
from subgraph_engine.operators.graph import PropertyGraph, ego_pieces, k_core
from subgraph_engine.operators.triangles import triangle_count
from subgraph_engine.plans import lists
from subgraph_engine.plans.lists import mapped, mapped_edges, pack, unpack
from subgraph_engine.plans.runtime import RunConfig
from subgraph_engine.plans.store import written
from subgraph_engine.sources import builders
from subgraph_engine.streaming import replays
from subgraph_engine.workloads import graphs, relational


@pytest.mark.parametrize("rows", [[7], [3, 3, 3], [0, 10**12, 5, 5, 10**12 - 1]])
def test_nth_least_of_few(spark, rows):
    df = spark.createDataFrame([(x,) for x in rows], "v long")
    assert [costs.nth_least(df, "v", n) for n in range(1, len(rows) + 1)] == sorted(rows)


def test_percentile_of_costs_is_exact(spark, monkeypatch):
    values = random.Random(5).sample(range(4_000_000), 60_000)
    df = spark.createDataFrame([(v / 2,) for v in values], "cost double").repartition(24)
    monkeypatch.setattr(costs, "task_costs", lambda g: df)
    assert costs.skew_stats(None).first()["p99"] == sorted(values)[59_400 - 1] / 2


def test_core_that_is_empty(spark, monkeypatch):
    """The first round drops 5 and 6, the second 1 and 4, the third the rest: no 3-core, and one edge before the end."""
    edges = [(1, 2), (2, 3), (3, 4), (2, 4), (1, 3), (1, 5), (4, 6)]
    g = PropertyGraph(spark.createDataFrame(edges, "src long, dst long"))
    assert k_core(g, 3).count() == 0
    monkeypatch.setattr(graphs, "graph", lambda *_: g)
    assert [tuple(r) for r in graphs.QUERIES["kcore"](spark, "").collect()] == [(2, 3)]
    core = PropertyGraph(spark.createDataFrame([(a, b) for a in range(4) for b in range(a + 1, 4)] + [(3, 9)], "src long, dst long"))
    assert k_core(core, 3, last=True).count() == k_core(core, 3).count() == 6


def test_hierarchy_is_of_a_table(spark, tmp_path):
    """Gaps in the keys make more roots; every supplier is in one tree."""
    keys = [*range(40), 100, 101, 200, 403]
    for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events"):
        spark.createDataFrame([(k,) for k in keys], "s_suppkey long").write.parquet(f"{tmp_path}/{t}.parquet")

    def up(k):
        return (k, 0) if k == 0 or k // 2 not in keys else (up(k // 2)[0], up(k // 2)[1] + 1)

    got = relational.QUERIES["op_rec_hierarchy"](spark, str(tmp_path)).collect()
    assert sorted(map(tuple, got)) == sorted((k, *up(k)) for k in keys)
    assert {r["root"] for r in got} == {0, 100, 101, 403}


def test_mapped_lists(spark):
    """Lists that are marked, that are too wide for it, and vertices without one."""
    near = {1: [2, 3, 9], 2: [1, 3], 3: [1, 2, 10**12], 9: [1, 10**12], 10**12: [3, 9]}
    lists = mapped(spark.createDataFrame(list(near.items()), "id long, nbrs array<long>"))
    assert lists.union([1, 2, 5]).tolist() == [1, 2, 3, 9]
    assert lists.union([1, 3, 9]).tolist() == [1, 2, 3, 9, 10**12]
    for u in [*near, 5]:
        assert lists.of(u).tolist() == near.get(u, [])
        assert [lists.shared(u, v) for v in [*near, 5]] == [len({*near.get(u, [])} & {*near.get(v, [])}) for v in [*near, 5]]


@pytest.mark.parametrize("name", ["op_udf_scalar", "op_udf_pandas", "op_udf_arrow", "op_udtf_mine"])
def test_no_list_moves_with_an_edge(spark, name):
    """What the functions are given, and what is shuffled, holds ids only."""
    plan = relational.QUERIES[name](spark, "/root/testdata/sf0.001")._jdf.queryExecution().executedPlan().toString()
    assert "array" not in plan.lower() and not re.search("collect_list|Join", plan)


@pytest.mark.parametrize(("hops", "forward"), [(1, False), (1, True), (2, False), (2, True), (3, True)])
def test_ego_pieces_without_rows_of_paths(spark, hops, forward):
    rng = random.Random(hops)
    edges = sorted({tuple(sorted(rng.sample(range(30), 2))) for _ in range(45)})
    got = ego_pieces(PropertyGraph(spark.createDataFrame(edges, "src long, dst long")), hops, forward)
    assert "Join" not in got._jdf.queryExecution().executedPlan().toString()
    want = {}
    for root in range(30):
        seen, edge = set(), {root}
        for _ in range(hops):
            edge = {v for e in edges for u, v in (e, e[::-1]) if u in edge and (v > root if forward else v != root)}
            seen |= edge
        want |= {root: sorted(seen)} if seen else {}
    assert {r["root"]: r["members"] for r in got.collect()} == want


def test_broadcast_only_of_what_the_driver_holds(spark, monkeypatch):
    sf, join = "/root/testdata/sf0.001", relational.QUERIES["op_join_broadcast"]

    def kind(df):
        return re.findall("BroadcastHashJoin|SortMergeJoin", df._jdf.queryExecution().executedPlan().toString())[0]

    small = join(spark, sf)
    monkeypatch.setattr(relational, "BROADCAST_ROWS", 100, raising=False)
    large = join(spark, sf)
    assert (kind(small), kind(large)) == ("BroadcastHashJoin", "SortMergeJoin")
    assert sorted(small.collect()) == sorted(large.collect())


def test_triangles_of_a_large_bucket_come_in_parts():
    """161,700 triangles of a hundred users, with little of them in memory at once."""
    users, rows = [50, 7], 0
    tracemalloc.start()
    for part in replays.closed(users, [7, *range(100), 3]):
        assert 0 < len(part) <= replays.ROWS
        rows += len(part)
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert rows == 161_700 and sorted(users) == list(range(100)) and most < 6e6
    users = [4, 1]
    assert sorted(r for part in replays.closed(users, [3, 2, 4]) for r in part) == [t for t in itertools.combinations(range(1, 5), 3)]


@pytest.mark.parametrize("orient", ["id", "degree"])
def test_intersections_without_a_join(spark, orient):
    """Nothing is broadcast and no list moves with an edge."""
    g = PropertyGraph(spark.createDataFrame([(1, 2), (1, 3), (2, 3), (3, 4), (2, 4), (4, 5)], "src long, dst long"))
    got = triangle_count(g, "intersect", orient)
    assert "Join" not in got._jdf.queryExecution().executedPlan().toString() and got.first()[0] == 2


def met(spark, seed=1, copies=3, items=24, groups=30):
    """A graph of items that meet in groups, where some items are copies of others: as edges, and by classes."""
    rng = random.Random(seed)
    rows = {(rng.randrange(items), rng.randrange(groups)) for _ in range(items * 3)}
    rows |= {(1000 * k + i, g) for i, g in rows if i % 3 for k in range(1, 1 + i % copies)}
    rows |= {(500, 99), (501, 99), (600, 98), (700, None), (None, 3)}  # a class beside all others, and items that meet nobody
    df = spark.createDataFrame(sorted(rows, key=str), "item long, grp long").repartition(3)
    edges = builders.pairs_of(df, "item", "grp").select("src", "dst").distinct()
    return PropertyGraph(written(edges, "met")), Classes.made(*builders.alike(df, "item", "grp"))


def test_classes_of_items_in_the_same_groups(spark):
    g, c = met(spark)
    whole = [tuple(r) for r in g.edges.collect()]
    near = {v: {v} for e in whole for v in e}
    for a, b in whole:
        near[a].add(b)
        near[b].add(a)
    first = [r["id"] for r in c.graph.ids().collect()]
    assert len(first) < len(near) and sum(c.near.size(v) for v in first) == len(near)
    for v in first:
        own = c.near.members.of(v).tolist() or [v]
        assert min(own) == v and all(near[u] == near[v] for u in own)


@pytest.mark.parametrize("seed", [1, 2])
def test_wedges_are_no_rows(spark, seed):
    g, c = met(spark, seed)
    got = [triangle_count(x, "wedge") for x in (g, c)]
    assert not any("Join" in x._jdf.queryExecution().executedPlan().toString() for x in got)
    assert {x.first()[0] for x in got} == {triangle_count(g).first()[0]}


def test_baselines_of_classes(spark, monkeypatch):
    """Whole graph and classes give what the serial search gives, and no clique, message or copy of a list is a row of its own."""
    stored = []
    monkeypatch.setattr(systems, "written", lambda df, what: stored.append(df) or written(df, what))
    g, c = met(spark)
    want = {app: systems.serial(g, app) for app in ("triangles", "maximum_clique", "maximal_cliques")}
    for x in (g, c):
        assert systems.ego_cliques(x, 3) == (3 * want["triangles"], want["triangles"])
        assert {systems.materialized(x, app, bins)["value"] == want[app] for app in ("triangles", "maximum_clique") for bins in (1, 100_000)} == {True}
        assert systems.vertex_centric(x, "maximal_cliques")[0] == want["maximal_cliques"]
        assert not stored
        assert systems.level_sync(x, "maximal_cliques")[0] == want["maximal_cliques"]
        assert systems.level_sync(x, "triangles")[0] == want["triangles"] and systems.level_sync(x, "maximum_clique")[0] == want["maximum_clique"]
        assert {tuple(df.columns) for df in stored} == {("members", "maximal")}
        stored.clear()
    assert len({systems.ego_cliques(x, 4) for x in (g, c)}) == len({systems.vertex_centric(x, "maximal_cliques") for x in (g, c)}) == 1
    sizes = [systems.level_sync(x, "maximal_cliques")[1] for x in (g, c)]
    assert sizes[0] == sizes[1] and len(sizes[0]) == want["maximum_clique"] + 1
    assert triangles.triangle_tasks(c, RunConfig(queue="stream", batch_capacity=3)).value == want["triangles"]
    lists = [sorted(r["members"] for r in rows.collect()) for rows in (cliques.maximal_clique_run(g).results, c.expanded(cliques.maximal_clique_run(c.graph).results))]
    assert lists[0] == lists[1] and len(lists[0]) == want["maximal_cliques"]


def test_paths_of_classes(spark):
    """Members of a class have labels of their own, and may be next to each other on a path."""
    g, c = met(spark)
    label = F.element_at(F.array(*map(F.lit, "abcd")), (F.col("id") % 4 + 1).cast("int"))
    e = g.edges.collect()
    near = {(a, b) for r in e for a, b in (r, r[::-1])}
    of = {v: "abcd"[v % 4] for v, _ in near}
    paths = [(x, y, z) for x, y in near for u, z in near if u == y and (of[x], of[y], of[z]) == ("b", "a", "c")]
    want = {"paths": len(paths), "closed": sum((x, z) in near for x, _, z in paths)}
    every = g.ids().select("id", label.alias("label"))
    first = {u: v for r in c.graph.ids().collect() for v in [r["id"]] for u in (c.near.members.of(v).tolist() or [v])}
    labelled = spark.createDataFrame([(first[v], v, of[v]) for v in of], "id long, member long, label string")
    assert want["closed"] and systems.path_explore(PropertyGraph(g.edges, every)) == systems.path_explore(c, labelled) == want


@pytest.mark.parametrize("up", [True, False])
@pytest.mark.parametrize("most", [1, 2_000_000])
def test_lists_of_those_met_without_pairs(spark, monkeypatch, up, most):
    """Wide ids, repeats, nulls and items that meet nobody; no row is a pair, and the lists are those of the joined edges."""
    monkeypatch.setattr(lists, "MET", most)
    rng = random.Random(most)
    rows = [(rng.choice([3, 4, 7, 9, 10**12, -5, 12]), rng.randrange(9)) for _ in range(25)] + [(77, 100), (None, 1), (5, None), (4, 200), (5, 200), (4, 200)]
    df = spark.createDataFrame(rows, "item long, grp long").repartition(3)
    edges = builders.pairs_of(df, "item", "grp").select("src", "dst").distinct()
    stored = []
    monkeypatch.setattr(classes, "written", lambda d, what: stored.append(d) or written(d, what))
    c = Classes.met(edges, df, "item", "grp", up)
    assert [d.columns for d in stored] == [["id"]] and "Join" not in stored[0]._jdf.queryExecution().executedPlan().toString()
    near = {}
    for a, b in map(tuple, edges.collect()):
        near.setdefault(a, []).append(b)
        if not up:
            near.setdefault(b, []).append(a)
    assert {r["id"]: c.near.lists.of(r["id"]).tolist() for r in c.graph.ids().collect()} == {v: sorted(x) for v, x in near.items()}
    every = np.array([77, *near, 77, *near, 6])
    items, lengths = c.near.lists.gathered(every)
    assert [x.tolist() for x in np.split(items, np.cumsum(lengths)[:-1])] == [sorted(near.get(v, [])) for v in every.tolist()]
    pairs = np.array([(a, b) for a in every.tolist() for b in every.tolist()])
    assert c.near.lists.having(pairs[:, 0], pairs[:, 1]).tolist() == [b in near.get(a, []) for a, b in pairs.tolist()]
    g = PropertyGraph(edges)
    assert systems.materialized(c, "triangles")["value"] == systems.vertex_centric(g, "triangles")[0] == systems.serial(g, "triangles") > 0


@pytest.mark.parametrize("name", ["base_materialized_co_part", "base_vertex_co_part"])
def test_parts_of_an_order_are_no_pairs(spark, monkeypatch, name):
    """The edges are never made: the methods look lists up that come from the orders."""
    monkeypatch.setattr(builders, "co_part", lambda spark, sf: spark.createDataFrame([], "src long, dst long"))
    assert graphs.QUERIES[name](spark, "/root/testdata/sf0.001").first()[0] == 125_968


def shuffled(spark):
    """Bytes that all stages so far have written for others."""
    sc = spark.sparkContext
    stages = sc._jsc.sc().statusStore().stageList(None, False, False, sc._gateway.new_array(sc._jvm.double, 0), None)
    return sum(stages.apply(k).shuffleWriteBytes() for k in range(stages.size()))


def test_rows_of_lists_move_packed(spark, tmp_path):
    """Groups' and items' rows take under 6 bytes each on their way, and the stored lists are listed without another one."""
    rng = np.random.default_rng(5)
    rows = spark.createDataFrame(pa.table({"item": rng.integers(0, 20_000, 400_000), "grp": rng.integers(0, 100_000, 400_000)}))
    rows.write.parquet(f"{tmp_path}/rows")
    rows, before = spark.read.parquet(f"{tmp_path}/rows"), shuffled(spark)
    c = Classes.met(rows, rows, "item", "grp", up=True)
    assert 0 < shuffled(spark) - before < 2 * 6 * 400_000
    assert c.graph.ids().count() == c.graph.ids().distinct().count() > 19_000


@pytest.mark.parametrize("pairs", [[(5, 7)], [(-3, 9), (-3, -(2**63)), (4, 2**63 - 1)], [(-(2**63), 0), (2**63 - 1, 0)], [(k // 3, k * 1000) for k in range(1000)]])
def test_packed_rows_come_back(pairs):
    ids, items = np.array(pairs, np.int64).T
    got = unpack(pack(ids.copy(), items.copy()))
    assert [x.tolist() for x in got] == [ids.tolist(), items.tolist()]


def test_lists_of_any_ids(spark):
    """Repeats, negative ids, one id for most rows and the largest numbers; all of them are listed."""
    near = {0: set(range(500)), -7: {2**63 - 1, -(2**63)}, 2**63 - 1: {1}, -(2**63): {-1, 3}}
    rows = [(v, u) for v, us in near.items() for u in us] * 2
    lists = mapped_edges(spark.createDataFrame(rows, "id long, nbr long"))
    assert {v: set(lists.of(v).tolist()) for v in near} == near and lists.of(0).tolist() == sorted(near[0])
    assert sorted(r["id"] for r in lists.ids(spark).collect()) == sorted(near)
    assert mapped_edges(spark.createDataFrame([], "id long, nbr long")).of(1).tolist() == []


def test_maximal_cliques_are_counted_without_tasks(spark, monkeypatch):
    """Whole graph, classes and lists of groups give what the serial search gives; neither tasks nor lists are rows."""
    monkeypatch.setattr(cliques, "run_program", None)
    g, c = met(spark)
    want = systems.serial(g, "maximal_cliques")
    assert cliques.count_maximal_cliques(g) == cliques.count_maximal_cliques(c) == want > 0
    rows = spark.createDataFrame([(v, k) for k, e in enumerate(g.edges.collect()) for v in e], "item long, grp long")
    assert cliques.count_maximal_cliques(Classes.met(g.edges, rows, "item", "grp")) == want


def test_pages_of_the_same_links_stand_as_one(spark):
    """Every page ten times over has the same maximal cliques, from as few classes."""
    sf = "/root/testdata/sf0.001"
    pages = builders.page_links(spark, sf)
    more = pages.crossJoin(spark.range(10).toDF("copy")).select((F.col("page_id") + F.col("copy") * 10**6).alias("page_id"), "href")
    found = [Classes.made(*builders.alike(x, "page_id", "href")) for x in (pages, more)]
    assert len({c.graph.ids().count() for c in found}) == 1
    want = cliques.maximal_clique_run(graphs.graph(spark, sf, "page_link"), mode="count").value
    assert {cliques.count_maximal_cliques(c) for c in found} == {want}


@pytest.mark.parametrize("most", [1, 1_000_000])
def test_matches_by_looked_up_lists(spark, monkeypatch, most):
    """A cycle of four labels counted without tasks, by brute force and with lists of any length first."""
    monkeypatch.setattr(matching, "ROWS", most)
    monkeypatch.setattr(matching, "run_program", None)
    rng, query = random.Random(most), graphs.KG_CYCLE
    kinds = {q: [100 * q + k for k in range(6)] for q in query.labels}
    near = {(i, j): {(a, b) for a in kinds[i] for b in kinds[j] if rng.random() < 0.4} for i, j in ((2, 1), (2, 3), (1, 4), (3, 4))}
    lists = {k: mapped_edges(spark.createDataFrame([*x, *x], "id long, nbr long")) for k, x in near.items()}
    want = sum((c, o) in near[2, 1] and (c, n) in near[2, 3] and (o, s) in near[1, 4] and (n, s) in near[3, 4] for o, c, n, s in itertools.product(*(kinds[q] for q in (1, 2, 3, 4))))
    roots = spark.createDataFrame([(v,) for v in kinds[2]], "id long")
    assert matching.count_looked_up(query, 2, roots, lists) == want > 0


@pytest.mark.parametrize("most", [1, 1_000_000])
@pytest.mark.parametrize("name", ["cycle", "transitive"])
def test_directed_matches_without_edges(spark, monkeypatch, tmp_path, name, most):
    """Users of the same times stand as one, follow each other or not; nulls and equal times are no edges. By brute force."""
    for where, what in ((matching, "ROWS"), (lists, "MET"), (lists, "PACKED")):
        monkeypatch.setattr(where, what, most)
    monkeypatch.setattr(matching, "run_program", None)
    monkeypatch.setattr(builders, "follow_user", None)
    rng = random.Random(7)
    some = [(rng.randrange(40), rng.choice("xy"), rng.randrange(3) * 600 + rng.randrange(20)) for _ in range(160)]
    some = [(u + 40 * k, x, t) for u, x, t in some for k in range(1 + u % 4)]  # of every fourth user none, of others up to three copies
    rows = [*some, (None, "x", 5), (3, None, 5), (5, "x", None)]
    df = spark.createDataFrame([(k, u, x, t) for k, (u, x, t) in enumerate(rows)], "event_id long, user_id long, event_type string, t long")
    df.select("event_id", F.timestamp_seconds("t").alias("ts"), "user_id", "event_type").write.parquet(f"{tmp_path}/events.parquet")
    e = {(u, v) for u, x, s in some for v, y, t in some if x == y and s // 600 == t // 600 and s < t and u != v}
    label = {u: "abcdefg"[(u * 1103515245 + 12345) % 2**31 // 65536 % 7] for u, *_ in some}
    a, b, c = ([u for u in label if label[u] == x] for x in "abc")
    want = [(u, v, w) for u in a for v in b for w in c if {(u, v), (v, w), (w, u) if name == "cycle" else (u, w)} <= e]
    got = [tuple(r) for r in graphs.QUERIES[f"match_directed_{name}"](spark, str(tmp_path)).collect()]
    assert sorted(got) == sorted(want) and want


def test_later_ones_in_a_group(spark):
    """Equal times are not later, an id may have itself, and ids may repeat in groups."""
    rows = spark.createDataFrame([(1, 0, 5), (1, 1, 9), (2, 0, 7), (3, 2, 1)], "id long, grp long, at long")
    others = spark.createDataFrame([(1, 0, 6), (2, 0, 7), (2, 1, 10), (4, 0, 5), (5, 3, 100)], "id long, grp long, at long")
    found = lists.mapped_before(rows, others)
    assert [found.of(v).tolist() for v in (1, 2, 3, 4)] == [[1, 2], [], [], []]
