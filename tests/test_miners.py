"""Miners on graphs with known answers, and the same answers under every setting."""

import itertools
import random

import pytest
from pyspark.sql import functions as F

from subgraph_engine.baselines import systems
from subgraph_engine.baselines.budget import BudgetExceeded
from subgraph_engine.functions.kernels import FIVE, QueryGraph
from subgraph_engine.measures import costs
from subgraph_engine.operators import cliques, matching, quasi, triangles
from subgraph_engine.operators.graph import PropertyGraph, connected_components, densest_subgraph, encode_ids, forward_adjacency, k_core
from subgraph_engine.plans.program import StepOutcome, TaskProgram
from subgraph_engine.plans.runtime import RunConfig, run_program


def graph(spark, pairs, labels=None):
    edges = spark.createDataFrame(sorted(pairs), "src long, dst long")
    return PropertyGraph(edges, spark.createDataFrame(sorted(labels.items()), "id long, label string") if labels else None)


def complete(n):
    return list(itertools.combinations(range(n), 2))


WORKED = {1: "b", 2: "a", 4: "b", 5: "c", 7: "b", 8: "d"}
WORKED_EDGES = [(1, 2), (2, 4), (2, 5), (4, 5), (5, 7), (7, 8)]


def mappings(result):
    return sorted(tuple(r["members"]) for r in result.results.collect())


def test_worked_match(spark):
    g = graph(spark, WORKED_EDGES, WORKED)
    for how in ({"rules": True}, {}, {"root": 1}, {"injective": False}, {"rules": True, "injective": False}):
        assert mappings(matching.match_run(g, **how)) == [(2, 5, 4, 7, 8)]
    assert [tuple(r) for r in systems.twig_join(g)[0].collect()] == [(2, 5, 4, 7, 8)]
    assert systems.path_explore(g) == {"paths": 2, "closed": 1}
    assert systems.serial(g, "matches") == 1


@pytest.mark.parametrize(
    "edges, labels, want",
    [
        ([(1, 2), (2, 5), (5, 7), (7, 8)], {1: "b", 2: "a", 5: "c", 7: "b", 8: "d"}, 0),  # no b-vertex beside both
        ([(2, 4), (2, 5), (4, 5), (4, 8)], {2: "a", 4: "b", 5: "c", 8: "d"}, 0),  # one b-vertex can't stand twice
        ([(2, 4), (2, 5), (4, 5), (5, 7), (7, 8)], {2: "a", 4: "b", 5: "c", 7: "b", 8: "d"}, 1),  # one inside, one outside
        ([(2, 4), (2, 5), (4, 5), (2, 7), (5, 7), (7, 8), (4, 9)], {2: "a", 4: "b", 5: "c", 7: "b", 8: "d", 9: "d"}, 2),  # either may be the fourth
        ([(1, 2), (2, 4), (2, 5), (4, 5), (5, 7)], {k: v for k, v in WORKED.items() if k != 8}, 0),  # no d
    ],
)
def test_rules(spark, edges, labels, want):
    g = graph(spark, edges, labels)
    assert (matching.match_run(g, rules=True, count=True).value or 0) == want
    assert (matching.match_run(g, count=True).value or 0) == want


def test_edge_labels(spark):
    edges = spark.createDataFrame([(1, 2, "x"), (1, 3, "y")], "src long, dst long, elabel string")
    g = PropertyGraph(edges, spark.createDataFrame([(1, "a"), (2, "b"), (3, "b")], "id long, label string"))
    assert mappings(matching.match_run(g, QueryGraph({1: "a", 2: "b"}, ((1, 2, "y"),)), root=1)) == [(1, 3)]


def test_known_graphs(spark):
    k6 = graph(spark, complete(6))
    assert {triangles.triangle_count(k6, m).first()[0] for m in ("tasks", "intersect", "wedge")} == {20}
    assert cliques.maximum_clique(k6).value == 6
    assert [r["members"] for r in cliques.maximal_clique_run(k6).results.collect()] == [list(range(6))]
    cycle = graph(spark, [(0, 1), (1, 2), (2, 3), (3, 4), (0, 4)])
    assert triangles.triangle_count(cycle, "tasks").first()[0] == 0
    bipartite = graph(spark, [(a, b) for a in range(3) for b in range(3, 6)])
    assert triangles.triangle_count(bipartite).first()[0] == 0
    assert cliques.maximal_clique_run(bipartite, mode="count").value == 9
    empty = graph(spark, [(0, 1)])
    empty = PropertyGraph(empty.edges.where("src > dst"))
    assert triangles.triangle_count(empty, "tasks").first()[0] == 0
    assert cliques.maximum_clique(empty).value == 0


def test_isolated_vertices_are_maximal_cliques(spark):
    g = graph(spark, [(1, 2)], {1: "a", 2: "a", 3: "a"})
    assert sorted(r["members"] for r in cliques.maximal_clique_run(g).results.collect()) == [[1, 2], [3]]


def test_smaller_vertices_stop_larger_pieces(spark):
    g = graph(spark, [(a, b) for a in (1, 2, 3, 4) for b in (1, 2, 3, 4) if a < b])
    rows = cliques.maximal_clique_run(g).results.collect()
    assert [(r["root"], r["members"]) for r in rows] == [(1, [1, 2, 3, 4])]


def test_quasi_clique_through_a_vertex_between(spark):
    g = graph(spark, [(1, 3), (2, 3), (2, 4), (4, 5), (1, 5)])
    assert [r["members"] for r in quasi.quasi_clique_sets(g, (1, 2), 5).collect()] == [[1, 2, 3, 4, 5]]


def random_pairs(seed, n=24, p=0.3):
    rng = random.Random(seed)
    return [(a, b) for a in range(n) for b in range(a + 1, n) if rng.random() < p]


SETTINGS = [RunConfig(), RunConfig(batch_capacity=3), RunConfig(cache_capacity=4), RunConfig(queue="stream"), RunConfig(share=False), RunConfig(minhash_values=1), RunConfig(parts=1)]


def test_answers_do_not_depend_on_settings(spark):
    pairs = random_pairs(5)
    g = graph(spark, pairs)
    assert len({triangles.triangle_tasks(g, c).value for c in SETTINGS} | {triangles.triangle_tasks(g, orient="degree").value, systems.serial(g, "triangles"), systems.level_sync(g, "triangles")[0]}) == 1
    sizes = {cliques.maximum_clique(g, sync=s, bound=b, max_piece=p, max_depth=2).value for s in ("periodic", "final", "none") for b in ("color", "none") for p in (None, 3)}
    assert sizes == {systems.serial(g, "maximum_clique")}
    n = cliques.maximal_clique_run(g, mode="count").value
    assert n == systems.serial(g, "maximal_cliques") == systems.vertex_centric(g, "maximal_cliques")[0] == systems.level_sync(g, "maximal_cliques")[0]
    assert n == sum(r["cliques"] for r in cliques.clique_histogram(g).collect())


def test_quasi_cliques_at_one_are_cliques(spark):
    g = graph(spark, random_pairs(2, 12, 0.5))
    sets = {tuple(r["members"]) for r in quasi.quasi_clique_sets(g, (1, 1), 3).collect()}
    found = {tuple(r["members"]) for k in range(3, 8) for r in cliques.k_cliques(g, k).results.collect()}
    assert sets == found
    maximal = {tuple(r["members"]) for r in quasi.quasi_clique_sets(g, (1, 1), 3, output="maximal").collect()}
    assert maximal == {s for s in sets if not any(set(s) < set(t) for t in sets)}


def test_budgets(spark):
    g = graph(spark, random_pairs(5))
    with pytest.raises(BudgetExceeded):
        systems.serial(g, "triangles", most_edges=3)
    with pytest.raises(BudgetExceeded):
        systems.level_sync(g, "maximal_cliques", max_rows=20)
    with pytest.raises(BudgetExceeded):
        systems.vertex_centric(g, "maximal_cliques", frame_limit=5)


def test_pull_counts(spark):
    g = graph(spark, random_pairs(7))
    tasks = costs.triangle_requests(g)
    forward = {r["id"]: r["nbrs"] for r in forward_adjacency(g).collect()}
    for w in (1, 3):
        got = costs.pull_stats(tasks, w, 4).first()
        assert got["total"] == sum(len(x) - 1 for x in forward.values() if len(x) >= 2)
        assert got["fetched"] <= got["remote"] <= got["total"]
        if w == 1:
            assert got["remote"] == 0
    misses = [costs.cache_stats(tasks, 3, c, 4).agg(F.sum("misses")).first()[0] for c in (1, 4, 100)]
    assert misses == sorted(misses, reverse=True)


def test_balance_is_even(spark):
    rows = spark.createDataFrame([(k, float(1 + k % 50)) for k in range(2000)], "root long, cost double")
    sums = [r["s"] for r in costs.balance(rows, 8).groupBy("bin").agg(F.sum("cost").alias("s")).collect()]
    assert len(sums) == 8 and max(sums) < 1.2 * sum(sums) / 8


def test_helpers(spark):
    two = complete(4) + [(a + 10, b + 10) for a, b in complete(3)]
    g = graph(spark, two)
    assert {(r["id"], r["component"]) for r in connected_components(g).collect()} == {(k, 0) for k in range(4)} | {(k, 10) for k in (10, 11, 12)}
    assert k_core(g, 3).count() == 6
    density, kept = densest_subgraph(g)
    assert density >= 1.5 / (2 * 1.1) and kept.count() > 0
    coded, names = encode_ids(spark.createDataFrame([("x", "y"), ("y", "z")], "src string, dst string"))
    assert names.count() == 3 and coded.count() == 2


def test_validation(spark):
    with pytest.raises(ValueError):
        graph(spark, [(2, 1)]).validate()
    with pytest.raises(ValueError):
        graph(spark, [(1, 2), (1, 2)]).validate()
    with pytest.raises(ValueError):
        graph(spark, [(1, 2)], {1: "a"}).validate()
    rough = spark.createDataFrame([(2, 1), (1, 2), (3, 3), (None, 1)], "src long, dst long")
    assert PropertyGraph.canonical(rough).validate().edges.count() == 1


def test_user_program(spark):
    from subgraph_engine.operators.graph import adjacency

    class StarProgram(TaskProgram):
        """A user's own program: how many pairs of neighbours each vertex has."""

        def seed(self, adjacency):
            return adjacency.select(F.col("id").alias("root"), F.col("nbrs").alias("own"), F.array().cast("array<bigint>").alias("pulls"))

        def step(self, task, frontier, shared):
            return StepOutcome(value=len(task.own) * (len(task.own) - 1) // 2)

    assert run_program(adjacency(graph(spark, complete(5))), StarProgram()).value == 5 * 6


def test_hub(spark):
    g = graph(spark, [(0, k) for k in range(1, 3000)])
    assert triangles.triangle_tasks(g, RunConfig(cache_capacity=100)).value == 0


def test_plans_have_no_cartesian_and_prune_columns(spark):
    import __spark_entry__

    plan = __spark_entry__.queries()["op_scan_pruned"](spark, "/root/testdata/sf0.001")._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(l_shipdate), GreaterThanOrEqual" in plan and "l_extendedprice" not in plan
    plan = triangles.triangle_count(graph(spark, complete(4)))._jdf.queryExecution().executedPlan().toString()
    assert "Cartesian" not in plan and "NestedLoop" not in plan and "Python" not in plan


def test_five_is_the_pattern():
    assert FIVE.layers(1) == [{1}, {2, 3}, {4}, {5}]


def test_adjacency_is_built_once(spark):
    """However many rounds a run takes, the rows of the source are computed once."""
    seen = spark.sparkContext.accumulator(0)
    edges = sorted(random_pairs(5))

    def counted(batches):
        for batch in batches:
            seen.add(batch.num_rows)
            yield batch

    from subgraph_engine.operators.graph import adjacency

    lists = adjacency(PropertyGraph(spark.createDataFrame(edges, "src long, dst long").mapInArrow(counted, "src long, dst long")))
    got = run_program(lists, quasi.QuasiCliqueProgram(1, 1, 3, None))
    assert got.metrics["rounds"] > 1 and seen.value == len(edges)


def test_splitting_changes_no_answer(spark):
    g = graph(spark, random_pairs(9, 20, 0.4), {k: "abcde"[k % 5] for k in range(20)})
    whole, parts = (sorted(map(tuple, cliques.maximal_clique_run(g, max_piece=p).results.select("members").collect())) for p in (None, 2))
    assert whole == parts
    whole, parts = (sorted(mappings(matching.match_run(g, rules=True, max_piece=p))) for p in (None, 1))
    assert whole == parts and whole
    for mode in ("all", "maximal", "largest"):
        whole, parts = (sorted(tuple(r["members"]) for r in quasi.quasi_clique_sets(g, (3, 5), 4, output=mode, max_piece=p).collect()) for p in (None, 3))
        assert whole == parts and whole
    assert quasi.quasi_run(g, (3, 5), 4, mode="count", max_piece=3).value == len(quasi.quasi_clique_sets(g, (3, 5), 4).collect())


def test_hub_beside_a_clique(spark):
    """A star of thousands and a clique around its hub: lists in chunks, batches bounded by items, the same answers."""
    from subgraph_engine.plans import runtime

    g = graph(spark, sorted({(0, k) for k in range(1, 3000)} | set(complete(9))))
    chunk, runtime.CHUNK = runtime.CHUNK, 100
    try:
        config = RunConfig(item_capacity=200)
        assert triangles.triangle_tasks(g, config).value == 84
        assert cliques.maximum_clique(g, config=config, max_piece=4, max_depth=2).value == 9
        assert cliques.maximal_clique_run(g, mode="count", config=config, max_piece=50).value == 1 + 3000 - 9
    finally:
        runtime.CHUNK = chunk


def test_batches_are_bounded_by_items_and_cost(spark):
    from subgraph_engine.plans.queue import Weights, plan_batches

    rows = [(k, k, [0] * 3, [1000 + k, 7], None, 1) for k in range(50)]
    tasks = spark.createDataFrame(rows, "root long, task_id long, own array<long>, pulls array<long>, state binary, iteration int")
    batches = plan_batches(tasks, 1, item_capacity=25, lists=Weights({7: 10}, 2.0)).groupBy("batch").agg(F.count("*").alias("n")).collect()
    assert max(r["n"] for r in batches) == 7  # a shared list of 10, and 2 for each task
    batches = plan_batches(tasks, 1, cost_capacity=45.0, lists=Weights({7: 10}, 2.0)).groupBy("batch").agg(F.count("*").alias("n")).collect()
    assert max(r["n"] for r in batches) == 3  # 12 items and 3 pairs each


def test_directions_count(spark):
    edges = spark.createDataFrame([(1, 2, "x"), (2, 3, "x"), (3, 1, "y"), (2, 1, "z")], "src long, dst long, elabel string")
    g = PropertyGraph(edges, spark.createDataFrame([(1, "a"), (2, "b"), (3, "c")], "id long, label string"), True)

    def found(*arcs):
        return mappings(matching.match_run(g, QueryGraph({1: "a", 2: "b", 3: "c"}, arcs), root=1))

    assert found((1, 2), (2, 3), (3, 1)) == [(1, 2, 3)]
    assert found((1, 2), (2, 3), (1, 3)) == []
    assert found((2, 1, "z"), (1, 2, "x"), (2, 3)) == [(1, 2, 3)]
    assert found((2, 1, "x"), (2, 3)) == []
    assert mappings(matching.match_run(g.reversed(), QueryGraph({1: "a", 2: "b", 3: "c"}, ((2, 1), (3, 2), (1, 3))), root=2)) == [(1, 2, 3)]
    assert g.undirected().edges.count() == 3


def test_lists_stay_in_their_buckets(spark):
    from subgraph_engine.operators.graph import adjacency
    from subgraph_engine.plans import runtime

    lists = runtime.stored(adjacency(graph(spark, complete(30))))
    wanted = spark.range(30).withColumn("of", F.lit(1)).hint("merge")
    plan = wanted.join(runtime._chunks(lists), "id")._jdf.queryExecution().executedPlan().toString()
    side = plan[plan.index("Generate explode"):]
    assert "Bucketed: true" in side and "Exchange" not in side
