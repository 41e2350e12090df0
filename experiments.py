"""Runs the experiment workloads on the given tables and prints their tables as Markdown.

    python experiments.py [sf_dir] [part ...]

Parts: answers, steps, systems, batches, caches, files, queues, pruning, estimates, scaling (all by default).
Absolute times depend on the machine; what matters is which side wins and how a measure moves. A run
of more than LIMIT seconds is stopped and counts as failed.
"""

from __future__ import annotations

import json
import os
import signal
import subprocess
import sys
import tempfile
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from subgraph_engine.baselines import systems
from subgraph_engine.baselines.budget import BudgetExceeded
from subgraph_engine.measures import costs
from subgraph_engine.operators import cliques, matching, triangles
from subgraph_engine.operators.graph import forward_adjacency
from subgraph_engine.plans.runtime import RunConfig, run_program, stored
from subgraph_engine.plans.store import written
from subgraph_engine.workloads.graphs import graph, lettered


def session(cores: int = 8) -> SparkSession:
    here = os.path.dirname(os.path.abspath(__file__))
    os.environ["PYTHONPATH"] = ":".join([here, *filter(None, [os.environ.get("PYTHONPATH")])])
    builder = SparkSession.builder.master(f"local[{cores}]").config("spark.sql.shuffle.partitions", str(cores)).config("spark.driver.memory", "8g")
    builder = builder.config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC")
    spark = builder.config("spark.checkpoint.dir", tempfile.mkdtemp(prefix="experiments_")).getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def line(row: tuple) -> None:
    print("| " + " | ".join(f"{x:.2f}" if isinstance(x, float) else str(x) for x in row) + " |", flush=True)


def show(title: str, head: list[str], rows: list[tuple]) -> None:
    print(f"\n### {title}\n\n| {' | '.join(head)} |\n|{'-|' * len(head)}")
    for r in rows:
        line(r)
    sys.stdout.flush()


LIMIT = int(os.environ.get("EXPERIMENT_LIMIT", "120"))


def _stop(*_) -> None:
    raise TimeoutError


def took(run) -> tuple[object, float]:
    """The answer (or the limit that it fails at) and the seconds."""
    signal.signal(signal.SIGALRM, _stop)
    signal.alarm(LIMIT)
    began = time.perf_counter()
    try:
        out = run()
    except BudgetExceeded as e:
        out = f"fails: {e}"
    except TimeoutError:
        SparkSession.getActiveSession().sparkContext.cancelAllJobs()
        out = f"stopped after {LIMIT} s"
    finally:
        signal.alarm(0)
    return out, time.perf_counter() - began


def answers(spark, sf):
    rows = []
    for name in ("doc_line", "co_user", "co_part", "page_link"):
        g = graph(spark, sf, name)
        rows.append((name, g.ids().count(), g.edges.count(), triangles.triangle_count(g).first()[0], cliques.maximum_clique(g).value if name != "page_link" else "-"))
    show("Graphs and answers", ["graph", "vertices", "edges", "triangles", "largest clique"], rows)


def steps(spark, sf):
    """Loading and building the graph, storing its lists, and mining, each by itself."""
    rows = []
    for name in ("doc_line", "co_user", "co_part"):
        g, load = took(lambda name=name: graph(spark, sf, name))
        lists, build = took(lambda g=g: stored(forward_adjacency(g)))
        for app, run in {"triangles": lambda: run_program(lists, triangles.TriangleProgram()).value, "largest clique": lambda: run_program(lists, cliques.MaxCliqueProgram(), shared={"best": 0}).value}.items():
            answer, mine = took(run)
            rows.append((name, app, answer, load, build, mine))
    show("Seconds by step", ["graph", "problem", "answer", "load and pair", "build lists", "mine"], rows)


def systems_table(spark, sf):
    show("Systems", ["graph", "problem", "system", "answer", "seconds", "times the tasks' seconds"], [])
    for name, rows_limit, frame in (("co_part", 400_000, 50_000), ("co_user", 2_000, 20_000), ("doc_line", 1_000_000, 200_000)):
        g = graph(spark, sf, name)
        m = lettered(spark, sf, name)
        problems = {
            "triangles": {
                "tasks": lambda: triangles.triangle_tasks(g).value, "list intersection": lambda: triangles.triangle_count(g).first()[0], "wedge join": lambda: triangles.triangle_count(g, "wedge").first()[0],
                "serial": lambda: systems.serial(g, "triangles"), "level by level": lambda: systems.level_sync(g, "triangles")[0], "vertex messages": lambda: systems.vertex_centric(g, "triangles")[0],
                "materialised first": lambda: int(systems.materialized(g, "triangles")["value"]),
            },
            "largest clique": {
                "tasks": lambda: cliques.maximum_clique(g).value, "serial": lambda: systems.serial(g, "maximum_clique"), "level by level": lambda: systems.level_sync(g, "maximum_clique", max_rows=rows_limit)[0],
                "materialised first": lambda: int(systems.materialized(g, "maximum_clique")["value"]),
            },
            "maximal cliques": {
                "tasks": lambda: cliques.maximal_clique_run(g, mode="count").value, "serial": lambda: systems.serial(g, "maximal_cliques"),
                f"level by level, {rows_limit} rows": lambda: systems.level_sync(g, "maximal_cliques", max_rows=rows_limit)[0], f"vertex messages, frame {frame}": lambda: systems.vertex_centric(g, "maximal_cliques", frame)[0],
            },
            "matches": {"tasks": lambda: matching.match_run(m, rules=True, count=True).value, "twig join": lambda: systems.twig_join(m)[0].count(), "serial": lambda: systems.serial(m, "matches")},
        }
        for problem, runs in problems.items():
            base = None
            for system, run in runs.items():
                answer, s = took(run)
                base = base or s
                line((name, problem, system, answer, s, s / base if isinstance(answer, int) else "-"))


def batches(spark, sf):
    g = graph(spark, sf, "co_part")
    tasks = written(costs.triangle_requests(g), "requests")
    rows = []
    for b in (10, 100, 1000, 10_000, 100_000):
        got, s = took(lambda b=b: triangles.triangle_tasks(g, RunConfig(batch_capacity=b, balance=0)))
        rows.append((b, costs.pull_stats(tasks, 8, b).first()["fetched"], got.metrics["fetched"], got.metrics["batches"], s))
    got, s = took(lambda: triangles.triangle_tasks(g))
    rows.append(("by cost", "-", got.metrics["fetched"], got.metrics["batches"], s))
    show("Batch capacity (triangles, co_part)", ["tasks of a batch", "fetched, 8 owners", "fetched in the run", "batches", "seconds"], rows)
    rows = []
    for c in (500, 2000, 8000, 1_000_000):
        got, s = took(lambda c=c: triangles.triangle_tasks(g, RunConfig(cache_capacity=c, batch_capacity=100_000, balance=0)))
        rows.append((c, got.metrics["fetched"], got.metrics["batches"], s))
    show("Vertices that a batch may hold (triangles, co_part)", ["vertices", "fetched in the run", "batches", "seconds"], rows)


def estimates(spark, sf):
    """How well estimated costs foretell measured seconds, and what they are good for."""
    g = graph(spark, sf, "co_part")
    seen = written(costs.task_costs(g).join(triangles.triangle_tasks(g, RunConfig(trace=True)).trace, "root"), "seen")
    slope, start = costs.fit_costs(seen)
    r = seen.agg(F.corr("cost", "seconds").alias("r"), F.max("seconds").alias("most"), F.avg("seconds").alias("mean")).first()
    show("Estimated cost and measured seconds (triangles, co_part)", ["tasks", "seconds a unit", "seconds a task", "correlation", "most over mean"], [(seen.count(), f"{slope:.2e}", f"{start:.2e}", r["r"], r["most"] / r["mean"])])
    rows = []
    for how, bins in (("dealt by cost", costs.balance(seen, 16).select("root", "bin")), ("dealt by id", seen.select("root", F.pmod("root", F.lit(16)).alias("bin")))):
        sums = [x["s"] for x in seen.join(bins, "root").groupBy("bin").agg(F.sum("seconds").alias("s")).collect()]
        rows.append((how, max(sums) / (sum(sums) / len(sums))))
    show("Sixteen workers' measured seconds", ["tasks", "most over mean"], rows)


def caches(spark, sf):
    g = graph(spark, sf, "co_part")
    tasks, n = written(costs.triangle_requests(g), "requests"), g.ids().count()
    rows = []
    for share in (0.01, 0.05, 0.2, 1.0):
        got = costs.cache_stats(tasks, 8, max(1, int(n * share)), 25).agg(F.sum("hits"), F.sum("misses"), F.sum("evictions")).first()
        rows.append((share, *got))
    show("Cache capacity (share of the vertices)", ["share", "hits", "misses", "evictions"], rows)


def files(spark, sf):
    tasks = written(costs.triangle_requests(graph(spark, sf, "co_part")), "requests")
    rows = [(w, c, kind, *costs.queue_io(tasks, w, kind, c, 10 * c).agg(F.sum("tasks"), F.sum("reads"), F.sum("writes")).first()) for w in (1, 2, 4, 8) for c in (25, 100, 400) for kind in ("lsh", "stream")]
    show("Queue files read and written", ["workers", "file capacity", "queue", "tasks", "reads", "writes"], rows)


def queues(spark, sf):
    rows = []
    for name in ("co_part", "doc_line", "co_user"):
        g = graph(spark, sf, name)
        rows += [(name, kind, fetched, s) for kind, s, fetched in costs.queue_overhead(g, 8, 25)]
    show("Queue order (25 tasks of a batch, 8 owners)", ["graph", "order", "fetched", "seconds of ordering and counting"], rows)


def pruning(spark, sf):
    g = graph(spark, sf, "co_part")
    rows = []
    for sync in ("periodic", "final", "none"):
        got, s = took(lambda sync=sync: cliques.maximum_clique(g, sync=sync, bound="color" if sync != "none" else "none"))
        rows.append((sync, got.value, got.metrics["nodes"], got.metrics["done"], got.metrics["fetched"], s))
    show("Largest clique: sharing the best size", ["sync", "size", "search nodes", "tasks", "fetched", "seconds"], rows)
    show("Reply policy (triangles, co_part)", ["policy", "items"], [tuple(r) for r in costs.reply_sizes(g).collect()])


def scaling(spark, sf):
    rows = []
    for cores in (1, 2, 4, 8):
        code = f"import experiments as e, json; s = e.session({cores}); print('GOT', json.dumps(e.scaled(s, {sf!r})))"
        out = subprocess.run([sys.executable, "-c", code], capture_output=True, text=True, cwd=os.path.dirname(os.path.abspath(__file__)))
        rows.append((cores, *json.loads(out.stdout.partition("GOT")[2])))
    show("Scaling with cores (seconds)", ["cores", "triangles", "maximal cliques", "matching"], rows)


def scaled(spark, sf) -> list[float]:
    g, m = graph(spark, sf, "co_part"), lettered(spark, sf, "co_part")
    triangles.triangle_tasks(graph(spark, sf, "co_user"))  # warm
    config = RunConfig(batch_capacity=100, parts=32)
    runs = (lambda: triangles.triangle_tasks(g, config).value, lambda: cliques.maximal_clique_run(g, mode="count", config=config).value, lambda: matching.match_run(m, rules=True, count=True, config=config).value)
    return [took(run)[1] for run in runs]


PARTS = {"answers": answers, "steps": steps, "systems": systems_table, "batches": batches, "caches": caches, "files": files, "queues": queues, "pruning": pruning, "estimates": estimates, "scaling": scaling}


def main() -> None:
    sf = next((a for a in sys.argv[1:] if "/" in a), "/root/testdata/sf0.01")
    names = [a for a in sys.argv[1:] if a in PARTS] or list(PARTS)
    spark = session()
    triangles.triangle_tasks(graph(spark, sf, "co_user"))  # warm
    for name in names:
        PARTS[name](spark, sf)


if __name__ == "__main__":
    main()
