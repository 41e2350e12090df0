"""Connected components of a table of links, by rounds of star contraction.

Each round links every vertex's larger neighbours to its smallest neighbour, then every vertex's
smaller neighbours and itself to the smallest of them. Rounds end when the links no longer change;
then each vertex hangs on its component's smallest one. Links stay in the cluster; each round's
links go to the shared folder, and those of the round before are deleted.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from subgraph_engine.llm.common import discard, written


def components(links: DataFrame, rounds: int = 60) -> DataFrame:
    """``v, root``: the smallest vertex of each vertex's component; ``links`` has ``a, b``.

    Vertices without a link to another one are left out.
    """
    links = links.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).where("a <> b").distinct()
    links, before = written(links, "links", shrink=8), None
    for _ in range(rounds):
        now = links.agg(F.count("*").alias("n"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")).alias("h")).first()
        if now == before:
            break
        before = now
        both = links.select(F.explode(F.array(F.struct("a", "b"), F.struct(F.col("b").alias("a"), F.col("a").alias("b"))))).select("col.a", "col.b")
        least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
        large = both.join(least, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b"))
        least = large.groupBy("a").agg(F.min("b").alias("m"))
        ends = F.explode(F.array(F.struct(F.col("a").alias("a"), F.col("m").alias("b")), F.struct(F.col("b").alias("a"), F.col("m").alias("b"))))
        small = large.join(least, "a").select(ends).select("col.a", "col.b").where("a <> b").distinct()
        links, old = written(small, "links", shrink=8), links
        discard(old)
    else:
        raise RuntimeError(f"components did not settle in {rounds} rounds")
    ends = F.explode(F.array(F.struct(F.col("a").alias("v"), F.col("b").alias("root")), F.struct(F.col("b").alias("v"), F.col("b").alias("root"))))
    return links.select(ends).select("col.v", "col.root").distinct()
