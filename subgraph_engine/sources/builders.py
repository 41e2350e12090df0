"""Graphs from the given tables: undirected, each edge once with ``src < dst``.

Pairs that meet in a group (parts of an order, users of a bucket, documents of a line) grow with
the square of the group, which is the size of the graph itself. Groups that are only noise beyond a
size are bounded by parameters that are part of the graph's definition.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from subgraph_engine.plans.store import written
from subgraph_engine.sources.tables import load

#: Fixed values of the label rule: a linear congruence, shifted, modulo the number of letters.
LETTERS = "abcdefg"


def pairs_of(rows: DataFrame, item: str, *group: str) -> DataFrame:
    """``src, dst`` and the groups of all pairs of distinct items that meet in a group."""
    rows = rows.select(*group, item).distinct()
    a, b = rows.withColumnRenamed(item, "src"), rows.withColumnRenamed(item, "dst")
    return a.join(b, list(group)).where("src < dst")


def alike(rows: DataFrame, item: str, *group: str) -> tuple[DataFrame, DataFrame]:
    """``src, dst`` among the least of all items that are in exactly the same groups, and ``id, nbrs``: who these are.

    Items of the same groups meet each other and the same others, so the pairs of one stand for those of all.
    """
    first, members = least_alike(rows, item, *group)
    return pairs_of(first, item, *group).select("src", "dst").distinct(), members


def least_alike(rows: DataFrame, item: str, *group: str) -> tuple[DataFrame, DataFrame]:
    """The rows of the least of all items that are in exactly the same groups, and ``id, nbrs``: who these are."""
    rows = written(rows.select(*group, item).dropna().distinct(), "groups")
    key = F.sha2(F.to_json(F.array_sort(F.collect_list(F.struct(*group)))), 256)
    same = rows.groupBy(item).agg(key.alias("key")).groupBy("key").agg(F.array_sort(F.collect_list(item)).alias("nbrs"))
    members = written(same.select(F.get("nbrs", F.lit(0)).alias("id"), "nbrs"), "members")
    return rows.join(members.select(F.col("id").alias(item)), item, "left_semi"), members


def co_part(spark: SparkSession, sf: str, orders: int = 1) -> DataFrame:
    """Parts in at least ``orders`` common orders, with the number of these as weight."""
    met = pairs_of(order_parts(spark, sf), "l_partkey", "l_orderkey")
    return met.groupBy("src", "dst").agg(F.count("*").alias("weight")).where(F.col("weight") >= orders)


def order_parts(spark: SparkSession, sf: str) -> DataFrame:
    """``l_orderkey, l_partkey`` of the lines; parts of an order are joined in ``co_part``."""
    return load(spark, sf, "lineitem").select("l_orderkey", "l_partkey")


def co_supplier(spark: SparkSession, sf: str) -> DataFrame:
    """Suppliers in a common order."""
    return pairs_of(load(spark, sf, "lineitem").select("l_orderkey", "l_suppkey"), "l_suppkey", "l_orderkey").select("src", "dst").distinct()


def co_user(spark: SparkSession, sf: str, seconds: int = 600) -> DataFrame:
    """Users with an event of the same type in one bucket of time."""
    return pairs_of(user_buckets(spark, sf, seconds), "user_id", "event_type", "bucket").select("src", "dst").distinct()


def user_buckets(spark: SparkSession, sf: str, seconds: int = 600) -> DataFrame:
    """``user_id, event_type, bucket`` of the events."""
    bucket = F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / (seconds * 1_000_000)).alias("bucket")
    return load(spark, sf, "events").select("user_id", "event_type", bucket)


def user_spans(spark: SparkSession, sf: str, seconds: int = 600) -> DataFrame:
    """``event_type, bucket, user_id, first, last``: a user's first and last time in a bucket.

    The first event is before and the last one after all that any event of the user's is.
    """
    events = load(spark, sf, "events").select("user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    rows = events.withColumn("bucket", F.floor(F.col("t") / (seconds * 1_000_000)))
    return rows.groupBy("event_type", "bucket", "user_id").agg(F.min("t").alias("first"), F.max("t").alias("last"))


def follow_user(spark: SparkSession, sf: str, seconds: int = 600) -> DataFrame:
    """Directed: from a user to each that has an event of the same type later in the same bucket of time."""
    spans = user_spans(spark, sf, seconds)
    a, b = spans.select("event_type", "bucket", F.col("user_id").alias("src"), "first"), spans.select("event_type", "bucket", F.col("user_id").alias("dst"), "last")
    return a.join(b, ["event_type", "bucket"]).where("src <> dst and first < last").select("src", "dst").distinct()


def doc_line(spark: SparkSession, sf: str, least: int = 30, most_docs: int = 50) -> DataFrame:
    """Documents that share a trimmed line of ``least`` characters found in 2 to ``most_docs`` documents."""
    lines = load(spark, sf, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("line")).select("doc_id", F.trim("line").alias("line"))
    lines = lines.where(F.length("line") >= least).distinct()
    shared = lines.groupBy("line").agg(F.count("*").alias("n")).where((F.col("n") >= 2) & (F.col("n") <= most_docs)).select("line")
    return pairs_of(lines.join(shared, "line"), "doc_id", "line").select("src", "dst").distinct()


def page_links(spark: SparkSession, sf: str, share: float = 0.08) -> DataFrame:
    """``page_id, href``: each page's links that are on at least two pages and at most ``share`` of all."""
    pages = load(spark, sf, "pages")
    links = pages.select("page_id", F.explode(F.regexp_extract_all("html", F.lit(r'href="([^"]*)"'), F.lit(1))).alias("href")).distinct()
    most = pages.count() * share
    shared = links.groupBy("href").agg(F.count("*").alias("n")).where((F.col("n") >= 2) & (F.col("n") <= most)).select("href")
    return links.join(shared, "href")


def page_link(spark: SparkSession, sf: str, share: float = 0.08) -> DataFrame:
    """Pages that share a link found on at least two pages and at most ``share`` of all."""
    return pairs_of(page_links(spark, sf, share), "page_id", "href").select("src", "dst").distinct()


def dot(a: str, b: str) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def emb_sim(spark: SparkSession, sf: str, least: float = 0.30, tables: int = 12, bits: int = 0) -> DataFrame:
    """Pairs of vectors with a dot product of ``least``.

    With ``bits`` = 0 each vector meets all others (exact; for up to some thousand vectors). Else
    vectors meet that share a sign pattern of ``bits`` axes in one of ``tables`` (a recall below one).
    """
    vectors = load(spark, sf, "embeddings").select("vec_id", "embedding")
    a = vectors.toDF("src", "x")
    b = vectors.toDF("dst", "y")
    if not bits:
        met = a.join(F.broadcast(b), F.col("src") < F.col("dst"))
    else:
        def signs(v: str) -> Column:
            keys = []
            for t in range(tables):
                key = F.lit(t)
                for k in range(bits):
                    i = (t * bits + k) % 64
                    key = key * 2 + (F.get(v, F.lit(i)) + F.get(v, F.lit((i * 7 + t) % 64)) > 0).cast("int")
                keys.append(key.cast("long"))
            return F.explode(F.array(*keys)).alias("key")

        met = a.select("src", "x", signs("x")).join(b.select("dst", "y", signs("y")), "key").where("src < dst").drop("key").dropDuplicates(["src", "dst"])
    return met.where(dot("x", "y") >= least).select("src", "dst")


#: Kinds of the typed graph; an id is kind * 10^12 + key.
KINDS = {"region": 1, "nation": 2, "customer": 3, "supplier": 4, "part": 5, "order": 6}


def typed_id(kind: str, key: str) -> Column:
    return F.lit(KINDS[kind] * 10**12) + F.col(key).cast("long")


#: Edges of the typed graph: the table, and kind and key of both ends; the name has the kinds.
FOREIGN_KEYS = {
    "nation-region": ("nation", "nation", "n_nationkey", "region", "n_regionkey"), "customer-nation": ("customer", "customer", "c_custkey", "nation", "c_nationkey"),
    "supplier-nation": ("supplier", "supplier", "s_suppkey", "nation", "s_nationkey"), "order-customer": ("orders", "order", "o_orderkey", "customer", "o_custkey"),
    "order-part": ("lineitem", "order", "l_orderkey", "part", "l_partkey"), "order-supplier": ("lineitem", "order", "l_orderkey", "supplier", "l_suppkey"),
    "part-supplier": ("lineitem", "part", "l_partkey", "supplier", "l_suppkey"),
}


def typed_pairs(spark: SparkSession, sf: str, kind: str, other: str) -> DataFrame:
    """``id, nbr``: the ends of an edge of two kinds in this order, repeats as often as the table has them."""
    table, a, key, b, other_key = next(x for x in FOREIGN_KEYS.values() if {x[1], x[3]} == {kind, other})
    ends = {a: typed_id(a, key), b: typed_id(b, other_key)}
    return load(spark, sf, table).select(ends[kind].alias("id"), ends[other].alias("nbr")).dropna()


def typed_graph(spark: SparkSession, sf: str) -> DataFrame:
    """Edges of the foreign keys, with an edge label; ``src < dst`` follows from the kinds."""

    def edge(name: str) -> DataFrame:
        table, a, key, b, other_key = FOREIGN_KEYS[name]
        one, two = typed_id(a, key), typed_id(b, other_key)
        return load(spark, sf, table).select(F.least(one, two).alias("src"), F.greatest(one, two).alias("dst"), F.lit(name).alias("elabel")).distinct()

    return reduce(DataFrame.unionByName, map(edge, FOREIGN_KEYS))


def kind_of(v: str) -> Column:
    names = F.array(*[F.lit(k) for k in KINDS])
    return F.get(names, (F.floor(F.col(v) / 10**12) - 1).cast("int"))


def letter_label(v: Column) -> Column:
    """A letter for each id, evenly spread: the random labels of the matching experiments."""
    x = F.pmod(v * 1103515245 + 12345, F.lit(1 << 31))
    k = F.pmod(F.floor(x / 65536), F.lit(len(LETTERS))).cast("int")
    return F.substring(F.lit(LETTERS), k + 1, F.lit(1))
