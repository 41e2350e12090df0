"""Relational operators that users of the graph methods need, one query each, with SQL."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from subgraph_engine.operators.graph import PropertyGraph, adjacency, forward_adjacency
from subgraph_engine.plans.lists import Lists, mapped
from subgraph_engine.plans.store import shared_dir, written
from subgraph_engine.sources.builders import co_user, dot
from subgraph_engine.sources.tables import AdjacencySource, load, load_adjacency_text, load_edges_text, save_adjacency_text

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def op(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def register(f: Query) -> Query:
        QUERIES[f"op_{name}"] = f
        if sql is not None:
            SQL[f"op_{name}"] = sql
        return f

    return register


def spark_sql(name: str, text: str, duck: str | None = None) -> None:
    """A query that is the same text, or nearly, in both engines."""

    def run(spark: SparkSession, sf: str) -> DataFrame:
        for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events"):
            load(spark, sf, t).createOrReplaceTempView(t)
        return spark.sql(text)

    op(name, duck or text)(run)


def cents(x: str) -> Column:
    """Money as whole hundredths, so that sums are exact."""
    return F.round(F.col(x) * 100).cast("long")


CENTS = "CAST(round({} * 100) AS BIGINT)"


def file_trip(df: DataFrame, kind: str, **options: str) -> DataFrame:
    """Written and read again with its schema."""
    import uuid

    path = f"{shared_dir(df.sparkSession)}/trip_{kind}_{uuid.uuid4().hex}"
    df.write.format(kind).options(**options).save(path)
    return df.sparkSession.read.format(kind).options(**options).schema(df.schema).load(path)


# sources and sinks -------------------------------------------------------------------------------
@op("scan_pruned", "SELECT l_orderkey, l_partkey, l_suppkey FROM lineitem WHERE l_shipdate >= TIMESTAMP '1995-01-01' AND l_shipdate < TIMESTAMP '1995-03-01'")
def scan_pruned(spark, sf):
    day = F.col("l_shipdate")
    return load(spark, sf, "lineitem").where((day >= F.lit("1995-01-01").cast("timestamp_ntz")) & (day < F.lit("1995-03-01").cast("timestamp_ntz"))).select("l_orderkey", "l_partkey", "l_suppkey")


for _kind in ("csv", "json", "orc"):
    op(f"scan_{_kind}_roundtrip", "SELECT c_custkey, c_name, c_nationkey, c_mktsegment FROM customer")(lambda spark, sf, kind=_kind: file_trip(load(spark, sf, "customer").select("c_custkey", "c_name", "c_nationkey", "c_mktsegment"), kind))


_CO_USER = "e AS (SELECT DISTINCT a.user_id AS src, b.user_id AS dst FROM (SELECT DISTINCT user_id, event_type, epoch_us(ts) // 600000000 AS k FROM events) a JOIN (SELECT DISTINCT user_id, event_type, epoch_us(ts) // 600000000 AS k FROM events) b ON a.event_type = b.event_type AND a.k = b.k AND a.user_id < b.user_id)"
_NBRS = f"WITH {_CO_USER}, s AS (SELECT src AS id, dst AS nbr FROM e UNION ALL SELECT dst, src FROM e) SELECT id, count(*) AS n, min(nbr) AS first FROM s GROUP BY id"


def _lists(df: DataFrame) -> DataFrame:
    return df.select("id", F.size("nbrs").cast("long").alias("n"), F.array_min("nbrs").alias("first"))


@op("scan_text_adjacency", _NBRS)
def scan_text_adjacency(spark, sf):
    import uuid

    path = f"{shared_dir(spark)}/adjacency_{uuid.uuid4().hex}"
    save_adjacency_text(adjacency(PropertyGraph(co_user(spark, sf))), path)
    return _lists(load_adjacency_text(spark, path))


@op("scan_edge_list", f"WITH {_CO_USER} SELECT src, dst FROM e")
def scan_edge_list(spark, sf):
    import uuid

    path = f"{shared_dir(spark)}/edges_{uuid.uuid4().hex}"
    co_user(spark, sf).select(F.concat_ws(" ", F.col("src").cast("string"), F.col("dst").cast("string")).alias("value")).write.text(path)
    return load_edges_text(spark, path)


@op("scan_adjacency_source", _NBRS)
def scan_adjacency_source(spark, sf):
    import uuid

    spark.dataSource.register(AdjacencySource)
    path = f"{shared_dir(spark)}/labelled_{uuid.uuid4().hex}".removeprefix("file:")
    rows = adjacency(PropertyGraph(co_user(spark, sf))).select("id", F.lit("a").alias("label"), F.transform("nbrs", lambda x: F.struct(x.alias("id"), F.lit("b").alias("label"), F.lit(None).cast("string").alias("elabel"))).alias("nbrs"))
    rows.write.format("adjacency").mode("append").option("path", path).save()
    got = spark.read.format("adjacency").option("path", path).load()
    return _lists(got.select("id", F.transform("nbrs", lambda x: x["id"]).alias("nbrs")))


@op("sink_partitioned", "SELECT o_orderkey, o_custkey FROM orders WHERE year(o_orderdate) = 1996")
def sink_partitioned(spark, sf):
    import uuid

    path = f"{shared_dir(spark)}/by_year_{uuid.uuid4().hex}"
    load(spark, sf, "orders").select("o_orderkey", "o_custkey", F.year("o_orderdate").alias("y")).write.partitionBy("y").parquet(path)
    return spark.read.parquet(path).where("y = 1996").select("o_orderkey", "o_custkey")


# projections and predicates ----------------------------------------------------------------------
spark_sql("proj_expr", f"SELECT o_orderkey, {CENTS.format('o_totalprice')} AS cents, o_orderkey % 7 AS rest FROM orders")
spark_sql("proj_case", "SELECT o_orderkey, CASE WHEN o_totalprice > 200000 THEN 'large' WHEN o_totalprice > 50000 THEN 'middle' ELSE 'small' END AS size FROM orders")


@op("proj_struct", "SELECT c_custkey, c_nationkey AS nation, c_mktsegment AS segment FROM customer")
def proj_struct(spark, sf):
    packed = load(spark, sf, "customer").select("c_custkey", F.struct(F.col("c_nationkey").alias("nation"), F.col("c_mktsegment").alias("segment")).alias("s"))
    return packed.select("c_custkey", "s.nation", "s.segment")


spark_sql("filter_range", "SELECT p_partkey FROM part WHERE p_size BETWEEN 10 AND 20 AND p_retailprice > 910")
spark_sql("filter_in", "SELECT p_partkey FROM part WHERE p_brand IN ('Brand#11', 'Brand#23') OR p_size IN (1, 2)")
spark_sql("filter_like", "SELECT p_partkey FROM part WHERE p_type LIKE '%E%' AND NOT p_name LIKE 'a%'")
spark_sql("filter_null_safe", "SELECT c_custkey FROM customer WHERE nullif(c_nationkey, 3) <=> NULL", "SELECT c_custkey FROM customer WHERE nullif(c_nationkey, 3) IS NOT DISTINCT FROM NULL")
spark_sql("subq_in", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_totalprice > 300000)")
spark_sql("subq_exists", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
spark_sql("subq_not_exists", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 400000)")
spark_sql("subq_scalar_corr", "SELECT l_orderkey, l_linenumber FROM lineitem l WHERE l_quantity > (SELECT 1.5 * avg(l_quantity) FROM lineitem x WHERE x.l_partkey = l.l_partkey)")

# joins -------------------------------------------------------------------------------------------
_JOINED = "SELECT o_orderpriority, count(*) AS n, CAST(sum(l_quantity) AS BIGINT) AS quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1"
#: Rows of orders that are sent to all tasks; they pass through the driver, about 100 bytes each.
BROADCAST_ROWS = 500_000


def _joined(spark: SparkSession, sf: str, hint: str) -> DataFrame:
    orders = load(spark, sf, "orders").select("o_orderkey", "o_orderpriority")
    if hint == "broadcast" and orders.count() > BROADCAST_ROWS:
        hint = "merge"
    return load(spark, sf, "lineitem").join(orders.hint(hint), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.sum("l_quantity").cast("long").alias("quantity"))


for _hint in ("shuffle_hash", "merge", "broadcast"):
    op(f"join_{_hint}", _JOINED)(lambda spark, sf, hint=_hint: _joined(spark, sf, hint))
for _how, _word in (("left", "LEFT"), ("right", "RIGHT"), ("full", "FULL")):
    # some customers stay without a partner for their balance
    spark_sql(f"join_{_how}", f"SELECT c_custkey, o_orderkey FROM (SELECT * FROM customer WHERE c_acctbal > 0) c {_word} JOIN (SELECT * FROM orders WHERE o_totalprice > 150000) o ON c_custkey = o_custkey")
spark_sql("join_semi", "SELECT p_partkey FROM part LEFT SEMI JOIN (SELECT l_partkey FROM lineitem WHERE l_quantity > 49) l ON p_partkey = l_partkey", "SELECT p_partkey FROM part WHERE p_partkey IN (SELECT l_partkey FROM lineitem WHERE l_quantity > 49)")
spark_sql("join_anti", "SELECT p_partkey FROM part LEFT ANTI JOIN (SELECT l_partkey FROM lineitem WHERE l_quantity > 49) l ON p_partkey = l_partkey", "SELECT p_partkey FROM part WHERE p_partkey NOT IN (SELECT l_partkey FROM lineitem WHERE l_quantity > 49)")
spark_sql("join_cross", "SELECT a.r_name AS x, b.r_name AS y FROM region a CROSS JOIN region b")
spark_sql("join_theta", "SELECT n_nationkey, r_regionkey FROM nation JOIN region ON n_regionkey < r_regionkey")
spark_sql("join_wedge", "SELECT a.o_custkey AS c, count(*) AS pairs FROM orders a JOIN orders b ON a.o_custkey = b.o_custkey AND a.o_orderkey < b.o_orderkey GROUP BY 1")

BAND = 10_000


def _in_band(lines: DataFrame, parts: DataFrame) -> DataFrame:
    """Prices within five of a part's: both sides meet in bands, the point side in one of them."""
    lines = lines.select("l_orderkey", "l_linenumber", cents("l_extendedprice").alias("x"))
    parts = parts.select("p_partkey", cents("p_retailprice").alias("p"))
    spread = parts.withColumn("band", F.explode(F.sequence(F.floor((F.col("p") - 500) / BAND), F.floor((F.col("p") + 500) / BAND))))
    met = lines.withColumn("band", F.floor(F.col("x") / BAND)).join(spread, "band")
    return met.where(F.col("x").between(F.col("p") - 500, F.col("p") + 500)).select("l_orderkey", "l_linenumber", "p_partkey")


@op("join_range", f"SELECT l_orderkey, l_linenumber, p_partkey FROM (SELECT l_orderkey, l_linenumber, {CENTS.format('l_extendedprice')} AS x FROM lineitem) JOIN (SELECT p_partkey, {CENTS.format('p_retailprice')} AS p FROM part) ON x BETWEEN p - 500 AND p + 500")
def join_range(spark, sf):
    """All lines with all parts at prices within five of theirs."""
    return _in_band(load(spark, sf, "lineitem"), load(spark, sf, "part"))


@op("join_interval", "SELECT a.event_id AS first, b.event_id AS second FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id <> b.event_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 30 MINUTE")
def join_interval(spark, sf):
    """Events of a user within half an hour of each other, by buckets of that length."""
    ev = load(spark, sf, "events").select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    wide = 30 * 60 * 1_000_000
    a = ev.toDF("first", "user_id", "ta").withColumn("slot", F.explode(F.array(F.floor(F.col("ta") / wide), F.floor(F.col("ta") / wide) + 1)))
    b = ev.toDF("second", "user_id", "tb").withColumn("slot", F.floor(F.col("tb") / wide))
    return a.join(b, ["user_id", "slot"]).where((F.col("first") != F.col("second")) & F.col("tb").between(F.col("ta"), F.col("ta") + wide)).select("first", "second")


@op("join_asof", "SELECT p.event_id, (SELECT arg_max(e.event_id, (e.ts, e.event_id)) FROM events e WHERE e.user_id = p.user_id AND e.event_type <> 'purchase' AND e.ts <= p.ts) AS before FROM events p WHERE p.event_type = 'purchase'")
def join_asof(spark, sf):
    """Each purchase with its user's last other event: one ordered pass over both."""
    ev = load(spark, sf, "events").select("event_id", "user_id", "ts", (F.col("event_type") == "purchase").alias("buys"))
    w = Window.partitionBy("user_id").orderBy("ts", "buys", "event_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return ev.withColumn("before", F.last(F.when(~F.col("buys"), F.col("event_id")), ignorenulls=True).over(w)).where("buys").select("event_id", "before")


@op("join_lateral", "SELECT c_custkey, o_orderkey FROM (SELECT c_custkey, o_orderkey, row_number() OVER (PARTITION BY c_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM customer JOIN orders ON c_custkey = o_custkey) WHERE r <= 2")
def join_lateral(spark, sf):
    c, o = load(spark, sf, "customer").alias("c"), load(spark, sf, "orders").alias("o")
    top = o.where(F.col("o_custkey") == F.col("c.c_custkey").outer()).orderBy(F.desc("o_totalprice"), "o_orderkey").limit(2)
    return c.lateralJoin(top).select("c_custkey", "o_orderkey")


@op("join_salted", "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
def join_salted(spark, sf):
    """A hot key is dealt to eight tasks, and the small side goes to each."""
    left = load(spark, sf, "customer").withColumn("salt", F.pmod(F.xxhash64("c_custkey"), F.lit(8)).cast("int"))
    right = load(spark, sf, "nation").withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(7))))
    return left.join(right, (F.col("c_nationkey") == F.col("n_nationkey")) & (left.salt == right.salt)).groupBy("n_name").agg(F.count("*").alias("n"))


# aggregates --------------------------------------------------------------------------------------
spark_sql("agg_basic", f"SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(l_quantity) AS BIGINT) AS quantity, CAST(sum({CENTS.format('l_extendedprice')}) AS BIGINT) AS cents, min(l_shipdate) AS first, max(l_shipdate) AS last FROM lineitem GROUP BY 1, 2")
spark_sql("agg_distinct", "SELECT count(DISTINCT l_partkey) AS parts FROM lineitem")
spark_sql("agg_multi_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY 1")
spark_sql("agg_filter", "SELECT o_orderpriority, count(*) FILTER (WHERE o_totalprice > 100000) AS large, count(*) AS n FROM orders GROUP BY 1")
spark_sql("agg_having", "SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1 HAVING count(*) > 12")
spark_sql("agg_stats", "SELECT l_returnflag, round(stddev_samp(l_quantity), 4) AS sd, round(corr(l_quantity, l_extendedprice), 4) AS r, round(avg(l_discount), 4) AS discount FROM lineitem GROUP BY 1")
spark_sql("agg_percentile", "SELECT l_returnflag, round(percentile(l_quantity, 0.5), 4) AS median, round(percentile(l_quantity, 0.9), 4) AS p90 FROM lineitem GROUP BY 1", "SELECT l_returnflag, round(quantile_cont(l_quantity, 0.5), 4) AS median, round(quantile_cont(l_quantity, 0.9), 4) AS p90 FROM lineitem GROUP BY 1")
spark_sql("agg_min_by", "SELECT l_orderkey, min_by(l_linenumber, struct(l_extendedprice, l_linenumber)) AS cheapest FROM lineitem GROUP BY 1", "SELECT l_orderkey, arg_min(l_linenumber, (l_extendedprice, l_linenumber)) AS cheapest FROM lineitem GROUP BY 1")
spark_sql("agg_bool", "SELECT l_orderkey, bool_and(l_quantity > 5) AS every, bool_or(l_quantity > 45) AS some, bit_or(l_linenumber) AS bits FROM lineitem GROUP BY 1")
_CUBE = "SELECT r_name, n_name, c_mktsegment, count(*) AS n, CAST(grouping(r_name) AS INT) AS g FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY {}"
spark_sql("agg_rollup", _CUBE.format("ROLLUP (r_name, n_name, c_mktsegment)"))
spark_sql("agg_cube", _CUBE.format("CUBE (r_name, n_name, c_mktsegment)"))
spark_sql("agg_grouping_sets", _CUBE.format("GROUPING SETS ((r_name, n_name), (c_mktsegment), (r_name, n_name, c_mktsegment))"))


@op("agg_approx_distinct")
def agg_approx_distinct(spark, sf):
    return load(spark, sf, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("users"))


@op("agg_collect", "SELECT l_orderkey, string_agg(DISTINCT l_partkey::VARCHAR, ',' ORDER BY l_partkey::VARCHAR) AS parts FROM lineitem GROUP BY 1")
def agg_collect(spark, sf):
    return load(spark, sf, "lineitem").groupBy("l_orderkey").agg(F.array_join(F.array_sort(F.collect_set(F.col("l_partkey").cast("string"))), ",").alias("parts"))


@op("agg_pivot", "SELECT date_trunc('day', ts)::DATE AS day, count(*) FILTER (WHERE event_type = 'click') AS click, count(*) FILTER (WHERE event_type = 'view') AS view FROM events WHERE event_type IN ('click', 'view') GROUP BY 1")
def agg_pivot(spark, sf):
    rows = load(spark, sf, "events").where(F.col("event_type").isin("click", "view")).select(F.to_date("ts").alias("day"), "event_type")
    return rows.groupBy("day").pivot("event_type", ["click", "view"]).agg(F.count(F.lit(1))).fillna(0)


@op("agg_unpivot", "SELECT p_partkey, 'size' AS name, p_size::BIGINT AS value FROM part UNION ALL SELECT p_partkey, 'cents', CAST(round(p_retailprice * 100) AS BIGINT) FROM part")
def agg_unpivot(spark, sf):
    rows = load(spark, sf, "part").select("p_partkey", F.col("p_size").cast("long").alias("size"), cents("p_retailprice").alias("cents"))
    return rows.unpivot("p_partkey", ["size", "cents"], "name", "value")


# windows -----------------------------------------------------------------------------------------
_ORDERS = "PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey"
_B = "CAST({} AS BIGINT)"
spark_sql("win_rank", f"SELECT o_orderkey, {_B.format(f'row_number() OVER ({_ORDERS})')} AS rn, {_B.format('rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority)')} AS rk, {_B.format('dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority)')} AS dr FROM orders")
spark_sql("win_ntile", f"SELECT o_orderkey, {_B.format(f'ntile(4) OVER ({_ORDERS})')} AS quarter FROM orders")
spark_sql("win_dist", f"SELECT o_orderkey, round(percent_rank() OVER ({_ORDERS}), 6) AS pr, round(cume_dist() OVER ({_ORDERS}), 6) AS cd FROM orders")
spark_sql("win_lag_lead", f"SELECT o_orderkey, lag(o_orderkey) OVER ({_ORDERS}) AS before, lead(o_orderkey, 2) OVER ({_ORDERS}) AS second FROM orders")
spark_sql("win_first_last", f"SELECT o_orderkey, first_value(o_orderkey) OVER ({_ORDERS}) AS most, last_value(o_orderkey) OVER ({_ORDERS} ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS least FROM orders")
spark_sql("win_nth", f"SELECT o_orderkey, nth_value(o_orderkey, 2) OVER ({_ORDERS} ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second FROM orders")
spark_sql("win_running_rows", f"SELECT l_orderkey, l_linenumber, {_B.format('sum(l_quantity) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_quantity ROWS BETWEEN 2 PRECEDING AND CURRENT ROW)')} AS recent, l_partkey, l_suppkey FROM lineitem")
spark_sql("win_range_days", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY datediff(o_orderdate, TIMESTAMP '1992-01-01') RANGE BETWEEN 30 PRECEDING AND CURRENT ROW) AS month FROM orders", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY date_diff('day', TIMESTAMP '1992-01-01', o_orderdate) RANGE BETWEEN 30 PRECEDING AND CURRENT ROW) AS month FROM orders")
spark_sql("win_sessions", "SELECT user_id, CAST(count(*) AS BIGINT) AS sessions FROM (SELECT user_id, ts, lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS before FROM events) WHERE before IS NULL OR ts > before + INTERVAL 6 HOUR GROUP BY user_id")

# order, sets -------------------------------------------------------------------------------------
spark_sql("sort_global", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC NULLS LAST, o_orderkey")
spark_sql("topk_global", "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
spark_sql("topk_group", f"SELECT o_custkey, o_orderkey FROM (SELECT o_custkey, o_orderkey, row_number() OVER ({_ORDERS}) AS r FROM orders) WHERE r <= 3")
spark_sql("limit_offset", "SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 10 OFFSET 25")
_Y = "SELECT l_partkey FROM lineitem WHERE year(l_shipdate) = {}"
for _name, _word in (("union_all", "UNION ALL"), ("union", "UNION"), ("intersect", "INTERSECT"), ("intersect_all", "INTERSECT ALL"), ("except", "EXCEPT"), ("except_all", "EXCEPT ALL")):
    spark_sql(f"set_{_name}", f"{_Y.format(1995)} {_word} {_Y.format(1996)}")
spark_sql("set_distinct", "SELECT DISTINCT l_partkey, l_suppkey FROM lineitem")

# strings, dates, numbers -------------------------------------------------------------------------
spark_sql("str_basic", "SELECT p_partkey, upper(p_name) AS up, length(p_name) AS n, substring(p_name, 2, 5) AS mid, concat(p_brand, '/', p_type) AS both, replace(p_type, ' ', '_') AS snake, lpad(CAST(p_size AS STRING), 4, '0') AS padded FROM part", "SELECT p_partkey, upper(p_name) AS up, length(p_name)::INT AS n, substring(p_name, 2, 5) AS mid, concat(p_brand, '/', p_type) AS both, replace(p_type, ' ', '_') AS snake, lpad(CAST(p_size AS VARCHAR), 4, '0') AS padded FROM part")
spark_sql("str_regex", "SELECT p_partkey, regexp_extract(p_brand, '([0-9]+)', 1) AS digits, regexp_replace(p_name, '[aeiou]+', '*') AS bare FROM part", "SELECT p_partkey, regexp_extract(p_brand, '([0-9]+)', 1) AS digits, regexp_replace(p_name, '[aeiou]+', '*', 'g') AS bare FROM part")
spark_sql("str_split_explode", "SELECT word, count(*) AS n FROM (SELECT explode(split(p_name, ' ')) AS word FROM part) GROUP BY 1", "SELECT word, count(*) AS n FROM (SELECT unnest(string_split(p_name, ' ')) AS word FROM part) GROUP BY 1")
spark_sql("str_hash_md5", "SELECT p_partkey, md5(p_name) AS digest FROM part")
spark_sql("str_levenshtein", "SELECT a.n_name AS x, b.n_name AS y, CAST(levenshtein(a.n_name, b.n_name) AS BIGINT) AS d FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey")
spark_sql("date_parts", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, dayofmonth(o_orderdate) AS d, quarter(o_orderdate) AS q FROM orders", "SELECT o_orderkey, year(o_orderdate)::INT AS y, month(o_orderdate)::INT AS m, dayofmonth(o_orderdate)::INT AS d, quarter(o_orderdate)::INT AS q FROM orders")
spark_sql("date_arith", "SELECT o_orderkey, CAST(datediff(o_orderdate, TIMESTAMP '1992-01-01') AS BIGINT) AS days, add_months(CAST(o_orderdate AS DATE), 2) AS later FROM orders", "SELECT o_orderkey, date_diff('day', TIMESTAMP '1992-01-01', o_orderdate) AS days, (CAST(o_orderdate AS DATE) + INTERVAL 2 MONTH)::DATE AS later FROM orders")
spark_sql("date_bucket", "SELECT date_trunc('hour', ts) AS hour, count(*) AS n FROM events GROUP BY 1")
spark_sql("math_basic", "SELECT p_partkey, floor(p_retailprice) AS f, ceil(p_retailprice) AS c, round(sqrt(p_size), 6) AS root, round(ln(p_size), 6) AS log, greatest(p_size, 25) AS g, abs(p_size - 25) AS a FROM part", "SELECT p_partkey, floor(p_retailprice)::BIGINT AS f, ceil(p_retailprice)::BIGINT AS c, round(sqrt(p_size), 6) AS root, round(ln(p_size), 6) AS log, greatest(p_size, 25) AS g, abs(p_size - 25) AS a FROM part")
spark_sql("math_bit", "SELECT p_partkey, p_partkey & 12 AS both, p_partkey | 3 AS either, shiftleft(p_partkey, 3) AS up FROM part", "SELECT p_partkey, p_partkey & 12 AS both, p_partkey | 3 AS either, p_partkey << 3 AS up FROM part")
spark_sql("math_mod", "SELECT pmod(p_partkey * 48271 + 7, 97) AS slot, count(*) AS n FROM part GROUP BY 1", "SELECT (p_partkey * 48271 + 7) % 97 AS slot, count(*) AS n FROM part GROUP BY 1")


# arrays, maps, json ------------------------------------------------------------------------------
_PARTS = "WITH a AS (SELECT l_orderkey, list_sort(list_distinct(list(l_partkey))) AS p FROM lineitem GROUP BY 1)"


def _part_lists(spark, sf):
    return load(spark, sf, "lineitem").groupBy("l_orderkey").agg(F.array_sort(F.collect_set("l_partkey")).alias("p"))


@op("arr_setops", f"{_PARTS}, b AS (SELECT x.l_orderkey, x.p, y.p AS q FROM a x JOIN a y ON y.l_orderkey = x.l_orderkey + 1) SELECT l_orderkey, len(list_intersect(p, q)) AS both, len(list_distinct(list_concat(p, q))) AS either, len(list_filter(p, lambda v: NOT list_contains(q, v))) AS rest FROM b")
def arr_setops(spark, sf):
    a = _part_lists(spark, sf)
    b = a.select((F.col("l_orderkey") - 1).alias("l_orderkey"), F.col("p").alias("q"))
    out = a.join(b, "l_orderkey")
    return out.select("l_orderkey", *[F.size(f("p", "q")).cast("long").alias(n) for f, n in ((F.array_intersect, "both"), (F.array_union, "either"), (F.array_except, "rest"))])


@op("arr_lambda", f"{_PARTS} SELECT l_orderkey, list_sum(list_transform(p, lambda v: v * 2))::BIGINT AS twice, len(list_filter(p, lambda v: v % 2 = 0)) AS even FROM a")
def arr_lambda(spark, sf):
    twice = F.aggregate(F.transform("p", lambda v: v * 2), F.lit(0).cast("long"), lambda a, v: a + v)
    return _part_lists(spark, sf).select("l_orderkey", twice.alias("twice"), F.size(F.filter("p", lambda v: v % 2 == 0)).cast("long").alias("even"))


@op("arr_explode", f"{_PARTS} SELECT l_orderkey, unnest(p) AS part, unnest(range(len(p))) AS pos FROM a")
def arr_explode(spark, sf):
    return _part_lists(spark, sf).select("l_orderkey", F.posexplode("p").alias("pos", "part")).select("l_orderkey", "part", F.col("pos").cast("long").alias("pos"))


@op("arr_sort_slice", f"{_PARTS} SELECT l_orderkey, p[1] AS least, p[-1] AS most, array_to_string(list_slice(p, 1, 2), ',') AS two FROM a")
def arr_sort_slice(spark, sf):
    return _part_lists(spark, sf).select("l_orderkey", F.array_min("p").alias("least"), F.array_max("p").alias("most"), F.array_join(F.transform(F.slice("p", 1, 2), lambda v: v.cast("string")), ",").alias("two"))


@op("map_hist", "SELECT user_id, string_agg(event_type || '=' || n::VARCHAR, ',' ORDER BY event_type) AS hist FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY 1, 2) GROUP BY 1")
def map_hist(spark, sf):
    counts = load(spark, sf, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    maps = counts.groupBy("user_id").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("event_type", "n")))).alias("m"))
    return maps.select("user_id", F.array_join(F.transform(F.map_keys("m"), lambda k: F.concat(k, F.lit("="), F.element_at("m", k).cast("string"))), ",").alias("hist"))


@op("json_extract", "SELECT event_id, (props::JSON ->> '$.k')::BIGINT AS k FROM events")
def json_extract(spark, sf):
    return load(spark, sf, "events").select("event_id", F.from_json("props", "k bigint")["k"].alias("k"))


@op("json_path", "SELECT event_id, props::JSON ->> '$.k' AS k FROM events")
def json_path(spark, sf):
    return load(spark, sf, "events").select("event_id", F.get_json_object("props", "$.k").alias("k"))


@op("vec_dot", "SELECT a.vec_id, round(list_sum(list_transform(range(1, 65), lambda i: a.embedding[i]::DOUBLE * b.embedding[i]::DOUBLE)), 6) AS d FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")
def vec_dot(spark, sf):
    v = load(spark, sf, "embeddings").select("vec_id", "embedding")
    return v.toDF("vec_id", "x").join(v.select((F.col("vec_id") - 1).alias("vec_id"), F.col("embedding").alias("y")), "vec_id").select("vec_id", F.round(dot("x", "y"), 6).alias("d"))


#: Each supplier stands below the one with half its key; those without such a one are roots.
_HALVES = "WITH RECURSIVE r(n, root, level) AS (SELECT s_suppkey, s_suppkey, 0 FROM supplier c WHERE s_suppkey = 0 OR NOT EXISTS (SELECT 1 FROM supplier p WHERE p.s_suppkey = c.s_suppkey {div} 2) UNION ALL SELECT s_suppkey, root, level + 1 FROM r JOIN supplier ON s_suppkey {div} 2 = n WHERE s_suppkey <> 0) SELECT n, root, level FROM r"
spark_sql("rec_hierarchy", _HALVES.format(div="div"), _HALVES.format(div="//"))


# functions and grouped maps ----------------------------------------------------------------------
_SHARED = f"WITH {_CO_USER}, s AS (SELECT src AS id, dst AS nbr FROM e UNION ALL SELECT dst, src FROM e) SELECT e.src, e.dst, (SELECT count(*) FROM s a JOIN s b ON a.nbr = b.nbr WHERE a.id = e.src AND b.id = e.dst) AS shared FROM e"


def shared_udf(kind: str, lists: Lists):
    """The size of the intersection of two vertices' stored lists as a Python function of rows, of pandas series, or of Arrow arrays."""
    if kind == "scalar":
        return F.udf(lambda u, v: lists.shared(u, v), T.LongType())
    if kind == "pandas":
        @F.pandas_udf("long")
        def pandas_kind(u: pd.Series, v: pd.Series) -> pd.Series:
            return pd.Series([lists.shared(x, y) for x, y in zip(u, v, strict=True)])

        return pandas_kind

    @F.arrow_udf("long")
    def arrow_kind(u: pa.Array, v: pa.Array) -> pa.Array:
        return pa.array([lists.shared(x, y) for x, y in zip(u.to_pylist(), v.to_pylist(), strict=True)], pa.int64())

    return arrow_kind


def _shared(spark, sf, kind):
    """Edges move by themselves; the lists of their ends stay in the shared folder."""
    edges = written(co_user(spark, sf), "co_user")
    lists = mapped(adjacency(PropertyGraph(edges)))
    return edges.sortWithinPartitions("src").select("src", "dst", shared_udf(kind, lists)("src", "dst").alias("shared"))


for _kind in ("scalar", "pandas", "arrow"):
    op(f"udf_{_kind}", _SHARED)(lambda spark, sf, kind=_kind: _shared(spark, sf, kind))


@op("udaf_grouped", "SELECT l_suppkey, max(l_quantity) AS best FROM lineitem GROUP BY 1")
def udaf_grouped(spark, sf):
    @F.pandas_udf("double")
    def best(x: pd.Series) -> float:
        return float(x.max())

    return load(spark, sf, "lineitem").groupBy("l_suppkey").agg(best("l_quantity").alias("best"))


_TRI = f"WITH {_CO_USER} SELECT a.src AS root, count(*) AS triangles FROM e a JOIN e b ON a.dst = b.src JOIN e c ON c.src = a.src AND c.dst = b.dst GROUP BY 1"


@op("udtf_mine", _TRI)
def udtf_mine(spark, sf):
    """``mine_triangles(TABLE(pieces) PARTITION BY root)``: a table function over each root's edges, which looks the lists up."""
    edges = written(co_user(spark, sf), "co_user")
    lists = mapped(forward_adjacency(PropertyGraph(edges)))

    @F.udtf(returnType="root: bigint, triangles: bigint")
    class Mine:
        def __init__(self):
            self.root, self.n = None, 0

        def eval(self, row):
            self.root = row["root"]
            self.n += lists.shared(row["root"], row["id"])

        def terminate(self):
            if self.n:
                yield self.root, self.n

    spark.udtf.register("mine_triangles", Mine)
    edges.select(F.col("src").alias("root"), F.col("dst").alias("id")).createOrReplaceTempView("pieces")
    return spark.sql("SELECT * FROM mine_triangles(TABLE(pieces) PARTITION BY root)")


_SPAN = "SELECT user_id, count(*) AS n, max(value) - min(value) AS span FROM events GROUP BY 1"


@op("gm_pandas", _SPAN)
def gm_pandas(spark, sf):
    def span(pdf: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"user_id": [pdf.user_id.iloc[0]], "n": [len(pdf)], "span": [pdf.value.max() - pdf.value.min()]})

    return load(spark, sf, "events").select("user_id", "value").groupBy("user_id").applyInPandas(span, "user_id long, n long, span double")


@op("gm_arrow", _SPAN)
def gm_arrow(spark, sf):
    def span(t: pa.Table) -> pa.Table:
        ends = pc.min_max(t["value"]).as_py()
        return pa.table({"user_id": t["user_id"][:1], "n": pa.array([t.num_rows]), "span": pa.array([ends["max"] - ends["min"]])})

    return load(spark, sf, "events").select("user_id", "value").groupBy("user_id").applyInArrow(span, "user_id long, n long, span double")


@op("gm_cogroup", "SELECT coalesce(c.k, o.k) AS nation, coalesce(c.n, 0) AS customers, coalesce(o.n, 0) AS suppliers FROM (SELECT c_nationkey AS k, count(*) AS n FROM customer GROUP BY 1) c FULL JOIN (SELECT s_nationkey AS k, count(*) AS n FROM supplier GROUP BY 1) o ON c.k = o.k")
def gm_cogroup(spark, sf):
    def both(c: pa.Table, s: pa.Table) -> pa.Table:
        k = (c["k"] if c.num_rows else s["k"])[:1]
        return pa.table({"nation": k.cast(pa.int32()), "customers": pa.array([c.num_rows]), "suppliers": pa.array([s.num_rows])})

    c = load(spark, sf, "customer").select(F.col("c_nationkey").alias("k"))
    s = load(spark, sf, "supplier").select(F.col("s_nationkey").alias("k"))
    return c.groupBy("k").cogroup(s.groupBy("k")).applyInArrow(both, "nation int, customers long, suppliers long")


@op("map_arrow", "SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, l_quantity * 2 AS twice FROM lineitem")
def map_arrow(spark, sf):
    def twice(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([*b.columns[:4], pc.multiply(b.column(4), 2.0)], names=[*b.schema.names[:4], "twice"])

    rows = load(spark, sf, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity")
    return rows.mapInArrow(twice, "l_orderkey long, l_linenumber int, l_partkey long, l_suppkey long, twice double")


# sampling ----------------------------------------------------------------------------------------
@op("sample_rows")
def sample_rows(spark, sf):
    return load(spark, sf, "orders").sample(fraction=0.1, seed=7).select("o_orderkey")


@op("sample_by")
def sample_by(spark, sf):
    return load(spark, sf, "orders").sampleBy("o_orderpriority", {"1-URGENT": 0.5}, seed=7).select("o_orderkey", "o_orderpriority")


@op("sample_hash", "SELECT o_orderkey FROM orders WHERE substr(md5(o_orderkey::VARCHAR), 1, 1) = '0'")
def sample_hash(spark, sf):
    """A sixteenth by hash: the same rows on every run and machine."""
    return load(spark, sf, "orders").where(F.substring(F.md5(F.col("o_orderkey").cast("string").cast("binary")), 1, 1) == "0").select("o_orderkey")
