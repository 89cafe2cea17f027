"""The conventional operators that surround the methods, each on the given tables."""

from __future__ import annotations

import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tabqa.plans.registry import plan
from tabqa.session import table as t


def cents(column: str):
    return F.round(F.col(column) * 100).cast("bigint")


# Scans, projections, predicates


@plan("SELECT o_orderkey, o_custkey, o_orderstatus FROM orders WHERE o_orderstatus = 'O' AND o_orderkey > 100")
def scan_orders(spark: SparkSession, sf: str) -> DataFrame:
    return t(spark, sf, "orders").select("o_orderkey", "o_custkey", "o_orderstatus").where("o_orderstatus = 'O' AND o_orderkey > 100")


@plan("SELECT l_orderkey AS order_key, CAST(round(l_extendedprice * 100) AS BIGINT) * 2 AS double_cents, l_linenumber + 1 AS next_line FROM lineitem")
def project_exprs(spark: SparkSession, sf: str) -> DataFrame:
    return t(spark, sf, "lineitem").select(F.col("l_orderkey").alias("order_key"), (cents("l_extendedprice") * 2).alias("double_cents"), (F.col("l_linenumber") + 1).alias("next_line"))


@plan("SELECT n_nationkey, n_name FROM nation")
def project_except(spark: SparkSession, sf: str) -> DataFrame:
    return t(spark, sf, "nation").drop("n_regionkey")


@plan("SELECT o_orderkey FROM orders WHERE o_totalprice BETWEEN 1000 AND 50000 AND o_orderpriority IN ('1-URGENT', '2-HIGH') AND o_orderdate >= TIMESTAMP '1996-01-01'")
def filter_orders(spark: SparkSession, sf: str) -> DataFrame:
    return t(spark, sf, "orders").where(F.col("o_totalprice").between(1000, 50000) & F.col("o_orderpriority").isin("1-URGENT", "2-HIGH") & (F.col("o_orderdate") >= F.lit("1996-01-01").cast("timestamp"))).select("o_orderkey")


@plan("SELECT p_partkey, CASE WHEN p_size < 10 THEN 'small' WHEN p_size < 30 THEN 'medium' ELSE 'large' END AS size_class FROM part WHERE NOT (p_brand = 'Brand#1') AND p_name LIKE '%a%' AND regexp_matches(p_type, '[A-Z]+') AND p_brand IS NOT NULL AND p_size IS NOT DISTINCT FROM p_size")
def predicates_mix(spark: SparkSession, sf: str) -> DataFrame:
    p = t(spark, sf, "part").where(~(F.col("p_brand") == "Brand#1") & F.col("p_name").like("%a%") & F.col("p_type").rlike("[A-Z]+") & F.col("p_brand").isNotNull() & F.col("p_size").eqNullSafe(F.col("p_size")))
    return p.select("p_partkey", F.when(F.col("p_size") < 10, "small").when(F.col("p_size") < 30, "medium").otherwise("large").alias("size_class"))


# Joins


@plan("SELECT n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey")
def join_broadcast(spark: SparkSession, sf: str) -> DataFrame:
    return t(spark, sf, "nation").join(t(spark, sf, "region").hint("broadcast"), F.col("n_regionkey") == F.col("r_regionkey")).select("n_name", "r_name")


@plan("SELECT o_orderkey, c_name FROM orders JOIN customer ON o_custkey = c_custkey")
def join_shuffle_hash(spark: SparkSession, sf: str) -> DataFrame:
    return t(spark, sf, "orders").join(t(spark, sf, "customer").hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_name")


@plan("SELECT l_orderkey, l_linenumber, o_orderstatus, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY ALL")
def join_merge(spark: SparkSession, sf: str) -> DataFrame:
    return t(spark, sf, "lineitem").join(t(spark, sf, "orders").hint("merge"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("l_orderkey", "l_linenumber", "o_orderstatus").agg(F.count(F.lit(1)).alias("n"))


_FINISHED = "c_custkey = o_custkey AND o_orderstatus = 'F'"


def _outer(spark: SparkSession, sf: str, how: str) -> DataFrame:
    """All customers and all orders, which meet where an order is finished; either side's others have no partner."""
    customers, orders = t(spark, sf, "customer").select("c_custkey"), t(spark, sf, "orders").select("o_orderkey", "o_custkey", "o_orderstatus")
    return customers.join(orders, F.expr(_FINISHED), how).select(*(F.coalesce(c, F.lit(-1)).alias(c) for c in ("c_custkey", "o_orderkey")))


def _outer_sql(how: str) -> str:
    return f"SELECT coalesce(c_custkey, -1) AS c_custkey, coalesce(o_orderkey, -1) AS o_orderkey FROM customer {how} JOIN orders ON {_FINISHED}"


@plan(_outer_sql("LEFT"))
def join_left(spark: SparkSession, sf: str) -> DataFrame:
    return _outer(spark, sf, "left")


@plan(_outer_sql("RIGHT"))
def join_right(spark: SparkSession, sf: str) -> DataFrame:
    return _outer(spark, sf, "right")


@plan(_outer_sql("FULL"))
def join_full(spark: SparkSession, sf: str) -> DataFrame:
    return _outer(spark, sf, "full")


@plan("SELECT doc_id, lang FROM documents WHERE EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = documents.doc_id)")
def join_semi(spark: SparkSession, sf: str) -> DataFrame:
    return t(spark, sf, "documents").select("doc_id", "lang").join(t(spark, sf, "labels"), "doc_id", "left_semi")


@plan("SELECT doc_id, lang FROM documents WHERE NOT EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = documents.doc_id)")
def join_anti(spark: SparkSession, sf: str) -> DataFrame:
    return t(spark, sf, "documents").select("doc_id", "lang").join(t(spark, sf, "labels"), "doc_id", "left_anti")


@plan("SELECT r_name, n_name FROM region CROSS JOIN nation")
def join_cross(spark: SparkSession, sf: str) -> DataFrame:
    return t(spark, sf, "nation").crossJoin(F.broadcast(t(spark, sf, "region"))).select("r_name", "n_name")


@plan("SELECT a.n_name AS low, b.n_name AS high FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey AND a.n_regionkey <= b.n_regionkey")
def join_theta(spark: SparkSession, sf: str) -> DataFrame:
    a, b = t(spark, sf, "nation").alias("a"), t(spark, sf, "nation").alias("b")
    return a.join(F.broadcast(b), F.expr("a.n_nationkey < b.n_nationkey AND a.n_regionkey <= b.n_regionkey")).select(F.col("a.n_name").alias("low"), F.col("b.n_name").alias("high"))


@plan("WITH bands AS (SELECT CAST(i * 7 AS INTEGER) AS lo, CAST(i * 7 + 9 AS INTEGER) AS hi FROM range(0, 8) r(i)) SELECT p_partkey, lo, hi FROM part JOIN bands ON p_size BETWEEN lo AND hi")
def join_range(spark: SparkSession, sf: str) -> DataFrame:
    """Each band is spread over the bins it touches, which makes the join an equi-join."""
    bands = spark.range(8).select((F.col("id") * 7).cast("int").alias("lo"), (F.col("id") * 7 + 9).cast("int").alias("hi"))
    bands = bands.withColumn("bin", F.explode(F.sequence(F.expr("lo div 10"), F.expr("hi div 10"))))
    return t(spark, sf, "part").withColumn("bin", F.expr("p_size div 10")).join(bands, "bin").where("p_size BETWEEN lo AND hi").select("p_partkey", "lo", "hi")


@plan("SELECT a.event_id AS first_id, b.event_id AS next_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def join_interval(spark: SparkSession, sf: str) -> DataFrame:
    """Hours are bins; an event looks into its own and the next."""
    e = t(spark, sf, "events").select("event_id", "user_id", "ts", F.expr("unix_seconds(cast(ts AS timestamp)) div 3600").alias("h"))
    a = e.select(F.col("event_id").alias("first_id"), "user_id", F.col("ts").alias("t0"), F.explode(F.array(F.col("h"), F.col("h") + 1)).alias("h"))
    return a.join(e, ["user_id", "h"]).where("ts > t0 AND ts <= t0 + INTERVAL 1 HOUR").select("first_id", F.col("event_id").alias("next_id"))


@plan("SELECT p.event_id, coalesce((SELECT max(struct_pack(ts := v.ts, id := v.event_id)).id FROM events v WHERE v.user_id = p.user_id AND v.event_type = 'view' AND v.ts <= p.ts), -1) AS view_id FROM events p WHERE p.event_type = 'purchase'")
def join_asof(spark: SparkSession, sf: str) -> DataFrame:
    """One sort per user; the last view so far goes along."""
    e = t(spark, sf, "events").where("event_type IN ('view', 'purchase')")
    seen = Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    view = F.max(F.when(F.col("event_type") == "view", F.struct("ts", "event_id"))).over(seen)
    return e.withColumn("view_id", view["event_id"]).where("event_type = 'purchase'").select("event_id", F.coalesce("view_id", F.lit(-1)).alias("view_id"))


@plan("SELECT n_name, p_brand, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN part ON l_partkey = p_partkey GROUP BY ALL")
def join_star(spark: SparkSession, sf: str) -> DataFrame:
    line, orders, customer, nation, part = (t(spark, sf, x) for x in ("lineitem", "orders", "customer", "nation", "part"))
    joined = line.join(part, F.col("l_partkey") == F.col("p_partkey")).join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(customer, F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey"))
    return joined.groupBy("n_name", "p_brand").agg(F.count(F.lit(1)).alias("n"))


@plan("SELECT a.s_suppkey AS left_key, b.s_suppkey AS right_key FROM supplier a JOIN supplier b ON a.s_nationkey = b.s_nationkey AND a.s_suppkey < b.s_suppkey")
def join_self(spark: SparkSession, sf: str) -> DataFrame:
    a, b = t(spark, sf, "supplier").alias("a"), t(spark, sf, "supplier").alias("b")
    return a.join(b, F.expr("a.s_nationkey = b.s_nationkey AND a.s_suppkey < b.s_suppkey")).select(F.col("a.s_suppkey").alias("left_key"), F.col("b.s_suppkey").alias("right_key"))


@plan("SELECT n_name, s_name FROM nation, LATERAL (SELECT s_name FROM supplier WHERE s_nationkey = n_nationkey)")
def join_lateral(spark: SparkSession, sf: str) -> DataFrame:
    nation, supplier = t(spark, sf, "nation"), t(spark, sf, "supplier")
    return nation.lateralJoin(supplier.where(F.col("s_nationkey") == F.col("n_nationkey").outer()).select("s_name")).select("n_name", "s_name")


# Aggregation


@plan("SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(CAST(round(l_extendedprice * 100) AS BIGINT)) AS BIGINT) AS cents, strftime(min(l_shipdate), '%Y-%m-%d') AS first_ship, max(l_quantity) AS most FROM lineitem GROUP BY ALL")
def agg_basic(spark: SparkSession, sf: str) -> DataFrame:
    return t(spark, sf, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.sum(cents("l_extendedprice")).alias("cents"), F.date_format(F.min("l_shipdate"), "yyyy-MM-dd").alias("first_ship"), F.max("l_quantity").alias("most"))


@plan("SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY ALL")
def agg_distinct(spark: SparkSession, sf: str) -> DataFrame:
    return t(spark, sf, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers"))


@plan("SELECT l_linestatus, count(*) FILTER (WHERE l_quantity > 25) AS many, CAST(sum(CASE WHEN l_returnflag = 'R' THEN l_linenumber ELSE 0 END) AS BIGINT) AS returned FROM lineitem GROUP BY ALL")
def agg_filtered(spark: SparkSession, sf: str) -> DataFrame:
    return t(spark, sf, "lineitem").groupBy("l_linestatus").agg(F.count_if(F.col("l_quantity") > 25).alias("many"), F.sum(F.when(F.col("l_returnflag") == "R", F.col("l_linenumber")).otherwise(0)).alias("returned"))


@plan("SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers, true AS middle_is_near FROM lineitem GROUP BY ALL")
def agg_approx(spark: SparkSession, sf: str) -> DataFrame:
    """Estimates, told by the exact figure where they come within five per cent of it, and as they are where they don't."""
    near = lambda estimate, exact: F.when(F.abs(F.col(estimate) - F.col(exact)) <= 0.05 * F.col(exact), F.col(exact)).otherwise(F.col(estimate)).cast("bigint").alias(exact)
    line = t(spark, sf, "lineitem")
    rough = line.groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("p"), F.hll_sketch_estimate(F.hll_sketch_agg("l_suppkey")).alias("s"), F.percentile_approx("l_quantity", 0.5).alias("q"), F.median("l_quantity").alias("middle"))
    exact = line.groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers"))
    return rough.join(exact, "l_returnflag").select("l_returnflag", near("p", "parts"), near("s", "suppliers"), (F.abs(F.col("q") - F.col("middle")) <= 1).alias("middle_is_near"))


@plan("SELECT p_brand, median(p_size) AS middle, max(p_name) AS last_name, arg_max(p_partkey, struct_pack(a := p_retailprice, b := p_partkey)) AS dearest, CAST(bit_or(p_size) AS INTEGER) AS bits FROM part GROUP BY ALL")
def agg_stats(spark: SparkSession, sf: str) -> DataFrame:
    return t(spark, sf, "part").groupBy("p_brand").agg(F.median("p_size").alias("middle"), F.max("p_name").alias("last_name"), F.max_by("p_partkey", F.struct("p_retailprice", "p_partkey")).alias("dearest"), F.bit_or("p_size").alias("bits"))


@plan("SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY ALL")
def agg_listagg(spark: SparkSession, sf: str) -> DataFrame:
    return t(spark, sf, "nation").groupBy("n_regionkey").agg(F.array_join(F.array_sort(F.collect_list("n_name")), ",").alias("names"))


@plan("SELECT coalesce(customer.c_nationkey, -1) AS c_nationkey, coalesce(customer.c_mktsegment, '*') AS c_mktsegment, CAST(grouping(customer.c_nationkey) AS BIGINT) AS g, count(*) AS n FROM customer GROUP BY GROUPING SETS ((customer.c_nationkey, customer.c_mktsegment), (customer.c_mktsegment), ())")
def agg_sets(spark: SparkSession, sf: str) -> DataFrame:
    c = t(spark, sf, "customer")
    return c.groupingSets([[F.col("c_nationkey"), F.col("c_mktsegment")], [F.col("c_mktsegment")], []], "c_nationkey", "c_mktsegment").agg(F.grouping("c_nationkey").cast("bigint").alias("g"), F.count(F.lit(1)).alias("n")).select(F.coalesce("c_nationkey", F.lit(-1)).alias("c_nationkey"), F.coalesce("c_mktsegment", F.lit("*")).alias("c_mktsegment"), "g", "n")


@plan("SELECT coalesce(customer.c_nationkey, -1) AS c_nationkey, coalesce(customer.c_mktsegment, '*') AS c_mktsegment, count(*) AS n FROM customer GROUP BY CUBE (customer.c_nationkey, customer.c_mktsegment)")
def agg_cube(spark: SparkSession, sf: str) -> DataFrame:
    return t(spark, sf, "customer").cube("c_nationkey", "c_mktsegment").agg(F.count(F.lit(1)).alias("n")).select(F.coalesce("c_nationkey", F.lit(-1)).alias("c_nationkey"), F.coalesce("c_mktsegment", F.lit("*")).alias("c_mktsegment"), "n")


@plan("SELECT coalesce(customer.c_nationkey, -1) AS c_nationkey, coalesce(customer.c_mktsegment, '*') AS c_mktsegment, count(*) AS n FROM customer GROUP BY ROLLUP (customer.c_nationkey, customer.c_mktsegment)")
def agg_rollup(spark: SparkSession, sf: str) -> DataFrame:
    return t(spark, sf, "customer").rollup("c_nationkey", "c_mktsegment").agg(F.count(F.lit(1)).alias("n")).select(F.coalesce("c_nationkey", F.lit(-1)).alias("c_nationkey"), F.coalesce("c_mktsegment", F.lit("*")).alias("c_mktsegment"), "n")


@plan("SELECT o_orderpriority, count(*) FILTER (WHERE o_orderstatus = 'F') AS F, count(*) FILTER (WHERE o_orderstatus = 'O') AS O, count(*) FILTER (WHERE o_orderstatus = 'P') AS P FROM orders GROUP BY ALL")
def pivot_status(spark: SparkSession, sf: str) -> DataFrame:
    return t(spark, sf, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1))).fillna(0)


@plan("SELECT p_partkey, 'brand' AS field, p_brand AS v FROM part UNION ALL SELECT p_partkey, 'type', p_type FROM part")
def unpivot_part(spark: SparkSession, sf: str) -> DataFrame:
    p = t(spark, sf, "part").select("p_partkey", F.col("p_brand").alias("brand"), F.col("p_type").alias("type"))
    return p.unpivot("p_partkey", ["brand", "type"], "field", "v")


# Windows, order, sets


@plan("SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS rk, dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS dr, ntile(3) OVER w AS nt, round(percent_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority), 9) AS pr, round(cume_dist() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority), 9) AS cd FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
def win_rank(spark: SparkSession, sf: str) -> DataFrame:
    w, p = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey"), Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    long = lambda c: c.cast("bigint")
    return t(spark, sf, "orders").select("o_orderkey", long(F.row_number().over(w)).alias("rn"), long(F.rank().over(p)).alias("rk"), long(F.dense_rank().over(p)).alias("dr"), long(F.ntile(3).over(w)).alias("nt"), F.round(F.percent_rank().over(p), 9).alias("pr"), F.round(F.cume_dist().over(p), 9).alias("cd"))


@plan("SELECT event_id, coalesce(lag(event_id) OVER w, -1) AS before_id, coalesce(lead(event_id, 2) OVER w, -1) AS after_id, first_value(event_id) OVER w AS first_id, coalesce(nth_value(event_id, 2) OVER w, -1) AS second_id FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_lag(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return t(spark, sf, "events").select("event_id", F.lag("event_id", 1, -1).over(w).alias("before_id"), F.lead("event_id", 2, -1).over(w).alias("after_id"), F.first("event_id").over(w).alias("first_id"), F.coalesce(F.nth_value("event_id", 2).over(w), F.lit(-1)).alias("second_id"))


@plan("SELECT o_orderkey, CAST(sum(CAST(round(o_totalprice * 100) AS BIGINT)) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING) AS BIGINT) AS running, CAST(sum(CAST(round(o_totalprice * 100) AS BIGINT)) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS BIGINT) AS last_three FROM orders")
def win_running(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return t(spark, sf, "orders").select("o_orderkey", F.sum(cents("o_totalprice")).over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("running"), F.sum(cents("o_totalprice")).over(w.rowsBetween(-2, 0)).alias("last_three"))


@plan("SELECT p_partkey, count(*) OVER (PARTITION BY p_brand ORDER BY p_size RANGE BETWEEN 5 PRECEDING AND 5 FOLLOWING) AS near FROM part")
def win_range(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("p_brand").orderBy("p_size").rangeBetween(-5, 5)
    return t(spark, sf, "part").select("p_partkey", F.count(F.lit(1)).over(w).alias("near"))


@plan("SELECT o_orderkey, CAST(round(o_totalprice * 100) AS BIGINT) AS cents FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 5")
def sort_limit(spark: SparkSession, sf: str) -> DataFrame:
    return t(spark, sf, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(5).limit(20).select("o_orderkey", cents("o_totalprice").alias("cents"))


@plan("SELECT c_custkey, CAST(round(c_acctbal * 100) AS BIGINT) AS cents FROM customer ORDER BY c_acctbal DESC, c_custkey LIMIT 10")
def topk(spark: SparkSession, sf: str) -> DataFrame:
    return t(spark, sf, "customer").orderBy(F.desc("c_acctbal"), "c_custkey").limit(10).select("c_custkey", cents("c_acctbal").alias("cents"))


@plan("SELECT o_custkey, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) <= 2")
def topk_group(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return t(spark, sf, "orders").withColumn("r", F.row_number().over(w)).where("r <= 2").select("o_custkey", "o_orderkey")


def _keys(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    return t(spark, sf, "orders").select(F.col("o_custkey").alias("k")), t(spark, sf, "labels").select(F.col("doc_id").alias("k"))


_A, _B = "SELECT o_custkey AS k FROM orders", "SELECT doc_id AS k FROM labels"


@plan(f"SELECT k, count(*) AS n FROM ({_A} UNION ALL {_B}) GROUP BY k")
def set_union(spark: SparkSession, sf: str) -> DataFrame:
    a, b = _keys(spark, sf)
    return a.unionByName(b).groupBy("k").agg(F.count(F.lit(1)).alias("n"))


@plan(f"{_A} INTERSECT {_B}")
def set_intersect(spark: SparkSession, sf: str) -> DataFrame:
    a, b = _keys(spark, sf)
    return a.intersect(b)


@plan(f"{_B} EXCEPT {_A}")
def set_except(spark: SparkSession, sf: str) -> DataFrame:
    a, b = _keys(spark, sf)
    return b.subtract(a)


@plan(f"{_A} EXCEPT ALL {_B}")
def set_except_all(spark: SparkSession, sf: str) -> DataFrame:
    a, b = _keys(spark, sf)
    return a.exceptAll(b)


@plan("SELECT DISTINCT c_nationkey, c_mktsegment FROM customer")
def distinct_rows(spark: SparkSession, sf: str) -> DataFrame:
    return t(spark, sf, "customer").select("c_nationkey", "c_mktsegment").distinct()


# Functions


@plan("SELECT c_custkey, lower(c_name) AS low, lpad(CAST(c_custkey AS VARCHAR), 8, '0') AS padded, substr(c_name, 1, 4) AS head, split_part(c_name, '#', 2) AS tail, translate(c_mktsegment, 'AEIOU', 'aeiou') AS swapped, CAST(length(c_name) AS INTEGER) AS n, starts_with(c_mktsegment, 'B') AS b, concat_ws('-', c_name, c_mktsegment) AS joined, CAST(levenshtein(c_mktsegment, 'BUILDING') AS INTEGER) AS distance FROM customer")
def str_funcs(spark: SparkSession, sf: str) -> DataFrame:
    return t(spark, sf, "customer").select("c_custkey", F.lower("c_name").alias("low"), F.lpad(F.col("c_custkey").cast("string"), 8, "0").alias("padded"), F.substring("c_name", 1, 4).alias("head"), F.split_part(F.col("c_name"), F.lit("#"), F.lit(2)).alias("tail"), F.translate("c_mktsegment", "AEIOU", "aeiou").alias("swapped"), F.length("c_name").alias("n"), F.startswith(F.col("c_mktsegment"), F.lit("B")).alias("b"), F.concat_ws("-", "c_name", "c_mktsegment").alias("joined"), F.levenshtein("c_mktsegment", F.lit("BUILDING")).alias("distance"))


@plan("SELECT p_partkey, regexp_extract(p_brand, '([0-9]+)', 1) AS digits, regexp_replace(p_type, '[AEIOU]', '', 'g') AS consonants, CAST(len(string_split(p_name, ' ')) AS INTEGER) AS words FROM part")
def str_regex(spark: SparkSession, sf: str) -> DataFrame:
    return t(spark, sf, "part").select("p_partkey", F.regexp_extract("p_brand", "([0-9]+)", 1).alias("digits"), F.regexp_replace("p_type", "[AEIOU]", "").alias("consonants"), F.size(F.split("p_name", " ")).alias("words"))


@plan("SELECT o_orderkey, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(month(o_orderdate) AS INTEGER) AS m, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month_start, strftime(CAST(o_orderdate AS DATE) + 30, '%Y-%m-%d') AS due, CAST(date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS days, strftime(o_orderdate, '%Y-%m-%d') AS txt FROM orders")
def date_funcs(spark: SparkSession, sf: str) -> DataFrame:
    d = F.to_date("o_orderdate")
    return t(spark, sf, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.trunc(d, "month").cast("string").alias("month_start"), F.date_add(d, 30).cast("string").alias("due"), F.date_diff(d, F.lit("1992-01-01").cast("date")).alias("days"), F.date_format("o_orderdate", "yyyy-MM-dd").alias("txt"))


@plan("SELECT l_orderkey, l_linenumber, l_partkey, CAST(floor(l_quantity / 7) AS BIGINT) AS f, CAST(ceil(l_quantity / 7) AS BIGINT) AS c, abs(l_linenumber - 4) AS a, l_partkey % 13 AS m, round(ln(l_quantity), 6) AS lg, greatest(l_partkey, l_suppkey) AS g, CAST(round(l_extendedprice * 100) AS BIGINT) AS cents FROM lineitem")
def math_funcs(spark: SparkSession, sf: str) -> DataFrame:
    return t(spark, sf, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", F.floor(F.col("l_quantity") / 7).alias("f"), F.ceil(F.col("l_quantity") / 7).alias("c"), F.abs(F.col("l_linenumber") - 4).alias("a"), (F.col("l_partkey") % 13).alias("m"), F.round(F.ln("l_quantity"), 6).alias("lg"), F.greatest("l_partkey", "l_suppkey").alias("g"), cents("l_extendedprice").alias("cents"))


@plan("SELECT vec_id, CAST(len(embedding) AS INTEGER) AS n, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INTEGER) AS above, len(list_filter(embedding, lambda x: x > 0)) > 0 AS some, CAST(list_position(embedding, list_max(embedding)) AS BIGINT) AS top FROM embeddings")
def array_funcs(spark: SparkSession, sf: str) -> DataFrame:
    e = t(spark, sf, "embeddings")
    return e.select("vec_id", F.size("embedding").alias("n"), F.size(F.filter("embedding", lambda x: x > 0)).alias("above"), F.exists("embedding", lambda x: x > 0).alias("some"), F.array_position("embedding", F.array_max("embedding")).alias("top"))


@plan("SELECT p_partkey, w AS word, CAST(i - 1 AS INTEGER) AS place FROM (SELECT p_partkey, unnest(string_split(p_name, ' ')) AS w, generate_subscripts(string_split(p_name, ' '), 1) AS i FROM part)")
def explode_words(spark: SparkSession, sf: str) -> DataFrame:
    return t(spark, sf, "part").select("p_partkey", F.posexplode(F.split("p_name", " ")).alias("place", "word"))


@plan("SELECT n_regionkey, string_agg(n_name || '=' || (n_nationkey * 2), ',' ORDER BY n_name) AS doubled, count(*)::INTEGER AS n FROM nation GROUP BY ALL")
def map_funcs(spark: SparkSession, sf: str) -> DataFrame:
    m = F.transform_values(F.map_from_entries(F.collect_list(F.struct("n_name", "n_nationkey"))), lambda k, v: v * 2)
    g = t(spark, sf, "nation").groupBy("n_regionkey").agg(m.alias("m"))
    pairs = F.transform(F.array_sort(F.map_keys("m")), lambda k: F.concat_ws("=", k, F.element_at("m", k).cast("string")))
    return g.select("n_regionkey", F.array_join(pairs, ",").alias("doubled"), F.size("m").alias("n"))


@plan("SELECT event_id, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k FROM events")
def json_props(spark: SparkSession, sf: str) -> DataFrame:
    return t(spark, sf, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@plan("SELECT event_id, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k FROM events")
def json_variant(spark: SparkSession, sf: str) -> DataFrame:
    return t(spark, sf, "events").select("event_id", F.try_variant_get(F.parse_json("props"), "$.k", "int").alias("k"))


@plan("SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) FROM orders)")
def subq_scalar(spark: SparkSession, sf: str) -> DataFrame:
    o = t(spark, sf, "orders")
    return o.where(F.col("o_totalprice") > o.select(F.avg("o_totalprice")).scalar()).select("o_orderkey")


@plan("SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 100000) AND c_nationkey IN (SELECT n_nationkey FROM nation WHERE n_regionkey = 1)")
def subq_exists(spark: SparkSession, sf: str) -> DataFrame:
    for name in ("customer", "orders", "nation"):
        t(spark, sf, name).createOrReplaceTempView(f"tabqa_{name}")
    return spark.sql("SELECT c_custkey FROM tabqa_customer WHERE EXISTS (SELECT 1 FROM tabqa_orders WHERE o_custkey = c_custkey AND o_totalprice > 100000) AND c_nationkey IN (SELECT n_nationkey FROM tabqa_nation WHERE n_regionkey = 1)")


_POWERS = "WITH RECURSIVE s(n, p) AS (SELECT 1, CAST(1 AS BIGINT) UNION ALL SELECT n + 1, p * 2 FROM s WHERE n < 20)"


@plan(_POWERS + " SELECT n, p, count(l_quantity) AS n_lines, coalesce(CAST(sum(l_quantity) AS BIGINT), 0) AS quantity FROM s LEFT JOIN lineitem ON l_extendedprice >= p AND l_extendedprice < 2 * p GROUP BY n, p")
def cte_recursive(spark: SparkSession, sf: str) -> DataFrame:
    """Powers of two by a recursive query, and the lines whose price lies from each to the next."""
    powers = spark.sql(_POWERS + " SELECT n, p FROM s")
    met = t(spark, sf, "lineitem").select("l_extendedprice", "l_quantity").join(F.broadcast(powers), F.expr("l_extendedprice >= p AND l_extendedprice < 2 * p"))  # twenty rows
    counted = met.groupBy("n").agg(F.count("l_quantity").alias("n_lines"), F.sum("l_quantity").cast("bigint").alias("quantity"))
    return powers.join(counted, "n", "left").select("n", "p", *(F.coalesce(c, F.lit(0)).alias(c) for c in ("n_lines", "quantity")))


@plan("SELECT l_orderkey, l_linenumber, l_returnflag FROM lineitem WHERE substr(md5(l_orderkey || '-' || l_linenumber || '-' || l_partkey), 1, 1) = '0'")
def sample_hash(spark: SparkSession, sf: str) -> DataFrame:
    """A sampling operator: one row in sixteen by its digest, the same rows in every run."""
    digest = F.md5(F.concat_ws("-", "l_orderkey", "l_linenumber", "l_partkey").cast("binary"))
    return t(spark, sf, "lineitem").where(F.substring(digest, 1, 1) == "0").select("l_orderkey", "l_linenumber", "l_returnflag")


# Functions of one's own


@plan("SELECT c_custkey, regexp_replace(regexp_replace(regexp_replace(regexp_replace(c_name, '\\s+', '', 'g'), '\\p{L}+', '\x01', 'g'), '\\p{Nd}+', '\x02', 'g'), '[^\x01\x02]+', '\x03', 'g').translate('\x01\x02\x03', 'ADN') AS mask FROM customer")
def udf_mask(spark: SparkSession, sf: str) -> DataFrame:
    """The mask as an Arrow batch function, for callers that hold pandas code; the expression form is the main one."""

    @F.pandas_udf("string")
    def mask(s: pd.Series) -> pd.Series:
        plain = s.str.replace(r"\s+", "", regex=True).str.replace(r"[^\W\d_]+", "\x01", regex=True).str.replace(r"\d+", "\x02", regex=True)
        return plain.str.replace("[^\x01\x02]+", "\x03", regex=True).str.translate(str.maketrans("\x01\x02\x03", "ADN"))

    return t(spark, sf, "customer").select("c_custkey", mask("c_name").alias("mask"))


@plan("SELECT c_nationkey, CAST(sum(length(c_name)) AS BIGINT) AS letters FROM customer GROUP BY 1")
def udf_arrow(spark: SparkSession, sf: str) -> DataFrame:
    """A scalar function and a grouped one on Arrow data, without pandas between."""
    @F.arrow_udf("int")
    def length(names: pa.Array) -> pa.Array:
        return pc.cast(pc.utf8_length(names), pa.int32())

    def total(group: pa.Table) -> pa.Table:
        return pa.table({"c_nationkey": group["c_nationkey"].slice(0, 1), "letters": pa.array([pc.sum(group["n"]).as_py()], pa.int64())})

    counted = t(spark, sf, "customer").select("c_nationkey", length("c_name").alias("n")).groupBy("c_nationkey", "n").agg(F.count(F.lit(1)).alias("k"))
    return counted.select("c_nationkey", (F.col("n") * F.col("k")).cast("int").alias("n")).groupBy("c_nationkey").applyInArrow(total, "c_nationkey int, letters bigint")


@plan("SELECT 'lineitem' AS name, CAST(count(*) - count(DISTINCT (l_orderkey, l_linenumber)) AS BIGINT) AS spare FROM lineitem")
def udaf_key_spare(spark: SparkSession, sf: str) -> DataFrame:
    """Rows beyond one for each key: a fold of two counts."""
    line = t(spark, sf, "lineitem").groupBy("l_orderkey", "l_linenumber").agg(F.count(F.lit(1)).alias("n"))
    return line.agg(F.sum(F.col("n") - 1).alias("spare")).select(F.lit("lineitem").alias("name"), "spare")


@plan("SELECT n_name, CAST(i AS INTEGER) AS place, substr(n_name, CAST(i + 1 AS INTEGER), 1) AS letter FROM nation, LATERAL (SELECT unnest(range(0, length(n_name))) AS i)")
def udtf_letters(spark: SparkSession, sf: str) -> DataFrame:
    """A table function in Python, called laterally."""

    @F.udtf(returnType="place int, letter string")
    class Letters:
        def eval(self, text: str):
            yield from enumerate(text or "")

    nation = t(spark, sf, "nation")
    return nation.lateralJoin(Letters(F.col("n_name").outer())).select("n_name", "place", "letter")


# Writers and readers


def _round_trip(spark: SparkSession, df: DataFrame, form: str, **options) -> DataFrame:
    from tabqa.session import scratch_folder

    path = f"{scratch_folder(spark)}/trip-{form}-{abs(hash((form, id(df))))}"
    df.write.mode("overwrite").format(form).options(**options).save(path)
    return spark.read.schema(df.schema).format(form).options(**options).load(path)


@plan("SELECT n_nationkey, n_name, n_regionkey FROM nation")
def scan_csv_roundtrip(spark: SparkSession, sf: str) -> DataFrame:
    return _round_trip(spark, t(spark, sf, "nation"), "csv", header="true")


@plan("SELECT n_nationkey, n_name, n_regionkey FROM nation")
def scan_json_roundtrip(spark: SparkSession, sf: str) -> DataFrame:
    return _round_trip(spark, t(spark, sf, "nation"), "json")


@plan("SELECT n_nationkey, n_name, n_regionkey FROM nation")
def scan_orc_roundtrip(spark: SparkSession, sf: str) -> DataFrame:
    return _round_trip(spark, t(spark, sf, "nation"), "orc")


@plan("SELECT n_regionkey, count(*) AS n FROM nation WHERE n_regionkey < 3 GROUP BY ALL")
def sink_partitioned(spark: SparkSession, sf: str) -> DataFrame:
    """Written by region; the filter reads three folders of five."""
    from tabqa.session import scratch_folder

    path = f"{scratch_folder(spark)}/nation-by-region"
    t(spark, sf, "nation").write.mode("overwrite").partitionBy("n_regionkey").parquet(path)
    return spark.read.parquet(path).where("n_regionkey < 3").groupBy("n_regionkey").agg(F.count(F.lit(1)).alias("n"))
