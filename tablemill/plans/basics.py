"""Queries of the relational, string, array, JSON, vector and statistical operators the methods stand on."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from tablemill.functions import det
from tablemill.operators.corpus import strip_html
from tablemill.plans.corpus import STRIP_SQL
from tablemill.plans.registry import query


def r6(c, name):
    return F.round(c, 6).alias(name)


def revenue():
    return F.col("l_extendedprice") * (1 - F.col("l_discount"))


# --- projection and filters ---------------------------------------------------


@query("src_parquet_scan", "SELECT c_custkey, c_name, c_acctbal FROM customer")
def src_parquet_scan(t):
    return t.customer.select("c_custkey", "c_name", "c_acctbal")


@query("proj_line_revenue", "SELECT l_orderkey, l_partkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 6) AS revenue, round(l_extendedprice * (1 - l_discount) * (1 + l_tax), 6) AS charge FROM lineitem")
def proj_line_revenue(t):
    return t.lineitem.select("l_orderkey", "l_partkey", "l_linenumber", r6(revenue(), "revenue"), r6(revenue() * (1 + F.col("l_tax")), "charge"))


@query("proj_struct_pack", "SELECT n_nationkey, 'nation:' || n_name || '@' || n_regionkey AS packed FROM nation")
def proj_struct_pack(t):
    s = t.nation.select("n_nationkey", F.struct("n_name", "n_regionkey").alias("s"))
    return s.select("n_nationkey", F.concat(F.lit("nation:"), "s.n_name", F.lit("@"), F.col("s.n_regionkey").cast("string")).alias("packed"))


@query("filter_range", "SELECT o_orderkey, o_totalprice FROM orders WHERE o_orderdate BETWEEN TIMESTAMP '1996-01-01' AND TIMESTAMP '1996-12-31' AND o_totalprice > 200000")
def filter_range(t):
    return t.orders.where("o_orderdate between timestamp_ntz'1996-01-01' and timestamp_ntz'1996-12-31' and o_totalprice > 200000").select("o_orderkey", "o_totalprice")


@query("filter_in", "SELECT p_partkey, p_brand, p_type FROM part WHERE p_type IN ('PROMO', 'LARGE') AND p_size NOT IN (1, 2, 3)")
def filter_in(t):
    return t.part.where(F.col("p_type").isin("PROMO", "LARGE") & ~F.col("p_size").isin(1, 2, 3)).select("p_partkey", "p_brand", "p_type")


@query("filter_regex", "SELECT p_partkey, p_name FROM part WHERE regexp_matches(p_name, '^(red|blue) .*t$') OR p_name ILIKE '%RING'")
def filter_regex(t):
    return t.part.where(F.col("p_name").rlike("^(red|blue) .*t$") | F.col("p_name").ilike("%RING")).select("p_partkey", "p_name")


@query("filter_null_safe", "SELECT d.doc_id, l.quality FROM documents d LEFT JOIN labels l USING (doc_id) WHERE l.quality IS NOT DISTINCT FROM NULL OR l.quality = 0")
def filter_null_safe(t):
    return t.documents.join(t.labels, "doc_id", "left").where(F.col("quality").eqNullSafe(F.lit(None)) | (F.col("quality") == 0)).select("doc_id", "quality")


# --- joins -------------------------------------------------------------------


@query("join_star_inner", """
SELECT n_name, o_orderpriority, count(*)::BIGINT AS lines, round(sum(l_extendedprice * (1 - l_discount)), 4) AS revenue
FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY 1, 2""")
def join_star_inner(t):
    both = t.lineitem.join(t.orders, F.col("l_orderkey") == F.col("o_orderkey")).join(t.customer, F.col("o_custkey") == F.col("c_custkey")).join(t.nation, F.col("c_nationkey") == F.col("n_nationkey"))
    return both.groupBy("n_name", "o_orderpriority").agg(F.count("*").alias("lines"), F.round(F.sum(revenue()), 4).alias("revenue"))


@query("join_left_missing", "SELECT c_custkey FROM customer LEFT JOIN orders ON c_custkey = o_custkey WHERE o_orderkey IS NULL")
def join_left_missing(t):
    return t.customer.join(t.orders, F.col("c_custkey") == F.col("o_custkey"), "left").where("o_orderkey is null").select("c_custkey")


@query("join_full_outer", "SELECT coalesce(a.n, b.n) AS nation, a.customers, b.suppliers FROM (SELECT c_nationkey AS n, count(*)::BIGINT AS customers FROM customer WHERE c_nationkey < 18 GROUP BY 1) a FULL JOIN (SELECT s_nationkey AS n, count(*)::BIGINT AS suppliers FROM supplier WHERE s_nationkey > 5 GROUP BY 1) b ON a.n = b.n")
def join_full_outer(t):
    a = t.customer.where("c_nationkey < 18").groupBy(F.col("c_nationkey").alias("nation")).agg(F.count("*").alias("customers"))
    b = t.supplier.where("s_nationkey > 5").groupBy(F.col("s_nationkey").alias("nation")).agg(F.count("*").alias("suppliers"))
    return a.join(b, "nation", "full")


@query("join_semi_labelled", "SELECT doc_id, lang FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)")
def join_semi_labelled(t):
    return t.documents.join(t.labels.where("quality = 1"), "doc_id", "left_semi").select("doc_id", "lang")


@query("join_anti_unlabelled", "SELECT doc_id, source FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def join_anti_unlabelled(t):
    return t.documents.join(t.labels, "doc_id", "left_anti").select("doc_id", "source")


@query("join_theta_price_band", "SELECT b.band, count(*)::BIGINT AS parts FROM part JOIN (VALUES ('low', 0, 1000), ('mid', 1000, 1500), ('high', 1500, 99999)) b(band, lo, hi) ON p_retailprice >= b.lo AND p_retailprice < b.hi GROUP BY 1")
def join_theta_price_band(t):
    bands = t.spark.createDataFrame([("low", 0, 1000), ("mid", 1000, 1500), ("high", 1500, 99999)], "band string, lo int, hi int")
    return t.part.join(F.broadcast(bands), (F.col("p_retailprice") >= F.col("lo")) & (F.col("p_retailprice") < F.col("hi"))).groupBy("band").agg(F.count("*").alias("parts"))


@query("join_cross_templates", "SELECT r_name || ' by ' || m AS question FROM region, (VALUES ('count'), ('mean'), ('sum')) v(m)")
def join_cross_templates(t):
    measures = t.spark.createDataFrame([("count",), ("mean",), ("sum",)], "m string")
    return t.region.crossJoin(F.broadcast(measures)).select(F.concat("r_name", F.lit(" by "), "m").alias("question"))


@query("join_range_interval", "SELECT e.event_id, o.o_orderkey FROM events e JOIN orders o ON e.user_id = o.o_custkey AND date_diff('day', o.o_orderdate, e.ts) BETWEEN 7000 AND 9500 WHERE e.event_type = 'error'")
def join_range_interval(t):
    e = t.events.where("event_type = 'error'")
    days = F.datediff("ts", "o_orderdate")
    return e.join(t.orders, (F.col("user_id") == F.col("o_custkey")) & days.between(7000, 9500)).select("event_id", "o_orderkey")


@query("join_asof_events", "SELECT a.event_id, b.event_id AS last_click FROM (SELECT * FROM events WHERE event_type = 'purchase') a ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'click') b ON a.user_id = b.user_id AND a.ts >= b.ts")
def join_asof_events(t):
    """Union of both sides; the last click is carried along each user's time line."""
    w = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "click", 0).otherwise(1))
    both = t.events.where("event_type in ('click', 'purchase')").select("user_id", "ts", "event_type", "event_id")
    last = F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(w)
    return both.withColumn("last_click", last).where("event_type = 'purchase'").select("event_id", "last_click")


@query("join_lateral_topk", "SELECT n_nationkey, c.c_custkey, c.c_acctbal FROM nation, LATERAL (SELECT c_custkey, c_acctbal FROM customer WHERE c_nationkey = n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 2) c")
def join_lateral_topk(t):
    w = Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")
    top = t.customer.withColumn("r", F.row_number().over(w)).where("r <= 2")
    return t.nation.join(top, F.col("n_nationkey") == F.col("c_nationkey")).select("n_nationkey", "c_custkey", "c_acctbal")


@query("join_self_pairs", "SELECT a.s_suppkey AS a, b.s_suppkey AS b FROM supplier a JOIN supplier b ON a.s_nationkey = b.s_nationkey AND a.s_suppkey < b.s_suppkey AND abs(a.s_acctbal - b.s_acctbal) < 500")
def join_self_pairs(t):
    a, b = t.supplier.alias("a"), t.supplier.alias("b")
    on = (F.col("a.s_nationkey") == F.col("b.s_nationkey")) & (F.col("a.s_suppkey") < F.col("b.s_suppkey")) & (F.abs(F.col("a.s_acctbal") - F.col("b.s_acctbal")) < 500)
    return a.join(b, on).select(F.col("a.s_suppkey").alias("a"), F.col("b.s_suppkey").alias("b"))


# --- aggregation -------------------------------------------------------------


@query("agg_pricing_summary", """
SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS sum_qty, round(sum(l_extendedprice), 2) AS sum_base, round(sum(l_extendedprice * (1 - l_discount)), 2) AS sum_disc,
 round(avg(l_quantity), 6) AS avg_qty, round(avg(l_discount), 6) AS avg_disc, count(*)::BIGINT AS lines FROM lineitem WHERE l_shipdate <= TIMESTAMP '2000-09-02' GROUP BY 1, 2""")
def agg_pricing_summary(t):
    kept = t.lineitem.where("l_shipdate <= timestamp_ntz'2000-09-02'")
    return kept.groupBy("l_returnflag", "l_linestatus").agg(F.round(F.sum("l_quantity"), 2).alias("sum_qty"), F.round(F.sum("l_extendedprice"), 2).alias("sum_base"), F.round(F.sum(revenue()), 2).alias("sum_disc"), r6(F.avg("l_quantity"), "avg_qty"), r6(F.avg("l_discount"), "avg_disc"), F.count("*").alias("lines"))


@query("agg_distinct", "SELECT l_suppkey, count(DISTINCT l_partkey)::BIGINT AS parts, count(DISTINCT l_orderkey)::BIGINT AS orders FROM lineitem GROUP BY 1")
def agg_distinct(t):
    return t.lineitem.groupBy("l_suppkey").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_orderkey").alias("orders"))


@query("agg_percentiles", "SELECT o_orderpriority, round(quantile_cont(o_totalprice, 0.25), 6) AS p25, round(median(o_totalprice), 6) AS p50, round(quantile_cont(o_totalprice, 0.9), 6) AS p90 FROM orders GROUP BY 1")
def agg_percentiles(t):
    return t.orders.groupBy("o_orderpriority").agg(*[r6(F.percentile("o_totalprice", p), n) for p, n in ((0.25, "p25"), (0.5, "p50"), (0.9, "p90"))])


@query("agg_max_by", "SELECT p_brand, arg_max(p_partkey, p_retailprice * 100000 + p_partkey) AS dearest, arg_min(p_partkey, p_retailprice * 100000 + p_partkey) AS cheapest FROM part GROUP BY 1")
def agg_max_by(t):
    key = F.col("p_retailprice") * 100000 + F.col("p_partkey")
    return t.part.groupBy("p_brand").agg(F.max_by("p_partkey", key).alias("dearest"), F.min_by("p_partkey", key).alias("cheapest"))


@query("agg_conditional", "SELECT o_custkey, count(*) FILTER (WHERE o_orderstatus = 'F')::BIGINT AS finished, bool_and(o_totalprice > 1000) AS all_large, bool_or(o_orderpriority = '1-URGENT') AS any_urgent FROM orders GROUP BY 1")
def agg_conditional(t):
    return t.orders.groupBy("o_custkey").agg(F.count_if(F.col("o_orderstatus") == "F").alias("finished"), F.bool_and(F.col("o_totalprice") > 1000).alias("all_large"), F.bool_or(F.col("o_orderpriority") == "1-URGENT").alias("any_urgent"))


@query("agg_listagg", "SELECT r_name, string_agg(n_name, ',' ORDER BY n_name) AS nations FROM nation JOIN region ON n_regionkey = r_regionkey GROUP BY 1")
def agg_listagg(t):
    return t.nation.join(t.region, F.col("n_regionkey") == F.col("r_regionkey")).groupBy("r_name").agg(F.array_join(F.array_sort(F.collect_list("n_name")), ",").alias("nations"))


@query("agg_moments", "SELECT event_type, count(*)::BIGINT AS n, round(avg(value), 6) AS mean, round(stddev_samp(value), 6) AS sd, round(var_pop(value), 6) AS var FROM events GROUP BY 1")
def agg_moments(t):
    return t.events.groupBy("event_type").agg(F.count("*").alias("n"), r6(F.avg("value"), "mean"), r6(F.stddev_samp("value"), "sd"), r6(F.var_pop("value"), "var"))


@query("agg_rollup_region", """
SELECT r_name, n_name, grouping(r_name)::INT * 2 + grouping(n_name)::INT AS level, count(*)::BIGINT AS customers, round(sum(c_acctbal), 2) AS balance
FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)""")
def agg_rollup_region(t):
    both = t.customer.join(t.nation, F.col("c_nationkey") == F.col("n_nationkey")).join(t.region, F.col("n_regionkey") == F.col("r_regionkey"))
    return both.rollup("r_name", "n_name").agg(F.grouping_id().cast("int").alias("level"), F.count("*").alias("customers"), F.round(F.sum("c_acctbal"), 2).alias("balance"))


@query("agg_cube_flags", "SELECT l_returnflag, l_linestatus, count(*)::BIGINT AS lines FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def agg_cube_flags(t):
    return t.lineitem.cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("lines"))


@query("agg_grouping_sets", "SELECT p_brand, p_type, count(*)::BIGINT AS parts FROM part GROUP BY GROUPING SETS ((p_brand), (p_type), ())")
def agg_grouping_sets(t):
    p = t.part
    return p.groupingSets([[p.p_brand], [p.p_type], []], p.p_brand, p.p_type).agg(F.count("*").alias("parts"))


@query("pivot_year_segment", """
SELECT year(o_orderdate)::INT AS year, round(sum(o_totalprice) FILTER (WHERE o_orderstatus = 'F'), 2) AS f, round(sum(o_totalprice) FILTER (WHERE o_orderstatus = 'O'), 2) AS o, round(sum(o_totalprice) FILTER (WHERE o_orderstatus = 'P'), 2) AS p FROM orders GROUP BY 1""")
def pivot_year_segment(t):
    wide = t.orders.groupBy(F.year("o_orderdate").alias("year")).pivot("o_orderstatus", ["F", "O", "P"]).agg(F.round(F.sum("o_totalprice"), 2))
    return wide.select("year", F.col("F").alias("f"), F.col("O").alias("o"), F.col("P").alias("p"))


@query("unpivot_cells", "SELECT p_partkey, 'p_brand' AS name, p_brand AS value FROM part UNION ALL SELECT p_partkey, 'p_type', p_type FROM part UNION ALL SELECT p_partkey, 'p_size', p_size::VARCHAR FROM part")
def unpivot_cells(t):
    return t.part.select("p_partkey", "p_brand", "p_type", F.col("p_size").cast("string").alias("p_size")).unpivot("p_partkey", ["p_brand", "p_type", "p_size"], "name", "value")


@query("transpose_cells", "SELECT attribute, AFRICA, AMERICA, ASIA FROM (SELECT 'r_regionkey' AS attribute, max(r_regionkey) FILTER (WHERE r_name = 'AFRICA') AS AFRICA, max(r_regionkey) FILTER (WHERE r_name = 'AMERICA') AS AMERICA, max(r_regionkey) FILTER (WHERE r_name = 'ASIA') AS ASIA FROM region)")
def transpose_cells(t):
    long = t.region.select(F.lit("r_regionkey").alias("attribute"), "r_name", "r_regionkey")
    return long.groupBy("attribute").pivot("r_name", ["AFRICA", "AMERICA", "ASIA"]).agg(F.max("r_regionkey"))


# --- windows and order -------------------------------------------------------


@query("win_rank_brand", "SELECT p_partkey, p_brand, (rank() OVER w)::INT AS rk, (dense_rank() OVER w)::INT AS dr, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size)")
def win_rank_brand(t):
    w = Window.partitionBy("p_brand").orderBy("p_size")
    return t.part.select("p_partkey", "p_brand", F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), r6(F.percent_rank().over(w), "pr"), r6(F.cume_dist().over(w), "cd"))


@query("win_running_total", "SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING), 2) AS running FROM orders")
def win_running_total(t):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(Window.unboundedPreceding, 0)
    return t.orders.select("o_orderkey", F.round(F.sum("o_totalprice").over(w), 2).alias("running"))


@query("win_moving_avg_range", "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 6 HOURS PRECEDING AND CURRENT ROW), 6) AS avg6h FROM events")
def win_moving_avg_range(t):
    rows = t.events.select("event_id", "user_id", "ts", "value")
    rows.createOrReplaceTempView("tm_moving")
    return rows.sparkSession.sql("SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 6 HOURS PRECEDING AND CURRENT ROW), 6) AS avg6h FROM tm_moving")


@query("win_lag_delta", "SELECT event_id, round(value - lag(value) OVER w, 6) AS delta, lead(event_id) OVER w AS next_event, first_value(event_id) OVER w AS first_event FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_lag_delta(t):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return t.events.select("event_id", r6(F.col("value") - F.lag("value").over(w), "delta"), F.lead("event_id").over(w).alias("next_event"), F.first("event_id").over(w).alias("first_event"))


@query("win_ntile", "SELECT c_custkey, ntile(4) OVER (PARTITION BY c_mktsegment ORDER BY c_acctbal, c_custkey) AS quartile FROM customer")
def win_ntile(t):
    return t.customer.select("c_custkey", F.ntile(4).over(Window.partitionBy("c_mktsegment").orderBy("c_acctbal", "c_custkey")).cast("long").alias("quartile"))


@query("topk_customers", "SELECT c_custkey, c_acctbal FROM customer ORDER BY c_acctbal DESC, c_custkey LIMIT 10")
def topk_customers(t):
    return t.customer.select("c_custkey", "c_acctbal").orderBy(F.desc("c_acctbal"), "c_custkey").limit(10)


@query("topk_per_group", "SELECT p_type, p_partkey, rk::INT AS rk FROM (SELECT p_type, p_partkey, row_number() OVER (PARTITION BY p_type ORDER BY p_retailprice DESC, p_partkey) AS rk FROM part) WHERE rk <= 3")
def topk_per_group(t):
    w = Window.partitionBy("p_type").orderBy(F.desc("p_retailprice"), "p_partkey")
    return t.part.select("p_type", "p_partkey", F.row_number().over(w).alias("rk")).where("rk <= 3")


@query("sample_md5", f"SELECT o_orderkey FROM orders WHERE {det.sql_unit(chr(39) + 's' + chr(39), 'o_orderkey')} < 0.1")
def sample_md5(t):
    return t.orders.where(det.unit("s", F.col("o_orderkey")) < 0.1).select("o_orderkey")


# --- sets, subqueries and writes ---------------------------------------------


@query("set_union_all", "SELECT c_nationkey AS k FROM customer UNION ALL SELECT s_nationkey FROM supplier")
def set_union_all(t):
    return t.customer.select(F.col("c_nationkey").alias("k")).union(t.supplier.select("s_nationkey"))


@query("set_intersect", "SELECT o_custkey AS k FROM orders INTERSECT SELECT user_id FROM events")
def set_intersect(t):
    return t.orders.select(F.col("o_custkey").alias("k")).intersect(t.events.select("user_id"))


@query("set_except_all", "SELECT l_partkey AS k FROM lineitem EXCEPT ALL SELECT p_partkey FROM part")
def set_except_all(t):
    return t.lineitem.select(F.col("l_partkey").alias("k")).exceptAll(t.part.select("p_partkey"))


@query("sub_scalar_avg", "SELECT p_partkey FROM part WHERE p_retailprice > (SELECT avg(p_retailprice) FROM part) * 1.05")
def sub_scalar_avg(t):
    t.part.createOrReplaceTempView("tm_part")
    return t.spark.sql("SELECT p_partkey FROM tm_part WHERE p_retailprice > (SELECT avg(p_retailprice) FROM tm_part) * 1.05")


@query("sub_exists", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 400000)")
def sub_exists(t):
    t.orders.createOrReplaceTempView("tm_orders")
    t.customer.createOrReplaceTempView("tm_customer")
    return t.spark.sql("SELECT c_custkey FROM tm_customer WHERE EXISTS (SELECT 1 FROM tm_orders WHERE o_custkey = c_custkey AND o_totalprice > 400000)")


@query("sub_cte", "WITH s AS (SELECT l_suppkey, sum(l_quantity) AS q FROM lineitem GROUP BY 1) SELECT l_suppkey, q FROM s WHERE q >= (SELECT quantile_cont(q, 0.9) FROM s)")
def sub_cte(t):
    t.lineitem.createOrReplaceTempView("tm_lineitem")
    return t.spark.sql("WITH s AS (SELECT l_suppkey, sum(l_quantity) AS q FROM tm_lineitem GROUP BY 1) SELECT l_suppkey, q FROM s WHERE q >= (SELECT percentile(q, 0.9) FROM s)")


@query("sql_param_query", "SELECT o_orderkey FROM orders WHERE o_orderstatus = 'P' AND o_totalprice BETWEEN 100000 AND 150000")
def sql_param_query(t):
    return t.spark.sql("SELECT o_orderkey FROM {o} WHERE o_orderstatus = :s AND o_totalprice BETWEEN :a AND :b", args={"s": "P", "a": 100000, "b": 150000}, o=t.orders)


@query("op_insert_rows", "SELECT n_nationkey, n_name, n_regionkey FROM nation UNION ALL SELECT 99, 'NEWLAND', 0")
def op_insert_rows(t):
    return t.nation.unionByName(t.spark.createDataFrame([(99, "NEWLAND", 0)], "n_nationkey int, n_name string, n_regionkey int"))


@query("op_delete_rows", "SELECT l_orderkey, l_partkey, l_linenumber FROM lineitem WHERE NOT (l_returnflag = 'R')")
def op_delete_rows(t):
    return t.lineitem.where(~(F.col("l_returnflag") == "R")).select("l_orderkey", "l_partkey", "l_linenumber")


@query("op_modify_rows", "SELECT p_partkey, round(CASE WHEN p_brand = 'Brand#4' THEN p_retailprice * 1.05 ELSE p_retailprice END, 6) AS p_retailprice FROM part")
def op_modify_rows(t):
    return t.part.select("p_partkey", r6(F.when(F.col("p_brand") == "Brand#4", F.col("p_retailprice") * 1.05).otherwise(F.col("p_retailprice")), "p_retailprice"))


# --- values ------------------------------------------------------------------


@query("str_normalise_names", "SELECT c_custkey, lower(regexp_replace(trim(c_name), '[^A-Za-z0-9]+', '_', 'g')) AS name, lpad(c_custkey::VARCHAR, 8, '0') AS code, upper(substr(c_mktsegment, 1, 1)) || lower(substr(c_mktsegment, 2)) AS segment FROM customer")
def str_normalise_names(t):
    return t.customer.select("c_custkey", F.lower(F.regexp_replace(F.trim("c_name"), "[^A-Za-z0-9]+", "_")).alias("name"), F.lpad(F.col("c_custkey").cast("string"), 8, "0").alias("code"), F.initcap("c_mktsegment").alias("segment"))


@query("str_levenshtein", "SELECT a.n_name AS a, b.n_name AS b, levenshtein(a.n_name, b.n_name)::INT AS d FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey AND a.n_regionkey = b.n_regionkey")
def str_levenshtein(t):
    a, b = t.nation.alias("a"), t.nation.alias("b")
    both = a.join(b, (F.col("a.n_nationkey") < F.col("b.n_nationkey")) & (F.col("a.n_regionkey") == F.col("b.n_regionkey")))
    return both.select(F.col("a.n_name").alias("a"), F.col("b.n_name").alias("b"), F.levenshtein("a.n_name", "b.n_name").alias("d"))


@query("str_regex_extract", "SELECT p_partkey, regexp_extract(p_brand, '#([0-9]+)', 1)::INT AS brand_no, length(p_name)::INT AS n, string_split(p_name, ' ')[1] AS head FROM part")
def str_regex_extract(t):
    return t.part.select("p_partkey", F.regexp_extract("p_brand", "#([0-9]+)", 1).cast("int").alias("brand_no"), F.length("p_name").alias("n"), F.split("p_name", " ")[0].alias("head"))


@query("date_month_revenue", "SELECT strftime(date_trunc('month', o_orderdate), '%Y-%m') AS month, quarter(any_value(o_orderdate))::INT AS quarter, count(*)::BIGINT AS orders, round(sum(o_totalprice), 2) AS total FROM orders GROUP BY 1")
def date_month_revenue(t):
    return t.orders.groupBy(F.date_format("o_orderdate", "yyyy-MM").alias("month")).agg(F.max(F.quarter("o_orderdate")).alias("quarter"), F.count("*").alias("orders"), F.round(F.sum("o_totalprice"), 2).alias("total"))


@query("date_ship_delay", "SELECT date_diff('day', o_orderdate, l_shipdate)::INT // 365 AS years, count(*)::BIGINT AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_shipdate >= o_orderdate GROUP BY 1")
def date_ship_delay(t):
    both = t.lineitem.join(t.orders, F.col("l_orderkey") == F.col("o_orderkey")).where("l_shipdate >= o_orderdate")
    return both.groupBy(F.floor(F.datediff("l_shipdate", "o_orderdate") / 365).cast("int").alias("years")).agg(F.count("*").alias("n"))


@query("math_log_bins", "SELECT floor(log10(l_extendedprice) * 4)::INT AS bin, count(*)::BIGINT AS n FROM lineitem WHERE l_extendedprice > 0 GROUP BY 1")
def math_log_bins(t):
    return t.lineitem.where("l_extendedprice > 0").groupBy(F.floor(F.log10("l_extendedprice") * 4).cast("int").alias("bin")).agg(F.count("*").alias("n"))


@query("math_width_bucket", "SELECT CASE WHEN c_acctbal < 0 THEN 0 WHEN c_acctbal >= 10000 THEN 11 ELSE floor(c_acctbal / 1000)::INT + 1 END AS bucket, count(*)::BIGINT AS n FROM customer GROUP BY 1")
def math_width_bucket(t):
    return t.customer.groupBy(F.width_bucket("c_acctbal", F.lit(0.0), F.lit(10000.0), F.lit(10)).cast("int").alias("bucket")).agg(F.count("*").alias("n"))


@query("arr_token_stats", r"SELECT doc_id, len(regexp_extract_all(text, '\S+'))::INT AS n, len(list_distinct(regexp_extract_all(lower(text), '\S+')))::INT AS kinds, list_max(list_transform(regexp_extract_all(text, '\S+'), lambda w: length(w)))::INT AS longest FROM documents")
def arr_token_stats(t):
    ws = F.regexp_extract_all("text", F.lit(r"\S+"), F.lit(0))
    return t.documents.select("doc_id", F.size(ws).alias("n"), F.size(F.array_distinct(F.regexp_extract_all(F.lower("text"), F.lit(r"\S+"), F.lit(0)))).alias("kinds"), F.array_max(F.transform(ws, lambda w: F.length(w))).alias("longest"))


@query("arr_ngrams", r"WITH w AS (SELECT regexp_extract_all(lower(text), '\S+') AS ws FROM benchmark), g AS (SELECT unnest(list_transform(range(1, len(ws)), lambda i: ws[i] || ' ' || ws[i+1])) AS g FROM w) SELECT g, count(*)::BIGINT AS n FROM g GROUP BY g")
def arr_ngrams(t):
    from tablemill.functions.text import ngrams, tokens

    return t.benchmark.select(F.explode(ngrams(tokens(F.lower("text")), 2)).alias("g")).groupBy("g").agg(F.count("*").alias("n"))


@query("arr_dot_product", "SELECT a.vec_id, round(list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda p: p[1]::DOUBLE * p[2]::DOUBLE)), 4) AS dot FROM embeddings a JOIN embeddings b ON b.vec_id = 0")
def arr_dot_product(t):
    first = t.embeddings.where("vec_id = 0").select(F.col("embedding").alias("q"))
    dot = F.aggregate(F.zip_with("embedding", "q", lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda a, x: a + x)
    return t.embeddings.crossJoin(F.broadcast(first)).select("vec_id", F.round(dot, 4).alias("dot"))


@query("map_tag_vector", "SELECT doc_id, 'chars=' || n_chars || ',lang=' || lang AS tags FROM documents WHERE n_chars > 100")
def map_tag_vector(t):
    m = F.map_from_entries(F.array(*[F.struct(F.lit(k).alias("k"), v.alias("v")) for k, v in (("chars", F.col("n_chars").cast("string")), ("lang", F.col("lang")))]))
    return t.documents.where("n_chars > 100").select("doc_id", F.array_join(F.transform(F.map_entries(m), lambda e: F.concat(e["key"], F.lit("="), e["value"])), ",").alias("tags"))


@query("json_props_sum", "SELECT event_type, sum(json_extract(props, '$.k')::BIGINT)::BIGINT AS k, max(json_extract(props, '$.k')::INT) AS top FROM events GROUP BY 1")
def json_props_sum(t):
    k = F.from_json("props", "k int")["k"]
    return t.events.groupBy("event_type").agg(F.sum(k.cast("long")).alias("k"), F.max(k).alias("top"))


@query("json_row_serialise", """SELECT r_regionkey, '{"r_regionkey":' || r_regionkey || ',"r_name":"' || r_name || '"}' AS j FROM region""")
def json_row_serialise(t):
    return t.region.select("r_regionkey", F.to_json(F.struct("r_regionkey", "r_name")).alias("j"))


@query("html_title", "SELECT page_id, regexp_extract(html, '<title>(.*?)</title>', 1, 's') AS title FROM pages")
def html_title(t):
    return t.pages.select("page_id", F.regexp_extract("html", "(?s)<title>(.*?)</title>", 1).alias("title"))


@query("html_links", """SELECT page_id, len(regexp_extract_all(html, 'href="([^"]*)"', 1))::BIGINT AS links, array_to_string(list_sort(list_distinct(regexp_extract_all(html, 'href="([^"]*)"', 1))), ' ') AS hrefs FROM pages""")
def html_links(t):
    hrefs = F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))
    return t.pages.select("page_id", F.size(hrefs).cast("long").alias("links"), F.array_join(F.array_sort(F.array_distinct(hrefs)), " ").alias("hrefs"))


@query("html_strip_text", f"SELECT page_id, md5({STRIP_SQL}) AS h, length({STRIP_SQL})::INT AS n FROM pages")
def html_strip_text(t):
    return t.pages.select("page_id", strip_html(F.col("html")).alias("s")).select("page_id", F.md5("s").alias("h"), F.length("s").alias("n"))


@query("url_host_counts", "SELECT regexp_extract(url, '^[a-z]+://([^/?#:]+)', 1) AS host, count(*)::BIGINT AS pages FROM pages GROUP BY 1")
def url_host_counts(t):
    return t.pages.groupBy(F.parse_url("url", F.lit("HOST")).alias("host")).agg(F.count("*").alias("pages"))


def holes():
    return det.unit("hole", F.col("event_id")) < 0.2


HOLES_SQL = det.sql_unit("'hole'", "event_id") + " < 0.2"


@query("null_impute_mean", f"WITH h AS (SELECT event_id, event_type, CASE WHEN {HOLES_SQL} THEN NULL ELSE value END AS v FROM events) SELECT event_id, round(coalesce(v, avg(v) OVER (PARTITION BY event_type)), 6) AS value FROM h")
def null_impute_mean(t):
    from tablemill.operators.tables import impute

    return impute(t.events.select("event_id", "event_type", F.when(~holes(), F.col("value")).alias("value")), "value", "mean", ["event_type"]).select("event_id", r6(F.col("value"), "value"))


@query("null_ffill", f"WITH h AS (SELECT event_id, user_id, CASE WHEN {HOLES_SQL} THEN NULL ELSE value END AS v FROM events) SELECT event_id, last_value(v IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY event_id ROWS UNBOUNDED PRECEDING) AS value FROM h")
def null_ffill(t):
    from tablemill.operators.tables import impute

    return impute(t.events.select("event_id", "user_id", F.when(~holes(), F.col("value")).alias("value")), "value", "ffill", ["user_id"], ["event_id"]).select("event_id", "value")


# --- vectors and statistics --------------------------------------------------


DOT_SQL = "list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda p: p[1]::DOUBLE * p[2]::DOUBLE))"


@query("vec_cosine_topk", f"SELECT q, vec_id, round(s, 4) AS score, rk FROM (SELECT b.vec_id AS q, a.vec_id, {DOT_SQL} AS s, row_number() OVER (PARTITION BY b.vec_id ORDER BY round({DOT_SQL}, 6) DESC, a.vec_id) AS rk FROM embeddings a JOIN embeddings b ON b.vec_id % 20 = 0 AND a.vec_id <> b.vec_id) WHERE rk <= 5")
def vec_cosine_topk(t):
    from tablemill.operators.encoder import nearest

    q = t.embeddings.where("vec_id % 20 = 0").select(F.col("vec_id").alias("q"), F.col("embedding").alias("query"))
    return nearest(q, t.embeddings.select("vec_id", "embedding"), 5).select("q", "vec_id", F.round("score", 4).alias("score"), "rk")


@query("vec_centroids", "SELECT label, round(avg(embedding[1]::DOUBLE), 6) AS x1, round(avg(embedding[2]::DOUBLE), 6) AS x2, round(avg(embedding[64]::DOUBLE), 6) AS x64, count(*)::BIGINT AS n FROM embeddings GROUP BY 1")
def vec_centroids(t):
    return t.embeddings.groupBy("label").agg(*[r6(F.avg(F.col("embedding")[i - 1].cast("double")), f"x{i}") for i in (1, 2, 64)], F.count("*").alias("n"))


@query("stat_welch_t", """
WITH s AS (SELECT o_orderstatus AS g, count(*)::DOUBLE AS n, avg(o_totalprice) AS m, var_samp(o_totalprice) AS v FROM orders GROUP BY 1)
SELECT round((a.m - b.m) / sqrt(a.v / a.n + b.v / b.n), 6) AS t, round(pow(a.v / a.n + b.v / b.n, 2) / (pow(a.v / a.n, 2) / (a.n - 1) + pow(b.v / b.n, 2) / (b.n - 1)), 4) AS df FROM s a, s b WHERE a.g = 'F' AND b.g = 'O'""")
def stat_welch_t(t):
    from tablemill.operators.stats import welch_t

    return welch_t(t.orders, "o_orderstatus", "o_totalprice", "F", "O")


@query("stat_chi2", """
WITH c AS (SELECT l_returnflag AS a, l_linestatus AS b, count(*)::DOUBLE AS n FROM lineitem GROUP BY 1, 2), r AS (SELECT a, sum(n) AS n FROM c GROUP BY 1), k AS (SELECT b, sum(n) AS n FROM c GROUP BY 1), z AS (SELECT sum(n) AS n FROM c)
SELECT round(sum(pow(coalesce(c.n, 0) - r.n * k.n / z.n, 2) / (r.n * k.n / z.n)), 6) AS chi2, ((count(DISTINCT r.a) - 1) * (count(DISTINCT k.b) - 1))::BIGINT AS df FROM r CROSS JOIN k CROSS JOIN z LEFT JOIN c ON c.a = r.a AND c.b = k.b""")
def stat_chi2(t):
    from tablemill.operators.stats import chi2

    return chi2(t.lineitem, "l_returnflag", "l_linestatus")


@query("stat_linear_fit", "SELECT p_type, round(regr_slope(p_retailprice, p_size), 6) AS slope, round(regr_intercept(p_retailprice, p_size), 6) AS intercept, round(regr_r2(p_retailprice, p_size), 6) AS r2, round(corr(p_retailprice, p_size), 6) AS r FROM part GROUP BY 1")
def stat_linear_fit(t):
    y, x = F.col("p_retailprice"), F.col("p_size").cast("double")
    return t.part.groupBy("p_type").agg(r6(F.regr_slope(y, x), "slope"), r6(F.regr_intercept(y, x), "intercept"), r6(F.regr_r2(y, x), "r2"), r6(F.corr(y, x), "r"))


# --- chart data --------------------------------------------------------------


@query("viz_bar_series", "SELECT c_mktsegment AS x, round(sum(o_totalprice), 2) AS y FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
def viz_bar_series(t):
    return t.orders.join(t.customer, F.col("o_custkey") == F.col("c_custkey")).groupBy(F.col("c_mktsegment").alias("x")).agg(F.round(F.sum("o_totalprice"), 2).alias("y"))


@query("viz_histogram", "SELECT floor(l_quantity / 5)::INT AS bin, count(*)::BIGINT AS n FROM lineitem GROUP BY 1")
def viz_histogram(t):
    return t.lineitem.groupBy(F.floor(F.col("l_quantity") / 5).cast("int").alias("bin")).agg(F.count("*").alias("n"))


@query("viz_box_stats", "SELECT event_type, min(value) AS low, round(quantile_cont(value, 0.25), 6) AS q1, round(median(value), 6) AS mid, round(quantile_cont(value, 0.75), 6) AS q3, max(value) AS high FROM events GROUP BY 1")
def viz_box_stats(t):
    return t.events.groupBy("event_type").agg(F.min("value").alias("low"), r6(F.percentile("value", 0.25), "q1"), r6(F.percentile("value", 0.5), "mid"), r6(F.percentile("value", 0.75), "q3"), F.max("value").alias("high"))
