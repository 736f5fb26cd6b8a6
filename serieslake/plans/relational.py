"""Joins, aggregates, windows, sorts, set operations and functions on the given tables."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..operators import joins as J
from ..operators import series as R
from .registry import Tables, query

def revenue():
    return F.col("l_extendedprice") * (1 - F.col("l_discount"))


# --- joins --------------------------------------------------------------------------------------


@query("SELECT n_name, count(*) AS customers, round(sum(c_acctbal), 4) AS balance FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def j_broadcast_customer_nation(t: Tables):
    # nation is a fixed list of 25 rows
    return t.customer.join(F.broadcast(t.nation), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count(F.lit(1)).alias("customers"), F.round(F.sum("c_acctbal"), 4).alias("balance"))


@query("SELECT o_orderpriority, count(*) AS lines, round(sum(l_extendedprice * (1 - l_discount)), 4) AS revenue FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderpriority")
def j_merge_orders_lineitem(t: Tables):
    lines = t.lineitem.select("l_orderkey", revenue().alias("r"))
    return t.orders.select("o_orderkey", "o_orderpriority").hint("merge").join(lines, F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("lines"), F.round(F.sum("r"), 4).alias("revenue"))


@query("SELECT p_brand, round(sum(l_quantity), 4) AS quantity FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_brand")
def j_shufflehash_part_lineitem(t: Tables):
    return t.lineitem.select("l_partkey", "l_quantity").join(t.part.select("p_partkey", "p_brand").hint("shuffle_hash"), F.col("l_partkey") == F.col("p_partkey")).groupBy("p_brand").agg(F.round(F.sum("l_quantity"), 4).alias("quantity"))


@query("SELECT lo AS band, count(*) AS parts FROM part JOIN (SELECT unnest(range(0, 3000, 100)) AS lo) b ON p_retailprice >= lo AND p_retailprice < lo + 100 GROUP BY lo")
def j_theta_part_price_band(t: Tables):
    # 30 bands: a fixed list
    bands = t.spark.range(0, 3000, 100).select(F.col("id").alias("band"))
    return t.part.select("p_retailprice").join(F.broadcast(bands), (F.col("p_retailprice") >= F.col("band")) & (F.col("p_retailprice") < F.col("band") + 100)).groupBy("band").agg(F.count(F.lit(1)).alias("parts"))


@query("SELECT c_mktsegment, count(*) AS customers FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 200000) GROUP BY c_mktsegment")
def j_semi_customers_with_orders(t: Tables):
    dear = t.orders.where("o_totalprice > 200000").select(F.col("o_custkey").alias("c_custkey"))
    return t.customer.join(dear, "c_custkey", "left_semi").groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("customers"))


@query("SELECT p_type, count(*) AS parts FROM part WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey AND l_returnflag = 'R') GROUP BY p_type")
def j_anti_parts_never_returned(t: Tables):
    returned = t.lineitem.where("l_returnflag = 'R'").select(F.col("l_partkey").alias("p_partkey"))
    return t.part.join(returned, "p_partkey", "left_anti").groupBy("p_type").agg(F.count(F.lit(1)).alias("parts"))


_SPANS = "SELECT user_id AS owner, min(event_id) AS first_id, min(event_id) + 400 AS last_id FROM events GROUP BY user_id"


@query(f"SELECT owner, count(*) AS inside FROM events JOIN ({_SPANS}) s ON event_id BETWEEN first_id AND last_id AND event_type = 'purchase' GROUP BY owner")
def j_interval_events_sessions(t: Tables):
    spans = t.events.groupBy(F.col("user_id").alias("owner")).agg(F.min("event_id").alias("first_id")).withColumn("last_id", F.col("first_id") + 400)
    bought = t.events.where("event_type = 'purchase'").select("event_id")
    return J.interval(bought, spans, "event_id", "first_id", "last_id", 512).groupBy("owner").agg(F.count(F.lit(1)).alias("inside"))


@query("SELECT p.event_id, p.user_id, v.view_id FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT user_id, event_id AS view_id, event_id AS at FROM events WHERE event_type = 'view') v ON p.user_id = v.user_id AND p.event_id >= v.at")
def j_asof_purchase_last_view(t: Tables):
    bought = t.events.where("event_type = 'purchase'").select("event_id", "user_id")
    views = t.events.where("event_type = 'view'").select("user_id", F.col("event_id").alias("view_id"))
    return J.asof(bought, views, "user_id", "event_id", "view_id", ["view_id"])


@query("SELECT lang, count(*) AS docs, CAST(sum(CASE WHEN quality IS NULL THEN 1 ELSE 0 END) AS BIGINT) AS unlabelled, CAST(coalesce(sum(quality), 0) AS BIGINT) AS good FROM documents LEFT JOIN labels USING (doc_id) GROUP BY lang")
def j_left_documents_labels(t: Tables):
    return t.documents.select("doc_id", "lang").join(t.labels, "doc_id", "left").groupBy("lang").agg(F.count(F.lit(1)).alias("docs"), F.sum(F.col("quality").isNull().cast("bigint")).alias("unlabelled"), F.coalesce(F.sum("quality"), F.lit(0)).cast("bigint").alias("good"))


@query("""SELECT strftime(coalesce(o.d, s.d), '%Y-%m') AS month, CAST(count(o.n) AS BIGINT) AS order_days, CAST(count(s.n) AS BIGINT) AS ship_days
FROM (SELECT CAST(o_orderdate AS DATE) AS d, count(*) AS n FROM orders GROUP BY 1) o FULL JOIN (SELECT CAST(l_shipdate AS DATE) AS d, count(*) AS n FROM lineitem GROUP BY 1) s ON o.d = s.d GROUP BY 1""")
def j_full_daily_orders_ships(t: Tables):
    o = t.orders.groupBy(F.to_date("o_orderdate").alias("d")).agg(F.count(F.lit(1)).alias("o"))
    s = t.lineitem.groupBy(F.to_date("l_shipdate").alias("d")).agg(F.count(F.lit(1)).alias("s"))
    return o.join(s, "d", "full").groupBy(F.date_format("d", "yyyy-MM").alias("month")).agg(F.count("o").alias("order_days"), F.count("s").alias("ship_days"))


@query("SELECT n_nationkey, o.c_custkey, o.c_acctbal FROM nation, LATERAL (SELECT c_custkey, c_acctbal FROM customer WHERE c_nationkey = n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 3) o")
def j_lateral_top3_customers(t: Tables):
    # a lateral top-3 as a window: one shuffle by nation, limited on the map side
    w = Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")
    top = t.customer.withColumn("r", F.row_number().over(w)).where("r <= 3")
    return top.join(F.broadcast(t.nation.select("n_nationkey")), F.col("c_nationkey") == F.col("n_nationkey")).select("n_nationkey", "c_custkey", "c_acctbal")


@query("SELECT p_type, count(*) AS lines, round(sum(l_quantity * p_retailprice), 2) AS worth FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_type")
def j_salted_lineitem_part(t: Tables):
    lines = t.lineitem.select(F.col("l_partkey").alias("p_partkey"), "l_orderkey", "l_quantity")
    got = J.salted(lines, t.part.select("p_partkey", "p_type", "p_retailprice"), "p_partkey", 8)
    return got.groupBy("p_type").agg(F.count(F.lit(1)).alias("lines"), F.round(F.sum(F.col("l_quantity") * F.col("p_retailprice")), 2).alias("worth"))


# --- aggregates ---------------------------------------------------------------------------------


@query("SELECT l_returnflag, l_linestatus, count(*) AS lines, round(sum(l_quantity), 4) AS qty, round(sum(l_extendedprice * (1 - l_discount) * (1 + l_tax)), 2) AS charge, round(avg(l_discount), 6) AS disc FROM lineitem WHERE l_shipdate <= TIMESTAMP '1998-09-02' GROUP BY ALL")
def a_price_by_flag_status(t: Tables):
    return t.lineitem.where("l_shipdate <= timestamp_ntz'1998-09-02'").groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("lines"), F.round(F.sum("l_quantity"), 4).alias("qty"), F.round(F.sum(revenue() * (1 + F.col("l_tax"))), 2).alias("charge"), F.round(F.avg("l_discount"), 6).alias("disc"))


@query("SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY event_type")
def a_distinct_users_by_type(t: Tables):
    return t.events.groupBy("event_type").agg(F.countDistinct("user_id").alias("users"))


@query("SELECT event_type, round(quantile_cont(value, 0.25), 6) AS p25, round(quantile_cont(value, 0.5), 6) AS p50, round(quantile_cont(value, 0.9), 6) AS p90 FROM events GROUP BY event_type")
def a_percentiles_value(t: Tables):
    return t.events.groupBy("event_type").agg(*(F.round(F.percentile("value", p), 6).alias(f"p{int(p * 100)}") for p in (0.25, 0.5, 0.9)))


@query("SELECT user_id, round(stddev_pop(value), 6) AS dev, round(avg(value), 6) AS mean FROM events GROUP BY user_id")
def a_stddev_by_user(t: Tables):
    return t.events.groupBy("user_id").agg(F.round(F.stddev_pop("value"), 6).alias("dev"), F.round(F.avg("value"), 6).alias("mean"))


@query("SELECT r_name, n_name, count(*) AS customers FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")
def a_rollup_region_nation(t: Tables):
    places = t.nation.join(F.broadcast(t.region), F.col("n_regionkey") == F.col("r_regionkey"))
    return t.customer.join(F.broadcast(places), F.col("c_nationkey") == F.col("n_nationkey")).rollup("r_name", "n_name").agg(F.count(F.lit(1)).alias("customers"))


@query("SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 4) AS qty FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def a_cube_flag_status(t: Tables):
    return t.lineitem.cube("l_returnflag", "l_linestatus").agg(F.round(F.sum("l_quantity"), 4).alias("qty"))


@query("SELECT p_brand, p_type, count(*) AS parts, CAST(grouping_id(p_brand, p_type) AS BIGINT) AS gid FROM part GROUP BY GROUPING SETS ((p_brand, p_type), (p_type), ())")
def a_grouping_sets_brand_type(t: Tables):
    b, k = F.col("p_brand"), F.col("p_type")
    return t.part.groupingSets([[b, k], [k], []], b, k).agg(F.count(F.lit(1)).alias("parts"), F.grouping_id().alias("gid"))


@query("SELECT user_id, arg_max(event_id, (value, event_id)) AS event_id, max(value) AS value FROM events GROUP BY user_id")
def a_argmax_event_per_user(t: Tables):
    return t.events.groupBy("user_id").agg(F.max(F.struct("value", "event_id")).alias("m")).select("user_id", "m.event_id", "m.value")


_TYPES = ("click", "purchase", "signup", "view", "error")


@query("SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, " + ", ".join(f"count(*) FILTER (event_type = '{k}') AS {k}" for k in _TYPES) + " FROM events GROUP BY 1")
def a_pivot_type_by_day(t: Tables):
    got = t.events.groupBy(F.to_date("ts").cast("string").alias("day")).pivot("event_type", list(_TYPES)).agg(F.count(F.lit(1)))
    return got.na.fill(0)


@query("SELECT o_custkey, bool_and(o_orderstatus = 'F') AS all_done, bool_or(o_orderstatus = 'F') AS any_done FROM orders GROUP BY o_custkey")
def a_all_done_flag(t: Tables):
    return t.orders.groupBy("o_custkey").agg(F.bool_and(F.col("o_orderstatus") == "F").alias("all_done"), F.bool_or(F.col("o_orderstatus") == "F").alias("any_done"))


@query("SELECT conv_id, string_agg(role, '>' ORDER BY turn) AS roles, CAST(sum(length(text)) AS BIGINT) AS chars FROM conversations GROUP BY conv_id")
def a_collect_turns_ordered(t: Tables):
    got = t.conversations.groupBy("conv_id").agg(F.sort_array(F.collect_list(F.struct("turn", "role"))).alias("r"), F.sum(F.length("text")).alias("chars"))
    return got.select("conv_id", F.array_join(F.transform("r", lambda x: x["role"]), ">").alias("roles"), "chars")


@query("SELECT p_brand, min(p_size) AS least, max(p_size) AS most, min_by(p_partkey, (p_retailprice, p_partkey)) AS cheapest FROM part GROUP BY p_brand")
def a_min_max_by(t: Tables):
    return t.part.groupBy("p_brand").agg(F.min("p_size").alias("least"), F.max("p_size").alias("most"), F.min_by("p_partkey", F.struct("p_retailprice", "p_partkey")).alias("cheapest"))


@query()
def a_approx_distinct(t: Tables):
    return t.lineitem.agg(F.approx_count_distinct("l_orderkey").alias("orders"))


@query()
def a_kll_median(t: Tables):
    return t.events.agg(F.expr("kll_sketch_get_quantile_double(kll_sketch_agg_double(value), 0.5D)").alias("median"))


# --- windows ------------------------------------------------------------------------------------


@query("SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING), 6) AS running FROM events")
def w_running_value(t: Tables):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return t.events.select("event_id", F.round(F.sum("value").over(w), 6).alias("running"))


@query("SELECT o_orderkey, CAST(rank() OVER w AS BIGINT) AS r, CAST(dense_rank() OVER w AS BIGINT) AS d FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderpriority)")
def w_rank_orders_per_customer(t: Tables):
    w = Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    return t.orders.select("o_orderkey", F.rank().over(w).cast("bigint").alias("r"), F.dense_rank().over(w).cast("bigint").alias("d"))


@query("SELECT p_partkey, CAST(ntile(4) OVER (PARTITION BY p_brand ORDER BY p_retailprice, p_partkey) AS BIGINT) AS quarter FROM part")
def w_ntile_price(t: Tables):
    return t.part.select("p_partkey", F.ntile(4).over(Window.partitionBy("p_brand").orderBy("p_retailprice", "p_partkey")).cast("bigint").alias("quarter"))


@query("SELECT event_id, CAST(epoch_us(ts) - epoch_us(lag(ts) OVER w) AS BIGINT) AS gap_us, lead(event_id) OVER w AS next_id FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def w_lag_gap(t: Tables):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    return t.events.select("event_id", (us - F.lag(us).over(w)).alias("gap_us"), F.lead("event_id").over(w).alias("next_id"))


@query("SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS 4 PRECEDING), 6) AS avg5 FROM events")
def w_moving_avg_rows(t: Tables):
    return t.events.select("event_id", F.round(F.avg("value").over(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-4, 0)), 6).alias("avg5"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW) AS last_day FROM events")
def w_count_1d_range(t: Tables):
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    return t.events.withColumn("_us", us).select("event_id", F.count(F.lit(1)).over(Window.partitionBy("user_id").orderBy("_us").rangeBetween(-86_400_000_000, 0)).alias("last_day"))


@query("SELECT DISTINCT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, first_value(event_id) OVER w AS first_id, last_value(event_id) OVER w AS last_id, nth_value(event_id, 2) OVER w AS second_id FROM events WINDOW w AS (PARTITION BY CAST(ts AS DATE) ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def w_first_last_of_day(t: Tables):
    # ends of a day by one aggregation of narrow structs; no window over a whole day
    got = t.events.groupBy(F.to_date("ts").cast("string").alias("day")).agg(F.min(F.struct("ts", "event_id")).alias("a"), F.max(F.struct("ts", "event_id")).alias("b"))
    w = Window.partitionBy("day").orderBy("ts", "event_id")
    second = t.events.select(F.to_date("ts").cast("string").alias("day"), "ts", "event_id").withColumn("r", F.row_number().over(w)).where("r <= 2").where("r = 2").select("day", F.col("event_id").alias("second_id"))
    return got.join(second, "day", "left").select("day", F.col("a.event_id").alias("first_id"), F.col("b.event_id").alias("last_id"), "second_id")


@query("SELECT p_partkey, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM part WINDOW w AS (PARTITION BY p_type ORDER BY p_retailprice, p_partkey)")
def w_percent_rank(t: Tables):
    w = Window.partitionBy("p_type").orderBy("p_retailprice", "p_partkey")
    return t.part.select("p_partkey", F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"))


# --- sort, limit, set operations ----------------------------------------------------------------


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def t_topk_global(t: Tables):
    return t.orders.select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20)


@query("SELECT user_id, event_id, CAST(r AS BIGINT) AS r FROM (SELECT user_id, event_id, row_number() OVER (PARTITION BY user_id ORDER BY value DESC, event_id) AS r FROM events) WHERE r <= 3")
def t_topk_per_group(t: Tables):
    w = Window.partitionBy("user_id").orderBy(F.desc("value"), "event_id")
    return t.events.select("user_id", "event_id", F.row_number().over(w).cast("bigint").alias("r")).where("r <= 3")


@query("SELECT s_suppkey, s_name FROM supplier ORDER BY s_suppkey LIMIT 5 OFFSET 3")
def t_limit_offset(t: Tables):
    return t.supplier.select("s_suppkey", "s_name").orderBy("s_suppkey").offset(3).limit(5)


@query("SELECT kind, count(*) AS n FROM (SELECT 'c' AS kind, c_nationkey AS k FROM customer UNION ALL SELECT 's', s_nationkey FROM supplier) GROUP BY kind")
def s_union_all_by_name(t: Tables):
    a = t.customer.select(F.lit("c").alias("kind"), F.col("c_nationkey").alias("k"))
    b = t.supplier.select(F.col("s_nationkey").alias("k"), F.lit("s").alias("kind"))
    return a.unionByName(b).groupBy("kind").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT o_custkey AS k FROM orders WHERE o_orderstatus = 'F' INTERSECT SELECT o_custkey FROM orders WHERE o_orderstatus = 'O'")
def s_intersect_keys(t: Tables):
    return t.orders.where("o_orderstatus = 'F'").select(F.col("o_custkey").alias("k")).intersect(t.orders.where("o_orderstatus = 'O'").select("o_custkey"))


@query("SELECT k, count(*) AS n FROM (SELECT l_partkey AS k FROM lineitem WHERE l_returnflag = 'A' EXCEPT ALL SELECT l_partkey FROM lineitem WHERE l_returnflag = 'R') GROUP BY k")
def s_except_all_keys(t: Tables):
    a = t.lineitem.where("l_returnflag = 'A'").select(F.col("l_partkey").alias("k"))
    return a.exceptAll(t.lineitem.where("l_returnflag = 'R'").select("l_partkey")).groupBy("k").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT DISTINCT event_type, user_id FROM events")
def s_drop_duplicates(t: Tables):
    return t.events.select("event_type", "user_id").dropDuplicates()


# --- functions ----------------------------------------------------------------------------------


@query("SELECT CAST(json_extract(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1")
def f_json_props(t: Tables):
    return t.events.select(F.get_json_object("props", "$.k").cast("bigint").alias("k")).groupBy("k").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT page_id, split_part(url, '/', 3) AS host, split_part(url, '/', 4) AS lang, CAST(length(url) AS BIGINT) AS len FROM pages")
def f_string_paths(t: Tables):
    return t.pages.select("page_id", F.split_part("url", F.lit("/"), F.lit(3)).alias("host"), F.split_part("url", F.lit("/"), F.lit(4)).alias("lang"), F.length("url").cast("bigint").alias("len"))


@query("SELECT o_orderkey, CAST(year(o_orderdate) AS BIGINT) AS y, CAST(quarter(o_orderdate) AS BIGINT) AS q, CAST(dayofyear(o_orderdate) AS BIGINT) AS d, CAST(date_trunc('month', o_orderdate) AS VARCHAR)[1:10] AS m FROM orders")
def f_date_parts(t: Tables):
    d = F.col("o_orderdate")
    return t.orders.select("o_orderkey", F.year(d).cast("bigint").alias("y"), F.quarter(d).cast("bigint").alias("q"), F.dayofyear(d).cast("bigint").alias("d"), F.date_format(F.date_trunc("month", d), "yyyy-MM-dd").alias("m"))


@query("SELECT strftime(m, '%Y-%m') AS month, count(o_orderkey) AS orders FROM (SELECT unnest(generate_series(DATE '1992-01-01', DATE '1998-12-01', INTERVAL 1 MONTH)) AS m) g LEFT JOIN orders ON date_trunc('month', o_orderdate) = m GROUP BY 1")
def f_month_grid(t: Tables):
    grid = t.spark.range(1).select(F.explode(F.sequence(F.lit("1992-01-01").cast("date"), F.lit("1998-12-01").cast("date"), F.expr("interval 1 month"))).alias("m")).select(F.date_format("m", "yyyy-MM").alias("month"))
    counts = t.orders.groupBy(F.date_format("o_orderdate", "yyyy-MM").alias("month")).agg(F.count(F.lit(1)).alias("orders"))
    return grid.join(counts, "month", "left").na.fill(0, ["orders"])


@query("SELECT p_partkey, round(sqrt(p_retailprice), 6) AS root, CAST(p_size << 2 AS BIGINT) AS up, CAST(p_size >> 1 AS BIGINT) AS down, CAST(bit_count(p_size) AS BIGINT) AS ones, greatest(p_size, 25) AS g FROM part")
def f_math_bits(t: Tables):
    s = F.col("p_size")
    return t.part.select("p_partkey", F.round(F.sqrt("p_retailprice"), 6).alias("root"), F.shiftleft(s, 2).cast("bigint").alias("up"), F.shiftright(s, 1).cast("bigint").alias("down"), F.bit_count(s).cast("bigint").alias("ones"), F.greatest(s, F.lit(25)).alias("g"))


@query("SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x)), 6) AS norm2, CAST(len(list_filter(embedding, lambda x: x > 0)) AS BIGINT) AS positive, round(CAST(list_max(embedding) AS DOUBLE), 6) AS most FROM embeddings")
def f_array_higher_order(t: Tables):
    v = F.transform("embedding", lambda x: x.cast("double"))
    return t.embeddings.select("vec_id", F.round(F.aggregate(F.transform(v, lambda x: x * x), F.lit(0.0), lambda a, x: a + x), 6).alias("norm2"), F.size(F.filter(v, lambda x: x > 0)).cast("bigint").alias("positive"), F.round(F.array_max(v), 6).alias("most"))


@query("SELECT user_id, string_agg(event_type || '=' || n, ',' ORDER BY event_type) AS counts FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY ALL) GROUP BY user_id")
def f_map_ops(t: Tables):
    by = t.events.groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    m = by.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    entries = F.array_sort(F.map_entries(F.map_filter("m", lambda k, v: v > 0)))
    return m.select("user_id", F.array_join(F.transform(entries, lambda e: F.concat(e["key"], F.lit("="), e["value"].cast("string"))), ",").alias("counts"))


@query("SELECT label, CAST(pos - 1 AS BIGINT) AS pos, round(avg(CAST(x AS DOUBLE)), 6) AS mean FROM (SELECT label, unnest(embedding) AS x, generate_subscripts(embedding, 1) AS pos FROM embeddings) GROUP BY ALL")
def f_posexplode_vectors(t: Tables):
    return t.embeddings.select("label", F.posexplode("embedding").alias("pos", "x")).groupBy("label", F.col("pos").cast("bigint").alias("pos")).agg(F.round(F.avg(F.col("x").cast("double")), 6).alias("mean"))


@query("SELECT event_type, CAST(sum(CASE WHEN value > 100 THEN 1 ELSE 0 END) AS BIGINT) AS big FROM (SELECT event_type, value FROM events) GROUP BY event_type")
def f_struct_access(t: Tables):
    s = t.events.select(F.struct("event_type", "value").alias("e"))
    return s.groupBy(F.col("e.event_type").alias("event_type")).agg(F.sum((F.col("e.value") > 100).cast("bigint")).alias("big"))


@query("SELECT user_id, CAST(event_id AS BIGINT) AS last_id, round(a, 6) AS mean4 FROM (SELECT user_id, event_id, avg(value) OVER w AS a, count(*) OVER w AS n FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS 3 PRECEDING)) WHERE n = 4")
def f_windows_to_means(t: Tables):
    got = R.key_windows(t.events, "user_id", ["ts", "event_id"], "value", "event_id", 4)
    mean = F.round(F.aggregate("values", F.lit(0.0), lambda a, x: a + x) / 4, 6)
    return got.select(F.col("series_id").alias("last_id"), mean.alias("mean4")).join(t.events.select("user_id", F.col("event_id").alias("last_id")), "last_id")


class _PrefixPaths:
    """All prefixes of a path string, as a table function."""

    def eval(self, path: str):
        for d in range(len(path) + 1):
            yield (path[:d], d)


sx_path_prefixes = F.udtf(_PrefixPaths, returnType="prefix string, depth int")


@query("SELECT p_type, CAST(depth AS BIGINT) AS depth, count(*) AS n FROM (SELECT p_type, unnest(generate_series(0, 4)) AS depth FROM part) GROUP BY ALL")
def f_udtf_prefixes(t: Tables):
    t.spark.udtf.register("sx_path_prefixes", sx_path_prefixes)
    t.part.select("p_type", F.lit("0110").alias("path")).createOrReplaceTempView("_paths")
    return t.spark.sql("SELECT p_type, CAST(x.depth AS BIGINT) AS depth, count(*) AS n FROM _paths, LATERAL sx_path_prefixes(path) x GROUP BY p_type, x.depth")


@F.pandas_udf(T.DoubleType())
def _mean(x: pd.Series) -> float:
    return float(x.mean())


@query("SELECT label, round(avg(CAST(embedding[1] AS DOUBLE)), 6) AS mean FROM embeddings GROUP BY label")
def f_grouped_mean_series(t: Tables):
    return t.embeddings.select("label", F.get("embedding", F.lit(0)).cast("double").alias("x")).groupBy("label").agg(F.round(_mean("x"), 6).alias("mean"))


@query("SELECT doc_id, CAST(len(list_filter(string_split_regex(text, '[ \\n\\t]+'), lambda x: length(x) > 10)) AS BIGINT) AS long_words FROM documents WHERE source LIKE 'src1%' AND n_chars BETWEEN 500 AND 3000 AND lang IN ('en', 'de') AND lang IS NOT DISTINCT FROM lang")
def p_predicates(t: Tables):
    d = t.documents.where(F.col("source").like("src1%") & F.col("n_chars").between(500, 3000) & F.col("lang").isin("en", "de") & F.col("lang").eqNullSafe(F.col("lang")))
    return d.select("doc_id", F.size(F.filter(F.split("text", "[ \\n\\t]+"), lambda x: F.length(x) > 10)).cast("bigint").alias("long_words"))
