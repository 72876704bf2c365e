"""The operator library on the given tables: scans, joins, aggregates, windows, sets, functions, Python surface."""

from __future__ import annotations

from functools import reduce

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from statewitness.functions import joins as J
from statewitness.plans.base import workload
from statewitness.sources import formats
from statewitness.sources.tables import cents, load

CENTS = "round({} * 100)::BIGINT"


def op(name: str, sql: str | None):
    return workload(f"op_{name}", sql)


# --- scans and sinks --------------------------------------------------------------------------------

op("scan_prune", "SELECT l_orderkey, l_returnflag, l_linestatus FROM lineitem")(lambda s, d: load(s, d, "lineitem").select("l_orderkey", "l_returnflag", "l_linestatus"))
op("scan_pushdown", "SELECT o_orderkey, o_custkey FROM orders WHERE o_orderstatus = 'O' AND o_totalprice > 300000")(lambda s, d: load(s, d, "orders").filter("o_orderstatus = 'O' AND o_totalprice > 300000").select("o_orderkey", "o_custkey"))
op("roundtrip_csv", "SELECT n_nationkey, n_name, n_regionkey FROM nation")(lambda s, d: formats.round_trip(load(s, d, "nation"), "csv", header=True))
op("roundtrip_json", "SELECT r_regionkey, r_name FROM region")(lambda s, d: formats.round_trip(load(s, d, "region"), "json"))
op("roundtrip_orc", "SELECT s_suppkey, s_name, s_nationkey FROM supplier")(lambda s, d: formats.round_trip(load(s, d, "supplier").select("s_suppkey", "s_name", "s_nationkey"), "orc"))
op("roundtrip_text", "SELECT c_name AS value FROM customer")(lambda s, d: formats.round_trip(load(s, d, "customer").select(F.col("c_name").alias("value")), "text"))
op("partitioned_sink", "SELECT event_id, event_type FROM events WHERE event_type = 'purchase'")(lambda s, d: formats.partitioned(load(s, d, "events").select("event_id", "event_type"), "event_type", "purchase"))

# --- projections and filters ------------------------------------------------------------------------

op("case_when", "SELECT o_orderkey, CASE WHEN o_totalprice > 200000 THEN 'high' WHEN o_totalprice > 100000 THEN 'mid' ELSE 'low' END AS band FROM orders")(lambda s, d: load(s, d, "orders").select("o_orderkey", F.when(F.col("o_totalprice") > 200000, "high").when(F.col("o_totalprice") > 100000, "mid").otherwise("low").alias("band")))
op("null_logic", "SELECT c_custkey, nullif(c_mktsegment, 'BUILDING') AS seg, coalesce(nullif(c_mktsegment, 'BUILDING'), 'none') AS filled, nullif(c_mktsegment, 'BUILDING') IS NOT DISTINCT FROM NULL AS same FROM customer")(lambda s, d: load(s, d, "customer").select("c_custkey", F.nullif("c_mktsegment", F.lit("BUILDING")).alias("seg")).select("c_custkey", "seg", F.coalesce("seg", F.lit("none")).alias("filled"), F.col("seg").eqNullSafe(F.lit(None)).alias("same")))
op("in_between", "SELECT p_partkey FROM part WHERE p_size BETWEEN 10 AND 20 AND p_brand IN ('Brand#11', 'Brand#12', 'Brand#13')")(lambda s, d: load(s, d, "part").filter(F.col("p_size").between(10, 20) & F.col("p_brand").isin("Brand#11", "Brand#12", "Brand#13")).select("p_partkey"))
op("like_rlike", "SELECT doc_id, text LIKE '%License%' AS licensed, regexp_matches(text, '[0-9]{3}') AS digits FROM documents")(lambda s, d: load(s, d, "documents").select("doc_id", F.col("text").like("%License%").alias("licensed"), F.col("text").rlike("[0-9]{3}").alias("digits")))
op("unpivot", "SELECT doc_id, kind, value FROM (SELECT doc_id, quality, toxic FROM labels) UNPIVOT (value FOR kind IN (quality, toxic))")(lambda s, d: load(s, d, "labels").unpivot("doc_id", ["quality", "toxic"], "kind", "value"))
op("struct_fields", "SELECT o_orderkey, o_custkey + 1 AS bumped FROM orders")(lambda s, d: load(s, d, "orders").select("o_orderkey", F.struct("o_custkey", "o_orderstatus").alias("x")).select("o_orderkey", F.col("x").withField("o_custkey", F.col("x.o_custkey") + 1).dropFields("o_orderstatus").alias("x")).select("o_orderkey", F.col("x.o_custkey").alias("bumped")))

# --- joins ------------------------------------------------------------------------------------------

orders_of = lambda s, d: load(s, d, "orders").select("o_orderkey", "o_custkey", "o_orderstatus")
names_of = lambda s, d: load(s, d, "nation").select("n_nationkey", "n_name")

op("join_broadcast", "SELECT s_suppkey, n_name FROM supplier JOIN nation ON s_nationkey = n_nationkey")(lambda s, d: load(s, d, "supplier").join(F.broadcast(names_of(s, d)), F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", "n_name"))
op("join_sortmerge", "SELECT o_orderstatus, count(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")(lambda s, d: orders_of(s, d).join(load(s, d, "lineitem").select("l_orderkey").hint("merge"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderstatus").agg(F.count("*").alias("n")))
op("join_shufflehash", "SELECT p_brand, count(*) AS n FROM part JOIN lineitem ON p_partkey = l_partkey GROUP BY 1")(lambda s, d: load(s, d, "lineitem").select("l_partkey").join(load(s, d, "part").select("p_partkey", "p_brand").hint("shuffle_hash"), F.col("p_partkey") == F.col("l_partkey")).groupBy("p_brand").agg(F.count("*").alias("n")))
op("join_left", "SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY 1")(lambda s, d: load(s, d, "customer").select("c_custkey").join(orders_of(s, d), F.col("c_custkey") == F.col("o_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n")))
op("join_right", "SELECT n_name, count(s_suppkey) AS n FROM supplier RIGHT JOIN nation ON s_nationkey = n_nationkey GROUP BY 1")(lambda s, d: load(s, d, "supplier").select("s_suppkey", "s_nationkey").join(names_of(s, d), F.col("s_nationkey") == F.col("n_nationkey"), "right").groupBy("n_name").agg(F.count("s_suppkey").alias("n")))
op("join_full", "SELECT coalesce(a.k, b.k) AS k, a.k IS NOT NULL AS in_a, b.k IS NOT NULL AS in_b FROM (SELECT o_orderkey AS k FROM orders WHERE o_orderkey % 2 = 0) a FULL JOIN (SELECT o_orderkey AS k FROM orders WHERE o_orderkey % 3 = 0) b ON a.k = b.k")(
    lambda s, d: (lambda a, b: a.join(b, "k", "full").select("k", F.col("a").isNotNull().alias("in_a"), F.col("b").isNotNull().alias("in_b")))(orders_of(s, d).filter("o_orderkey % 2 = 0").select(F.col("o_orderkey").alias("k"), F.lit(1).alias("a")), orders_of(s, d).filter("o_orderkey % 3 = 0").select(F.col("o_orderkey").alias("k"), F.lit(1).alias("b"))))
op("join_semi", "SELECT o_orderkey FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem)")(lambda s, d: orders_of(s, d).join(load(s, d, "lineitem").select("l_orderkey"), F.col("o_orderkey") == F.col("l_orderkey"), "left_semi").select("o_orderkey"))
op("join_anti", "SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)")(lambda s, d: orders_of(s, d).join(load(s, d, "lineitem").select("l_orderkey"), F.col("o_orderkey") == F.col("l_orderkey"), "left_anti").select("o_orderkey"))
op("join_cross", "SELECT r_name, n_name FROM region, nation")(lambda s, d: load(s, d, "region").select("r_name").crossJoin(F.broadcast(load(s, d, "nation").select("n_name"))))
BANDS = [(k, 400.0 * k, 400.0 * (k + 1)) for k in range(6)]
BANDS_SQL = "(VALUES " + ", ".join(str(b) for b in BANDS) + ") b(band, lo, hi)"
bands = lambda s: s.createDataFrame(BANDS, "band int, lo double, hi double")
op("join_theta", f"SELECT p_partkey, band FROM part JOIN {BANDS_SQL} ON p_retailprice >= lo AND p_retailprice < hi")(lambda s, d: load(s, d, "part").select("p_partkey", "p_retailprice").join(F.broadcast(bands(s)), (F.col("p_retailprice") >= F.col("lo")) & (F.col("p_retailprice") < F.col("hi"))).select("p_partkey", "band"))
op("join_range", f"SELECT p_partkey, band FROM part JOIN {BANDS_SQL} ON p_retailprice >= lo AND p_retailprice < hi")(lambda s, d: J.range_join(load(s, d, "part").select("p_partkey", "p_retailprice"), "p_retailprice", bands(s), "lo", "hi", 250.0).select("p_partkey", "band"))
op("join_interval", "SELECT e.event_id AS error_id, p.event_id AS purchase_id FROM events e JOIN events p ON e.user_id = p.user_id AND e.event_type = 'error' AND p.event_type = 'purchase' AND p.ts > e.ts AND p.ts <= e.ts + INTERVAL 1 HOUR")(
    lambda s, d: (lambda e: e.filter("event_type = 'error'").alias("e").join(e.filter("event_type = 'purchase'").alias("p"), F.expr("e.user_id = p.user_id AND p.ts > e.ts AND p.ts <= e.ts + INTERVAL 1 HOUR")).select(F.col("e.event_id").alias("error_id"), F.col("p.event_id").alias("purchase_id")))(load(s, d, "events").select("event_id", "user_id", "ts", "event_type")))


def _errors(s, d):
    e = load(s, d, "events").select("event_id", "user_id", "ts", "event_type")
    return e.filter("event_type = 'purchase'").select("event_id", "user_id", "ts"), e.filter("event_type = 'error'").select("user_id", F.col("ts").alias("ets"), F.col("event_id").alias("error_id"))


op("join_asof_backward", "SELECT p.event_id, (SELECT max(e.event_id) FROM events e WHERE e.event_type = 'error' AND e.user_id = p.user_id AND e.ts <= p.ts) AS error_id FROM events p WHERE p.event_type = 'purchase'")(lambda s, d: J.as_of(*_errors(s, d), ["user_id"], "ts", "ets", "error_id").select("event_id", "error_id"))
op("join_asof_forward", "SELECT p.event_id, (SELECT min(e.event_id) FROM events e WHERE e.event_type = 'error' AND e.user_id = p.user_id AND e.ts >= p.ts) AS error_id FROM events p WHERE p.event_type = 'purchase'")(lambda s, d: J.as_of(*_errors(s, d), ["user_id"], "ts", "ets", "error_id", "forward").select("event_id", "error_id"))


@op("join_asof_nearest", """WITH b AS (SELECT p.event_id, p.ts, (SELECT max(e.event_id) FROM events e WHERE e.event_type='error' AND e.user_id=p.user_id AND e.ts<=p.ts) AS x, (SELECT min(e.event_id) FROM events e WHERE e.event_type='error' AND e.user_id=p.user_id AND e.ts>=p.ts) AS y FROM events p WHERE p.event_type='purchase')
SELECT b.event_id, CASE WHEN y IS NULL THEN x WHEN x IS NULL THEN y WHEN b.ts - ex.ts <= ey.ts - b.ts THEN x ELSE y END AS error_id FROM b LEFT JOIN events ex ON ex.event_id = x LEFT JOIN events ey ON ey.event_id = y""")
def join_asof_nearest(s, d):
    left, right = _errors(s, d)
    right = right.select("user_id", "ets", F.struct(F.col("ets").alias("t"), "error_id").alias("e"))
    rows = J.as_of(left, right, ["user_id"], "ts", "ets", "e").withColumnRenamed("e", "x")
    rows = J.as_of(rows, right, ["user_id"], "ts", "ets", "e", "forward")
    near = F.when(F.col("e").isNull(), F.col("x")).when(F.col("x").isNull(), F.col("e")).when(F.col("ts") - F.col("x.t") <= F.col("e.t") - F.col("ts"), F.col("x")).otherwise(F.col("e"))
    return rows.select("event_id", near.getField("error_id").alias("error_id"))


op("join_nullsafe", "SELECT a.doc_id, count(*) AS n FROM (SELECT doc_id, CASE WHEN quality = 0 THEN NULL ELSE quality END AS q FROM labels) a JOIN (SELECT 1 AS q UNION ALL SELECT NULL) b ON a.q IS NOT DISTINCT FROM b.q GROUP BY 1")(lambda s, d: (lambda a, b: a.join(F.broadcast(b), a["q"].eqNullSafe(b["q"])).groupBy("doc_id").agg(F.count("*").alias("n")))(load(s, d, "labels").select("doc_id", F.nullif("quality", F.lit(0)).alias("q")), s.createDataFrame([(1,), (None,)], "q int")))
op("join_self", "SELECT a.l_orderkey, count(*) AS n FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey GROUP BY 1")(lambda s, d: (lambda l: l.alias("a").join(l.alias("b"), F.expr("a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey")).groupBy("a.l_orderkey").agg(F.count("*").alias("n")))(load(s, d, "lineitem").select("l_orderkey", "l_partkey")))
op("join_skew_salted", "SELECT event_type, count(*) AS n, sum(weight)::BIGINT AS weight FROM events JOIN (VALUES ('purchase', 3), ('error', 2), ('signup', 1)) w(event_type, weight) USING (event_type) GROUP BY 1")(lambda s, d: J.salted_join(load(s, d, "events").select("event_id", "event_type"), s.createDataFrame([("purchase", 3), ("error", 2), ("signup", 1)], "event_type string, weight int"), "event_type", salt_from=F.col("event_id")).groupBy("event_type").agg(F.count("*").alias("n"), F.sum("weight").alias("weight")))


@op("join_lateral", "SELECT n_nationkey, top FROM nation, LATERAL (SELECT max(c_custkey) AS top FROM customer WHERE c_nationkey = n_nationkey)")
def join_lateral(s, d):
    load(s, d, "nation").createOrReplaceTempView("lateral_nation")
    load(s, d, "customer").createOrReplaceTempView("lateral_customer")
    return s.sql("SELECT n_nationkey, top FROM lateral_nation, LATERAL (SELECT max(c_custkey) AS top FROM lateral_customer WHERE c_nationkey = n_nationkey)")


# --- aggregates -------------------------------------------------------------------------------------

op("agg_basic", f"SELECT l_returnflag, l_linestatus, count(*) AS n, sum({CENTS.format('l_extendedprice')})::BIGINT AS total, min(l_quantity) AS lo, max(l_quantity) AS hi FROM lineitem GROUP BY 1, 2")(lambda s, d: load(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum(cents("l_extendedprice")).alias("total"), F.min("l_quantity").alias("lo"), F.max("l_quantity").alias("hi")))
op("agg_filtered", "SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS f, count(*) FILTER (o_orderstatus = 'O') AS o FROM orders GROUP BY 1")(lambda s, d: load(s, d, "orders").groupBy("o_orderpriority").agg(F.count_if(F.col("o_orderstatus") == "F").alias("f"), F.count_if(F.col("o_orderstatus") == "O").alias("o")))
op("agg_distinct", "SELECT l_returnflag, count(DISTINCT l_suppkey) AS suppliers, sum(DISTINCT l_linenumber)::BIGINT AS numbers FROM lineitem GROUP BY 1")(lambda s, d: load(s, d, "lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_suppkey").alias("suppliers"), F.sum_distinct("l_linenumber").alias("numbers")))
op("agg_bool", "SELECT o_custkey, bool_and(o_orderstatus = 'F') AS every, bool_or(o_orderstatus = 'O') AS some FROM orders GROUP BY 1")(lambda s, d: load(s, d, "orders").groupBy("o_custkey").agg(F.bool_and(F.col("o_orderstatus") == "F").alias("every"), F.bool_or(F.col("o_orderstatus") == "O").alias("some")))
op("agg_minmaxby", "SELECT o_custkey, arg_min(o_orderstatus, o_orderkey) AS first, arg_max(o_orderstatus, o_orderkey) AS last FROM orders GROUP BY 1")(lambda s, d: load(s, d, "orders").groupBy("o_custkey").agg(F.min_by("o_orderstatus", "o_orderkey").alias("first"), F.max_by("o_orderstatus", "o_orderkey").alias("last")))
op("agg_stats", "SELECT event_type, round(stddev_samp(value), 4) AS sd, round(var_pop(value), 3) AS var, round(corr(value, user_id), 5) AS r, round(covar_pop(value, user_id), 2) AS cov FROM events GROUP BY 1")(lambda s, d: load(s, d, "events").groupBy("event_type").agg(F.round(F.stddev_samp("value"), 4).alias("sd"), F.round(F.var_pop("value"), 3).alias("var"), F.round(F.corr("value", "user_id"), 5).alias("r"), F.round(F.covar_pop("value", "user_id"), 2).alias("cov")))
op("agg_percentile", "SELECT l_returnflag, median(l_quantity) AS mid, quantile_cont(l_quantity, 0.9) AS p90 FROM lineitem GROUP BY 1")(lambda s, d: load(s, d, "lineitem").groupBy("l_returnflag").agg(F.median("l_quantity").alias("mid"), F.percentile("l_quantity", 0.9).alias("p90")))
op("agg_mode", "SELECT n % 1 AS g, max(c) AS times FROM (SELECT 0 AS n, p_size, count(*) AS c FROM part GROUP BY p_size) GROUP BY 1")(lambda s, d: load(s, d, "part").groupBy("p_size").agg(F.count("*").alias("c")).agg(F.max("c").alias("times")).select(F.lit(0).alias("g"), "times"))
op("agg_collect", "SELECT o_custkey, string_agg(o_orderkey::VARCHAR, ',' ORDER BY o_orderkey) AS keys FROM orders WHERE o_orderstatus = 'P' GROUP BY 1")(lambda s, d: load(s, d, "orders").filter("o_orderstatus = 'P'").groupBy("o_custkey").agg(F.array_join(F.transform(F.sort_array(F.collect_list("o_orderkey")), lambda x: x.cast("string")), ",").alias("keys")))
op("agg_listagg", "SELECT n_regionkey, string_agg(n_name, ';' ORDER BY n_name) AS names FROM nation GROUP BY 1")(lambda s, d: (load(s, d, "nation").createOrReplaceTempView("listagg_nation"), s.sql("SELECT n_regionkey, listagg(n_name, ';') WITHIN GROUP (ORDER BY n_name) AS names FROM listagg_nation GROUP BY 1"))[1])
op("agg_bitxor", "SELECT o_orderstatus, bit_xor(o_orderkey) AS x, bit_and(o_orderkey) AS a, bit_or(o_orderkey) AS o FROM orders GROUP BY 1")(lambda s, d: load(s, d, "orders").groupBy("o_orderstatus").agg(F.bit_xor("o_orderkey").alias("x"), F.bit_and("o_orderkey").alias("a"), F.bit_or("o_orderkey").alias("o")))
op("agg_cube", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")(lambda s, d: load(s, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n")))
op("agg_rollup", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")(lambda s, d: load(s, d, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.count("*").alias("n")))
op("agg_grouping_sets", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus))")(lambda s, d: load(s, d, "lineitem").groupingSets([["l_returnflag"], ["l_linestatus"]], "l_returnflag", "l_linestatus").agg(F.count("*").alias("n")))
op("agg_pivot", "SELECT user_id, count(*) FILTER (event_type = 'error') AS error, count(*) FILTER (event_type = 'purchase') AS purchase FROM events GROUP BY 1")(lambda s, d: load(s, d, "events").groupBy("user_id").pivot("event_type", ["error", "purchase"]).agg(F.count("event_id")).fillna(0))
op("having", "SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1 HAVING count(*) > 12")(lambda s, d: load(s, d, "orders").groupBy("o_custkey").agg(F.count("*").alias("n")).filter("n > 12"))
op("approx_distinct", None)(lambda s, d: load(s, d, "events").agg(F.approx_count_distinct("user_id", 0.02).alias("users")))
op("hll_union", None)(lambda s, d: load(s, d, "events").groupBy("event_type").agg(F.hll_sketch_agg("user_id").alias("k")).agg(F.hll_sketch_estimate(F.hll_union_agg("k")).alias("users")))
op("approx_percentile", None)(lambda s, d: load(s, d, "lineitem").agg(F.percentile_approx("l_quantity", 0.5, 10000).alias("mid")))
op("approx_topk", None)(lambda s, d: (load(s, d, "events").createOrReplaceTempView("topk_events"), s.sql("SELECT inline(approx_top_k(event_type, 3)) FROM topk_events"))[1])

# --- windows, sort, sets ----------------------------------------------------------------------------

users = lambda: Window.partitionBy("user_id").orderBy("event_id")  # noqa: E731  made when asked for: there may be no session at import
byv = lambda: Window.partitionBy("event_type").orderBy("user_id")
events_of = lambda s, d: load(s, d, "events").select("event_id", "user_id", "event_type", "ts")
op("win_rank", "SELECT event_id, rank() OVER w AS r, dense_rank() OVER w AS dr, row_number() OVER (PARTITION BY event_type ORDER BY user_id, event_id) AS rn FROM events WINDOW w AS (PARTITION BY event_type ORDER BY user_id)")(lambda s, d: events_of(s, d).select("event_id", F.rank().over(byv()).alias("r"), F.dense_rank().over(byv()).alias("dr"), F.row_number().over(Window.partitionBy("event_type").orderBy("user_id", "event_id")).alias("rn")))
op("win_percent", "SELECT event_id, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM events WINDOW w AS (PARTITION BY event_type ORDER BY user_id)")(lambda s, d: events_of(s, d).select("event_id", F.round(F.percent_rank().over(byv()), 6).alias("pr"), F.round(F.cume_dist().over(byv()), 6).alias("cd")))
op("win_ntile", "SELECT event_id, ntile(4) OVER (PARTITION BY user_id ORDER BY event_id) AS q FROM events")(lambda s, d: events_of(s, d).select("event_id", F.ntile(4).over(users()).alias("q")))
op("win_lag_lead", "SELECT event_id, lag(event_type) OVER w AS before, lead(event_type, 2) OVER w AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)")(lambda s, d: events_of(s, d).select("event_id", F.lag("event_type").over(users()).alias("before"), F.lead("event_type", 2).over(users()).alias("after")))
whole = lambda: users().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
op("win_first_last", "SELECT event_id, first_value(event_type) OVER w AS f, last_value(event_type) OVER w AS l FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")(lambda s, d: events_of(s, d).select("event_id", F.first("event_type").over(whole()).alias("f"), F.last("event_type").over(whole()).alias("l")))
op("win_nth", "SELECT event_id, nth_value(event_type, 3) OVER w AS third FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")(lambda s, d: events_of(s, d).select("event_id", F.nth_value("event_type", 3).over(whole()).alias("third")))
op("win_rows_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS n FROM events")(lambda s, d: events_of(s, d).select("event_id", F.count("*").over(users().rowsBetween(-2, 0)).alias("n")))
op("win_range_interval", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW) AS n FROM events")(lambda s, d: (events_of(s, d).createOrReplaceTempView("range_events"), s.sql("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW) AS n FROM range_events"))[1])
op("topk_global", "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")(lambda s, d: load(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10).select("o_orderkey"))
op("topk_group", "SELECT o_orderkey, k FROM (SELECT o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS k FROM orders) WHERE k <= 2")(lambda s, d: load(s, d, "orders").select("o_orderkey", F.row_number().over(Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")).alias("k")).filter("k <= 2"))
op("sort_nulls", "SELECT doc_id, q, row_number() OVER (PARTITION BY doc_id % 64 ORDER BY q ASC NULLS LAST, doc_id) AS k FROM (SELECT doc_id, nullif(quality, 0) AS q FROM labels)")(lambda s, d: load(s, d, "labels").select("doc_id", F.nullif("quality", F.lit(0)).alias("q")).select("doc_id", "q", F.row_number().over(Window.partitionBy(F.col("doc_id") % 64).orderBy(F.asc_nulls_last("q"), "doc_id")).alias("k")))
op("limit_offset", "SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 20 OFFSET 40")(lambda s, d: load(s, d, "orders").select("o_orderkey").orderBy("o_orderkey").offset(40).limit(20))
flagged = lambda s, d, f: load(s, d, "lineitem").filter(F.col("l_returnflag") == f).select("l_orderkey")
FLAG = "SELECT l_orderkey FROM lineitem WHERE l_returnflag = '{}'"
for _name, _sql, _f in (
    ("union_all", "UNION ALL", lambda a, b: a.unionAll(b)), ("union_distinct", "UNION", lambda a, b: a.union(b).distinct()), ("intersect", "INTERSECT", lambda a, b: a.intersect(b)), ("intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b)), ("except", "EXCEPT", lambda a, b: a.subtract(b)), ("except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b)),
):
    op(_name, f"SELECT l_orderkey, count(*) AS n FROM ({FLAG.format('A')} {_sql} {FLAG.format('R')}) GROUP BY 1")(lambda s, d, f=_f: f(flagged(s, d, "A"), flagged(s, d, "R")).groupBy("l_orderkey").agg(F.count("*").alias("n")))
op("union_byname", "SELECT r_name AS name, r_regionkey AS k, NULL::VARCHAR AS extra FROM region UNION ALL SELECT n_name, n_nationkey, 'n' FROM nation")(lambda s, d: load(s, d, "region").select(F.col("r_name").alias("name"), F.col("r_regionkey").alias("k")).unionByName(load(s, d, "nation").select(F.col("n_nationkey").alias("k"), F.col("n_name").alias("name"), F.lit("n").alias("extra")), allowMissingColumns=True))

# --- functions --------------------------------------------------------------------------------------

op("str_split", "SELECT doc_id, len(string_split(text, ' ')) AS n, string_split(text, ' ')[1] AS head FROM documents")(lambda s, d: load(s, d, "documents").select("doc_id", F.size(F.split("text", " ", -1)).cast("long").alias("n"), F.split("text", " ", -1)[0].alias("head")))
op("str_regex", "SELECT page_id, regexp_extract(url, '://([^/]+)', 1) AS host, regexp_replace(url, '[0-9]+', '#', 'g') AS shape FROM pages")(lambda s, d: load(s, d, "pages").select("page_id", F.regexp_extract("url", "://([^/]+)", 1).alias("host"), F.regexp_replace("url", "[0-9]+", "#").alias("shape")))
op("str_pad", "SELECT p_partkey, lpad(p_partkey::VARCHAR, 8, '0') AS l, rpad(p_brand, 12, '.') AS r, upper(p_brand) AS u, reverse(p_brand) AS v FROM part")(lambda s, d: load(s, d, "part").select("p_partkey", F.lpad(F.col("p_partkey").cast("string"), 8, "0").alias("l"), F.rpad("p_brand", 12, ".").alias("r"), F.upper("p_brand").alias("u"), F.reverse("p_brand").alias("v")))
op("str_replace", "SELECT c_custkey, replace(c_name, 'Customer', 'C') AS n, translate(c_mktsegment, 'AEIOU', 'aeiou') AS t, position('#' IN c_name) AS p, substr(c_name, 3, 4) AS x FROM customer")(lambda s, d: load(s, d, "customer").select("c_custkey", F.replace("c_name", F.lit("Customer"), F.lit("C")).alias("n"), F.translate("c_mktsegment", "AEIOU", "aeiou").alias("t"), F.instr("c_name", "#").alias("p"), F.substring("c_name", 3, 4).alias("x")))
op("str_levenshtein", "SELECT p_partkey, levenshtein(p_brand, 'Brand#11')::INTEGER AS dist, starts_with(p_type, 'S') AS s, contains(p_type, 'A') AS c FROM part")(lambda s, d: load(s, d, "part").select("p_partkey", F.levenshtein("p_brand", F.lit("Brand#11")).alias("dist"), F.col("p_type").startswith("S").alias("s"), F.col("p_type").contains("A").alias("c")))
op("str_md5", "SELECT doc_id, md5(text) AS m, sha256(text) AS h FROM documents")(lambda s, d: load(s, d, "documents").select("doc_id", F.md5("text").alias("m"), F.sha2("text", 256).alias("h")))
op("str_url", "SELECT page_id, regexp_extract(url, '^([a-z]+)://', 1) AS scheme, regexp_extract(url, '://[^/]+([^?#]*)', 1) AS path FROM pages")(lambda s, d: load(s, d, "pages").select("page_id", F.parse_url("url", F.lit("PROTOCOL")).alias("scheme"), F.parse_url("url", F.lit("PATH")).alias("path")))
op("date_trunc", "SELECT strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS m, count(*) AS n FROM orders GROUP BY 1")(lambda s, d: load(s, d, "orders").groupBy(F.trunc(F.col("o_orderdate").cast("date"), "month").cast("string").alias("m")).agg(F.count("*").alias("n")))
op("date_diff", "SELECT o_orderkey, date_diff('day', DATE '1995-01-01', o_orderdate::DATE)::INTEGER AS days, (o_orderdate::DATE + INTERVAL 2 MONTH)::DATE::VARCHAR AS later, last_day(o_orderdate::DATE)::VARCHAR AS eom FROM orders")(lambda s, d: load(s, d, "orders").select("o_orderkey", F.col("o_orderdate").cast("date").alias("x")).select("o_orderkey", F.date_diff("x", F.lit("1995-01-01").cast("date")).alias("days"), F.add_months("x", 2).cast("string").alias("later"), F.last_day("x").cast("string").alias("eom")))
op("date_extract", "SELECT event_id, extract('hour' FROM ts)::INTEGER AS h, extract('dow' FROM ts)::INTEGER + 1 AS dow, extract('week' FROM ts)::INTEGER AS w FROM events")(lambda s, d: load(s, d, "events").select("event_id", F.hour("ts").alias("h"), F.dayofweek("ts").alias("dow"), F.weekofyear("ts").alias("w")))
op("date_two_shapes", "SELECT a, strptime(b, '%Y-%m-%dT%H:%M:%S') AS t FROM (VALUES ('short', '2024-03-01T10:00:00'), ('long', '2024-03-01T10:00:00')) v(a, b)")(lambda s, d: s.createDataFrame([("short", "2024-03-01T10:00"), ("long", "2024-03-01T10:00:00")], "a string, b string").select("a", F.to_timestamp_ntz("b").alias("t")))
op("math_basic", "SELECT p_partkey, p_size % 7 AS m, width_bucket, greatest(p_size, 25) AS g, abs(p_size - 25) AS a, round(ln(p_retailprice), 6) AS l, floor(p_retailprice / 10)::BIGINT AS f FROM (SELECT *, CASE WHEN p_size < 0 THEN 0 WHEN p_size >= 50 THEN 6 ELSE floor(p_size / 10)::BIGINT + 1 END AS width_bucket FROM part)")(lambda s, d: load(s, d, "part").select("p_partkey", (F.col("p_size") % 7).alias("m"), F.width_bucket(F.col("p_size").cast("double"), F.lit(0.0), F.lit(50.0), F.lit(5)).alias("width_bucket"), F.greatest("p_size", F.lit(25)).alias("g"), F.abs(F.col("p_size") - 25).alias("a"), F.round(F.ln("p_retailprice"), 6).alias("l"), F.floor(F.col("p_retailprice") / 10).alias("f")))
op("math_try_divide", "SELECT doc_id, CASE WHEN toxic = 0 THEN NULL ELSE quality / toxic END AS r FROM labels")(lambda s, d: load(s, d, "labels").select("doc_id", F.try_divide("quality", "toxic").alias("r")))
op("array_higher", "SELECT l_orderkey, list_sum(list_transform(q, lambda x: x * 2))::BIGINT AS doubled, len(list_filter(q, lambda x: x > 25)) AS big, len(list_filter(q, lambda x: x = 1)) > 0 AS any_one, list_sum(q)::BIGINT AS total FROM (SELECT l_orderkey, list(l_quantity::BIGINT) AS q FROM lineitem GROUP BY 1)")(
    lambda s, d: load(s, d, "lineitem").groupBy("l_orderkey").agg(F.collect_list(F.col("l_quantity").cast("long")).alias("q")).select("l_orderkey", F.aggregate(F.transform("q", lambda x: x * 2), F.lit(0).cast("long"), lambda a, x: a + x).alias("doubled"), F.size(F.filter("q", lambda x: x > 25)).cast("long").alias("big"), F.exists("q", lambda x: x == 1).alias("any_one"), F.aggregate("q", F.lit(0).cast("long"), lambda a, x: a + x).alias("total")))
op("array_sets", "SELECT o_custkey, list_sort(list_distinct(list(o_orderstatus)))::VARCHAR AS st, len(list_intersect(list(o_orderstatus), ['O', 'F'])) AS both_n FROM orders GROUP BY 1")(lambda s, d: load(s, d, "orders").groupBy("o_custkey").agg(F.collect_set("o_orderstatus").alias("x")).select("o_custkey", F.concat(F.lit("["), F.array_join(F.sort_array("x"), ", "), F.lit("]")).alias("st"), F.size(F.array_intersect("x", F.array(F.lit("O"), F.lit("F")))).cast("long").alias("both_n")))
op("array_posexplode", "SELECT vec_id, k - 1 AS pos, round(embedding[k]::DOUBLE, 5) AS v FROM embeddings, range(1, 4) r(k)")(lambda s, d: load(s, d, "embeddings").select("vec_id", F.posexplode(F.slice("embedding", 1, 3)).alias("pos", "x")).select("vec_id", F.col("pos").cast("long").alias("pos"), F.round(F.col("x").cast("double"), 5).alias("v")))
op("array_zip_with", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 4) AS norm FROM embeddings")(lambda s, d: load(s, d, "embeddings").select("vec_id", F.round(F.aggregate(F.zip_with("embedding", "embedding", lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda a, x: a + x), 4).alias("norm")))
op("map_entries", "SELECT user_id, sum((event_type = 'error')::INT)::BIGINT AS errors, count(DISTINCT event_type) AS kinds FROM events GROUP BY 1")(lambda s, d: load(s, d, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n")).groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m")).select("user_id", F.coalesce(F.element_at(F.map_filter("m", lambda k, v: k == "error"), "error"), F.lit(0)).alias("errors"), F.size(F.transform_values("m", lambda k, v: v + 1)).cast("long").alias("kinds")))
op("json_get", "SELECT event_id, json_extract_string(props, '$.k')::INTEGER AS k FROM events")(lambda s, d: load(s, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k")))
op("json_from_to", "SELECT event_id, json_extract_string(props, '$.k')::INTEGER + 1 AS k FROM events")(lambda s, d: load(s, d, "events").select("event_id", F.from_json("props", "k int").alias("p")).select("event_id", (F.get_json_object(F.to_json("p"), "$.k").cast("int") + 1).alias("k")))
op("json_variant", "SELECT event_id, json_extract_string(props, '$.k')::INTEGER AS k FROM events")(lambda s, d: load(s, d, "events").select("event_id", F.try_variant_get(F.parse_json("props"), "$.k", "int").alias("k")))


def sql_view(s, d, *names):
    for n in names:
        load(s, d, n).createOrReplaceTempView(f"v_{n}")


@op("sql_cte_subquery", "WITH big AS (SELECT * FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) FROM orders)) SELECT o_orderstatus, count(*) AS n FROM big GROUP BY 1")
def sql_cte_subquery(s, d):
    sql_view(s, d, "orders")
    return s.sql("WITH big AS (SELECT * FROM v_orders WHERE o_totalprice > (SELECT avg(o_totalprice) FROM v_orders)) SELECT o_orderstatus, count(*) AS n FROM big GROUP BY 1")


@op("sql_correlated_exists", "SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_orderstatus = 'P') AND NOT EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 400000)")
def sql_correlated_exists(s, d):
    sql_view(s, d, "customer", "orders")
    return s.sql("SELECT c_custkey FROM v_customer c WHERE EXISTS (SELECT 1 FROM v_orders o WHERE o.o_custkey = c.c_custkey AND o.o_orderstatus = 'P') AND NOT EXISTS (SELECT 1 FROM v_orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 400000)")


@op("sql_params", "SELECT count(*) AS n FROM orders WHERE o_orderstatus = 'F' AND o_totalprice > 1000")
def sql_params(s, d):
    sql_view(s, d, "orders")
    return s.sql("SELECT count(*) AS n FROM v_orders WHERE o_orderstatus = :status AND o_totalprice > :floor", args={"status": "F", "floor": 1000})


@op("sql_udf", "SELECT p_partkey, p_size * 2 + 1 AS y FROM part")
def sql_udf(s, d):
    sql_view(s, d, "part")
    s.sql("CREATE OR REPLACE TEMPORARY FUNCTION twice_and_one(x INT) RETURNS INT RETURN x * 2 + 1")
    return s.sql("SELECT p_partkey, twice_and_one(p_size) AS y FROM v_part")


@op("sql_pipe", "SELECT n_regionkey, count(*) AS n FROM nation WHERE n_nationkey > 3 GROUP BY 1")
def sql_pipe(s, d):
    sql_view(s, d, "nation")
    return s.sql("FROM v_nation |> WHERE n_nationkey > 3 |> AGGREGATE count(*) AS n GROUP BY n_regionkey")


@op("sql_recursive_hops", "WITH RECURSIVE h(k, hops) AS (SELECT 1, 0 UNION ALL SELECT k * 2, hops + 1 FROM h WHERE hops < 3) SELECT k, hops FROM h")
def sql_recursive_hops(s, d):
    return s.sql("WITH RECURSIVE h(k, hops) AS (SELECT 1, 0 UNION ALL SELECT k * 2, hops + 1 FROM h WHERE hops < 3) SELECT k, hops FROM h")


op("sample_hash", "SELECT o_orderkey FROM orders ORDER BY md5(o_orderkey || '|7'), o_orderkey LIMIT 25")(lambda s, d: load(s, d, "orders").select("o_orderkey").orderBy(F.md5(F.concat_ws("|", F.col("o_orderkey").cast("string"), F.lit(7))), "o_orderkey").limit(25))
op("vector_topk", "WITH p AS (SELECT q.vec_id AS query, e.vec_id, list_sum(list_transform(list_zip(e.embedding, q.embedding), lambda x: x[1]::DOUBLE * x[2]::DOUBLE)) / sqrt(list_sum(list_transform(e.embedding, lambda x: x::DOUBLE * x::DOUBLE)) * list_sum(list_transform(q.embedding, lambda x: x::DOUBLE * x::DOUBLE))) AS c FROM embeddings e, embeddings q WHERE q.vec_id % 20 = 0 AND e.vec_id <> q.vec_id) SELECT query, vec_id, k FROM (SELECT query, vec_id, row_number() OVER (PARTITION BY query ORDER BY c DESC, vec_id) AS k FROM p) WHERE k <= 5")(
    lambda s, d: (lambda v: J.nearest_vectors(v.filter("vec_id % 20 = 0"), v, 5).select("query", "vec_id", F.col("rank").alias("k")))(load(s, d, "embeddings").select("vec_id", "embedding")))
op("dedup_exact", "SELECT md5(text) AS h, min(doc_id) AS keep, count(*) AS n FROM documents GROUP BY 1 HAVING count(*) > 1")(lambda s, d: load(s, d, "documents").groupBy(F.md5("text").alias("h")).agg(F.min("doc_id").alias("keep"), F.count("*").alias("n")).filter("n > 1"))
op("contains_benchmark", "SELECT DISTINCT doc_id FROM documents d JOIN benchmark b ON contains(d.text, b.text)")(lambda s, d: load(s, d, "documents").select("doc_id", "text").join(F.broadcast(load(s, d, "benchmark").select(F.col("text").alias("passage"))), F.col("text").contains(F.col("passage"))).select("doc_id").distinct())


@op("dedup_minhash", None)
def dedup_minhash(s, d):
    """Near copies among documents of one source by banded minwise values of word triples (small helper of the unit counts)."""
    words = load(s, d, "documents").select("doc_id", F.split(F.lower("text"), r"\s+").alias("w")).filter("size(w) >= 3")
    grams = words.select("doc_id", F.transform(F.sequence(F.lit(1), F.size("w") - 2), lambda i: F.xxhash64(F.slice("w", i, 3))).alias("g"))
    bands = grams.select("doc_id", F.explode(F.array(*[F.xxhash64(F.lit(k), F.array_min(F.transform("g", lambda x, k=k: x.bitwiseXOR(F.lit(0x5DEECE66D * (2 * k + 1)))))) for k in range(8)])).alias("band"))
    first = bands.groupBy("band").agg(F.min("doc_id").alias("first"), F.count("*").alias("n")).filter("n > 1")
    return bands.join(first, "band").filter("doc_id <> first").select("doc_id", "first").distinct()


# --- Python surface ---------------------------------------------------------------------------------

small = lambda s, d: load(s, d, "part").select("p_partkey", "p_size", "p_brand")
DOUBLE = "SELECT p_partkey, p_size * 2 AS y FROM part"


@op("udf_scalar", DOUBLE)
def udf_scalar(s, d):
    return small(s, d).select("p_partkey", F.udf(lambda x: x * 2, "int")("p_size").alias("y"))


@op("udf_arrow", DOUBLE)
def udf_arrow(s, d):
    return small(s, d).select("p_partkey", F.udf(lambda x: x * 2, "int", useArrow=True)("p_size").alias("y"))


@op("pandas_udf", DOUBLE)
def op_pandas_udf(s, d):
    @F.pandas_udf("int")
    def twice(x: pd.Series) -> pd.Series:
        return x * 2

    return small(s, d).select("p_partkey", twice("p_size").alias("y"))


@op("pandas_udaf", "SELECT p_brand, max(p_size) - min(p_size) AS spread FROM part GROUP BY 1")
def op_pandas_udaf(s, d):
    @F.pandas_udf("int")
    def spread(x: pd.Series) -> int:
        return int(x.max() - x.min())

    return small(s, d).groupBy("p_brand").agg(spread("p_size").alias("spread"))


@op("apply_in_pandas", "SELECT p_brand, count(*) AS n FROM part GROUP BY 1")
def op_apply_in_pandas(s, d):
    return small(s, d).groupBy("p_brand").applyInPandas(lambda p: pd.DataFrame({"p_brand": [p["p_brand"].iloc[0]], "n": [len(p)]}), "p_brand string, n long")


@op("cogroup", "SELECT k, count(*) FILTER (side = 'a') AS before, count(*) FILTER (side = 'b') AS after FROM (SELECT o_custkey AS k, 'a' AS side FROM orders UNION ALL SELECT o_custkey, 'b' FROM orders WHERE o_orderstatus = 'F') GROUP BY 1")
def op_cogroup(s, d):
    """Snapshots before and after, entity by entity."""
    rows = load(s, d, "orders").select(F.col("o_custkey").alias("k"), "o_orderstatus")
    both = lambda key, a, b: pd.DataFrame({"k": [key[0]], "before": [len(a)], "after": [len(b)]})
    return rows.groupBy("k").cogroup(rows.filter("o_orderstatus = 'F'").groupBy("k")).applyInPandas(both, "k long, before long, after long")


@op("map_in_pandas", DOUBLE)
def op_map_in_pandas(s, d):
    def run(batches):
        for b in batches:
            yield pd.DataFrame({"p_partkey": b["p_partkey"], "y": b["p_size"] * 2})

    return small(s, d).select("p_partkey", "p_size").mapInPandas(run, "p_partkey long, y int")


@op("map_in_arrow", DOUBLE)
def op_map_in_arrow(s, d):
    def run(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(b.column(1).to_numpy() * 2, pa.int32())], names=["p_partkey", "y"])

    return small(s, d).select("p_partkey", "p_size").mapInArrow(run, "p_partkey long, y int")


@op("udtf", "SELECT k AS n, k * k AS square FROM range(5) r(k)")
def op_udtf(s, d):
    @F.udtf(returnType="n: bigint, square: bigint")
    class Squares:
        def eval(self, upto: int):
            for k in range(upto):
                yield k, k * k

    return Squares(F.lit(5))


@op("delta_digest_by_arm", "SELECT arm, count(*) AS n FROM (SELECT unnest(['unpatched', 'patched']) AS arm FROM region) GROUP BY 1")
def delta_digest_by_arm(s, d) -> DataFrame:
    """Arms as rows: a two-row broadcast instead of two jobs."""
    arms = reduce(DataFrame.union, [s.range(1).select(F.lit(a).alias("arm")) for a in ("unpatched", "patched")])
    return load(s, d, "region").crossJoin(F.broadcast(arms)).groupBy("arm").agg(F.count("*").alias("n"))
