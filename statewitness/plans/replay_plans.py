"""Gold replay, constructed controls, graders, sequences and reach."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from statewitness.functions.state import table_digest
from statewitness.operators import replay as R
from statewitness.plans.base import workload
from statewitness.sources.tables import load

CHARGED = "SELECT DISTINCT l_orderkey AS task_id FROM lineitem WHERE l_returnflag = 'A'"
TASKS = f"SELECT o_orderkey AS task_id, o_orderstatus AS status, o_orderpriority IN ('3-MEDIUM', '4-NOT SPECIFIED', '5-LOW') AS user_side FROM orders JOIN ({CHARGED}) ON o_orderkey = task_id"
CONFORMING = f"SELECT * FROM ({TASKS}) WHERE status = 'O'"


def tasks(spark, d, conforming: bool) -> DataFrame:
    rows = load(spark, d, "orders").select(F.col("o_orderkey").alias("task_id"), F.col("o_orderstatus").alias("status"), F.col("o_orderpriority").isin("3-MEDIUM", "4-NOT SPECIFIED", "5-LOW").alias("user_side"))
    return rows.filter("status = 'O'") if conforming else rows


def lines(spark, d) -> DataFrame:
    return load(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_shipdate", "l_partkey", "l_suppkey", "l_returnflag")


def runs(spark, d, constructions: list[str], conforming: bool = True) -> DataFrame:
    charges = R.gold_charge(R.gold_actions(lines(spark, d)))
    paths = reduce(DataFrame.union, [R.build(charges, c) for c in constructions])
    return R.graded(R.run(paths, tasks(spark, d, conforming)))


@workload("gold_replay_null", f"SELECT arm, count(*) AS tasks, 0::BIGINT AS reaching, count(*) AS shipped_pass, 0::BIGINT AS changed FROM ({CONFORMING}), (VALUES ('unpatched'), ('patched')) a(arm) GROUP BY arm")
def gold_replay_null(spark, d):
    """Gold paths on open orders: nothing reaches the missing guard and no verdict changes, in all tasks."""
    rows = runs(spark, d, ["gold"])
    m = R.margins(rows).select("verdict_changed")
    per = rows.groupBy("arm").agg(F.count("*").alias("tasks"), F.count_if("reached").alias("reaching"), F.count_if("shipped").alias("shipped_pass"))
    return per.crossJoin(F.broadcast(m)).withColumnRenamed("verdict_changed", "changed")


@workload("gold_replay_seeded", f"SELECT task_id, status FROM ({CONFORMING}) ORDER BY md5(task_id || '|1'), task_id LIMIT 5")
def gold_replay_seeded(spark, d):
    """The seeded sample of five gold tasks (the sample is the feature)."""
    charges = R.gold_charge(R.gold_actions(lines(spark, d)))
    rows = tasks(spark, d, True).join(charges, "task_id", "left_semi").select("task_id", "status")
    return R.seeded(rows, "task_id", 5, 1)


@workload("gold_replay_natural", f"SELECT count(*) AS tasks, count(*) FILTER (status <> 'O') AS reaching FROM ({TASKS})")
def gold_replay_natural(spark, d):
    """Gold paths on all orders: charges that meet an order that is not open."""
    rows = runs(spark, d, ["gold"], conforming=False).filter("arm = 'unpatched'")
    return rows.agg(F.count("*").alias("tasks"), F.count_if("reached").alias("reaching"))


def control_sql(name: str, passes: str) -> str:
    return f"SELECT '{name}' AS construction, count(*) AS tasks, {passes}::BIGINT AS shipped_u, 0::BIGINT AS shipped_p, count(*) AS state_changed, {passes}::BIGINT AS verdict_changed FROM ({CONFORMING})"


@workload("control_hold_before", control_sql("hold_before", "count(*) FILTER (NOT user_side)"))
def control_hold_before(spark, d):
    """A hold before the charge: only tasks without a user-side assertion pass unpatched (the confound)."""
    return R.margins(runs(spark, d, ["hold_before"]))


@workload("control_hold_release", control_sql("hold_release", "count(*)"))
def control_hold_release(spark, d):
    """A hold before and a release after: every shipped verdict changes between arms."""
    return R.margins(runs(spark, d, ["hold_release"]))


@workload("control_margins", f"""SELECT construction, arm, shipped, independent, count(*) AS tasks FROM (
SELECT construction, arm, arm = 'unpatched' AND (construction = 'hold_release' OR NOT user_side) AS shipped, arm = 'patched' AS independent FROM ({CONFORMING}), (VALUES ('hold_before'), ('hold_release')) c(construction), (VALUES ('unpatched'), ('patched')) a(arm)) GROUP BY ALL""")
def control_margins(spark, d):
    """Shipped against independent verdicts by construction and arm."""
    return runs(spark, d, ["hold_before", "hold_release"]).groupBy("construction", "arm", "shipped", "independent").agg(F.count("*").alias("tasks"))


@workload("control_rows", f"SELECT (2 * 2 * count(*))::BIGINT AS n_rows FROM ({CONFORMING})")
def control_rows(spark, d):
    """Tasks x constructions x arms."""
    return runs(spark, d, ["hold_before", "hold_release"]).agg(F.count("*").alias("n_rows"))


BOOKED = "SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1"


def book_cancel(spark, d) -> DataFrame:
    """Book then cancel, for each customer: infeasible beyond 20 orders; stock comes back in the patched arm alone."""
    held = load(spark, d, "orders").groupBy(F.col("o_custkey").alias("task_id")).agg(F.count("*").alias("n"))
    arms = spark.createDataFrame([(a,) for a in R.ARMS], "arm string")
    return held.crossJoin(F.broadcast(arms)).select("task_id", "arm", (F.col("n") <= 20).alias("feasible"), F.when(F.col("arm") == "patched", 0).otherwise(-1).alias("stock_change"))


@workload("control_book_cancel", f"SELECT arm, count(*) FILTER (n <= 20) AS tasks, count(*) AS all_tasks, 0::BIGINT AS shipped_pass, count(*) FILTER (n <= 20 AND arm = 'patched') AS independent_pass, count(*) FILTER (n <= 20 AND arm = 'unpatched') AS stock_changed FROM ({BOOKED}), (VALUES ('unpatched'), ('patched')) a(arm) GROUP BY arm")
def control_book_cancel(spark, d):
    """The whole-database hash differs from gold on both arms, so no shipped verdict changes."""
    rows = book_cancel(spark, d)
    ok = F.col("feasible")
    whole_hash_equal = F.lit(False)  # the path itself is not in the gold run
    return rows.groupBy("arm").agg(F.count_if(ok).alias("tasks"), F.count("*").alias("all_tasks"), F.count_if(ok & whole_hash_equal).alias("shipped_pass"), F.count_if(ok & (F.col("stock_change") == 0)).alias("independent_pass"), F.count_if(ok & (F.col("stock_change") != 0)).alias("stock_changed"))


@workload("controls_feasible", f"SELECT n <= 20 AS feasible, count(*) AS tasks FROM ({BOOKED}) GROUP BY 1")
def controls_feasible(spark, d):
    return book_cancel(spark, d).filter("arm = 'patched'").groupBy("feasible").agg(F.count("*").alias("tasks"))


@workload("grader_whole_hash", f"WITH g AS (SELECT sum(('0x' || substr(md5(concat_ws('|', o_orderkey, o_orderstatus)), 1, 15))::HUGEINT) AS s FROM orders) SELECT construction, arm, construction = 'gold' AS equals_gold FROM g, (VALUES ('gold'), ('hold_before')) c(construction), (VALUES ('unpatched'), ('patched')) a(arm)")
def grader_whole_hash(spark, d):
    """A whole-state hash tells any extra step from gold, defect or not: both arms differ alike."""
    orders = load(spark, d, "orders").select("o_orderkey", "o_orderstatus")
    charges = R.gold_charge(R.gold_actions(lines(spark, d))).select(F.col("task_id").alias("o_orderkey"), F.lit(True).alias("held"))
    gold = table_digest(orders, ["o_orderkey", "o_orderstatus"]).select(F.col("digest").alias("g"))
    held = orders.join(charges, "o_orderkey", "left").select("o_orderkey", F.when(F.col("held"), "H").otherwise(F.col("o_orderstatus")).alias("o_orderstatus"))
    parts = []
    for c, state in (("gold", orders), ("hold_before", held)):
        for arm in R.ARMS:
            parts.append(table_digest(state, ["o_orderkey", "o_orderstatus"]).crossJoin(F.broadcast(gold)).select(F.lit(c).alias("construction"), F.lit(arm).alias("arm"), (F.col("digest") == F.col("g")).alias("equals_gold")))
    return reduce(DataFrame.union, parts)


OPS = "SELECT l_orderkey, string_agg(CASE l_returnflag WHEN 'A' THEN 'charge' WHEN 'R' THEN 'cancel' ELSE 'revise' END, ',' ORDER BY l_linenumber, l_shipdate, l_partkey, l_suppkey) AS ops FROM lineitem GROUP BY 1"


@workload("action_sequences", f"SELECT count(*) AS sequences, max(tasks)::BIGINT AS largest, sum(tasks)::BIGINT AS tasks FROM (SELECT ops, count(*) AS tasks FROM ({OPS}) GROUP BY 1)")
def action_sequences(spark, d):
    return R.sequences(R.gold_actions(lines(spark, d))).agg(F.count("*").alias("sequences"), F.max("tasks").alias("largest"), F.sum("tasks").alias("tasks"))


REACH = "SELECT event_type, last_value(CASE WHEN event_type IN ('error', 'signup') THEN event_type END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS held FROM events"


@workload("event_reach", f"SELECT count(*) AS purchases, count(*) FILTER (held = 'error') AS reaching FROM ({REACH}) WHERE event_type = 'purchase'")
def event_reach(spark, d):
    """Purchases while the user is held: real reach, without a constructed path."""
    rows = load(spark, d, "events").select("user_id", "ts", "event_id", "event_type")
    rows = rows.withColumn("held", R.held_while_buying(rows)).filter("event_type = 'purchase'")
    return rows.agg(F.count("*").alias("purchases"), F.count_if("held").alias("reaching"))


@workload("action_success_vs_written", "SELECT role, count(*) AS calls, count(*) FILTER (length(text) > 100) AS accepted, 0::BIGINT AS written FROM conversations GROUP BY role")
def action_success_vs_written(spark, d):
    """A success rate over payloads says nothing about writes: acceptance is counted, no row is written."""
    rows = load(spark, d, "conversations").select("conv_id", "turn", "role", (F.length("text") > 100).alias("accepted"))
    written = rows.filter("false").select("conv_id", "turn", F.lit(1).alias("w"))
    return rows.join(written, ["conv_id", "turn"], "left").groupBy("role").agg(F.count("*").alias("calls"), F.count_if("accepted").alias("accepted"), F.count("w").alias("written"))


@workload("grader_repaired", "SELECT arm, count(*) AS tasks, count(*) AS told_pass, count(*) FILTER (arm = 'patched') AS read_back_pass FROM (SELECT DISTINCT user_id FROM events), (VALUES ('unpatched'), ('patched')) a(arm) GROUP BY arm")
def grader_repaired(spark, d):
    """A grader that believes the message passes both arms; one that reads the record back, the patched alone."""
    from statewitness.operators import conformance as C
    from statewitness.operators.desk import TOOLS

    tool = TOOLS["post_event"]
    calls = C.invoke(tool, C.probe_rows(tool, tool.slice(spark, d))).filter("purpose = 'happy'")
    return calls.groupBy("arm").agg(F.count("*").alias("tasks"), F.count_if(F.col("message").contains("accepted")).alias("told_pass"), F.count_if(F.col("post.n_events") == F.col("pre.n_events") + 1).alias("read_back_pass"))


@workload("patch_verified", "SELECT 'charge_order' AS tool, count(DISTINCT o_custkey) AS triggers, 0::BIGINT AS unpatched_errors, count(DISTINCT o_custkey) AS patched_errors FROM orders WHERE o_orderstatus <> 'O' UNION ALL SELECT 'cancel_order', (SELECT count(DISTINCT l_orderkey) FROM lineitem), (SELECT count(DISTINCT l_orderkey) FROM lineitem), 0")
def patch_verified(spark, d):
    """One-hunk repairs under the trigger: success becomes an error; stock that was lost comes back."""
    from statewitness.operators import conformance as C
    from statewitness.operators.desk import TOOLS

    charge, cancel = TOOLS["charge_order"], TOOLS["cancel_order"]
    a = C.invoke(charge, C.probe_rows(charge, charge.slice(spark, d))).filter("purpose = 'falsify' AND target = 'pre.open'").select("arm", F.col("error").isNotNull().alias("bad"))
    b = C.invoke(cancel, C.probe_rows(cancel, cancel.slice(spark, d))).filter("purpose = 'happy'").select("arm", (F.col("post.stock") != F.col("pre.stock") + F.col("pre.reserved")).alias("bad"))
    n = lambda arm: F.count_if((F.col("arm") == arm) & F.col("bad"))
    out = [df.agg(F.count_if(F.col("arm") == "patched").alias("triggers"), n("unpatched").alias("unpatched_errors"), n("patched").alias("patched_errors")).select(F.lit(t).alias("tool"), "triggers", "unpatched_errors", "patched_errors") for t, df in (("charge_order", a), ("cancel_order", b))]
    return out[0].union(out[1])
