"""Differential replay: gold and constructed action paths on both arms of the charge tool, and graders.

A path is rows (task_id, seq, op, amount). State before each call is folded with windows over the task:
the last status-setting operation before it, and what the task started with. Actions are dealt out by
task once; arms and constructions multiply rows, not jobs.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from statewitness.operators.conformance import ARMS

AMOUNT = 40
SPREAD = 10


def gold_actions(lines: DataFrame) -> DataFrame:
    """(task_id, seq, op): an order's lines in the order of their key; flags name the operation."""
    w = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_shipdate", "l_partkey", "l_suppkey")
    op = F.when(F.col("l_returnflag") == "A", "charge").when(F.col("l_returnflag") == "R", "cancel").otherwise("revise")
    return lines.select(F.col("l_orderkey").alias("task_id"), (F.row_number().over(w) * SPREAD).alias("seq"), op.alias("op"))


def gold_charge(actions: DataFrame) -> DataFrame:
    """The first charge of each task that has one."""
    return actions.filter("op = 'charge'").groupBy("task_id").agg(F.min("seq").alias("seq")).select("task_id", "seq", F.lit("charge").alias("op"))


def build(charges: DataFrame, construction: str) -> DataFrame:
    """Actions of a construction around the gold charge: ``gold``, ``hold_before`` or ``hold_release``."""
    parts = [charges]
    if construction in ("hold_before", "hold_release"):
        parts.append(charges.select("task_id", (F.col("seq") - 1).alias("seq"), F.lit("hold").alias("op")))
    if construction == "hold_release":
        parts.append(charges.select("task_id", (F.col("seq") + 1).alias("seq"), F.lit("release").alias("op")))
    return reduce(DataFrame.union, parts).withColumn("construction", F.lit(construction))


def run(paths: DataFrame, tasks: DataFrame) -> DataFrame:
    """End state of each (task, construction, arm): charged, end status, whether the call met a shut order.

    ``tasks`` holds (task_id, status, user_side): the starting status, and whether the task's grader also asks
    for an open order at the end.
    """
    arms = paths.sparkSession.createDataFrame([(a,) for a in ARMS], "arm string")
    rows = paths.join(tasks, "task_id").crossJoin(F.broadcast(arms))
    w = Window.partitionBy("task_id", "construction", "arm").orderBy("seq")
    sets = F.when(F.col("op") == "hold", "F").when(F.col("op") == "release", "O")
    before = F.coalesce(F.last(sets, ignorenulls=True).over(w.rowsBetween(Window.unboundedPreceding, -1)), "status")
    rows = rows.withColumn("before", before).withColumn("sets", sets)
    shut = (F.col("op") == "charge") & (F.col("before") != "O")
    done = (F.col("op") == "charge") & ((F.col("arm") == "unpatched") | (F.col("before") == "O"))
    return rows.groupBy("task_id", "construction", "arm", "user_side").agg(
        F.bool_or(done).alias("charged"),
        F.bool_or(shut).alias("reached"),
        F.coalesce(F.max_by("sets", F.when(F.col("sets").isNotNull(), F.col("seq"))), F.first("status")).alias("end_status"),
    )


def graded(runs: DataFrame) -> DataFrame:
    """Shipped verdict (balance, and on some tasks an open order at the end) and the independent one (no call met a shut order)."""
    shipped = F.col("charged") & (~F.col("user_side") | (F.col("end_status") == "O"))
    return runs.withColumn("shipped", shipped).withColumn("independent", ~(F.col("reached") & F.col("charged")))


def margins(rows: DataFrame) -> DataFrame:
    """For each construction: passes by arm, state changed between arms, verdicts changed between arms."""
    pick = lambda arm, c: F.max(F.when(F.col("arm") == arm, F.col(c).cast("int")))
    per = rows.groupBy("task_id", "construction").agg(*[pick(a, c).alias(f"{c}_{a[0]}") for a in ARMS for c in ("shipped", "independent", "charged")])
    yes = lambda c: F.coalesce(F.sum(c), F.lit(0)).alias(c)
    return per.groupBy("construction").agg(
        F.count("*").alias("tasks"), yes("shipped_u"), yes("shipped_p"),
        F.count_if(F.col("charged_u") != F.col("charged_p")).alias("state_changed"),
        F.count_if(F.col("shipped_u") != F.col("shipped_p")).alias("verdict_changed"),
    )


def sequences(actions: DataFrame) -> DataFrame:
    """(digest, tasks) of each distinct operation sequence (a task's list is as long as its order)."""
    listed = F.sort_array(F.collect_list(F.struct("seq", "op")))
    text = F.array_join(F.transform(listed, lambda x: x["op"]), ",")
    return actions.groupBy("task_id").agg(text.alias("ops")).groupBy("ops").agg(F.count("*").alias("tasks"))


def seeded(df: DataFrame, key: str, k: int, seed: int) -> DataFrame:
    """The same k rows whatever the partitioning: smallest hashes of key and seed first."""
    return df.orderBy(F.md5(F.concat_ws("|", F.col(key).cast("string"), F.lit(seed))), key).limit(k)


def held_while_buying(events: DataFrame) -> Column:
    """Whether a purchase comes while the user's last error or signup was an error."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    state = F.last(F.when(F.col("event_type").isin("error", "signup"), F.col("event_type")), ignorenulls=True).over(w)
    return state == "error"
