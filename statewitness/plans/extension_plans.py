"""Our extensions beside the paper's methods: recorded-call probes, frames with an excepted key, table functions."""

from __future__ import annotations

from pyspark.sql import functions as F

from statewitness.functions.state import changed_cells
from statewitness.operators import trace
from statewitness.operators.contract import clause_name, is_draft
from statewitness.plans.base import workload
from statewitness.plans.conformance_plans import charged
from statewitness.plans.trace_plans import EVALUATOR_NAMES, KNOWN_PATHS
from statewitness.sources import code
from statewitness.sources.tables import load


@workload("probe_recorded", "SELECT l_returnflag AS op, count(DISTINCT (l_quantity, l_discount, l_tax)) AS probes FROM lineitem GROUP BY 1")
def probe_recorded(spark, d):
    """Probes from recorded calls instead of the snapshot: every distinct argument set that was really used."""
    calls = load(spark, d, "lineitem").select(F.col("l_returnflag").alias("op"), F.to_json(F.struct("l_quantity", "l_discount", "l_tax")).alias("args"))
    return calls.distinct().groupBy("op").agg(F.count("*").alias("probes"))


@workload("frame_except_key", "SELECT count(*) AS changed, count(*) FILTER (o_orderkey % 7 <> 0) AS outside FROM orders WHERE o_orderstatus = 'F' AND o_orderkey % 7 = 0")
def frame_except_key(spark, d):
    """A frame that excepts the call's own keys: no cell of another record changed."""
    before, after = charged(spark, d)
    cells = changed_cells(before, after, "o_orderkey")
    named = before.filter("o_orderkey % 7 = 0").select(F.col("o_orderkey").alias("key"), F.lit(True).alias("named"))
    rows = cells.join(named, "key", "left")
    return rows.agg(F.count("*").alias("changed"), F.count_if(F.col("named").isNull()).alias("outside"))


@workload("grader_ungrounded", "SELECT evaluator, evaluator = 'told_so' AS ungrounded, count(*) AS tasks, count(DISTINCT o_custkey) AS customers FROM orders JOIN (VALUES (0,'by_constant'),(1,'collection_only'),(2,'computed'),(3,'exact_status'),(4,'through_helpers'),(5,'told_so'),(6,'too_deep')) e(k, evaluator) ON k = o_orderkey % 7 GROUP BY 1, 2")
def grader_ungrounded(spark, d):
    """Graders that read nothing but what the agent was told (a property of the evaluator, not a seventh class), and the orders that they grade."""
    sites = trace.read_sites(code.nodes(code.source_rows(spark, code.EVALUATOR_SOURCES)), EVALUATOR_NAMES, KNOWN_PATHS)
    graders = sites.groupBy("evaluator").agg(F.bool_and(F.col("target") == trace.TRANSCRIPT).alias("ungrounded"))
    names = spark.createDataFrame(list(enumerate(sorted(EVALUATOR_NAMES))), "k long, evaluator string")
    tasks = load(spark, d, "orders").select((F.col("o_orderkey") % 7).alias("k"), "o_custkey").groupBy("k").agg(F.count("*").alias("tasks"), F.countDistinct("o_custkey").alias("customers"))
    return tasks.join(names, "k").join(graders, "evaluator").select("evaluator", "ungrounded", "tasks", "customers")


@workload("contract_drafts", "SELECT tool, count(*) FILTER (NOT filled) AS drafts, count(*) FILTER (filled) AS counted FROM (SELECT o_orderpriority AS tool, bool_or(o_orderstatus = 'F') AS filled FROM orders GROUP BY o_orderpriority, o_custkey) GROUP BY 1")
def contract_drafts(spark, d):
    """Drafted clauses are placeholders: they are listed and stay out of every count.

    A priority is a tool with an effect for each of its customers, drafted until one of their orders is filled.
    """
    orders = load(spark, d, "orders").groupBy(F.col("o_orderpriority").alias("tool"), "o_custkey").agg(F.bool_or(F.col("o_orderstatus") == "F").alias("filled"))
    rows = orders.select("tool", clause_name("eff", F.col("o_custkey"), ~F.col("filled")).alias("clause_id"))
    return rows.groupBy("tool").agg(F.count_if(is_draft(F.col("clause_id"))).alias("drafts"), F.count_if(~is_draft(F.col("clause_id"))).alias("counted"))


@workload("op_udtf_table_arg", "SELECT p_brand AS brand, count(*) AS n FROM part GROUP BY 1")
def op_udtf_table_arg(spark, d):
    """A table function over a partitioned table argument."""

    class CountRows:
        def __init__(self):
            self.brand, self.n = None, 0

        def eval(self, row):
            self.brand = row["p_brand"]
            self.n += 1

        def terminate(self):
            if self.n:
                yield self.brand, self.n

    spark.udtf.register("count_rows", F.udtf(CountRows, returnType="brand: string, n: bigint"))
    load(spark, d, "part").select("p_brand").createOrReplaceTempView("udtf_part")
    return spark.sql("SELECT brand, n FROM count_rows(TABLE(udtf_part) PARTITION BY p_brand)")
