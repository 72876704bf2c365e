"""Score at risk: from violated clauses to fields, evaluators and tasks; oracle grounding."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# How an evaluator reads a field, and how a grader decides.
EXACT, COLLECTION, WHOLE, FORCED = "attr", "collection", "whole_digest", "forced"
STATE, TRANSCRIPT, MIXED, NONE = "state", "transcript", "mixed", "none"
UNDEFINED, NOT_COMPUTABLE, UNTRACED, COUNTED = "undefined", "not_computable", "untraced", "counted"
MAX_HOPS = 3


def fields(violations: DataFrame, clauses: DataFrame, source: str = "compiled") -> DataFrame:
    """(tool, clause_id, path, direction): what a violated clause says was or was not written.

    ``compiled`` takes the paths the compiler recorded; the baseline ``string`` picks them from the text,
    where quoted words look like paths too.
    """
    rows = violations.select("tool", "clause_id").distinct().join(F.broadcast(clauses.select("tool", "clause_id", "kind", "predicate", "paths")), ["tool", "clause_id"])
    if source == "string":
        path = F.explode(F.regexp_extract_all("predicate", F.lit(r"([A-Za-z_]+\.[A-Za-z_.]+)"), F.lit(1)))
    else:
        path = F.explode("paths")
    rows = rows.select("tool", "clause_id", "kind", path.alias("path")).filter("path LIKE 'pre.%' OR path LIKE 'post.%'" if source == "compiled" else "true")
    direction = F.when(F.col("kind") == "pre", "written_despite_guard").otherwise("not_written")
    return rows.select("tool", "clause_id", F.regexp_replace("path", r"^(pre|post)\.", "").alias("path"), direction.alias("direction")).distinct()


def read_facts(nodes: DataFrame, known: list[str]) -> DataFrame:
    """(func, kind, value) from evaluator syntax: state or transcript reads, path constants, calls, unresolved."""
    top = F.substring_index("name", ".", 1)
    attr = nodes.filter((F.col("kind") == "attribute") & top.isin("state", "transcript", "pre", "post"))
    longest = attr.select("func", F.when(top == "transcript", TRANSCRIPT).otherwise(STATE).alias("kind"), F.regexp_replace("name", r"^(state|pre|post|transcript)\.", "").alias("value"))
    constants = nodes.filter((F.col("kind") == "constant") & F.col("text").isin(*known)).select("func", F.lit(STATE).alias("kind"), F.col("text").alias("value"))
    calls = nodes.filter("kind = 'call' AND name NOT IN ('len', 'getattr', 'lookup')").select("func", F.lit("call").alias("kind"), F.col("name").alias("value"))
    computed = nodes.filter("kind = 'call' AND name = 'getattr'").select("func", F.lit("computed").alias("kind"), F.col("name").alias("value"))
    return reduce(DataFrame.union, [longest, constants, calls, computed]).distinct()


def read_sites(nodes: DataFrame, evaluators: list[str], known: list[str], max_hops: int = MAX_HOPS) -> DataFrame:
    """(evaluator, path, target, resolved, hops): helpers called by bare name are followed ``max_hops`` deep.

    What can't be resolved (computed access, deeper or unknown helpers) is a row with a null path.
    """
    facts = read_facts(nodes, known)
    calls = facts.filter("kind = 'call'").select(F.col("func").alias("caller"), F.col("value").alias("callee"))
    roots = nodes.filter((F.col("kind") == "function") & F.col("func").isin(*evaluators)).select(F.col("func").alias("evaluator"), F.col("func"))
    level, reached = roots.withColumn("hops", F.lit(0)), []
    for hop in range(max_hops + 1):
        reached.append(level)
        if hop < max_hops:
            level = level.join(calls, level["func"] == calls["caller"]).select("evaluator", F.col("callee").alias("func"), F.lit(hop + 1).alias("hops"))
    walked = reduce(DataFrame.union, reached).groupBy("evaluator", "func").agg(F.min("hops").alias("hops"))
    reads = walked.join(facts.filter(F.col("kind").isin(STATE, TRANSCRIPT)), "func").select("evaluator", F.col("value").alias("path"), F.col("kind").alias("target"), F.lit(True).alias("resolved"), "hops")
    defined = nodes.filter("kind = 'function'").select(F.col("func").alias("callee")).distinct()
    computed = walked.join(facts.filter("kind = 'computed'"), "func").select("evaluator", "hops")
    deeper = walked.filter(F.col("hops") == max_hops).join(calls, F.col("func") == F.col("caller")).select("evaluator", (F.col("hops") + 1).alias("hops"))
    unknown = walked.join(calls, F.col("func") == F.col("caller")).join(defined, "callee", "left_anti").select("evaluator", (F.col("hops") + 1).alias("hops"))
    open_ = computed.union(deeper).union(unknown).groupBy("evaluator").agg(F.min("hops").alias("hops"))
    return reads.union(open_.select("evaluator", F.lit(None).cast("string").alias("path"), F.lit(STATE).alias("target"), F.lit(False).alias("resolved"), "hops"))


def basis(site: Column, field: Column, resolved: Column, whole: Column) -> Column:
    """How a read site meets a field: the attribute itself, its collection only, the whole state, or by force."""
    return F.when(~resolved, FORCED).when(whole, WHOLE).when(site == field, EXACT).when(field.startswith(F.concat(site, F.lit("."))), COLLECTION)


def exposure(tasks: DataFrame, sites: DataFrame, found: DataFrame, rule: str = "path") -> DataFrame:
    """(task_id, tool, basis): every task whose evaluator reads a field of a defect; sites and fields are broadcast.

    ``names_only`` is the baseline that matches the last name of a path and ignores what is read.
    """
    if rule == "names_only":
        last = lambda c: F.element_at(F.split(c, r"\."), -1)
        hits = sites.crossJoin(found).filter(F.col("site_path").isNull() | F.col("whole") | (last("site_path") == last("path")) | F.col("path").startswith(F.col("site_path"))).select("evaluator", "tool", F.lit("name").alias("basis")).distinct()
    else:
        kind = basis(F.col("site_path"), F.col("path"), F.col("resolved"), F.col("whole"))
        hits = sites.filter(F.col("target") == STATE).crossJoin(found).withColumn("basis", kind).filter("basis IS NOT NULL").select("evaluator", "tool", "basis").distinct()
    return tasks.join(F.broadcast(hits), "evaluator").select("task_id", "tool", "basis")


def grounding(per_case: DataFrame, group: str) -> DataFrame:
    """State, transcript, mixed or no oracle; exposure is undefined where state is not what is graded."""
    rows = per_case.groupBy(group).agg(F.bool_or(F.col("target") == STATE).alias("s"), F.bool_or(F.col("target") == TRANSCRIPT).alias("t"))
    kind = F.when(F.col("s") & F.col("t"), MIXED).when(F.col("s"), STATE).when(F.col("t"), TRANSCRIPT).otherwise(NONE)
    return rows.select(group, kind.alias("grounding"), F.when(kind == STATE, COUNTED).otherwise(UNDEFINED).alias("status"))
