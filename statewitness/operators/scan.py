"""The static half: five checks (and one for parameters never read) on syntax nodes; candidates only."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from statewitness.operators import conformance as C
from statewitness.sources.code import FALSY_TYPES

# The class that each check hints at.
HINTS = {"literal_success": C.PHANTOM, "dead_guard": C.UNENFORCED, "cosmetic_param": C.IGNORED, "unread_param": C.IGNORED, "truthy_guard": C.IGNORED, "verb_pair": C.PARTIAL}


def _flags(rows: DataFrame, check: str) -> DataFrame:
    return rows.select("file", "func", F.col("lineno").cast("int").alias("lineno"), F.lit(check).alias("check"), F.lit(HINTS[check]).alias("class_hint"))


def literal_success(nodes: DataFrame) -> DataFrame:
    """A function that writes state and returns a constant text."""
    writers = nodes.filter("kind = 'write'").select("file", "func").distinct()
    returns = nodes.filter("kind = 'return' AND role = 'constant'")
    return _flags(returns.join(writers, ["file", "func"], "left_semi"), "literal_success")


def dead_guard(nodes: DataFrame, lines: DataFrame) -> DataFrame:
    """A commented-out condition inside a function's span (a range join bounded by the file)."""
    spans = nodes.filter("kind = 'function'").select("file", "func", F.col("lineno").alias("lo")).join(nodes.filter("kind = 'end'").select("file", "func", F.col("lineno").alias("hi")), ["file", "func"])
    dead = lines.filter(F.col("text").rlike(r"^\s*#.*\bif\b")).select("file", F.col("line").alias("lineno"))
    return _flags(dead.join(spans, "file").filter("lineno BETWEEN lo AND hi"), "dead_guard")


def parameter_uses(nodes: DataFrame) -> DataFrame:
    """(file, func, name, lineno, reads, cosmetic) of each parameter but the environment's own."""
    params = nodes.filter("kind = 'param' AND name NOT IN ('state', 'transcript')").select("file", "func", "name", "lineno", "text")
    reads = nodes.filter("kind = 'read'").groupBy("file", "func", "name").agg(F.count("*").alias("reads"), F.bool_and(F.col("role").isin("log", "returned_fstring")).alias("cosmetic"))
    return params.join(reads, ["file", "func", "name"], "left")


def cosmetic_param(nodes: DataFrame) -> DataFrame:
    return _flags(parameter_uses(nodes).filter("cosmetic"), "cosmetic_param")


def unread_param(nodes: DataFrame) -> DataFrame:
    return _flags(parameter_uses(nodes).filter("reads IS NULL"), "unread_param")


def truthy_guard(nodes: DataFrame) -> DataFrame:
    """A truth test on a parameter whose type has a meaningful falsy value."""
    params = nodes.filter((F.col("kind") == "param") & F.col("text").isin(*FALSY_TYPES)).select("file", "func", "name")
    return _flags(nodes.filter("kind = 'test' AND role = 'truth'").join(params, ["file", "func", "name"], "left_semi"), "truthy_guard")


def verb_pair(nodes: DataFrame, pairs: DataFrame) -> DataFrame:
    """Do/undo pairs whose undo side never names a field that the do side writes."""
    written = nodes.filter("kind = 'write'").select(F.col("func").alias("do"), F.col("name").alias("field")).distinct()
    named = nodes.filter("kind IN ('write', 'field')").select(F.col("func").alias("undo"), F.col("name").alias("field")).distinct()
    missing = pairs.join(written, "do").join(named, ["undo", "field"], "left_anti").select("undo").distinct()
    return _flags(nodes.filter("kind = 'function'").join(missing, F.col("func") == F.col("undo")), "verb_pair")


def scan(nodes: DataFrame, lines: DataFrame, pairs: DataFrame) -> DataFrame:
    """All flags: (file, func, lineno, check, class_hint)."""
    return reduce(DataFrame.unionByName, [literal_success(nodes), dead_guard(nodes, lines), cosmetic_param(nodes), unread_param(nodes), truthy_guard(nodes), verb_pair(nodes, pairs)])


def score(flags: DataFrame, sites: DataFrame, outside: list[str], scope: str = "population") -> DataFrame:
    """Counts by outcome: a flag is true only at a confirmed site; every other flag is false, none is dropped."""
    seen = flags if scope == "whole_file" else flags.filter(~F.col("func").isin(*outside))
    hit = seen.join(F.broadcast(sites.withColumn("site", F.lit(True))), ["file", "func", "check"], "left")
    found = hit.filter("site").select("file", "func", "check").distinct()
    counts = hit.agg(F.count("*").alias("flags"), F.count_if("site").alias("true_flags"), F.count_if(F.col("site").isNull()).alias("false_flags"))
    return counts.crossJoin(found.agg(F.count("*").alias("sites_found"))).crossJoin(sites.agg(F.count("*").alias("sites")))
