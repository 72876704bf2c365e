"""Ledgers, units, agreement, scope, coverage, registration and disclosure."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def append_new(ledger: DataFrame, new: DataFrame, keys: list[str]) -> DataFrame:
    """Rows of ``new`` that a ledger lacks: writing them twice changes nothing."""
    return new.join(ledger.select(*keys), keys, "left_anti")


def adjudicated(rows: DataFrame, decisions: DataFrame, key: str) -> DataFrame:
    """A flag or row is a finding only by a recorded decision; without one it is a candidate."""
    out = rows.join(decisions, key, "left")
    return out.withColumn("status", F.when(F.col("decision") == "confirmed", "finding").when(F.col("decision") == "rejected", "rejected").otherwise("candidate"))


def units(rows: DataFrame) -> DataFrame:
    """Clauses, rows, instances, cells and sites by benchmark and class, with totals (a copied helper counts once)."""
    return rows.rollup("benchmark", "class").agg(
        F.count("*").alias("n_rows"), F.countDistinct("tool", "class").alias("instances"), F.countDistinct("benchmark", "class").alias("cells"), F.countDistinct("site").alias("sites"), F.grouping_id().alias("level"))


def agreement(a: DataFrame, b: DataFrame, keys: list[str], only_successful: bool = False) -> DataFrame:
    """(stratum, pairs, agreeing) of two annotators' verdicts on one probe corpus.

    Untestable against anything is a disagreement. ``only_successful`` keeps comparable pairs alone.
    """
    both = a.withColumnRenamed("verdict", "va").join(b.withColumnRenamed("verdict", "vb").drop("call_ok", "stratum"), keys)
    if only_successful:
        both = both.filter("call_ok")
    same = (F.col("va") == F.col("vb")) & (F.col("va") != "untestable")
    return both.groupBy("stratum").agg(F.count("*").alias("pairs"), F.count_if(same).alias("agreeing"))


def in_scope(tools: DataFrame, rule: str) -> DataFrame:
    """Tools that change state, by tag, by a write in their code, or by what they advertise."""
    column = {"tag": "tagged", "writes": "writes", "advertised": "advertises"}[rule]
    return tools.filter(F.col(column)).select("tool")


def post_hoc(results: DataFrame, plans: DataFrame) -> DataFrame:
    """Results with the latest plan registered before them; without one the analysis is post hoc."""
    hit = results.join(plans, "item", "left").filter("registered_ts IS NULL OR registered_ts < result_ts")
    latest = hit.groupBy("item", "result_ts").agg(F.max_by("plan_id", "registered_ts").alias("plan_id"))
    return results.join(latest, ["item", "result_ts"], "left").select("item", "result_ts", "plan_id", F.col("plan_id").isNull().alias("post_hoc"))


def latest_status(log: DataFrame, order: str = "day") -> DataFrame:
    """Disclosure: the last entry of each finding (by ``order``); silence is dated, never read as consent."""
    return log.groupBy("finding").agg(F.max_by("status", order).alias("status"), F.max("day").alias("day"), F.count("*").alias("entries"))


def audit_claims(claims: DataFrame, ledger: DataFrame) -> DataFrame:
    """Every stated number against the one that the ledgers give."""
    return claims.join(ledger, "name", "left").select("name", "stated", "found", F.coalesce(F.col("stated") == F.col("found"), F.lit(False)).alias("holds"))
