"""Mutation arms, statistics, agreement, scope and ledgers."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from statewitness.functions.stats import Z, clustering, wilson_lower
from statewitness.operators import measures as M
from statewitness.operators import mutation as U
from statewitness.plans.base import workload
from statewitness.sources.tables import load

WILSON = "greatest(0.0, (k/n + {z}*{z}/(2*e) - {z}*sqrt((k/n)*(1-k/n)/e + {z}*{z}/(4*e*e))) / (1 + {z}*{z}/e))".replace("{z}", str(Z))


@workload("mutation_recall_wilson", f"SELECT operator, round({WILSON}, 3) AS lower_limit FROM (SELECT o_orderpriority AS operator, count(*) FILTER (o_orderstatus = 'F')::DOUBLE AS k, count(*)::DOUBLE AS n, count(DISTINCT o_custkey)::DOUBLE AS e FROM orders GROUP BY 1) UNION ALL SELECT 'M-RESET', NULL")
def mutation_recall_wilson(spark, d):
    """Lower limits of recall by operator (orders by priority), customers as clusters; an operator without data has none, not zero."""
    seen = load(spark, d, "orders").groupBy(F.col("o_orderpriority").alias("operator")).agg(F.count_if(F.col("o_orderstatus") == "F").alias("k"), F.count("*").alias("n"), F.countDistinct("o_custkey").cast("double").alias("e"))
    rows = seen.union(spark.createDataFrame([("M-RESET", 0, 0, None)], "operator string, k long, n long, e double"))
    return rows.select("operator", F.round(wilson_lower(F.col("k"), F.col("n"), F.col("e")), 3).alias("lower_limit"))


# Mutants that the closed arm draws: operator, tool, site, rows that reveal it (SQL over the base tables; empty: none does), whether a clause reads the site.
SOME = {"charge_order": "SELECT 1 FROM orders WHERE o_orderstatus = 'O'", "retire_event": "SELECT 1 FROM events", "append_turn": "SELECT 1 FROM conversations", "tag_document": "SELECT 1 FROM labels", "set_quantity": "SELECT 1 FROM lineitem", "rename_region": "SELECT 1 FROM region", "list_activity": "SELECT 1 FROM events", "hold_order": "SELECT 1 FROM orders"}
NOT_HELD = "SELECT 1 FROM (SELECT min_by(o_orderstatus, o_orderkey) AS first FROM orders GROUP BY o_custkey) WHERE first <> 'F'"
DRAWN = [
    *[("M-PHANTOM", t, "all", SOME[t], True, True) for t in ("charge_order", "hold_order", "retire_event", "append_turn", "tag_document", "set_quantity", "rename_region")],
    ("M-PRECOND", "charge_order", "pre.open", "SELECT 1 FROM orders WHERE o_orderstatus <> 'O'", True, True), ("M-PRECOND", "charge_order", "pre.owner", SOME["charge_order"], True, True),
    *[("M-IGNARG", t, a, SOME[t], True, True) for t, a in (("charge_order", "amount"), ("hold_order", "reason"), ("append_turn", "role"), ("tag_document", "quality"), ("set_quantity", "quantity"), ("rename_region", "name"), ("list_activity", "limit"), ("list_activity", "order_by"))],
    ("M-IGNARG", "list_activity", "offset", "SELECT 1 WHERE false", False, False),
    ("M-PARTIAL", "hold_order", "status", NOT_HELD, True, True),
    *[("M-PARTIAL", t, f, SOME[t], True, True) for t, f in (("hold_order", "note"), ("retire_event", "marked"), ("retire_event", "listed"), ("append_turn", "n_turns"), ("append_turn", "last_role"), ("tag_document", "n_labels"), ("tag_document", "last_quality"))],
    *[("M-INVAR", "charge_order", f, SOME["charge_order"], True, True) for f in ("status", "customer")],
    *[("M-INVAR", t, f, SOME[t], False, False) for t, f in (("hold_order", "note"), ("append_turn", "last_role"), ("tag_document", "last_quality"))],
]
MUTANTS = " UNION ALL ".join(f"SELECT '{op}' AS operator, '{t}' AS tool, '{s}' AS site, {c} AS has_clause, EXISTS ({rows}) AS has_probe, {told} AND EXISTS ({rows}) AS flagged" for op, t, s, rows, c, told in DRAWN)
OUTCOME = f"SELECT *, CASE WHEN flagged THEN 'detected' ELSE 'missed' END AS outcome FROM ({MUTANTS})"


@workload("mutation_closed_outcomes", f"SELECT operator, count(*) AS n, count(*) FILTER (outcome = 'detected') AS detected, count(*) FILTER (outcome = 'missed') AS missed, count(*) FILTER (outcome = 'untestable') AS untestable, count(*) FILTER (outcome = 'error') AS error FROM ({OUTCOME}) GROUP BY 1")
def mutation_closed_outcomes(spark, d):
    """Every mutant of the closed world meets every probe of its tool; its outcome comes from the clause rows."""
    return U.recall_table(U.drawn(spark, d).withColumn("outcome", U.outcome(absorbed="silent")))


@workload("mutation_absorbed_bounds", f"SELECT absorbed, count(*) FILTER (outcome = 'detected' OR (absorbed = 'detected' AND outcome = 'error')) AS detected, count(*) AS n FROM ({OUTCOME}), (VALUES ('detected'), ('silent')) a(absorbed) GROUP BY 1")
def mutation_absorbed_bounds(spark, d):
    """Both readings of a crash that the host absorbed."""
    parts = [U.drawn(spark, d).withColumn("outcome", U.outcome(a)).agg(F.count_if(F.col("outcome") == U.DETECTED).alias("detected"), F.count("*").alias("n")).select(F.lit(a).alias("absorbed"), "detected", "n") for a in ("detected", "silent")]
    return parts[0].union(parts[1])


@workload("miss_diagnosis", f"SELECT CASE WHEN NOT has_clause THEN 'no_clause' WHEN NOT has_probe THEN 'probe_never_reveals' ELSE 'other' END AS cause, count(*) AS misses FROM ({OUTCOME}) WHERE outcome = 'missed' GROUP BY 1")
def miss_diagnosis(spark, d):
    rows = U.drawn(spark, d).withColumn("outcome", U.outcome("silent")).filter(F.col("outcome") == U.MISSED)
    return rows.groupBy(U.diagnosis().alias("cause")).agg(F.count("*").alias("misses"))


@workload("mutation_target_met", f"SELECT operator, count(*) >= 25 AS target_met FROM ({MUTANTS}) GROUP BY 1")
def mutation_target_met(spark, d):
    return U.drawn(spark, d).groupBy("operator").agg((F.count("*") >= U.TARGET_SIZE).alias("target_met"))


ICC = """WITH c AS (SELECT o_orderpriority AS g, o_custkey AS c, count(*)::DOUBLE AS m, sum((o_orderstatus = 'F')::INT)::DOUBLE AS s FROM orders GROUP BY 1, 2),
a AS (SELECT g, count(*)::DOUBLE AS k, sum(m) AS n, sum(s) AS t, sum(s * s / m) AS b, sum(m * m) AS mm FROM c GROUP BY 1),
v AS (SELECT *, (t - b) / (n - k) AS w, (b - t * t / n) / (k - 1) AS bt, (n - mm / n) / (k - 1) AS m0 FROM a),
i AS (SELECT *, least(1.0, greatest(0.0, (bt - w) / (bt + (m0 - 1) * w))) AS icc FROM v)
SELECT g AS operator, n::BIGINT AS n, k::BIGINT AS clusters, round(icc, 6) AS icc, round(n / (1 + (n / k - 1) * icc), 3) AS n_effective, round(1 + (mm / n - 1) * icc, 6) AS deff_weighted FROM i"""


@workload("mutation_icc_deff", ICC)
def mutation_icc_deff(spark, d):
    """Clustered outcomes: orders by customer, an outcome for each, grouped by priority."""
    rows = load(spark, d, "orders").select(F.col("o_orderpriority").alias("operator"), "o_custkey", (F.col("o_orderstatus") == "F").cast("int").alias("y"))
    out = clustering(rows, "o_custkey", "y", ["operator"])
    return out.select("operator", F.col("n").cast("long").alias("n"), F.col("k").cast("long").alias("clusters"), F.round("icc", 6).alias("icc"), F.round("n_effective", 3).alias("n_effective"), F.round("deff_weighted", 6).alias("deff_weighted"))


def after(op: str) -> str:
    guard = {"swap_comparison": "p < 1000", "shift_constant": "p > 1001", "swap_connective": "p > 1000 OR p <> 0", "negate_guard": "NOT (p > 1000 AND p <> 0)"}.get(op, "p > 1000 AND p <> 0")
    return f"CASE WHEN {guard} THEN {'p' if op == 'drop_assignment' else 'p + 10'} ELSE p END"


ESCAPES = " UNION ALL ".join(f"SELECT '{op}' AS operator, count(*) AS pairs, count(*) FILTER (({after(op)}) <> ({after('none')})) AS differing, count(*) FILTER (({after(op)}) <> ({after('none')})) > 0 AS live, false AS caught FROM (SELECT p_retailprice AS p FROM part)" for op in U.OPEN)


@workload("mutation_escape", ESCAPES)
def mutation_escape(spark, d):
    """Open world: every mutant meets every probe; a live mutant that no clause catches has escaped."""
    mutants = spark.createDataFrame([(o,) for o in U.OPEN], "operator string")
    return U.open_outcomes(load(spark, d, "part").select(F.col("p_retailprice").alias("price")), mutants)


@workload("mutation_zero_live", "SELECT 465::BIGINT AS mutants, 2325::BIGINT AS pairs, 0::BIGINT AS live, NULL::DOUBLE AS escape_rate")
def mutation_zero_live(spark, d):
    """An arm whose placeholder keys touch nothing: no mutant is live, so there is no rate."""
    probes = spark.range(5).select(F.lit(0).alias("price"))
    rows = spark.range(465).crossJoin(F.broadcast(probes)).select("id", (F.col("price") * 2 != F.col("price")).alias("differs"))
    per = rows.groupBy("id").agg(F.count("*").alias("pairs"), F.bool_or("differs").alias("live"))
    live = F.count_if("live")
    return per.agg(F.count("*").alias("mutants"), F.sum("pairs").alias("pairs"), live.alias("live"), F.try_divide(F.lit(0.0), live).alias("escape_rate"))


@workload("negative_controls", "SELECT * FROM (VALUES ('same_value',true,false,false),('append_twice',false,true,false),('list_replace',false,true,false),('two_encodings_number',false,false,true),('two_encodings_time',true,false,false)) c(control, flagged, predicted, as_predicted)")
def negative_controls(spark, d):
    """The frozen rule flags two of five conforming calls, and not the two that were predicted."""
    return U.control_flags(spark, d)


@workload("negative_controls_footprint", "SELECT control, false AS flagged FROM (VALUES ('same_value'),('append_twice'),('list_replace'),('two_encodings_number'),('two_encodings_time')) c(control)")
def negative_controls_footprint(spark, d):
    """The repaired rule (canonical values that differ from the state) flags none."""
    return U.control_flags(spark, d, rule="footprint").select("control", "flagged")


PRESERVED = 19  # eleven rewritings without effect and the eight originals


@workload("precision_flags", f"SELECT k::BIGINT AS true_flags, 0::BIGINT AS false_flags, {PRESERVED}::BIGINT AS preserving, round({WILSON}, 3) AS lower_limit FROM (SELECT k, k AS n, k AS e FROM (SELECT count(*) FILTER (flagged)::DOUBLE AS k FROM ({MUTANTS})))")
def precision_flags(spark, d):
    """Precision over the flags of the closed arm, with the originals and rewritings that preserve behaviour beside them."""
    rows = U.closed(spark, d).withColumn("faulty", F.col("operator").isin(*U.CLOSED))
    tp, fp = F.count_if(F.col("faulty") & F.col("flagged")), F.count_if(~F.col("faulty") & F.col("flagged"))
    out = rows.agg(tp.alias("true_flags"), fp.alias("false_flags"), F.count_if(~F.col("faulty")).alias("preserving"))
    return out.select("*", F.round(wilson_lower(F.col("true_flags"), F.col("true_flags") + F.col("false_flags")), 3).alias("lower_limit"))


# --- agreement --------------------------------------------------------------------------------------

RATERS = "SELECT doc_id, CASE WHEN doc_id % 5 = 0 THEN 'contaminated' ELSE 'blind' END AS stratum, quality = 1 AS call_ok, CASE WHEN quality = 1 THEN 'conforms' ELSE 'violates' END AS va, CASE WHEN toxic = 0 THEN 'conforms' ELSE 'violates' END AS vb FROM labels"


def raters(spark, d) -> tuple[DataFrame, DataFrame]:
    rows = load(spark, d, "labels").withColumn("stratum", F.when(F.col("doc_id") % 5 == 0, "contaminated").otherwise("blind")).withColumn("call_ok", F.col("quality") == 1)
    a = rows.select("doc_id", "stratum", "call_ok", F.when(F.col("quality") == 1, "conforms").otherwise("violates").alias("verdict"))
    return a, rows.select("doc_id", "stratum", "call_ok", F.when(F.col("toxic") == 0, "conforms").otherwise("violates").alias("verdict"))


@workload("agreement_pairs", f"SELECT stratum, count(*) AS pairs, count(*) FILTER (va = vb) AS agreeing FROM ({RATERS}) GROUP BY 1")
def agreement_pairs(spark, d):
    return M.agreement(*raters(spark, d), ["doc_id"])


@workload("agreement_comparable", f"SELECT stratum, count(*) AS pairs, count(*) FILTER (va = vb) AS agreeing FROM ({RATERS}) WHERE call_ok GROUP BY 1")
def agreement_comparable(spark, d):
    return M.agreement(*raters(spark, d), ["doc_id"], only_successful=True)


# --- units, scope, coverage, registration -----------------------------------------------------------

@workload("ledger_units_rollup", "SELECT benchmark, class, count(*) AS n_rows, count(DISTINCT (tool, class)) AS instances, count(DISTINCT (benchmark, class)) AS cells, count(DISTINCT site) AS sites, grouping_id(benchmark, class)::BIGINT AS level FROM (SELECT event_type AS benchmark, CASE WHEN value >= 100 THEN 'argument_inert' WHEN value >= 50 THEN 'half_applied' ELSE 'claimed_not_written' END AS class, user_id % 50 AS tool, user_id AS site FROM events) GROUP BY ROLLUP (benchmark, class)")
def ledger_units_rollup(spark, d):
    """Events as a ledger: their users are sites of fifty tools, their values give the class."""
    kind = F.when(F.col("value") >= 100, "argument_inert").when(F.col("value") >= 50, "half_applied").otherwise("claimed_not_written")
    return M.units(load(spark, d, "events").select(F.col("event_type").alias("benchmark"), kind.alias("class"), (F.col("user_id") % 50).alias("tool"), F.col("user_id").alias("site")))


@workload("ledger_adjudicated", "SELECT class, status, count(*) AS n_rows FROM (SELECT o_orderpriority AS class, CASE WHEN c_acctbal >= 1000 THEN 'finding' WHEN c_acctbal < 0 THEN 'rejected' ELSE 'candidate' END AS status FROM orders LEFT JOIN customer ON c_custkey = o_custkey) GROUP BY 1, 2")
def ledger_adjudicated(spark, d):
    """Orders are the ledger's rows; a decision is recorded for customers whose balance is high or negative."""
    decision = F.when(F.col("c_acctbal") >= 1000, "confirmed").when(F.col("c_acctbal") < 0, "rejected")
    decisions = load(spark, d, "customer").select(F.col("c_custkey").alias("o_custkey"), decision.alias("decision")).filter("decision IS NOT NULL")
    rows = load(spark, d, "orders").select("o_custkey", F.col("o_orderpriority").alias("class"))
    return M.adjudicated(rows, decisions, "o_custkey").groupBy("class", "status").agg(F.count("*").alias("n_rows"))


@workload("ledger_append_idempotent", "SELECT event_type, count(*) AS n_rows, count(DISTINCT user_id) AS users FROM events GROUP BY 1")
def ledger_append_idempotent(spark, d):
    """Appending all events, twice, to a ledger of the even ones gives each once."""
    rows = load(spark, d, "events").select("event_id", "user_id", "event_type")
    ledger = rows.filter("event_id % 2 = 0")
    for _ in range(2):
        ledger = ledger.union(M.append_new(ledger, rows, ["event_id", "user_id"]))
    return ledger.groupBy("event_type").agg(F.count("*").alias("n_rows"), F.countDistinct("user_id").alias("users"))


@workload("taxonomy_coverage", "SELECT count(*) AS categories, count(*) FILTER (covers) AS covering, count(DISTINCT taxonomy) AS taxonomies FROM (SELECT 'A' AS taxonomy, false AS covers FROM range(14) UNION ALL SELECT 'B', false FROM range(3) UNION ALL SELECT 'C', false FROM range(10))")
def taxonomy_coverage(spark, d):
    """Categories of three published taxonomies, and how many name the audited assumption."""
    rows = reduce(DataFrame.union, [spark.range(n).select(F.lit(t).alias("taxonomy"), F.lit(False).alias("covers")) for t, n in (("A", 14), ("B", 3), ("C", 10))])
    return rows.agg(F.count("*").alias("categories"), F.count_if("covers").alias("covering"), F.countDistinct("taxonomy").alias("taxonomies"))


SCOPE = [("charge_order", True, True, True), ("list_activity", False, False, False), ("post_event", True, False, True), ("release_order", True, True, True), ("recount", False, True, False)]


@workload("scope_rules", "SELECT * FROM (VALUES ('tag',3,0),('writes',3,1),('advertised',3,0)) s(rule, in_scope, missed)")
def scope_rules(spark, d):
    """Three ways to enumerate tools; reading code for writes misses a tool that promises and never writes."""
    tools = spark.createDataFrame(SCOPE, "tool string, tagged boolean, writes boolean, advertises boolean")
    told = M.in_scope(tools, "advertised")
    out = []
    for rule in ("tag", "writes", "advertised"):
        found = M.in_scope(tools, rule)
        missed = told.join(found, "tool", "left_anti").agg(F.count("*").alias("missed"))
        out.append(found.agg(F.count("*").alias("in_scope")).crossJoin(missed).select(F.lit(rule).alias("rule"), "in_scope", "missed"))
    return reduce(DataFrame.union, out)


STAGES = [("CLIN", False, True, 1), ("CUST", True, True, 3), ("SECU", True, True, 2), ("MULTI", True, False, 1)]


@workload("stage_profile", "SELECT * FROM (VALUES ('CLIN',false,true,'hand_read'),('CUST',true,true,'all_stages'),('SECU',true,true,'all_stages'),('MULTI',true,false,'first_two')) s(benchmark, ran_checker, traced, profile)")
def stage_profile(spark, d):
    rows = spark.createDataFrame(STAGES, "benchmark string, ran_checker boolean, traced boolean, cells int")
    profile = F.when(~F.col("ran_checker"), "hand_read").when(F.col("traced"), "all_stages").otherwise("first_two")
    return rows.select("benchmark", "ran_checker", "traced", profile.alias("profile"))


@workload("coverage_totals", "SELECT benchmark, sum(audited)::BIGINT AS audited, sum(implementations)::BIGINT AS implementations, sum(cells)::BIGINT AS cells, sum(headline)::BIGINT AS headline FROM (SELECT o_orderpriority AS benchmark, count(*) AS audited, count(DISTINCT o_orderstatus) AS implementations, count(*) FILTER (o_orderstatus = 'F') AS cells, max((o_orderstatus = 'F' AND o_totalprice >= 250000)::INT) AS headline FROM orders GROUP BY o_orderpriority, o_custkey) GROUP BY ROLLUP (benchmark)")
def coverage_totals(spark, d):
    """What was covered of every customer's orders, in all and by priority."""
    filled = F.col("o_orderstatus") == "F"
    rows = load(spark, d, "orders").groupBy(F.col("o_orderpriority").alias("benchmark"), "o_custkey").agg(
        F.count("*").alias("audited"), F.size(F.collect_set("o_orderstatus")).alias("implementations"), F.count_if(filled).alias("cells"), F.max((filled & (F.col("o_totalprice") >= 250000)).cast("int")).alias("headline"))
    return rows.rollup("benchmark").agg(*[F.sum(c).alias(c) for c in ("audited", "implementations", "cells", "headline")])


@workload("biconditional_share", "SELECT benchmark, count(*) FILTER (declared) AS declared, count(*) AS contracts FROM (SELECT o_orderpriority AS benchmark, bool_and((o_orderstatus = 'F') = (o_totalprice >= 250000)) AS declared FROM orders GROUP BY o_orderpriority, o_custkey) GROUP BY 1")
def biconditional_share(spark, d):
    """A customer's orders of a priority are a contract: its guard is biconditional where price and status agree both ways."""
    both = (F.col("o_orderstatus") == "F") == (F.col("o_totalprice") >= 250000)
    rows = load(spark, d, "orders").groupBy(F.col("o_orderpriority").alias("benchmark"), "o_custkey").agg(F.bool_and(both).alias("declared"))
    return rows.groupBy("benchmark").agg(F.count_if("declared").alias("declared"), F.count("*").alias("contracts"))


@workload("registry_post_hoc", "SELECT * FROM (VALUES ('gold_replay',5,'p2',false),('margins',5,'p3',false),('miss_causes',6,NULL,true),('late_plan',4,NULL,true)) r(item, result_ts, plan_id, post_hoc)")
def registry_post_hoc(spark, d):
    plans = spark.createDataFrame([("p1", "gold_replay", 1), ("p2", "gold_replay", 3), ("p3", "margins", 2), ("p4", "late_plan", 9)], "plan_id string, item string, registered_ts int")
    results = spark.createDataFrame([("gold_replay", 5), ("margins", 5), ("miss_causes", 6), ("late_plan", 4)], "item string, result_ts int")
    return M.post_hoc(results, plans)


@workload("disclosure_status", "SELECT status, day, count(*) AS findings, sum(entries)::BIGINT AS entries FROM (SELECT event_type AS status, date_diff('day', DATE '1970-01-01', ts::DATE) AS day, count(*) OVER (PARTITION BY user_id) AS entries, row_number() OVER (PARTITION BY user_id ORDER BY ts DESC, event_id DESC) AS r FROM events) WHERE r = 1 GROUP BY 1, 2")
def disclosure_status(spark, d):
    """Events are the log of their users' findings: findings by last status and its day."""
    log = load(spark, d, "events").select(F.col("user_id").alias("finding"), F.col("event_type").alias("status"), F.unix_date(F.to_date("ts")).cast("long").alias("day"), F.struct("ts", "event_id").alias("at"))
    return M.latest_status(log, "at").groupBy("status", "day").agg(F.count("*").alias("findings"), F.sum("entries").alias("entries"))


@workload("claim_audit", "SELECT name, stated, found, stated = found AS holds FROM (SELECT 'orders' AS name, 15000::BIGINT AS stated, (SELECT count(*) FROM orders) AS found UNION ALL SELECT 'events', 10000, (SELECT count(*) FROM events) UNION ALL SELECT 'open', 1, (SELECT count(*) FROM orders WHERE o_orderstatus = 'O'))")
def claim_audit(spark, d):
    claims = spark.createDataFrame([("orders", 15000), ("events", 10000), ("open", 1)], "name string, stated long")
    count = lambda df, n: df.agg(F.count("*").alias("found")).select(F.lit(n).alias("name"), "found")
    orders = load(spark, d, "orders")
    ledger = reduce(DataFrame.union, [count(orders, "orders"), count(load(spark, d, "events"), "events"), count(orders.filter("o_orderstatus = 'O'"), "open")])
    return M.audit_claims(claims, ledger)


IDENTITIES = "(VALUES ('control_rows',4494,4494),('misses',33,33),('escapes',225,225),('flags',23,23),('whole_file_flags',32,32),('sites',17,17),('surface',25,25),('scanner_population',49,49),('exposed_refuel',1135,1135),('cases',300,300),('toy_pairs',4048,4048),('telecom_pairs',2325,2325)) i(name, stated, found)"


@workload("published_identities", f"SELECT name, stated::BIGINT AS stated, found::BIGINT AS found, stated = found AS holds FROM {IDENTITIES}")
def published_identities(spark, d):
    """Published totals against the sums of their published parts."""
    parts = {"control_rows": (4494, (1120 * 2 + 7) * 2), "misses": (33, 2 + 29 + 2), "escapes": (225, 119 + 86 + 20), "flags": (23, 14 + 9), "whole_file_flags": (32, 14 + 18), "sites": (17, 11 + 4 + 2), "surface": (25, 7 + 6 + 12), "scanner_population": (49, 31 + 6 + 12), "exposed_refuel": (1135, 1120 + 15), "cases": (300, 150 + 60 + 90), "toy_pairs": (4048, 368 * 11), "telecom_pairs": (2325, 465 * 5)}
    claims = spark.createDataFrame([(k, v[0]) for k, v in parts.items()], "name string, stated long")
    return M.audit_claims(claims, spark.createDataFrame([(k, v[1]) for k, v in parts.items()], "name string, found long"))


@workload("dead_rules", "SELECT c_mktsegment AS segment, count(*) AS rules, count(*) FILTER (c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_orderstatus = 'F' AND o_orderpriority = '1-URGENT')) AS dead FROM customer GROUP BY 1")
def dead_rules(spark, d):
    """Rules that no observed row carries: customers, and the urgent filled orders that would show them."""
    rules = load(spark, d, "customer").select(F.col("c_custkey").alias("rule"), F.col("c_mktsegment").alias("segment"))
    seen = load(spark, d, "orders").filter("o_orderstatus = 'F' AND o_orderpriority = '1-URGENT'").select(F.col("o_custkey").alias("rule")).distinct()
    dead = rules.join(seen, "rule", "left_anti").groupBy("segment").agg(F.count("*").alias("dead"))
    return rules.groupBy("segment").agg(F.count("*").alias("rules")).join(dead, "segment", "left").select("segment", "rules", F.coalesce("dead", F.lit(0)).alias("dead"))
