"""Clause verdicts of the desk tools, probe plans, state digests and diffs, rollups."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from statewitness.functions.state import changed_cells, table_digest
from statewitness.operators import conformance as C
from statewitness.operators.desk import TOOLS
from statewitness.plans.base import workload
from statewitness.sources.tables import LINE_KEY, cents, load

FIRST_LINE = "SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_shipdate) AS k FROM lineitem) WHERE k = 1"


def rows(tool: str, *cases: tuple[str, str, str, str, str]) -> str:
    """SQL for a tool's verdict table: (arm, clause, groups, failing groups, classes if failing)."""
    parts = []
    for arm, clause, n, bad, classes in cases:
        parts.append(f"SELECT '{tool}' AS tool, '{arm}' AS arm, '{clause}' AS clause_id, ({n})::BIGINT AS n_groups, ({bad})::BIGINT AS n_failed, '{classes}' AS cls")
    return (
        "SELECT tool, arm, clause_id, n_groups, n_failed, CASE WHEN n_failed > 0 THEN 'violates' WHEN n_groups > 0 THEN 'conforms' ELSE 'untestable' END AS verdict, "
        "CASE WHEN n_groups = 0 THEN 'no_observable_state' END AS reason, CASE WHEN n_failed > 0 THEN cls ELSE '' END AS classes FROM (" + " UNION ALL ".join(parts) + ")"
    )


def both(clause: str, n: str, bad: str, classes: str, patched: str = "0") -> list[tuple[str, str, str, str, str]]:
    return [("unpatched", clause, n, bad, classes), ("patched", clause, n, patched, classes)]


OPEN = "SELECT count(DISTINCT o_custkey) FROM orders WHERE o_orderstatus = 'O'"
ORDERED = "SELECT count(DISTINCT l_orderkey) FROM lineitem"
USERS = "SELECT count(DISTINCT user_id) FROM events"
NATIONS = "SELECT count(DISTINCT c_nationkey) FROM customer"
CUSTOMERS = "SELECT count(*) FROM customer"
EVENTS = "SELECT count(*) FROM events"

CASES = {
    "verdict_unenforced_charge": ("charge_order", [
        *both("pre.open", "SELECT count(DISTINCT o_custkey) FROM orders WHERE o_orderstatus <> 'O'", "SELECT count(DISTINCT o_custkey) FROM orders WHERE o_orderstatus <> 'O'", "guard_not_enforced"),
        *both("pre.owner", OPEN, "0", ""), *both("eff.total", OPEN, "0", ""), *both("frame.status", OPEN, "0", ""), *both("frame.customer", OPEN, "0", ""), *both("arg.amount", OPEN, "0", "")]),
    "verdict_partial_cancel": ("cancel_order", [*both("eff.closed", ORDERED, "0", ""), *both("eff.stock", ORDERED, "SELECT count(*) FROM (SELECT l_orderkey FROM lineitem GROUP BY 1 HAVING sum(l_quantity) <> 0)", "half_applied")]),
    "verdict_ignored_revise": ("revise_line", [
        ("unpatched", "eff.quantity", ORDERED, ORDERED, "argument_inert,claimed_not_written"),
        ("unpatched", "eff.discount", ORDERED, f"SELECT count(*) FROM ({FIRST_LINE}) WHERE l_discount <> 0", "argument_inert,claimed_not_written"),
        ("unpatched", "eff.tax", ORDERED, f"SELECT count(*) FROM ({FIRST_LINE}) WHERE l_tax <> 0", "argument_inert,claimed_not_written"),
        *[("patched", f"eff.{f}", ORDERED, "0", "") for f in ("quantity", "discount", "tax")],
        *both("arg.quantity", ORDERED, "0", ""), *[(a, f"arg.{f}", "0", "0", "") for a in C.ARMS for f in ("discount", "tax")]]),
    "verdict_ignored_ship_aggravated": ("schedule_ship", [*both("eff.from", ORDERED, "0", ""), *both("arg.ship_from", ORDERED, "0", ""), *both("arg.ship_until", ORDERED, ORDERED, "argument_inert")]),
    "verdict_ignored_listing": ("list_activity", [*both("arg.order_by", USERS, USERS, "argument_inert"), *both("arg.limit", USERS, "0", "")]),
    "verdict_ignored_register": ("register_customer", [*both("eff.row", NATIONS, "0", ""), *both("arg.segment", NATIONS, "0", ""), *both("arg.email", NATIONS, NATIONS, "argument_inert")]),
    "verdict_phantom_post": ("post_event", [*both("eff.row", USERS, USERS, "claimed_not_written,half_applied")]),
    "verdict_heldout_update_customer": ("update_customer", [
        *both("eff.name", CUSTOMERS, "SELECT count(*) FROM customer WHERE c_name <> ''", "argument_inert"), *both("eff.segment", CUSTOMERS, "SELECT count(*) FROM customer WHERE c_mktsegment <> ''", "argument_inert"),
        *both("eff.acctbal", CUSTOMERS, "SELECT count(*) FROM customer WHERE c_acctbal <> 0", "argument_inert"), *both("eff.nation", CUSTOMERS, "SELECT count(*) FROM customer WHERE c_nationkey <> 0", "argument_inert"),
        *[(a, f"arg.{f}", "0", "0", "") for a in C.ARMS for f in ("name", "segment", "acctbal", "nation")]]),
    "verdict_blind_retire": ("retire_event", [*both("eff.marked", EVENTS, "0", ""), *both("eff.gone", EVENTS, EVENTS, "half_applied")]),
    "verdict_candidate_hold": ("hold_order", [*both("eff.held", "SELECT count(DISTINCT o_custkey) FROM orders", "0", ""), *both("arg.reason", "SELECT count(DISTINCT o_custkey) FROM orders", "SELECT count(DISTINCT o_custkey) FROM orders", "argument_inert")]),
}
for _name, (_tool, _cases) in CASES.items():
    workload(_name, rows(_tool, *_cases))(lambda spark, d, t=_tool: C.verdicts(spark, d, TOOLS[t]))

workload("verdict_ignored_revise_conjunctive", rows("revise_line", *CASES["verdict_ignored_revise"][1]))(lambda spark, d: C.verdicts(spark, d, TOOLS["revise_line"], rule="conjunctive"))
workload("verdict_ship_conjunctive", rows("schedule_ship", *both("eff.from", ORDERED, "0", ""), *both("arg.ship_from", ORDERED, "0", ""), *both("arg.ship_until", ORDERED, "0", "")))(lambda spark, d: C.verdicts(spark, d, TOOLS["schedule_ship"], rule="conjunctive"))


@workload("ship_aggravated_sets", f"SELECT arm, clause_id, ({ORDERED})::BIGINT AS n_sets, CASE WHEN arm = 'unpatched' AND clause_id = 'arg.ship_until' THEN ({ORDERED}) ELSE 0 END::BIGINT AS n_aggravated FROM (VALUES ('unpatched'), ('patched')) a(arm), (VALUES ('arg.ship_from'), ('arg.ship_until')) c(clause_id)")
def ship_aggravated_sets(spark, d):
    tool = TOOLS["schedule_ship"]
    sets = C.variant_rows(tool, C.invoke(tool, C.probe_rows(tool, tool.slice(spark, d))))
    return sets.groupBy("arm", "clause_id").agg(F.count("*").alias("n_sets"), F.count_if("aggravated").alias("n_aggravated"))


@workload("charge_witness", """
WITH w AS (SELECT o_custkey, min(o_orderkey) AS o_orderkey FROM orders WHERE o_orderstatus <> 'O' GROUP BY 1)
SELECT o_custkey, o_orderkey, o_orderstatus AS status, round(o_totalprice * 100)::BIGINT AS before_cents, round((o_totalprice + 40.0) * 100)::BIGINT AS after_cents, 'added 40.0' AS message
FROM w JOIN orders USING (o_orderkey, o_custkey)""")
def charge_witness(spark, d):
    """The ledger's witness rows of the missing guard: call, difference and return."""
    tool = TOOLS["charge_order"]
    calls = C.invoke(tool, C.probe_rows(tool, tool.slice(spark, d)))
    bad = calls.filter("arm = 'unpatched' AND purpose = 'falsify' AND target = 'pre.open' AND error IS NULL AND size(delta) > 0")
    return bad.select(F.col("grp").alias("o_custkey"), F.col("key").alias("o_orderkey"), F.col("pre.status").alias("status"), F.round(F.col("pre.total") * 100).cast("long").alias("before_cents"), F.round(F.col("post.total") * 100).cast("long").alias("after_cents"), "message")


# --- the whole desk ---------------------------------------------------------------------------------


def desk_verdicts(spark, d, dedup_mode="raw") -> DataFrame:
    parts = [C.verdicts(spark, d, t, dedup_mode=dedup_mode).withColumn("population", F.lit(t.population)).withColumn("candidate", F.lit(t.candidate)) for t in TOOLS.values()]
    return reduce(DataFrame.unionByName, parts)


EXPECT = {
    "charge_order": ("SELECT count(*) FROM orders WHERE o_orderstatus <> 'O'", 6), "hold_order": ("SELECT count(*) FROM orders", 2), "cancel_order": ("SELECT count(*) FROM lineitem WHERE l_quantity <> 0", 2),
    "revise_line": ("SELECT count(*) FROM lineitem", 6), "schedule_ship": ("SELECT count(*) FROM lineitem", 3), "list_activity": ("SELECT count(*) FROM events", 2), "register_customer": ("SELECT count(*) FROM customer", 3),
    "update_customer": ("SELECT count(*) FROM customer WHERE c_name <> ''", 8), "retire_event": ("SELECT count(*) FROM events", 2), "post_event": ("SELECT count(*) FROM events", 1),
}
UNTESTED = {"place_order": 2, "share_conversation": 2, "open_conversation": 2, "send_notice": 2, "swap_lines": 2}
NEVER_VARIED = {"revise_line": 2, "update_customer": 4, "stamp_ship": 0}


def rollup_sql() -> str:
    parts = []
    for name, tool in TOOLS.items():
        n = sum(len(tool.contract.of(k)) for k in ("pre", "eff", "frame", "arg"))
        bad = EXPECT.get(name, ("SELECT 0", 0))[0]
        if name in UNTESTED:
            verdict, open_ = "'untestable'", n
        else:
            verdict = f"CASE WHEN arm = 'unpatched' AND ({bad}) > 0 THEN 'violates' ELSE 'conforms' END"
            open_ = NEVER_VARIED.get(name, 0) + (1 if name == "stamp_ship" else 0)
        parts.append(f"SELECT '{name}' AS tool, arm, {n}::BIGINT AS n_clauses, {open_}::BIGINT AS n_untestable, {verdict} AS verdict FROM (VALUES ('unpatched'), ('patched')) a(arm)")
    return " UNION ALL ".join(parts)


@workload("tool_rollup", rollup_sql())
def tool_rollup(spark, d):
    return C.rollup(desk_verdicts(spark, d))


@workload("clause_verdict_rows", f"SELECT arm, verdict, count(*) AS n_tools, sum(n_clauses)::BIGINT AS n_clauses FROM ({rollup_sql()}) GROUP BY ALL")
def clause_verdict_rows(spark, d):
    per = C.rollup(desk_verdicts(spark, d))
    return per.groupBy("arm", "verdict").agg(F.count("*").alias("n_tools"), F.sum("n_clauses").alias("n_clauses"))


@workload("untestable_share", f"SELECT arm, sum(n_untestable)::BIGINT AS n_untestable, sum(n_clauses)::BIGINT AS n_clauses, round(sum(n_untestable) / sum(n_clauses), 6) AS share FROM ({rollup_sql()}) GROUP BY arm")
def untestable_share(spark, d):
    """Untestable clauses stay in the denominator."""
    v = desk_verdicts(spark, d)
    n = F.count_if(F.col("verdict") == C.UNTESTABLE)
    return v.groupBy("arm").agg(n.alias("n_untestable"), F.count("*").alias("n_clauses"), F.round(n / F.count("*"), 6).alias("share"))


SURFACE = f"SELECT tool, verdict FROM ({rollup_sql()}) WHERE arm = 'unpatched' AND tool <> 'post_event'"


@workload("surface_rate", f"SELECT count(*) FILTER (verdict = 'violates' AND tool <> 'hold_order') AS confirmed, count(*) FILTER (verdict = 'violates') AS violating, count(*) FILTER (verdict = 'untestable') AS untestable, count(*) AS tools, count(*) FILTER (verdict <> 'untestable') AS scored, round(count(*) FILTER (verdict = 'violates' AND tool <> 'hold_order') / count(*), 6) AS rate_all, round(count(*) FILTER (verdict = 'violates' AND tool <> 'hold_order') / count(*) FILTER (verdict <> 'untestable'), 6) AS rate_scored FROM ({SURFACE})")
def surface_rate(spark, d):
    """Divergent tools on the complete surface of 25, with untestable ones kept and dropped."""
    v = desk_verdicts(spark, d).filter("arm = 'unpatched' AND tool <> 'post_event'")
    candidate = F.create_map(*[x for t in TOOLS.values() for x in (F.lit(t.name), F.lit(t.candidate))])
    per = C.rollup(v).withColumn("confirmed", (F.col("verdict") == C.VIOLATES) & ~candidate[F.col("tool")])
    k, scored = F.count_if("confirmed"), F.count_if(F.col("verdict") != C.UNTESTABLE)
    return per.agg(k.alias("confirmed"), F.count_if(F.col("verdict") == C.VIOLATES).alias("violating"), F.count_if(F.col("verdict") == C.UNTESTABLE).alias("untestable"), F.count("*").alias("tools"), scored.alias("scored"), F.round(k / F.count("*"), 6).alias("rate_all"), F.round(k / scored, 6).alias("rate_scored"))


POPULATION = " UNION ALL ".join(f"SELECT '{t.name}' AS tool, '{t.population}' AS population" for t in TOOLS.values())


@workload("population_rates", f"SELECT population, count(*) AS tools, count(*) FILTER (verdict = 'violates') AS violating, count(*) FILTER (verdict = 'untestable') AS untestable FROM ({rollup_sql()}) JOIN ({POPULATION}) USING (tool) WHERE arm = 'unpatched' GROUP BY population")
def population_rates(spark, d):
    """Populations are never pooled."""
    v = desk_verdicts(spark, d).filter("arm = 'unpatched'")
    per = C.rollup(v).join(F.broadcast(v.select("tool", "population").distinct()), "tool")
    return per.groupBy("population").agg(F.count("*").alias("tools"), F.count_if(F.col("verdict") == C.VIOLATES).alias("violating"), F.count_if(F.col("verdict") == C.UNTESTABLE).alias("untestable"))


# --- probes -----------------------------------------------------------------------------------------


@workload("probe_harvest", "SELECT o_orderstatus AS value, k AS rank, o_orderkey FROM (SELECT o_orderstatus, o_orderkey, row_number() OVER (PARTITION BY o_orderstatus ORDER BY md5(o_orderkey::VARCHAR), o_orderkey) AS k FROM orders) WHERE k <= 5")
def probe_harvest(spark, d):
    """Candidate argument values from the snapshot: a capped, seeded choice for each value, in one pass.

    The cap is the feature: a probe plan takes k candidates. Ranks come after a per-partition cut by the
    same order, so no value's rows meet in one task.
    """
    from pyspark.sql.window import Window

    rows = load(spark, d, "orders").select("o_orderstatus", "o_orderkey", F.md5(F.col("o_orderkey").cast("string")).alias("draw"), F.pmod(F.xxhash64("o_orderkey"), F.lit(64)).alias("salt"))
    w = Window.partitionBy("o_orderstatus", "salt").orderBy("draw", "o_orderkey")
    cut = rows.withColumn("k", F.row_number().over(w)).filter("k <= 5")
    final = Window.partitionBy("o_orderstatus").orderBy("draw", "o_orderkey")
    return cut.withColumn("rank", F.row_number().over(final)).filter("rank <= 5").select(F.col("o_orderstatus").alias("value"), "rank", "o_orderkey")


@workload("probe_precondition_pairs", "SELECT o_custkey AS customer, min(o_orderkey) FILTER (o_orderstatus = 'O') AS satisfying, min(o_orderkey) FILTER (o_orderstatus <> 'O') AS falsifying FROM orders GROUP BY 1")
def probe_precondition_pairs(spark, d):
    held = F.col("o_orderstatus") == "O"
    return load(spark, d, "orders").groupBy(F.col("o_custkey").alias("customer")).agg(F.min(F.when(held, F.col("o_orderkey"))).alias("satisfying"), F.min(F.when(~held, F.col("o_orderkey"))).alias("falsifying"))


@workload("probe_happy", "SELECT o_custkey AS grp, min(o_orderkey) AS key FROM orders WHERE o_orderstatus = 'O' GROUP BY 1")
def probe_happy(spark, d):
    tool = TOOLS["charge_order"]
    return C.probe_rows(tool, tool.slice(spark, d)).filter("purpose = 'happy'").select("grp", "key")


@workload("probe_variants", f"SELECT l_orderkey AS grp, arg_name, variant_no, (l_quantity + variant_no + 1)::BIGINT AS quantity FROM ({FIRST_LINE}), (VALUES ('quantity', 0), ('quantity', 1)) v(arg_name, variant_no)")
def probe_variants(spark, d):
    tool = TOOLS["revise_line"]
    return C.probe_rows(tool, tool.slice(spark, d)).filter("purpose = 'variant'").select("grp", "arg_name", "variant_no", F.col("args.quantity").cast("long").alias("quantity"))


@workload("probe_joint_falsy", f"SELECT l_orderkey AS grp, 0::BIGINT AS quantity, 0::BIGINT AS discount, 0::BIGINT AS tax FROM ({FIRST_LINE})")
def probe_joint_falsy(spark, d):
    tool = TOOLS["revise_line"]
    rows = C.probe_rows(tool, tool.slice(spark, d)).filter("purpose = 'joint_falsy'")
    return rows.select("grp", *[F.col(f"args.{k}").cast("long").alias(k) for k in ("quantity", "discount", "tax")])


@workload("probe_dedup_modes", "SELECT mode, CASE mode WHEN 'raw' THEN 4 * n ELSE 3 * n END::BIGINT AS n_probes, CASE mode WHEN 'raw' THEN 4 * n ELSE 0 END::BIGINT AS n_unsupported FROM (VALUES ('raw'), ('canonical')) m(mode), (SELECT count(DISTINCT conv_id) AS n FROM conversations)")
def probe_dedup_modes(spark, d):
    """Raw hashing of list arguments stops a tool; canonical text doesn't, and drops the repeated variant."""
    tool = TOOLS["share_conversation"]
    probes = C.probe_rows(tool, tool.slice(spark, d))
    probes = probes.unionByName(probes.filter("purpose = 'happy'"))
    parts = [C.dedup(probes, m).agg(F.count("*").alias("n_probes"), F.count_if(F.col("reason").isNotNull()).alias("n_unsupported")).select(F.lit(m).alias("mode"), "n_probes", "n_unsupported") for m in ("raw", "canonical")]
    return parts[0].union(parts[1])


@workload("probe_distinct_gate", "SELECT a::BIGINT AS pair, gate, CASE WHEN gate = 'value' THEN x = y ELSE x_text = y_text END AS same FROM (VALUES (1, 2.0, 2.0, '2', '2.0'), (2, 0.0, 0.0, '0', '0.0'), (3, 1.5, 1.5, '1.5', '1.5')) t(a, x, y, x_text, y_text), (VALUES ('value'), ('typed')) g(gate)")
def probe_distinct_gate(spark, d):
    """2 and 2.0 are one value by the faithful gate and two by the typed one (JSON text of typed structs)."""
    rows = spark.createDataFrame([(1, 2, 2.0), (2, 0, 0.0)], "pair long, i int, x double")
    typed = F.to_json(F.struct(F.col("i").alias("v"))) == F.to_json(F.struct(F.col("x").alias("v")))
    ints = rows.select("pair", (F.col("i") == F.col("x")).alias("value"), typed.alias("typed"))
    same = spark.createDataFrame([(3, 1.5)], "pair long, x double").select("pair", F.lit(True).alias("value"), F.lit(True).alias("typed"))
    both_gates = ints.union(same)
    return both_gates.select("pair", F.explode(F.array(F.struct(F.lit("value").alias("gate"), F.col("value").alias("same")), F.struct(F.lit("typed").alias("gate"), F.col("typed").alias("same")))).alias("g")).select("pair", "g.gate", "g.same")


# --- state ------------------------------------------------------------------------------------------


def charged(spark, d) -> tuple[DataFrame, DataFrame]:
    before = load(spark, d, "orders").select("o_orderkey", "o_orderstatus", cents("o_totalprice").alias("total_cents"))
    hit = (F.col("o_orderstatus") == "F") & (F.col("o_orderkey") % 7 == 0)
    return before, before.withColumn("total_cents", F.when(hit, F.col("total_cents") + 4000).otherwise(F.col("total_cents")))


@workload("state_diff_orders", "SELECT o_orderkey AS key, 'total_cents' AS field, round(o_totalprice * 100)::BIGINT::VARCHAR AS before, (round(o_totalprice * 100)::BIGINT + 4000)::VARCHAR AS after FROM orders WHERE o_orderstatus = 'F' AND o_orderkey % 7 = 0")
def state_diff_orders(spark, d):
    """Changed cells between two snapshots of a keyed table."""
    before, after = charged(spark, d)
    return changed_cells(before, after, "o_orderkey")


@workload("state_digest_md5", "SELECT arm, count(*) AS n_rows, sum(('0x' || substr(md5(concat_ws('|', o_orderkey, o_orderstatus, cents)), 1, 15))::HUGEINT)::VARCHAR AS digest FROM (SELECT 'before' AS arm, o_orderkey, o_orderstatus, round(o_totalprice * 100)::BIGINT AS cents FROM orders UNION ALL SELECT 'after', o_orderkey, o_orderstatus, round(o_totalprice * 100)::BIGINT + CASE WHEN o_orderstatus = 'F' AND o_orderkey % 7 = 0 THEN 4000 ELSE 0 END FROM orders) GROUP BY arm")
def state_digest_md5(spark, d):
    before, after = charged(spark, d)
    parts = [table_digest(df, ["o_orderkey", "o_orderstatus", "total_cents"]).select(F.lit(k).alias("arm"), "n_rows", F.col("digest").cast("string").alias("digest")) for k, df in (("before", before), ("after", after))]
    return parts[0].union(parts[1])


@workload("state_digest_volatile", "SELECT 'status' AS compared, true AS equal UNION ALL SELECT 'all', (SELECT count(*) = 0 FROM orders WHERE o_orderstatus = 'F' AND o_orderkey % 7 = 0)")
def state_digest_volatile(spark, d):
    """The declared-volatile rule: excluded fields don't count in a comparison."""
    before, after = charged(spark, d)
    out = []
    for name, cols in (("status", ["o_orderkey", "o_orderstatus"]), ("all", ["o_orderkey", "o_orderstatus", "total_cents"])):
        a, b = table_digest(before, cols), table_digest(after, cols)
        out.append(a.alias("a").crossJoin(F.broadcast(b.alias("b"))).select(F.lit(name).alias("compared"), ((F.col("a.n_rows") == F.col("b.n_rows")) & (F.col("a.digest") == F.col("b.digest"))).alias("equal")))
    return out[0].union(out[1])


@workload("frame_charge", "SELECT count(*) AS n_calls, 0::BIGINT AS n_outside, count(*) AS n_inside FROM (SELECT o_custkey FROM orders WHERE o_orderstatus = 'O' GROUP BY 1)")
def frame_charge(spark, d):
    """Every changed field of the happy charge is among the advertised paths."""
    tool = TOOLS["charge_order"]
    calls = C.invoke(tool, C.probe_rows(tool, tool.slice(spark, d))).filter("arm = 'unpatched' AND purpose = 'happy'")
    inside = F.forall("delta", lambda x: x["field"].isin("total"))
    return calls.agg(F.count("*").alias("n_calls"), F.count_if(~inside).alias("n_outside"), F.count_if(inside).alias("n_inside"))


STOCK = "SELECT p_partkey, p_size::BIGINT AS p_size, sum(l_quantity::BIGINT)::BIGINT AS reserved FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1, 2"


@workload("verdict_invariant_stock", f"SELECT arm, count(*) AS n_sequences, count(*) FILTER (arm = 'unpatched' AND reserved <> 0) AS n_broken, CASE WHEN arm = 'unpatched' AND count(*) FILTER (reserved <> 0) > 0 THEN 'invariant_broken' ELSE '' END AS classes FROM ({STOCK}), (VALUES ('unpatched'), ('patched')) a(arm) GROUP BY arm")
def verdict_invariant_stock(spark, d):
    """Stock is what it was after every line of a part has been booked and cancelled."""
    lines = load(spark, d, "lineitem").groupBy("l_partkey").agg(F.sum(F.col("l_quantity").cast("long")).alias("reserved"))
    parts = lines.join(load(spark, d, "part").select("p_partkey", F.col("p_size").cast("long").alias("p_size")), F.col("l_partkey") == F.col("p_partkey"))
    arms = spark.createDataFrame([(a,) for a in C.ARMS], "arm string")
    end = parts.crossJoin(F.broadcast(arms)).withColumn("at_end", F.col("p_size") - F.col("reserved") + F.when(F.col("arm") == "patched", F.col("reserved")).otherwise(0))
    broken = F.count_if(F.col("at_end") != F.col("p_size"))
    return end.groupBy("arm").agg(F.count("*").alias("n_sequences"), broken.alias("n_broken"), F.when(broken > 0, C.INVARIANT).otherwise("").alias("classes"))


@workload("verdict_reset_leak", "SELECT arm, CASE WHEN arm = 'unpatched' AND (SELECT count(*) FROM orders WHERE o_orderpriority = '1-URGENT' AND o_orderstatus = 'F' AND o_orderkey % 7 = 0) > 0 THEN 'violates' ELSE 'conforms' END AS verdict, CASE WHEN arm = 'unpatched' AND (SELECT count(*) FROM orders WHERE o_orderpriority = '1-URGENT' AND o_orderstatus = 'F' AND o_orderkey % 7 = 0) > 0 THEN 'reset_residue' ELSE '' END AS classes FROM (VALUES ('unpatched'), ('patched')) a(arm)")
def verdict_reset_leak(spark, d):
    """A reset that forgets urgent orders leaves residue; a full one doesn't (order-free digests compared)."""
    first = load(spark, d, "orders").select("o_orderkey", "o_orderstatus", "o_orderpriority", cents("o_totalprice").alias("total_cents"))
    hit = (F.col("o_orderstatus") == "F") & (F.col("o_orderkey") % 7 == 0)
    used = F.when(hit, F.col("total_cents") + 4000).otherwise(F.col("total_cents"))
    cols = ["o_orderkey", "o_orderstatus", "total_cents"]
    out = []
    for arm in C.ARMS:
        left = F.when((F.lit(arm) == "unpatched") & (F.col("o_orderpriority") == "1-URGENT"), used).otherwise(F.col("total_cents"))
        a, b = table_digest(first, cols), table_digest(first.withColumn("total_cents", left), cols)
        leaks = (F.col("a.digest") != F.col("b.digest")) | (F.col("a.n_rows") != F.col("b.n_rows"))
        out.append(a.alias("a").crossJoin(F.broadcast(b.alias("b"))).select(F.lit(arm).alias("arm"), F.when(leaks, C.VIOLATES).otherwise(C.CONFORMS).alias("verdict"), F.when(leaks, C.RESET).otherwise("").alias("classes")))
    return out[0].union(out[1])
