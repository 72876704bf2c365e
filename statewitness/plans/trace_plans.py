"""Static scan, contract validation, tiers, and the score-at-risk trace."""

from __future__ import annotations

from pyspark.sql import functions as F

from statewitness.operators import scan, trace
from statewitness.operators.contract import Clause, Contract, Provenance, clause_rows, draft, tier_of, validate
from statewitness.operators.desk import TOOLS
from statewitness.plans.base import workload
from statewitness.sources import code
from statewitness.sources.tables import load

# --- static half ------------------------------------------------------------------------------------


def flags(spark):
    sources = code.source_rows(spark, code.TOOL_SOURCES)
    pairs = spark.createDataFrame(code.VERB_PAIRS, "do string, undo string")
    return scan.scan(code.nodes(sources), code.source_lines(sources), pairs)


def sites(spark):
    return spark.createDataFrame(code.SITES, "file string, func string, check string")


FLAGS = """(VALUES ('orders.py','charge_order','dead_guard','guard_not_enforced',7),('orders.py','hold_order','cosmetic_param','argument_inert',12),('orders.py','cancel_order','verb_pair','half_applied',23),
('lines.py','revise_line','truthy_guard','argument_inert',5),('lines.py','revise_line','truthy_guard','argument_inert',7),('lines.py','revise_line','truthy_guard','argument_inert',9),('lines.py','revise_line','literal_success','claimed_not_written',11),
('lines.py','schedule_ship','cosmetic_param','argument_inert',13),('people.py','register_customer','unread_param','argument_inert',2),('people.py','update_customer','truthy_guard','argument_inert',9),('people.py','update_customer','truthy_guard','argument_inert',11),
('people.py','post_event','literal_success','claimed_not_written',18),('people.py','post_event','unread_param','argument_inert',15),('orders.py','list_orders','truthy_guard','argument_inert',33)) f(file, func, "check", class_hint, lineno)"""


@workload("scan_flags", f"SELECT * FROM {FLAGS}")
def scan_flags(spark, d):
    """Flags of the five checks, and of parameters never read, on the desk's sources."""
    return flags(spark)


@workload("scan_score_population", "SELECT 13::BIGINT AS flags, 10::BIGINT AS true_flags, 3::BIGINT AS false_flags, 7::BIGINT AS sites_found, 7::BIGINT AS sites")
def scan_score_population(spark, d):
    return scan.score(flags(spark), sites(spark), code.OUTSIDE_POPULATION)


@workload("scan_score_wholefile", "SELECT 14::BIGINT AS flags, 10::BIGINT AS true_flags, 4::BIGINT AS false_flags, 7::BIGINT AS sites_found, 7::BIGINT AS sites")
def scan_score_wholefile(spark, d):
    return scan.score(flags(spark), sites(spark), code.OUTSIDE_POPULATION, scope="whole_file")


@workload("page_nodes_links", r"""
WITH l AS (SELECT page_id, unnest(regexp_extract_all(html, '<a href="([^"]*)"', 1)) AS target FROM pages), c AS (SELECT page_id, len(regexp_extract_all(html, '<!--')) AS comments FROM pages)
SELECT page_id, count(target) AS links, count(DISTINCT target) AS targets, any_value(comments)::INTEGER AS comments FROM c LEFT JOIN l USING (page_id) GROUP BY page_id""")
def page_nodes_links(spark, d):
    """The page analogue: links that a page declares, and what it comments out."""
    pages = load(spark, d, "pages").select("page_id", F.regexp_extract_all("html", F.lit('<a href="([^"]*)"'), F.lit(1)).alias("t"), F.regexp_count("html", F.lit("<!--")).alias("comments"))
    return pages.select("page_id", F.size("t").cast("long").alias("links"), F.size(F.array_distinct("t")).cast("long").alias("targets"), "comments")


# --- contracts --------------------------------------------------------------------------------------

FIXTURES = [
    Contract("good", (Clause("eff.total", "post.total == pre.total + args.amount", Provenance("docstring", "a.txt", 1, "amount is added", "v1")), Clause("frame.rest", "post.status == pre.status"), Clause("pre.open", "pre.status == 'O'", Provenance("tool_return", "a.txt", 3, "must be open", "v1")))),
    Contract("bad", (Clause("eff.total", "post.total == total + 1", Provenance("docstring", "a.txt", 1, "amount is removed", "v1")), Clause("pre.log", "pre.status == 'O'", Provenance("tool_return", "a.txt", 4, "status", "v1")), Clause("note.x", "args.x == 1", Provenance("prompt", "p.txt", 9, "be kind", "v1")))),
    draft("new", ["amount"]),
]


@workload("contract_validator", """
WITH templates(k, tool, clause_id, kind, surface, compiles, is_draft) AS (VALUES (0,'good','eff.total','eff','docstring',true,false),(1,'good','frame.rest','frame',NULL,true,false),(2,'good','pre.open','pre','tool_return',true,false),
(3,'bad','eff.total','eff','docstring',false,false),(4,'bad','pre.log','pre','tool_return',true,false),(5,'bad','note.x','note','prompt',true,false),(6,'new','eff.amount_draft','eff',NULL,true,true)),
c AS (SELECT t.*, o_orderstatus = 'F' AS quoted, o_orderpriority IN ('1-URGENT', '2-HIGH') AS returned, bool_or(o_orderstatus = 'F') OVER (PARTITION BY o_custkey) AS in_file, count(*) OVER (PARTITION BY o_custkey, k) AS twins FROM orders JOIN templates t ON k = o_orderkey % 7)
SELECT tool, clause_id, check_no::INTEGER AS check_no, count(*) FILTER (ok) AS passing, count(*) FILTER (NOT ok) AS failing FROM (SELECT tool, clause_id, check_no, CASE check_no WHEN 1 THEN kind <> 'note' WHEN 2 THEN compiles WHEN 3 THEN compiles OR kind NOT IN ('eff', 'frame', 'inv')
WHEN 4 THEN surface IS NULL OR quoted OR (surface = 'prompt' AND in_file) WHEN 5 THEN twins = 1 WHEN 8 THEN CASE surface WHEN 'tool_return' THEN returned WHEN 'prompt' THEN in_file ELSE true END ELSE true END AS ok FROM c, range(1, 9) r(check_no)) GROUP BY 1, 2, 3""")
def contract_validator(spark, d):
    """Every order instantiates a clause of the fixtures, which quotes its own line (its status) in its customer's file."""
    orders = load(spark, d, "orders").withColumn("file", F.col("o_custkey").cast("string"))
    kind = F.when(F.col("o_orderpriority") == "1-URGENT", "return").when(F.col("o_orderpriority") == "2-HIGH", "raise").otherwise("log")
    lines = orders.select("file", F.col("o_orderkey").alias("line"), F.col("o_orderstatus").alias("text"), kind.alias("kind"))
    templates = clause_rows(spark, FIXTURES).drop("file", "line", "quote")
    numbers = spark.createDataFrame([(k, c.tool, x.clause_id) for k, (c, x) in enumerate((c, x) for c in FIXTURES for x in c.clauses)], "k int, tool string, clause_id string")
    cited = orders.select("file", F.col("o_orderkey").alias("line"), F.lit("F").alias("quote"), (F.col("o_orderkey") % 7).cast("int").alias("k"))
    clauses = cited.join(F.broadcast(templates.join(numbers, ["tool", "clause_id"])), "k").withColumn("tool", F.concat_ws("@", "tool", "file"))
    rows = validate(clauses, lines).groupBy(F.substring_index("tool", "@", 1).alias("tool"), "clause_id", "check_no")
    return rows.agg(F.count_if("ok").alias("passing"), F.count_if(~F.col("ok")).alias("failing"))


@workload("contract_quote_check", "SELECT doc_id, k::INTEGER AS line, contains(line, 'the') AS quoted FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) AS k FROM documents)")
def contract_quote_check(spark, d):
    """Quotes at a cited file and line: every line of every document is cited."""
    cited = load(spark, d, "documents").select("doc_id", F.posexplode(F.split("text", "\n", -1)).alias("k", "line"))
    return cited.select("doc_id", (F.col("k") + 1).alias("line"), F.col("line").contains("the").alias("quoted"))


TIERS = "(VALUES ('docstring','agent-visible'),('schema','agent-visible'),('prompt','agent-visible'),('tool_return','agent-visible'),('readme','agent-visible'),('standard','agent-visible'),('comment','maintainer-annotated'),('log','maintainer-annotated'),('todo','maintainer-annotated'),(NULL,'author-assigned')) t(surface, tier)"


@workload("tier_assignment", f"SELECT surface, tier, tier = 'author-assigned' AS inferred FROM {TIERS}")
def tier_assignment(spark, d):
    rows = spark.createDataFrame([(s,) for s in ("docstring", "schema", "prompt", "tool_return", "readme", "standard", "comment", "log", "todo", None)], "surface string")
    return rows.select("surface", tier_of(F.col("surface")).alias("tier"), F.col("surface").isNull().alias("inferred"))


SURFACES = ("docstring", "schema", "prompt", "tool_return", "readme", "standard", "comment", "log", "todo", None)


@workload("headline_cells", """SELECT benchmark, class, count(*) AS cells, count(*) FILTER (visible AND observed AND confirmed) AS headline FROM (SELECT o_orderpriority AS benchmark, o_orderstatus AS class,
o_custkey % 10 < 6 AS visible, max(o_totalprice) >= 100000 AS observed, min(o_orderkey) % 3 <> 0 AS confirmed FROM orders GROUP BY o_orderpriority, o_orderstatus, o_custkey) GROUP BY 1, 2""")
def headline_cells(spark, d):
    """A cell is headline only if its clause is agent-visible, its class ran, and a person confirmed it.

    A cell is a customer's orders of a priority and status; the surface of its clause goes by the customer.
    """
    surface = F.element_at(F.array(*[F.lit(x) for x in SURFACES]), (F.col("o_custkey") % len(SURFACES) + 1).cast("int"))
    cells = load(spark, d, "orders").groupBy(F.col("o_orderpriority").alias("benchmark"), F.col("o_orderstatus").alias("class"), "o_custkey").agg((F.max("o_totalprice") >= 100000).alias("observed"), (F.min("o_orderkey") % 3 != 0).alias("confirmed"))
    headline = (tier_of(surface) == "agent-visible") & F.col("observed") & F.col("confirmed")
    return cells.groupBy("benchmark", "class").agg(F.count("*").alias("cells"), F.count_if(headline).alias("headline"))


@workload("benign_split", "SELECT o_orderpriority AS surface, count(*) FILTER (o_orderstatus = 'F') AS disclosed, count(*) FILTER (o_orderstatus <> 'F') AS undisclosed FROM orders WHERE o_orderkey % 5 = 0 GROUP BY 1")
def benign_split(spark, d):
    """A divergence that some agent-visible surface discloses is benign; the rest are defects."""
    orders = load(spark, d, "orders")
    divergent = orders.filter("o_orderkey % 5 = 0").select("o_orderkey", F.col("o_orderpriority").alias("surface"))
    told = orders.filter("o_orderstatus = 'F'").select("o_orderkey")
    benign = divergent.join(told, "o_orderkey", "left_semi").withColumn("d", F.lit(1))
    defect = divergent.join(told, "o_orderkey", "left_anti").withColumn("d", F.lit(0))
    return benign.union(defect).groupBy("surface").agg(F.sum("d").alias("disclosed"), F.sum(1 - F.col("d")).alias("undisclosed"))


# --- trace ------------------------------------------------------------------------------------------

EVALUATORS = [("1-URGENT", "e_exact", "orders.status", "state", True, False), ("2-HIGH", "e_collection", "orders", "state", True, False), ("3-MEDIUM", "e_whole", None, "state", True, True), ("4-NOT SPECIFIED", "e_forced", None, "state", False, False), ("5-LOW", "e_told", "orders.status", "transcript", True, False)]


def tasks_and_sites(spark, d):
    rows = spark.createDataFrame(EVALUATORS, "priority string, evaluator string, site_path string, target string, resolved boolean, whole boolean")
    orders = load(spark, d, "orders").select(F.col("o_orderkey").alias("task_id"), F.col("o_orderpriority").alias("priority"), "o_orderstatus")
    tasks = orders.join(F.broadcast(rows.select("priority", "evaluator")), "priority")
    found = spark.createDataFrame([("charge_order", "orders.status")], "tool string, path string")
    return tasks, rows.drop("priority"), found


PRIORITIES = "SELECT o_orderkey AS task_id, 'charge_order' AS tool, CASE o_orderpriority WHEN '1-URGENT' THEN 'attr' WHEN '2-HIGH' THEN 'collection' WHEN '3-MEDIUM' THEN 'whole_digest' WHEN '4-NOT SPECIFIED' THEN 'forced' END AS basis FROM orders WHERE o_orderpriority <> '5-LOW'"


@workload("trace_exposure", PRIORITIES)
def trace_exposure(spark, d):
    return trace.exposure(*tasks_and_sites(spark, d))


@workload("trace_exposure_names_only", "SELECT 'name' AS basis, count(*) AS tasks, (SELECT count(*) FROM orders) AS all_tasks FROM orders")
def trace_exposure_names_only(spark, d):
    """The baseline by names marks every task, transcripts included."""
    tasks, sites_, found = tasks_and_sites(spark, d)
    rows = trace.exposure(tasks, sites_, found, rule="names_only")
    return rows.groupBy("basis").agg(F.count("*").alias("tasks")).crossJoin(tasks.agg(F.count("*").alias("all_tasks")))


@workload("trace_exposure_summary", f"SELECT tool, basis, count(*) AS exposed, grouping_id(tool, basis)::BIGINT AS level, bool_and(basis <> 'forced') AS bound FROM ({PRIORITIES}) GROUP BY GROUPING SETS ((tool, basis), (tool))")
def trace_exposure_summary(spark, d):
    """Bases never pool; the union is stated apart, and a count is a bound only when all rows are resolved."""
    rows = trace.exposure(*tasks_and_sites(spark, d))
    return spark.sql("SELECT tool, basis, count(*) AS exposed, grouping_id(tool, basis) AS level, bool_and(basis <> 'forced') AS bound FROM {rows} GROUP BY GROUPING SETS ((tool, basis), (tool))", rows=rows)


@workload("trace_fields", "SELECT * FROM (VALUES ('charge_order','pre.open','status','written_despite_guard'),('cancel_order','eff.stock','stock','not_written'),('cancel_order','eff.stock','reserved','not_written'),('revise_line','eff.discount','discount','not_written'),('revise_line','eff.tax','tax','not_written'),('revise_line','eff.quantity','quantity','not_written'),('retire_event','eff.gone','listed','not_written'),('post_event','eff.row','n_events','not_written')) f(tool, clause_id, path, direction)")
def trace_fields(spark, d):
    bad = [("charge_order", "pre.open"), ("cancel_order", "eff.stock"), ("revise_line", "eff.discount"), ("revise_line", "eff.tax"), ("revise_line", "eff.quantity"), ("retire_event", "eff.gone"), ("post_event", "eff.row")]
    clauses = clause_rows(spark, [t.contract for t in TOOLS.values()])
    return trace.fields(spark.createDataFrame(bad, "tool string, clause_id string"), clauses)


@workload("trace_fields_from_text", "SELECT * FROM (VALUES ('quoted','eff.x','post.note','not_written','string'),('quoted','eff.x','a.b','not_written','string'),('quoted','eff.x','note','not_written','compiled')) f(tool, clause_id, path, direction, source)")
def trace_fields_from_text(spark, d):
    """The baseline that reads paths from a predicate's text takes a quoted word for a path."""
    clauses = clause_rows(spark, [Contract("quoted", (Clause("eff.x", "post.note == 'a.b'"),))])
    bad = clauses.select("tool", "clause_id")
    text = trace.fields(bad, clauses, "string").withColumn("path", F.when(F.col("path") == "note", "post.note").otherwise(F.col("path"))).withColumn("source", F.lit("string"))
    return text.union(trace.fields(bad, clauses).withColumn("source", F.lit("compiled")))


EVALUATOR_NAMES = ["exact_status", "collection_only", "through_helpers", "too_deep", "by_constant", "computed", "told_so"]
KNOWN_PATHS = ["orders.status", "orders.total"]


@workload("trace_read_sites_hops", "SELECT * FROM (VALUES ('exact_status','orders.status','state',true,0),('collection_only','orders','state',true,0),('through_helpers','orders.total','state',true,3),('too_deep',NULL,'state',false,4),('by_constant','orders.status','state',true,0),('computed',NULL,'state',false,0),('told_so','last','transcript',true,0)) r(evaluator, path, target, resolved, hops)")
def trace_read_sites_hops(spark, d):
    """Read sites of the evaluators' sources: helpers are followed three hops, anything else is forced in."""
    found = trace.read_sites(code.nodes(code.source_rows(spark, code.EVALUATOR_SOURCES)), EVALUATOR_NAMES, KNOWN_PATHS)
    whole = F.col("path").isin("orders.status", "orders.total", "orders", "last") | F.col("path").isNull()
    return found.filter(whole)


GOLD = "SELECT DISTINCT l_orderkey AS task_id FROM lineitem WHERE l_returnflag = 'A'"


@workload("trace_gold_call", f"SELECT basis, count(*) AS exposed, count(g.task_id) AS gold_call FROM ({PRIORITIES}) e LEFT JOIN ({GOLD}) g USING (task_id) GROUP BY basis")
def trace_gold_call(spark, d):
    gold = load(spark, d, "lineitem").filter("l_returnflag = 'A'").select(F.col("l_orderkey").alias("task_id")).distinct().withColumn("g", F.lit(1))
    rows = trace.exposure(*tasks_and_sites(spark, d)).join(gold, "task_id", "left")
    return rows.groupBy("basis").agg(F.count("*").alias("exposed"), F.count("g").alias("gold_call"))


@workload("trace_exposed_vs_gold_setops", f"WITH e AS (SELECT task_id FROM ({PRIORITIES})), g AS ({GOLD}) SELECT (SELECT count(*) FROM (SELECT * FROM e INTERSECT SELECT * FROM g)) AS both_sets, (SELECT count(*) FROM (SELECT * FROM e EXCEPT SELECT * FROM g)) AS exposed_only, (SELECT count(*) FROM (SELECT * FROM g EXCEPT SELECT * FROM e)) AS gold_only")
def trace_exposed_vs_gold_setops(spark, d):
    """Exposed tasks and tasks that call the tool need not nest."""
    e = trace.exposure(*tasks_and_sites(spark, d)).select("task_id")
    g = load(spark, d, "lineitem").filter("l_returnflag = 'A'").select(F.col("l_orderkey").alias("task_id")).distinct()
    count = lambda df, name: df.agg(F.count("*").alias(name))
    return count(e.intersect(g), "both_sets").crossJoin(count(e.exceptAll(g), "exposed_only")).crossJoin(count(g.exceptAll(e), "gold_only"))


@workload("trace_levels", "SELECT count(*) AS tasks, count(*) FILTER (o_orderpriority <> '5-LOW') AS exposed, count(*) FILTER (reach) AS reaching, count(*) FILTER (reach AND o_orderpriority <> '5-LOW') AS both_levels FROM (SELECT o_orderpriority, o_orderkey IN (SELECT l_orderkey FROM lineitem WHERE l_returnflag = 'A') AND o_orderstatus <> 'O' AS reach FROM orders)")
def trace_levels(spark, d):
    """Exposed and reaching are separate facts of a task; neither is derived from the other."""
    tasks, sites_, found = tasks_and_sites(spark, d)
    exposed = trace.exposure(tasks, sites_, found).select("task_id").distinct().withColumn("exposed", F.lit(True))
    calls = load(spark, d, "lineitem").filter("l_returnflag = 'A'").select(F.col("l_orderkey").alias("task_id")).distinct().withColumn("calls", F.lit(True))
    rows = tasks.join(exposed, "task_id", "left").join(calls, "task_id", "left")
    reach = F.coalesce("calls", F.lit(False)) & (F.col("o_orderstatus") != "O")
    return rows.agg(F.count("*").alias("tasks"), F.count_if("exposed").alias("exposed"), F.count_if(reach).alias("reaching"), F.count_if(reach & F.coalesce("exposed", F.lit(False))).alias("both_levels"))


@workload("trace_statuses", "SELECT * FROM (VALUES ('CLIN','undefined',NULL::BIGINT),('CUST','counted',1135),('SECU-email','untraced',NULL),('MULTI','not_computable',NULL)) s(benchmark, status, exposed)")
def trace_statuses(spark, d):
    """Undefined, untraced and not computable are statuses; none of them is a zero."""
    rows = spark.createDataFrame([("CLIN", True, True, "transcript", None), ("CUST", True, True, "state", 1135), ("SECU-email", True, False, "state", None), ("MULTI", False, True, "state", None)], "benchmark string, reachable boolean, has_field boolean, graded string, n long")
    status = F.when(~F.col("reachable"), trace.NOT_COMPUTABLE).when(~F.col("has_field"), trace.UNTRACED).when(F.col("graded") != "state", trace.UNDEFINED).otherwise(trace.COUNTED)
    return rows.select("benchmark", status.alias("status"), F.when(status == trace.COUNTED, F.col("n")).alias("exposed"))


@workload("grader_grounding", "SELECT grounding, 'undefined' AS status, count(*) AS cases FROM (SELECT conv_id, CASE WHEN conv_id % 10 < 5 THEN 'none' WHEN conv_id % 10 < 7 THEN 'transcript' ELSE 'mixed' END AS grounding FROM conversations GROUP BY conv_id) GROUP BY 1")
def grader_grounding(spark, d):
    """Graders by what they read: none of these cases is graded on state alone, so no count is given."""
    r = F.col("conv_id") % 10
    reads = F.when(r < 5, F.array(F.lit("none"))).when(r < 7, F.array(F.lit("transcript"))).otherwise(F.array(F.lit("transcript"), F.lit("state")))
    cases = load(spark, d, "conversations").select("conv_id").distinct().select("conv_id", F.explode(reads).alias("target"))
    return trace.grounding(cases, "conv_id").groupBy("grounding", "status").agg(F.count("*").alias("cases"))


@workload("reader_containment", "SELECT 40::BIGINT AS functions, 22::BIGINT AS named, 22::BIGINT AS supersets, 1.75 AS median_ratio, 10.0 AS worst_ratio, 18::BIGINT AS named_none")
def reader_containment(spark, d):
    """A second reader's sites against the extractor's, for each function: containment and size ratio."""
    k = F.col("id")
    reader = F.when(k < 22, F.sequence(F.lit(1).cast("long"), F.when(k == 0, 1).otherwise(2).cast("long"))).otherwise(F.array().cast("array<bigint>"))
    extractor = F.sequence(F.lit(1).cast("long"), F.when(k == 0, 10).when(k < 12, 3).otherwise(4).cast("long"))
    rows = spark.range(40).select(reader.alias("a"), extractor.alias("b"))
    named = F.size("a") > 0
    ratio = F.when(named, F.size("b") / F.size("a"))
    return rows.agg(F.count("*").alias("functions"), F.count_if(named).alias("named"), F.count_if(named & (F.size(F.array_except("a", "b")) == 0) & (F.size("b") > F.size("a"))).alias("supersets"), F.percentile(ratio, 0.5).alias("median_ratio"), F.max(ratio).alias("worst_ratio"), F.count_if(~named).alias("named_none"))
