"""Grammar, validator, statistics, plans, scan and invariance."""

import gc
import weakref

import numpy as np
import pytest
from pyspark.sql import functions as F

from conftest import SF
from statewitness import registry
from statewitness.functions import joins
from statewitness.llm.arrow_text import tidied
from statewitness.functions.joins import as_of, range_join
from statewitness.functions.state import table_digest, wide_digest
from statewitness.functions.stats import clustering, wilson_value
from statewitness.operators import conformance as C
from statewitness.operators.contract import from_json, to_json
from statewitness.operators.desk import TOOLS
from statewitness.operators.grammar import GrammarError, compile_predicate
from statewitness.sources import contracts as files
from statewitness.sources.tables import load
from statewitness.streaming import monitor as S


@pytest.mark.parametrize(("k", "n", "eff", "want"), [(5, 7, 7, 0.359), (1, 7, 5, 0.020), (4, 21, 15.13, 0.066), (1, 8, 6, 0.018), (0, 8, 8, 0.0), (25, 25, 25, 0.867), (225, 229, 229, 0.956)])
def test_published_lower_limits(k, n, eff, want):
    assert round(wilson_value(k, n, eff), 3) == want


def test_no_data_has_no_limit():
    assert wilson_value(0, 0) is None


def test_mean_cluster_size_gives_published_effective_sizes(spark):
    rows = [("a", c, int(c == 0)) for c, m in enumerate((3, 1, 1, 1, 1)) for _ in range(m)]
    out = clustering(spark.createDataFrame(rows, "g string, c int, y int"), "c", "y", ["g"]).first()
    assert out["icc"] == pytest.approx(1.0) and out["n_effective"] == pytest.approx(5.0)


@pytest.mark.parametrize("text", ["__import__('os')", "pre.x.y()", "total == 1", "lambda: 1", "pre.x if pre.y else 1", "[x for x in pre.l]", "any(pre.l == 1 for pre in pre.l)", "pre.x == "])
def test_grammar_refuses(text):
    with pytest.raises(GrammarError):
        compile_predicate(text)


def test_grammar_compiles_the_worked_example(spark):
    c = compile_predicate("any(l.status == 'O' for l in pre.lines if l.id == args.line)")
    assert c.paths == ("pre.lines", "pre.lines.status", "args.line", "pre.lines.id") or set(c.paths) == {"pre.lines", "pre.lines.status", "pre.lines.id", "args.line"}
    rows = spark.sql("SELECT named_struct('lines', array(named_struct('id', 1, 'status', 'O'), named_struct('id', 2, 'status', 'F'))) AS pre, named_struct('line', x) AS args FROM VALUES (1), (2), (3) t(x)")
    assert [r[0] for r in rows.select(c.column).collect()] == [True, False, False]


def test_contract_files_round_trip(spark, tmp_path):
    kept = [t.contract for t in TOOLS.values()]
    files.write(kept, str(tmp_path))
    assert from_json(to_json(kept[0])) == kept[0]
    spark.dataSource.register(files.ContractSource)
    a = spark.read.format("tool_contract").load(str(tmp_path)).collect()
    assert sorted(map(tuple, a), key=str) == sorted(map(tuple, files.load(spark, str(tmp_path)).collect()), key=str)
    assert len(a) == sum(len(c.clauses) for c in kept)


def test_patched_arm_of_every_planted_tool_conforms(spark):
    for name in ("charge_order", "cancel_order", "post_event", "register_customer"):
        rows = C.verdicts(spark, SF, TOOLS[name]).collect()
        assert {r["verdict"] for r in rows if r["arm"] == "patched"} <= {"conforms"}
        assert "violates" in {r["verdict"] for r in rows if r["arm"] == "unpatched"}


def test_partial_rule_of_the_table_needs_an_effect_that_held(spark):
    rows = C.verdicts(spark, SF, TOOLS["post_event"], partial="table").filter("arm = 'unpatched'").first()
    assert rows["classes"] == "claimed_not_written"


def test_guard_filters_reach_the_scan(spark):
    plan = registry.queries()["op_scan_pushdown"](spark, SF)._jdf.queryExecution().toString()
    pushed = plan.split("PushedFilters: [")[1]
    assert "o_orderstatus" in pushed and "ReadSchema: struct<o_orderkey:bigint,o_custkey:bigint,o_orderstatus:string,o_totalprice:double>" in pushed
    plan = registry.queries()["op_scan_prune"](spark, SF)._jdf.queryExecution().toString()
    assert "ReadSchema: struct<l_orderkey:bigint,l_returnflag:string,l_linestatus:string>" in plan


def test_verdict_plans_stay_in_the_jvm(spark):
    plan = C.verdicts(spark, SF, TOOLS["charge_order"])._jdf.queryExecution().toString()
    assert "Python" not in plan and "CartesianProduct" not in plan


def test_results_do_not_hang_on_partitioning(spark):
    name, before = "verdict_unenforced_charge", spark.conf.get("spark.sql.shuffle.partitions")
    want = sorted(map(str, registry.queries()[name](spark, SF).collect()))
    try:
        for n in ("1", "7"):
            spark.conf.set("spark.sql.shuffle.partitions", n)
            assert sorted(map(str, registry.queries()[name](spark, SF).collect())) == want
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)


def test_digests_agree_with_row_differences(spark):
    a = load(spark, SF, "orders").select("o_orderkey", "o_orderstatus")
    b = a.withColumn("o_orderstatus", F.when(F.col("o_orderkey") == a.agg(F.min("o_orderkey")).first()[0], "X").otherwise(F.col("o_orderstatus")))
    for digest in (table_digest, wide_digest):
        one, same, other = (digest(x, a.columns).first() for x in (a, a.repartition(5), b))
        assert one == same and one != other
    assert a.exceptAll(b).count() == 1


def test_as_of_and_range_joins_against_brute_force(spark):
    left = spark.createDataFrame([("u", 1), ("u", 5), ("v", 2)], "g string, t int")
    right = spark.createDataFrame([("u", 1, 10), ("u", 4, 40), ("v", 3, 30)], "g string, rt int, x int")
    back = {(r["g"], r["t"]): r["x"] for r in as_of(left, right, ["g"], "t", "rt", "x").collect()}
    ahead = {(r["g"], r["t"]): r["x"] for r in as_of(left, right, ["g"], "t", "rt", "x", "forward").collect()}
    assert back == {("u", 1): 10, ("u", 5): 40, ("v", 2): None}
    assert ahead == {("u", 1): 10, ("u", 5): None, ("v", 2): 30}
    points = spark.createDataFrame([(float(x),) for x in range(20)], "p double")
    ranges = spark.createDataFrame([("a", 0.0, 7.0), ("b", 5.0, 18.5)], "n string, lo double, hi double")
    got = {(r["p"], r["n"]) for r in range_join(points, "p", ranges, "lo", "hi", 4.0).collect()}
    assert got == {(float(p), n) for p in range(20) for n, lo, hi in (("a", 0, 7), ("b", 5, 18.5)) if lo <= p < hi}


def test_raw_dedup_leaves_list_tools_untestable(spark):
    raw = C.verdicts(spark, SF, TOOLS["share_conversation"], dedup_mode="raw").select("verdict", "reason").distinct().collect()
    assert [tuple(r) for r in raw] == [("untestable", "adapter_unsupported")]
    fixed = C.verdicts(spark, SF, TOOLS["share_conversation"]).select("verdict").distinct().collect()
    assert [r[0] for r in fixed] == ["conforms"]


def test_complete_streams_leave_no_rows_at_the_driver(spark, tmp_path):
    rows = spark.sql("SELECT id AS event_id, TIMESTAMP_NTZ'2024-01-01' + make_dt_interval(0, int(id) * 4) AS ts, id % 2 AS user_id, 'view' AS event_type, 1.0D AS value, '' AS props FROM range(6)")
    rows.write.parquet(f"{tmp_path}/some/events.parquet")
    rows.limit(0).write.parquet(f"{tmp_path}/none/events.parquet")
    before = {t.name for t in spark.catalog.listTables()}
    got = S.drained(S.sessions(S.event_stream(spark, f"{tmp_path}/some"), "9 hours"), "complete")
    assert sorted((r["user_id"], r["n"]) for r in got.collect()) == [(0, 3), (1, 3)] and got.inputFiles()
    assert S.drained(S.sessions(S.event_stream(spark, f"{tmp_path}/none")), "complete").count() == 0
    assert {t.name for t in spark.catalog.listTables()} == before


def test_nearest_vectors_with_ties_copies_blocks_and_odd_rows(spark, monkeypatch):
    rng = np.random.default_rng(4)
    base = rng.standard_normal((40, 8)).astype(np.float32)
    rows = [(k, base[k % 40].tolist()) for k in rng.permutation(300).tolist()] + [(k, base[3].tolist()) for k in range(300, 340)] + [(340, (2 * base[3]).tolist())]

    def brute(rows):
        out, m = {}, {k: np.array(v, np.float64) for k, v in rows}
        total = lambda a, b: float(np.cumsum(a * b)[-1])
        for q in (k for k in m if k % 20 == 0):
            scored = [(-total(m[v], m[q]) / np.sqrt(total(m[v], m[v]) * total(m[q], m[q])), v) for v in m if v != q]
            out |= {(q, r + 1): v for r, (_, v) in enumerate(sorted(scored)[:5])}
        return out

    for name, value in (("QUERY_BLOCK", 6), ("QUERY_CHUNK", 3), ("VECTOR_CHUNK", 50)):
        monkeypatch.setattr(joins, name, value)
    for parts in (1, 5):
        df = spark.createDataFrame(rows, "vec_id long, embedding array<float>").repartition(parts)
        out = joins.nearest_vectors(df.filter("vec_id % 20 = 0"), df, 5)
        assert {(r["query"], r["rank"]): r["vec_id"] for r in out.collect()} == brute(rows)
        assert "CrossJoin" not in (plan := out._jdf.queryExecution().toString()) and "NestedLoop" not in plan  # no row for each pair
    df = spark.createDataFrame([*rows[:30], (990, None)], "vec_id long, embedding array<float>")
    out = joins.nearest_vectors(df.filter("vec_id % 20 = 0 AND embedding IS NOT NULL"), df, 5)
    assert {(r["query"], r["rank"]): r["vec_id"] for r in out.collect()} == brute(rows[:30])


READS_TABLES = ("biconditional_share", "contract_drafts", "contract_validator", "coverage_totals", "dead_rules", "disclosure_status", "grader_ungrounded", "headline_cells", "ledger_adjudicated", "ledger_append_idempotent", "ledger_units_rollup", "mutation_recall_wilson")


@pytest.mark.parametrize("name", READS_TABLES)
def test_input_comes_from_tables(spark, name):
    assert registry.queries()[name](spark, SF).inputFiles()


def test_workers_free_what_a_task_left_in_cycles():
    class Held:
        def __init__(self):
            self.me = self

    seen = []

    def run(batches):
        seen.append(weakref.ref(Held()))
        yield from batches

    gc.disable()
    try:
        assert list(tidied(run)(iter([1, 2]))) == [1, 2] and seen[0]() is None
    finally:
        gc.enable()
