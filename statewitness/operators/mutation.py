"""Mutation arms: faults planted in tools of the desk, live filter, outcomes, miss diagnosis, escapes.

A mutant is an arm. It switches what a tool's call does through columns, so all mutants of a tool meet all
its probes in one job: arms are broadcast and crossed with the probes. The tool's patched code runs beside
them, and what it is flagged for is not held against a mutant. No call raises out of a job, so a mutant
that crashes its caller is outside this arm, and there is no reset path that a mutant could break.
"""

from __future__ import annotations

import re
from dataclasses import dataclass, replace
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from statewitness.operators import conformance as C

# Operators of the closed world, one for each class, and of the open world.
CLOSED = ("M-PHANTOM", "M-PRECOND", "M-IGNARG", "M-PARTIAL", "M-INVAR", "M-RESET")
OPEN = ("swap_comparison", "shift_constant", "swap_connective", "drop_assignment", "negate_guard")
DETECTED, MISSED, UNTESTABLE, ERROR = "detected", "missed", "untestable", "error"
NO_CLAUSE, NO_PROBE, CRASH = "no_clause", "probe_never_reveals", "crash"
TARGET_SIZE = 25

#: Tools of the closed-world arm: guards, several writes, one write, forwarded arguments.
CLOSED_TOOLS = ("charge_order", "hold_order", "retire_event", "append_turn", "tag_document", "set_quantity", "rename_region", "list_activity")
ORIGINAL, PRESERVING = "original", "preserving"
MUTANT = "arm string, tool string, operator string, site string, has_clause boolean"


@dataclass(frozen=True)
class Mutant:
    """A tool's patched code with one change, and whether a clause of its contract reads what was changed."""

    operator: str
    site: str
    tool: C.Tool
    has_clause: bool

    @property
    def arm(self) -> str:
        return f"{self.operator}:{self.site}"


def arguments_read(tool: C.Tool) -> list[str]:
    """Arguments that the patched code writes or forwards."""
    texts = [patched for _, patched in (*tool.writes.values(), tool.forwarded)]
    return [a for a in tool.args if any(re.search(rf"\bargs\.{a}\b", x) for x in texts)]


def closed_mutants(tool: C.Tool) -> list[Mutant]:
    """Every site of a tool that an operator of the closed world, or a rewriting without effect, applies to.

    Phantom: nothing is written. Precondition: one guard is gone. Ignored argument: its happy value is used
    for every value. Partial: one of several writes is gone. Invariant: a field that no effect is told of is
    stored in another form. Preserving: a write becomes a conditional with two like branches.
    """
    contract = tool.contract
    after = {p for c in (*contract.of("eff"), *contract.of("frame")) if not c.deferred for p in c.compiled.reads("post")}
    effects = {p for c in contract.of("eff") for p in c.compiled.reads("post")}
    told_args = {c.arg for c in contract.of("arg")} | {p.split(".")[1] for c in contract.of("eff") for p in c.compiled.reads("args")}
    code = {f: patched for f, (_, patched) in tool.writes.items()}
    out: list[Mutant] = []

    def add(operator: str, site: str, has_clause: bool, writes: dict[str, str] | None = None, **changed) -> None:
        sides = {f: (x, x) for f, x in (code if writes is None else {**code, **writes}).items()}
        out.append(Mutant(operator, site, replace(tool, writes=sides, **changed), has_clause))

    def kept(f: str) -> dict[str, str]:
        return {f: f"pre.{f}"}

    if code:
        add("M-PHANTOM", "all", bool(effects), reduce(lambda a, f: a | kept(f), code, {}))
    for n, g in enumerate(tool.guards):
        add("M-PRECOND", g.clause_id, any(c.clause_id == g.clause_id for c in contract.of("pre")), guards=tuple(replace(x, unpatched=k != n) for k, x in enumerate(tool.guards)))
    for a in arguments_read(tool):
        fixed = lambda x, a=a: re.sub(rf"\bargs\.{a}\b", lambda _: f"({tool.args[a]})", x)
        add("M-IGNARG", a, a in told_args, {f: fixed(x) for f, x in code.items()}, forwarded=(fixed(tool.forwarded[1]),) * 2)
    for f in code if len(code) > 1 else ():
        add("M-PARTIAL", f, f"post.{f}" in after or any(f"args.{a}" in code[f] and a in told_args for a in tool.args), kept(f))
    for f in UNTOLD.get(tool.name, ()):
        add("M-INVAR", f, f"post.{f}" in after, {f: f"{code.get(f, f'pre.{f}')} {UNTOLD[tool.name][f]}"})
    for f, x in code.items():
        add(PRESERVING, f, True, {f: f"if(length(cast({x} AS string)) > 2, {x}, {x})"})
    return [m if m.operator == "M-PRECOND" else replace_guards(m) for m in out]


#: Fields that no effect clause names, and how a mutant changes the form in which they are stored.
UNTOLD = {"charge_order": {"status": "|| '!'", "customer": "+ 1"}, "hold_order": {"note": "|| '!'"}, "append_turn": {"last_role": "|| '!'"}, "tag_document": {"last_quality": "+ 1"}}


def replace_guards(m: Mutant) -> Mutant:
    """The mutant with all guards in force, as in the patched code."""
    return replace(m, tool=replace(m.tool, guards=tuple(replace(g, unpatched=True) for g in m.tool.guards)))


def closed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Closed-world mutants, run: (tool, operator, site, has_clause, has_probe, flagged), preserving ones and originals too.

    ``flagged``: a clause is violated that the original keeps. ``has_probe``: some probe's call differs from the original's.
    """
    from statewitness.operators.desk import TOOLS

    parts = []
    for tool in (TOOLS[x] for x in CLOSED_TOOLS):
        mutants = closed_mutants(tool)
        codes = {ORIGINAL: (tool, 1), **{m.arm: (m.tool, 0) for m in mutants}}
        calls, seen = C.probe_rows(tool, tool.slice(spark, sf_dir)), F.struct("ok", "digest")
        calls = C.invoke(tool, calls, {ORIGINAL: (tool, 1)}).select(*calls.columns, seen.alias("known"))
        tuples = C.invoke(tool, calls, codes)
        rows = C.clause_rows(tool, tuples).select("arm", "clause_id", "held")
        if tool.variants:
            rows = rows.unionByName(C.variant_rows(tool, tuples).select("arm", "clause_id", "held"))
        per = rows.groupBy("clause_id", "arm").agg(F.bool_or(~F.col("held")).alias("broken"))  # clauses times arms: few rows
        before = F.max(F.when(F.col("arm") == ORIGINAL, F.col("broken"))).over(Window.partitionBy("clause_id"))
        per = per.select("arm", (F.col("broken") & ((F.col("arm") == ORIGINAL) | ~F.coalesce(before, F.lit(False)))).alias("flagged"))
        flagged = per.groupBy("arm").agg(F.bool_or("flagged").alias("flagged"))
        live = tuples.groupBy("arm").agg(F.bool_or(seen != F.col("known")).alias("has_probe"))
        listed = [(ORIGINAL, tool.name, ORIGINAL, "all", True), *[(m.arm, tool.name, m.operator, m.site, m.has_clause) for m in mutants]]
        out = spark.createDataFrame(listed, MUTANT).join(F.broadcast(flagged), "arm", "left").join(F.broadcast(live), "arm", "left")
        parts.append(out.select("tool", "operator", "site", "has_clause", F.coalesce("has_probe", F.lit(False)).alias("has_probe"), F.coalesce("flagged", F.lit(False)).alias("flagged")))
    return reduce(DataFrame.unionByName, parts)


def drawn(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The mutants of the six classes, without originals and preserving rewritings."""
    return closed(spark, sf_dir).filter(F.col("operator").isin(*CLOSED)).withColumn("crashes", F.lit(False))


def outcome(absorbed: str = "detected") -> Column:
    """Detected means flagged; a raw exception is an error, apart from a miss.

    Whether a crash that the host absorbed counts as found is not settled, so it is a parameter
    ('detected' or 'silent'), and both bounds can be given.
    """
    crash = F.lit(ERROR) if absorbed == "silent" else F.when(F.col("flagged"), DETECTED).otherwise(ERROR)
    return F.when(F.col("crashes"), crash).when(F.col("flagged"), DETECTED).otherwise(MISSED)


def diagnosis() -> Column:
    """Why a miss was missed."""
    return F.when(~F.col("has_clause"), NO_CLAUSE).when(~F.col("has_probe"), NO_PROBE).otherwise("other")


def mutated_price(price: Column, mutant: Column) -> tuple[Column, Column]:
    """(price after, error) of a repricing under an open-world mutant: raise by 10 if the price is above 1000 and the part is not free."""
    guard = F.when(mutant == "swap_comparison", price < 1000).when(mutant == "shift_constant", price > 1001).when(mutant == "swap_connective", (price > 1000) | (price != 0)).when(mutant == "negate_guard", ~((price > 1000) & (price != 0))).otherwise((price > 1000) & (price != 0))
    raised = F.when(mutant == "drop_assignment", price).otherwise(price + 10)
    return F.when(guard, raised).otherwise(price), F.lit(None).cast("string")


def open_outcomes(parts: DataFrame, mutants: DataFrame) -> DataFrame:
    """(operator, pairs, differing, live, caught): a mutant is live where some probe's tuple differs from the original's.

    The contract's only effect clause says that a price never falls, so it catches few of them.
    """
    original, _ = mutated_price(F.col("price"), F.lit("none"))
    rows = parts.crossJoin(F.broadcast(mutants))
    after, _ = mutated_price(F.col("price"), F.col("operator"))
    rows = rows.select("operator", (after != original).alias("differs"), (after < F.col("price")).alias("violates"))
    per = rows.groupBy("operator").agg(F.count("*").alias("pairs"), F.count_if("differs").alias("differing"), F.bool_or("violates").alias("caught"))
    return per.select("operator", "pairs", "differing", (F.col("differing") > 0).alias("live"), "caught")


def recall_table(outcomes: DataFrame) -> DataFrame:
    """Counts of outcomes for each operator; all of them stay in the denominator."""
    return outcomes.groupBy("operator").agg(F.count("*").alias("n"), *[F.count_if(F.col("outcome") == o).alias(o) for o in (DETECTED, MISSED, UNTESTABLE, ERROR)])


def negative_controls() -> list[tuple[str, str, bool]]:
    """(control, tool, predicted to be flagged), fixed before the run."""
    return [("same_value", "set_quantity", False), ("append_twice", "tag_document", True), ("list_replace", "swap_lines", True), ("two_encodings_number", "top_up_customer", False), ("two_encodings_time", "stamp_ship", False)]


def control_flags(spark: SparkSession, sf_dir: str, rule: str = "state_only") -> DataFrame:
    """(control, flagged, predicted, as_predicted) of the five negative controls, run through the variant rule."""
    from statewitness.operators.desk import TOOLS

    variants = {
        "same_value": {"quantity": ("pre.quantity", "pre.quantity + 0.0D")},
        "append_twice": {"quality": ("1", "0")},
        "two_encodings_number": {"amount": ("2.0D", "cast(2 AS double)")},
        "two_encodings_time": {"iso": ("'2024-03-01T10:00'", "'2024-03-01T10:00:00'")},
    }
    parts = []
    for name, tool_name, predicted in negative_controls():
        tool = TOOLS[tool_name]
        if not tool.synthesizer:
            flagged = spark.range(1).select(F.lit(False).alias("flagged"))
        else:
            tool = replace(tool, variants=variants[name], falsy={})
            calls = C.invoke(tool, C.probe_rows(tool, tool.slice(spark, sf_dir)))
            if name == "same_value":
                # two calls with distinct values that both equal the state: the state, and nothing to change
                calls = calls.withColumn("args", F.col("args").withField("quantity", F.concat(F.col("args.quantity").cast("string"), F.when(F.col("variant_no") == 1, "0").otherwise(""))))
            sets = C.variant_rows(tool, calls.filter("arm = 'unpatched'"), rule)
            flagged = sets.agg(F.coalesce(F.bool_or(~F.col("held")), F.lit(False)).alias("flagged"))
        parts.append(flagged.select(F.lit(name).alias("control"), "flagged", F.lit(predicted).alias("predicted")))
    out = parts[0]
    for more in parts[1:]:
        out = out.union(more)
    return out.select("control", "flagged", "predicted", (F.col("flagged") == F.col("predicted")).alias("as_predicted"))
