"""The dynamic conformance check: probes, invocation on two arms, clause verdicts, classes, rollup.

A tool is a transformation of rows: ``pre`` and ``args`` structs in, ``post``, success, error and message
out. Probes are rows, arms are rows; one job runs every probe of a tool on both arms. A fresh environment
for each probe costs nothing, since rows never change in place, and a call's state is the slice that it
touches, not the whole snapshot.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from statewitness.operators.contract import Contract

ARMS = ("unpatched", "patched")
# Engine labels of the six classes and of the evaluator-layer property.
PHANTOM, UNENFORCED, IGNORED, PARTIAL, INVARIANT, RESET, UNGROUNDED = "claimed_not_written", "guard_not_enforced", "argument_inert", "half_applied", "invariant_broken", "reset_residue", "claim_graded"
CONFORMS, VIOLATES, UNTESTABLE = "conforms", "violates", "untestable"
NO_STATE, TYPE_ERROR, NO_RESET, UNSUPPORTED = "no_observable_state", "predicate_type_error", "no_reset_path", "adapter_unsupported"


@dataclass(frozen=True)
class Guard:
    """A precondition in the implementation; the unpatched arm may have lost it."""

    clause_id: str
    condition: str
    unpatched: bool = True


@dataclass(frozen=True)
class Tool:
    """What a tool advertises (its contract) and what it does (SQL expressions over pre and args, by arm)."""

    name: str
    contract: Contract
    slice: Callable[[SparkSession, str], DataFrame]  # grp, key, pre
    args: dict[str, str]  # argument -> value on the happy call
    writes: dict[str, tuple[str, str]] = field(default_factory=dict)  # state field -> (unpatched, patched)
    guards: tuple[Guard, ...] = ()
    message: str = "'done'"
    variants: dict[str, tuple[str, ...]] = field(default_factory=dict)
    falsy: dict[str, str] = field(default_factory=dict)
    falsify: dict[str, dict[str, str]] = field(default_factory=dict)  # precondition -> arguments that break it
    forwarded: tuple[str, str] = ("''", "''")
    observe: str = "state"
    population: str = "anchor"
    candidate: bool = False
    list_args: bool = False
    synthesizer: bool = True


# --- probes -----------------------------------------------------------------------------------------


def args_struct(tool: Tool, changed: dict[str, str] | None = None) -> Column:
    values = {**tool.args, **(changed or {})}
    return F.struct(*[F.expr(v).alias(k) for k, v in values.items()])


def holds_all(tool: Tool) -> Column:
    found = [c.compiled.column for c in tool.contract.of("pre")]
    return reduce(lambda a, b: a & b, found) if found else F.lit(True)


def probe_rows(tool: Tool, state: DataFrame) -> DataFrame:
    """Probe plan of a tool over its slice: one pass of conditional aggregates for each group.

    A happy call; for each precondition a call that falsifies it; for each effective argument calls that
    differ in it alone; a joint-falsy call where two or more effective arguments admit a falsy value.
    """
    rows = state.withColumn("args", args_struct(tool))
    chosen = F.struct("key", "pre")
    picks = [F.min_by(chosen, F.when(holds_all(tool), F.col("key"))).alias("happy")]
    searched = [c for c in tool.contract.of("pre") if c.clause_id not in tool.falsify]
    picks += [F.min_by(chosen, F.when(~c.compiled.column, F.col("key"))).alias(f"false_{k}") for k, c in enumerate(searched)]
    picked = rows.groupBy("grp").agg(*picks)
    plans: list[tuple[str, Column, str | None, str | None, int, dict[str, str]]] = [("happy", F.col("happy"), None, None, 0, {})]
    plans += [("falsify", F.col(f"false_{k}"), c.clause_id, None, 0, {}) for k, c in enumerate(searched)]
    plans += [("falsify", F.col("happy"), c, None, 0, change) for c, change in tool.falsify.items()]
    for arg, values in tool.variants.items():
        plans += [("variant", F.col("happy"), None, arg, n, {arg: v}) for n, v in enumerate(values)]
    if len(tool.falsy) > 1:
        plans.append(("joint_falsy", F.col("happy"), None, None, 0, tool.falsy))
    kinds = [F.struct(F.lit(n).alias("plan"), at.alias("at"), F.lit(purpose).alias("purpose"), F.lit(clause).cast("string").alias("target"), F.lit(arg).cast("string").alias("arg_name"), F.lit(variant).alias("variant_no")) for n, (purpose, at, clause, arg, variant, _) in enumerate(plans)]
    told = ("plan", "purpose", "target", "arg_name", "variant_no")
    out = picked.select("grp", F.explode(F.array(*kinds)).alias("p")).filter("p.at.key IS NOT NULL").select("grp", "p.at.key", "p.at.pre", *[f"p.{x}" for x in told])
    return out.select("grp", "key", "pre", planned_args(tool, [change for *_, change in plans]).alias("args"), *told)


def planned_args(tool: Tool, changes: list[dict[str, str]]) -> Column:
    """The arguments of each planned call: a value of its own where the plan changes one, else the happy value."""
    fields = []
    for name, happy in tool.args.items():
        value = F.expr(happy)
        for n, change in enumerate(changes):
            if change.get(name, happy) != happy:
                value = F.when(F.col("plan") == n, F.expr(change[name])).otherwise(value)
        fields.append(value.alias(name))
    return F.struct(*fields)


def canonical(args: Column) -> Column:
    """Canonical JSON of an argument struct (text, so 2 and 2.0 stay apart)."""
    return F.to_json(args)


def dedup(probes: DataFrame, mode: str = "canonical") -> DataFrame:
    """Drop repeated probes of a group. ``raw`` can't hash list-valued arguments and marks them unsupported."""
    keyed = probes.withColumn("args_json", canonical(F.col("args")))
    if mode == "raw":
        listed = any(t.dataType.typeName() == "array" for t in probes.schema["args"].dataType.fields)
        return keyed.withColumn("reason", F.lit(UNSUPPORTED if listed else None).cast("string"))
    return keyed.dropDuplicates(["grp", "key", "purpose", "target", "arg_name", "args_json"]).withColumn("reason", F.lit(None).cast("string"))


# --- invocation -------------------------------------------------------------------------------------


def by_code(codes: dict[str, tuple[Tool, int]], of: Callable[[Tool], tuple[str, str]]) -> Column:
    """The expression that each arm's code has at one place; one expression where all arms agree."""
    texts = {arm: of(tool)[side] for arm, (tool, side) in codes.items()}
    *some, last = texts
    if len(set(texts.values())) == 1:
        return F.expr(texts[last])
    out = F.expr(texts[last])
    for arm in some:
        if texts[arm] != texts[last]:
            out = F.when(F.col("arm") == arm, F.expr(texts[arm])).otherwise(out)
    return out


def invoke(tool: Tool, calls: DataFrame, codes: dict[str, tuple[Tool, int]] | None = None) -> DataFrame:
    """Call tuples on all arms: post, error, ok, message, delta, forwarded and digests.

    An arm runs a tool's unpatched (0) or patched (1) code; ``codes`` names other arms, such as mutants of ``tool``.
    """
    codes = codes or {ARMS[0]: (tool, 0), ARMS[1]: (tool, 1)}
    arms = calls.sparkSession.createDataFrame([(a,) for a in codes], "arm string")
    rows = calls.crossJoin(F.broadcast(arms))
    error = F.lit(None).cast("string")
    for n, g in reversed(list(enumerate(tool.guards))):
        on = [arm for arm, (code, side) in codes.items() if side or code.guards[n].unpatched]
        enforced = F.lit(True) if len(on) == len(codes) else F.col("arm").isin(on)
        error = F.when(enforced & ~F.expr(g.condition), F.lit(f"{tool.contract.on_violation}: {g.clause_id}")).otherwise(error)
    rows = rows.withColumn("error", error)
    fields = calls.schema["pre"].dataType.fieldNames()
    new = [by_code(codes, lambda x, f=f: x.writes.get(f, (f"pre.{f}", f"pre.{f}"))).alias(f) for f in fields]
    post = F.when(F.col("error").isNull(), F.struct(*new)).otherwise(F.col("pre"))
    rows = rows.withColumn("post", post).withColumn("ok", F.col("error").isNull()).withColumn("message", F.when(F.col("ok"), F.expr(tool.message)))
    rows = rows.withColumn("forwarded", F.when(F.col("ok"), by_code(codes, lambda x: x.forwarded)))
    changes = [F.when(~F.col(f"pre.{f}").eqNullSafe(F.col(f"post.{f}")), F.struct(F.lit(f).alias("field"), F.col(f"pre.{f}").cast("string").alias("before"), F.col(f"post.{f}").cast("string").alias("after"))) for f in fields]
    rows = rows.withColumn("delta", F.filter(F.array(*changes), lambda x: x.isNotNull()))
    seen = F.to_json("post") if tool.observe == "state" else F.col("forwarded")
    return rows.withColumn("digest", F.md5(seen))


# --- verdicts ---------------------------------------------------------------------------------------


def clause_rows(tool: Tool, tuples: DataFrame, rule: str = "verdict") -> DataFrame:
    """(arm, grp, purpose, clause_id, held, classes) for effects, frames and preconditions of each call.

    ``rule='verdict'``: a failing effect clause that reads no effective argument is a partial effect;
    ``rule='table'``: only if another effect clause of the same call holds.
    """
    c = tool.contract
    effects, parts = c.of("eff"), []
    good = F.col("ok") & holds_all(tool)
    told = [e for e in effects if not e.deferred]
    any_held = reduce(lambda a, b: a | b, [F.coalesce(e.compiled.column, F.lit(False)) for e in told]) if told else F.lit(False)
    phantom = good & ~any_held if c.biconditional and told else F.lit(False)
    for e in effects:
        if e.deferred:
            continue
        held = e.compiled.column
        own = F.lit(IGNORED) if c.reads_effective(e) else F.when(F.lit(rule == "verdict") | any_held, F.lit(PARTIAL))
        classes = F.array_compact(F.array(F.when(~held, own), F.when(~held & phantom, F.lit(PHANTOM))))
        parts.append(F.when(good, F.struct(F.lit(e.clause_id).alias("clause_id"), held.alias("held"), classes.alias("classes"))))
    failed_effect = reduce(lambda a, b: a | b, [~e.compiled.column for e in told]) if told else F.lit(False)
    for f in c.of("frame"):
        held = f.compiled.column
        classes = F.array_compact(F.array(F.when(~held & failed_effect, F.lit(PARTIAL))))
        parts.append(F.when(good & (F.col("purpose") == "happy"), F.struct(F.lit(f.clause_id).alias("clause_id"), held.alias("held"), classes.alias("classes"))))
    for p in c.of("pre"):
        broken = F.col("ok") | (F.size("delta") > 0)
        classes = F.array_compact(F.array(F.when(broken, F.lit(UNENFORCED))))
        parts.append(F.when((F.col("purpose") == "falsify") & (F.col("target") == p.clause_id), F.struct(F.lit(p.clause_id).alias("clause_id"), (~broken).alias("held"), classes.alias("classes"))))
    if not parts:
        return tuples.sparkSession.createDataFrame([], "arm string, grp string, purpose string, clause_id string, held boolean, classes array<string>")
    rows = tuples.withColumn("c", F.explode(F.array_compact(F.array(*parts))))
    return rows.select("arm", "grp", "purpose", "c.clause_id", "c.held", "c.classes")


def variant_rows(tool: Tool, tuples: DataFrame, rule: str = "state_only", distinct: str = "value") -> DataFrame:
    """The ignored-argument rule on variant sets: (arm, grp, clause_id, held, classes, aggravated).

    ``state_only`` looks at the observable alone; ``conjunctive`` also wants the message invariant;
    ``footprint`` fires only for values that differ from each other in canonical form and from the state.
    ``distinct='value'`` compares numbers by value (2 and 2.0 are one), ``'typed'`` by their JSON text.
    """
    if not tool.variants:
        return tuples.sparkSession.createDataFrame([], "arm string, grp string, clause_id string, held boolean, classes array<string>, aggravated boolean")
    parts = []
    for arg in tool.variants:
        value = F.col(f"args.{arg}").cast("string") if distinct == "value" else F.get_json_object(canonical(F.col("args")), f"$.{arg}")
        rows = tuples.filter((F.col("purpose") == "variant") & (F.col("arg_name") == arg) & F.col("ok")).withColumn("v", value)
        if rule == "footprint":
            fields = tuples.schema["pre"].dataType.fieldNames()
            field_name = arg if arg in fields else None
            if field_name:
                rows = rows.filter(~F.col("v").eqNullSafe(F.col(f"pre.{field_name}").cast("string")))
            rows = rows.withColumn("v", F.regexp_replace("v", r"T(\d\d:\d\d):00$", "T$1"))
        sets = rows.groupBy("arm", "grp").agg(F.countDistinct("v").alias("values"), F.countDistinct("digest").alias("states"), F.countDistinct("message").alias("messages"))
        fired = F.col("states") == 1
        if rule == "conjunctive":
            fired = fired & (F.col("messages") <= 1)
        sets = sets.filter("values >= 2")
        parts.append(sets.select("arm", F.col("grp").cast("string").alias("grp"), F.lit(f"arg.{arg}").alias("clause_id"), (~fired).alias("held"), F.array_compact(F.array(F.when(fired, F.lit(IGNORED)))).alias("classes"), (fired & (F.col("messages") > 1)).alias("aggravated")))
    return reduce(DataFrame.unionByName, parts)


def verdicts(spark: SparkSession, sf_dir: str, tool: Tool, rule: str = "state_only", partial: str = "verdict", dedup_mode: str = "canonical") -> DataFrame:
    """One row for each clause and arm: groups evaluated, groups failing, verdict, reason, classes."""
    names = [c for k in ("pre", "eff", "frame", "arg") for c in tool.contract.of(k)]
    listed = spark.createDataFrame([(tool.name, a, c.clause_id) for a in ARMS for c in names], "tool string, arm string, clause_id string")
    stopped = not tool.synthesizer or (tool.list_args and dedup_mode == "raw")
    if stopped:
        return listed.select("tool", "arm", "clause_id", F.lit(0).cast("long").alias("n_groups"), F.lit(0).cast("long").alias("n_failed"), F.lit(UNTESTABLE).alias("verdict"), F.lit(UNSUPPORTED).alias("reason"), F.lit("").alias("classes"))
    tuples = invoke(tool, probe_rows(tool, tool.slice(spark, sf_dir)))
    rows = clause_rows(tool, tuples, partial).select("arm", F.col("grp").cast("string").alias("grp"), "clause_id", "held", "classes")
    if tool.variants:
        rows = rows.unionByName(variant_rows(tool, tuples, rule).drop("aggravated"))
    per = rows.groupBy("arm", "clause_id").agg(
        F.countDistinct("grp").alias("n_groups"),
        F.countDistinct(F.when(~F.col("held"), F.col("grp"))).alias("n_failed"),
        F.array_join(F.sort_array(F.array_distinct(F.flatten(F.collect_set("classes")))), ",").alias("classes"),
    )
    out = listed.join(F.broadcast(per), ["arm", "clause_id"], "left")
    verdict = F.when(F.coalesce("n_failed", F.lit(0)) > 0, VIOLATES).when(F.coalesce("n_groups", F.lit(0)) > 0, CONFORMS).otherwise(UNTESTABLE)
    return out.select("tool", "arm", "clause_id", F.coalesce("n_groups", F.lit(0)).alias("n_groups"), F.coalesce("n_failed", F.lit(0)).alias("n_failed"), verdict.alias("verdict"), F.when(verdict == UNTESTABLE, F.lit(NO_STATE)).alias("reason"), F.coalesce("classes", F.lit("")).alias("classes"))


def rollup(clause_verdicts: DataFrame) -> DataFrame:
    """Tool verdicts: any violation violates; nothing gradable is untestable; else conforms, ungraded counted."""
    return clause_verdicts.groupBy("tool", "arm").agg(
        F.count("*").alias("n_clauses"),
        F.count_if(F.col("verdict") == UNTESTABLE).alias("n_untestable"),
        F.when(F.bool_or(F.col("verdict") == VIOLATES), VIOLATES).when(F.bool_and(F.col("verdict") == UNTESTABLE), UNTESTABLE).otherwise(CONFORMS).alias("verdict"),
    )
