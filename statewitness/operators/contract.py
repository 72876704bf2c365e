"""Contracts: clauses with provenance, grounding tiers, drafts, and the validator."""

from __future__ import annotations

import json
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from statewitness.operators.grammar import Compiled, GrammarError, compile_predicate

KINDS = ("pre", "eff", "frame", "arg", "inv")
# Surfaces and the tier that each belongs to.
AGENT_VISIBLE = ("docstring", "schema", "prompt", "tool_return", "readme", "standard")
MAINTAINER_ANNOTATED = ("comment", "log", "todo")
TIERS = ("agent-visible", "maintainer-annotated", "author-assigned")
#: Surfaces whose visibility is tested rather than presumed.
TESTED_SURFACES = ("tool_return", "prompt")


def tier_of(surface: F.Column) -> F.Column:
    return F.when(surface.isin(*AGENT_VISIBLE), TIERS[0]).when(surface.isin(*MAINTAINER_ANNOTATED), TIERS[1]).otherwise(TIERS[2])


def clause_name(kind: str, what: F.Column, draft: F.Column) -> F.Column:
    """The id of a clause about ``what``, with a draft's suffix."""
    return F.concat(F.lit(f"{kind}."), what.cast("string"), F.when(draft, "_draft").otherwise(""))


def is_draft(clause_id: F.Column) -> F.Column:
    return clause_id.endswith("_draft")


@dataclass(frozen=True)
class Provenance:
    surface: str | None = None
    file: str | None = None
    line: int | None = None
    quote: str | None = None
    commit: str | None = None


@dataclass(frozen=True)
class Clause:
    clause_id: str
    predicate: str = "True"
    provenance: Provenance = Provenance()
    arg: str | None = None
    deferred: bool = False

    @property
    def kind(self) -> str:
        return self.clause_id.split(".")[0]

    @property
    def draft(self) -> bool:
        return self.clause_id.endswith("_draft")

    @property
    def inferred(self) -> bool:
        """Draft and author-assigned clauses alike."""
        return self.draft or self.provenance.surface is None

    @property
    def compiled(self) -> Compiled:
        return compile_predicate(self.predicate)


@dataclass(frozen=True)
class Contract:
    tool: str
    clauses: tuple[Clause, ...] = ()
    biconditional: bool = False
    on_violation: str = "ValueError"

    def of(self, kind: str) -> tuple[Clause, ...]:
        """Final clauses of a kind: drafts are outside every count."""
        return tuple(c for c in self.clauses if c.kind == kind and not c.draft)

    @property
    def effective(self) -> tuple[str, ...]:
        return tuple(c.arg for c in self.of("arg"))

    def reads_effective(self, clause: Clause) -> bool:
        return any(p.split(".")[1] in self.effective for p in clause.compiled.reads("args") if "." in p)


CLAUSE_ROW = "tool string, clause_id string, kind string, predicate string, paths array<string>, surface string, file string, line int, quote string, commit string, inferred boolean, draft boolean, deferred boolean, biconditional boolean"


def clause_rows(spark: SparkSession, contracts: list[Contract]) -> DataFrame:
    """Contracts as rows; a predicate outside the language has null paths (check 2 reports it)."""
    rows = []
    for contract in contracts:
        for c in contract.clauses:
            try:
                paths: list[str] | None = list(c.compiled.paths)
            except GrammarError:
                paths = None
            p = c.provenance
            rows.append((contract.tool, c.clause_id, c.kind, c.predicate, paths, p.surface, p.file, p.line, p.quote, p.commit, c.inferred, c.draft, c.deferred, contract.biconditional))
    return spark.createDataFrame(rows, CLAUSE_ROW).withColumn("tier", tier_of(F.col("surface")))


def draft(tool: str, args: list[str]) -> Contract:
    """Placeholders for a person to fill: constant-true predicates with a draft suffix."""
    return Contract(tool, tuple(Clause(f"eff.{a}_draft") for a in args))


def validate(clauses: DataFrame, lines: DataFrame) -> DataFrame:
    """Eight checks for each clause: (tool, clause_id, check_no, ok).

    ``lines`` holds source lines (file, line, text, kind); kind is the syntax on the line ('return',
    'raise', 'log', 'comment', 'text' ...). 1 known kind prefix; 2 the predicate compiles without free
    names; 3 effect, frame and invariant predicates read state; 4 the quote is on the cited line,
    verbatim; 5 ids are unique in a file; 6 the inferred flag fits surface and draft; 7 a draft carries the
    constant predicate and the suffix; 8 a cited tool-return line is a return or raise, a cited prompt
    quote occurs anywhere in its file.
    """
    twins = clauses.groupBy("tool", "clause_id").agg(F.count("*").alias("twins"))
    at = lines.select(F.col("file").alias("f"), F.col("line").alias("at"), F.col("text").alias("on_line"), F.col("kind").alias("line_kind"))
    rows = clauses.join(twins, ["tool", "clause_id"]).join(at, (F.col("file") == F.col("f")) & (F.col("line") == F.col("at")), "left")
    prompts = clauses.filter("surface = 'prompt'").join(at, F.col("file") == F.col("f")).filter(F.col("on_line").contains(F.col("quote"))).select("tool", "clause_id").distinct().withColumn("in_file", F.lit(True))
    rows = rows.join(prompts, ["tool", "clause_id"], "left")
    quoted = F.coalesce(F.col("on_line").contains(F.col("quote")), F.lit(False))
    reads_state = F.exists("paths", lambda p: p.startswith("pre.") | p.startswith("post.") | p.startswith("result"))
    checks = [
        F.col("kind").isin(*KINDS),
        F.col("paths").isNotNull(),
        ~F.col("kind").isin("eff", "frame", "inv") | F.col("draft") | F.coalesce(reads_state, F.lit(False)),
        F.col("surface").isNull() | quoted | ((F.col("surface") == "prompt") & F.coalesce("in_file", F.lit(False))),
        F.col("twins") == 1,
        F.col("inferred") == (F.col("surface").isNull() | F.col("draft")),
        F.col("draft") == ((F.col("predicate") == "True") & F.col("clause_id").endswith("_draft")),
        F.when(F.col("surface") == "tool_return", F.coalesce(F.col("line_kind").isin("return", "raise"), F.lit(False))).when(F.col("surface") == "prompt", F.coalesce("in_file", F.lit(False))).otherwise(True),
    ]
    stacked = F.explode(F.array(*[F.struct(F.lit(k + 1).alias("check_no"), c.alias("ok")) for k, c in enumerate(checks)])).alias("c")
    return rows.select("tool", "clause_id", stacked).select("tool", "clause_id", "c.check_no", "c.ok")


def to_json(contract: Contract) -> str:
    """A contract file's text (one JSON document a tool; JSON is a subset of YAML)."""
    body = {"tool": contract.tool, "biconditional": contract.biconditional, "on_violation": contract.on_violation, "clauses": [{"id": c.clause_id, "predicate": c.predicate, "arg": c.arg, "deferred": c.deferred, "provenance": c.provenance.__dict__} for c in contract.clauses]}
    return json.dumps(body, indent=1, sort_keys=True)


def from_json(text: str) -> Contract:
    body = json.loads(text)
    clauses = tuple(Clause(c["id"], c["predicate"], Provenance(**c["provenance"]), c.get("arg"), c.get("deferred", False)) for c in body["clauses"])
    return Contract(body["tool"], clauses, body.get("biconditional", False), body.get("on_violation", "ValueError"))
