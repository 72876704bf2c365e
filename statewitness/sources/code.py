"""Source code as rows: the desk's tools, the evaluators, and a parser that executes nothing."""

from __future__ import annotations

import ast
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession

# Desk tools as a maintainer would ship them; each defect site is marked in SITES.
TOOL_SOURCES = {
    "orders.py": '''
def charge_order(state, order: int, customer: int, amount: float):
    """Checks: status must be O, customer owns it."""
    row = state.orders[order]
    if row.customer != customer:
        raise ValueError("customer does not own the order")
    # if row.status != "O":
    #     raise ValueError("status must be O")
    row.total = row.total + amount
    return f"added {amount}"

def hold_order(state, order: int, reason: str):
    """The order is held for a reason."""
    state.orders[order].status = "F"
    log.info("held", reason)
    return state.orders[order].status

def place_order(state, order: int, lines: list):
    state.orders[order].lines = lines
    state.parts.stock = state.parts.stock - len(lines)
    return state.orders[order].lines

def cancel_order(state, order: int):
    """The order is closed and its quantities return to stock."""
    state.orders[order].lines = []
    return state.orders[order].lines

def release_order(state, order: int):
    state.orders[order].status = "O"
    return state.orders[order].status

def list_orders(state, limit: int):
    if limit:
        return state.orders.first
    return state.orders.rows
''',
    "lines.py": '''
def revise_line(state, line: int, quantity: float, discount: float, tax: float):
    """Sets quantity, discount and tax."""
    row = state.lines[line]
    if quantity:
        row.quantity = quantity
    if discount:
        row.discount = discount
    if tax:
        row.tax = tax
    return "line updated"

def schedule_ship(state, line: int, start: str, until: str):
    """Stores the window from start until the end."""
    state.lines[line].start = start
    return f"booked until {until}"

def set_quantity(state, line: int, quantity: float):
    state.lines[line].quantity = quantity
    return state.lines[line].quantity
''',
    "people.py": '''
def register_customer(state, name: str, nation: int, email: str):
    """An invitation should be sent to email."""
    state.customers[name].nation = nation
    return state.customers[name].nation

def update_customer(state, customer: int, name: str, balance: float):
    row = state.customers[customer]
    if name:
        row.name = name
    if balance:
        row.balance = balance
    return row.name

def post_event(state, user: int, value: float):
    """The event is recorded."""
    state.pending.size = value
    return "request accepted and executed"
''',
}
# (file, function, check) of every confirmed defect site, and functions outside the audited population.
SITES = [
    ("orders.py", "charge_order", "dead_guard"), ("orders.py", "cancel_order", "verb_pair"), ("lines.py", "revise_line", "truthy_guard"), ("lines.py", "schedule_ship", "cosmetic_param"),
    ("people.py", "register_customer", "unread_param"), ("people.py", "update_customer", "truthy_guard"), ("people.py", "post_event", "literal_success"),
]
OUTSIDE_POPULATION = ["set_quantity", "list_orders"]
VERB_PAIRS = [("place_order", "cancel_order"), ("hold_order", "release_order")]
FALSY_TYPES = ("int", "float", "str", "bool", "list")

EVALUATOR_SOURCES = {
    "evaluators.py": '''
def exact_status(state, transcript):
    return state.orders.status == "F"

def collection_only(state, transcript):
    return len(state.orders) > 0

def through_helpers(state, transcript):
    return first_helper(state)

def first_helper(state):
    return second_helper(state)

def second_helper(state):
    return third_helper(state)

def third_helper(state):
    return state.orders.total > 0

def too_deep(state, transcript):
    return zeroth_helper(state)

def zeroth_helper(state):
    return first_helper(state)

def by_constant(state, transcript):
    return lookup("orders.status")

def computed(state, transcript):
    return getattr(state, "orders" + "x")

def told_so(state, transcript):
    return "accepted" in transcript.last
''',
}


class _Reader(ast.NodeVisitor):
    def __init__(self, file: str):
        self.file, self.rows, self.stack = file, [], []
        self.func: str | None = None
        self.params: dict[str, str] = {}
        self.context = ["body"]

    def add(self, kind: str, name: str, node: ast.AST, role: str = "", text: str = "") -> int:
        self.rows.append((self.file, self.func or "", len(self.rows), self.stack[-1] if self.stack else -1, kind, name, getattr(node, "lineno", 0), role, text))
        return len(self.rows) - 1

    def within(self, role: str, nodes) -> None:
        self.context.append(role)
        for n in nodes:
            self.visit(n)
        self.context.pop()

    def visit_FunctionDef(self, node: ast.FunctionDef) -> None:
        self.func = node.name
        at = self.add("function", node.name, node, text=ast.get_docstring(node) or "")
        self.rows.append((self.file, node.name, len(self.rows), at, "end", "", node.end_lineno, "", ""))
        self.stack.append(at)
        self.params = {}
        for a in node.args.args:
            kind = ast.unparse(a.annotation) if a.annotation else ""
            self.params[a.arg] = kind
            self.add("param", a.arg, a, text=kind)
        for n in node.body:
            self.visit(n)
        self.stack.pop()
        self.func = None

    def visit_Return(self, node: ast.Return) -> None:
        constant = isinstance(node.value, ast.Constant) and isinstance(node.value.value, str)
        self.add("return", "", node, "constant" if constant else "value", str(node.value.value) if constant else "")
        self.within("returned_fstring" if isinstance(node.value, ast.JoinedStr) else "return", [node.value] if node.value else [])

    def visit_If(self, node: ast.If) -> None:
        if isinstance(node.test, ast.Name):
            self.add("test", node.test.id, node, "truth")
        self.within("test", [node.test])
        for n in [*node.body, *node.orelse]:
            self.visit(n)

    def visit_Call(self, node: ast.Call) -> None:
        name = ast.unparse(node.func)
        self.add("call", name, node, self.context[-1])
        self.within("log" if name.startswith("log.") else self.context[-1], [*node.args, *[k.value for k in node.keywords]])

    def visit_Assign(self, node: ast.Assign) -> None:
        for t in node.targets:
            if isinstance(t, ast.Attribute):
                self.add("write", t.attr, node, "state", ast.unparse(t))
                self.within("target", [t.value])
        self.within("value", [node.value])

    def visit_Attribute(self, node: ast.Attribute) -> None:
        path = ast.unparse(node)
        if path.replace(".", "").replace("_", "").isalnum():
            self.add("attribute", path, node, self.context[-1])
        inner: ast.AST = node
        while isinstance(inner, ast.Attribute):
            self.add("field", inner.attr, inner, self.context[-1])
            inner = inner.value
        self.visit(inner)

    def visit_Name(self, node: ast.Name) -> None:
        if node.id in self.params:
            self.add("read", node.id, node, self.context[-1])

    def visit_Constant(self, node: ast.Constant) -> None:
        if isinstance(node.value, str):
            self.add("constant", "", node, self.context[-1], node.value)


NODE = "file string, func string, node_id int, parent_id int, kind string, name string, lineno int, role string, text string"


def parse(file: str, text: str) -> list[tuple]:
    reader = _Reader(file)
    try:
        reader.visit(ast.parse(text))
    except SyntaxError as error:
        return [(file, "", 0, -1, "error", "", error.lineno or 0, "", str(error))]
    return reader.rows


def source_rows(spark: SparkSession, sources: dict[str, str]) -> DataFrame:
    return spark.createDataFrame(list(sources.items()), "file string, text string")


def nodes(sources: DataFrame) -> DataFrame:
    """Syntax nodes of (file, text) rows; a file that does not parse gives one error row."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        names = [p.split()[0] for p in NODE.split(", ")]
        for batch in batches:
            yield pd.DataFrame([r for f, t in zip(batch["file"], batch["text"]) for r in parse(f, t or "")], columns=names)

    return sources.mapInPandas(run, NODE)


def source_lines(sources: DataFrame) -> DataFrame:
    """(file, line, text), line numbers from 1."""
    from pyspark.sql import functions as F

    return sources.select("file", F.posexplode(F.split("text", "\n")).alias("at", "text")).select("file", (F.col("at") + 1).alias("line"), "text")
