"""The simulated desk: 26 tools on the given tables, with planted divergences in the unpatched arm."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from statewitness.operators.conformance import Guard, Tool
from statewitness.operators.contract import Clause, Contract, Provenance
from statewitness.sources.tables import load


def said(quote: str, surface: str | None = "docstring", line: int = 1) -> Provenance:
    return Provenance(surface, "desk.txt", line, quote, "v1")


def entity(table: str, grp: str, key: str, *fields: str):
    """A slice of one table: group, key, and the state fields as ``pre``."""

    def read(spark: SparkSession, sf_dir: str) -> DataFrame:
        return load(spark, sf_dir, table).selectExpr(f"{grp} AS grp", f"{key} AS key", f"struct({', '.join(fields)}) AS pre")

    return read


def counted(table: str, grp: str, *fields: str):
    """A slice with one row a group, whose fields are aggregates."""

    def read(spark: SparkSession, sf_dir: str) -> DataFrame:
        rows = load(spark, sf_dir, table).groupBy(F.expr(grp).alias("grp"))
        names = [f.rsplit(" AS ", 1) for f in fields]
        return rows.agg(*[F.expr(e).alias(n) for e, n in names]).select("grp", F.col("grp").alias("key"), F.struct(*[n for _, n in names]).alias("pre"))

    return read


def order_stock(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders with lines: status, units reserved by the lines and units in stock of their parts."""
    lines = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_quantity")
    stock = load(spark, sf_dir, "part").select("p_partkey", "p_size")
    held = lines.join(stock, F.col("l_partkey") == F.col("p_partkey")).groupBy("l_orderkey").agg(F.sum(F.col("l_quantity").cast("long")).alias("reserved"), F.sum(F.col("p_size").cast("long")).alias("stock"))
    orders = load(spark, sf_dir, "orders").select("o_orderkey", "o_orderstatus")
    return held.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).select(F.col("o_orderkey").alias("grp"), F.col("o_orderkey").alias("key"), F.struct(F.col("o_orderstatus").alias("status"), "reserved", "stock").alias("pre"))


LINE = "struct(l_orderkey, l_linenumber, l_partkey, l_suppkey, l_shipdate)"


def same(field: str) -> tuple[str, str]:
    return field, field


def eff(name: str, predicate: str, quote: str, surface: str | None = "docstring", deferred: bool = False) -> Clause:
    return Clause(f"eff.{name}", predicate, said(quote, surface), deferred=deferred)


def arg(name: str, quote: str = "", surface: str | None = "schema") -> Clause:
    return Clause(f"arg.{name}", "True", said(quote or name, surface), name)


def contract(tool: str, *clauses: Clause, biconditional: bool = False) -> Contract:
    return Contract(tool, clauses, biconditional)


def kept(field: str) -> Clause:
    return Clause(f"frame.{field}", f"post.{field} == pre.{field}", Provenance())


TOOLS: dict[str, Tool] = {}


def add(tool: Tool) -> None:
    TOOLS[tool.name] = tool


add(Tool(
    "charge_order",
    contract("charge_order", Clause("pre.open", "pre.status == 'O'", said("status must be O")), Clause("pre.owner", "args.customer == pre.customer", said("customer owns it")), eff("total", "post.total == pre.total + args.amount", "amount is added"), kept("status"), kept("customer"), arg("amount")),
    entity("orders", "o_custkey", "o_orderkey", "o_orderstatus AS status", "o_custkey AS customer", "o_totalprice AS total"),
    {"customer": "pre.customer", "amount": "40.0D"}, {"total": same("pre.total + args.amount")},
    (Guard("pre.open", "pre.status = 'O'", unpatched=False), Guard("pre.owner", "args.customer = pre.customer")),
    "concat('added ', args.amount)", {"amount": ("40.0D", "80.0D")}, falsify={"pre.owner": {"customer": "pre.customer + 1"}},
))
add(Tool(
    "hold_order",
    contract("hold_order", eff("held", "post.status == 'F'", "order is held"), arg("reason", "reason", None)),
    entity("orders", "o_custkey", "o_orderkey", "o_orderstatus AS status", "'' AS note"),
    {"reason": "'late'"}, {"status": same("'F'"), "note": ("pre.note", "args.reason")}, variants={"reason": ("'late'", "'fraud'")}, candidate=True,
))
add(Tool(
    "cancel_order",
    contract("cancel_order", eff("closed", "post.status == 'F'", "order is closed"), eff("stock", "post.stock == pre.stock + pre.reserved", "quantities return to stock", "comment")),
    order_stock, {"confirm": "true"}, {"status": same("'F'"), "stock": ("pre.stock", "pre.stock + pre.reserved")},
))
add(Tool(
    "revise_line",
    contract("revise_line", eff("quantity", "post.quantity == args.quantity", "quantity is set"), eff("discount", "post.discount == args.discount", "discount is set"), eff("tax", "post.tax == args.tax", "tax is set"), arg("quantity"), arg("discount"), arg("tax"), biconditional=True),
    entity("lineitem", "l_orderkey", LINE, "l_quantity AS quantity", "l_discount AS discount", "l_tax AS tax"),
    {"quantity": "pre.quantity + 1", "discount": "pre.discount + 0.01D", "tax": "pre.tax + 0.01D"},
    {f: (f"if(args.{f} <> 0, args.{f}, pre.{f})", f"args.{f}") for f in ("quantity", "discount", "tax")}, message="'line updated'",
    variants={"quantity": ("pre.quantity + 1", "pre.quantity + 2")}, falsy={"quantity": "0.0D", "discount": "0.0D", "tax": "0.0D"},
))
add(Tool(
    "schedule_ship",
    contract("schedule_ship", eff("from", "post.ship_from == args.ship_from", "start is stored"), arg("ship_from"), arg("ship_until", "until when")),
    entity("lineitem", "l_orderkey", LINE, "'' AS ship_from", "'' AS ship_until"),
    {"ship_from": "'2024-01-01'", "ship_until": "'2024-01-05'"}, {"ship_from": same("args.ship_from"), "ship_until": ("pre.ship_until", "args.ship_until")}, message="concat('booked until ', args.ship_until)",
    variants={"ship_from": ("'2024-01-01'", "'2024-01-02'"), "ship_until": ("'2024-01-05'", "'2024-01-06'")},
))
add(Tool(
    "list_activity",
    contract("list_activity", arg("order_by", "order_by"), arg("limit", "limit")),
    counted("events", "user_id", "count(*) AS n_events"),
    {"limit": "10", "offset": "0", "order_by": "'ts'"}, forwarded=("concat_ws('|', args.limit, args.offset)", "concat_ws('|', args.limit, args.offset, args.order_by)"), observe="forwarded",
    variants={"order_by": ("'ts'", "'value'"), "limit": ("10", "20")},
))
add(Tool(
    "register_customer",
    contract("register_customer", eff("row", "post.n_customers == pre.n_customers + 1", "a customer is added"), arg("segment"), arg("email", "an invitation should be sent to email")),
    counted("customer", "c_nationkey", "count(*) AS n_customers", "'' AS last_segment", "'' AS outbox"),
    {"segment": "'BUILDING'", "email": "'a@example.org'"}, {"n_customers": same("pre.n_customers + 1"), "last_segment": same("args.segment"), "outbox": ("pre.outbox", "args.email")},
    variants={"segment": ("'BUILDING'", "'MACHINERY'"), "email": ("'a@example.org'", "'b@example.org'")},
))
add(Tool("release_order", contract("release_order", eff("open", "post.status == 'O'", "order is open")), entity("orders", "o_custkey", "o_orderkey", "o_orderstatus AS status"), {"confirm": "true"}, {"status": same("'O'")}, population="heldout"))
add(Tool("place_order", contract("place_order", eff("lines", "post.n_lines == pre.n_lines + len(args.lines)", "lines are added"), arg("lines")), counted("lineitem", "l_orderkey", "count(*) AS n_lines"), {"lines": "array(1L, 2L)"}, {"n_lines": same("pre.n_lines + size(args.lines)")}, variants={"lines": ("array(1L, 2L)", "array(3L)")}, population="heldout", list_args=True))
add(Tool("set_quantity", contract("set_quantity", eff("quantity", "post.quantity == args.quantity", "quantity is set"), arg("quantity")), entity("lineitem", "l_orderkey", LINE, "l_quantity AS quantity"), {"quantity": "pre.quantity + 1"}, {"quantity": same("args.quantity")}, variants={"quantity": ("pre.quantity + 1", "pre.quantity + 2")}, population="heldout"))
add(Tool("stamp_ship", contract("stamp_ship", eff("date", "post.ship_date == pre.ship_date", "date is set", deferred=True), arg("iso")), entity("lineitem", "l_orderkey", LINE, "cast(l_shipdate AS string) AS ship_date"), {"iso": "'2024-03-01T10:00'"}, {"ship_date": same("cast(to_timestamp_ntz(args.iso) AS string)")}, variants={"iso": ("'2024-03-01T10:00'", "'2024-03-02T10:00'")}, population="heldout"))
add(Tool(
    "update_customer",
    contract("update_customer", *[eff(f, f"post.{f} == args.{f}", f"{f} is set") for f in ("name", "segment", "acctbal", "nation")], *[arg(f) for f in ("name", "segment", "acctbal", "nation")]),
    entity("customer", "c_custkey", "c_custkey", "c_name AS name", "c_mktsegment AS segment", "c_acctbal AS acctbal", "c_nationkey AS nation"),
    {"name": "'New'", "segment": "'NONE'", "acctbal": "pre.acctbal + 1", "nation": "pre.nation + 1"},
    {**{f: (f"if(args.{f} <> '', args.{f}, pre.{f})", f"args.{f}") for f in ("name", "segment")}, **{f: (f"if(args.{f} <> 0, args.{f}, pre.{f})", f"args.{f}") for f in ("acctbal", "nation")}},
    falsy={"name": "''", "segment": "''", "acctbal": "0.0D", "nation": "0"}, population="heldout",
))
add(Tool("top_up_customer", contract("top_up_customer", eff("balance", "post.acctbal == pre.acctbal + args.amount", "amount is added"), arg("amount")), entity("customer", "c_nationkey", "c_custkey", "c_acctbal AS acctbal"), {"amount": "2.0D"}, {"acctbal": same("pre.acctbal + args.amount")}, variants={"amount": ("2.0D", "3.0D")}, population="heldout"))
add(Tool("retire_event", contract("retire_event", eff("marked", "post.marked == True", "event is retired"), eff("gone", "post.listed == False", "event leaves the listings")), entity("events", "event_id", "event_id", "false AS marked", "true AS listed"), {"confirm": "true"}, {"marked": same("true"), "listed": ("pre.listed", "false")}, population="blind"))
for name, table, grp, fields in (("share_conversation", "conversations", "conv_id", "count(*) AS n"), ("open_conversation", "conversations", "conv_id % 10", "count(*) AS n"), ("send_notice", "events", "user_id", "count(*) AS n")):
    add(Tool(name, contract(name, eff("rows", "post.n == pre.n + len(args.receivers)", "receivers are told"), arg("receivers")), counted(table, grp, fields), {"receivers": "array('a', 'b')"}, {"n": same("pre.n + size(args.receivers)")}, variants={"receivers": ("array('a', 'b')", "array('a')")}, population="blind", list_args=True))
add(Tool("append_turn", contract("append_turn", eff("turn", "post.n_turns == pre.n_turns + 1", "a turn is added"), arg("role")), counted("conversations", "conv_id", "count(*) AS n_turns", "'' AS last_role"), {"role": "'user'"}, {"n_turns": same("pre.n_turns + 1"), "last_role": same("args.role")}, variants={"role": ("'user'", "'assistant'")}, population="blind"))
add(Tool("tag_document", contract("tag_document", eff("row", "post.n_labels == pre.n_labels + 1", "a label is added"), arg("quality")), counted("labels", "doc_id % 100", "count(*) AS n_labels", "cast(null AS int) AS last_quality"), {"quality": "1"}, {"n_labels": same("pre.n_labels + 1"), "last_quality": same("args.quality")}, variants={"quality": ("0", "1")}, population="blind"))
add(Tool("swap_lines", contract("swap_lines", eff("lines", "post.n_lines == len(args.lines)", "lines are replaced"), arg("lines")), counted("lineitem", "l_orderkey", "count(*) AS n_lines"), {"lines": "array(named_struct('part', 1L))"}, {"n_lines": same("size(args.lines)")}, population="blind", list_args=True, synthesizer=False))
for name, table, grp, key, field_name, state, values in (
    ("reprice_part", "part", "p_brand", "p_partkey", "price", "p_retailprice", ("pre.price + 1", "pre.price + 2")),
    ("move_supplier", "supplier", "s_nationkey", "s_suppkey", "nation", "s_nationkey", ("pre.nation + 1", "pre.nation + 2")),
    ("rename_region", "region", "r_regionkey", "r_regionkey", "name", "r_name", ("'A'", "'B'")),
    ("readdress_page", "pages", "page_id % 50", "page_id", "url", "url", ("'http://a.example/'", "'http://b.example/'")),
    ("relabel_vector", "embeddings", "label", "vec_id", "mark", "label", ("pre.mark + 1", "pre.mark + 2")),
):
    add(Tool(name, contract(name, eff(field_name, f"post.{field_name} == args.{field_name}", f"{field_name} is set"), arg(field_name)), entity(table, grp, key, f"{state} AS {field_name}"), {field_name: values[0]}, {field_name: same(f"args.{field_name}")}, variants={field_name: values}, population="blind"))
add(Tool(
    "post_event",
    contract("post_event", eff("row", "post.n_events == pre.n_events + 1", "event is recorded", "prompt"), biconditional=True),
    counted("events", "user_id", "count(*) AS n_events"), {"value": "1.0D"}, {"n_events": ("pre.n_events", "pre.n_events + 1")}, message="'request accepted and executed'", population="clinical",
))
