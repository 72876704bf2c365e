"""Clause predicates: a small whitelisted expression language, compiled to columns with the paths it reads.

Roots are ``pre``, ``post``, ``args`` and ``result``; there are comparisons, and/or/not, arithmetic, ``in``
over constant lists, ``len``, and ``any``/``all`` over a list-valued path with one loop name. Everything
else is refused, so a contract file can't run code. Draft predicates (the constant True) compile to
a literal that the optimizer drops.
"""

from __future__ import annotations

import ast
import operator
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

ROOTS = ("pre", "post", "args", "result")
_COMPARE = {ast.Eq: operator.eq, ast.NotEq: operator.ne, ast.Lt: operator.lt, ast.LtE: operator.le, ast.Gt: operator.gt, ast.GtE: operator.ge}
_ARITHMETIC = {ast.Add: operator.add, ast.Sub: operator.sub, ast.Mult: operator.mul, ast.Div: operator.truediv, ast.Mod: operator.mod}


class GrammarError(ValueError):
    """A predicate outside the language, or a free name."""


@dataclass(frozen=True)
class Compiled:
    column: Column
    paths: tuple[str, ...]

    def reads(self, root: str) -> tuple[str, ...]:
        return tuple(p for p in self.paths if p.split(".")[0] == root)


class _Compiler:
    def __init__(self, roots: tuple[str, ...]):
        self.roots = roots
        self.paths: list[str] = []

    def compile(self, node: ast.AST, bound: dict[str, tuple[Column, str]]) -> Column:
        match node:
            case ast.Expression(body=body):
                return self.compile(body, bound)
            case ast.Constant(value=value) if value is None or isinstance(value, (bool, int, float, str)):
                return F.lit(value)
            case ast.Attribute() | ast.Name():
                return self.path(node, bound)
            case ast.BoolOp(op=op, values=values):
                parts = [self.compile(v, bound) for v in values]
                return reduce(operator.and_ if isinstance(op, ast.And) else operator.or_, parts)
            case ast.UnaryOp(op=ast.Not(), operand=inner):
                return ~self.compile(inner, bound)
            case ast.UnaryOp(op=ast.USub(), operand=inner):
                return -self.compile(inner, bound)
            case ast.BinOp(left=left, op=op, right=right) if type(op) in _ARITHMETIC:
                return _ARITHMETIC[type(op)](self.compile(left, bound), self.compile(right, bound))
            case ast.Compare(left=left, ops=ops, comparators=right):
                sides = [left, *right]
                return reduce(operator.and_, [self.compare(op, a, b, bound) for op, a, b in zip(ops, sides, sides[1:])])
            case ast.Call(func=ast.Name(id="len"), args=[inner], keywords=[]):
                return F.size(self.compile(inner, bound))
            case ast.Call(func=ast.Name(id=("any" | "all") as which), args=[ast.GeneratorExp(elt=test, generators=[loop])], keywords=[]):
                return self.quantified(which, test, loop, bound)
        raise GrammarError(f"{type(node).__name__} is not in the language")

    def compare(self, op: ast.cmpop, left: ast.AST, right: ast.AST, bound: dict) -> Column:
        if isinstance(op, (ast.In, ast.NotIn)):
            if not isinstance(right, (ast.List, ast.Tuple)) or not all(isinstance(x, ast.Constant) for x in right.elts):
                raise GrammarError("'in' takes a list of constants")
            held = self.compile(left, bound).isin([x.value for x in right.elts])
            return held if isinstance(op, ast.In) else ~held
        if isinstance(op, (ast.Is, ast.IsNot)) and isinstance(right, ast.Constant) and right.value is None:
            found = self.compile(left, bound)
            return found.isNull() if isinstance(op, ast.Is) else found.isNotNull()
        if type(op) not in _COMPARE:
            raise GrammarError(f"{type(op).__name__} is not in the language")
        return _COMPARE[type(op)](self.compile(left, bound), self.compile(right, bound))

    def quantified(self, which: str, test: ast.AST, loop: ast.comprehension, bound: dict) -> Column:
        if not isinstance(loop.target, ast.Name) or loop.is_async:
            raise GrammarError("a loop binds one name")
        if loop.target.id in self.roots or loop.target.id in bound:
            raise GrammarError(f"{loop.target.id} is bound already")
        listed, name = self.compile(loop.iter, bound), loop.target.id
        prefix = self.paths[-1]

        def body(item: Column) -> Column:
            inner = {**bound, name: (item, prefix)}
            kept = [self.compile(c, inner) for c in loop.ifs]
            held = self.compile(test, inner)
            if which == "any":
                return reduce(operator.and_, [*kept, held])
            return reduce(operator.or_, [*[~k for k in kept], held])

        return F.exists(listed, body) if which == "any" else F.forall(listed, body)

    def path(self, node: ast.AST, bound: dict) -> Column:
        names: list[str] = []
        while isinstance(node, ast.Attribute):
            names.append(node.attr)
            node = node.value
        if not isinstance(node, ast.Name):
            raise GrammarError("a path starts with a name")
        names.reverse()
        if node.id in bound:
            column, prefix = bound[node.id]
            self.paths.append(".".join([prefix, *names]))
            return reduce(lambda c, k: c.getField(k), names, column)
        if node.id not in self.roots:
            raise GrammarError(f"{node.id} is a free name")
        self.paths.append(".".join([node.id, *names]))
        return F.col(".".join([node.id, *names]))


def compile_predicate(text: str, roots: tuple[str, ...] = ROOTS) -> Compiled:
    """A predicate as a boolean column, with every path it reads in order of appearance."""
    try:
        tree = ast.parse(text, mode="eval")
    except SyntaxError as error:
        raise GrammarError(str(error)) from error
    work = _Compiler(roots)
    column = work.compile(tree, {})
    return Compiled(column, tuple(dict.fromkeys(work.paths)))
