"""Expressions: one small tree that is evaluated in Python (the oracle), shown as SQL, and given to Spark as a Column."""

from __future__ import annotations

import re
from dataclasses import dataclass
from typing import Any, Callable

from pyspark.sql import Column
from pyspark.sql import functions as F


class Expr:
    def __add__(self, o):
        return Bin("+", self, wrap(o))

    def __sub__(self, o):
        return Bin("-", self, wrap(o))

    def __mul__(self, o):
        return Bin("*", self, wrap(o))

    def eq(self, o):
        return Bin("=", self, wrap(o))

    def same(self, o):
        return Bin("IS NOT DISTINCT FROM", self, wrap(o))

    def __lt__(self, o):
        return Bin("<", self, wrap(o))

    def __le__(self, o):
        return Bin("<=", self, wrap(o))

    def __gt__(self, o):
        return Bin(">", self, wrap(o))

    def __ge__(self, o):
        return Bin(">=", self, wrap(o))

    def ne(self, o):
        return Bin("<>", self, wrap(o))

    def __and__(self, o):
        return Bin("AND", self, wrap(o))

    def __or__(self, o):
        return Bin("OR", self, wrap(o))

    def __invert__(self):
        return Fn("(NOT {})", (self,))


@dataclass(frozen=True)
class Lit(Expr):
    value: Any

    def sql(self):
        if self.value is None:
            return "NULL"
        if isinstance(self.value, bool):
            return str(self.value).upper()
        return "'" + self.value.replace("'", "''") + "'" if isinstance(self.value, str) else str(self.value)


@dataclass(frozen=True)
class Col(Expr):
    name: str

    def sql(self):
        return self.name


@dataclass(frozen=True)
class Bin(Expr):
    op: str
    left: Expr
    right: Expr

    def sql(self):
        return f"({self.left.sql()} {self.op} {self.right.sql()})"


@dataclass(frozen=True)
class If(Expr):
    cond: Expr
    then: Expr
    other: Expr

    def sql(self):
        return f"(CASE WHEN {self.cond.sql()} THEN {self.then.sql()} ELSE {self.other.sql()} END)"


@dataclass(frozen=True)
class Fn(Expr):
    """An opaque SQL template over argument expressions."""

    template: str
    args: tuple[Expr, ...]

    def sql(self):
        return self.template.format(*(a.sql() for a in self.args))


def wrap(x) -> Expr:
    return x if isinstance(x, Expr) else Lit(x)


def col(name: str) -> Col:
    return Col(name)


_NAME = re.compile(r"'[^']*'|\b[a-z_][a-z0-9_]*\b(?!\s*\()")


def fn(text: str, *args) -> Fn:
    """An opaque expression. Without arguments, lower-case names outside quotes that aren't called are its columns."""
    if args:
        return Fn(text, tuple(Col(a) if isinstance(a, str) else wrap(a) for a in args))
    names: list[str] = []

    def mark(m):
        if m[0][0] == "'":
            return m[0].replace("{", "{{").replace("}", "}}")
        names.append(m[0])
        return "{}"

    return Fn(_NAME.sub(mark, text), tuple(map(Col, names)))


def parts(e: Expr) -> tuple[Expr, ...]:
    if isinstance(e, Bin):
        return e.left, e.right
    if isinstance(e, If):
        return e.cond, e.then, e.other
    return e.args if isinstance(e, Fn) else ()


def rebuild(e: Expr, kids) -> Expr:
    if isinstance(e, Bin):
        return Bin(e.op, *kids)
    if isinstance(e, If):
        return If(*kids)
    return Fn(e.template, tuple(kids)) if isinstance(e, Fn) else e


def cols(e: Expr) -> frozenset[str]:
    return frozenset([e.name]) if isinstance(e, Col) else frozenset().union(*(cols(p) for p in parts(e)))


def refs(e: Expr) -> int:
    """Attribute references in an expression, with repeats."""
    return 1 if isinstance(e, Col) else sum(refs(p) for p in parts(e))


def substitute(e: Expr, by: dict[str, Expr]) -> Expr:
    if isinstance(e, Col):
        return by.get(e.name, e)
    return rebuild(e, [substitute(p, by) for p in parts(e)]) if parts(e) else e


def conjuncts(e: Expr) -> list[Expr]:
    if isinstance(e, Bin) and e.op == "AND":
        return conjuncts(e.left) + conjuncts(e.right)
    return [e]


def conjunction(es) -> Expr:
    es = list(es)
    out = es[0] if es else Lit(True)
    for e in es[1:]:
        out = out & e
    return out


def to_column(e: Expr) -> Column:
    return F.expr(e.sql())


_OPS: dict[str, Callable] = {
    "+": lambda a, b: a + b, "-": lambda a, b: a - b, "*": lambda a, b: a * b, "=": lambda a, b: a == b,
    "<>": lambda a, b: a != b, "<": lambda a, b: a < b, "<=": lambda a, b: a <= b, ">": lambda a, b: a > b, ">=": lambda a, b: a >= b,
}


def evaluate(e: Expr, row: dict):
    """Value of an expression for one row, with SQL's three-valued logic."""
    if isinstance(e, Lit):
        return e.value
    if isinstance(e, Col):
        return row[e.name]
    if isinstance(e, If):
        return evaluate(e.then if evaluate(e.cond, row) is True else e.other, row)
    if isinstance(e, Fn):
        if e.template == "(NOT {})":
            v = evaluate(e.args[0], row)
            return None if v is None else not v
        raise ValueError(f"opaque: {e.template}")
    a, b = evaluate(e.left, row), evaluate(e.right, row)
    if e.op == "AND":
        return False if a is False or b is False else None if a is None or b is None else True
    if e.op == "OR":
        return True if a is True or b is True else None if a is None or b is None else False
    if e.op == "IS NOT DISTINCT FROM":
        return a == b
    return None if a is None or b is None else _OPS[e.op](a, b)
