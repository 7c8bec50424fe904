"""Why and why-not provenance of non-recursive Datalog with negation, as a graph of tuples, firings and goals.

A rule's firing relation holds every binding of its variables. Why: positive goals are joined, negated goals anti-joined,
all goals succeed. Why-not: bindings come from the question's constants and named, bounded domains of the other variables;
each goal is looked up, and bindings with some failed goal are the reasons. Firings are limited to what the question
reaches, from its constants down through derived relations. Duplicates may be removed after each step; where that
happens is a choice.
"""

from __future__ import annotations

import math
import re
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from provloom.plans.cost import Profile, profile
from provloom.plans.search import Best, Choices, optimize


@dataclass(frozen=True)
class Atom:
    rel: str
    args: tuple
    positive: bool = True


@dataclass(frozen=True)
class Rule:
    head: Atom
    body: tuple[Atom, ...]
    compare: tuple[tuple[object, str, object], ...] = ()


def is_var(x) -> bool:
    return isinstance(x, str) and x[:1].isupper()


_ATOM = re.compile(r"\s*(not\s+)?([a-z]\w*)\(([^)]*)\)\s*$")
_COMPARE = re.compile(r"\s*([\w']+)\s*(<>|<=|>=|=|<|>)\s*([\w']+)\s*$")


def _term(t: str):
    t = t.strip()
    return int(t) if re.fullmatch(r"-?\d+", t) else t.strip("'") if t[:1] == "'" else t


def parse(text: str) -> list[Rule]:
    """Rules like ``far(X, Z) :- near(X, Y), near(Y, Z), not near(X, Z), X <> Z.``; recursion is refused."""
    out = []
    for line in filter(None, (x.strip() for x in text.replace("\n", " ").split("."))):
        head, _, body = line.partition(":-")
        atoms, compare = [], []
        for part in re.split(r",(?![^(]*\))", body):
            if m := _ATOM.match(part):
                atoms.append(Atom(m[2], tuple(map(_term, m[3].split(","))), not m[1]))
            elif m := _COMPARE.match(part):
                compare.append((_term(m[1]), m[2], _term(m[3])))
            else:
                raise ValueError(f"can't read {part!r}")
        m = _ATOM.match(head)
        rule = Rule(Atom(m[2], tuple(map(_term, m[3].split(",")))), tuple(atoms), tuple(compare))
        bound = {a for g in atoms if g.positive for a in g.args if is_var(a)}
        if {a for g in (rule.head, *atoms) for a in g.args if is_var(a)} - bound:
            raise ValueError(f"unsafe rule: {line}")
        out.append(rule)
    strata(out)
    return out


def strata(rules: list[Rule]) -> list[str]:
    """Derived relations, each after those it uses."""
    idb = {r.head.rel for r in rules}
    order: list[str] = []

    def visit(name, path):
        if name in path:
            raise ValueError(f"recursive: {name}")
        if name in order or name not in idb:
            return
        for r in rules:
            if r.head.rel == name:
                for g in r.body:
                    visit(g.rel, (*path, name))
        order.append(name)

    for r in rules:
        visit(r.head.rel, ())
    return order


class Program:
    def __init__(self, rules: list[Rule] | str, edb: dict[str, DataFrame], choices: Choices | None = None, optimize: str = "heu"):
        self.rules = parse(rules) if isinstance(rules, str) else rules
        self.edb, self.choices, self.optimize = edb, choices or Choices(), optimize
        self.idb = set(strata(self.rules))

    def _distinct(self, df: DataFrame, needed: bool) -> DataFrame:
        """A distinct that isn't needed for the result may go: never without optimisation, always by heuristic, else by choice."""
        if needed or self.optimize == "none":
            return df.distinct()
        if self.optimize == "heu":
            return df
        return df if self.choices.choose(2, "drop_distinct", ("remove", "keep")) == 0 else df.distinct()

    def relation(self, name: str, bind: DataFrame | None = None) -> DataFrame:
        """Tuples of a relation as columns a0, a1, ...; bind: limit to these tuples."""
        if name in self.idb:
            parts = [self.firings(r, bind).select(*(F.col(t).alias(f"a{i}") if is_var(t) else F.lit(t).alias(f"a{i}") for i, t in enumerate(r.head.args))) for r in self.rules if r.head.rel == name]
            return reduce(DataFrame.unionAll, parts).distinct()
        df = self.edb[name]
        df = df.toDF(*(f"a{i}" for i in range(len(df.columns))))
        return df.join(_small(bind), bind.columns, "left_semi") if bind is not None else df

    def _goal(self, g: Atom, df: DataFrame) -> DataFrame:
        """The goal's tuples with its variables as columns."""
        cond, seen = [], {}
        for i, t in enumerate(g.args):
            if not is_var(t):
                cond.append(F.col(f"a{i}") == F.lit(t))
            elif t in seen:
                cond.append(F.col(f"a{i}") == F.col(seen[t]))
            else:
                seen[t] = f"a{i}"
        for c in cond:
            df = df.where(c)
        return df.select(*(F.col(c).alias(v) for v, c in seen.items()))

    def _asked(self, g: Atom, out: DataFrame | None) -> DataFrame | None:
        """What the bindings so far and the goal's constants ask of a derived relation; None: all of it."""
        if g.rel not in self.idb or out is None:
            return None
        first = {t: i for i, t in reversed([*enumerate(g.args)]) if is_var(t) and t in out.columns}
        if not first:
            return None
        asked = out.select(*(F.col(t).alias(f"a{i}") for t, i in first.items())).distinct()
        return asked.select("*", *(F.lit(t).alias(f"a{i}") for i, t in enumerate(g.args) if not is_var(t)))

    def firings(self, r: Rule, bind: DataFrame | None = None) -> DataFrame:
        """Bindings of the rule's variables under which all goals succeed; bind: tuples of the head (a0, a1, ...)."""
        out = None
        if bind is not None:
            cond = [F.col(f"a{i}") == F.lit(t) for i, t in enumerate(r.head.args) if not is_var(t) and f"a{i}" in bind.columns]
            vs = {}
            for i, t in enumerate(r.head.args):
                if is_var(t) and f"a{i}" in bind.columns:
                    if t in vs:
                        cond.append(F.col(f"a{i}") == F.col(vs[t]))
                    else:
                        vs[t] = f"a{i}"
            out = reduce(DataFrame.where, cond, bind).select(*(F.col(c).alias(v) for v, c in vs.items()))
            out = F.broadcast(out) if _bounded(bind) else out
        for g in sorted(r.body, key=lambda g: not g.positive):
            goal = self._goal(g, self.relation(g.rel, self._asked(g, out)))
            shared = [c for c in goal.columns if out is not None and c in out.columns]
            if g.positive:
                out = goal if out is None else out.join(goal, shared, "inner") if shared else out.crossJoin(goal)
            elif goal.columns:
                out = out.join(goal.distinct(), goal.columns, "left_anti")
            else:
                out = out.join(goal.limit(1).withColumn("__x", F.lit(1)), F.lit(True), "left_anti")
        for a, op, b in r.compare:
            out = out.where(F.expr(f"{_sql(a)} {op} {_sql(b)}"))
        return out

    def why(self, rel: str, question: DataFrame) -> DataFrame:
        """Edges behind the asked tuples (columns a0, a1, ... of question; fewer columns ask for all that agree)."""
        if self.optimize == "cost":
            self.choices = Choices(self.search(rel, question).path)
        edges, todo = [], [(rel, question.distinct() if not _bounded(question) else question)]
        while todo:
            name, bind = todo.pop()
            for k, r in enumerate(self.rules):
                if r.head.rel != name:
                    continue
                fire = self._distinct(self.firings(r, bind), False)
                edges.append(self._edges(r, k, fire, [F.lit(True)] * len(r.body)))
                for g in r.body:
                    if g.positive and g.rel in self.idb:
                        reached = fire.select(*(F.col(t).alias(f"a{i}") if is_var(t) else F.lit(t).alias(f"a{i}") for i, t in enumerate(g.args)))
                        todo.append((g.rel, self._distinct(reached, False)))
        return reduce(DataFrame.unionAll, edges).distinct()

    def search(self, rel: str, question: DataFrame) -> Best:
        """The distincts to keep behind the asked tuples, by the cost of all that follows each of them."""
        known = {name: profile(df) for name, df in self.edb.items()}
        asked = question.count()
        return optimize(lambda c: self._steps(rel, asked, known, c), lambda steps: sum(seconds for *_, seconds in steps))

    def _size(self, name: str, known: dict[str, Profile]) -> tuple[float, list[float]]:
        """Estimated tuples of a relation, and distinct values by argument."""
        if name not in self.idb:
            return known[name].rows, list(known[name].ndv.values())
        rows, ndv = 0.0, None
        for r in (r for r in self.rules if r.head.rel == name):
            n, values = self._bindings(r, {}, 1.0, known)
            mine = [values.get(t, 1.0) for t in r.head.args]
            rows += min(n, math.prod(mine))
            ndv = mine if ndv is None else [max(x, y) for x, y in zip(ndv, mine)]
        return rows, ndv

    def _bindings(self, r: Rule, bound: dict[str, float], rows: float, known) -> tuple[float, dict[str, float]]:
        """Estimated bindings of a rule's variables, from rows of its bound ones, and distinct values by variable."""
        values = dict(bound)
        for g in sorted(r.body, key=lambda g: not g.positive):
            if not g.positive:
                rows *= 0.5
                continue
            n, ndv = self._size(g.rel, known)
            for t, d in zip(g.args, ndv):
                if t in values or not is_var(t):
                    n /= max(d, 1.0)
                else:
                    values[t] = d
            rows *= n
        return rows * 0.33 ** len(r.compare), values

    def _steps(self, rel: str, asked: float, known, c: Choices) -> list[tuple]:
        """(what, rows, seconds) in the order in which ``why`` makes its choices."""
        shuffle, row = 0.12, 120e-9
        steps, todo = [], [(rel, float(asked), float(asked))]
        while todo:
            name, rows, different = todo.pop()
            for r in self.rules:
                if r.head.rel != name:
                    continue
                bound = {t: different for t in r.head.args if is_var(t)}
                each, values = self._bindings(r, bound, 1.0, known)
                fire, real = rows * each, different * each
                steps.append(("join", fire, fire * row))
                if c.choose(2, "drop_distinct", ("remove", "keep")):
                    steps.append(("distinct", fire, shuffle + fire * row * 3))
                    fire = real
                steps.append(("edges", fire, fire * (1 + 2 * len(r.body)) * row * 4))
                for g in r.body:
                    if g.positive and g.rel in self.idb:
                        left, once = fire, min(real, math.prod(min(values.get(t, 1.0), real) for t in g.args))
                        if c.choose(2, "drop_distinct", ("remove", "keep")):
                            steps.append(("distinct", left, shuffle + left * row * 3))
                            left = once
                        todo.append((g.rel, left, once))
        return steps

    def why_not(self, rel: str, question: DataFrame, domains: dict[str, DataFrame]) -> DataFrame:
        """Edges of the failed firings for the asked tuples; every variable the question leaves open needs a domain."""
        edges = []
        for k, r in enumerate(self.rules):
            if r.head.rel != rel:
                continue
            bound = {t: f"a{i}" for i, t in enumerate(r.head.args) if is_var(t) and f"a{i}" in question.columns}
            b = question.select(*(F.col(c).alias(v) for v, c in bound.items())).distinct()
            for v in sorted({t for g in r.body for t in g.args if is_var(t)} - set(bound)):
                if v not in domains:
                    raise ValueError(f"variable {v} needs a bounded domain")
                b = b.join(domains[v].toDF(v), F.lit(True))
            for a, op, c in r.compare:
                b = b.where(F.expr(f"{_sql(a)} {op} {_sql(c)}"))
            for j, g in enumerate(r.body):
                goal = self._goal(g, self.relation(g.rel)).distinct().withColumn(f"__g{j}", F.lit(True))
                on = [c for c in goal.columns if c != f"__g{j}"]
                b = b.join(goal, on, "left") if on else b.join(goal.limit(1), F.lit(True), "left")
                got = F.col(f"__g{j}").isNotNull()
                b = b.withColumn(f"ok_{j}", got if g.positive else ~got).drop(f"__g{j}")
            b = b.where(" or ".join(f"not ok_{j}" for j in range(len(r.body))))
            edges.append(self._edges(r, k, b, [F.col(f"ok_{j}") for j in range(len(r.body))], F.lit(False)))
        return reduce(DataFrame.unionAll, edges).distinct()

    def _edges(self, r: Rule, k: int, fire: DataFrame, ok: list[Column], fired: Column | None = None) -> DataFrame:
        """tuple -> firing, firing -> goals, goals -> tuples, one row each, from one pass over the firings."""
        fired = F.lit(True) if fired is None else fired
        vs = sorted({t for g in (r.head, *r.body) for t in g.args if is_var(t)})
        node = lambda tag, args: F.concat(F.lit(f"{tag}("), F.concat_ws(",", *(F.col(t).cast("string") if is_var(t) else F.lit(str(t)) for t in args)), F.lit(")"))
        firing = node(f"r{k}", vs)
        edge = lambda s, d, sk, dk, o: F.struct(s.alias("src"), d.alias("dst"), F.lit(sk).alias("src_kind"), F.lit(dk).alias("dst_kind"), F.lit(k).alias("rule"), o.alias("success"))
        rows = [edge(node(r.head.rel, r.head.args), firing, "rel", "rule", fired)]
        for j, g in enumerate(r.body):
            goal = node(f"r{k}.g{j}", [*vs])
            kind = "rel" if g.rel in self.idb else "edb"
            rows += [edge(firing, goal, "rule", "goal", ok[j]), edge(goal, node(g.rel, g.args), "goal", kind, ok[j])]
        return fire.select(F.explode(F.array(*rows)).alias("e")).select("e.*")


def _sql(t) -> str:
    return t if is_var(t) else f"'{t}'" if isinstance(t, str) else str(t)


def _bounded(bind: DataFrame) -> bool:
    """Questions made from driver-side values are small by construction."""
    return getattr(bind, "provloom_bounded", False)


def _small(bind: DataFrame) -> DataFrame:
    return F.broadcast(bind) if _bounded(bind) else bind


def question(spark: SparkSession, values: list[tuple]) -> DataFrame:
    q = spark.createDataFrame(values, ", ".join(f"a{i} {'long' if isinstance(v, int) else 'string'}" for i, v in enumerate(values[0])))
    q.provloom_bounded = len(values) <= 10_000
    return q


#: Programs over pairs co(x, y): neighbours of neighbours, neighbours without self pairs, indirect pairs, paths of three.
PROGRAMS = {
    "d1": "d1(X) :- co(X, Y), co(Y, Z).",
    "d2": "d2(X) :- co(X, Y), not co(X, X).",
    "d3": "d3(X, Z) :- co(X, Y), co(Y, Z), not co(X, Z).",
    "d4": "d4(X) :- co(X, Y), co(Y, Z), co(Z, W).",
    "d5": "d5(X) :- hop(X, Z), co(Z, W), W < 40. hop(X, Z) :- co(X, Y), co(Y, Z).",
}


def co_purchases(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distinct ordered pairs of different parts that stand in one order."""
    l = spark.read.parquet(f"{sf_dir}/lineitem.parquet").select("l_orderkey", "l_partkey").distinct()
    r = l.select(F.col("l_orderkey").alias("ok"), F.col("l_partkey").alias("y"))
    return l.join(r, (F.col("l_orderkey") == F.col("ok")) & (F.col("l_partkey") != F.col("y"))).select(F.col("l_partkey").alias("x"), "y").distinct()
