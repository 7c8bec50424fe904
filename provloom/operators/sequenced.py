"""The sequenced form of a plain query: its snapshot at each instant is the query's result over the tables' snapshots.

A query graph over period tables is compiled operator by operator onto the functions of ``temporal``; its result is brought
to a normal form. Where the inferred keys show that no two equal rows hold at once, both normal forms are right and the
cheaper one is searched for; elsewhere only the bag form is.

Outer, semi and anti joins, windows and limits have no sequenced form here and raise, as do joins without an equality. An
aggregate without keys gives no row for instants without input.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from provloom.functions.expr import to_column
from provloom.operators import temporal
from provloom.plans.cost import Estimate, ModelCost, profile
from provloom.plans.ir import Aggregate, Distinct, Join, Node, Project, Rel, Select, SetOp, topological
from provloom.plans.props import equalities, infer_keys
from provloom.plans.search import Best, Choices, optimize

_INTEGERS = ("tinyint", "smallint", "int", "bigint")


def compile_periods(root: Node, tables: dict[str, DataFrame], b: str = "b", e: str = "e") -> DataFrame:
    """The query's rows with periods, in no normal form. tables: names to DataFrames with the columns b and e."""
    got: dict[int, DataFrame] = {}
    for n in topological(root):
        k = [got[id(x)] for x in n.kids]
        if isinstance(n, Rel):
            df = tables[n.name].where(F.col(b) < F.col(e)).select(*(F.col(a).alias(c) for a, c in n.attrs), b, e)
        elif isinstance(n, Select):
            df = k[0].filter(to_column(n.cond))
        elif isinstance(n, Project):
            df = k[0].select(*(to_column(x).alias(a) for x, a in n.items), b, e)
        elif isinstance(n, Join) and n.how == "inner":
            df = _join(n, *k, b, e)
        elif isinstance(n, SetOp):
            df = _setop(n, k[0], k[1].toDF(*n.schema, b, e), b, e)
        elif isinstance(n, Distinct):
            df = temporal.sequenced_distinct(k[0], list(n.schema), b, e)
        elif isinstance(n, Aggregate):
            df = _aggregate(n, k[0], b, e)
        else:
            raise ValueError(f"no sequenced form of {type(n).__name__} {getattr(n, 'how', '')}".strip())
        got[id(n)] = df
    return got[id(root)]


def _join(n: Join, left: DataFrame, right: DataFrame, b: str, e: str) -> DataFrame:
    if n.cond is None or not equalities(n.cond):
        raise ValueError("a sequenced join needs an equality; temporal.overlap_join deals periods to buckets without one")
    right = right.withColumnsRenamed({b: "__rb", e: "__re"})
    both = left.join(right, to_column(n.cond) & (F.col(b) < F.col("__re")) & (F.col("__rb") < F.col(e)))
    return both.select(*n.schema, F.greatest(b, "__rb").alias(b), F.least(e, "__re").alias(e))


def _setop(n: SetOp, left: DataFrame, right: DataFrame, b: str, e: str) -> DataFrame:
    cols = list(n.schema)
    if n.kind == "union":
        return left.unionAll(right)
    minus = temporal.sequenced_difference(left, right, cols, b, e)
    # what left has more often than right goes; the rest is in both
    return minus if n.kind == "except" else temporal.sequenced_difference(left, minus, cols, b, e)


def _aggregate(n: Aggregate, df: DataFrame, b: str, e: str) -> DataFrame:
    keys = list(n.keys)
    if any(f in ("min", "max") for f, _, _ in n.aggs):
        if len(n.aggs) > 1:
            raise ValueError("a sequenced minimum or maximum stands alone in its aggregate")
        (f, x, name), = n.aggs
        out = temporal.sequenced_minmax(df.select(*keys, to_column(x).alias("__v"), b, e), keys, "__v", f, b, e)
        return out.select(*keys, F.col(f).alias(name), b, e)
    if bad := [f for f, _, _ in n.aggs if f not in ("count", "sum", "avg")]:
        raise ValueError(f"no sequenced form of {bad[0]}")
    given = df.select(*keys, *(to_column(x).alias(f"__x{i}") for i, (_, x, _) in enumerate(n.aggs)), b, e)
    kinds, one = dict(given.dtypes), F.lit(1).cast("long")
    deltas = {"__n": (one, -one)}
    for i in range(len(n.aggs)):
        x, kind = F.col(f"__x{i}"), kinds[f"__x{i}"]
        held = x.isNotNull().cast("long")
        deltas[f"__c{i}"] = (held, -held)
        if n.aggs[i][0] != "count":
            # running sums of doubles would not come back to what they were
            exact = kind if kind.startswith("decimal") else "bigint" if kind in _INTEGERS else "decimal(28,6)"
            v = F.coalesce(x.cast(exact), F.lit(0).cast(exact))
            deltas[f"__s{i}"] = (v, -v)
    swept = temporal._sweep(given, keys, deltas, b, e) if keys else temporal.global_sweep(given, deltas, b, e)

    def value(i: int, f: str):
        if f == "count":
            return F.col(f"__c{i}")
        total = F.when(F.col(f"__c{i}") > 0, F.col(f"__s{i}"))
        exact = kinds[f"__x{i}"] in _INTEGERS or kinds[f"__x{i}"].startswith("decimal")
        return total.cast("double") / F.col(f"__c{i}") if f == "avg" else total if exact else total.cast("double")

    out = swept.where("__n > 0").select(*keys, *(value(i, f).alias(name) for i, (f, _, name) in enumerate(n.aggs)), b, e)
    return temporal.coalesce_set(out, list(n.schema), b, e)


def form_cost(model: ModelCost, root: Node):
    """Seconds of a normal form of the query's result: set sorts the rows, bag their end points and then the runs."""
    rows, width = (lambda x: (x.rows, x.width + 16))(model.estimate(root))

    def sort(n: float) -> float:
        return model._move(Estimate(n, {}, width, 0)) + model._work(n, True)

    return {"set": sort(rows), "bag": sort(2 * rows) + model._work(2 * rows, True)}.__getitem__


def choose_form(root: Node, model: ModelCost, keys: dict[str, list[tuple]]) -> Best:
    """The cheapest normal form among those that are right; keys hold at each instant."""
    legal = ("set", "bag") if infer_keys(root, keys)[id(root)] else ("bag",)
    return optimize(lambda c: legal[c.choose(len(legal), "coalesce", legal) if len(legal) > 1 else 0], form_cost(model, root))


def sequenced(spark: SparkSession, root: Node, tables: dict[str, DataFrame], how: str = "choose", keys: dict[str, list[tuple]] | None = None, model: ModelCost | None = None, b: str = "b", e: str = "e") -> DataFrame:
    """The query at every instant. how: ``set``, ``bag``, ``none``, or ``choose`` by keys and cost (profiles take a job a table)."""
    df = compile_periods(root, tables, b, e)
    if how == "choose":
        names = {n.name for n in topological(root) if isinstance(n, Rel)}
        how = choose_form(root, model or ModelCost({t: profile(tables[t]) for t in names}), keys or {}).plan
    if how == "bag" and isinstance(root, SetOp) and root.kind != "union":
        return df  # differences are in the bag form already
    return temporal.coalesce(df, list(root.schema), how, b=b, e=e)
