"""Queries with their provenance: compile, rewrite, choose, run."""

from __future__ import annotations

import time
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from provloom.operators import flat
from provloom.plans import rules
from provloom.plans.cost import ModelCost
from provloom.plans.ir import Node, Rel, topological
from provloom.plans.lower import to_dataframe
from provloom.plans.search import AdaptiveStop, Best, Choices, Sequential, optimize
from provloom.sources.catalog import KEYS, profiles


@dataclass
class ProvResult:
    df: DataFrame
    plan: Node
    trace: Best | None
    compile_seconds: float


AGG = {"window": 0, "join": 1}
DELTA = {"remove": 0, "keep": 1}


def capture(spark: SparkSession, sf_dir: str, query: Node, agg: str = "choose", diff: str = "left", optimize_: str = "cost", drop_distinct: str = "choose", strategy=None, stop=None, keys=None, tables=None, keep_empty: bool = False, which=rules.DEFAULT) -> ProvResult:
    """Flat provenance of a query.

    optimize_: ``none`` compiles as it is, ``heu`` applies the rules (every removable distinct goes), ``cost`` searches
    the open choices for the cheapest plan. agg and drop_distinct fix their choices unless they are ``choose``.
    """
    began, keys = time.perf_counter(), KEYS if keys is None else keys
    fixed = {}
    if agg != "choose":
        fixed["agg_method"] = AGG[agg]
    if optimize_ == "heu":
        fixed["drop_distinct"] = 0
    elif drop_distinct != "choose":
        fixed["drop_distinct"] = DELTA[drop_distinct]

    def pipeline(c: Choices) -> Node:
        node = rules.share_common(flat.rewrite(query, c, diff=diff, keep_empty=keep_empty))
        return node if optimize_ == "none" else rules.fixpoint(node, keys, which, c)

    trace = None
    if optimize_ == "cost":
        model = ModelCost(profiles(spark, sf_dir, {n.name for n in topological(query) if isinstance(n, Rel)}))
        trace = optimize(pipeline, model, strategy or Sequential(), stop or AdaptiveStop(), fixed=fixed)
        plan = trace.plan
    else:
        plan = pipeline(Choices(fixed=fixed))
    return ProvResult(to_dataframe(plan, spark, tables or sf_dir), plan, trace, time.perf_counter() - began)


def backward(result: DataFrame, condition: str, relation: str) -> DataFrame:
    """Input rows of a relation that the chosen result rows come from."""
    mine = [c for c in result.columns if c.startswith(f"prov_{relation}_")]
    return result.where(condition).select(*mine).where(" or ".join(f"{c} is not null" for c in mine)).distinct()


def forward(result: DataFrame, condition: str) -> DataFrame:
    """Result rows that come from the input rows chosen by a condition on provenance columns."""
    return result.where(condition).select(*[c for c in result.columns if not c.startswith("prov_")]).distinct()
