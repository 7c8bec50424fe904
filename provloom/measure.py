"""Measures: runtimes, totals, ratios, optimisation time, sizes, shapes of plans, competitive ratio."""

from __future__ import annotations

import time
from statistics import median

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from provloom.functions.expr import refs
from provloom.plans.cost import rank_correlation  # noqa: F401
from provloom.plans.ir import Aggregate, Distinct, Join, Node, Project, WindowOp, count_nodes, topological


def runtime(make, runs: int = 3, warm: bool = True) -> float:
    """Median wall seconds of running make() into the noop sink."""
    took = []
    for i in range(runs + warm):
        t = time.perf_counter()
        make().write.format("noop").mode("overwrite").save()
        if i >= warm:
            took.append(time.perf_counter() - t)
    return median(took)


def total(seconds: dict[str, float | None], limit: float) -> tuple[float, bool]:
    """Sum over queries; a query over the limit (None) counts as the limit, and the sum is a lower bound."""
    late = [q for q, s in seconds.items() if s is None or s > limit]
    return sum(limit if q in late else s for q, s in seconds.items()), bool(late)


def relative_to(base: dict[str, float], other: dict[str, float]) -> float:
    """Mean over the queries of the time relative to the base configuration."""
    both = [q for q in base if q in other]
    return sum(other[q] / base[q] for q in both) / len(both)


def relative_to_best(totals: dict[str, dict[str, float]]) -> dict[str, tuple[float, float, float]]:
    """Per configuration: least, mean and greatest slowdown over the workloads, the best configuration of each being 1."""
    configs = {c for t in totals.values() for c in t}
    ratios = {c: [t[c] / min(t.values()) for t in totals.values() if c in t] for c in configs}
    return {c: (min(r), sum(r) / len(r), max(r)) for c, r in ratios.items()}


def competitive_ratio(steps: list[tuple[float, float]]) -> float:
    """Total (optimisation up to the adaptive stop plus best estimate) over the best stop's; steps: (seconds, estimate)."""
    spent, best, sums, stop = 0.0, float("inf"), [], None
    for took, estimate in steps:
        spent += took
        best = min(best, estimate)
        sums.append(spent + best)
        if stop is None and spent >= best:
            stop = sums[-1]
    return (sums[-1] if stop is None else stop) / min(sums)


def expr_refs(node: Node) -> int:
    """Attribute references in all projections of a graph."""
    return sum(refs(e) for n in topological(node) if isinstance(n, Project) for e, _ in n.items)


def shape(node: Node) -> dict[str, int]:
    return {k.__name__: count_nodes(node, k) for k in (Distinct, WindowOp, Join, Aggregate, Project)}


def physical(df: DataFrame) -> dict[str, int]:
    """Operators of the physical plan that cost most."""
    text = df._jdf.queryExecution().executedPlan().toString()
    return {k: text.count(k) for k in ("Exchange hashpartitioning", "BroadcastExchange", "SortMergeJoin", "BroadcastHashJoin", "Window ", "HashAggregate", "BroadcastNestedLoopJoin")}


def result_size(df: DataFrame) -> DataFrame:
    """Rows and bytes (as JSON) of a result."""
    return df.agg(F.count("*").alias("n_rows"), F.sum(F.length(F.to_json(F.struct(*df.columns)))).alias("n_bytes"))
