"""Sequenced queries over period tables (half-open [b, e)), and the normal forms of their results.

Selections and projections pass periods on; joins intersect overlapping periods; aggregates, distinct and difference
sweep over the endpoints of a group. A result is brought to a normal form: *set* merges touching and overlapping periods
of equal rows (right if no two equal rows hold at once), *bag* keeps how often a row holds at each instant.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from provloom.plans.search import Choices


def overlap_join(left: DataFrame, right: DataFrame, on: list[str], b: str = "b", e: str = "e", bucket: int | None = None) -> DataFrame:
    """Pairs of rows that agree on ``on`` and overlap; the period is their intersection.

    Without equal columns, or with ``bucket`` (length in the period's integer unit), each period is dealt to the buckets it
    touches, and a pair is formed in the first bucket both touch alone.
    """
    r = right.select(*(F.col(c).alias(f"r_{c}") for c in right.columns))
    cond = (F.col(b) < F.col(f"r_{e}")) & (F.col(f"r_{b}") < F.col(e))
    for c in on:
        cond = cond & (F.col(c) == F.col(f"r_{c}"))
    l = left
    if bucket:
        l = l.withColumn("__k", F.explode(F.sequence(F.floor(F.col(b) / bucket), F.floor((F.col(e) - 1) / bucket))))
        r = r.withColumn("__rk", F.explode(F.sequence(F.floor(F.col(f"r_{b}") / bucket), F.floor((F.col(f"r_{e}") - 1) / bucket))))
        cond = cond & (F.col("__k") == F.col("__rk")) & (F.col("__k") == F.floor(F.greatest(F.col(b), F.col(f"r_{b}")) / bucket))
    elif not on:
        raise ValueError("an overlap join without equal columns needs bucket")
    own = [c for c in left.columns if c not in (b, e)]
    theirs = [c for c in right.columns if c not in (b, e, *on)]
    return l.join(r, cond).select(*own, *(F.col(f"r_{c}").alias(c) for c in theirs), F.greatest(b, f"r_{b}").alias(b), F.least(e, f"r_{e}").alias(e))


def _sweep(df: DataFrame, keys: list[str], deltas: dict[str, tuple[Column, Column]], b: str, e: str) -> DataFrame:
    """Running sums of deltas per group between neighbouring change points: keys, deltas, b, e."""
    at = lambda t, k: df.select(*keys, F.col(t).alias("t"), *(d[k].alias(n) for n, d in deltas.items()))
    points = at(b, 0).unionAll(at(e, 1)).groupBy(*keys, "t").agg(*(F.sum(n).alias(n) for n in deltas))
    w = Window.partitionBy(*keys).orderBy("t")
    run = w.rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return points.select(*keys, *(F.sum(n).over(run).alias(n) for n in deltas), F.col("t").alias(b), F.lead("t").over(w).alias(e)).where(F.col(e).isNotNull())


def global_sweep(df: DataFrame, deltas: dict[str, tuple[Column, Column]], b: str = "b", e: str = "e", parts: int | None = None) -> DataFrame:
    """The sweep without groups, in two passes: ranges of time carry the sums of all ranges before them."""
    spark = df.sparkSession
    at = lambda t, k: df.select(F.col(t).alias("t"), *(d[k].alias(n) for n, d in deltas.items()))
    points = at(b, 0).unionAll(at(e, 1)).groupBy("t").agg(*(F.sum(n).alias(n) for n in deltas))
    parts = parts or int(spark.conf.get("spark.sql.shuffle.partitions"))
    num = F.col("t").cast("double") if dict(points.dtypes)["t"] in ("bigint", "int") else F.unix_micros(F.col("t").cast("timestamp")).cast("double")
    points = points.withColumn("tnum", num)
    cuts = sorted(set(points.approxQuantile("tnum", [i / parts for i in range(1, parts)], 0.01)))
    part = F.lit(0)
    for c in cuts:
        part = part + (F.col("tnum") >= c).cast("int")
    points = points.withColumn("part", part)
    ends = points.groupBy("part").agg(F.min("t").alias("first"), *(F.sum(n).alias(f"s_{n}") for n in deltas))
    w = Window.orderBy("part")  # one row a range
    carry = ends.select("part", F.lead("first").over(w).alias("then"), *((F.sum(f"s_{n}").over(w) - F.col(f"s_{n}")).alias(f"c_{n}") for n in deltas))
    v = Window.partitionBy("part").orderBy("t")
    run = v.rowsBetween(Window.unboundedPreceding, Window.currentRow)
    local = points.select("part", "t", F.lead("t").over(v).alias("next"), *(F.sum(n).over(run).alias(n) for n in deltas))
    out = local.join(F.broadcast(carry), "part")
    return out.select(*((F.col(n) + F.col(f"c_{n}")).alias(n) for n in deltas), F.col("t").alias(b), F.coalesce("next", "then").alias(e)).where(F.col(e).isNotNull())


def sequenced_aggregate(df: DataFrame, keys: list[str], value: str | None = None, b: str = "b", e: str = "e", time_domain: tuple | None = None) -> DataFrame:
    """count (and, with value, total as decimal and average) per group at every instant; empty instants give no row unless a
    time domain is named (global count alone)."""
    one = F.lit(1).cast("long")
    deltas = {"n": (one, -one)}
    if value:
        v = F.col(value).cast("decimal(18,2)")
        deltas["total"] = (v, -v)
    swept = _sweep(df, keys, deltas, b, e) if keys else global_sweep(df, deltas, b, e)
    out = swept.where("n > 0")
    if time_domain is not None:
        if keys or value:
            raise ValueError("a time domain is for the global count")
        lo, hi = (F.lit(x).cast(df.schema[b].dataType) for x in time_domain)
        gaps = swept.where("n = 0").select("n", b, e)
        ends = df.agg(F.min(b).alias("x"), F.max(e).alias("y"))
        edge = ends.select(F.lit(0).cast("long").alias("n"), lo.alias(b), F.coalesce("x", hi).alias(e)).unionAll(ends.where("y is not null").select(F.lit(0).cast("long"), F.col("y"), hi)).where(F.col(b) < F.col(e))
        return out.unionByName(gaps).unionByName(edge)
    if value:
        out = out.withColumn("average", F.round(F.col("total").cast("double") / F.col("n"), 6))
    return coalesce_set(out, [c for c in out.columns if c not in (b, e)], b, e)


def sequenced_minmax(df: DataFrame, keys: list[str], value: str, f: str, b: str = "b", e: str = "e") -> DataFrame:
    """Minimum or maximum at every instant: rows are cut at all endpoints of their group, then grouped."""
    points = df.select(*keys, F.col(b).alias("t")).union(df.select(*keys, F.col(e))).distinct()
    w = Window.partitionBy(*keys).orderBy("t")
    cells = points.select(*keys, F.col("t").alias("cb"), F.lead("t").over(w).alias("ce")).where("ce is not null")
    cut = cells.join(df, [*keys]) if keys else cells.crossJoin(df)
    cut = cut.where((F.col(b) <= F.col("cb")) & (F.col("ce") <= F.col(e)))
    out = cut.groupBy(*keys, "cb", "ce").agg(F.expr(f"{f}({value})").alias(f)).select(*keys, f, F.col("cb").alias(b), F.col("ce").alias(e))
    return coalesce_set(out, [*keys, f], b, e)


def sequenced_difference(left: DataFrame, right: DataFrame, cols: list[str], b: str = "b", e: str = "e") -> DataFrame:
    """Bag difference at every instant."""
    one = F.lit(1).cast("long")
    both = left.select(*cols, b, e, one.alias("__d")).unionAll(right.select(*cols, b, e, -one))
    swept = _sweep(both, cols, {"__n": (F.col("__d"), -F.col("__d"))}, b, e).where("__n > 0")
    return _repeat(_runs(swept, cols, b, e), cols, b, e)


def sequenced_distinct(df: DataFrame, cols: list[str], b: str = "b", e: str = "e") -> DataFrame:
    return coalesce_set(df, cols, b, e)


def coalesce_set(df: DataFrame, cols: list[str], b: str = "b", e: str = "e") -> DataFrame:
    """Maximal periods of equal rows: gaps and islands over the latest end so far."""
    w = Window.partitionBy(*cols).orderBy(b)
    before = F.max(e).over(w.rowsBetween(Window.unboundedPreceding, -1))
    d = df.where(F.col(b) < F.col(e)).withColumn("__new", F.when(before.isNull() | (before < F.col(b)), 1).otherwise(0))
    d = d.withColumn("__i", F.sum("__new").over(w.rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    return d.groupBy(*cols, "__i").agg(F.min(b).alias(b), F.max(e).alias(e)).select(*cols, b, e)


def _runs(swept: DataFrame, cols, b, e) -> DataFrame:
    """Neighbouring pieces of one count become one."""
    w = Window.partitionBy(*cols).orderBy(b)
    d = swept.withColumn("__new", F.when((F.lag(e).over(w) == F.col(b)) & (F.lag("__n").over(w) == F.col("__n")), 0).otherwise(1))
    d = d.withColumn("__i", F.sum("__new").over(w.rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    return d.groupBy(*cols, "__i").agg(F.first("__n").alias("__n"), F.min(b).alias(b), F.max(e).alias(e))


#: Copies of a run that are made in one go.
COPIES = 4096


def _repeat(runs: DataFrame, cols, b, e) -> DataFrame:
    """Each run as often as it counts. A few groups may hold most copies, so parts of runs are dealt to all tasks first."""
    parts = runs.select(*cols, b, e, "__n", F.explode(F.sequence(F.lit(0).cast("long"), F.col("__n") - 1, F.lit(COPIES).cast("long"))).alias("__p"))
    parts = parts.repartition(int(runs.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    return parts.select(*cols, b, e, F.explode(F.expr(f"array_repeat(0, int(least(__n - __p, {COPIES})))")).alias("__c")).select(*cols, b, e)


def coalesce_bag(df: DataFrame, cols: list[str], b: str = "b", e: str = "e") -> DataFrame:
    """The one encoding that keeps multiplicities: pieces of constant count, each as often as it counts."""
    one = F.lit(1).cast("long")
    swept = _sweep(df.where(F.col(b) < F.col(e)), cols, {"__n": (one, -one)}, b, e).where("__n > 0")
    return _repeat(_runs(swept, cols, b, e), cols, b, e)


def coalesce(df: DataFrame, cols: list[str], how: str = "choose", keys=(), choices: Choices | None = None, b: str = "b", e: str = "e") -> DataFrame:
    """set, bag, none, or a choice between the first two where a key without period columns makes set right."""
    if how == "none":
        return df.select(*cols, b, e)
    if how == "choose":
        legal = any(not {b, e} & set(k) for k in keys)
        how = ("set", "bag")[(choices or Choices()).choose(2, "coalesce", ("set", "bag"))] if legal else "bag"
    return coalesce_set(df, cols, b, e) if how == "set" else coalesce_bag(df, cols, b, e)


def snapshot(df: DataFrame, t, b: str = "b", e: str = "e") -> DataFrame:
    return df.where((F.col(b) <= F.lit(t)) & (F.lit(t) < F.col(e))).drop(b, e)
