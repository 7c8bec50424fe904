"""Where-provenance: for every output cell, the set of (relation, key, attribute) cells it was copied from."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from provloom.functions.expr import Col, to_column
from provloom.plans.ir import Aggregate, Distinct, Join, Node, Project, Rel, Select, SetOp
from provloom.plans.lower import _agg

CELL = "array<struct<rel:string,key:string,attr:string>>"


def capture_where(spark: SparkSession, tables, q: Node, keys: dict[str, list[tuple]]) -> DataFrame:
    """The query's columns with ``where_<column>`` arrays. Only plain references copy; computed cells have no origin."""
    load = (lambda n: spark.read.parquet(f"{tables}/{n}.parquet")) if isinstance(tables, str) else tables.__getitem__
    w = lambda c: f"where_{c}"
    none = F.array().cast(CELL)
    if isinstance(q, Rel):
        key = keys[q.name][0]
        ident = F.concat_ws("|", *(F.col(k).cast("string") for k in key))
        df = load(q.name)
        cell = lambda a: F.array(F.struct(F.lit(q.name).alias("rel"), ident.alias("key"), F.lit(a).alias("attr"))).alias(w(dict(q.attrs)[a]))
        return df.select(*(F.col(a).alias(b) for a, b in q.attrs), *(cell(a) for a, _ in q.attrs))
    if isinstance(q, Select):
        return capture_where(spark, tables, q.child, keys).where(to_column(q.cond))
    if isinstance(q, Project):
        df = capture_where(spark, tables, q.child, keys)
        return df.select(*(to_column(e).alias(a) for e, a in q.items), *((F.col(w(e.name)) if isinstance(e, Col) else none).alias(w(a)) for e, a in q.items))
    if isinstance(q, Join):
        l, r = capture_where(spark, tables, q.left, keys), capture_where(spark, tables, q.right, keys)
        j = l.crossJoin(r) if q.cond is None else l.join(r, to_column(q.cond), {"semi": "left_semi", "anti": "left_anti"}.get(q.how, q.how))
        return j.select(*q.schema, *map(w, q.schema))
    if isinstance(q, SetOp) and q.kind == "union":
        l, r = capture_where(spark, tables, q.left, keys), capture_where(spark, tables, q.right, keys)
        return l.select(*q.schema, *map(w, q.schema)).unionAll(r.select(*q.right.schema, *map(w, q.right.schema)))
    if isinstance(q, (Aggregate, Distinct)):
        df = capture_where(spark, tables, q.child, keys)
        group = q.keys if isinstance(q, Aggregate) else q.schema
        aggs = [F.expr(_agg(f, e)).alias(a) for f, e, a in q.aggs] if isinstance(q, Aggregate) else []
        out = df.groupBy(*group).agg(*aggs, *(F.array_sort(F.array_distinct(F.flatten(F.collect_set(w(c))))).alias(w(c)) for c in group))
        return out.select(*q.schema, *(F.col(w(c)) if c in group else none.alias(w(c)) for c in q.schema))
    raise ValueError(f"no where-provenance for {type(q).__name__}")
