"""Nested provenance: one document per result row, whose shape follows the query.

The type is fixed by the plan: a base row is a leaf, a join a product of two documents, a grouping a sum of its group's
documents, a union a sum with one filled side. Serialisers and evaluations walk that static type and build one Column, so
nothing runs in Python. Documents of a group are collected; a group over ``max_leaves`` raises rather than truncate.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from provloom.functions.expr import to_column
from provloom.plans import rules
from provloom.plans.ir import Aggregate, Distinct, Join, Node, Project, Rel, Select, SetOp, topological
from provloom.plans.lower import _agg

DOC = "prov_doc"


@dataclass(frozen=True)
class Shape:
    """kind: leaf (name, attrs), mult (l, r), add (item), either (l, r)."""

    kind: str
    name: str = ""
    attrs: tuple[str, ...] = ()
    kids: tuple[Shape, ...] = ()


def build(q: Node, spark: SparkSession, tables) -> tuple[DataFrame, Shape]:
    """The query's rows with their document, and the document's shape."""
    load = (lambda n: spark.read.parquet(f"{tables}/{n}.parquet")) if isinstance(tables, str) else tables.__getitem__
    if isinstance(q, Rel):
        df = load(q.name).select(*(F.col(a).alias(b) for a, b in q.attrs))
        return df.withColumn(DOC, F.struct(*(F.col(b).alias(a) for a, b in q.attrs))), Shape("leaf", q.name, tuple(a for a, _ in q.attrs))
    if isinstance(q, Select):
        df, s = build(q.child, spark, tables)
        return df.where(to_column(q.cond)), s
    if isinstance(q, Project):
        df, s = build(q.child, spark, tables)
        return df.select(*(to_column(e).alias(a) for e, a in q.items), DOC), s
    if isinstance(q, Join):
        left, ls = build(q.left, spark, tables)
        right, rs = build(q.right, spark, tables)
        left, right = left.withColumnRenamed(DOC, "doc_l"), right.withColumnRenamed(DOC, "doc_r")
        j = left.crossJoin(right) if q.cond is None else left.join(right, to_column(q.cond), q.how)
        return j.select(*q.schema, F.struct(F.col("doc_l").alias("l"), F.col("doc_r").alias("r")).alias(DOC)), Shape("mult", kids=(ls, rs))
    if isinstance(q, (Aggregate, Distinct)):
        df, s = build(q.child, spark, tables)
        keys = q.keys if isinstance(q, Aggregate) else q.schema
        aggs = [F.expr(_agg(f, e)).alias(a) for f, e, a in q.aggs] if isinstance(q, Aggregate) else []
        return df.groupBy(*keys).agg(*aggs, F.collect_list(DOC).alias(DOC)).select(*q.schema, DOC), Shape("add", kids=(s,))
    if isinstance(q, SetOp) and q.kind == "union":
        (left, ls), (right, rs) = build(q.left, spark, tables), build(q.right, spark, tables)
        lt, rt = left.schema[DOC].dataType, right.schema[DOC].dataType
        a = left.select(*q.schema, F.struct(F.col(DOC).alias("l"), F.lit(None).cast(rt).alias("r")).alias(DOC))
        b = right.select(*(F.col(x).alias(y) for x, y in zip(q.right.schema, q.schema)), F.struct(F.lit(None).cast(lt).alias("l"), F.col(DOC).alias("r")).alias(DOC))
        return a.unionAll(b), Shape("either", kids=(ls, rs))
    raise ValueError(f"no documents for {type(q).__name__}")


def capture_nested(spark: SparkSession, sf_dir: str, query: Node, factorize: bool = True, keys=None, max_leaves: int | None = None) -> tuple[DataFrame, Shape]:
    """Documents of a query; with factorize, groupings are pushed below joins first, so sums stand inside products."""
    from provloom.sources.catalog import KEYS

    q = rules.fixpoint(query, keys or KEYS, rules.FACTORIZE) if factorize else query
    df, shape = build(q, spark, sf_dir)
    if max_leaves:
        df = df.withColumn(DOC, F.when(evaluate(F.col(DOC), shape, "leaves") > max_leaves, F.raise_error(F.lit("document over max_leaves"))).otherwise(F.col(DOC)))
    return df, shape


#: Columns that hold a document's values where no document is built.
_LEAVES, _COUNT = "__leaves", "__count"


def _valued(q: Node, spark: SparkSession, tables) -> DataFrame:
    """The query's rows with the number of leaves and of derivations of the documents that ``build`` would give them."""
    if isinstance(q, Rel):
        load = (lambda n: spark.read.parquet(f"{tables}/{n}.parquet")) if isinstance(tables, str) else tables.__getitem__
        one = F.lit(1).cast("long")
        return load(q.name).select(*(F.col(a).alias(b) for a, b in q.attrs), one.alias(_LEAVES), one.alias(_COUNT))
    if isinstance(q, Select):
        return _valued(q.child, spark, tables).where(to_column(q.cond))
    if isinstance(q, Project):
        return _valued(q.child, spark, tables).select(*(to_column(e).alias(a) for e, a in q.items), _LEAVES, _COUNT)
    if isinstance(q, Join):
        left, right = (_valued(x, spark, tables).withColumnsRenamed({_LEAVES: f"{_LEAVES}_{k}", _COUNT: f"{_COUNT}_{k}"}) for k, x in enumerate(q.kids))
        j = left.crossJoin(right) if q.cond is None else left.join(right, to_column(q.cond))
        return j.select(*q.schema, (F.col(f"{_LEAVES}_0") + F.col(f"{_LEAVES}_1")).alias(_LEAVES), (F.col(f"{_COUNT}_0") * F.col(f"{_COUNT}_1")).alias(_COUNT))
    if isinstance(q, (Aggregate, Distinct)):
        keys = q.keys if isinstance(q, Aggregate) else q.schema
        aggs = [F.expr(_agg(f, e)).alias(a) for f, e, a in q.aggs] if isinstance(q, Aggregate) else []
        sums = [F.coalesce(F.sum(c), F.lit(0).cast("long")).alias(c) for c in (_LEAVES, _COUNT)]
        return _valued(q.child, spark, tables).groupBy(*keys).agg(*aggs, *sums).select(*q.schema, _LEAVES, _COUNT)
    left, right = (_valued(x, spark, tables) for x in q.kids)
    return left.unionAll(right.toDF(*q.schema, _LEAVES, _COUNT))


def capture_sizes(spark: SparkSession, sf_dir: str, query: Node, factorize: bool = True, keys=None) -> DataFrame:
    """What ``sizes`` says of the documents of ``capture_nested``. A sum's value is the sum of its parts' values, so a group
    keeps two numbers and no document; outer, semi and anti joins have their documents built."""
    from provloom.sources.catalog import KEYS

    q = rules.fixpoint(query, keys or KEYS, rules.FACTORIZE) if factorize else query
    if any(isinstance(n, Join) and n.how not in ("inner", "cross") or isinstance(n, SetOp) and n.kind != "union" for n in topological(q)):
        return sizes(*build(q, spark, sf_dir))
    return _valued(q, spark, sf_dir).withColumnsRenamed({_LEAVES: "n_leaves", _COUNT: "n_derivations"})


def evaluate(doc, s: Shape, semiring: str, weight=None):
    """A document in a semiring: leaves (references written), count (derivations), bool, cost (cheapest, weight of a leaf)."""
    if s.kind == "leaf":
        one = {"leaves": F.lit(1).cast("long"), "count": F.lit(1).cast("long"), "bool": F.lit(True), "cost": weight(doc, s) if weight else F.lit(1.0)}[semiring]
        return F.when(doc.isNotNull(), one)
    kids = lambda d, f: evaluate(d[f], s.kids[0 if f == "l" else 1], semiring, weight)
    zero = {"leaves": F.lit(0).cast("long"), "count": F.lit(0).cast("long"), "bool": F.lit(False), "cost": F.lit(float("inf"))}[semiring]
    plus = {"leaves": lambda a, b: a + b, "count": lambda a, b: a + b, "bool": lambda a, b: a | b, "cost": lambda a, b: F.least(a, b)}[semiring]
    if s.kind == "mult":
        l, r = kids(doc, "l"), kids(doc, "r")
        times = {"leaves": lambda a, b: a + b, "count": lambda a, b: a * b, "bool": lambda a, b: a & b, "cost": lambda a, b: a + b}[semiring]
        return times(l, F.coalesce(r, F.lit(0).cast("long") if semiring == "leaves" else r))
    if s.kind == "either":
        return F.coalesce(kids(doc, "l"), kids(doc, "r"))
    return F.aggregate(doc, zero, lambda acc, x: plus(acc, evaluate(x, s.kids[0], semiring, weight)))


def to_xml(doc, s: Shape):
    """The document as text: add, mult and relation elements."""
    if s.kind == "leaf":
        attrs = F.concat(*[x for a in s.attrs for x in (F.lit(f' {a}="'), F.coalesce(F.regexp_replace(F.regexp_replace(doc[a].cast("string"), "&", "&amp;"), '"', "&quot;"), F.lit("")), F.lit('"'))])
        return F.concat(F.lit(f"<{s.name}"), attrs, F.lit("/>"))
    if s.kind == "mult":
        return F.concat(F.lit("<mult>"), to_xml(doc["l"], s.kids[0]), F.coalesce(to_xml(doc["r"], s.kids[1]), F.lit("")), F.lit("</mult>"))
    if s.kind == "either":
        return F.coalesce(to_xml(doc["l"], s.kids[0]), to_xml(doc["r"], s.kids[1]))
    return F.concat(F.lit("<add>"), F.array_join(F.transform(doc, lambda x: to_xml(x, s.kids[0])), ""), F.lit("</add>"))


def sizes(df: DataFrame, shape: Shape) -> DataFrame:
    """The plain columns with n_leaves (references written) and n_derivations of each document."""
    d = F.col(DOC)
    return df.select(*[c for c in df.columns if c != DOC], evaluate(d, shape, "leaves").alias("n_leaves"), evaluate(d, shape, "count").alias("n_derivations"))
