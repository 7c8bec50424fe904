"""Provenance as PROV documents: entities, an activity, and used, generated and derived edges, as JSON fragments.

Each section is a projection (and a distinct) of the flat result. Ids come from keys where the catalog has them; else
rows are numbered by a window over all attributes, unless the section that would show the number isn't asked for.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from provloom.capture import capture
from provloom.plans.ir import Node, Rel, topological
from provloom.plans.props import infer_keys
from provloom.sources.catalog import KEYS

SECTIONS = ("entity", "activity", "used", "wasGeneratedBy", "wasDerivedFrom")


def _id(prefix: str, cols: list[str]):
    return F.concat(F.lit(f"{prefix}:"), F.concat_ws("|", *(F.col(c).cast("string") for c in cols)))


def fragments(spark: SparkSession, sf_dir: str, query: Node, sections=SECTIONS, optimize_: str = "heu", staged: bool = True) -> DataFrame:
    """(section, id, json). With optimize_ none, rows of every relation are numbered by a window even where a key would do."""
    r = capture(spark, sf_dir, query, optimize_="heu" if optimize_ == "cost" else optimize_, agg="join")
    df = r.df
    rels = [n for n in topological(query) if isinstance(n, Rel)]
    key = min(infer_keys(query, KEYS)[id(query)], key=lambda k: (len(k), sorted(k)), default=None)
    ids = {}
    for n in rels:
        p = f"prov_{n.name}_" + (f"{n.access}_" if n.access > 1 else "")
        keys = KEYS.get(n.name) or []
        attrs = [f"{p}{a}" for a, _ in n.attrs if f"{p}{a}" in df.columns]
        if keys and optimize_ != "none":
            ids[p] = (n.name, _id(n.name, [f"{p}{a}" for a in keys[0]]), attrs)
        else:
            df = df.withColumn(f"n_{p}", F.dense_rank().over(Window.orderBy(*attrs)) if optimize_ == "none" else F.xxhash64(*attrs))
            ids[p] = (n.name, _id(n.name, [f"n_{p}"]), attrs)
    plain = [c for c in r.df.columns if not c.startswith("prov_")]
    out = _id("result", sorted(key) if key else plain)
    if staged and len(sections) > 1 and optimize_ != "none":
        from pyspark import StorageLevel

        df = df.persist(StorageLevel.DISK_ONLY)  # one run of the query serves all sections; lost blocks are recomputed
    q = F.lit("activity:query")
    parts = []
    frag = lambda d, s, i, j: d.select(F.lit(s).alias("section"), i.alias("id"), F.to_json(j).alias("json"))
    if "entity" in sections:
        parts.append(frag(df, "entity", out, F.struct(*plain)))
        parts += [frag(df.where(" or ".join(f"{a} is not null" for a in attrs)), "entity", i, F.struct(*(F.col(a).alias(a[len(p) :]) for a in attrs))) for p, (_, i, attrs) in ids.items()]
    if "activity" in sections:
        parts.append(spark.range(1).select(F.lit("activity").alias("section"), q.alias("id"), F.lit('{"type":"query"}').alias("json")))
    for p, (_, i, attrs) in ids.items():
        has = df.where(" or ".join(f"{a} is not null" for a in attrs))
        if "used" in sections:
            parts.append(frag(has, "used", F.concat(F.lit("used:"), i), F.struct(q.alias("activity"), i.alias("entity"))))
        if "wasDerivedFrom" in sections:
            parts.append(frag(has, "wasDerivedFrom", F.concat(F.lit("der:"), out, F.lit(">"), i), F.struct(out.alias("generatedEntity"), i.alias("usedEntity"))))
    if "wasGeneratedBy" in sections:
        parts.append(frag(df, "wasGeneratedBy", F.concat(F.lit("gen:"), out), F.struct(out.alias("entity"), q.alias("activity"))))
    whole = parts[0]
    for x in parts[1:]:
        whole = whole.unionAll(x)
    return whole.distinct()


def lines(frags: DataFrame) -> DataFrame:
    """The document that ``document`` makes, a line for each fragment: (section, id, line). In the order of section and id the
    lines together are one JSON value, and no task holds more than its own lines."""
    ends = frags.groupBy("section").agg(F.min("id").alias("__first"), F.max("id").alias("__last"))  # a row for each section
    bounds = frags.agg(F.min("section").alias("__from"), F.max("section").alias("__to"))
    d = frags.join(F.broadcast(ends), "section").crossJoin(F.broadcast(bounds))
    opened = F.concat(F.when(F.col("section") == F.col("__from"), "{").otherwise(","), F.lit('"'), F.col("section"), F.lit('":{'))
    begin = F.when(F.col("id") == F.col("__first"), opened).otherwise(",")
    end = F.when(F.col("id") == F.col("__last"), F.when(F.col("section") == F.col("__to"), "}}").otherwise("}")).otherwise("")
    return d.select("section", "id", F.concat(begin, F.lit('"'), F.col("id"), F.lit('":'), F.col("json"), end).alias("line")).orderBy("section", "id")


def document(frags: DataFrame, max_rows: int = 100_000) -> DataFrame:
    """All fragments as one JSON value; raises if there are more than max_rows, as one task builds it: ``lines`` has no such bound."""
    n = frags.count()
    if n > max_rows:
        raise ValueError(f"{n} fragments are too many for one value; lines() gives the document line by line")
    per = frags.groupBy("section").agg(F.array_sort(F.collect_list(F.struct("id", "json"))).alias("xs"))
    body = F.concat(F.lit('"'), F.col("section"), F.lit('":{'), F.array_join(F.transform("xs", lambda x: F.concat(F.lit('"'), x["id"], F.lit('":'), x["json"])), ","), F.lit("}"))
    return per.select(body.alias("b")).agg(F.concat(F.lit("{"), F.array_join(F.array_sort(F.collect_list("b")), ","), F.lit("}")).alias("document"))


def export_query(sf_dir: str = "") -> Node:
    from provloom.functions.expr import col
    from provloom.sources.catalog import rel

    j = rel("nation").join(rel("customer"), col("n_nationkey").eq(col("c_nationkey"))).join(rel("orders"), col("c_custkey").eq(col("o_custkey")))
    return j.select("n_name", "c_custkey", "o_orderkey")
