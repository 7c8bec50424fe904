"""Schemas, keys and profiles of tables. Parquet has no constraints, so keys are declared, and verified on request."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from provloom.plans.cost import Profile, profile
from provloom.plans.ir import Rel, table

STAR = {
    "region": "r_regionkey r_name", "nation": "n_nationkey n_name n_regionkey",
    "customer": "c_custkey c_name c_nationkey c_acctbal c_mktsegment", "supplier": "s_suppkey s_name s_nationkey s_acctbal",
    "part": "p_partkey p_name p_brand p_type p_size p_retailprice",
    "orders": "o_orderkey o_custkey o_orderstatus o_totalprice o_orderdate o_orderpriority",
    "lineitem": "l_orderkey l_partkey l_suppkey l_linenumber l_quantity l_extendedprice l_discount l_tax l_returnflag l_linestatus l_shipdate",
    "events": "event_id ts user_id event_type value props", "documents": "doc_id text lang source n_chars",
    "labels": "doc_id quality toxic", "conversations": "conv_id turn role text",
}
KEYS = {
    "region": [("r_regionkey",), ("r_name",)], "nation": [("n_nationkey",), ("n_name",)], "customer": [("c_custkey",), ("c_name",)],
    "supplier": [("s_suppkey",), ("s_name",)], "part": [("p_partkey",)], "orders": [("o_orderkey",)], "lineitem": [], "events": [("event_id",)],
    "documents": [("doc_id",)], "labels": [("doc_id",)], "conversations": [("conv_id", "turn")],
}

_PROFILES: dict[tuple[str, str], Profile] = {}


def rel(name: str, access: int = 1, prefix: str = "") -> Rel:
    """A table of the star schema; prefix renames its columns for a second access."""
    cs = STAR[name].split()
    return table(name, cs, access, {c: prefix + c for c in cs} if prefix else None)


def profiles(spark: SparkSession, sf_dir: str, names) -> dict[str, Profile]:
    """Profiles of tables, one job each, kept per folder."""
    for n in names:
        if (sf_dir, n) not in _PROFILES:
            df = spark.read.parquet(f"{sf_dir}/{n}.parquet")
            _PROFILES[sf_dir, n] = profile(df.select(*[c for c in df.columns if c in STAR.get(n, "").split()] or df.columns))
    return {n: _PROFILES[sf_dir, n] for n in names}


def verify_key(df: DataFrame, key: tuple[str, ...]) -> bool:
    """Whether no two rows of this snapshot share the key's values."""
    return df.groupBy(*key).count().where(F.col("count") > 1).limit(1).count() == 0 if key else df.limit(2).count() <= 1
