"""Workloads on the star schema: eleven benchmark queries, chains of aggregations, and small queries for each operator."""

from __future__ import annotations

import math

from provloom.functions.expr import Col, If, Lit, col, fn
from provloom.plans.ir import Aggregate, Distinct, Limit, Node, SetOp
from provloom.sources.catalog import STAR, rel


def money(e: str) -> object:
    """A price in whole cents: sums are exact in every plan."""
    return fn(f"CAST(round({e} * 100) AS BIGINT)")


def percent(e: str) -> object:
    return fn(f"CAST(round(100 * ({e})) AS BIGINT)")


def date(d: str):
    return fn(f"TIMESTAMP_NTZ '{d} 00:00:00'")


REVENUE = money("l_extendedprice") * percent("1 - l_discount")


def t01() -> Node:
    return rel("lineitem").where(col("l_shipdate") <= date("2001-09-02")).group(
        ("l_returnflag", "l_linestatus"), ("sum", fn("CAST(l_quantity AS BIGINT)"), "sum_qty"), ("sum", money("l_extendedprice"), "sum_price"), ("count", Lit(1), "n"))


def t03() -> Node:
    j = rel("customer").where(col("c_mktsegment").eq("BUILDING")).join(rel("orders").where(col("o_orderdate") < date("1998-03-15")), col("c_custkey").eq(col("o_custkey")))
    j = j.join(rel("lineitem").where(col("l_shipdate") > date("1998-03-15")), col("l_orderkey").eq(col("o_orderkey")))
    return j.group(("l_orderkey", "o_orderdate"), ("sum", REVENUE, "revenue"))


def t05() -> Node:
    j = rel("customer").join(rel("orders").where((col("o_orderdate") >= date("1996-01-01")) & (col("o_orderdate") < date("1997-01-01"))), col("c_custkey").eq(col("o_custkey")))
    j = j.join(rel("lineitem"), col("l_orderkey").eq(col("o_orderkey"))).join(rel("supplier"), col("l_suppkey").eq(col("s_suppkey")) & col("c_nationkey").eq(col("s_nationkey")))
    j = j.join(rel("nation"), col("s_nationkey").eq(col("n_nationkey"))).join(rel("region").where(col("r_name").eq("ASIA")), col("n_regionkey").eq(col("r_regionkey")))
    return j.group(("n_name",), ("sum", REVENUE, "revenue"))


def t06() -> Node:
    c = (col("l_shipdate") >= date("1996-01-01")) & (col("l_shipdate") < date("1997-01-01")) & fn("(CAST(l_discount AS DECIMAL(4,2)) BETWEEN 0.05 AND 0.07)") & (col("l_quantity") < 24)
    return rel("lineitem").where(c).group((), ("sum", money("l_extendedprice") * percent("l_discount"), "revenue"))


def t07() -> Node:
    j = rel("supplier").join(rel("lineitem").where((col("l_shipdate") >= date("1997-01-01")) & (col("l_shipdate") <= date("1998-12-31"))), col("s_suppkey").eq(col("l_suppkey")))
    j = j.join(rel("orders"), col("o_orderkey").eq(col("l_orderkey"))).join(rel("customer"), col("c_custkey").eq(col("o_custkey")))
    j = j.join(rel("nation"), col("s_nationkey").eq(col("n_nationkey"))).join(rel("nation", 2, "x_"), col("c_nationkey").eq(col("x_n_nationkey")))
    a, b = "NATION_6", "NATION_7"
    j = j.where((col("n_name").eq(a) & col("x_n_name").eq(b)) | (col("n_name").eq(b) & col("x_n_name").eq(a)))
    items = [(col("n_name"), "supp_nation"), (col("x_n_name"), "cust_nation"), (fn("year(l_shipdate)"), "l_year"), (REVENUE, "volume")]
    return j.select(*items).group(("supp_nation", "cust_nation", "l_year"), ("sum", col("volume"), "revenue"))


def t08() -> Node:
    j = rel("part").where(col("p_type").eq("ECONOMY")).join(rel("lineitem"), col("p_partkey").eq(col("l_partkey"))).join(rel("supplier"), col("s_suppkey").eq(col("l_suppkey")))
    j = j.join(rel("orders").where((col("o_orderdate") >= date("1995-01-01")) & (col("o_orderdate") <= date("1996-12-31"))), col("l_orderkey").eq(col("o_orderkey"))).join(rel("customer"), col("o_custkey").eq(col("c_custkey")))
    j = j.join(rel("nation"), col("c_nationkey").eq(col("n_nationkey"))).join(rel("region").where(col("r_name").eq("AMERICA")), col("n_regionkey").eq(col("r_regionkey")))
    j = j.join(rel("nation", 2, "x_"), col("s_nationkey").eq(col("x_n_nationkey")))
    items = [(fn("year(o_orderdate)"), "o_year"), (REVENUE, "volume"), (If(col("x_n_name").eq("NATION_1"), REVENUE, Lit(0)), "own")]
    return j.select(*items).group(("o_year",), ("sum", col("own"), "own_volume"), ("sum", col("volume"), "all_volume"))


def t10() -> Node:
    j = rel("customer").join(rel("orders").where((col("o_orderdate") >= date("1997-10-01")) & (col("o_orderdate") < date("1998-01-01"))), col("c_custkey").eq(col("o_custkey")))
    j = j.join(rel("lineitem").where(col("l_returnflag").eq("R")), col("l_orderkey").eq(col("o_orderkey"))).join(rel("nation"), col("c_nationkey").eq(col("n_nationkey")))
    return j.group(("c_custkey", "c_name", "n_name"), ("sum", REVENUE, "revenue"))


def t12() -> Node:
    j = rel("orders").join(rel("lineitem").where(fn("(l_returnflag IN ('A', 'R'))") & col("l_linestatus").eq("F") & (col("l_shipdate") >= date("1997-01-01")) & (col("l_shipdate") < date("1998-01-01"))), col("o_orderkey").eq(col("l_orderkey")))
    high = fn("CAST(CASE WHEN o_orderpriority IN ('1-URGENT', '2-HIGH') THEN 1 ELSE 0 END AS BIGINT)")
    return j.group(("l_returnflag",), ("sum", high, "high_lines"), ("count", Lit(1), "lines"))


def t13() -> Node:
    j = rel("customer").join(rel("orders").where(col("o_orderstatus").ne("P")), col("c_custkey").eq(col("o_custkey")), "left")
    return j.group(("c_custkey",), ("count", col("o_orderkey"), "c_count")).group(("c_count",), ("count", Lit(1), "custdist"))


def t14() -> Node:
    j = rel("lineitem").where((col("l_shipdate") >= date("1997-09-01")) & (col("l_shipdate") < date("1997-10-01"))).join(rel("part"), col("l_partkey").eq(col("p_partkey")))
    return j.group((), ("sum", If(col("p_type").eq("PROMO"), REVENUE, Lit(0)), "promo"), ("sum", REVENUE, "revenue"))


T19 = "((p_brand = 'Brand#12' AND l_quantity BETWEEN 1 AND 11 AND p_size BETWEEN 1 AND 5) OR (p_brand = 'Brand#23' AND l_quantity BETWEEN 10 AND 20 AND p_size BETWEEN 1 AND 10) OR (p_brand = 'Brand#3' AND l_quantity BETWEEN 20 AND 30 AND p_size BETWEEN 1 AND 15))"


def t19() -> Node:
    return rel("lineitem").join(rel("part"), col("l_partkey").eq(col("p_partkey"))).where(fn(T19)).group((), ("sum", REVENUE, "revenue"))


BENCH = {"t01": t01, "t03": t03, "t05": t05, "t06": t06, "t07": t07, "t08": t08, "t10": t10, "t12": t12, "t13": t13, "t14": t14, "t19": t19}


def chain_divisors(i: int, top: int) -> list[int]:
    """Group sizes of a chain of i aggregations that ends in groups of top parts."""
    return [2 ** math.ceil(k * math.log2(top) / i) for k in range(1, i + 1)]


def chain(i: int, top: int = 512) -> Node:
    """i aggregations, one over the other: parts summed by ranges of keys that grow by powers of two."""
    node: Node = rel("part").select((fn("CAST(p_partkey AS BIGINT)"), "k0"), (money("p_retailprice"), "s0"))
    # division without div, which DuckDB lacks
    before = 1
    for level, d in enumerate(chain_divisors(i, top), 1):
        ratio = d // before
        node = node.select((fn(f"CAST(floor(k{level - 1} / {ratio}) AS BIGINT)"), f"k{level}"), (col(f"s{level - 1}"), f"v{level}"))
        node = node.group((f"k{level}",), ("sum", col(f"v{level}"), f"s{level}"))
        before = d
    return node


def top_divisor(sf_dir: str) -> int:
    """The last level's group size for the given table sizes, so that every chain ends in four or five groups."""
    return 4096 if sf_dir.rstrip("/").endswith("0.1") and "0.01" not in sf_dir else 64 if sf_dir.rstrip("/").endswith("0.001") else 512


def small() -> dict[str, Node]:
    """One small query for each operator's rewrite."""
    n, c, s, o = rel("nation"), rel("customer"), rel("supplier"), rel("orders")
    cn, sn = c.select((col("c_nationkey"), "k")), s.select((col("s_nationkey"), "k"))
    co = col("c_custkey").eq(col("o_custkey"))
    dear = o.where(col("o_totalprice") > 150000)
    return {
        "l1_spj_intro": c.join(dear, co).join(n, col("c_nationkey").eq(col("n_nationkey"))).select("n_name", "o_orderkey"),
        "l1_union": SetOp("union", cn, sn), "l1_distinct": Distinct(cn),
        "l1_intersect": SetOp("intersect", cn, sn), "l1_except_left": SetOp("except", n.select((col("n_nationkey"), "k")), sn.where(col("k") < 10)),
        "l1_outer": c.where(col("c_custkey") < 300).join(dear, co, "left").select("c_name", "o_orderkey"),
        "l1_semi": c.join(dear, co, "semi").select("c_custkey", "c_name"), "l1_anti": c.join(o, co, "anti").select("c_custkey", "c_name"),
        "l1_agg": o.group(("o_orderstatus",), ("sum", money("o_totalprice"), "total"), ("count", Lit(1), "n")),
        "l1_agg_global": o.group((), ("sum", money("o_totalprice"), "total"), ("max", col("o_orderkey"), "last")),
        "l1_agg_nested": o.group(("o_custkey",), ("sum", money("o_totalprice"), "total")).join(c, co).group(("c_nationkey",), ("sum", col("total"), "nation_total"), ("count", Lit(1), "buyers")),
        "l1_having": o.group(("o_custkey",), ("count", Lit(1), "n")).where(col("n") > 15),
        "l1_count_distinct": o.group(("o_orderstatus",), ("count_distinct", col("o_custkey"), "buyers")),
        "l1_limit": Limit(o.select("o_orderkey", "o_totalprice"), ("-o_totalprice", "o_orderkey"), 10),
    }
