"""Queries over periods in their sequenced form, sets of why-questions, and late events."""

from __future__ import annotations

import uuid
from functools import partial

from pyspark.sql import functions as F

from provloom.functions.expr import col
from provloom.operators import datalog, sequenced, temporal
from provloom.plans import search
from provloom.plans.ir import Distinct, SetOp, table
from provloom.streaming import events
from provloom.workloads import registry as reg

#: Keys that hold at each instant: a user's next period begins where the one before it ends.
KEYS = {"sal": [("user_id",)], "dept": [("dept_user",)], "emp": [("emp_user",)]}


def _sal():
    return table("sal", ("user_id", "value"))


def _dept():
    return table("dept", ("dept_user", "d"))


def _both():
    return _sal().join(_dept(), col("user_id").eq(col("dept_user")))


#: Plain queries: averages, joins, and operators that leave several equal rows at an instant.
PLAIN = {
    "s1": lambda: _both().group(("d",), ("count", col("value"), "n"), ("avg", col("value"), "average")),
    "s2": lambda: _both().join(table("emp", ("emp_user",)), col("user_id").eq(col("emp_user"))).select("user_id", "value", "d"),
    "union": lambda: SetOp("union", _sal().select("user_id"), _dept().select((col("dept_user"), "u2"))),
    "except": lambda: SetOp("except", _dept().select("d"), _dept().where(col("dept_user") < 100).select((col("d"), "d2"))),
    "distinct": lambda: Distinct(_dept().select("d")),
}


def tables(spark, sf_dir):
    sal, dept, emp = reg.periods(spark, sf_dir)
    return {"sal": sal, "dept": dept.withColumnRenamed("user_id", "dept_user"), "emp": emp.withColumnRenamed("user_id", "emp_user")}


def _plain(name, spark, sf_dir):
    return sequenced.sequenced(spark, PLAIN[name](), tables(spark, sf_dir), keys=KEYS)


_AVG = "a3 AS (SELECT d, n, CAST(sum_y AS DOUBLE) / n AS average, b, e FROM (SELECT d, t AS b, lead(t) OVER (PARTITION BY d ORDER BY t) AS e, CAST(sum(x) OVER (PARTITION BY d ORDER BY t) AS BIGINT) AS n, sum(y) OVER (PARTITION BY d ORDER BY t) AS sum_y FROM q1) WHERE n > 0 AND e IS NOT NULL)"
_EXACT = reg._A1.replace("DECIMAL(18,2)", "DECIMAL(28,6)").replace(" FROM j UNION", " FROM j WHERE b < e UNION").replace(" FROM j)", " FROM j WHERE b < e)")
reg.add("temp_seq_s1", partial(_plain, "s1"), f"WITH {reg._SALS}, {reg._DEPTS}, {reg._J1}, {_EXACT}, {_AVG}, {reg._set_sql('a3', 'd, n, average')}")
reg.add("temp_seq_s2", partial(_plain, "s2"), f"WITH {reg._SALS}, {reg._DEPTS}, {reg._EMPS}, {reg._J1}, {reg._J2}, {reg._set_sql('j2', 'user_id, value, d')}")
_ALL = "both_ AS (SELECT user_id, b, e FROM sal UNION ALL SELECT user_id, b, e FROM dept)"
reg.add("temp_seq_union", partial(_plain, "union"), f"WITH {reg._SALS}, {reg._DEPTS}, {_ALL}, {reg._bag_sql('both_', 'user_id')}")
# all rows less those of some users are those of the others
_REST = "rest AS (SELECT d, b, e FROM dept WHERE user_id >= 100)"
reg.add("temp_seq_except", partial(_plain, "except"), f"WITH {reg._DEPTS}, {_REST}, {reg._bag_sql('rest', 'd')}")
reg.add("temp_seq_distinct", partial(_plain, "distinct"), f"WITH {reg._DEPTS}, {reg._set_sql('dept', 'd')}")


def _s1_average(spark, sf_dir, how):
    """The average alone: equal averages of different counts merge."""
    sal, dept, _ = reg.periods(spark, sf_dir)
    out = temporal.sequenced_aggregate(temporal.overlap_join(sal, dept, ["user_id"]), ["d"], "value")
    return temporal.coalesce(out.select("d", (F.col("total").cast("double") / F.col("n")).alias("average"), "b", "e"), ["d", "average"], how)


_ROUND = "a4 AS (SELECT d, total / n AS average, b, e FROM a2)"
for _how, _sql in (("set", reg._set_sql), ("bag", reg._bag_sql)):
    reg.add(f"temp_s1_average_{_how}", partial(_s1_average, how=_how), f"WITH {reg._SALS}, {reg._DEPTS}, {reg._J1}, {reg._A1}, {_ROUND}, {_sql('a4', 'd, average')}")

# --- why-questions over several values --------------------------------------------------------------------------------


def _asked(n: int) -> list[int]:
    return [7 + 5 * i for i in range(n)]


def _why(name, spark, sf_dir, values, optimize="heu"):
    p = datalog.Program(datalog.PROGRAMS[name], {"co": datalog.co_purchases(spark, sf_dir)}, search.Choices(()), optimize)
    return p.why(name, datalog.question(spark, values))


for _n in (5, 20):
    _in = ", ".join(map(str, _asked(_n)))
    reg.add(f"dl_d1_edges_{_n}_values", partial(_why, "d1", values=[(x,) for x in _asked(_n)]), reg._D1.replace("a.x = 7", f"a.x IN ({_in})"))
    reg.add(f"dl_d2_edges_{_n}_values", partial(_why, "d2", values=[(x,) for x in _asked(_n)]), reg._D2.replace("WHERE x = 7", f"WHERE x IN ({_in})"))
    _pairs = ", ".join(f"({x}, 11)" for x in _asked(_n))
    reg.add(f"dl_d3_edges_{_n}_values", partial(_why, "d3", values=[(x, 11) for x in _asked(_n)]), reg._D3.replace("a.x = 7 AND b.y IN (7, 11, 13, 17, 19)", f"(a.x, b.y) IN ({_pairs})"))

# --- late events ------------------------------------------------------------------------------------------------------------


def _late(spark, sf_dir):
    """Events by day and type where the first quarter of the days comes last, after the watermark has passed it."""
    folder = f"{reg._scratch(spark)}/late_{uuid.uuid4().hex}"
    ev = spark.read.parquet(f"{sf_dir}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    early, odd = F.col("ts") < F.lit("2024-01-08").cast("timestamp"), F.col("event_id") % 2 == 1
    # a batch drops what its forerunner's watermark has passed, and the first has none: two batches go before the late one
    for part in (ev.where(~early & odd), ev.where(~early & ~odd), ev.where(early)):
        part.coalesce(1).write.mode("append").parquet(folder)
    stream = spark.readStream.schema(ev.schema).option("maxFilesPerTrigger", 1).parquet(folder).withWatermark("ts", "1 hour")
    return events.run(events.tumbling(stream).select("w_start", "event_type", "n"), "append")


reg.add("stream_late", _late, "SELECT date_trunc('day', ts)::TIMESTAMP AS w_start, event_type, count(*) AS n FROM events WHERE ts >= TIMESTAMP '2024-01-08' AND date_trunc('day', ts) + INTERVAL 1 DAY <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR GROUP BY 1, 2")
