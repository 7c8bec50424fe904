"""Sequenced queries: snapshots of the result are the plain query over snapshots."""

import pytest

from provloom.functions.expr import Lit, col
from provloom.operators import sequenced, temporal
from provloom.plans.cost import ModelCost, Profile
from provloom.plans.ir import Distinct, Limit, SetOp, table
from provloom.plans.lower import to_dataframe

#: Boats at berths and the tides of berths, dealt by a rule; some periods are empty, some values null.
BOATS = [(f"boat{i % 5}", i % 3, None if i % 6 == 4 else 3 * i % 8, (i * 7) % 11, (i * 7) % 11 + (i * 5) % 6) for i in range(16)]
TIDES = [(i % 3, f"tide{i % 2}", (i * 4) % 9, (i * 4) % 9 + 1 + i % 4) for i in range(8)]


def boat():
    return table("boat", ("name", "berth", "crew"))


def tide():
    return table("tide", ("at", "kind"))


def here():
    return boat().join(tide(), col("berth").eq(col("at")))


QUERIES = {
    "select": lambda: boat().where(col("crew") > 2).select("name"),
    "join": lambda: here().select("name", "kind"),
    "group": lambda: here().group(("kind",), ("count", col("crew"), "n"), ("sum", col("crew"), "s"), ("avg", col("crew"), "m")),
    "rows": lambda: boat().group(("berth",), ("count", Lit(1), "n")),
    "max": lambda: boat().group(("berth",), ("max", col("crew"), "top")),
    "distinct": lambda: Distinct(boat().select("berth")),
    "union": lambda: SetOp("union", boat().select("berth"), tide().select("at")),
    "except": lambda: SetOp("except", boat().select("berth"), tide().select("at")),
    "intersect": lambda: SetOp("intersect", boat().select("berth"), tide().select("at")),
}


@pytest.fixture(scope="module")
def periods(spark):
    return {"boat": spark.createDataFrame(BOATS, "name string, berth int, crew int, b long, e long"), "tide": spark.createDataFrame(TIDES, "at int, kind string, b long, e long")}


@pytest.mark.parametrize("name", QUERIES)
def test_snapshots(spark, periods, name):
    q = QUERIES[name]()
    got = sequenced.sequenced(spark, q, periods)
    rows = got.select(*q.schema, "b", "e").collect()
    assert all(r["b"] < r["e"] for r in rows)
    for t in (0, 4, 5, 9, 20):
        now = {k: temporal.snapshot(v, t) for k, v in periods.items()}
        want = sorted(map(str, (tuple(r) for r in to_dataframe(q, spark, now).collect())))
        assert sorted(str(tuple(r)[:-2]) for r in rows if r["b"] <= t < r["e"]) == want


def test_no_rows(spark, periods):
    none = {k: v.limit(0) for k, v in periods.items()}
    for name in ("group", "union", "except", "distinct"):
        assert sequenced.sequenced(spark, QUERIES[name](), none, "bag").count() == 0


def test_form_follows_keys_and_cost():
    model = ModelCost({"boat": Profile(1e6, {"name": 1e5}, {}), "tide": Profile(1e3, {}, {})})
    q = boat().select("name", "berth")
    assert [x[2] for x in sequenced.choose_form(q, model, {"boat": [("name",)]}).trace] == [("coalesce=set",), ("coalesce=bag",)]
    assert sequenced.choose_form(q, model, {"boat": [("name",)]}).plan == "set"
    # equal rows may hold at once: the bag form alone is right, whatever it costs
    assert sequenced.choose_form(q, model, {}).plan == "bag"
    assert sequenced.choose_form(boat().select("berth"), model, {"boat": [("name",)]}).plan == "bag"


@pytest.mark.parametrize("q", [Limit(boat(), ("name",), 3), boat().join(tide(), col("berth").eq(col("at")), "left"), boat().join(tide(), col("berth") < col("at"))])
def test_no_sequenced_form(periods, q):
    with pytest.raises(ValueError):
        sequenced.compile_periods(q, periods)
