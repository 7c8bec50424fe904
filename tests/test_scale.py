"""Queries whose results hung on the folder's name, on its size or on rows made up: against their SQL and against other plans."""

import json

import duckdb
import pytest
from pyspark.sql import functions as F

from provloom.workloads import registry
from tests.test_queries import SF, rows


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events".split():
        c.sql(f"create view {t} as select * from read_parquet('{SF}/{t}.parquet')")
    return c


@pytest.mark.parametrize("name", ["sagg_1_join", "sagg_2_window", "sagg_10_cost"])
def test_chains_end_in_the_groups_of_their_sql(spark, duck, name):
    """The group size hung on the folder's name."""
    assert rows(registry.QUERIES[name](spark, SF).toPandas()) == rows(duck.sql(registry.ORACLES[name]).df())


@pytest.mark.parametrize("name", [f"sagg_{i}_{k}" for i, ks in ((10, "join join_none window window_none"), (1, "cost join join_none window window_none"), (2, "cost join join_none")) for k in ks.split()])
def test_chains_keep_their_groups_in_any_folder(spark, duck, name, tmp_path_factory):
    """In a folder called sf0.1 chains ended in groups of 4096 parts, while their SQL says 512."""
    folder = tmp_path_factory.mktemp("chains") / "sf0.1"
    folder.mkdir()
    (folder / "part.parquet").symlink_to(f"{SF}/part.parquet")
    assert rows(registry.QUERIES[name](spark, str(folder)).toPandas()) == rows(duck.sql(registry.ORACLES[name]).df())


@pytest.mark.parametrize("name", ["f1", "f2", "f3"])
@pytest.mark.parametrize("factorize", [False, True])
def test_sizes_need_no_documents(spark, name, factorize):
    """A group's documents were collected before they were counted."""
    from provloom.operators import nested

    make = getattr(registry, name)
    got = nested.capture_sizes(spark, SF, make(), factorize)
    assert "collect_list" not in got._jdf.queryExecution().optimizedPlan().toString()
    assert rows(got.toPandas()) == rows(nested.sizes(*nested.capture_nested(spark, SF, make(), factorize)).toPandas())


def test_subgoals_are_bound(spark):
    """A derived goal was worked out for all tuples, whatever was asked."""
    from provloom.operators import datalog

    co = spark.createDataFrame([(x, y) for x in range(30) for y in range(30) if x != y], "x long, y long")
    seen = []

    class Watched(datalog.Program):
        def relation(self, name, bind=None):
            out = super().relation(name, bind)
            seen.extend([out.count()] if name in self.idb else [])
            return out

    edges = Watched(datalog.PROGRAMS["d5"], {"co": co}).why("d5", datalog.question(spark, [(7,)]))
    assert seen == [30] and edges.where("src = 'd5(7)'").count() == 900 - 30
    # constants and repeated variables ask as well
    p = datalog.Program("p(X) :- q(X, X, 3). q(X, Y, Z) :- co(X, W), co(W, Y), co(Y, Z).", {"co": co})
    assert p.relation("p", datalog.question(spark, [(5,)])).collect()[0][0] == 5


def test_document_in_lines(spark):
    """Over 100,000 fragments raised; the lines in order are the document."""
    from provloom.operators import export

    frags = spark.range(100_005).selectExpr("if(id % 2 = 0, 'entity', 'used') as section", "concat('k', id) as id", "to_json(struct(id)) as json")
    text = "".join(r["line"] for r in export.lines(frags).collect())
    assert {s: len(x) for s, x in json.loads(text).items()} == {"entity": 50_003, "used": 50_002}
    few = frags.limit(7).unionAll(spark.range(1).selectExpr("'activity'", "'q'", "'{}'"))
    assert "".join(r["line"] for r in export.lines(few).collect()) == export.document(few).first()[0]
    got = registry.QUERIES["export_document"](spark, SF).collect()
    assert set(json.loads("".join(r["line"] for r in got))) == {"activity", "entity", "used"}


@pytest.mark.parametrize("name", ["stream_dedup", "stream_session", "stream_join_prov", "stream_tumbling_prov"])
def test_streams_are_written_by_executors(spark, duck, name):
    """The driver held all rows of a stream; the last windows came in complete mode alone."""
    df = registry.QUERIES[name](spark, SF)
    assert df.inputFiles() and rows(df.toPandas()) == rows(duck.sql(registry.ORACLES[name]).df())
    assert spark.conf.get("spark.sql.streaming.stateStore.providerClass", "").find("RocksDB") < 0


@pytest.mark.parametrize("name", ["cbo_adaptive", "cbo_bin_order", "cbo_plan_space", "cbo_seq_order", "cbo_seq_order_2", "cbo_sim_steps", "expr_eval_example", "factor_example", "join_example", "measure_relative"])
def test_examples_read_tables(spark, name, tmp_path):
    """They made their data up: on tables with fewer rows they gave the same."""
    for t in ("orders", "lineitem", "part", "supplier"):
        spark.read.parquet(f"{SF}/{t}.parquet").limit(3).write.parquet(f"{tmp_path}/{t}.parquet")
    few, all_ = registry.QUERIES[name](spark, str(tmp_path)), registry.QUERIES[name](spark, SF)
    assert rows(few.toPandas())[1] != rows(all_.toPandas())[1]


def test_difference_is_repeated_once_and_dealt_out(spark):
    """The difference's rows were swept again for the form that they have, and each group's copies lay in one task."""
    from provloom.operators import temporal
    from provloom.workloads import sequenced as w

    plan = lambda df: df._jdf.queryExecution().optimizedPlan().toString()
    assert plan(registry.QUERIES["temp_seq_except"](spark, SF)).count("array_repeat") == 1
    both = {how: w.sequenced.sequenced(spark, w.PLAIN["except"](), w.tables(spark, SF), how, keys=w.KEYS) for how in ("bag", "none")}
    again = temporal.coalesce_bag(both["none"], ["d"])
    assert rows(both["bag"].toPandas()) == rows(again.toPandas())
    runs = spark.createDataFrame([("x", 0, 5, 10_000), ("x", 5, 6, 1)], "k string, b long, e long, __n long").coalesce(1)
    made = temporal._repeat(runs, ["k"], "b", "e")
    assert made.count() == 10_001 and made.select(F.spark_partition_id()).distinct().count() > 1


def test_many_to_many_pairs_are_not_dealt_by_the_group(spark):
    """All pairs of a group were sorted and dealt by its few values to meet its one row, and lay in a few tasks."""
    from provloom.plans.ir import Distinct
    from provloom.plans.lower import few_groups, many_to_many
    from provloom.plans.props import infer_keys
    from provloom.sources.catalog import KEYS

    for name in ("l1_intersect", "fact_f3_flat_normal"):
        df = registry.QUERIES[name](spark, SF)
        plan = df._jdf.queryExecution().optimizedPlan().toString()
        assert "strategy=broadcast" in plan and "Repartition" in plan, plan
    q = registry.f3()
    assert many_to_many(q.child, infer_keys(q, KEYS))
    lines = registry.rel("lineitem").join(registry.rel("orders"), registry.col("l_orderkey").eq(registry.col("o_orderkey")))
    assert not many_to_many(lines, infer_keys(lines, KEYS))
    d = Distinct(registry.rel("customer").select("c_nationkey"))
    leaf = d.child.child
    assert few_groups(d, {id(leaf): True})[id(d)] and not few_groups(d, {id(leaf): False})[id(d)]
