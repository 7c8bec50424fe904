"""Provenance of streams: windowed counts whose rows carry the ids of the events they come from."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def _folder(spark: SparkSession) -> str:
    """A new folder of the shared checkpoint folder, or a temporary one where none is named."""
    sc = spark.sparkContext
    base = sc.getCheckpointDir() or sc.getConf().get("spark.checkpoint.dir", None) or tempfile.mkdtemp(prefix="provloom-")
    return f"{base}/stream_{uuid.uuid4().hex}"


def source(spark: SparkSession, sf_dir: str, late_by: str = "1 hour", end: bool = False) -> DataFrame:
    """The events table as a stream of its files, with a watermark. timestamp_ntz has no watermark, so ts gets the session's zone.

    end: a last row without id, type or user follows a year after the last event. The watermark then passes every event,
    and append mode gives the windows that would stay open; the window of the last row itself stays open.
    """
    table = spark.read.parquet(f"{sf_dir}/events.parquet")
    df = spark.readStream.schema(table.schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    if end:
        folder = _folder(spark)
        last = table.agg(F.max("ts").alias("ts")).where("ts is not null").selectExpr("ts + interval 1 year as ts")
        last.select(*(F.col("ts").cast(f.dataType).alias("ts") if f.name == "ts" else F.lit(None).cast(f.dataType).alias(f.name) for f in table.schema)).write.parquet(folder)
        df = df.unionAll(spark.readStream.schema(table.schema).parquet(folder))
    return df.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late_by)


#: State lies in native memory and on disk, not in the heap that the query's own rows need.
_STATE = ("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")


def run(df: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a streaming query over what is there and returns its rows. In append mode executors write them to Parquet, and state
    is kept by RocksDB; other modes have no such sink, and the driver holds the rows."""
    spark, name = df.sparkSession, f"s_{uuid.uuid4().hex}"
    if mode != "append":
        df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start().awaitTermination()
        return spark.table(name)
    folder, before = _folder(spark), spark.conf.get(_STATE[0], None)
    spark.conf.set(*_STATE)
    try:
        q = df.writeStream.format("parquet").option("path", f"{folder}/rows").option("checkpointLocation", f"{folder}/checkpoint").outputMode(mode).trigger(availableNow=True).start()
        q.awaitTermination()
    finally:
        spark.conf.unset(_STATE[0]) if before is None else spark.conf.set(_STATE[0], before)
    return spark.read.schema(df.schema).parquet(f"{folder}/rows")


def _sum():
    return F.sum(F.col("value").cast("decimal(18,2)")).cast("double").alias("total")


def _ids():
    return F.array_join(F.array_sort(F.collect_list("event_id")), ",").alias("prov_events")


def tumbling(events: DataFrame, size: str = "1 day") -> DataFrame:
    """Count, total and event ids per type and day. The ids are the window's provenance; state is bounded by the watermark."""
    g = events.groupBy(F.window("ts", size).alias("w"), "event_type").agg(F.count("*").alias("n"), _sum(), _ids())
    return g.select(F.col("w.start").cast("timestamp_ntz").alias("w_start"), "event_type", "n", "total", "prov_events")


def sliding(events: DataFrame, size: str = "2 days", step: str = "1 day") -> DataFrame:
    g = events.groupBy(F.window("ts", size, step).alias("w")).agg(F.count("*").alias("n"), _sum())
    return g.select(F.col("w.start").cast("timestamp_ntz").alias("w_start"), "n", "total")


def sessions(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    g = events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"), _ids())
    return g.select("user_id", F.col("w.start").cast("timestamp_ntz").alias("s_start"), "n", "prov_events")


def deduplicated(events: DataFrame) -> DataFrame:
    return events.dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id", "event_type")


def with_provenance(spark: SparkSession, query, tables: dict[str, DataFrame]) -> DataFrame:
    """Flat provenance of selections, projections and joins over streams and tables: the same plan, unbounded input."""
    from provloom.operators.flat import rewrite
    from provloom.plans.lower import to_dataframe

    return to_dataframe(rewrite(query), spark, tables)
