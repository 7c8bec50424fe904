"""Shared pieces of the training-data operators: text words, spilled tables, checked broadcasts, components."""

from __future__ import annotations

import gc
import tempfile
import uuid
from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

ASCII_SPACE = " \t\n\x0b\x0c\r"
#: Lower-cases A-Z and turns every other ASCII byte outside 0-9a-z into a space; bytes over 0x7F stay.
FOLD_WORDS = bytes(
    b + 32 if 65 <= b <= 90 else b if b >= 128 or 48 <= b <= 57 or 97 <= b <= 122 else 32 for b in range(256)
)
FOLD_CASE = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))


def alnum_words(text: str | None) -> list[bytes]:
    """Lower-cased words of ``[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+`` as UTF-8 bytes."""
    return (text or "").encode("utf-8", "surrogatepass").translate(FOLD_WORDS).split()


def space_words(text: str | None) -> list[bytes]:
    """Words of ``[^\\x20\\x09-\\x0D]+`` as UTF-8 bytes, A-Z lower-cased (bytes.split cuts at just these six)."""
    return (text or "").encode("utf-8", "surrogatepass").translate(FOLD_CASE).split()


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir where it is set, else a temporary one of this machine."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        named = sc.getConf().get("spark.checkpoint.dir", None)
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="provloom-"))
    return sc.getCheckpointDir()


def _write(df: DataFrame, codec: str) -> tuple[DataFrame, str]:
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/spill-{uuid.uuid4().hex}"
    df.write.option("compression", codec).parquet(path)
    return spark.read.schema(df.schema).parquet(path), path


def spill(df: DataFrame, codec: str = "zstd") -> DataFrame:
    """Writes df to the shared folder and reads it back: lineage ends here and a lost executor costs one task."""
    return _write(df, codec)[0]


class Scratch:
    """Spilled tables that only the steps inside a with block read: they go at its end, the shuffles behind them as the next
    one is written (while a call runs its caller still holds the plan, so a step's own shuffles can't go inside it)."""

    def __init__(self, spark: SparkSession):
        self.spark, self.paths = spark, []

    def __call__(self, df: DataFrame, codec: str = "zstd") -> DataFrame:
        free(self.spark)
        table, path = _write(df, codec)
        self.paths.append(path)
        return table

    def __enter__(self) -> Scratch:
        return self

    def __exit__(self, *_) -> None:
        for path in self.paths:
            at = self.spark._jvm.org.apache.hadoop.fs.Path(path)
            at.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(at, True)
        free(self.spark)


def free(spark: SparkSession) -> None:
    """Lets Spark delete the shuffle files of finished steps now: it does so when the driver's heap is collected."""
    gc.collect()
    spark._jvm.System.gc()


# Arrow's names of the column types in use.
_ARROW = {
    "long": pa.int64(), "int": pa.int32(), "string": pa.string(), "binary": pa.binary(), "boolean": pa.bool_(), "double": pa.float64(),
    "array<long>": pa.list_(pa.int64()), "array<array<long>>": pa.list_(pa.list_(pa.int64())),
}


def arrow_batch(rows: list[tuple], ddl: str) -> pa.RecordBatch:
    """Rows as one Arrow batch of the columns in ddl; nulls stay nulls, whole numbers stay whole."""
    fields = [x.split() for x in ddl.split(", ")]
    columns = list(zip(*rows)) if rows else [()] * len(fields)
    return pa.RecordBatch.from_arrays([pa.array(c, _ARROW[t]) for c, (_, t) in zip(columns, fields)], [n for n, _ in fields])


#: Rows of a batch that are turned into Python objects at once where memory counts.
ROWS_AT_ONCE = 1000


def parts(batches, most: int = ROWS_AT_ONCE):
    """The rows of Arrow batches in parts: as Python objects they take several times what they take in a batch."""
    return (b.slice(at, most) for b in batches for at in range(0, b.num_rows, most))


def beside(df: DataFrame, keep: list[str], use: list[str], setup: Callable, ddl: str, small: bool = False) -> DataFrame:
    """The columns keep as they are (never through pandas, so null ids lose no digit) beside those of ddl.

    setup() runs once a task and returns a function from the lists of the columns use to a row for each row; with small it
    gets ``ROWS_AT_ONCE`` rows of a batch at most.
    """

    def run(batches):
        fn = setup()
        for b in parts(batches) if small else batches:
            new = arrow_batch(fn(*(b.column(c).to_pylist() for c in use)), ddl)
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in keep), *new.columns], [*keep, *new.schema.names])

    kept = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in df.select(*keep).schema)
    return df.select(*dict.fromkeys([*keep, *use])).mapInArrow(run, f"{kept}, {ddl}")


#: Bytes a side may have to be broadcast; wider sides are joined by shuffling.
BROADCAST_BYTES = 24_000_000


def width(df: DataFrame) -> F.Column:
    """Bytes of a row, about."""
    total = F.lit(0)
    for f in df.schema:
        kind = f.dataType.simpleString()
        each = F.octet_length(f.name) + 24 if kind in ("string", "binary") else F.size(f.name) * 8 + 24 if kind.startswith("array") else F.lit(8)
        total = total + F.coalesce(each, F.lit(8))
    return total


def join_checked(left: DataFrame, right: DataFrame, on: list[str], how: str, most: int = BROADCAST_BYTES) -> DataFrame:
    """Joins to a materialised right side; broadcasts it only if a sum over its rows has shown that it is small."""
    small = right.agg(F.coalesce(F.sum(width(right)), F.lit(0))).first()[0] <= most
    return left.join(F.broadcast(right) if small else right.hint("merge"), on, how)


def components(edges: DataFrame, a: str = "a", b: str = "b", rounds: int = 60) -> DataFrame:
    """Connected components by alternating large-star and small-star steps.

    Returns (node, component): component is the smallest node reachable. Nodes without a partner don't appear.
    Each step is two joins on aggregated minima, so a hub is split by AQE and never gathered in one task.
    """
    e = spill(
        edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where("u <> v").distinct()
    )
    seen = None
    for _ in range(0 if e.isEmpty() else rounds):
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = large.where("u <> v").distinct()
        down = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(down, "u")
        small = small.select("u", F.col("m").alias("v")).unionByName(
            small.select(F.greatest("v", "m").alias("u"), F.least("v", "m").alias("v"))
        )
        e = spill(small.where("u <> v").distinct())
        now = e.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if now == seen:
            break
        seen = now
    else:
        if not e.isEmpty():
            raise RuntimeError(f"components did not settle in {rounds} rounds")
    star = e.groupBy("u").agg(F.min("v").alias("component")).select(F.col("u").alias("node"), "component")
    return star.unionByName(star.select(F.col("component").alias("node"), "component").distinct())


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def keyed(docs: DataFrame, *more: str) -> DataFrame:
    """doc_id, text (null: empty) and the columns named, under these names whatever else docs holds."""
    return docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"), *more)
