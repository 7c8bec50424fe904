"""A versioned table: one row per version of a tuple, valid from v_from up to v_to, written by transaction xid."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

OPEN = (1 << 62) - 1


@dataclass(frozen=True)
class VersionStore:
    """hist: attributes, v_from, v_to, xid, deleted. Tombstones are rows with deleted true; no-op updates are rows, too."""

    hist: DataFrame
    key: tuple[str, ...]

    @property
    def attrs(self) -> list[str]:
        return [c for c in self.hist.columns if c not in ("v_from", "v_to", "xid", "deleted")]

    def as_of(self, version: int) -> DataFrame:
        h = self.hist.where((F.col("v_from") <= version) & (F.lit(version) < F.col("v_to")))
        return h.where("not deleted").select(*self.attrs)

    def changed_by(self, xid: int) -> DataFrame:
        """Rows of the versions that a transaction wrote, tombstones included."""
        return self.hist.where(F.col("xid") == xid)

    def apply(self, txn, versions: DataFrame, begin: int, commit: int) -> VersionStore:
        """The store after a transaction; versions: its rows with flags (``reenact`` with keep_all)."""
        touched = versions.where("touched").select(*self.attrs, F.col("deleted"))
        keys = touched.select(*self.key).distinct()
        live = (F.col("v_to") == OPEN) & (F.col("v_from") <= begin)
        old = self.hist.where(live).join(keys, list(self.key), "left_semi").withColumn("v_to", F.lit(commit).cast("long"))
        rest = self.hist.where(live).join(keys, list(self.key), "left_anti").unionByName(self.hist.where(~live))
        new = touched.withColumn("v_from", F.lit(commit).cast("long")).withColumn("v_to", F.lit(OPEN).cast("long")).withColumn("xid", F.lit(txn.xid).cast("long"))
        return VersionStore(rest.unionByName(old).unionByName(new), self.key)


def initial(df: DataFrame, key: tuple[str, ...]) -> VersionStore:
    h = df.withColumn("v_from", F.lit(0).cast("long")).withColumn("v_to", F.lit(OPEN).cast("long"))
    return VersionStore(h.withColumn("xid", F.lit(0).cast("long")).withColumn("deleted", F.lit(False)), key)


def with_history(df: DataFrame, key: tuple[str, ...], column: str, share: float) -> VersionStore:
    """A store whose history has share times as many closed versions as df has rows: earlier values of column.

    Row by row by the key's hash, so a share of 10 gives each row ten closed versions and 0.1 gives a tenth of rows one.
    """
    whole, part = int(share), share - int(share)
    n = F.lit(whole) + (F.pmod(F.xxhash64(*key), F.lit(1000)) < int(1000 * part)).cast("int")
    h = df.withColumn("__v", F.explode(F.sequence(F.lit(0), n)))
    h = h.withColumn("v_from", F.col("__v").cast("long")).withColumn("v_to", F.when(F.col("__v") == n, F.lit(OPEN)).otherwise(F.col("__v") + 1).cast("long"))
    h = h.withColumn(column, F.col(column) - (n - F.col("__v"))).withColumn("xid", -F.col("__v").cast("long")).withColumn("deleted", F.lit(False))
    return VersionStore(h.drop("__v"), key)
