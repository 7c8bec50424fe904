"""Provenance of transactions: updates reenacted as projections over the version a transaction began with.

Only tuples the transaction affects are returned. Two ways find them: *filter* keeps tuples that meet the condition of any
update or delete in the version at the begin (exact: a tuple's first hit sees its values at the begin), *histjoin* joins
the keys that the transaction wrote to that version. Inserted tuples are added as a union.

*stack* lowers a transaction as a projection per statement; *fold* sends keyed updates through one pass over an array of
changes, so its plan doesn't grow with the number of statements.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from provloom.functions.expr import Bin, Col, Expr, If, Lit, substitute, to_column
from provloom.plans import rules
from provloom.plans.ir import Project, Rel
from provloom.plans.search import Best, Choices, optimize
from provloom.sources.history import VersionStore


#: Seconds that a condition takes on a row, and that a shuffle takes besides its rows.
ROW_S, SHUFFLE_S = 15e-9, 0.12
#: Statements from which keyed updates go through one pass instead of a projection each.
FOLD_FROM = 20


@dataclass(frozen=True)
class Update:
    cond: Expr
    sets: tuple[tuple[str, Expr], ...]


@dataclass(frozen=True)
class Delete:
    cond: Expr


@dataclass(frozen=True)
class Insert:
    """Constant rows, or a query: a function of the begin version that gives a DataFrame."""

    rows: tuple[tuple, ...] = ()
    query: object = None


@dataclass(frozen=True)
class Transaction:
    xid: int
    begin: int
    statements: tuple
    isolation: str = "SERIALIZABLE"

    def __post_init__(self):
        if self.isolation != "SERIALIZABLE":
            raise ValueError("only SERIALIZABLE transactions are reenacted")


def filter_updated(begin: DataFrame, txn: Transaction) -> DataFrame:
    """Rows that some update or delete hits. Conditions ``key = constant`` become one membership test."""
    points: dict[str, list] = {}
    other = []
    for s in txn.statements:
        if isinstance(s, (Update, Delete)):
            c = s.cond
            if isinstance(c, Bin) and c.op == "=" and isinstance(c.left, Col) and isinstance(c.right, Lit):
                points.setdefault(c.left.name, []).append(c.right.value)
            else:
                other.append(to_column(c))
    conds = [F.col(c).isin(v) for c, v in points.items()] + other
    if not conds:
        return begin.limit(0)
    out = conds[0]
    for c in conds[1:]:
        out = out | c
    return begin.where(out)


def hist_join(store: VersionStore, txn: Transaction) -> DataFrame:
    """Rows of the begin version whose key the transaction wrote."""
    return store.as_of(txn.begin).join(store.changed_by(txn.xid).select(*store.key).distinct(), list(store.key), "left_semi")


def _stack(df: DataFrame, attrs: list[str], txn: Transaction, factor: bool, flags: bool, whole: DataFrame) -> DataFrame:
    """whole: the begin version without restriction; what an insert's query reads comes from there, whatever df leaves out."""
    df = df.withColumn("deleted", F.lit(False)).withColumn("touched", F.lit(False))
    for i, s in enumerate(txn.statements, 1):
        if isinstance(s, Update):
            items = {a: If(s.cond & Col("deleted").eq(False), e, Col(a)) for a, e in s.sets}
            if factor:
                items = {a: rules.factored(e) for a, e in items.items()}
            hit = to_column(s.cond & Col("deleted").eq(False))
            df = df.select(*(to_column(items[a]).cast(df.schema[a].dataType).alias(a) if a in items else F.col(a) for a in attrs), *[c for c in df.columns if c not in (*attrs, "touched")], (F.col("touched") | F.coalesce(hit, F.lit(False))).alias("touched"), *([F.coalesce(hit, F.lit(False)).alias(f"upd_{i}")] if flags else []))
        elif isinstance(s, Delete):
            hit = F.coalesce(to_column(s.cond & Col("deleted").eq(False)), F.lit(False))
            df = df.select(*[c for c in df.columns if c not in ("deleted", "touched")], (F.col("deleted") | hit).alias("deleted"), (F.col("touched") | hit).alias("touched"), *([hit.alias(f"upd_{i}")] if flags else []))
        else:
            add = _inserted(df, attrs, s, lambda i=i: _stack(whole, attrs, replace(txn, statements=txn.statements[: i - 1]), factor, False, whole))
            rest = [c for c in df.columns if c not in add.columns]
            add = add.select(*add.columns, *(F.lit(None).cast(df.schema[c].dataType).alias(c) if c.startswith("prov_") else F.lit(c == "touched").alias(c) for c in rest))
            if flags:
                df, add = df.withColumn(f"upd_{i}", F.lit(False)), add.withColumn(f"upd_{i}", F.lit(True))
            df = df.unionByName(add)
    return df


def _inserted(df: DataFrame, attrs, s: Insert, now) -> DataFrame:
    """The rows of an insert; now() is the whole relation as the statements before it have left it."""
    if s.query is not None:
        return s.query(now().where("not deleted").select(*attrs)).select(*attrs)
    return df.sparkSession.createDataFrame([tuple(r) for r in s.rows], df.select(*attrs).schema)


def _fold(df: DataFrame, attrs: list[str], txn: Transaction) -> DataFrame:
    """Keyed additive updates ``a = a + k where key = v``: one join to their list, folded in statement order."""
    rows = []
    for i, s in enumerate(txn.statements, 1):
        (a, e), = s.sets
        rows.append((s.cond.right.value, i, a, float(e.right.value), s.cond.left.name))
    names = {(r[2], r[4]) for r in rows}
    if len(names) != 1:
        raise ValueError("fold needs updates of one column by one key")
    (a, key), = names
    log = df.sparkSession.createDataFrame([(v, i, k) for v, i, _, k, _ in rows], "__v long, i int, k double")
    log = log.groupBy("__v").agg(F.array_sort(F.collect_list(F.struct("i", "k"))).alias("log"))
    # the statement list is the driver's own: broadcasting it is bounded by the transaction
    d = df.join(F.broadcast(log), df[key] == log["__v"], "left").drop("__v")
    folded = F.when(F.col("log").isNull(), F.col(a)).otherwise(F.aggregate("log", F.col(a).cast("double"), lambda acc, x: acc + x["k"])).cast(df.schema[a].dataType)
    return d.withColumn(a, folded).withColumn("deleted", F.lit(False)).withColumn("touched", F.col("log").isNotNull()).drop("log")


def foldable(txn: Transaction) -> bool:
    return all(isinstance(s, Update) and len(s.sets) == 1 and isinstance(s.cond, Bin) and s.cond.op == "=" and isinstance(s.cond.left, Col) and isinstance(s.cond.right, Lit) and isinstance(s.sets[0][1], Bin) and s.sets[0][1].op == "+" and s.sets[0][1].left == Col(s.sets[0][0]) and isinstance(s.sets[0][1].right, Lit) for s in txn.statements) and len({(s.sets[0][0], s.cond.left.name) for s in txn.statements}) <= 1


def search_restriction(txn: Transaction, store: VersionStore) -> Best:
    """Filter or history join, whichever is estimated to take less time on this store."""
    rows, written = store.as_of(txn.begin).count(), store.changed_by(txn.xid).count()
    conds = [s.cond for s in txn.statements if isinstance(s, (Update, Delete))]
    # equality with a constant is looked up in one set, other conditions are evaluated one by one
    tests = sum(not (isinstance(c, Bin) and c.op == "=" and isinstance(c.right, Lit)) for c in conds) + 1

    def seconds(how: str) -> float:
        if how == "filter":
            return rows * tests * ROW_S
        if not written:
            return float("inf")  # the store doesn't hold what the transaction wrote
        return SHUFFLE_S + (2 * rows + written) * 3 * ROW_S

    return optimize(lambda c: ("filter", "histjoin")[c.choose(2, "txn_restrict", ("filter", "histjoin"))], seconds)


def capture_txn(txn: Transaction, store: VersionStore, restrict: str = "choose", lowering: str = "auto", optimize_: str = "heu", relation: str = "hist", choices: Choices | None = None, keep_all: bool = False, flags: bool = False) -> DataFrame:
    """Affected tuples after the transaction, with ``prov_`` columns of their version at the begin.

    A tuple inserted by the transaction has null provenance; ``deleted`` marks tombstones; with flags, ``upd_i``
    tells which statements hit it (stack lowering).
    """
    choices = choices or Choices()
    if restrict == "choose":
        if optimize_ == "cost":
            choices = Choices(search_restriction(txn, store).path)
        restrict = ("filter", "histjoin")[choices.choose(2, "txn_restrict", ("filter", "histjoin"))]
    if lowering == "auto":
        lowering = "fold" if len(txn.statements) > FOLD_FROM and not flags and foldable(txn) else "stack"
    attrs = store.attrs
    begin = whole = store.as_of(txn.begin)
    if not keep_all and restrict != "none":
        begin = filter_updated(begin, txn) if restrict == "filter" else hist_join(store, txn)
    begin = begin.select(*attrs, *(F.col(a).alias(f"prov_{relation}_{a}") for a in attrs))
    out = _fold(begin, attrs, txn) if lowering == "fold" else _stack(begin, attrs, txn, optimize_ != "none", flags, whole.select(*attrs))
    return out if keep_all else out.where("touched").drop("touched")
