"""Graphs to DataFrames and to SQL text."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from provloom.functions.expr import Bin, Col, conjuncts, to_column
from provloom.plans.ir import Aggregate, Distinct, Join, Limit, Node, Project, Rel, Select, SetOp, WindowOp, parents, topological
from provloom.plans.props import infer_keys

AGGS = {"sum": "sum({})", "count": "count({})", "min": "min({})", "max": "max({})", "avg": "avg({})", "count_distinct": "count(DISTINCT {})", "collect_list": "collect_list({})", "row_number": "row_number()", "first": "first({})"}


def _agg(f: str, e) -> str:
    return AGGS[f].format(e.sql() if e is not None else "")


#: Bytes of a table's files up to which groups by its columns are few enough to send to every task.
FEW = 1 << 21


def few_groups(root: Node, small: dict[int, bool]) -> dict[int, bool]:
    """Aggregates and sets whose rows are bounded by those of a small table, whatever lies below. small: by Rel."""

    def bounded(n: Node, cols: frozenset[str]) -> bool:
        """Whether the combinations of these columns are no more than a small table's rows."""
        if not cols or isinstance(n, Rel):
            return not cols or small[id(n)]
        if isinstance(n, Project):
            of = {a: e for e, a in n.items}
            return all(isinstance(of[c], Col) for c in cols) and bounded(n.child, frozenset(of[c].name for c in cols))
        if isinstance(n, Join):
            return any(cols <= frozenset(x.schema) and bounded(x, cols) for x in ((n.left, n.right) if n.how in ("inner", "left") else (n.left,) if n.how in ("semi", "anti") else ()))
        if isinstance(n, SetOp):
            at = [n.schema.index(c) for c in cols]
            left, right = bounded(n.left, cols), n.kind != "except" and bounded(n.right, frozenset(n.right.schema[i] for i in at))
            return left and right if n.kind == "union" else left or right
        if isinstance(n, Aggregate):
            return cols <= frozenset(n.keys) and bounded(n.child, cols) or bounded(n.child, frozenset(n.keys))
        return cols <= frozenset(n.kids[0].schema) and bounded(n.kids[0], cols)

    out: dict[int, bool] = {}
    for n in topological(root):
        if isinstance(n, (Select, Project)):
            out[id(n)] = out[id(n.kids[0])]
        else:
            out[id(n)] = isinstance(n, Distinct) and bounded(n.child, frozenset(n.schema)) or isinstance(n, Aggregate) and all(f != "collect_list" for f, _, _ in n.aggs) and bounded(n.child, frozenset(n.keys))
    return out


def many_to_many(n: Join, keys: dict[int, set[frozenset]]) -> bool:
    """Whether a row of either side may meet several of the other: its rows can be far more than those of both."""
    pairs = [(c.left.name, c.right.name) for c in conjuncts(n.cond) if isinstance(c, Bin) and c.op in ("=", "IS NOT DISTINCT FROM") and isinstance(c.left, Col) and isinstance(c.right, Col)]
    on = frozenset(x for p in pairs for x in p)
    return n.how == "inner" and bool(pairs) and not any(key <= on & frozenset(x.schema) for x in n.kids for key in keys[id(x)])


def _bytes(df: DataFrame) -> int:
    """Estimated bytes; streams have no end."""
    return 1 << 62 if df.isStreaming else int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))


def to_dataframe(root: Node, spark: SparkSession, tables) -> DataFrame:
    """tables: folder of Parquet files, or a mapping of names to DataFrames. A shared node is lowered once."""
    got: dict[int, DataFrame] = {}
    from provloom.sources.catalog import KEYS

    few, keys = None, None
    load = (lambda n: spark.read.parquet(f"{tables}/{n}.parquet")) if isinstance(tables, str) else tables.__getitem__
    for n in topological(root):
        k = [got[id(x)] for x in n.kids]
        if isinstance(n, Rel):
            df = load(n.name).select(*(F.col(a).alias(b) for a, b in n.attrs))
        elif isinstance(n, Select):
            df = k[0].filter(to_column(n.cond))
        elif isinstance(n, Project):
            df = k[0].select(*(to_column(e).alias(a) for e, a in n.items))
        elif isinstance(n, Join):
            how = {"semi": "left_semi", "anti": "left_anti"}.get(n.how, n.how)
            if n.how == "inner" and n.cond is not None:
                # the other side may be a many-to-many join, whose rows would else be sorted and dealt by the few groups
                few = few_groups(root, {id(x): _bytes(load(x.name)) <= FEW for x in topological(root) if isinstance(x, Rel)}) if few is None else few
                i = next((i for i, x in enumerate(n.kids) if few[id(x)]), None)
                k = [F.broadcast(x) if j == i else x for j, x in enumerate(k)]
                keys = infer_keys(root, KEYS) if keys is None else keys
                if i is None and not any(x.isStreaming for x in k) and many_to_many(n, keys):
                    # few files or few equal values would else hold all pairs in a few tasks, where the smaller side is sent to all
                    i = int(_bytes(k[1]) > _bytes(k[0]))
                    k[i] = k[i].repartition(int(spark.conf.get("spark.sql.shuffle.partitions")))
            df = k[0].crossJoin(k[1]) if n.cond is None else k[0].join(k[1], to_column(n.cond), how)
        elif isinstance(n, SetOp):
            right = k[1].toDF(*n.schema)
            df = {"union": k[0].unionAll, "intersect": k[0].intersectAll, "except": k[0].exceptAll}[n.kind](right)
        elif isinstance(n, Aggregate):
            aggs = [F.expr(_agg(f, e)).alias(a) for f, e, a in n.aggs]
            df = (k[0].groupBy(*n.keys).agg(*aggs) if aggs else k[0].select(*n.keys).distinct()) if n.keys else k[0].agg(*aggs)
        elif isinstance(n, Distinct):
            df = k[0].distinct()
        elif isinstance(n, WindowOp):
            w = Window.partitionBy(*n.keys)
            if n.order:
                w = w.orderBy(*n.order)
                if n.f != "row_number":
                    w = w.rangeBetween(Window.unboundedPreceding, Window.currentRow)
            df = k[0].withColumn(n.name, F.expr(_agg(n.f, n.expr)).over(w))
        else:
            df = k[0].orderBy(*(F.desc(o[1:]) if o[0] == "-" else F.asc(o) for o in n.order)).limit(n.n)
        got[id(n)] = df
    return got[id(root)]


def to_sql(root: Node) -> str:
    """One statement; nodes with several parents become common table expressions."""
    above, name, ctes = parents(root), {}, []

    def body(n: Node) -> str:
        k = [source(x) for x in n.kids]
        if isinstance(n, Rel):
            return f"SELECT {', '.join(a if a == b else f'{a} AS {b}' for a, b in n.attrs)} FROM {n.name}"
        if isinstance(n, Select):
            return f"SELECT * FROM {k[0]} WHERE {n.cond.sql()}"
        if isinstance(n, Project):
            return f"SELECT {', '.join(f'{e.sql()} AS {a}' for e, a in n.items)} FROM {k[0]}"
        if isinstance(n, Join):
            if n.how in ("semi", "anti"):
                return f"SELECT * FROM {k[0]} WHERE {'NOT ' * (n.how == 'anti')}EXISTS (SELECT 1 FROM {k[1]} WHERE {n.cond.sql()})"
            return f"SELECT * FROM {k[0]} CROSS JOIN {k[1]}" if n.cond is None else f"SELECT * FROM {k[0]} {n.how.upper()} JOIN {k[1]} ON {n.cond.sql()}"
        if isinstance(n, SetOp):
            return f"SELECT {', '.join(n.left.schema)} FROM {k[0]} {n.kind.upper()} ALL SELECT {', '.join(n.right.schema)} FROM {k[1]}"
        if isinstance(n, Aggregate):
            items = [*n.keys, *(f"{_agg(f, e)} AS {a}" for f, e, a in n.aggs)]
            return f"SELECT {', '.join(items)} FROM {k[0]}" + (f" GROUP BY {', '.join(n.keys)}" if n.keys else "")
        if isinstance(n, Distinct):
            return f"SELECT DISTINCT * FROM {k[0]}"
        if isinstance(n, WindowOp):
            over = " ".join(x for x in (f"PARTITION BY {', '.join(n.keys)}" if n.keys else "", f"ORDER BY {', '.join(n.order)}" if n.order else "") if x)
            return f"SELECT *, {_agg(n.f, n.expr)} OVER ({over}) AS {n.name} FROM {k[0]}"
        order = ", ".join(f"{o[1:]} DESC" if o[0] == "-" else o for o in n.order)
        return f"SELECT * FROM {k[0]} ORDER BY {order} LIMIT {n.n}"

    def source(n: Node) -> str:
        if id(n) in name:
            return name[id(n)]
        if len(above[id(n)]) > 1:
            text = body(n)
            name[id(n)] = f"shared{len(ctes)}"
            ctes.append(f"{name[id(n)]} AS ({text})")
            return name[id(n)]
        return f"({body(n)}) AS t{len(name) + id(n) % 100000}"

    text = body(root)
    return (f"WITH {', '.join(ctes)} " if ctes else "") + text
