"""N-gram Jaccard join by a blocked sparse matrix product of documents by n-grams.

Rows of the matrix are distinct n-gram sets (copies share a row). Grams are put in one order for all: rare before
frequent, by the counts of a sketch of fixed size summed over all documents. Two sets with Jaccard j or more must share
``m`` grams among their first ``n - ceil(j * n) + m`` (their head; ``m`` grows with the size, ``least_shared``), so only columns
of the heads are multiplied first:

* columns with few rows: each pair of rows in size range that shares ``m`` of them is a candidate, and its full product is
  computed; a pair whose ``m`` grams lie in part in columns with many rows is in a family;
* columns with many rows (families of near copies): the rows reached through such columns form a family. All rows of a
  family are compared with its least row first; rows that match it are connected, so only pairs with a row that doesn't
  are left. These are cut into blocks of one band of sizes, and each pair of blocks whose sizes can match is one small
  product, accumulated over slices of its columns. Pairs whose overlap so far and the grams still to come can't reach the
  bound are dropped after each slice. A block pair returns a spanning set of links, never all pairs.

Both ways are exact, so no link is lost. Components of the links give the class of each document.

Defined cases: null or empty texts have the empty set and no links; fewer than ``n`` words make one shingle of all; equal
sets link always; rows of one doc_id are rows of their own, linked by their own texts; null doc_ids take part, are never the
smallest, and a class of nothing else has a null component_id; an empty table gives an empty result.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from provloom.llm.common import Scratch, arrow_batch, beside, components, join_checked, keyed, parts, space_words, spill
from provloom.llm.kneser_ney import pack, unpack
from provloom.llm.licenses import rolling, word_hashes

#: Counters of the frequency sketch (4 bytes each).
SKETCH = 1 << 21
#: Shingles of a set for one more gram that its head must share: a rare passage alone makes no candidate then.
PER_SHARED = 50
#: Rows of a head column up to which its pairs are formed one by one.
FEW = 48
#: Rows of a block of a family, columns of a slice of its product.
BLOCK, SLICE = 400, 4096


def shingles(text: str, n: int, cache: dict) -> np.ndarray:
    """Sorted distinct 64-bit shingle hashes."""
    words = space_words(text)
    if not words:
        return np.zeros(0, np.uint64)
    return np.unique(rolling(word_hashes(words, cache), min(n, len(words))))


def enough(inter: int, a: int, b: int, percent: int) -> bool:
    return 100 * inter >= percent * (a + b - inter)


def least_shared(size: int, percent: int) -> int:
    """Grams that a set of this size shares, within the heads, with each set no smaller that it links to."""
    return min(-(-percent * size // 100), 2 + size // PER_SHARED)


def _cells(grams: np.ndarray) -> np.ndarray:
    return ((grams * np.uint64(0xD6E8FEB86659FD93)) >> np.uint64(64 - SKETCH.bit_length() + 1)).astype(np.int64)


def sketch(docs: DataFrame, n: int) -> np.ndarray:
    """Document frequencies of all shingles, folded into SKETCH counters: its size doesn't depend on the data."""

    def run(batches):
        total, cache = np.zeros(SKETCH, np.uint32), {}
        for b in parts(batches):
            got = [shingles(t, n, cache) for t in b.column("text").to_pylist()]
            if got:
                total += np.bincount(_cells(np.concatenate(got)), minlength=SKETCH).astype(np.uint32)
        at = np.flatnonzero(total)
        for part in range(0, SKETCH, 1 << 16):  # slices, so that equal slices of all tasks are summed together
            lo, hi = np.searchsorted(at, [part, part + (1 << 16)])
            if hi > lo:
                yield arrow_batch([(part, pack(total[part : part + (1 << 16)].astype("<u4")))], "part int, cells binary")

    def add(key, batch):
        total = np.zeros(1 << 16, np.uint64)
        for x in batch["cells"]:
            total += unpack(x, "<u4")
        return pd.DataFrame({"part": [key[0]], "cells": [np.minimum(total, 0xFFFFFFFF).astype("<u4").tobytes()]})

    sums = docs.select("text").mapInArrow(run, "part int, cells binary")
    out = np.zeros(SKETCH, np.uint32)
    for r in sums.groupBy("part").applyInPandas(add, "part int, cells binary").toLocalIterator():
        out[r["part"] : r["part"] + (1 << 16)] = np.frombuffer(r["cells"], "<u4")
    return out


def _heads(docs: DataFrame, n: int, percent: int, weights) -> DataFrame:
    """(doc_id, tkey, n_shingles, sig, head): sig names the set, head its first grams in the common order."""

    def setup():
        cache, w = {}, weights.value

        def one(text):
            s = shingles(text, n, cache)
            size = len(s)
            if not size:
                return 0, None, []
            k = size - -(-percent * size // 100) + least_shared(size, percent)
            # equal weights rank by hash; the sketch is coarse, so close counts count as equal
            rank = np.lexsort((s, np.log2(w[_cells(s)].astype(np.float64)).round(1)))[:k]
            return size, signature(s), s[rank].view(np.int64).tolist()

        return lambda texts: [one(t) for t in texts]

    return beside(docs, ["doc_id", "tkey"], ["text"], setup, "n_shingles long, sig long, head array<long>", small=True)


def signature(s: np.ndarray) -> int:
    return xxhash.xxh3_64_intdigest(s.tobytes()) - (1 << 63)


def _row(s: np.ndarray) -> bytes:
    """A row of the matrix: 48 bits of each shingle's hash, as differences of the sorted hashes."""
    return pack(np.diff(np.unique(s >> np.uint64(16)), prepend=np.uint64(0)))


def _grams(row: bytes) -> np.ndarray:
    return np.cumsum(unpack(row, "<u8"), dtype=np.uint64)


def _agree(x: np.ndarray, y: np.ndarray, percent: int) -> bool:
    return enough(len(np.intersect1d(x, y, assume_unique=True)), len(x), len(y), percent)


def _product(a: list[np.ndarray], b: list[np.ndarray] | None, percent: int, slice_: int = SLICE) -> list[tuple[int, int]]:
    """Row pairs (i of a, j of b) over the bound; b None: pairs i < j within a. Accumulates over column slices."""
    other = a if b is None else b
    cols, counts = np.unique(np.concatenate([*a, *([] if b is None else b)]), return_counts=True)
    cols = cols[counts > 1]
    sa, sb = np.array([len(x) for x in a]), np.array([len(x) for x in other])
    need = np.ceil(percent * (sa[:, None] + sb[None, :]) / (100 + percent) - 1e-9)
    alive = np.minimum(sa[:, None], sb[None, :]) >= need
    if b is None:
        alive &= np.arange(len(a))[:, None] < np.arange(len(a))[None, :]
    at = [np.searchsorted(cols, x[np.isin(x, cols, assume_unique=True)]) for x in a]
    bt = at if b is None else [np.searchsorted(cols, x[np.isin(x, cols, assume_unique=True)]) for x in b]
    overlap = np.zeros(alive.shape, np.float32)
    for lo in range(0, len(cols), slice_):
        hi = min(lo + slice_, len(cols))

        def dense(rows):
            m = np.zeros((len(rows), hi - lo), np.float32)
            for i, x in enumerate(rows):
                m[i, x[np.searchsorted(x, lo) : np.searchsorted(x, hi)] - lo] = 1
            return m

        overlap += dense(at) @ dense(bt).T
        left = np.minimum(*np.broadcast_arrays(np.array([len(x) - np.searchsorted(x, hi) for x in at])[:, None], np.array([len(x) - np.searchsorted(x, hi) for x in bt])[None, :]))
        alive &= overlap + left >= need
        if not alive.any():
            return []
    i, j = np.nonzero(alive & (overlap >= need))
    return [(x, y) for x, y in zip(i.tolist(), j.tolist()) if enough(int(overlap[x, y]), int(sa[x]), int(sb[y]), percent)]


def _span(pairs: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """The pairs that join something new: a spanning forest."""
    up: dict[int, int] = {}

    def root(x):
        while up.setdefault(x, x) != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    out = []
    for x, y in pairs:
        a, b = root(x), root(y)
        if a != b:
            up[a] = b
            out.append((x, y))
    return out


def links(docs: DataFrame, heads: DataFrame, n: int, percent: int) -> DataFrame:
    """(a, b): links between different sets by sig, enough of them to hold the components. Both tables have tkey."""
    with Scratch(docs.sparkSession) as tmp:
        sets = heads.where("sig is not null")
        entries = sets.select("sig", F.col("n_shingles").cast("int").alias("size"), F.explode("head").alias("gram"))
        shared = entries.groupBy("gram").agg(F.min("sig").alias("lo"), F.max("sig").alias("hi")).where("lo < hi").select("gram", "lo")
        members = tmp(entries.join(shared, "gram").groupBy("gram", "sig").agg(F.min("size").alias("size"), F.min("lo").alias("lo")))
        width = members.groupBy("gram").agg(F.count("*").alias("rows"))
        # few rows: pairs in size range that share enough
        few = members.join(width.where(F.col("rows") <= FEW), "gram").select("gram", "sig", "size")
        x, y = few.select("gram", F.col("sig").alias("a"), F.col("size").alias("sa")), few.select("gram", F.col("sig").alias("b"), F.col("size").alias("sb"))
        pairs = x.join(y, "gram").where(f"a < b and 100 * least(sa, sb) >= {percent} * greatest(sa, sb)")
        pairs = pairs.groupBy("a", "b").agg(F.count("*").alias("n"), F.min(F.least("sa", "sb")).alias("size"))
        pairs = tmp(pairs.where(f"n >= least(({percent} * size + 99) div 100, 2 + size div {PER_SHARED})").select("a", "b"))
        # many rows: families
        many = tmp(members.join(width.where(F.col("rows") > FEW), "gram").groupBy("sig", "lo").agg(F.min("size").alias("size")))
        family = components(many.select(F.col("sig").alias("a"), F.col("lo").alias("b"))).select(F.col("node").alias("sig"), F.col("component").alias("family"))
        family = tmp(many.groupBy("sig").agg(F.min("size").alias("size")).join(family, "sig"))
        wanted = pairs.select(F.explode(F.array("a", "b")).alias("sig")).union(family.select("sig")).distinct()
        matrix = tmp(_matrix(docs, sets, wanted, n, tmp))

        one = _verified(pairs, matrix, percent, tmp)

        # a family's least row against all its rows
        pivots = tmp(family.where("sig = family").select("family").join(matrix.withColumnRenamed("sig", "family"), "family").withColumnRenamed("grams", "first"))
        star = join_checked(family.join(matrix, "sig"), pivots, ["family"], "inner")
        star = beside(star, ["family", "sig", "size"], ["grams", "first"], lambda: lambda a, b: [(_agree(_grams(x), _grams(y), percent),) for x, y in zip(a, b)], "met boolean")
        star = tmp(star)
        return spill(one.unionByName(star.where("met and sig <> family").select(F.col("sig").alias("a"), F.col("family").alias("b"))).unionByName(_products(star, matrix, percent, tmp)))


def _verified(pairs: DataFrame, matrix: DataFrame, percent: int, tmp: Scratch) -> DataFrame:
    """The pairs over the bound. Pairs that hang together in groups of at most ``BLOCK`` rows are computed side by side, so
    each row travels once; larger groups are never gathered, their pairs are computed one by one."""
    group = tmp(components(pairs).withColumnsRenamed({"node": "sig", "component": "at"}))
    small = tmp(group.groupBy("at").agg(F.count("*").alias("rows")).where(F.col("rows") <= BLOCK).select("at"))
    rows = group.join(small, "at")
    asked = tmp(pairs.join(rows.withColumnRenamed("sig", "a"), "a", "left"))

    def together(key, left, right):
        grams = {k: _grams(x) for k, x in zip(right["sig"].tolist(), right["grams"])}
        keep = [_agree(grams[a], grams[b], percent) for a, b in zip(left["a"].tolist(), left["b"].tolist())]
        return left.loc[np.array(keep, bool), ["a", "b"]]

    near = asked.where("at is not null").groupBy("at").cogroup(rows.join(matrix, "sig").groupBy("at")).applyInPandas(together, "a long, b long")
    far = asked.where("at is null").select("a", "b")
    far = far.join(matrix.withColumnsRenamed({"sig": "a", "grams": "ga"}), "a").join(matrix.withColumnsRenamed({"sig": "b", "grams": "gb"}), "b")
    far = beside(far, ["a", "b"], ["ga", "gb"], lambda: lambda x, y: [(_agree(_grams(i), _grams(j), percent),) for i, j in zip(x, y)], "met boolean")
    return near.unionByName(far.where("met").select("a", "b"))


def _placed(docs: DataFrame) -> DataFrame:
    """docs with columns that are never null and name a row by its doc_id and text."""
    return docs.withColumns({"__none": F.col("doc_id").isNull(), "__id": F.coalesce("doc_id", F.lit(0)), "__key": F.xxhash64(F.coalesce("text", F.lit("")))})


PLACE = ["__none", "__id", "__key"]


def _matrix(docs: DataFrame, sets: DataFrame, wanted: DataFrame, n: int, tmp: Scratch) -> DataFrame:
    """(sig, grams): the full rows of the wanted sets, from one text of each, read again from the documents."""
    holders = sets.groupBy("sig").agg(F.min(F.struct("doc_id", "tkey")).alias("at")).join(wanted, "sig")
    holders = holders.select("sig", F.col("at.doc_id").isNull().alias("__none"), F.coalesce("at.doc_id", F.lit(0)).alias("__id"), F.col("at.tkey").alias("__key"))
    # one row of each set was named; rows that repeat it meet after the join
    rows = join_checked(_placed(docs).select(*PLACE, "text"), tmp(holders), PLACE, "inner").dropDuplicates([*PLACE, "sig"])

    def setup():
        cache: dict = {}
        return lambda texts: [(_row(shingles(t, n, cache)),) for t in texts]

    return beside(rows, ["sig"], ["text"], setup, "grams binary", small=True)


def _products(star: DataFrame, matrix: DataFrame, percent: int, tmp: Scratch) -> DataFrame:
    """Links of the rows that don't match their family's least row, with all rows of the family whose size can match."""
    # two sizes that can match are at most one band apart
    band = F.floor(F.log(F.col("size")) / (math.log(100 / percent) * 1.0001 if percent < 100 else 1e-9)).cast("int")
    left = star.where("not met").select("family").distinct()
    rows = star.join(left, "family").select("family", "sig", "met", band.alias("band"))
    counts = rows.groupBy("family", "met", "band").agg(F.ceil(F.count("*") / BLOCK).cast("int").alias("blocks"))
    rows = rows.join(counts, ["family", "met", "band"]).withColumn("block", F.pmod(F.xxhash64("sig"), F.col("blocks")).cast("int"))
    blocks = tmp(counts.select("family", "met", "band", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("block")))
    name = F.struct("met", "band", "block")
    x, y = blocks.select("family", name.alias("i")), blocks.select("family", name.alias("j"))
    pairs = x.join(y, "family").where("i <= j and not (i.met and j.met) and abs(i.band - j.band) <= 1")
    sides = pairs.select("family", "i", "j", F.explode(F.array_distinct(F.array("i", "j"))).alias("own"))
    tasks = rows.withColumn("own", name).select("family", "own", "sig").join(sides, ["family", "own"]).join(matrix, "sig")
    tasks = tasks.select("family", F.xxhash64("i", "j").alias("task"), (F.col("own") == F.col("i")).alias("first"), (F.col("i") == F.col("j")).alias("same"), "sig", "grams")

    def multiply(key, p):
        def side(q):
            return [_grams(x) for x in q["grams"]], q["sig"].tolist()

        a, of_a = side(p[p["first"]])
        if p["same"].iloc[0]:
            found = [(of_a[x], of_a[y]) for x, y in _product(a, None, percent)]
        else:
            b, of_b = side(p[~p["first"]])
            found = [(of_a[x], of_b[y]) for x, y in _product(a, b, percent)] if a and b else []
        return pd.DataFrame(_span(found), columns=["a", "b"]).astype("int64")

    return tasks.groupBy("family", "task").applyInPandas(multiply, "a long, b long")


def _classes(docs: DataFrame, n: int, percent: int) -> tuple[DataFrame, DataFrame]:
    """heads of all rows, and (sig, component_id, tkey): a class's smallest doc_id and the text of its first row."""
    d = keyed(docs).withColumn("tkey", F.xxhash64("text"))
    weights = docs.sparkSession.sparkContext.broadcast(sketch(d, n))
    heads = spill(_heads(d, n, percent, weights))
    weights.unpersist()
    comp = components(links(d, heads, n, percent))
    heads = heads.drop("head")
    first = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "tkey"))
    least = heads.where("sig is not null").groupBy("sig").agg(first.alias("first"))
    least = least.join(comp, least["sig"] == comp["node"], "left").select("sig", "first", F.coalesce("component", "sig").alias("class"))
    least = spill(least)
    best = least.groupBy("class").agg(F.min("first").alias("first"))
    return heads, least.select("sig", "class").join(best, "class").select("sig", F.col("first.doc_id").alias("component_id"), F.col("first.tkey").alias("first_tkey"))


def join(docs: DataFrame, n: int = 5, percent: int = 80) -> DataFrame:
    """Per row of docs: doc_id, n_shingles, component_id (smallest doc_id reachable by links)."""
    heads, classes = _classes(docs, n, percent)
    found = heads.join(classes, "sig", "left")
    own = F.when(F.col("sig").isNull(), F.col("doc_id")).otherwise(F.col("component_id"))
    return found.select("doc_id", "n_shingles", own.alias("component_id"))


def clean(docs: DataFrame, n: int = 5, percent: int = 80) -> DataFrame:
    """docs with the first row of each class (smallest doc_id, then text hash), with the columns of docs.

    Rows without words are in no class and stay; of rows equal in doc_id and text one stays.
    """
    heads, classes = _classes(docs, n, percent)
    rows = heads.where("sig is not null").join(classes, "sig").select("doc_id", "tkey", "component_id", "first_tkey")
    rows = rows.groupBy("doc_id", "tkey").agg(F.count("*").alias("n"), (F.min("component_id").eqNullSafe(F.col("doc_id")) & (F.min("first_tkey") == F.col("tkey"))).alias("stays"))
    some = spill(_placed(rows.where("not stays or n > 1").withColumn("text", F.lit(""))).withColumn("__key", F.col("tkey")).select(*PLACE, "stays"))
    d = _placed(docs)
    left = join_checked(d, some.select(PLACE), PLACE, "left_anti")
    again = some.where("stays").select(PLACE)
    if not again.isEmpty():
        left = left.unionByName(join_checked(d, again, PLACE, "left_semi").dropDuplicates(PLACE))
    return left.select(*docs.columns)
