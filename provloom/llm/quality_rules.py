"""Quality rules: per-document measures, and line frequency across the documents of a host.

A line that occurs in more than ``max_share`` of a host's documents (and in at least ``min_docs`` of them) is page
furniture: it is removed from every document of the host but the first that holds it. Documents that lose more than
``depleted`` of their words go. Documents of one host with equal texts count as one, so copies alone make no line
frequent.

Defined cases: null text has no words (base_failed, not kept); rows of null doc_id keep all their lines; a null source is a host of its own; repeated rows give
repeated result rows; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from collections import Counter

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from provloom.llm.common import ASCII_SPACE, beside, join_checked, keyed, spill

SYMBOLS = b"#*$%&|<>"
NORMAL = "trim(regexp_replace(lower(line), '[\\\\s0-9]+', ' '))"
MEASURES = "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long"


def measure(text: str) -> tuple[int, int, int, int, int]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words of one text."""
    raw = text.encode("utf-8", "surrogatepass")
    words = raw.split()
    n = len(words)
    chars = len(text) - sum(text.count(c) for c in ASCII_SPACE)
    symbols = sum(raw.count(c) for c in SYMBOLS)
    lines = [line for line in raw.split(b"\n") if line.strip()]
    grams = list(zip(words, words[1:], words[2:]))
    repeated = 0
    if len(set(grams)) < len(grams):
        counts = Counter(grams)
        marked = bytearray(n)
        for i, g in enumerate(grams):
            if counts[g] > 1:
                marked[i : i + 3] = b"\1\1\1"
        repeated = sum(marked)
    return n, chars, symbols, len(lines) - len(set(lines)), repeated


def measures(docs: DataFrame) -> DataFrame:
    """The base measures of every row, with tkey, a hash of its text."""
    d = keyed(docs).withColumn("tkey", F.xxhash64("text"))
    return beside(d, ["doc_id", "tkey"], ["text"], lambda: lambda texts: [measure(t) for t in texts], MEASURES, small=True)


def _lines(docs: DataFrame) -> DataFrame:
    d = keyed(docs, F.coalesce("source", F.lit("")).alias("host")).withColumn("tkey", F.xxhash64("text"))
    d = d.select("doc_id", "tkey", "host", F.posexplode(F.split("text", "\n")).alias("pos", "line"))
    return d.withColumn("norm", F.expr(NORMAL)).where("norm <> ''").withColumn("lh", F.xxhash64("norm"))


def frequent_lines(docs: DataFrame, max_share: float = 0.01, min_docs: int = 20) -> DataFrame:
    """(host, lh, n, keeper): lines over the limits, and the first document that holds each. Counts cover all rows."""
    lines = _lines(docs)
    per_text = lines.groupBy("host", "lh", "tkey").agg(F.min("doc_id").alias("first"))
    counted = per_text.groupBy("host", "lh").agg(F.count("*").alias("n"), F.min("first").alias("keeper"))
    hosts = (
        docs.select(F.coalesce("source", F.lit("")).alias("host"), F.xxhash64(F.coalesce("text", F.lit(""))).alias("tkey"))
        .groupBy("host", "tkey").count().groupBy("host").agg(F.count("*").alias("docs"))
    )
    return counted.where(F.col("n") >= min_docs).join(hosts, "host").where(F.col("n") > max_share * F.col("docs")).select("host", "lh", "n", "keeper")


def removals(docs: DataFrame, frequent: DataFrame) -> DataFrame:
    """(doc_id, tkey, cut: positions of the removed lines, removed_words). frequent must be materialised."""
    hit = join_checked(_lines(docs).select("doc_id", "tkey", "host", "pos", "lh", "line"), frequent, ["host", "lh"], "inner")
    hit = hit.where("doc_id <> keeper").withColumn("w", F.size(F.expr("filter(split(line, '[ \\\\x09-\\\\x0D]+'), x -> x <> '')")))
    hit = hit.groupBy("doc_id", "tkey", "pos").agg(F.max("w").alias("w"))
    return hit.groupBy("doc_id", "tkey").agg(F.collect_set("pos").alias("cut"), F.sum("w").alias("removed_words"))


def judge(docs: DataFrame, max_share: float = 0.01, min_docs: int = 20, depleted: float = 0.5, min_words: int = 50) -> DataFrame:
    """One row per row of docs: measures, removed_words, cut, base_failed, kept."""
    frequent = spill(frequent_lines(docs, max_share, min_docs))
    cuts = removals(docs, frequent)
    m = measures(docs).join(cuts, ["doc_id", "tkey"], "left").withColumn("removed_words", F.coalesce("removed_words", F.lit(0)))
    m = m.withColumn("base_failed", F.expr(f"n_words < {int(min_words)} or 100 * n_repeat_words > 50 * n_words"))
    return m.withColumn("kept", ~F.col("base_failed") & (F.col("removed_words") <= depleted * F.col("n_words")))


def clean(docs: DataFrame, **limits) -> DataFrame:
    """docs without the rejected documents and without their frequent lines, with the columns of docs."""
    verdicts = judge(docs, **limits).select("doc_id", "tkey", "cut", "kept").dropDuplicates(["doc_id", "tkey"])
    d = docs.withColumn("__tkey", F.xxhash64(F.coalesce("text", F.lit(""))))
    v = verdicts.select(F.col("doc_id").alias("__id"), F.col("tkey").alias("__tk"), F.col("cut").alias("__cut"), "kept").where("kept").drop("kept")
    d = d.join(v, (d["doc_id"].eqNullSafe(v["__id"])) & (d["__tkey"] == v["__tk"]), "inner")
    text = F.expr("case when __cut is null then text else array_join(filter(split(text, '\n'), (x, i) -> not array_contains(__cut, i)), '\n') end")
    d = d.withColumn("text", text)
    if "n_chars" in docs.columns:
        d = d.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))
    return d.select(*docs.columns)
