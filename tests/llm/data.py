"""Fixtures of the operator tests: given documents, and rows made to be awkward."""

import random

DOCS = "/root/testdata/sf0.001/documents.parquet"
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, tkey string, host string"


def awkward(n_near: int = 40) -> list[tuple]:
    """Nulls, empty and long texts, ties, repeated rows, families of copies and near copies, shared passages."""
    r = random.Random(5)
    vocab = [f"{a}{b}" for a in "the of and in to on er an st ti".split() for b in ["", "ing", "é", "x1"]]
    prose = lambda n: " ".join(r.choice(vocab) for _ in range(n))
    base, passage = prose(120), prose(25)
    texts = [None, "", " \n\t ", "One", "one two", "ONE two", "a\x0bb\x0cc\x1cd\x85e\xa0f", "ÀÉ ß İ σΣ", "日本語 テスト 😀"]
    for i in range(n_near):
        w = base.split()
        for _ in range(i % 4):
            w[r.randrange(len(w))] = f"edit{r.randrange(99)}"
        texts.append(" ".join(w[:60]) + "\n" + " ".join(w[60:]))
    texts += [base] * 6 + [base.upper()] * 2
    texts += [prose(30) + "\n" + passage + "\n" + prose(30) for _ in range(12)]
    texts += ["spam " * 5000, "x" * 20000, "x" * 49, "x" * 50, "aé" * 60, "line of five words here\n" * 30]
    rows = [(i, t, "en", None if i % 7 == 0 else f"src{i % 2}", len(t or ""), "clash", "clash") for i, t in enumerate(texts)]
    return rows + [rows[10], rows[10]]


def frame(spark, rows=None):
    return spark.createDataFrame(awkward() if rows is None else rows, SCHEMA).repartition(5)


def given(spark):
    return spark.read.parquet(DOCS)


def plain(df):
    """(doc_id, text) rows on the driver."""
    return [(r["doc_id"], r["text"] or "") for r in df.select("doc_id", "text").collect()]
