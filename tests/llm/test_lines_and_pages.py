"""Line dedup, page extraction and the pipeline."""

import random
import re
import weakref
from collections import defaultdict

import pytest
from pyspark.sql import functions as F

from provloom.llm import common, decontaminate, html_extract, jaccard_join, line_dedup
from tests.llm.data import SCHEMA, frame


def levenshtein(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        old, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            old, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, old + (x != y))
    return row[-1]


def line_docs():
    r = random.Random(2)
    word = lambda: "".join(r.choices("abcdefgh", k=r.randrange(4, 9)))
    base = [" ".join(word() for _ in range(12)) for _ in range(6)]
    rows, i = [], 0
    for line in base:
        for k in range(5):
            text = line if k < 2 else line.upper() if k == 2 else line.replace("a", "b", 1)
            rows.append((i, f"own {word()} {word()} {word()} {word()} {i}\n{text}\nshort line"))
            i += 1
    return [*rows, (i, None), (i + 1, ""), (i + 2, "\n\n"), rows[0]]


def test_line_dedup(spark):
    rows = line_docs()
    docs = spark.createDataFrame([(i, t, "en", "s", len(t or ""), "x", "y") for i, t in rows], SCHEMA)
    got = {r["doc_id"]: r for r in line_dedup.dedup(docs).collect()}
    assert line_dedup.clean(docs).columns == docs.columns and line_dedup.clean(docs).count() == len(rows)
    lines = [(i, p, x.lower().strip()) for i, t in dict(rows).items() for p, x in enumerate((t or "").split("\n"))]
    part = sorted(x for x in lines if len(x[2].split(" ")) >= 5)
    up = {x: x for x in part}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for n, a in enumerate(part):
        for b in part[:n]:
            if a[2] == b[2] or 1 - levenshtein(a[2], b[2]) / max(len(a[2]), len(b[2])) >= 0.8:
                x, y = sorted((root(a), root(b)))
                up[y] = x
    gone = defaultdict(set)
    for x in part:
        if root(x) != x:
            gone[x[0]].add(x[1])
    exact, first = defaultdict(set), {}
    for x in part:
        if first.setdefault(x[2], x) != x:
            exact[x[0]].add(x[1])
    for i, t in dict(rows).items():
        cut = set(range(len((t or "").split("\n")))) - set()
        kept = (got[i]["text"] or "").split("\n") if t is not None else []
        removed = got[i]["__n_removed"]
        assert len(exact[i]) <= removed <= len(gone[i])
        assert t is None or len(kept) == len(cut) - removed or not kept[0]


def test_line_dedup_links_hold(spark):
    """Every pair linked meets the similarity; pairs within three bits that meet it are connected."""
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    lines = line_dedup.occurrences(docs, 5)
    forms = lines.groupBy("nh").agg({"norm": "min"}).toDF("nh", "norm").cache()
    text = {r["nh"]: r["norm"] for r in forms.collect()}
    up = {x: x for x in text}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for r in line_dedup.links(lines, 80).collect():
        a, b = text[r["a"]], text[r["b"]]
        assert levenshtein(a, b) <= 0.2 * max(len(a), len(b))
        up[root(r["a"])] = root(r["b"])
    sig = [(r["nh"], r["b0"] | r["b1"] << 30 | r["b2"] << 60 | r["b3"] << 90) for r in line_dedup.signatures(forms).collect()]
    for n, (x, a) in enumerate(sig):
        for y, b in sig[:n]:
            if (a ^ b).bit_count() <= 3 and levenshtein(text[x], text[y]) <= 0.2 * max(len(text[x]), len(text[y])):
                assert root(x) == root(y)


def test_edit_similarity_of_long_lines(spark):
    """Comparing pieces first gives the same links as comparing whole lines, near the bound too."""
    r = random.Random(1)
    rows, pairs, want = [], [(2 * n, 2 * n + 1) for n in range(24)], set()
    for a, b in pairs:
        x = "".join(r.choice("abcdé日 ") for _ in range(r.choice([5, 60, 511, 512, 513, 900, 1400])))
        y = list(x)
        for _ in range(int(len(x) * r.choice([0.02, 0.1, 0.18, 0.2, 0.25, 0.4]))):
            k = r.randrange(len(y))
            y[k : k + 1] = r.choice(["q", "", y[k] + "z"])
            y = y or ["q"]
        y = "".join(y[len(y) // 8 :] + ["zzé"] * (len(y) // 30) if a % 12 == 0 else y)
        rows += [(a, x), (b, y)]
        if levenshtein(x, y) <= 0.2 * max(len(x), len(y)):
            want.add((a, b))
    forms, asked = spark.createDataFrame(rows, "nh long, norm string"), spark.createDataFrame(pairs, "a long, b long")
    assert {tuple(x) for x in line_dedup._linked(asked, forms, 80).collect()} == want


def test_unlike_long_lines_are_told_by_their_phrases(spark):
    """Unlike long lines cost pieces of every size and the whole distance; a bound by broken phrases rejects them, and no like pair."""
    r = random.Random(9)
    words = ["".join(r.choices("etaoinshrdlcumpgé", k=r.randrange(2, 9))) for _ in range(800)]
    prose = lambda n: " ".join(r.choices(words, k=n))
    rows, unlike = [], set()
    for n in range(40):
        x = prose(r.randrange(170, 260))
        y = list(x)
        for _ in range(int(len(x) * (0.05, 0.17, 0.19, 0.21)[n % 4])):
            k = r.randrange(len(y))
            y[k : k + 1] = r.choice(["q", "", y[k] + "z"])
        y = "".join(y)
        if n % 5 == 1:  # shifted as far as the bound allows
            cut = len(x) // 11
            y = x[cut:] + prose(60)[:cut]
        if n % 5 == 2:
            y = prose(60)[: len(x) // 10] + x
        if n % 5 == 3:
            y = prose(260)[: len(x)]
            unlike.add(2 * n)
        rows += [(2 * n, x), (2 * n + 1, y)]
    text = dict(rows)
    far = {a: levenshtein(text[a], text[a + 1]) for a in range(0, 80, 2)}
    allowed = {a: max(len(text[a]), len(text[a + 1])) * 20 // 100 for a in far}
    pairs = spark.createDataFrame([(a, text[a], text[a + 1], len(text[a]), len(text[a + 1]), allowed[a]) for a in far], "a long, na string, nb string, la int, lb int, k int")
    told = {x["a"] for x in pairs.where(line_dedup._broken("k")).select("a").collect()}
    assert all(far[a] > allowed[a] for a in told) and len(told & unlike) >= 0.75 * len(unlike) and min(len(t) for _, t in rows) > 300
    asked = spark.createDataFrame([(a, a + 1) for a in far], "a long, b long")
    got = {x["a"] for x in line_dedup._linked(asked, spark.createDataFrame(rows, "nh long, norm string"), 80).collect()}
    assert got == {a for a in far if far[a] <= allowed[a]} and len(got) > 15


def test_pairs_of_lines_are_compared_in_parts(spark, monkeypatch):
    """Four parts give the links of all pairs, and each shuffles only the forms that its pairs may have."""
    r = random.Random(3)
    rows = [(i - 40, "".join(r.choices("abc ", k=30))) for i in range(80)]
    rows += [(i + 1000, x[:-1] + "q") for i, x in rows]
    forms, asked = spark.createDataFrame(rows, "nh long, norm string"), spark.createDataFrame([(a, b) for a, _ in rows for b, _ in rows if a > b], "a long, b long")
    plans, write = [], line_dedup.Scratch.__call__
    monkeypatch.setattr(line_dedup.Scratch, "__call__", lambda self, df, codec="zstd": (plans.append(df._jdf.queryExecution().optimizedPlan().toString()), write(self, df, codec))[1])
    with common.Scratch(spark) as tmp:
        got = [tuple(x) for x in line_dedup._linked_in_parts(asked, forms, 80, tmp).collect()]
    assert len(got) == len(set(got)) >= 80 and set(got) == {tuple(x) for x in line_dedup._linked(asked, forms, 80).collect()}
    assert len(plans) == 4 and all(len(re.findall(r"\(nh#\d+L? & 1\)", p)) == 2 for p in plans), plans[0]


def test_line_normal_form(spark):
    """Punctuation and every kind of white space count as one space; words of any length vote."""
    line = "one small step for a man, one giant leap"
    same = [line, line + "\r", line.replace(" ", "\t"), line.replace(" ", "\u00a0") + ".", f"* {line.replace(',', ' -')} *", line.upper()]
    docs = spark.createDataFrame([(i, t) for i, t in enumerate(same)], "doc_id long, text string")
    got = {r["doc_id"]: r["__n_removed"] for r in line_dedup.dedup(docs).collect()}
    assert got == {0: 0, **dict.fromkeys(range(1, len(same)), 1)}
    forms = spark.createDataFrame([(1, "to be or not to be that is it"), (2, "to be or not to be that is us")], "nh long, norm string")
    a, b = [tuple(r[f"b{k}"] for k in range(4)) for r in line_dedup.signatures(forms).orderBy("nh").collect()]
    assert 0 < sum((x ^ y).bit_count() for x, y in zip(a, b)) < 40


@pytest.mark.parametrize("n_words", [8, 12, 40, 100])
def test_line_dedup_finds_changed_words(spark, n_words):
    """Lines with up to a tenth of their words changed meet and go."""
    r = random.Random(n_words)
    word = lambda: "".join(r.choices("abcdefgh", k=r.randrange(4, 9)))
    rows = []
    for i in range(10):
        words = [word() for _ in range(n_words)]
        rows.append((i, " ".join(words)))
        for k in r.sample(range(n_words), max(1, n_words // 10)):
            words[k] = "".join(r.choices("abcdefgh", k=len(words[k])))
        rows.append((100 + i, " ".join(words)))
    got = {x["doc_id"]: x["__n_removed"] for x in line_dedup.dedup(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    texts = dict(rows)
    want = {i: int(i >= 100 and levenshtein(texts[i], texts[i - 100]) <= 0.2 * max(len(texts[i]), len(texts[i - 100]))) for i in texts}
    assert sum(want.values()) > 5 and got == want


def test_line_buckets_are_dealt_once(spark, monkeypatch):
    """The cells of all lines are shuffled once for the least lines of the buckets and the join with them."""
    plans, write = [], line_dedup.Scratch.__call__

    def spy(self, df, codec="zstd"):
        if "least" in df.columns:
            df.collect()
            plans.append(df._jdf.queryExecution().executedPlan().toString().split("== Initial Plan ==")[0])
        return write(self, df, codec)

    monkeypatch.setattr(line_dedup.Scratch, "__call__", spy)
    docs = spark.createDataFrame(line_docs(), "doc_id long, text string")
    line_dedup.links(line_dedup.occurrences(docs, 5), 80)
    assert len(plans) == 1 and len(re.findall(r"ReusedExchange \[v#|ReusedExchange \[nh#", plans[0])) == 1, plans


def test_line_texts_are_dealt_once(spark, monkeypatch):
    """Signatures and grams are made behind one shuffle of the texts, and the cells of all lines are written to no table."""
    made, write = [], line_dedup.Scratch.__call__

    def spy(self, df, codec="zstd"):
        made.append(df.columns)
        return write(self, df, codec)

    monkeypatch.setattr(line_dedup.Scratch, "__call__", spy)
    docs = spark.createDataFrame(line_docs(), "doc_id long, text string")
    line_dedup.links(line_dedup.occurrences(docs, 5), 80)
    assert ["nh", "v"] not in made and ["nh", "size", "b0", "b1", "b2", "b3", "grams"] in made


def test_shuffles_of_a_step_go_before_the_next(spark, monkeypatch):
    """A step's shuffles stayed on disk while the next one was written: its plan was still held when they were to go."""
    plans, seen, free = [], [], common.free
    monkeypatch.setattr(common, "free", lambda s: (free(s), seen.append([p() is None for p in plans])))

    write = common._write
    monkeypatch.setattr(common, "_write", lambda df, codec: (seen.append("write"), write(df, codec))[1])
    with common.Scratch(spark) as tmp:
        for _ in range(3):
            box = [spark.range(100).groupBy((F.col("id") % 7).alias("k")).count()]
            plans.append(weakref.ref(box[0]))
            tmp(box.pop())
    assert seen == [[False], "write", [True, False], "write", [True, True, False], "write", [True, True, True]]


def test_line_dedup_awkward(spark):
    docs = frame(spark)
    assert line_dedup.clean(docs).count() == docs.count()
    assert line_dedup.clean(frame(spark, [])).count() == 0


PAGE = '<html><head><title>no</title></head><body><header>Top</header><nav><a>Home</a></nav><div class="cookie-notice">Cookies</div><article><h1>T &amp; &eacute;</h1><p>one <b>two</b>\n three<p>four<br>five<script>x</script><aside>side</aside><form>f</form></article><section id="comments"><p>c</p></section><footer>F</footer>'


@pytest.mark.parametrize("page,text", [
    (PAGE, "T & é\n\none two three\n\nfour five"),
    (None, ""), ("", ""), ("plain &lt;text&gt;", "plain <text>"), ("<p>a<p>b", "a\n\nb"), ("<div class='with-sidebar'>x</div><div class='sidebar'>y</div>", "x"),
    ("<main><ul><li>a<li>b</ul></main>tail", "a\n\nb"), ("<div>" * 3000 + "deep", "deep"), ("<p>a <!-- no --> b</p><p>unclosed <i>c", "a b\n\nunclosed c"),
])
def test_page(spark, page, text):
    df = spark.createDataFrame([(1, None, page, "x")], "page_id long, url string, html string, host string")
    assert [tuple(r) for r in html_extract.extract(df).collect()] == [(1, None, text, len(text))]


def test_wrapper(spark):
    r = random.Random(1)
    own = [" ".join(r.choices("alpha beta gamma delta epsilon zeta".split(), k=9)) + f" {i}" for i in range(8)]
    pages = [(i, f"http://a.example/{i}", f"<body><div><p>Site name here</p></div><div><p>{t}</p><p>more {t[::-1]}</p></div><div><p>All about us</p></div></body>") for i, t in enumerate(own)]
    pages += [(100 + i, f"http://b.example/{i}", "<body><p>the same page everywhere</p></body>") for i in range(8)]
    got = {x["page_id"]: x["text"] for x in html_extract.extract(spark.createDataFrame(pages, "page_id long, url string, html string")).collect()}
    assert all(got[i] == f"{t}\n\nmore {t[::-1]}" for i, t in enumerate(own))
    assert all(got[100 + i] == "the same page everywhere" for i in range(8))


def test_tree_match():
    leaf = lambda t, h=0: (t, h, ())
    a = ("div", 0, (leaf("p", 1), leaf("ul", 2), leaf("p", 3)))
    b = ("div", 0, (leaf("p", 9), leaf("h1", 4), leaf("p", 3)))
    assert html_extract.tree_match(a, b, {}) == 3 and html_extract.align(a, b) == sorted(html_extract.align(a, b), key=lambda x: html_extract.align(a, b).index(x))
    assert html_extract.tree_match(a, ("span", 0, ()), {}) == 0


def test_pipeline(spark):
    import corpus_pipeline

    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    now = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, now, "/root/testdata/sf0.001").cache()
        assert out.columns == docs.columns, name
        before, after = {r["doc_id"] for r in now.select("doc_id").collect()}, {r["doc_id"] for r in out.select("doc_id").collect()}
        assert after <= before
        if stage is corpus_pipeline.near_duplicates:
            assert after == {r["component_id"] for r in jaccard_join.join(now).collect()}
        if stage is corpus_pipeline.benchmarks:
            bad = decontaminate.scan(now, spark.read.parquet("/root/testdata/sf0.001/benchmark.parquet")).where("contaminated")
            assert after == before - {r["doc_id"] for r in bad.collect()}
        now = out
    pieces = corpus_pipeline.STAGES[-1][1](spark, now, "")
    assert {r["doc_id"] for r in pieces.select("doc_id").distinct().collect()} == {r["doc_id"] for r in now.collect()}
