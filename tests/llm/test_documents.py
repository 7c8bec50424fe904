"""Operators over documents against brute force."""

import hashlib
import math
import random
import re
import zlib
from collections import Counter, defaultdict
from fractions import Fraction
from itertools import combinations

import numpy as np
import pytest
from pyspark.sql import functions as F

from provloom.llm import common, decontaminate, jaccard_join, kneser_ney, licenses, packing, quality_rules, suffix_dedup, token_shards
from provloom.llm.tokens import default_path
from tests.llm.data import frame, given, plain

ALNUM = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
SPACE = re.compile(r"[^\x20\x09-\x0D]+")


def fold(t):
    return re.sub("[A-Z]", lambda m: m[0].lower(), t)


@pytest.fixture(scope="module", params=["given", "awkward", "empty"])
def docs(request, spark):
    df = {"given": lambda: given(spark), "awkward": lambda: frame(spark), "empty": lambda: frame(spark, [])}[request.param]()
    return df.cache()


def bag(rows):
    return Counter(tuple(r) for r in rows)


def test_licenses(docs):
    def brute(i, t):
        w = ALNUM.findall(fold(t))
        at, labels = [], set()
        for phrase, label in licenses.PHRASES.items():
            p = phrase.split()
            for k in range(len(w) - len(p) + 1):
                if w[k : k + len(p)] == p:
                    at.append(k)
                    labels.add(label)
        return i, len(w), len(at), min(at, default=None), max(at, default=None), ",".join(sorted(labels))

    got = licenses.scan(docs).collect()
    assert bag(r[:6] for r in got) == bag(brute(i, t) for i, t in plain(docs))
    assert all(0 <= r["score"] <= 1 and (r["score"] > 0) == bool(r["labels"]) for r in got)
    assert all(set(filter(None, r["base_labels"].split(","))) <= set(r["labels"].split(",")) for r in got)


def test_license_templates(spark):
    mit, zl = licenses.TEMPLATES["mit"], licenses.TEMPLATES["zlib"]
    words = mit.split()
    words[20:20] = ["inserted", "words"]
    texts = ["lead in " + " ".join(words) + " tail", zl, " ".join(mit.split()[:40]), "Creative work is CC BY here"]
    got = {r["doc_id"]: r for r in licenses.scan(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    assert got[0]["labels"] == "mit" and got[0]["score"] > 0.8
    assert got[1]["labels"] == "zlib" and got[1]["score"] == 1
    assert got[2]["labels"] == "" and got[2]["score"] == 0
    assert (got[3]["labels"], got[3]["first_word"], got[3]["n_base"]) == ("cc-by", 3, 1)


def test_license_notices(spark):
    texts = ["Some words. Released under the MIT License. More", "Licensed under the Apache License, Version 2.0.", "licensed under the Apache License, version 2", "Licensed under CC BY-NC 4.0", "the MIT License of old"]
    got = {r["doc_id"]: r for r in licenses.scan(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    assert [(got[i]["labels"], got[i]["score"]) for i in range(5)] == [("mit", 1), ("apache-2.0", 1), ("apache-2.0", 0.875), ("cc-by,cc-by-nc", 1), ("", 0)]
    assert all(len(licenses.alnum_words(t)) >= 5 for t in licenses.TEMPLATES.values())


def measure(t):
    w = SPACE.findall(t)
    lines = [x for x in t.split("\n") if SPACE.search(x)]
    at = defaultdict(list)
    for k in range(len(w) - 2):
        at[tuple(w[k : k + 3])].append(k)
    marked = {k + d for ks in at.values() if len(ks) > 1 for k in ks for d in range(3)}
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), len(marked)


def test_quality_measures(docs):
    got = quality_rules.judge(docs).collect()
    names = ["doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]
    assert bag([r[n] for n in names] for r in got) == bag((i, *measure(t)) for i, t in plain(docs))
    for r in got:
        assert r["base_failed"] == (r["n_words"] < 50 or 100 * r["n_repeat_words"] > 50 * r["n_words"])
        assert r["kept"] == (not r["base_failed"] and 2 * r["removed_words"] <= r["n_words"])


def test_quality_line_frequency(spark):
    import random

    r = random.Random(1)
    prose = lambda n: " ".join("".join(r.choices("abcdefghij", k=7)) for _ in range(n))
    menu = "home about contact sign in subscribe today"
    rows = [(i, prose(60) + "\n" + menu, "h") for i in range(30)]
    rows += [(100 + i, prose(60) + "\n" + " ".join([menu] * 1) + "\n" + "\n".join(f"Menu line {menu}" for _ in range(20)), "h") for i in range(30)]
    rows += [(200 + i, prose(60), "h") for i in range(5)] + [(300, "same copy " + prose(60), "h")]
    rows += [(301 + i, rows[-1][1], "h") for i in range(40)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = {x["doc_id"]: x for x in quality_rules.judge(docs).collect()}
    assert all(got[i]["kept"] for i in [*range(30), *range(200, 205), *range(300, 341)])
    assert got[0]["removed_words"] == 0 and got[5]["removed_words"] == 7
    assert not any(got[i]["kept"] for i in range(101, 130))
    left = {x["doc_id"]: x["text"] for x in quality_rules.clean(docs).collect()}
    assert left[5] == rows[5][1].split("\n")[0] and left[0] == rows[0][1] and left[303] == rows[-1][1]


def test_decontamination(docs, spark):
    items = spark.read.parquet("/root/testdata/sf0.001/benchmark.parquet").select("item_id", "text")
    own = [(900, "One"), (901, None), (902, " "), (903, "one two"), (904, docs_passage(docs))]
    items = items.union(spark.createDataFrame(own, "item_id long, text string"))
    pairs = [(str(i), ALNUM.findall(fold(t or ""))) for i, t in items.collect()]
    windows = defaultdict(set)
    for k, w in pairs:
        n = min(13, len(w))
        for s in range(len(w) - n + 1) if n else []:
            windows[tuple(w[s : s + n])].add(k)
    sizes = {len(x) for x in windows}

    def brute(i, t):
        w, hit, found = ALNUM.findall(fold(t)), set(), set()
        for n in sizes:
            for s in range(len(w) - n + 1):
                if (x := tuple(w[s : s + n])) in windows:
                    hit.update(range(s, s + n))
                    found |= windows[x]
        return i, len(w), len(hit), len(found), hashlib.sha256(",".join(sorted(found)).encode()).hexdigest(), bool(hit) and 20 * len(hit) >= len(w)

    got = decontaminate.scan(docs, items).drop("spans").collect()
    want = [brute(i, t) for i, t in plain(docs)]
    assert bag(got) == bag(want)
    left = decontaminate.clean(docs, items)
    assert left.columns == docs.columns
    assert bag([r["doc_id"]] for r in left.collect()) == bag([w[0]] for w in want if not w[5])


def docs_passage(docs):
    row = docs.where("length(text) > 300").orderBy("doc_id").first()
    return row["text"][50:250] if row else "none here"


def test_decontamination_cuts_hits(spark):
    """Documents that stay lose each word inside a window of an item, and the seams make no new window."""
    item = [f"item{k}" for k in range(20)]
    own = [f"Own{k}" for k in range(600)]
    texts = [
        " ".join(own[:300]) + " (" + ", ".join(item[:14]).upper() + ")\n" + " ".join(own[300:]), " ".join(own[:30] + item[:14]), " ".join(own + item[:12]),
        " ".join(own[:300] + item[:6] + item[:13] + item[6:13] + own[300:]), "", None,
    ]
    docs = spark.createDataFrame([(i, t, len(t or "")) for i, t in enumerate(texts)], "doc_id long, text string, n_chars long")
    left = decontaminate.clean(docs, spark.createDataFrame([(1, " ".join(item))], "item_id long, text string"))
    got = {r["doc_id"]: r for r in left.collect()}
    assert left.columns == docs.columns and set(got) == {0, 2, 3, 4, 5}
    assert got[0]["text"] == " ".join(own[:300]) + " ()\n" + " ".join(own[300:]) and got[0]["n_chars"] == len(got[0]["text"])
    assert (got[2]["text"], got[4]["text"], got[5]["text"]) == (texts[2], "", None)
    assert ALNUM.findall(fold(got[3]["text"])) == [x.lower() for x in own]


def test_automaton_blocks(spark):
    items = spark.createDataFrame([(i, f"alpha beta{i} gamma{i}") for i in range(20)], "item_id long, text string")
    assert len(decontaminate.item_blocks(items, 100)) > 2
    docs = spark.createDataFrame([(1, "x alpha beta3 gamma3 alpha beta19 gamma19")], "doc_id long, text string")
    whole = decontaminate.scan(docs, items).first()
    decontaminate.BLOCK_CHARS, old = 100, decontaminate.BLOCK_CHARS
    assert (whole["n_hit"], whole["n_items"], whole["spans"]) == (6, 2, [[1, 6]])
    decontaminate.BLOCK_CHARS = old


@pytest.mark.parametrize("n,percent", [(3, 90), (5, 80)])
def test_jaccard_join(docs, n, percent):
    rows = plain(docs)
    sets = []
    for i, t in rows:
        w = SPACE.findall(fold(t))
        sets.append(frozenset(tuple(w[k : k + n]) for k in range(len(w) - n + 1)) or (frozenset([tuple(w)]) if w else frozenset()))
    up = list(range(len(rows)))

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for x, y in combinations(range(len(rows)), 2):
        a, b = sets[x], sets[y]
        if a and b and 100 * len(a & b) >= percent * len(a | b):
            up[root(x)] = root(y)
    least = defaultdict(lambda: 1 << 60)
    for x, (i, _) in enumerate(rows):
        least[root(x)] = min(least[root(x)], i)
    got = jaccard_join.join(docs, n, percent).collect()
    assert bag(got) == bag((i, len(s), least[root(x)]) for x, ((i, _), s) in enumerate(zip(rows, sets)))


def test_jaccard_families(spark, monkeypatch):
    monkeypatch.setattr(jaccard_join, "FEW", 3)
    monkeypatch.setattr(jaccard_join, "BLOCK", 7)
    test_jaccard_join(frame(spark), 3, 90)
    monkeypatch.setattr(jaccard_join, "SLICE", 16)
    test_jaccard_join(frame(spark), 5, 80)


def test_jaccard_candidates_share_several_grams(spark, monkeypatch):
    """Texts that share a few of their rare grams by chance are not compared; near copies about the bound still meet."""
    r = random.Random(8)
    fresh = lambda n: [f"w{r.randrange(10**6)}" for _ in range(n)]
    rows = [(i, " ".join(r.choices("abcdefghijkl", k=300))) for i in range(40)]
    for i in range(100, 160, 2):
        w = fresh(r.choice([3, 4, 20, 49, 52, 110, 240, 600]))
        other = list(w)
        for k in r.sample(range(len(w)), len(w) * r.choice([0, 1, 2, 3]) // 100 + r.randrange(2)):
            other[k] = "changed"
        rows += [(i, " ".join(w)), (i + 1, " ".join(other))]
    asked, verified = [], jaccard_join._verified

    def spy(pairs, *rest):
        asked.append(pairs.count())
        return verified(pairs, *rest)

    monkeypatch.setattr(jaccard_join, "_verified", spy)
    test_jaccard_join(spark.createDataFrame(rows, "doc_id long, text string"), 3, 90)
    assert asked[0] <= 60


def test_jaccard_clean(docs):
    left = jaccard_join.clean(docs)
    assert left.columns == docs.columns
    kept = [r["doc_id"] for r in left.collect()]
    assert sorted(kept) == sorted({r["component_id"] for r in jaccard_join.join(docs).collect()})


def test_suffix_dedup(docs):
    rows, width = plain(docs), 50
    first = {}
    for i, t in rows:
        b = t.encode()
        for s in range(len(b) - width + 1):
            w = b[s : s + width]
            first[w] = min(first.get(w, i), i)

    def brute(i, t):
        b = t.encode()
        gone = bytearray(len(b))
        for s in range(len(b) - width + 1):
            if first[b[s : s + width]] < i:
                gone[s : s + width] = b"\1" * width
        keep = bytes(x for x, g in zip(b, gone) if not g)
        return i, len(b), sum(gone), len(re.findall(b"\1+", bytes(gone))), hashlib.sha256(keep).hexdigest()

    assert bag(suffix_dedup.dedup(docs, width).drop("kept").collect()) == bag(brute(i, t) for i, t in rows)


def test_suffix_sort():
    r = np.random.default_rng(3)
    text = r.integers(0, 3, (500, 9)).astype(np.uint8)
    text[::5] = text[0]
    group = r.integers(0, 20, 500)
    order, lcp = suffix_dedup.suffix_sort(text, group)
    keys = [(group[i], text[i].tobytes()) for i in order]
    assert sorted(order) == list(range(500)) and keys == sorted(keys)
    for k in range(1, 500):
        a, b = keys[k - 1], keys[k]
        want = next((j for j in range(9) if a[1][j] != b[1][j]), 9) if a[0] == b[0] else 0
        assert lcp[k] == want


def ids_of(rows):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(default_path())
    return [(i, np.array(tok.encode(t, add_special_tokens=False).ids + [2], "<u4")) for i, t in rows]


def test_token_shards(docs):
    rows = sorted(plain(docs))
    want, at = [], 0
    for i, ids in ids_of(rows):
        want.append((i, at, len(ids), zlib.crc32(ids.tobytes())))
        at += len(ids)
    shards = token_shards.write_shards(docs, shard_ids=5000)
    assert bag(token_shards.read_digest(shards).collect()) == bag(want)
    if rows:
        some = {i: ids.tolist() for i, ids in reversed(ids_of(rows)) if i % 9 == 0}
        assert token_shards.lookup(shards, [*some, 10**9]) == some


def test_perfect_hash():
    keys = list(range(-500, 5000, 7))
    seeds, slots = token_shards.perfect_hash(keys)
    assert sorted(slots.tolist()) == list(range(len(keys)))


def test_packing(docs):
    whole = Counter()
    for i, ids in ids_of(plain(docs)):
        whole[i, ids.tobytes()] += 1
    pieces, seqs = defaultdict(list), defaultdict(list)
    for r in packing.pack(docs).collect():
        seqs[r["sequence_id"]].append((r["offset"], r["length"]))
        pieces[r["doc_id"]].append(r)
    for s in seqs.values():
        at = 0
        for offset, n in sorted(s):
            assert offset == at and n > 0
            at += n
        assert at <= 4096
        assert at == 4096 or at & (at - 1) == 0
    assert sorted(seqs) == list(range(len(seqs)))
    for (i, ids), times in whole.items():
        mine = [r for r in pieces[i] if r["doc_tokens"] == len(ids) // 4]
        assert sum(r["length"] for r in mine) == times * len(ids) // 4
        for r in mine:
            assert r["ids_crc32"] == zlib.crc32(ids[4 * r["start"] : 4 * (r["start"] + r["length"])])
    assert set(pieces) == {i for i, _ in whole}


def test_best_fill():
    assert packing.best_fill({5: 2, 3: 4, 7: 1}, 11) in ({5: 1, 3: 2}, )
    assert sum(k * n for k, n in packing.best_fill({100: 3, 7: 5}, 215).items()) == 214
    assert packing.best_fill({}, 10) == {}


def discounts_of(counts):
    """D1, D2, D3+ of modified Kneser-Ney from counts of counts; 0.5, 0.75 and 0.9 where one of the four is missing."""
    n = [counts[k] for k in (1, 2, 3, 4)]
    if 0 in n:
        return 0.5, 0.75, 0.9
    y = Fraction(n[0], n[0] + 2 * n[1])
    d = [1 - 2 * y * Fraction(n[1], n[0]), 2 - 3 * y * Fraction(n[2], n[1]), 3 - 4 * y * Fraction(n[3], n[2])]
    return tuple(float(min(max(x, 0), k - Fraction(1, 100))) for k, x in enumerate(d, 1))


def model_scores(rows: list[tuple[int, bool, str]]) -> list[tuple[int, float]]:
    """The model's scores from plain dictionaries: (doc_id, held_out, text)."""
    docs = [(i, held, [None, *SPACE.findall(fold(t)), "\n"]) for i, held, t in rows]
    pairs = Counter(x for _, held, w in docs if not held for x in zip(w, w[1:]))
    ctx: dict = {}
    cont: Counter = Counter()
    for (a, b), c in pairs.items():
        s = ctx.setdefault(a, [0, 0, 0, 0])
        s[0] += c
        s[min(c, 3)] += 1
        cont[b] += 1
    coc = Counter(pairs.values())
    two = discounts_of(coc)
    c1 = Counter(cont.values())
    one, types = discounts_of(c1), len(pairs)
    less = lambda c, d: d[min(c, 3) - 1] if c else 0.0
    spared = sum(less(c, one) for c in cont.values()) / types if types else 1.0
    vocab = len({b for _, b in pairs})
    out = []
    for i, _, w in docs:
        s = 0.0
        for a, b in zip(w, w[1:]):
            low = (max(cont[b] - less(cont[b], one), 0) / types if types else 0) + spared / (vocab + 1)
            if a in ctx:
                t, n1, n2, n3 = ctx[a]
                c = pairs[a, b]
                p = (c - less(c, two)) / t + (two[0] * n1 + two[1] * n2 + two[2] * n3) / t * low
            else:
                p = low
            s += math.log10(p)
        out.append((i, s))
    return out


def test_kneser_ney(docs):
    rows = plain(docs)
    held = lambda i: zlib.crc32(str(i).encode()) % 10 == 0
    tokens = [(i, [*SPACE.findall(fold(t)), "\n"]) for i, t in rows]
    count = Counter(w for i, ws in tokens if not held(i) for w in ws)
    n, v = sum(count.values()), len(count)
    got = sorted(kneser_ney.score(docs).collect(), key=lambda r: (r["doc_id"], r["score"]))
    want = sorted(
        (i, held(i), len(ws), sum(count[w] > 0 for w in ws), n, sum(np.log10((count[w] + 0.1) / (n + 0.1 * (v + 1))) for w in ws)) for i, ws in tokens
    )
    assert [tuple(r)[:5] for r in got] == [w[:5] for w in want]
    assert np.allclose([r["base_score"] for r in got], [w[5] for w in want])
    model = sorted(model_scores([(i, held(i), t) for i, t in rows]))
    assert [i for i, _ in model] == [r["doc_id"] for r in got]
    assert np.allclose([r["score"] for r in got], [s for _, s in model])


def test_kneser_ney_beats_unigrams(spark):
    p = kneser_ney.perplexity(kneser_ney.score(spark.read.parquet("/root/testdata/sf0.01/documents.parquet"))).first()
    assert p["model"] < 0.9 * p["base"]


BIG = (1 << 53) + 1


def test_ids(spark):
    """Null ids, ids that floats can't hold and two texts under one id keep their rows, digits and links."""
    words = [f"word{k}" for k in range(60)]
    a, b, c = " ".join(words), " ".join(words[::-1]), " ".join(f"other{k}" for k in range(60))
    rows = [(2, a), (2, b), (1, a + " end"), (None, c), (BIG, c), (BIG + 2, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumn("source", F.lit("s")).coalesce(1)
    got = bag(r[::2] for r in jaccard_join.join(docs, 3, 90).collect())
    assert got == bag([(2, 1), (2, 2), (1, 1), (None, BIG), (BIG, BIG), (BIG + 2, BIG + 2)])
    kept = bag(tuple(r)[:2] for r in jaccard_join.clean(docs, 3, 90).collect())
    assert kept == bag([(2, b), (1, a + " end"), (BIG, c), (BIG + 2, None)])
    ids = bag([i] for i, _ in rows)
    items = spark.createDataFrame([(None, " ".join(words[:13])), (BIG, "other0 other1")], "item_id long, text string")
    for df in (quality_rules.judge(docs), decontaminate.scan(docs, items), licenses.scan(docs), kneser_ney.score(docs), suffix_dedup.dedup(docs), token_shards.read_digest(token_shards.write_shards(docs))):
        assert bag(df.select("doc_id").collect()) == ids
    assert {r["doc_id"] for r in packing.pack(docs).select("doc_id").collect()} == {i for i, _ in rows}  # tails may be cut
    hits = {(r["doc_id"], r["n_words"]): (r["n_hit"], r["n_items"], r["items_sha256"]) for r in decontaminate.scan(docs, items).collect()}
    sha = lambda x: hashlib.sha256(x.encode()).hexdigest()
    assert hits[2, 60] in ((13, 1, sha("")), (0, 0, sha(""))) and hits[1, 61] == (13, 1, sha("")) and hits[BIG, 60] == (2, 1, sha(str(BIG)))
    labelled = spark.createDataFrame([(None, licenses.TEMPLATES["mit"]), (1, licenses.TEMPLATES["mit"])], "doc_id long, text string")
    assert [r["labels"] for r in licenses.scan(labelled).collect()] == ["mit", "mit"]


def test_pieces_of_latin_words():
    """Words are split by spelled-out classes: each character of the range beside letters, digits and contractions as the library has it."""
    import numpy as np

    from provloom.llm import tokens

    enc = tokens.encoder(tokens.default_path())
    for c in map(chr, (*range(0x21, 0x7F), *range(0xA1, 0x250))):
        text = f"{c} a{c}1{c}{c}don't{c} X{c}LL's"
        assert np.frombuffer(enc.payload(text), "<u4").tolist() == [*enc.tokenizer.encode(text, add_special_tokens=False).ids, tokens.END_ID], c
    assert not any(p in enc.pieces for p in ("", " ")) and type(tokens._PIECES).__module__ == "re"


def test_repeated_contexts_are_judged_alike():
    """Rows alone in their part or under their key are left out of the classes; empty texts move no document's place."""
    import random

    import numpy as np

    from provloom.llm import suffix_dedup

    assert suffix_dedup._repeated(np.array([1, 1, 2, 3, 3, 3, 4])).tolist() == [True, True, False, True, True, True, False]
    assert len(suffix_dedup._repeated(np.zeros(0))) == 0 and not suffix_dedup._repeated(np.array([5])).any()
    r = random.Random(4)
    piece = lambda: bytes(r.choices(b"abc ", k=r.randrange(60, 90)))
    shared = [piece() for _ in range(6)]
    texts = [b"" if i % 5 == 0 else piece() + r.choice(shared) + piece() + r.choice(shared)[:55] for i in range(40)]
    a = suffix_dedup.Anchors(texts, 50)
    starts = {(int(d), s) for d, lo, hi in zip(a.doc, a.lo - a.begins[a.doc], a.hi - a.begins[a.doc]) for s in range(lo, hi + 1)}
    assert starts == {(i, s) for i, t in enumerate(texts) for s in range(len(t) - 49)}
    h, ctx, least, inverse, doc, where = suffix_dedup._block_contexts(list(range(40)), texts, np.unique(a.hash), 50)
    bits = suffix_dedup.decide(h, ctx, least, 50)
    for x, d, (lo, hi, at) in zip(inverse, doc, where.tolist()):
        for s in range(lo, hi + 1):
            earlier = any(texts[d][s : s + 50] in t for t in texts[: least[x]])
            assert bool(int(bits[x]) >> (at - s) & 1) == earlier


def test_batches_are_taken_in_parts(spark):
    """Where memory counts, a task holds no more rows as Python objects than it must; all rows come back in order."""
    df = spark.range(2500).select("id", F.col("id").cast("string").alias("text")).coalesce(1)
    got = common.beside(df, ["id"], ["text"], lambda: lambda t: [(len(t), int(x)) for x in t], "rows long, same long", small=True).collect()
    assert max(r["rows"] for r in got) <= common.ROWS_AT_ONCE and [r["same"] for r in got] == [r["id"] for r in got] == list(range(2500))
