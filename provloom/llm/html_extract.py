"""Main text of web pages by wrapper induction.

Each page becomes a tree of block nodes. Per host, the page of median size (smallest key of equals) gives the wrapper, so
stubs and giants don't; every page of the host is aligned with it by simple tree matching (the largest order-preserving
match of equal tags). Sizes of matches depend on tags alone, so they are kept by shape between pages. Votes per wrapper
node, summed over all pages of the host, say how often its own text came back unchanged: nodes that stay constant are
template, the others are slots. Content is what stands in slots or outside the wrapper, less the parts that markup
itself names as furniture (navigation, headers, footers, forms, comments and so on), inside the page's article or main
element where it has one.

Defined cases: null or empty html gives an empty text; pages whose url is null or has no scheme belong to no host and have
no template; of siblings with over ``CELLS`` pairs of different shape, those are matched first whose shape is unique on both
sides, and what lies between them in order of their tags; a host with fewer than three different pages has no template;
repeated rows give repeated result rows and count once, as do pages of equal content; html cut off anywhere is read as far as it goes.
"""

from __future__ import annotations

import html
import pickle
import re
from bisect import bisect_left
from collections import Counter
from itertools import accumulate

import pandas as pd
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from provloom.llm.common import Scratch, beside, join_checked, spill

# Element names by role.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title iframe noembed noframes xmp".split())
DROP = frozenset("head nav header footer aside form button menu dialog fieldset label select option optgroup datalist noscript template svg canvas".split()) | RAW
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd mark q s samp small span strike strong sub sup time tt u var ruby rt rp nobr br wbr img".split())
CLOSED_BY_BLOCK = frozenset(["p"])
# Words of class, id and role attributes that name furniture.
FURNITURE = re.compile(
    r"(?:^|[\s_-])(?:nav\w*|menu\w*|header|masthead|footer|sidebar\w*|side-?bar|aside|ads?|adv|advert\w*|banner\w*|sponsor\w*|promo\w*|"
    r"cookies?\w*|consent|gdpr|notices?|alert|popup|modal|overlay|newsletter|subscribe|signup|login|search\w*|"
    r"comments?|comment-?list|respond|replies|disqus|discussion|share|sharing|social\w*|related|recommend\w*|breadcrumbs?|"
    r"pagination|pager|toolbar|widget\w*|copyright|skip\w*|contentinfo|navigation|complementary|form)(?=$|[\s_-])",
    re.I,
)
#: Pages that a task aligns, about.
PAGES_PER_TASK = 20_000
#: Levels of a tree; blocks below hang from the last.
DEEPEST = 120
_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)(?:>|\Z)", re.S)
_NAMING = re.compile(r"(?:^|\s)(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
_HIDDEN = re.compile(r"(?:^|\s)(?:hidden(?=\s|$|=)|aria-hidden\s*=\s*[\"']?true)|display\s*:\s*none", re.I)


class Node:
    __slots__ = ("tag", "kids", "drop", "scope", "text")

    def __init__(self, tag: str, drop: bool, scope: bool):
        self.tag, self.kids, self.drop, self.scope, self.text = tag, [], drop, scope, None


def parse(page: str) -> Node:
    """The tree of block elements; leaves '#' hold the text of one block each."""
    root = Node("", False, False)
    stack, buf, at = [root], [], 0
    inline_drop: list[str] = []

    def flush():
        if buf:
            words = " ".join(html.unescape("".join(buf)).split())
            buf.clear()
            if words:
                leaf = Node("#", stack[-1].drop, stack[-1].scope)
                leaf.text = words
                stack[-1].kids.append(leaf)

    n = len(page)
    while at < n:
        m = _TOKEN.search(page, at)
        if m is None:
            if not inline_drop:
                buf.append(page[at:])
            break
        if m.start() > at and not inline_drop:
            buf.append(page[at : m.start()])
        at = m.end()
        tag = (m[2] or "").lower()
        if not tag:
            continue
        if m[1]:
            if inline_drop:
                if tag == inline_drop[-1]:
                    inline_drop.pop()
                    continue
                if tag in INLINE:
                    continue
                inline_drop.clear()
            if tag in INLINE:
                continue
            for i in range(len(stack) - 1, 0, -1):
                if stack[i].tag == tag:
                    flush()
                    del stack[i:]
                    break
            else:
                flush()
            continue
        attrs = m[3]
        if tag in RAW:
            end = re.compile(rf"</{re.escape(tag)}\s*>", re.I).search(page, at)
            if not attrs.rstrip().endswith("/"):
                at = end.end() if end else n
            continue
        if tag in INLINE:
            if tag == "br":
                buf.append(" ")
            elif inline_drop:
                if tag == inline_drop[-1]:
                    inline_drop.append(tag)
            elif attrs and tag not in VOID and (_named(attrs) or _HIDDEN.search(attrs)):
                inline_drop.append(tag)
            continue
        inline_drop.clear()
        flush()
        if tag in VOID:
            continue
        if stack[-1].tag in CLOSED_BY_BLOCK:
            stack.pop()
        elif tag in ("li", "dt", "dd", "tr", "td", "th", "option") and stack[-1].tag == tag:
            stack.pop()
        above = stack[-1]
        drop = above.drop or tag in DROP or bool(attrs) and tag not in ("html", "body", "main", "article") and (_named(attrs) or bool(_HIDDEN.search(attrs)))
        if tag == "article" and attrs and re.search(r"comment|repl(?:y|ies)|teaser|related|promo", " ".join(filter(None, (x for g in _NAMING.findall(attrs) for x in g))), re.I):
            drop = True
        node = Node(tag, drop, above.scope or tag in ("article", "main") and not drop)
        if len(stack) < DEEPEST:
            above.kids.append(node)
        else:
            node.kids = above.kids  # its blocks hang from the deepest node that is kept
        if not attrs.rstrip().endswith("/"):
            stack.append(node)
    flush()
    return root


def _named(attrs: str) -> bool:
    names = (x for g in _NAMING.findall(attrs) for v in g for x in v.split())
    return any(FURNITURE.search(x) for x in names if not x.lower().startswith(("has-", "with-", "no-", "without-", "js-")))


def skeleton(node: Node) -> tuple:
    """(tag, hash of the own text, children): what alignment needs of a tree."""
    return node.tag, xxhash.xxh3_64_intdigest(node.text) if node.text else 0, tuple(skeleton(k) for k in node.kids)


#: Pairs of unlike siblings up to which the best match is computed, and match sizes kept by a worker.
CELLS, KEPT = 1_000_000, 500_000
_SIZES: dict[tuple[int, int], int] = {}


def prepare(t: tuple) -> tuple:
    """A tree with, for each node, the hash of its shape (tags alone) and its number of nodes."""
    if len(t) == 5:
        return t
    kids = tuple(map(prepare, t[2]))
    return t[0], t[1], kids, hash((t[0], *(k[3] for k in kids))), 1 + sum(k[4] for k in kids)


def _size(a: tuple, b: tuple) -> int:
    if a[3] == b[3]:
        return a[4]
    if a[0] != b[0]:
        return 0
    if not a[2] or not b[2]:
        return 1
    key = (a[3], b[3])
    if (got := _SIZES.get(key)) is None:
        if len(_SIZES) > KEPT:
            _SIZES.clear()
        got = _SIZES[key] = 1 + sum(_size(a[2][i], b[2][j]) for i, j in _siblings(a[2], b[2]))
    return got


def _siblings(x: tuple, y: tuple) -> list[tuple[int, int]]:
    """The largest order-preserving match of two rows of siblings. Equal shapes at both ends match each other."""
    lead, last = 0, min(len(x), len(y))
    while lead < last and x[lead][3] == y[lead][3]:
        lead += 1
    tail = 0
    while tail < last - lead and x[-1 - tail][3] == y[-1 - tail][3]:
        tail += 1
    got = [(i, i) for i in range(lead)] + [(len(x) - 1 - i, len(y) - 1 - i) for i in range(tail)]
    mx, my = x[lead : len(x) - tail], y[lead : len(y) - tail]
    if not mx or not my:
        return got
    inner = _best(mx, my) if len(mx) * len(my) <= CELLS else _anchored(mx, my)
    return got + [(i + lead, j + lead) for i, j in inner]


def _best(x: tuple, y: tuple) -> list[tuple[int, int]]:
    gain = [[0] * (len(y) + 1)]
    for k in x:
        up, row, left = gain[-1], [0], 0
        for j, q in enumerate(y):
            w = _size(k, q)
            left = max(left, up[j + 1], up[j] + w if w else 0)
            row.append(left)
        gain.append(row)
    i, j, out = len(x), len(y), []
    while i and j:
        if gain[i][j] == gain[i - 1][j]:
            i -= 1
        elif gain[i][j] == gain[i][j - 1]:
            j -= 1
        else:
            i, j = i - 1, j - 1
            out.append((i, j))
    return out


def _anchored(x: tuple, y: tuple) -> list[tuple[int, int]]:
    """A match for long rows: shapes unique on both sides, in the longest common order, then what lies between them."""
    once = lambda z: {s: i for i, s in enumerate(k[3] for k in z) if n[s] == 1} if (n := Counter(k[3] for k in z)) else {}
    ux, uy = once(x), once(y)
    ends: list[int] = []
    at: list[tuple[int, int]] = []
    before: dict[int, int] = {}
    for i, j in sorted((i, uy[s]) for s, i in ux.items() if s in uy):
        k = bisect_left(ends, j)
        before[i] = at[k - 1][0] if k else -1
        ends[k : k + 1], at[k : k + 1] = [j], [(i, j)]
    pairs, place = [], dict(zip(ux.values(), (uy.get(s) for s in ux)))
    i = at[-1][0] if at else -1
    while i >= 0:
        pairs.append((i, place[i]))
        i = before[i]
    out, lo = list(pairs), (0, 0)
    for i, j in [*reversed(pairs), (len(x), len(y))]:
        gx, gy = x[lo[0] : i], y[lo[1] : j]
        if len(gx) * len(gy) <= CELLS:
            inner = _best(gx, gy) if gx and gy else []
        else:
            inner = [(k, k) for k in range(min(len(gx), len(gy))) if gx[k][0] == gy[k][0]]
        out += [(a + lo[0], b + lo[1]) for a, b in inner]
        lo = (i + 1, j + 1)
    return out


def tree_match(a: tuple, b: tuple, pairs: dict | None = None) -> int:
    """Size of the largest order-preserving match of two trees with equal root tags."""
    return _size(prepare(a), prepare(b))


def align(wrapper: tuple, page: tuple) -> list[tuple[int, int]]:
    """Matched nodes as (pre-order number in the wrapper, pre-order number in the page).

    Among matches of one size those that pair equal children at both ends of a row are taken.
    """
    wrapper, page = prepare(wrapper), prepare(page)
    if wrapper[0] != page[0]:
        return []
    out, todo = [], [(wrapper, page, 0, 0)]
    while todo:
        a, b, i, j = todo.pop()
        out.append((i, j))
        x, y = a[2], b[2]
        if not x or not y:
            continue
        lead, last = 0, min(len(x), len(y))
        while lead < last and x[lead] == y[lead]:
            lead += 1
        tail = 0
        while tail < last - lead and x[-1 - tail] == y[-1 - tail]:
            tail += 1
        got = [(k, k) for k in range(lead)] + [(len(x) - 1 - k, len(y) - 1 - k) for k in range(tail)]
        if lead + tail < last:
            got += [(k + lead, q + lead) for k, q in _siblings(x[lead : len(x) - tail], y[lead : len(y) - tail])]
        ia, jb = list(accumulate((k[4] for k in x), initial=i + 1)), list(accumulate((k[4] for k in y), initial=j + 1))
        todo += [(x[k], y[q], ia[k], jb[q]) for k, q in got]
    return out


def flat(t: tuple) -> list[tuple]:
    out, todo = [], [t]
    while todo:
        x = todo.pop()
        out.append(x)
        todo += reversed(x[2])
    return out


def main_text(root: Node, template: set[int]) -> str:
    """Blocks of the tree that are content; template: pre-order numbers of constant nodes."""
    leaves, number, todo = [], -1, [root]
    while todo:
        x = todo.pop()
        number += 1
        if x.text is not None and not x.drop:
            leaves.append((x, number in template))
        todo += reversed(x.kids)
    leaves = [x for x in leaves if x[0].scope] or leaves
    kept = [x.text for x, constant in leaves if not constant]
    if 2 * sum(map(len, kept)) < sum(len(x.text) for x, _ in leaves if x.scope):
        kept = [x.text for x, _ in leaves]  # an article that came back whole is an article, not furniture
    return "\n\n".join(kept)


def _pages(pages: DataFrame) -> DataFrame:
    host = F.lower(F.regexp_extract(F.coalesce("url", F.lit("")), r"^[a-zA-Z][a-zA-Z0-9+.-]*://([^/?#]*)", 1))
    return pages.select("page_id", "url", F.coalesce("html", F.lit("")).alias("html"), host.alias("host"))


def induce(pages: DataFrame, min_pages: int = 3, constant: float = 0.6) -> DataFrame:
    """(host, wrapper, fixed): the wrapper tree of each host with enough pages, and its constant nodes."""

    def trees(batches):
        for p in batches:
            got = [skeleton(parse(h)) for h in p["html"]]
            yield pd.DataFrame({"host": p["host"], "page_id": p["page_id"], "nodes": [len(flat(t)) for t in got], "tree": [pickle.dumps(t) for t in got]})

    def votes(batches):
        for p in batches:
            got: dict[tuple[str, int], int] = {}
            wrappers: dict[str, tuple] = {}
            for host, w, t in zip(p["host"], p["wrapper"], p["tree"]):
                if host not in wrappers:
                    a = prepare(pickle.loads(w))
                    wrappers[host] = a, flat(a)
                (a, fa), b = wrappers[host], prepare(pickle.loads(t))
                fb = flat(b)
                for i, j in align(a, b):
                    if fa[i][1] and fa[i][1] == fb[j][1]:
                        got[host, i] = got.get((host, i), 0) + 1
            yield pd.DataFrame([(h, i, n) for (h, i), n in got.items()], columns=["host", "node", "same"])

    spark = pages.sparkSession
    p = _pages(pages).where("host <> '' and page_id is not null")
    with Scratch(spark) as tmp:
        hosts = tmp(p.groupBy("host").agg(F.count("*").alias("pages")).where(F.col("pages") >= min_pages).select("host"))
        t = join_checked(p, hosts, ["host"], "inner").select("host", "page_id", "html")
        t = t.mapInPandas(trees, "host string, page_id long, nodes long, tree binary")
        t = tmp(t.groupBy("host", F.xxhash64("tree").alias("th")).agg(F.min("page_id").alias("page_id"), F.max("nodes").alias("nodes"), F.max("tree").alias("tree")))
        # the least size that half of a host's different pages don't exceed; sizes of a host are few
        sizes = t.groupBy("host", "nodes").agg(F.count("*").alias("k"), F.min("page_id").alias("page_id"))
        by = Window.partitionBy("host")
        sizes = sizes.withColumn("n", F.sum("k").over(by)).withColumn("upto", F.sum("k").over(by.orderBy("nodes")))
        first = sizes.where("n >= %d and 2 * upto >= n and 2 * (upto - k) < n" % min_pages).select("host", "n", "page_id")
        first = tmp(join_checked(t, tmp(first), ["host", "page_id"], "inner").groupBy("host").agg(F.max("n").alias("n"), F.max("tree").alias("wrapper")))
        # aligning takes far more time than its bytes show: pages are dealt out evenly, whatever their host
        parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), t.count() // PAGES_PER_TASK)
        voters = t.select("host", "tree", "th").repartition(parts, "host", "th").drop("th")
        counted = join_checked(voters, first, ["host"], "inner").mapInPandas(votes, "host string, node int, same long")
        fixed = counted.groupBy("host", "node").agg(F.sum("same").alias("same")).join(first.select("host", "n"), "host")
        fixed = fixed.where((F.col("same") >= F.lit(constant) * F.col("n")) & (F.col("same") >= min_pages))
        fixed = fixed.groupBy("host").agg(F.collect_list("node").alias("fixed"))
        return spill(first.join(fixed, "host").select("host", "wrapper", "fixed"))


def extract(pages: DataFrame, **how) -> DataFrame:
    """Per row of pages: page_id, url, text, n_chars."""

    def run(hosts, htmls, wrappers, fixed):
        out, loaded = [], {}  # wrappers of the batch's hosts
        for host, page, w, nodes in zip(hosts, htmls, wrappers, fixed):
            root, template = parse(page), set()
            if w is not None:
                if host not in loaded:
                    a = prepare(pickle.loads(w))
                    loaded[host] = a, flat(a), set(nodes)
                wrapper, fa, constant = loaded[host]
                own = prepare(skeleton(root))
                fb = flat(own)
                template = {j for i, j in align(wrapper, own) if i in constant and fa[i][1] == fb[j][1]}
            text = main_text(root, template)
            out.append((text, len(text)))
        return out

    joined = join_checked(_pages(pages), induce(pages, **how), ["host"], "left")
    return beside(joined, ["page_id", "url"], ["host", "html", "wrapper", "fixed"], lambda: run, "text string, n_chars long")
