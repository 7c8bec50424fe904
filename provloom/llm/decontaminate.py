"""Benchmark decontamination by a generalised suffix automaton over the words of all test items.

Training words are streamed through the automaton; the longest match that ends at each word is tracked. Where it
reaches ``window`` words, the last ``window`` words are a window of an item; items shorter than that are one window,
found through the automaton's suffix links. Words inside windows are hit.

Spans of at least one window are cut out of documents that stay; documents over the coverage limit go (``clean``).

Defined cases: null texts have no words and hit nothing; items without words are left out; items of null item_id count as
one item that adds no id to items_sha256; null doc_ids stay null; repeated rows give repeated
result rows; an empty benchmark hits nothing.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from provloom.llm.common import FOLD_WORDS, alnum_words, beside, keyed

#: Characters of test items in one automaton. Larger benchmarks are scanned by several, one after another.
BLOCK_CHARS = 16_000_000


class SuffixAutomaton:
    """Generalised automaton over integer sequences, with the items whose windows each state stands for."""

    def __init__(self, items: list[tuple[str, list[bytes]]], window: int):
        self.window = window
        self.vocab: dict[bytes, int] = {}
        self.next: list[dict[int, int]] = [{}]
        self.link = [-1]
        self.length = [0]
        self.ids = [k for k, w in items if w]  # null item_ids are one item without a name
        coded = [[self.vocab.setdefault(x, len(self.vocab)) for x in w] for _, w in items if w]
        for seq in coded:
            last = 0
            for c in seq:
                last = self._extend(last, c)
        self.shortest = min((min(len(s), window) for s in coded), default=0)
        n = len(self.link)
        self.whole: list[list[int]] = [[] for _ in range(n)]
        self.items: list[set[int]] = [set() for _ in range(n)]
        for k, seq in enumerate(coded):
            state = length = 0
            for c in seq:
                state, length = self.step(state, length, c)
                if length >= window:
                    self.items[self._window_state(state)].add(k)
            if len(seq) < window:
                self.whole[self._holding(state, len(seq))].append(k)
        self.short: list[tuple[tuple[int, int], ...]] = [()] * n
        for v in sorted(range(n), key=self.length.__getitem__):
            up = self.short[self.link[v]] if self.link[v] >= 0 else ()
            self.short[v] = up + tuple((len(coded[k]), k) for k in self.whole[v])

    def _extend(self, last: int, c: int) -> int:
        nxt, link, length = self.next, self.link, self.length
        if c in nxt[last]:
            q = nxt[last][c]
            return q if length[q] == length[last] + 1 else self._split(last, c, q)
        cur = self._new(length[last] + 1, {}, 0)
        p = last
        while p >= 0 and c not in nxt[p]:
            nxt[p][c] = cur
            p = link[p]
        if p >= 0:
            q = nxt[p][c]
            link[cur] = q if length[q] == length[p] + 1 else self._split(p, c, q)
        return cur

    def _new(self, length: int, edges: dict, link: int) -> int:
        self.next.append(edges)
        self.length.append(length)
        self.link.append(link)
        return len(self.link) - 1

    def _split(self, p: int, c: int, q: int) -> int:
        copy = self._new(self.length[p] + 1, dict(self.next[q]), self.link[q])
        self.link[q] = copy
        while p >= 0 and self.next[p].get(c) == q:
            self.next[p][c] = copy
            p = self.link[p]
        return copy

    def step(self, state: int, length: int, c: int) -> tuple[int, int]:
        while state and c not in self.next[state]:
            state = self.link[state]
            length = self.length[state]
        if c in self.next[state]:
            return self.next[state][c], length + 1
        return 0, 0

    def _holding(self, state: int, k: int) -> int:
        """The state up the suffix links that holds the suffix of k words."""
        while self.link[state] >= 0 and self.length[self.link[state]] >= k:
            state = self.link[state]
        return state

    def _window_state(self, state: int) -> int:
        return self._holding(state, self.window)

    def scan(self, words: list[bytes], hit: bytearray, found: set[str]) -> None:
        """Marks hit words and adds the ids of the items found."""
        if not self.shortest or len(words) < self.shortest:
            return
        codes = np.fromiter((self.vocab.get(w, -1) for w in words), np.int64, len(words))
        known = np.flatnonzero(np.diff(np.concatenate(([False], codes >= 0, [False])).astype(np.int8)))
        for lo, hi in zip(known[::2].tolist(), known[1::2].tolist()):
            if hi - lo < self.shortest:
                continue
            state = length = 0
            for i, c in enumerate(codes[lo:hi].tolist(), lo):
                state, length = self.step(state, length, c)
                if length >= self.window:
                    hit[i + 1 - self.window : i + 1] = b"\1" * self.window
                    found.update(self.ids[k] for k in self.items[self._window_state(state)])
                for n, k in self.short[state]:
                    if n <= length:
                        hit[i + 1 - n : i + 1] = b"\1" * n
                        found.add(self.ids[k])


_BUILT: dict[tuple[str, int], SuffixAutomaton] = {}


def _automaton(block: tuple[str, list], window: int) -> SuffixAutomaton:
    """The worker's automaton of a block (digest, items); a few are kept, the oldest goes first."""
    key = (block[0], window)
    if key not in _BUILT:
        if len(_BUILT) >= 4:
            del _BUILT[next(iter(_BUILT))]
        _BUILT[key] = SuffixAutomaton([(k, alnum_words(t)) for k, t in block[1]], window)
    return _BUILT[key]


def contaminating(n_hit: int, n_words: int, one_in: int) -> bool:
    return n_hit > 0 and one_in * n_hit >= n_words


def item_blocks(benchmark: DataFrame, max_chars: int = BLOCK_CHARS) -> list[tuple[str, list]]:
    """The items in blocks of bounded size. Items stream to the driver one partition at a time."""
    blocks, now, size = [], [], 0
    rows = benchmark.select(F.col("item_id").cast("string").alias("k"), F.coalesce("text", F.lit("")).alias("t"))
    for k, t in rows.dropDuplicates().orderBy(F.col("k").asc_nulls_first(), "t").toLocalIterator():
        if now and size + len(t) > max_chars:
            blocks.append(now)
            now, size = [], 0
        now.append((k, t))
        size += len(t)
    blocks += [now] if now else []
    return [(hashlib.sha256(repr(b).encode("utf-8", "surrogatepass")).hexdigest(), b) for b in blocks]


def scan(docs: DataFrame, benchmark: DataFrame, window: int = 13, one_in: int = 20) -> DataFrame:
    """Per row of docs: n_words, n_hit, n_items, items_sha256, contaminated, spans (first and last hit word of runs)."""
    sc = docs.sparkSession.sparkContext
    blocks = [sc.broadcast(b) for b in item_blocks(benchmark)]

    def judged(texts):
        out = []
        for words, hit, found in _marked(texts, blocks, window):
            marks = np.diff(np.frombuffer(b"\0" + bytes(hit) + b"\0", np.int8))
            spans = list(zip(np.flatnonzero(marks == 1).tolist(), (np.flatnonzero(marks == -1) - 1).tolist())) if found else []
            named = ",".join(sorted(k for k in found if k is not None))
            n_hit = sum(hit)
            out.append((words, n_hit, len(found), hashlib.sha256(named.encode()).hexdigest(), contaminating(n_hit, words, one_in), [list(s) for s in spans]))
        return out

    return beside(keyed(docs), ["doc_id"], ["text"], lambda: judged, "n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean, spans array<array<long>>")


def _marked(texts, blocks: list, window: int):
    """(number of words, hit, ids found) of each text. Blocks are the outer loop: each automaton is built once for all of them."""
    words = [alnum_words(t) for t in texts]
    hits, found = [bytearray(len(w)) for w in words], [set() for _ in words]
    for b in blocks:
        automaton = _automaton(b.value, window)
        for w, h, f in zip(words, hits, found):
            automaton.scan(w, h, f)
    return [(len(w), h, f) for w, h, f in zip(words, hits, found)]


def without_hits(text: str, hit: bytearray) -> str:
    """The text without its hit words: each run goes from its first word to its last, with what lies between."""
    raw = text.encode("utf-8", "surrogatepass")
    marks = np.diff(np.concatenate(([0], np.frombuffer(raw.translate(FOLD_WORDS), np.uint8) != 32, [0])).astype(np.int8))
    starts, ends = np.flatnonzero(marks == 1), np.flatnonzero(marks == -1)
    runs = np.diff(np.frombuffer(b"\0" + bytes(hit) + b"\0", np.int8))
    out, at = [], 0
    for lo, hi in zip(np.flatnonzero(runs == 1).tolist(), np.flatnonzero(runs == -1).tolist()):
        out.append(raw[at : starts[lo]])
        at = int(ends[hi - 1])
    return b"".join([*out, raw[at:]]).decode("utf-8", "surrogatepass")


def clean(docs: DataFrame, benchmark: DataFrame, window: int = 13, one_in: int = 20) -> DataFrame:
    """docs without contaminated documents and without the hit words of the others (n_chars follows), with the columns of docs.

    Where a cut brings words together that are a window again, they are cut, too, until none is left. The verdict is that of
    the whole text. The scan runs beside the row, nothing is shuffled.
    """
    sc = docs.sparkSession.sparkContext
    blocks = [sc.broadcast(b) for b in item_blocks(benchmark)]

    @F.pandas_udf("contaminated boolean, cut string")
    def judged(texts: pd.Series) -> pd.DataFrame:
        texts = texts.tolist()
        verdict, cut, todo = [False] * len(texts), [None] * len(texts), {}
        for i, (n, hit, _) in enumerate(_marked(texts, blocks, window)):
            verdict[i] = contaminating(sum(hit), n, one_in)
            if any(hit) and not verdict[i]:
                todo[i] = hit
        while todo:
            for i, hit in todo.items():
                cut[i] = without_hits(texts[i] if cut[i] is None else cut[i], hit)
            again = _marked([cut[i] for i in todo], blocks, window)
            todo = {i: hit for i, (_, hit, _) in zip(todo, again) if any(hit)}
        return pd.DataFrame({"contaminated": verdict, "cut": pd.Series(cut, dtype=object)})

    d = docs.withColumn("__judged", judged(F.coalesce("text", F.lit("")))).where("not __judged.contaminated")
    if "n_chars" in docs.columns:
        n = F.when(F.col("__judged.cut").isNull(), F.col("n_chars")).otherwise(F.length("__judged.cut"))
        d = d.withColumn("n_chars", n.cast(docs.schema["n_chars"].dataType))
    return d.withColumn("text", F.coalesce("__judged.cut", "text")).select(*docs.columns)
