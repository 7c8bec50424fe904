"""Removal of repeated byte strings, by hash-compared suffix sorting of anchored suffixes.

Every 50-byte window has an anchor: the 16 bytes in it whose hash is smallest (leftmost of equals). Equal windows have
their anchors at the same place, so windows need only be compared among occurrences of one anchor.

1. Documents lie in blocks. A block sends the distinct anchor hashes it holds to the hashes' buckets; a bucket answers
   which of them stand in two documents or more. This leaves the anchors of repeated text.
2. For those, a block sends each different context (the bytes of the anchor's windows) once, with the smallest doc_id
   that holds it. A bucket sorts the suffixes that begin at equal anchors: polynomial prefix hashes and a binary search
   find the common extension of two suffixes, so a comparison takes logarithmic time, in a mergesort over all anchors at
   once. Suffix order and common extensions to the left split the windows into classes of equal strings, checked byte
   by byte; the bucket answers, window by window, whether a document with a smaller doc_id holds it.
3. Blocks mark the windows and cut the bytes they cover.

A block sends one row to a bucket, so hot passages cost a bucket one context per block. Text is shuffled once.

Defined cases: null texts are empty; texts under 50 bytes lose nothing; rows of equal doc_id don't remove from each
other; repeated rows give repeated result rows; null doc_ids are the smallest; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pandas as pd
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from provloom.llm.common import keyed
from provloom.llm.kneser_ney import pack, unpack

K = 16
#: Bytes handled at once: temporary arrays take some fifty times that.
CHUNK = 1 << 20
#: Bytes of text in a block, about: a block, and the contexts sent to a bucket, fit a worker's memory at any size of the table.
BLOCK_BYTES = 12_000_000
#: Stands for null doc_ids, and sorts before all others.
NULL_ID = -(1 << 63)
_LOW = np.uint64(0xFFFFFFFF)
_BASE = np.uint64(0x9E3779B97F4A7C15)
_BYTE = (np.arange(1, 257, dtype=np.uint64) * np.uint64(0xD1342543DE82EF95)) ^ np.uint64(0x632BE59BD9B4E019)


def _gram_hashes(buf: np.ndarray) -> np.ndarray:
    """A 64-bit hash of the 16 bytes at each place."""
    n = len(buf) - K + 1
    raw = buf.tobytes()
    a = np.ndarray((n,), "<u8", raw, 0, (1,))
    b = np.ndarray((n,), "<u8", raw, 8, (1,))
    h = a * _BASE
    h ^= h >> np.uint64(32)
    h += b
    h *= np.uint64(0xFF51AFD7ED558CCD)
    h ^= h >> np.uint64(29)
    h *= np.uint64(0xC4CEB9FE1A85EC53)
    h ^= h >> np.uint64(32)
    return h


class Anchors:
    """Anchors of the windows of a run of documents: hash, place, first and last window start, document."""

    def __init__(self, texts: list[bytes], width: int):
        self.width = width
        self.buf = np.frombuffer(b"".join(texts), np.uint8)
        self.lengths = np.array([len(t) for t in texts], np.int64)
        self.begins = np.concatenate(([0], np.cumsum(self.lengths)[:-1])).astype(np.int64)
        n = len(self.buf)
        if n < width:
            self.at = self.lo = self.hi = self.doc = np.zeros(0, np.int64)
            self.hash = np.zeros(0, np.uint64)
            return
        h = _gram_hashes(self.buf)
        key = (h & ~_LOW) | np.arange(len(h), dtype=np.uint64)
        span, step, m = width - K + 1, 1, key
        while step * 2 <= span:
            m = np.minimum(m[: len(m) - step], m[step:])
            step *= 2
        m = np.minimum(m[: n - width + 1], m[span - step : span - step + n - width + 1])
        # windows over the end of a document are none; empty texts end where they begin, and count once
        ends = np.zeros(n + 1, np.int32)
        ends[self.begins] = 1
        ends = np.cumsum(ends[:n], dtype=np.int32)
        ok = ends[: n - width + 1] == ends[width - 1 :]
        starts, place = np.flatnonzero(ok), (m[ok] & _LOW).astype(np.int64)
        new = np.flatnonzero(np.diff(place, prepend=-1))
        self.at = place[new]
        self.lo = starts[new]
        self.hi = starts[np.concatenate((new[1:], [len(place)])) - 1] if len(new) else starts[:0]
        self.hash = h[self.at]
        self.doc = np.searchsorted(self.begins, self.at, side="right") - 1  # an empty text begins where the next one does
        self.padded = np.concatenate((np.zeros(width - K, np.uint8), self.buf, np.zeros(width, np.uint8)))

    def contexts(self, pick: np.ndarray) -> np.ndarray:
        """Bytes of the windows of the anchors picked, placed so that the anchor stands at width - K, zero elsewhere."""
        w, left = self.width, self.width - K
        at, lo, hi = self.at[pick], self.lo[pick], self.hi[pick]
        cols, begin, end = np.arange(left + w, dtype=np.int16), (lo - at + left).astype(np.int16)[:, None], (hi + w - at + left).astype(np.int16)[:, None]
        out = np.lib.stride_tricks.sliding_window_view(self.padded, left + w)[at]
        out *= (cols >= begin) & (cols < end)
        ends = np.stack([at - hi, at - lo], 1).astype(np.uint8)  # least and greatest distance of a window start to the left
        return np.concatenate([out, ends], 1)


def _chunks(texts: list[bytes]):
    lo = size = 0
    for i, t in enumerate(texts):
        if size and size + len(t) > CHUNK:
            yield lo, i
            lo, size = i, 0
        size += len(t)
    if lo < len(texts):
        yield lo, len(texts)


def _rows(p: pd.DataFrame) -> tuple[list, list[bytes]]:
    """doc_ids and texts of a block, in an order of their own."""
    ids = p["doc_id"].tolist()
    texts = [t.encode("utf-8", "surrogatepass") for t in p["text"]]
    order = sorted(range(len(ids)), key=lambda i: (ids[i], texts[i]))
    return [ids[i] for i in order], [texts[i] for i in order]


def _bucket(h: np.ndarray, buckets: int) -> np.ndarray:
    return ((h >> np.uint64(11)) % np.uint64(buckets)).astype(np.int64)


def _by_bucket(h: np.ndarray, buckets: int):
    b = _bucket(h, buckets)
    order = np.argsort(b, kind="stable")
    cuts = np.searchsorted(b[order], np.arange(buckets + 1))
    for k in range(buckets):
        if cuts[k] < cuts[k + 1]:
            yield k, order[cuts[k] : cuts[k + 1]]


def _distinct_hashes(ids: list, texts: list[bytes], width: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct anchor hashes of a block, and whether two documents hold them."""
    hashes, docs = [], []
    for lo, hi in _chunks(texts):
        a = Anchors(texts[lo:hi], width)
        hashes.append(a.hash)
        docs.append(np.array(ids[lo:hi], np.int64)[a.doc] if len(a.doc) else np.zeros(0, np.int64))
    h, d = np.concatenate([np.zeros(0, np.uint64), *hashes]), np.concatenate([np.zeros(0, np.int64), *docs])
    order = np.argsort(h, kind="stable")
    h, d = h[order], d[order]
    new = np.flatnonzero(np.diff(h, prepend=~h[:1])) if len(h) else np.zeros(0, np.int64)
    several = np.minimum.reduceat(d, new) != np.maximum.reduceat(d, new) if len(h) else np.zeros(0, bool)
    return h[new], several


def _eights(rows: np.ndarray) -> np.ndarray:
    """The columns of byte rows taken eight at a time, each as one array of 64-bit numbers."""
    wide = np.zeros((len(rows), -(-rows.shape[1] // 8) * 8), np.uint8)
    wide[:, : rows.shape[1]] = rows
    return np.ascontiguousarray(wide.view("<u8").T)


def _block_contexts(ids: list, texts: list[bytes], repeated: np.ndarray, width: int):
    """Distinct contexts of the block's repeated anchors: (hash, context, least doc), and each occurrence's context."""
    got, hs, ds, where = [], [], [], []
    for lo, hi in _chunks(texts):
        a = Anchors(texts[lo:hi], width)
        i = np.minimum(np.searchsorted(repeated, a.hash), max(len(repeated) - 1, 0))
        pick = np.flatnonzero(repeated[i] == a.hash) if len(repeated) and len(a.hash) else np.zeros(0, np.int64)
        for at in range(0, len(pick), 20_000):  # wide temporaries
            got.append(a.contexts(pick[at : at + 20_000]))
        hs.append(a.hash[pick])
        ds.append(a.doc[pick] + lo)
        where.append(np.stack([a.lo[pick] - a.begins[a.doc[pick]], a.hi[pick] - a.begins[a.doc[pick]], a.at[pick] - a.begins[a.doc[pick]]], 1) if len(pick) else np.zeros((0, 3), np.int64))
    size = 2 * width - K + 2
    ctx = np.concatenate([np.zeros((0, size), np.uint8), *got])
    h, doc = np.concatenate([np.zeros(0, np.uint64), *hs]), np.concatenate([np.zeros(0, np.int64), *ds])
    where = np.concatenate([np.zeros((0, 3), np.int64), *where])
    row, eight = h.copy(), _eights(ctx)
    for c in eight:
        c = (c ^ (c >> np.uint64(31))) * np.uint64(0xFF51AFD7ED558CCD)
        row = row * _BASE + (c ^ (c >> np.uint64(29)))
    _, first, inverse = np.unique(row, return_index=True, return_inverse=True)
    same = first[inverse]
    differ = h[same] != h
    for c in eight:
        differ |= c[same] != c
    odd = np.flatnonzero(differ)
    for x in odd:  # contexts that only share a hash stand for themselves
        inverse[x] = len(first)
        first = np.append(first, x)
    least = np.full(len(first), np.iinfo(np.int64).max)
    np.minimum.at(least, inverse, np.array(ids, np.int64)[doc] if len(doc) else np.zeros(0, np.int64))
    return h[first], ctx[first], least, inverse, doc, where


def prefix_hashes(text: np.ndarray) -> np.ndarray:
    """Polynomial hashes of all prefixes of each row."""
    return np.ascontiguousarray(_prefixes(text).T)


def _prefixes(text: np.ndarray) -> np.ndarray:
    """The same with a row for each length."""
    out = np.zeros((text.shape[1] + 1, text.shape[0]), np.uint64)
    for j, column in enumerate(np.ascontiguousarray(text.T)):
        out[j + 1] = out[j] * _BASE + _BYTE[column]
    return out


def common_extension(p: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Length of the longest common prefix of rows a[i] and b[i], by binary search over prefix hashes."""
    lo, hi = np.zeros(len(a), np.int64), np.full(len(a), p.shape[1] - 1, np.int64)
    while (open_ := lo < hi).any():
        mid = (lo + hi + 1) >> 1
        same = p[a, mid] == p[b, mid]
        lo = np.where(open_ & same, mid, lo)
        hi = np.where(open_ & ~same, mid - 1, hi)
    return lo


def suffix_sort(text: np.ndarray, group: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Order of the rows by (group, text), and the common prefix of each with the one before (0 at a group's start).

    A mergesort from runs of one row; each pass merges all pairs of neighbouring runs of all groups at once: a row's new
    place is its own rank plus its rank in the other run, found by binary search with hash-compared suffixes. Rows of
    equal group come together first.
    """
    order = np.argsort(group, kind="stable")
    g = group[order]
    begins = np.flatnonzero(np.diff(g, prepend=g[:1] - np.int64(1))) if len(g) else np.zeros(0, np.int64)
    sizes = np.diff(np.concatenate((begins, [len(g)])))
    p, end = prefix_hashes(text), text.shape[1]
    rank = np.arange(len(g)) - np.repeat(begins, sizes)
    begin, size = np.repeat(begins, sizes), np.repeat(sizes, sizes)

    def less(x, y, or_equal):
        n = common_extension(p, x, y)
        at = np.minimum(n, end - 1)
        return np.where(n == end, or_equal, text[x, at] < text[y, at])

    run = 1
    while len(g) and (sizes > run).any():
        todo = np.flatnonzero(size > run)
        r, b, s = rank[todo], begin[todo], size[todo]
        pair = r // (2 * run) * (2 * run)
        right = r - pair >= run
        o_lo = np.minimum(np.where(right, pair, pair + run), s)
        o_hi = np.minimum(o_lo + run, np.where(right, pair + run, s))
        lo, hi = o_lo.copy(), o_hi.copy()
        me = order[todo]
        while (go := np.flatnonzero(lo < hi)).size:
            mid = (lo[go] + hi[go]) >> 1
            # the row at mid comes before me; equals of the left run come first
            before = less(order[b[go] + mid], me[go], right[go])
            lo[go] = np.where(before, mid + 1, lo[go])
            hi[go] = np.where(before, hi[go], mid)
        own = r - np.where(right, pair + run, pair)
        order[b + pair + own + (lo - o_lo)] = me
        run *= 2
    lcp = np.zeros(len(g), np.int64)
    if len(g) > 1:
        lcp[1:] = common_extension(p, order[:-1], order[1:])
        lcp[begins] = 0
    return order, lcp


def _repeated(x: np.ndarray) -> np.ndarray:
    """Of a sorted array, whether an element stands there twice or more."""
    as_before = np.zeros(len(x) + 1, bool)
    as_before[1:-1] = x[1:] == x[:-1]
    return as_before[1:] | as_before[:-1]


def decide(h: np.ndarray, ctx: np.ndarray, least: np.ndarray, width: int) -> np.ndarray:
    """Per context a bit mask: bit x tells that the window starting x bytes left of the anchor is in an earlier document."""
    left = width - K
    text, ends = ctx[:, : left + width], ctx[:, left + width :].astype(np.int64)
    _, group = np.unique(h, return_inverse=True)
    bits = np.zeros(len(h), np.uint64)
    several = np.flatnonzero(np.bincount(group)[group] > 1)
    if not len(several):
        return bits
    text, ends, group, least = text[several], ends[several], group[several], least[several]
    order, lcp = suffix_sort(np.ascontiguousarray(text[:, left:]), group)
    text, ends, least = text[order], ends[order], least[order]
    back = _prefixes(text[:, :left][:, ::-1])
    fresh = np.diff(group[order], prepend=-1) != 0
    got = np.zeros(len(order), np.uint64)
    for x in range(left + 1):
        part = np.cumsum(fresh | (lcp < width - x))
        ok = np.flatnonzero((ends[:, 0] <= x) & (x <= ends[:, 1]))
        ok = ok[_repeated(part[ok])]  # a row alone in its part equals no other
        key = part[ok].astype(np.uint64) * np.uint64(0xFF51AFD7ED558CCD) + back[x][ok] * _BASE
        by = np.argsort(key)
        by = by[_repeated(key[by])]
        ok, key = ok[by], key[by]
        if not len(ok):
            continue
        new = np.diff(key, prepend=~key[:1]) != 0
        window = text[:, left - x : left - x + width]
        again = np.flatnonzero(~new)
        # neighbours of one key that differ: a collision splits the class
        new[again] = (window[ok[again]] != window[ok[again - 1]]).any(1)
        first = np.flatnonzero(new)
        small = np.repeat(np.minimum.reduceat(least[ok], first), np.diff(np.concatenate((first, [len(ok)]))))
        got[ok] |= (small < least[ok]).astype(np.uint64) << np.uint64(x)
    bits[several[order]] = got
    return bits


def dedup(docs: DataFrame, width: int = 50) -> DataFrame:
    """Per row: doc_id, n_bytes, n_removed, n_spans, kept_sha256, kept (the remaining bytes)."""
    if not K <= width <= K + 63:
        raise ValueError(f"width must lie between {K} and {K + 63}")
    parts = max(1, int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    d = keyed(docs).withColumn("doc_id", F.coalesce("doc_id", F.lit(NULL_ID)))
    held = d.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    blocks = max(2 * parts, -(-held // BLOCK_BYTES))  # a block has a share of the bytes, however few partitions there are
    parts = buckets = -(-blocks // 2)
    d = d.withColumn("block", F.pmod(F.xxhash64("doc_id", "text"), F.lit(blocks)).cast("int"))
    d = d.repartition(parts, "block")
    sent = "bucket int, block int, kind int, blob binary"
    frame = lambda rows: pd.DataFrame(rows, columns=["bucket", "block", "kind", "blob"])

    def ask(key, p):
        h, several = _distinct_hashes(*_rows(p), width)
        rows = []
        for k, at in _by_bucket(h, buckets):
            body = pack(np.diff(h[at], prepend=np.uint64(0)))
            rows.append((k, int(key[0]), 0, len(body).to_bytes(8, "little") + body + zstandard.compress(np.packbits(several[at]).tobytes(), 1)))
        return frame(rows)

    def answer(key, p):
        hs, several = [], []
        for blob in p["blob"]:
            n = int.from_bytes(blob[:8], "little")
            hs.append(np.cumsum(unpack(blob[8 : 8 + n], "<u8"), dtype=np.uint64))
            several.append(np.unpackbits(np.frombuffer(zstandard.decompress(blob[8 + n :]), np.uint8), count=len(hs[-1])).astype(bool))
        _, inverse, count = np.unique(np.concatenate(hs), return_inverse=True, return_counts=True)
        more = count > 1
        more |= np.bincount(inverse, np.concatenate(several), len(count)) > 0
        rows, at = [], 0
        for b, h in zip(p["block"], hs):
            rows.append((int(key[0]), int(b), 1, pack(h[more[inverse[at : at + len(h)]]])))
            at += len(h)
        return frame(rows)

    def repeated_of(right):
        got = [unpack(x, "<u8") for x in right.loc[right["kind"] == 1, "blob"]]
        return np.sort(np.concatenate([np.zeros(0, np.uint64), *got]))

    def tell(key, left, right):
        if not len(left):
            return frame([])
        h, ctx, least, *_ = _block_contexts(*_rows(left), repeated_of(right), width)
        rows = []
        for k, at in _by_bucket(h, buckets):
            rows.append((k, int(key[0]), 2, h[at].astype("<u8").tobytes() + least[at].astype("<i8").tobytes() + zstandard.compress(ctx[at].tobytes(), 1)))
            rows[-1] = (*rows[-1][:3], len(at).to_bytes(8, "little") + rows[-1][3])
        return frame(rows)

    def judge(key, p):
        hs, ls, cs = [], [], []
        for blob in p["blob"]:
            n = int.from_bytes(blob[:8], "little")
            hs.append(np.frombuffer(blob, "<u8", n, 8))
            ls.append(np.frombuffer(blob, "<i8", n, 8 + 8 * n))
            cs.append(np.frombuffer(zstandard.decompress(blob[8 + 16 * n :]), np.uint8).reshape(n, -1))
        bits = decide(np.concatenate(hs), np.concatenate(cs), np.concatenate(ls), width)
        rows, at = [], 0
        for b, h in zip(p["block"], hs):
            rows.append((int(key[0]), int(b), 3, zstandard.compress(bits[at : at + len(h)].astype("<u8").tobytes(), 1)))
            at += len(h)
        return frame(rows)

    def cut(key, left, right):
        ids, texts = _rows(left)
        h, _, least, inverse, doc, where = _block_contexts(ids, texts, repeated_of(right), width)
        bits = np.zeros(len(h), np.uint64)
        replies = {int(k): x for k, x in zip(right.loc[right["kind"] == 3, "bucket"], right.loc[right["kind"] == 3, "blob"])}
        for k, at in _by_bucket(h, buckets):
            bits[at] = np.frombuffer(zstandard.decompress(replies[k]), "<u8")
        own = np.array(ids, np.int64)[doc] if len(doc) else doc
        every = own > least[inverse] if len(doc) else np.zeros(0, bool)
        begins = np.concatenate(([0], np.cumsum([len(t) + 1 for t in texts])))  # a spare byte between documents
        edge = np.zeros(begins[-1] + width + 1, np.int32)
        for x in range(width - K + 1):
            start = where[:, 2] - x
            hit = (where[:, 0] <= start) & (start <= where[:, 1]) & (every | ((bits[inverse] >> np.uint64(x)) & np.uint64(1)).astype(bool))
            s = begins[doc[hit]] + start[hit]
            np.add.at(edge, s, 1)
            np.add.at(edge, s + width, -1)
        gone = np.cumsum(edge) > 0
        rows = []
        for i, (doc_id, t) in enumerate(zip(ids, texts)):
            g = gone[begins[i] : begins[i] + len(t)]
            n = int(g.sum())
            keep = np.frombuffer(t, np.uint8)[~g].tobytes() if n else t
            spans = int(np.count_nonzero(np.diff(g.astype(np.int8), prepend=0) == 1)) if n else 0
            rows.append((doc_id if doc_id != NULL_ID else None, len(t), n, spans, hashlib.sha256(keep).hexdigest(), keep))
        return pd.DataFrame(rows, columns=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"]).astype({"doc_id": "Int64"})

    asked = d.groupBy("block").applyInPandas(ask, sent)
    found = asked.groupBy("bucket").applyInPandas(answer, sent)
    told = d.groupBy("block").cogroup(found.groupBy("block")).applyInPandas(tell, sent)
    judged = told.groupBy("bucket").applyInPandas(judge, sent)
    return d.groupBy("block").cogroup(found.unionByName(judged).groupBy("block")).applyInPandas(
        cut, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary"
    )
