"""Interpolated modified Kneser-Ney bigram model, counted in Spark, and the scores it gives every document.

1. Documents are tokenised once into blocks: local word ids and the block's distinct words (``blocks``).
2. Each block sends its distinct bigrams with their counts to the bucket of the bigram's hash. A bucket keeps its bigrams as
   sorted hash arrays in a file that it maps into memory, looks up the total of every bigram a block has sent and returns
   totals in the block's own order. What it knows of single words (types by count, continuations) goes on to the buckets of
   the words.
3. Each block sends its distinct words with their counts to the buckets of the words. These sum up what blocks and bigram
   buckets have sent into sorted hash arrays, mapped the same way, and answer each block in its own order.
4. Each block meets its answers again and scores its documents.

Nothing of the model is gathered in one place: a bucket holds a fixed share of the bigrams or words, whatever a word's
frequency, and there are as many buckets as the bytes of all blocks ask for. Blocks send at most one message a bucket and
none without content, so there are never more messages than bigrams.

Words are known by 40 bits of a hash in bigrams (64 bits elsewhere): of V words some V * V / 2^41 pairs share their 40 bits
and with them their followers, 45 pairs at 10 million words.

Defined cases: null texts are empty and hold the end token alone; null doc_ids count as the text ``null``; repeated rows
count as often as they stand; an empty training set gives uniform scores; an empty table gives an empty result.
"""

from __future__ import annotations

import os
import tempfile
import uuid

import numpy as np
import pandas as pd
import xxhash
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from provloom.llm.common import arrow_batch, free, keyed, space_words, spill

END = b"\n"  # can't be a word
BLOCK = "block long, ids binary, nulls binary, train binary, lengths binary, tokens binary, words binary"
#: kind 0: a block's words or bigrams; 1: what bigram buckets know of words; 2: answers to a block; 3: numbers for all.
MESSAGE = "kind int, bucket int, block long, blob binary, a long, b long, c long, d long, e long"
#: Bits of a word in a bigram, and the word that stands before a document.
WORD_BITS = 40
_START = np.uint64(1)
#: Characters of a block of documents, and bytes of spilled blocks for each bucket.
BLOCK_CHARS, BUCKET_BYTES = 6_000_000, 8_000_000


def word_hash(word: bytes) -> int:
    return xxhash.xxh3_64_intdigest(word)


def pack(a: np.ndarray) -> bytes:
    """Byte planes, compressed: high bytes of small numbers cost next to nothing."""
    a = np.ascontiguousarray(a)
    return zstandard.compress(a.view(np.uint8).reshape(len(a), -1).T.tobytes() if len(a) else b"", 1)


def unpack(b: bytes, kind: str) -> np.ndarray:
    raw = np.frombuffer(zstandard.decompress(b), np.uint8)
    width = np.dtype(kind).itemsize
    return np.ascontiguousarray(raw.reshape(width, -1).T).view(kind).ravel() if len(raw) else np.zeros(0, kind)


class HashArrays:
    """Sorted keys with rows of values in one file, mapped into memory; the file goes when the maps are open."""

    def __init__(self, keys: np.ndarray, values: np.ndarray):
        values = values if values.ndim == 2 else values[:, None]
        fd, path = tempfile.mkstemp(prefix="kn-")  # of this task alone
        with os.fdopen(fd, "wb") as f:
            f.write(keys.astype("<u8").tobytes())
            f.write(np.ascontiguousarray(values, "<u8").tobytes())
        n, self.columns = len(keys), values.shape[1]
        self.keys = np.memmap(path, "<u8", "r", 0, (n,)) if n else keys
        self.values = np.memmap(path, "<u8", "r", 8 * n, values.shape) if n else values
        os.unlink(path)

    def get(self, keys: np.ndarray) -> np.ndarray:
        """Rows of values by key, 0 where there is none."""
        if not len(self.keys):
            return np.zeros((len(keys), self.columns), np.uint64)
        at = np.minimum(np.searchsorted(self.keys, keys), len(self.keys) - 1)
        return np.where((self.keys[at] == keys)[:, None], self.values[at], 0)


def add_up(keys: np.ndarray, values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct keys and the sums of their rows of values."""
    order = np.argsort(keys, kind="stable")
    keys, values = keys[order], values[order]
    first = np.flatnonzero(np.concatenate(([True], keys[1:] != keys[:-1]))) if len(keys) else np.zeros(0, np.int64)
    return keys[first], np.add.reduceat(values, first, axis=0) if len(keys) else values


def blocks(docs: DataFrame) -> DataFrame:
    """(block, ids, train, lengths, tokens, words): documents in a row, tokens as places in words (sorted hashes)."""

    def run(batches):
        now, size = [], 0
        for p in batches:
            for doc_id, train, text in zip(p.column("doc_id").to_pylist(), p.column("train").to_pylist(), p.column("text").to_pylist()):
                now.append((doc_id, train, text))
                size += len(text) + 1
                if size > BLOCK_CHARS:
                    yield block(now)
                    now, size = [], 0
        if now:
            yield block(now)

    def block(rows):
        places: dict[bytes, int] = {}
        tokens, lengths = [], []
        for _, _, text in rows:
            words = space_words(text)
            tokens += [places.setdefault(w, len(places)) for w in words]
            tokens.append(places.setdefault(END, len(places)))
            lengths.append(len(words) + 1)
        h = np.fromiter(map(word_hash, places), np.uint64, len(places))
        words, inverse = np.unique(h, return_inverse=True)
        t = inverse[np.array(tokens, np.int64)].astype("<u4")
        ids = np.array([x or 0 for x, _, _ in rows], "<i8")
        nulls = np.array([x is None for x, _, _ in rows], np.uint8)
        train = np.array([x for _, x, _ in rows], np.uint8)
        return arrow_batch([(uuid.uuid4().int >> 65, ids.tobytes(), nulls.tobytes(), train.tobytes(), np.array(lengths, "<u4").tobytes(), pack(t), pack(words))], BLOCK)

    held = F.pmod(F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit("null")).cast("binary")), F.lit(10)) == 0
    return keyed(docs).withColumn("train", ~held).mapInArrow(run, BLOCK)


def _bigrams(words: np.ndarray, tokens: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct bigrams in the order of the words' places: (place before + 1 or 0 at a start, place), and which one each token ends."""
    before = np.empty_like(tokens)
    before[1:] = tokens[:-1] + 1
    before[np.concatenate(([0], np.cumsum(lengths)[:-1])).astype(np.int64)] = 0
    keys, inverse = np.unique(before * (len(words) + 1) + tokens, return_inverse=True)
    return keys // (len(words) + 1), keys % (len(words) + 1), inverse


def _short(words: np.ndarray) -> np.ndarray:
    return words >> np.uint64(64 - WORD_BITS)


def _sides(words: np.ndarray, first: np.ndarray, second: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The hashes of WORD_BITS of the words of bigrams."""
    short = np.concatenate(([_START], _short(words)))
    return short[first], short[second + 1]


def _joined(first: np.ndarray, second: np.ndarray) -> np.ndarray:
    """One 64-bit hash of two words, for equality inside a bucket."""
    return _mix(_mix(first) * np.uint64(0x9E3779B97F4A7C15) + second)


def _narrow(a: np.ndarray) -> bytes:
    """Numbers of WORD_BITS without their empty bytes, by byte planes."""
    k = WORD_BITS // 8
    return zstandard.compress(np.ascontiguousarray(a.astype("<u8").view(np.uint8).reshape(len(a), 8)[:, :k].T).tobytes() if len(a) else b"", 1)


def _wide(b: bytes) -> np.ndarray:
    planes = np.frombuffer(zstandard.decompress(b), np.uint8).reshape(WORD_BITS // 8, -1)
    out = np.zeros((planes.shape[1], 8), np.uint8)
    out[:, : len(planes)] = planes.T
    return out.view("<u8").ravel()


def _parts(*blobs: bytes) -> bytes:
    return b"".join(x for b in blobs for x in (len(b).to_bytes(8, "little"), b))


def _of_parts(blob: bytes) -> list[bytes]:
    out, at = [], 0
    while at < len(blob):
        n = int.from_bytes(blob[at : at + 8], "little")
        out.append(blob[at + 8 : at + 8 + n])
        at += 8 + n
    return out


def _open(row) -> tuple:
    lengths = np.frombuffer(row["lengths"], "<u4").astype(np.int64)
    train = np.repeat(np.frombuffer(row["train"], np.uint8).astype(bool), lengths)
    return unpack(row["words"], "<u8"), unpack(row["tokens"], "<u4").astype(np.int64), lengths, train


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
    return x ^ (x >> np.uint64(33))


def _count(values: np.ndarray, mask: np.ndarray, n: int) -> np.ndarray:
    return np.bincount(values[mask], minlength=n).astype("<u4")


def _dealt(h: np.ndarray, buckets: int):
    """(bucket, places) of those that get something."""
    b = (_mix(h) % np.uint64(buckets)).astype(np.int64)
    order = np.argsort(b, kind="stable")
    cuts = np.searchsorted(b[order], np.arange(buckets + 1))
    return [(k, order[cuts[k] : cuts[k + 1]]) for k in np.flatnonzero(np.diff(cuts)).tolist()]


def sent(table: DataFrame, buckets: int, of_words: bool) -> DataFrame:
    """Messages of kind 0: the distinct words or bigrams of each block with their training counts, by bucket."""

    def run(batches):
        for p in batches:
            for row in p.to_pylist():
                words, tokens, lengths, train = _open(row)
                if of_words:
                    c = _count(tokens, train, len(words))
                    out = [(0, k, row["block"], _parts(pack(np.diff(words[at], prepend=np.uint64(0))), pack(c[at]))) for k, at in _dealt(_short(words), buckets)]
                else:
                    one, two, inverse = _bigrams(words, tokens, lengths)
                    one, two = _sides(words, one, two)
                    c = _count(inverse, train, len(one))
                    out = [(0, k, row["block"], _parts(pack(np.diff(one[at], prepend=np.uint64(0))), _narrow(two[at]), pack(c[at]))) for k, at in _dealt(_joined(one, two), buckets)]
                yield arrow_batch([(*m, 0, 0, 0, 0, 0) for m in out], MESSAGE)

    return table.mapInArrow(run, MESSAGE)


def _frame(rows: list[tuple]) -> pd.DataFrame:
    return pd.DataFrame([(*r, *[0] * (9 - len(r))) for r in rows], columns=[x.split()[0] for x in MESSAGE.split(", ")])


def count_bigrams(messages: DataFrame, buckets: int) -> DataFrame:
    """Messages of the bigram buckets: totals of a block's bigrams (2), sums of words for the buckets of words (1), counts of counts (3)."""

    def run(key, p):
        got = [_of_parts(x) for x in p["blob"]]
        one = np.concatenate([np.cumsum(unpack(x, "<u8"), dtype=np.uint64) for x, _, _ in got])
        two = np.concatenate([_wide(x) for _, x, _ in got])
        c = np.concatenate([unpack(x, "<u4") for _, _, x in got]).astype(np.uint64)
        every, seen = _joined(one, two), c > 0
        keys, at, inverse = np.unique(every[seen], return_index=True, return_inverse=True)
        total = np.bincount(inverse, c[seen], len(keys)).astype(np.uint64)
        model = HashArrays(keys, total)
        rows, lo = [], 0
        for b, (_, _, x) in zip(p["block"], got):
            n = len(unpack(x, "<u4"))
            rows.append((2, int(key[0]), int(b), pack(model.get(every[lo : lo + n])[:, 0])))
            lo += n
        n = len(keys)
        # of each first word: tokens, types seen once, twice, more often
        sums = np.stack([total, total == 1, total == 2, total >= 3], axis=1).astype(np.uint64)
        ctx, sums = add_up(one[seen][at], sums)
        # of each second word: types
        last, follows = np.unique(two[seen][at], return_counts=True)
        both = np.zeros((len(ctx) + len(last), 5), np.uint64)
        both[: len(ctx), :4], both[len(ctx) :, 4] = sums, follows
        word, sums = add_up(np.concatenate([ctx, last]), both)
        rows += [(1, k, 0, _parts(_narrow(word[at]), pack(sums[at].ravel()))) for k, at in _dealt(word, buckets)]
        rows.append((3, 0, 0, None, *(int((total == k).sum()) for k in (1, 2, 3, 4)), n))
        return _frame(rows)

    return messages.groupBy("bucket").applyInPandas(run, MESSAGE)


def sum_words(messages: DataFrame) -> DataFrame:
    """Messages of the buckets of words: count, bigram sums and continuations of a block's words (2); tokens, types (3, bucket 1),
    words by continuations (3, bucket 2), the sums of the document start (3, bucket 3)."""

    def run(key, p):
        by = p["kind"].to_numpy()
        blocks_, own, counts = p.loc[by == 0, "block"].tolist(), [], []
        for x in p.loc[by == 0, "blob"]:
            h, c = _of_parts(x)
            own.append(np.cumsum(unpack(h, "<u8"), dtype=np.uint64))
            counts.append(unpack(c, "<u4"))
        none = [np.zeros(0, np.uint64)]
        words, n = add_up(np.concatenate(own + none), np.concatenate(counts + none).astype(np.uint64).reshape(-1, 1))
        short, sums = [], []
        for x in p.loc[by == 1, "blob"]:
            h, v = _of_parts(x)
            short.append(_wide(h))
            sums.append(unpack(v, "<u8").reshape(-1, 5))
        short, sums = add_up(np.concatenate(short + none), np.concatenate([*sums, np.zeros((0, 5), np.uint64)]))
        stats = HashArrays(words, np.concatenate([n, HashArrays(short, sums).get(_short(words))], axis=1))
        rows = [(2, int(key[0]), int(b), _parts(*(pack(x) for x in stats.get(h).T))) for b, h in zip(blocks_, own)]
        rows.append((3, 1, 0, None, int(n.sum()), int((n > 0).sum())))
        types = sums[:, 4]
        rows.append((3, 2, 0, None, *(int((types == k).sum()) for k in (1, 2, 3, 4)), int((types >= 3).sum())))
        rows += [(3, 3, 0, None, *(int(x) for x in sums[i])) for i in np.flatnonzero(short == _START)]
        return _frame(rows)

    return messages.groupBy("bucket").applyInPandas(run, MESSAGE)


def discounts(n1: int, n2: int, n3: int, n4: int) -> tuple[float, float, float]:
    """The three discounts from counts of counts; where some are missing, plain ones that stay below their counts."""
    if min(n1, n2, n3, n4) <= 0:
        return 0.5, 0.75, 0.9
    y = n1 / (n1 + 2 * n2)
    return tuple(min(max(k - (k + 1) * y * b / a, 0.0), k - 0.01) for k, a, b in ((1, n1, n2), (2, n2, n3), (3, n3, n4)))


def _less(c: np.ndarray, d: tuple) -> np.ndarray:
    return np.select([c >= 3, c == 2, c == 1], [d[2], d[1], d[0]], 0.0)


def _numbers(messages: DataFrame) -> dict[int, tuple]:
    """The numbers for all, by what they tell: a row each."""
    total = messages.where("kind = 3").groupBy("bucket").agg(*(F.sum(x).alias(x) for x in "abcde")).collect()
    return {r["bucket"]: tuple(r)[1:] for r in total}


def score(docs: DataFrame, add: float = 0.1) -> DataFrame:
    """Per row: doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score (log10)."""
    spark = docs.sparkSession
    table = spill(blocks(docs))
    held = table.agg(F.coalesce(F.sum(F.octet_length("tokens") + F.octet_length("words")), F.lit(0))).first()[0]
    buckets = max(8, int(spark.conf.get("spark.sql.shuffle.partitions")), held // BUCKET_BYTES)
    counted = spill(count_bigrams(sent(table, buckets, False), buckets))
    free(spark)
    coc = _numbers(counted).get(0, (0,) * 5)
    summed = spill(sum_words(sent(table, buckets, True).unionByName(counted.where("kind = 1"))))
    free(spark)
    numbers = _numbers(summed)
    two, types = discounts(*coc[:4]), coc[4]
    big_n, vocabulary = numbers.get(1, (0, 0))[:2]
    cont = numbers.get(2, (0,) * 5)
    one = discounts(*cont[:4])
    spared = (one[0] * cont[0] + one[1] * cont[1] + one[2] * cont[4]) / types if types else 1.0
    begin = np.array(numbers.get(3, (0,) * 5), np.float64)  # the start of a document counts as a word

    def rate(left, right):
        row = left.iloc[0].to_dict()
        words, tokens, lengths, _ = _open(row)
        first, second, inverse = _bigrams(words, tokens, lengths)
        c2 = np.zeros(len(first))
        replies = dict(zip(right.loc[right["of"] == 0, "bucket"].tolist(), right.loc[right["of"] == 0, "blob"]))
        for k, at in _dealt(_joined(*_sides(words, first, second)), buckets):
            c2[at] = unpack(replies[k], "<u8")
        stat = np.zeros((len(words), 6))
        replies = dict(zip(right.loc[right["of"] == 1, "bucket"].tolist(), right.loc[right["of"] == 1, "blob"]))
        for k, at in _dealt(_short(words), buckets):
            for j, x in enumerate(_of_parts(replies[k])):
                stat[at, j] = unpack(x, "<u8")
        lower = (np.maximum(stat[:, 5] - _less(stat[:, 5], one), 0) / types if types else 0) + spared / (vocabulary + 1)
        # everything is computed once for each distinct bigram
        ctx = np.concatenate((begin[None, :4], stat[:, 1:5]))[first]
        seen = np.maximum(ctx[:, 0], 1)
        back = np.where(ctx[:, 0] > 0, ctx[:, 1:] @ np.array(two) / seen, 1.0)
        p = np.log10(np.where(ctx[:, 0] > 0, (c2 - _less(c2, two)) / seen, 0.0) + back * lower[second])
        base = np.log10((stat[:, 0] + add) / (big_n + add * (vocabulary + 1)))
        n = len(lengths)
        of = np.repeat(np.arange(n), lengths)
        ids = pd.array(np.frombuffer(row["ids"], "<i8"), "Int64")
        ids[np.frombuffer(row["nulls"], np.uint8).astype(bool)] = pd.NA
        return pd.DataFrame({
            "doc_id": ids, "held_out": np.frombuffer(row["train"], np.uint8) == 0, "n_tokens": lengths,
            "n_known": np.bincount(of, stat[tokens, 0] > 0, n).astype(np.int64), "train_tokens": big_n,
            "base_score": np.bincount(of, base[tokens], n), "score": np.bincount(of, p[inverse], n),
        })

    to_blocks = lambda t, of: t.where("kind = 2").select("block", "bucket", "blob", F.lit(of).alias("of"))
    answers = to_blocks(counted, 0).unionByName(to_blocks(summed, 1))
    return table.groupBy("block").cogroup(answers.groupBy("block")).applyInPandas(
        rate, "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"
    )


def perplexity(scored: DataFrame) -> DataFrame:
    """Perplexity of the held-out documents by the model and by the base measure."""
    held = scored.where("held_out")
    return held.agg(F.pow(F.lit(10.0), -F.sum("score") / F.sum("n_tokens")).alias("model"), F.pow(F.lit(10.0), -F.sum("base_score") / F.sum("n_tokens")).alias("base"))
