"""Token-id shards with a minimal perfect hash index.

A shard is one row of a Parquet table: ids of consecutive documents without separators (payload, uint16 where all ids
fit, else uint32, little endian), and an index of its keys. The index is a minimal perfect hash by displaced buckets: a
key's bucket holds a seed, and bucket, seed and key give a slot of its own, in which a fingerprint of the key and the
document's first id stand. Access by key costs one seed and one slot. A key that isn't in the shard is told by its
fingerprint (64 bits).

Shards lie in ascending order of doc_id: input is range-partitioned and sorted, and each task cuts its rows into shards
of about ``shard_ids`` ids, so a task holds one shard at a time.

Defined cases: null texts are empty and hold the end id alone; rows of null doc_id stand before all others and have no
keyed access; of repeated doc_ids each row
keeps its own ids, ordered by text, and access by key gives the first; an empty table makes no shard.
"""

from __future__ import annotations

import zlib

import numpy as np
import pandas as pd
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from provloom.llm.common import arrow_batch, keyed, spill
from provloom.llm.tokens import END_ID, default_path, encoder

SHARD = "part int, shard int, first_id long, n_docs long, n_ids long, width int, payload binary, seeds binary, fingerprints binary, starts binary, lengths binary, keys binary, order binary, n_null int"
DIGEST = "part int, doc_id long, local long, n_tokens long, ids_crc32 long"
KEYS_PER_BUCKET = 4


def _hash(key: int, seed: int) -> int:
    return xxhash.xxh3_64_intdigest(int(key).to_bytes(8, "little", signed=True), seed)


def perfect_hash(keys: list[int]) -> tuple[np.ndarray, np.ndarray]:
    """seeds by bucket, slot by key: distinct keys get the slots 0..n-1, one each."""
    n = len(keys)
    buckets: list[list[int]] = [[] for _ in range(-(-n // KEYS_PER_BUCKET) or 1)]
    for i, k in enumerate(keys):
        buckets[_hash(k, 0) % len(buckets)].append(i)
    seeds, slots, taken = np.zeros(len(buckets), "<u4"), np.zeros(n, "<u4"), bytearray(n)
    for b in sorted(range(len(buckets)), key=lambda b: -len(buckets[b])):
        seed = 1
        while buckets[b]:
            want = [_hash(keys[i], seed) % n for i in buckets[b]]
            if len(set(want)) == len(want) and not any(taken[s] for s in want):
                for i, s in zip(buckets[b], want):
                    slots[i], taken[s] = s, 1
                seeds[b] = seed
                break
            seed += 1
    return seeds, slots


class Shard:
    """Keyed access to one shard row."""

    def __init__(self, row):
        self.ids = np.frombuffer(row["payload"], f"<u{row['width']}")
        self.seeds = np.frombuffer(row["seeds"], "<u4")
        self.fingerprints = np.frombuffer(row["fingerprints"], "<u8")
        self.starts = np.frombuffer(row["starts"], "<u8")
        self.lengths = np.frombuffer(row["lengths"], "<u8")

    def locate(self, key: int) -> tuple[int, int] | None:
        """First id and number of ids of the document, None if the key isn't here."""
        n = len(self.fingerprints)
        if not n:
            return None
        seed = int(self.seeds[_hash(key, 0) % len(self.seeds)])
        slot = _hash(key, seed) % n
        if int(self.fingerprints[slot]) != _hash(key, 1 << 40):
            return None
        return int(self.starts[slot]), int(self.lengths[slot])

    def get(self, key: int) -> np.ndarray | None:
        at = self.locate(key)
        return None if at is None else self.ids[at[0] : at[0] + at[1]].astype("<u4")


def _shard_row(part: int, shard: int, base: int, docs: list[tuple[int, bytes]]) -> tuple:
    ids = np.frombuffer(b"".join(x for _, x in docs), "<u4")
    width = 2 if not len(ids) or ids.max() < 1 << 16 else 4
    lengths = np.array([len(x) // 4 for _, x in docs], "<u8")
    starts = np.concatenate(([0], np.cumsum(lengths)[:-1])).astype("<u8")
    first: dict[int, int] = {}
    for i, (k, _) in enumerate(docs):
        if k is not None:
            first.setdefault(k, i)
    keys = list(first)
    seeds, slots = perfect_hash(keys)
    at = np.fromiter((first[k] for k in keys), np.int64, len(keys))
    fp, st, ln = np.zeros(len(keys), "<u8"), np.zeros(len(keys), "<u8"), np.zeros(len(keys), "<u8")
    fp[slots] = np.fromiter((_hash(k, 1 << 40) for k in keys), np.uint64, len(keys))
    st[slots], ln[slots] = starts[at], lengths[at]
    every = np.array([k for k, _ in docs if k is not None], "<i8")
    return part, shard, base, len(docs), len(ids), width, ids.astype(f"<u{width}").tobytes(), seeds.tobytes(), fp.tobytes(), st.tobytes(), ln.tobytes(), every.tobytes(), lengths.astype("<u8").tobytes(), len(docs) - len(every)


def write_shards(docs: DataFrame, path: str | None = None, tokenizer: str | None = None, end: int = END_ID, shard_ids: int = 2_000_000, parts: int | None = None) -> DataFrame:
    """Encodes docs and writes the shard table to path (None: the shared folder); returns it as read back."""
    tokenizer = tokenizer or default_path()
    parts = parts or max(1, int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")))

    def run(batches):
        enc, part, shard, base, now, size = encoder(tokenizer), TaskContext.get().partitionId(), 0, 0, [], 0
        for b in batches:
            for doc_id, text in zip(b.column("doc_id").to_pylist(), b.column("text").to_pylist()):
                x = enc.payload(text, end)
                now.append((doc_id, x))
                size += len(x) // 4
                if size >= shard_ids:
                    yield arrow_batch([_shard_row(part, shard, base, now)], SHARD)
                    shard, base, now, size = shard + 1, base + size, [], 0
        if now:
            yield arrow_batch([_shard_row(part, shard, base, now)], SHARD)

    # the start of the text deals out rows of one doc_id, null too
    d = keyed(docs).repartitionByRange(parts, F.col("doc_id").asc_nulls_first(), F.substring("text", 1, 24))
    table = d.sortWithinPartitions(F.col("doc_id").asc_nulls_first(), "text").mapInArrow(run, SHARD)
    if path is None:
        return spill(table)
    table.write.option("compression", "zstd").parquet(path)
    return docs.sparkSession.read.parquet(path)


def read_digest(shards: DataFrame) -> DataFrame:
    """Per document, from the shards: doc_id, start, n_tokens, ids_crc32, through the index for each key."""

    def run(batches):
        for b in batches:
            rows = []
            for row in b.to_pylist():
                s, at, seen = Shard(row), 0, set()
                keys = [None] * row["n_null"] + np.frombuffer(row["keys"], "<i8").tolist()
                for key, n in zip(keys, np.frombuffer(row["order"], "<u8").tolist()):
                    if key is not None and key not in seen and s.locate(key) != (at, n):
                        raise ValueError(f"the index misplaces document {key}")
                    seen.add(key)
                    rows.append((row["part"], key, row["first_id"] + at, n, zlib.crc32(s.ids[at : at + n].astype("<u4").tobytes())))
                    at += n
            yield arrow_batch(rows, DIGEST)

    totals = shards.groupBy("part").agg(F.sum("n_ids").alias("ids"))
    before = totals.select("part", (F.sum("ids").over(Window.orderBy("part")) - F.col("ids")).alias("base"))
    found = shards.mapInArrow(run, DIGEST)
    # one row a range partition of the writer: as small as its task list
    found = found.join(F.broadcast(before), "part")
    return found.select("doc_id", (F.col("base") + F.col("local")).alias("start"), "n_tokens", "ids_crc32")


def lookup(shards: DataFrame, keys: list[int]) -> dict[int, list[int]]:
    """ids of single documents by key; only shards whose range can hold a key are opened."""
    wanted = sorted(set(keys))

    def run(batches):
        for p in batches:
            rows = []
            for row in p.to_dict("records"):
                s = Shard(row)
                rows += [(k, s.get(k).tolist()) for k in wanted if s.locate(k) is not None]
            yield pd.DataFrame(rows, columns=["doc_id", "ids"])

    return {r["doc_id"]: list(r["ids"]) for r in shards.mapInPandas(run, "doc_id long, ids array<long>").collect()}
