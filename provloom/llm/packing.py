"""Packing into sequences by minimum bin slack.

Every document's ids are cut into full windows and a tail shorter than a window. Tails wait in a pool; the longest one
opens a bin, and a bitset subset-sum dynamic program over the multiset of the other lengths finds the fill closest to the
window; counts per length are traced back through its layers. The tails left at a task's end, less than a window in all
or without an exact fill, are cut where needed so that every sequence but the last is full and the last falls into
powers of two: nothing is padded.

Pools are bounded (``pool`` tails), tasks are independent, so nothing of the documents is shuffled; a count of
sequences per task gives the numbers. Defined cases: null texts hold the end id alone; null doc_ids stay null; repeated rows are packed as often
as they stand; an empty table gives no piece.
"""

from __future__ import annotations

import zlib
from collections import defaultdict

from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from provloom.llm.common import arrow_batch, keyed, spill
from provloom.llm.tokens import END_ID, default_path, encoder

PIECE = "part int, seq long, doc_id long, start long, length long, ids_crc32 long, doc_tokens long, offset long"


def best_fill(counts: dict[int, int], capacity: int) -> dict[int, int]:
    """How many of each length give the largest sum up to capacity."""
    mask, reach, layers = (1 << (capacity + 1)) - 1, 1, []
    for size in sorted((s for s in counts if s <= capacity), reverse=True):
        left, k = min(counts[size], capacity // size), 1
        while left:
            k = min(k, left)
            grown = (reach | reach << (size * k)) & mask
            if grown != reach:
                layers.append((size, k, reach))
                reach = grown
            left -= k
            k *= 2
            if reach >> capacity:
                break
        if reach >> capacity:
            break
    total, used = reach.bit_length() - 1, defaultdict(int)
    for size, k, before in reversed(layers):
        if not before >> total & 1:
            used[size] += k
            total -= size * k
    return used


class Packer:
    """Turns documents' id payloads into pieces (seq, doc_id, start, length, crc, doc_tokens, offset)."""

    def __init__(self, window: int, pool: int):
        self.window, self.pool, self.seq, self.n = window, pool, 0, 0
        self.tails: dict[int, list] = defaultdict(list)

    def add(self, doc_id, ids: bytes):
        total, w = len(ids) // 4, self.window
        for at in range(0, total - w + 1, w):
            yield self._piece(doc_id, ids, at, w, total, 0)
            self.seq += 1
        if rest := total % w:
            self.tails[rest].append((doc_id, total - rest, total, ids[4 * (total - rest) :]))
            self.n += 1
        while self.n > self.pool:
            yield from self._bin()

    def _piece(self, doc_id, ids, at, n, total, offset):
        return self.seq, doc_id, at, n, zlib.crc32(ids[4 * at : 4 * (at + n)]), total, offset

    def _take(self, size):
        tail = self.tails[size].pop()
        if not self.tails[size]:
            del self.tails[size]
        self.n -= 1
        return tail

    def _bin(self):
        """One sequence: the longest tail and its best fill; what lacks is cut from another tail."""
        chosen = [self._take(max(self.tails))]
        room = self.window - (chosen[0][2] - chosen[0][1])
        for size, k in best_fill({s: len(t) for s, t in self.tails.items()}, room).items():
            chosen += [self._take(size) for _ in range(k)]
            room -= size * k
        if room and self.n:
            # a tail longer than the room: its head fills the bin, its rest waits as a shorter tail
            doc_id, first, total, ids = self._take(max(self.tails))
            chosen.append((doc_id, first, total, ids[: 4 * room], room))
            self.tails[total - first - room if len(ids) // 4 == total - first else len(ids) // 4 - room].append((doc_id, first + room, total, ids[4 * room :]))
            self.n += 1
        offset = 0
        for doc_id, first, total, ids, *_ in chosen:
            n = len(ids) // 4
            yield self.seq, doc_id, first, n, zlib.crc32(ids), total, offset
            offset += n
        self.seq += 1

    def finish(self):
        while self.n and sum(s * len(t) for s, t in self.tails.items()) >= self.window:
            yield from self._bin()
        rest = [self._take(max(self.tails)) for _ in range(self.n)]
        left = sum(len(t[3]) // 4 for t in rest)
        while left:
            room, offset = 1 << (left.bit_length() - 1), 0
            left -= room
            while room:
                doc_id, first, total, ids = rest.pop(0)
                n = min(len(ids) // 4, room)
                yield self.seq, doc_id, first, n, zlib.crc32(ids[: 4 * n]), total, offset
                offset, room = offset + n, room - n
                if 4 * n < len(ids):
                    rest.insert(0, (doc_id, first + n, total, ids[4 * n :]))
            self.seq += 1


def pack(docs: DataFrame, window: int = 4096, tokenizer: str | None = None, end: int = END_ID, pool: int = 1000) -> DataFrame:
    """Pieces: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset."""
    tokenizer = tokenizer or default_path()

    def run(batches):
        enc, packer, part = encoder(tokenizer), Packer(window, pool), TaskContext.get().partitionId()
        frame = lambda rows: arrow_batch([(part, *r) for r in rows], PIECE)
        for b in batches:
            yield frame([x for i, t in zip(b.column("doc_id").to_pylist(), b.column("text").to_pylist()) for x in packer.add(i, enc.payload(t, end))])
        yield frame(list(packer.finish()))

    pieces = spill(keyed(docs).mapInArrow(run, PIECE))
    totals = pieces.groupBy("part").agg((F.max("seq") + 1).alias("n"))
    before = totals.select("part", (F.sum("n").over(Window.orderBy("part")) - F.col("n")).alias("base"))
    # one row a task of the packing stage
    return pieces.join(F.broadcast(before), "part").select(
        "doc_id", "start", "length", "ids_crc32", "doc_tokens", (F.col("base") + F.col("seq")).alias("sequence_id"), "offset"
    )
