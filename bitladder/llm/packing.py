"""Packing documents into fixed windows by minimum bin slack.

Each scan partition is packed on its own, in the order of its rows, from a pool
of bounded size: no shuffle, and a lost task is simply run again.  A document's
full windows are cut off first; the remainders form a multiset of lengths.  The
largest remainder opens a window and a subset-sum over the others, held as bits
of one integer, finds the multiset that fills it closest; the counts are read
back from the bits.  If no multiset fills the window and the pool still holds
something, one more remainder is cut to fill it, so at most the last window of a
partition is padded.

Null doc_ids stay null, null and empty texts are just the end id, equal rows are
packed each, empty tables give no rows and other columns are not looked at.  Texts
are taken whole; one text's ids are in memory at a time, beside the pool.
"""

from __future__ import annotations

from bisect import bisect_left, bisect_right, insort
from collections import defaultdict, deque

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import id_and_bytes
from .tokens import id_cache


def best_fill(lengths, room: int) -> dict[int, int]:
    """The multiset of (length, count), largest first, whose sum is the largest up to ``room``.

    Bit s of ``reach`` says that sum s can be had.  Counts are split into powers
    of two, so an item is one shift; the bits before each item allow the way back.
    """
    full, reach, trail = (1 << (room + 1)) - 1, 1, []
    for length, count in lengths:
        left, step = min(count, room // length), 1
        while left > 0:
            take = min(step, left)
            trail.append((reach, length, take))
            reach |= (reach << (length * take)) & full
            left, step = left - take, step * 2
        if reach >> room:
            break
    total, chosen = reach.bit_length() - 1, defaultdict(int)
    for before, length, take in reversed(trail):
        if not before >> total & 1:
            total -= length * take
            chosen[length] += take
    return dict(chosen)


class Pool:
    """Pieces that wait for a window, by length."""

    def __init__(self, capacity: int):
        self.capacity, self.by_length, self.lengths, self.size = capacity, {}, [], 0

    def add(self, piece) -> None:
        queue = self.by_length.get(piece[2])
        if queue is None:
            queue = self.by_length[piece[2]] = deque()
            insort(self.lengths, piece[2])
        queue.append(piece)
        self.size += 1

    def take(self, length: int):
        queue = self.by_length[length]
        piece = queue.popleft()
        if not queue:
            del self.by_length[length]
            del self.lengths[bisect_left(self.lengths, length)]
        self.size -= 1
        return piece

    def window(self) -> list:
        """The next window's pieces."""
        first = self.take(self.lengths[-1])
        pieces, room = [first], self.capacity - first[2]
        fits = self.lengths[: bisect_right(self.lengths, room)]
        for length, n in best_fill(((k, len(self.by_length[k])) for k in reversed(fits)), room).items():
            pieces += [self.take(length) for _ in range(n)]
            room -= n * length
        if room and self.size:
            doc, start, length, total, ids = self.take(self.lengths[-1])
            pieces.append((doc, start, room, total, ids[: 4 * room]))
            self.add((doc, start + room, length - room, total, ids[4 * room :]))
        return pieces


def pack(docs: DataFrame, path: str, capacity: int = 2048, end_id: int = 1, pool_docs: int = 4096) -> DataFrame:
    """A row per piece: doc_id, start, length, doc_tokens, ids (little-endian uint32),
    sequence_id, offset.

    A document is its ids by the tokenizer at ``path`` and then ``end_id``; null
    or empty text is just ``end_id``.  Rows with equal doc_id are packed each.
    Each id lies in one piece; in a sequence offsets run without gap from 0.
    """

    def packed(batches):
        cache = id_cache(path)
        end = np.array([end_id], dtype="<u4").tobytes()
        pool, sequence, out = Pool(capacity), TaskContext.get().partitionId() << 40, []

        def emit(pieces):
            nonlocal sequence
            at = 0
            for doc, start, length, total, ids in pieces:
                out.append((doc, start, length, total, ids, sequence, at))
                at += length
            sequence += 1

        def rows():
            cols = list(zip(*out, strict=True))
            out.clear()
            kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.int64(), pa.int64()]
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], ["doc_id", "start", "length", "doc_tokens", "ids", "sequence_id", "offset"])

        for batch in batches:
            for at in range(0, batch.num_rows, 1024):
                part = batch.slice(at, 1024)
                for doc, ids in zip(part.column(0).to_pylist(), cache.encode(part.column(1).to_pylist()), strict=True):
                    ids += end
                    total, start = len(ids) // 4, 0
                    while total - start >= capacity:
                        emit([(doc, start, capacity, total, ids[4 * start : 4 * (start + capacity)])])
                        start += capacity
                    if start < total:
                        pool.add((doc, start, total - start, total, ids[4 * start :]))
                while pool.size > pool_docs:
                    emit(pool.window())
                if len(out) >= 2048:
                    yield rows()
        while pool.size:
            emit(pool.window())
            if len(out) >= 2048:
                yield rows()
        if out:
            yield rows()

    return id_and_bytes(docs).mapInArrow(packed, "doc_id long, start long, length long, doc_tokens long, ids binary, sequence_id long, offset long")


def digest(pieces: DataFrame) -> DataFrame:
    """The contract's columns of ``pack``'s pieces."""
    return pieces.select("doc_id", "start", "length", F.crc32("ids").alias("ids_crc32"), "doc_tokens", "sequence_id", "offset")
