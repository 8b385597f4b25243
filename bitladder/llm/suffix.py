"""Byte-span deduplication by blockwise suffix sorting with a difference cover.

Every window of ``window`` bytes names its *anchor*: the run of ``ANCHOR`` bytes
in it with the smallest hash, so equal windows name the same one.  Neighbouring
windows with one anchor travel together as a *segment* of at most
``2 * window - ANCHOR`` bytes.  Only segments whose anchor occurs elsewhere are
sent, each distinct one once per chunk, to the bucket of the anchor's hash.

A bucket is one text, its segments one after the other, whose suffixes are sorted
one block of leading bytes at a time.  Before that the suffixes at the places of a
difference cover are ranked by doubling.  A block is sorted by its first eight
bytes; suffixes that tie are ordered by cover ranks: for any two of them there is
a distance below ``PERIOD`` at which both stand on a cover place.  So a tie of any
length costs one comparison of ranks, and memory is the bucket, its cover ranks
and one block.  Neighbours in the sorted order with a common prefix of ``window``
bytes are one class; its smallest document keeps the bytes.

Texts are UTF-8 bytes, taken whole; null counts as empty; matches never cross
documents.  A null doc_id comes before all others.  Rows that repeat a doc_id count
as one document, so they do not remove each other.  Empty tables give no rows;
other columns, whatever their names, are not looked at.  A text is never split, so
the longest one is held in memory with a few numbers for each byte.
"""

from __future__ import annotations

import itertools

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import REQUEST, Chunk, anchors, answered, bucket_bits, chunk_table, covered, cut, doc_blocks, each_chunk, ids_out, later_bits, mixed, requests_batch, spans_of, window_starts, with_answers
from .windows import bits_of, distinct, seen_elsewhere

ANCHOR = 16
SALT = np.uint64(0x9E3779B97F4A7C15)
PERIOD = 7
#: suffixes that are sorted at once, unless more begin with the same two bytes
BLOCK = 1 << 18


def difference_cover(period: int) -> list[int]:
    """The smallest set of residues whose differences give every residue."""
    for size in range(1, period + 1):
        for rest in itertools.combinations(range(1, period), size - 1):
            if len({(a - b) % period for a in (0, *rest) for b in (0, *rest)}) == period:
                return [0, *rest]
    return list(range(period))


def words64(data: np.ndarray, at: np.ndarray) -> np.ndarray:
    """The eight bytes from each place as one big-endian number; ``data`` has eight bytes more than places."""
    return np.ndarray((len(data) - 7,), ">u8", data, 0, (1,))[at].astype(np.uint64)


class CoverRanks:
    """Ranks of the suffixes at cover places, by at least ``depth`` bytes.

    The places of one period are neighbours in ``rank``, so a place one period on is
    ``len(cover)`` entries on, and doubling needs no search.
    """

    def __init__(self, data: np.ndarray, depth: int, period: int = PERIOD):
        self.period, cover = period, difference_cover(period)
        self.size = len(cover)
        self.slot = np.full(period, -1, np.int64)
        self.slot[cover] = np.arange(self.size)
        places = (np.arange(-(-(len(data) - 8) // period))[:, None] * period + np.array(cover)[None, :]).ravel()
        places = places[places < len(data) - 8]
        key = words64(data, places) >> np.uint64(64 - 8 * min(8, period))
        rank = np.unique(key, return_inverse=True)[1]
        have, periods = period, 1
        while have < depth:
            after = np.zeros(len(rank), np.int64)
            after[: max(len(rank) - self.size * periods, 0)] = rank[self.size * periods :] + 1
            rank = np.unique(rank * np.int64(len(rank) + 2) + after, return_inverse=True)[1]
            have, periods = 2 * have, 2 * periods
        self.rank = rank.astype(np.int32)
        shift = [[next(d for d in range(period) if (a + d) % period in cover and (b + d) % period in cover) for b in range(period)] for a in range(period)]
        #: the distance at which places of two residues both meet the cover
        self.shift = np.array(shift)

    def at(self, place: np.ndarray) -> np.ndarray:
        return self.rank[place // self.period * self.size + self.slot[place % self.period]].astype(np.int64)


def leading_blocks(data: np.ndarray, starts: np.ndarray, size: int = BLOCK):
    """The starts of one block of leading bytes after another."""
    lead = data[starts].astype(np.int32) << 8 | data[starts + 1]
    count = np.bincount(lead, minlength=1 << 16)
    block = np.cumsum(count) // size  # a leading pair of bytes is never in two blocks
    for b in np.unique(block[np.flatnonzero(count)]).tolist():
        yield starts[block[lead] == b]


def sorted_ties(data: np.ndarray, starts: np.ndarray, ranks: CoverRanks) -> tuple[np.ndarray, np.ndarray]:
    """The suffixes that agree in their first eight bytes with another, in order, and their tie's number.

    A suffix's place in its tie is the number of suffixes before it, counted for
    each residue by the ranks at the distance of the two residues.
    """
    key = words64(data, starts)
    order = np.argsort(key, kind="stable")
    key, starts = key[order], starts[order]
    same = key[1:] == key[:-1]
    tied = np.zeros(len(key), bool)
    tied[1:] |= same
    tied[:-1] |= same
    number = np.cumsum(np.concatenate([[True], ~same]))[tied] if len(key) else np.empty(0, np.int64)
    starts = starts[tied]
    if not len(starts):
        return starts, number
    residue, span = starts % ranks.period, np.int64(len(ranks.rank) + 2)
    classes = []
    for r in range(ranks.period):
        mine = np.flatnonzero(residue == r)
        own = number[mine] * span + ranks.at(starts[mine] + ranks.shift[r, r])
        classes.append(mine[np.argsort(own, kind="stable")])
    before = np.zeros(len(starts), np.int64)
    for a, mine in enumerate(classes):
        for b, other in enumerate(classes):
            if not len(mine) or not len(other):
                continue
            if a == b:
                before[mine] += np.arange(len(mine))
                continue
            d = int(ranks.shift[a, b])
            left = number[mine] * span + ranks.at(starts[mine] + d)
            right = number[other] * span + ranks.at(starts[other] + d)
            before[mine] += np.searchsorted(right, left, side="left" if b > a else "right")
    order = np.lexsort((before, number))
    return starts[order], number[order]


def prefix_classes(data: np.ndarray, starts: np.ndarray, number: np.ndarray, length: int) -> np.ndarray:
    """Whether each suffix differs from the one before it within ``length`` bytes."""
    new = np.ones(len(starts), dtype=bool)
    new[1:] = number[1:] != number[:-1]
    for k in range(8, length, 8):
        # the last read overlaps the one before, so that it ends with the window
        v = words64(data, starts + min(k, length - 8))
        new[1:] |= v[1:] != v[:-1]
    return new


class Segments:
    """The segments of one chunk whose anchor occurs in more than one document."""

    def __init__(self, chunk: Chunk, window: int, bits: int):
        self.chunk, self.window, self.bits = chunk, window, bits
        self.asked = np.empty(0, np.uint64)
        self.start = self.stop = self.anchor = self.doc = self.entry = np.empty(0, np.int64)
        found = [self.block(a, b) for a, b in doc_blocks(chunk.lens)]
        found = [x for x in found if x is not None]
        if not found:
            return
        self.start, self.stop, self.anchor, self.doc, hashes = (np.concatenate(x) for x in zip(*found, strict=True))
        del found
        self.asked, self.entry, _ = distinct(hashes)
        ids = chunk.ids[self.doc]
        least = np.full(len(self.asked), np.iinfo(np.int64).max)
        most = np.full(len(self.asked), np.iinfo(np.int64).min)
        np.minimum.at(least, self.entry, ids)
        np.maximum.at(most, self.entry, ids)
        self.shared = least != most

    def block(self, first: int, last: int):
        """Segments of the documents from ``first`` to before ``last``, and their anchors' hashes."""
        lens, offset = self.chunk.lens[first:last], int(self.chunk.starts[first])
        at, doc = window_starts(lens, self.window)
        if not len(at):
            return None
        n = int(lens.sum()) - ANCHOR + 1
        low = np.ndarray((n,), "<u8", self.chunk.blob, offset, (1,))
        high = np.ndarray((n,), "<u8", self.chunk.blob, offset + 8, (1,))
        hashes = mixed(low * np.uint64(0x9E3779B97F4A7C15) + mixed(high))
        place = anchors(hashes, at, self.window - ANCHOR + 1)
        new = np.ones(len(at), dtype=bool)
        new[1:] = (place[1:] != place[:-1]) | (doc[1:] != doc[:-1])
        head = np.flatnonzero(new)
        tail = np.append(head[1:], len(at)) - 1
        # the smallest hashes crowd at the low end; mixed again they spread over the buckets
        return at[head] + offset, at[tail] + offset, place[head] + offset, doc[head] + first, mixed(hashes[place[head]] + SALT)

    def select(self, answer: dict[int, bytes]) -> None:
        """Keep the live segments and list the distinct ones, by anchor hash."""
        if not len(self.asked):
            self.keys, self.texts, self.first, self.left, self.number = self.asked, [], np.empty(0, np.int64), np.empty(0, np.int64), self.entry
            return
        live = np.flatnonzero((self.shared | bits_of(answer, self.asked, self.bits))[self.entry])
        live = live[np.argsort(self.entry[live], kind="stable")]
        self.start, self.stop, self.anchor, self.doc, entry = (x[live] for x in (self.start, self.stop, self.anchor, self.doc, self.entry))
        ids = self.chunk.ids[self.doc]
        known: dict[tuple, int] = {}
        number = np.empty(len(live), np.int64)
        blob, w = self.chunk.blob, self.window
        for i, (a, b, p, e) in enumerate(zip(self.start.tolist(), self.stop.tolist(), self.anchor.tolist(), entry.tolist(), strict=True)):
            number[i] = known.setdefault((e, p - a, blob[a : b + w]), len(known))
        self.number = number
        self.first = np.full(len(known), np.iinfo(np.int64).max)
        np.minimum.at(self.first, number, ids)
        self.keys = self.asked[[k[0] for k in known]] if known else np.empty(0, np.uint64)
        self.left = np.array([k[1] for k in known], dtype=np.int64)
        self.texts = [k[2] for k in known]

    def requests(self):
        """For each bucket: first documents, anchor offsets, lengths, and the bytes."""
        for bucket, a, b in cut(self.keys, self.bits):
            lens = np.array([len(t) for t in self.texts[a:b]], dtype=np.uint8)
            yield bucket, self.chunk.chunk_id, b"".join((np.int64(b - a).tobytes(), self.first[a:b].tobytes(), self.left[a:b].astype(np.uint8).tobytes(), lens.tobytes(), *self.texts[a:b]))

    def removed(self, answer: dict[int, bytes]) -> np.ndarray:
        """A flag for each byte of the chunk."""
        n = len(self.chunk.blob)
        if not len(self.keys):
            return np.zeros(n, dtype=bool)
        masks = np.zeros(len(self.keys), np.uint64)
        for bucket, a, b in cut(self.keys, self.bits):
            masks[a:b] = np.frombuffer(answer[bucket], dtype=np.uint64)
        every = np.uint64(2**64 - 1)
        mask = np.where(self.chunk.ids[self.doc] != self.first[self.number], every, masks[self.number])
        hit = np.flatnonzero(mask)
        starts = []
        for k in range(self.window - ANCHOR + 1):
            at = self.start[hit] + k
            starts.append(at[(at <= self.stop[hit]) & (mask[hit] >> np.uint64(k) & np.uint64(1)).astype(bool)])
        return covered(n, np.concatenate(starts), self.window)


def resolver(window: int):
    def resolve(blobs: list[bytes]) -> list[bytes]:
        """For each segment, the mask of its windows that a smaller document holds."""
        sizes, first, left, lens, bodies = [], [], [], [], []
        for b in blobs:
            n = int(np.frombuffer(b, np.int64, 1)[0])
            sizes.append(n)
            first.append(np.frombuffer(b, np.int64, n, 8))
            left.append(np.frombuffer(b, np.uint8, n, 8 + 8 * n))
            lens.append(np.frombuffer(b, np.uint8, n, 8 + 9 * n))
            bodies.append(b[8 + 10 * n :])
        first, left, lens = np.concatenate(first), np.concatenate(left), np.concatenate(lens).astype(np.int64)
        # equal segments of several chunks are one, of their smallest document
        known: dict[bytes, int] = {}
        same, at, body = np.empty(len(lens), np.int64), 0, b"".join(bodies)
        for i, n in enumerate(lens.tolist()):
            same[i] = known.setdefault(body[at : at + n], len(known))
            at += n
        del bodies, body
        doc = np.full(len(known), np.iinfo(np.int64).max)
        np.minimum.at(doc, same, first)
        size = np.array([len(t) for t in known], dtype=np.int64)
        data = np.frombuffer(b"".join(known) + bytes(window + 16), np.uint8)
        del known
        starts, segment = window_starts(size, window)
        best = np.full(len(data), np.iinfo(np.int64).max)
        if len(starts):
            ranks = CoverRanks(data, window)
            owner = np.zeros(len(data), np.int32)
            owner[starts] = segment
            best[starts] = doc[segment]  # what ties with no other is still its segment's, which several chunks may hold
            del segment
            for block in leading_blocks(data, starts):
                order, number = sorted_ties(data, block, ranks)
                if not len(order):
                    continue
                new = prefix_classes(data, order, number, window)
                smallest = np.minimum.reduceat(doc[owner[order]], np.flatnonzero(new))
                best[order] = smallest[np.cumsum(new) - 1]
        begin, masks = (np.cumsum(size) - size)[same], np.zeros(len(lens), np.uint64)
        for k in range(window - ANCHOR + 1):  # bit k of a segment is its k-th window
            has = np.flatnonzero(lens >= window + k)
            hit = has[best[begin[has] + k] < first[has]]
            masks[hit] |= np.uint64(1) << np.uint64(k)
        ends = np.cumsum(sizes)
        return [masks[e - n : e].tobytes() for n, e in zip(sizes, ends.tolist(), strict=True)]

    return resolve


def dedup_spans(docs: DataFrame, window: int = 50) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept (bytes), and the removed spans.

    ``window`` is 24 to 79 bytes: a segment's windows are the bits of one number.
    """
    if not ANCHOR + 8 <= window <= ANCHOR + 63:
        raise ValueError("window must be from 24 to 79 bytes")
    chunks = chunk_table(docs)
    bits = bucket_bits(chunks, 0.5)
    later = later_bits(bits)

    def ask(batches):
        for chunk in each_chunk(batches):
            keys = Segments(chunk, window, bits).asked
            yield requests_batch([(bucket, chunk.chunk_id, keys[a:b].tobytes()) for bucket, a, b in cut(keys, bits)], later)

    joined = with_answers(chunks, answered(chunks.mapInArrow(ask, REQUEST), seen_elsewhere, later), "shared")

    def send(batches):
        for chunk in each_chunk(batches):
            s = Segments(chunk, window, bits)
            s.select(chunk.answer("shared"))
            yield requests_batch(list(s.requests()), later)

    final = with_answers(joined, answered(joined.mapInArrow(send, REQUEST), resolver(window), later), "masks")

    def apply(batches):
        for chunk in each_chunk(batches):
            s = Segments(chunk, window, bits)
            s.select(chunk.answer("shared"))
            flags = s.removed(chunk.answer("masks"))
            gone, kept, begins, stops = [], [], [], []
            for text, a, b in zip(chunk.texts(), chunk.starts.tolist(), chunk.ends.tolist(), strict=True):
                f = flags[a:b]
                n = int(f.sum())
                gone.append(n)
                kept.append(np.frombuffer(text, dtype=np.uint8)[~f].tobytes() if n else text)
                x, y = spans_of(f) if n else ((), ())
                begins.append(list(x))
                stops.append(list(y))
            for i in range(0, len(kept), 512):
                part = slice(i, i + 512)
                yield pa.RecordBatch.from_arrays(
                    [ids_out(chunk.ids[part]), pa.array(chunk.lens[part]), pa.array(gone[part], pa.int64()), pa.array(kept[part], pa.binary()), pa.array(begins[part], pa.list_(pa.int64())), pa.array(stops[part], pa.list_(pa.int64()))],
                    ["doc_id", "n_bytes", "n_removed", "kept", "span_starts", "span_ends"],
                )

    out = final.mapInArrow(apply, "doc_id long, n_bytes long, n_removed long, kept binary, span_starts array<long>, span_ends array<long>")
    return out.withColumn("n_spans", F.size("span_starts").cast("long"))
