"""Substring deduplication on words, by level-wise doubling.

A window of ``window`` words can only repeat if every shorter window in it
repeats.  The first level therefore asks, for windows of ``start`` words, which
occur twice; to keep that question small each window of the next level names one
of its shorter windows, the one with the smallest hash, and equal windows name
the same one.  What survives is extended to twice the length and asked again,
until the full length, or until no candidate is left.  At the last level a bucket
answers whether a key was first seen in a smaller document, and a chunk settles
order within its own documents.

Words are divided by ASCII white space and compared unchanged, by 64-bit hashes of the
words and two 64-bit keys over the hashes of a window: texts are told apart as long as
no two of their different words share a hash.  Null or empty text has no words, a null
doc_id comes before all others, rows that repeat a doc_id are one document.  Texts are
taken whole; the longest one is held in memory with a few numbers for each word.
Empty tables give no rows; other columns, whatever their names, are not looked at.
"""

from __future__ import annotations

from itertools import compress

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import REQUEST, Chunk, anchors, answered, bucket_bits, chunk_table, chunk_words, covered, cut, each_chunk, ids_out, later_bits, mixed, requests_batch, spans_of, window_starts, with_answers

FACTORS = (np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC6A4A7935BD1E995))


def folded(h: np.ndarray, n: int, factor: np.uint64) -> np.ndarray:
    """A 64-bit key of every run of ``n`` hashes."""
    key = np.zeros(max(len(h) - n + 1, 0), np.uint64)
    for k in range(n):
        key = key * factor + h[k : k + len(key)]
    return mixed(key)


def twice(key: np.ndarray, at: np.ndarray, n: int, factor: np.uint64) -> np.ndarray:
    """Keys of the windows of ``2 n`` at ``at``, from the keys of their halves."""
    return mixed(key[at] * factor + key[at + n])


def distinct(keys: np.ndarray):
    """Distinct keys in order, the key number of each entry, and how often each occurs."""
    return np.unique(keys, return_inverse=True, return_counts=True)


def bits_of(answer: dict[int, bytes], keys: np.ndarray, bits: int) -> np.ndarray:
    """Answers for sorted distinct keys, as they were cut into buckets."""
    out = np.zeros(len(keys), dtype=bool)
    for bucket, a, b in cut(keys, bits):
        if bucket in answer:
            out[a:b] = np.unpackbits(np.frombuffer(answer[bucket], dtype=np.uint8), count=b - a).astype(bool)
    return out


def seen_elsewhere(blobs: list[bytes]) -> list[bytes]:
    """Whether each key of a chunk is in another chunk's blob too."""
    keys = [np.frombuffer(b, dtype=np.uint64) for b in blobs]
    every = np.sort(np.concatenate(keys))
    twice_or_more = np.unique(every[1:][every[1:] == every[:-1]])
    out = []
    for k in keys:
        at = np.minimum(np.searchsorted(twice_or_more, k), max(len(twice_or_more) - 1, 0))
        out.append(np.packbits(twice_or_more[at] == k if len(twice_or_more) else np.zeros(len(k), bool)).tobytes())
    return out


def first_elsewhere(blobs: list[bytes]) -> list[bytes]:
    """Whether a smaller document than the chunk's own first holds each key."""
    parts = [np.frombuffer(b, dtype=np.uint64).reshape(3, -1) for b in blobs]
    k1, k2, doc = (np.concatenate([p[i] for p in parts]) for i in range(3))
    doc = doc.view(np.int64)
    order = np.lexsort((doc, k2, k1))
    a, b, d = k1[order], k2[order], doc[order]
    new = np.ones(len(a), dtype=bool)
    new[1:] = (a[1:] != a[:-1]) | (b[1:] != b[:-1])
    first = d[np.maximum.accumulate(np.where(new, np.arange(len(a)), 0))]
    flag = np.empty(len(a), dtype=bool)
    flag[order] = d != first
    ends = np.cumsum([p.shape[1] for p in parts])
    return [np.packbits(flag[e - p.shape[1] : e]).tobytes() for p, e in zip(parts, ends.tolist(), strict=True)]


class Windows:
    """The windows of one chunk, level by level."""

    def __init__(self, chunk: Chunk, window: int, start: int, bits: int):
        self.chunk, self.window, self.bits = chunk, window, bits
        self.hashes, self.lens = chunk_words(chunk)
        self.keys = [folded(self.hashes, start, f) for f in FACTORS]
        self.length = start
        self.at, self.doc = window_starts(self.lens, min(2 * start, window) if start < window else start)
        if len(self.at):
            if start < window:
                # chosen by another hash than the one that deals keys to buckets
                chosen = anchors(mixed(self.keys[0] + FACTORS[0]), self.at, start + 1)
            else:
                chosen = self.at
            self.asked, self.entry, self.count = distinct(self.keys[0][chosen])
            # a window is asked about through its anchor; the anchor counts once per place
            places, which = np.unique(chosen, return_index=True)
            self.count = np.bincount(self.entry[which], minlength=len(self.asked))
        else:
            self.asked, self.entry, self.count = np.empty(0, np.uint64), np.empty(0, np.int64), np.empty(0, np.int64)

    def extend(self, answer: dict[int, bytes]) -> None:
        """Keep what repeats, and go on to twice the length."""
        again = (self.count > 1) | bits_of(answer, self.asked, self.bits)
        live = again[self.entry] if len(self.entry) else np.empty(0, bool)
        at, doc = self.at[live], self.doc[live]
        n = self.length
        full = np.zeros(len(self.keys[0]), dtype=bool)
        for i, f in enumerate(FACTORS):
            key = np.zeros(max(len(self.hashes) - 2 * n + 1, 0), np.uint64)
            key[at] = twice(self.keys[i], at, n, f)
            self.keys[i] = key
        self.length = 2 * n
        if self.length < self.window:
            full[at] = True
            begin = np.cumsum(self.lens) - self.lens
            fits = at + 2 * self.length <= (begin + self.lens)[doc]
            at, doc = at[fits], doc[fits]
            both = full[at + self.length]
            # at this level each window of twice the length asks about both halves
            at, doc = at[both], doc[both]
            halves = np.unique(np.concatenate([at, at + self.length]))
            self.asked, inverse, self.count = distinct(self.keys[0][halves])
            number = np.zeros(len(self.keys[0]), dtype=np.int64)
            number[halves] = inverse
            self.entry = number[at]
            self.second = number[at + self.length]
            self.at, self.doc = at, doc
        else:
            self.at, self.doc = at, doc
            self.group()

    def group(self) -> None:
        """Distinct full-length keys of this chunk with their first place."""
        begin = np.cumsum(self.lens) - self.lens
        ids, rel = self.chunk.ids[self.doc], self.at - begin[self.doc]
        k1, k2 = self.keys[0][self.at], self.keys[1][self.at]
        self.order = order = np.lexsort((rel, ids, k2, k1))
        a, b = k1[order], k2[order]
        new = np.ones(len(a), dtype=bool)
        new[1:] = (a[1:] != a[:-1]) | (b[1:] != b[:-1])
        self.number = np.cumsum(new) - 1
        head = np.flatnonzero(new)
        self.k1, self.k2, self.first = a[head], b[head], ids[order][head]
        first_rel = rel[order][head]
        self.later = (ids[order] != self.first[self.number]) | (rel[order] != first_rel[self.number]) if len(a) else np.empty(0, bool)

    def removed(self, answer: dict[int, bytes]) -> np.ndarray:
        """A flag for each word of the chunk."""
        gone = self.later
        if len(self.k1):
            gone = gone | bits_of(answer, self.k1, self.bits)[self.number]
        return covered(len(self.hashes), np.sort(self.at[self.order[gone]]), self.window)


def dedup_windows(docs: DataFrame, window: int = 20, start: int | None = None) -> DataFrame:
    """doc_id, n_words, n_removed, kept_text, and the removed spans of words.

    ``window`` must be ``start`` times a power of two; ``start`` is half of it by default.
    """
    start = start or max(window // 2, 1)
    levels, length = 0, start
    while length < window:
        levels, length = levels + 1, 2 * length
    if length != window:
        raise ValueError("window must be start times a power of two")
    chunks = chunk_table(docs)
    bits = bucket_bits(chunks, 0.25)
    later = later_bits(bits)

    def to_level(chunk: Chunk, n: int) -> Windows:
        w = Windows(chunk, window, start, bits)
        if levels == 0:
            w.group()
        for k in range(n):
            if k and hasattr(w, "second"):
                answer = chunk.answer(f"a{k}")
                again = (w.count > 1) | bits_of(answer, w.asked, bits)
                both = again[w.entry] & again[w.second]
                w.at, w.doc, w.entry = w.at[both], w.doc[both], w.entry[both]
            w.extend(chunk.answer(f"a{k}"))
        return w

    joined = chunks
    for k in range(levels):

        def ask(batches, k=k):
            for chunk in each_chunk(batches):
                keys = to_level(chunk, k).asked
                yield requests_batch([(bucket, chunk.chunk_id, keys[a:b].tobytes()) for bucket, a, b in cut(keys, bits)], later)

        joined = with_answers(joined, answered(joined.mapInArrow(ask, REQUEST), seen_elsewhere, later), f"a{k}")

    def ask_first(batches):
        for chunk in each_chunk(batches):
            w = to_level(chunk, levels)
            docs_ = w.first.view(np.uint64)
            yield requests_batch([(bucket, chunk.chunk_id, b"".join(x[a:b].tobytes() for x in (w.k1, w.k2, docs_))) for bucket, a, b in cut(w.k1, bits)], later)

    final = with_answers(joined, answered(joined.mapInArrow(ask_first, REQUEST), first_elsewhere, later), "last")

    def apply(batches):
        for chunk in each_chunk(batches):
            w = to_level(chunk, levels)
            flags = w.removed(chunk.answer("last"))
            ends = np.cumsum(w.lens)
            gone, kept, begins, stops = [], [], [], []
            for text, a, b in zip(chunk.texts(), (ends - w.lens).tolist(), ends.tolist(), strict=True):
                f = flags[a:b]
                n = int(f.sum())
                gone.append(n)
                words = text.split()
                kept.append(b" ".join(compress(words, (~f).tolist()) if n else words))
                s, e = spans_of(f) if n else ((), ())
                begins.append(list(s))
                stops.append(list(e))
            for i in range(0, len(kept), 512):
                part = slice(i, i + 512)
                yield pa.RecordBatch.from_arrays(
                    [ids_out(chunk.ids[part]), pa.array(w.lens[part]), pa.array(gone[part], pa.int64()), pa.array(kept[part], pa.binary()), pa.array(begins[part], pa.list_(pa.int64())), pa.array(stops[part], pa.list_(pa.int64()))],
                    ["doc_id", "n_words", "n_removed", "kept_text", "span_starts", "span_ends"],
                )

    out = final.mapInArrow(apply, "doc_id long, n_words long, n_removed long, kept_text binary, span_starts array<long>, span_ends array<long>")
    return out.withColumn("kept_text", F.col("kept_text").cast("string"))
