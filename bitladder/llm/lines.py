"""Line deduplication by a range-partitioned, sorted stream of line hashes.

Lines become (hash, document, position) rows.  They are range-partitioned and
sorted by all three, so a line that a third of all documents hold is spread over
many partitions, and written once.  Streaming through a partition shows where a
hash's first document ends; only a hash that runs on from an earlier partition
needs outside help: one first document per partition boundary.  What comes back
per document is a compressed bitmap of kept lines, never text.

A line's key is the line stripped of ASCII white space with A-Z lower-cased.
Null and empty texts are one empty line.  A null doc_id sorts before all others.
Rows that repeat a doc_id count as the same document.  Texts are taken whole, one in
memory at a time; empty tables give no rows.  Other columns are not looked at; those
that ``keep`` names come back, under ``in_`` and their name where the operator has a
column of that name.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import NULL_ID, handed_on, id_and_bytes, slices, written

SPACE = b" \t\n\r\x0b\x0c"


def text_lines(text: bytes, min_chars: int):
    """(position, 128-bit key hash) of each line whose key has ``min_chars`` code points."""
    from xxhash import xxh3_128_digest

    for at, line in enumerate(text.split(b"\n")):
        key = line.strip(SPACE).lower()
        if len(key) >= min_chars and (len(key) >= 4 * min_chars or len(key.decode("utf-8", "replace")) >= min_chars):
            yield at, xxh3_128_digest(key)


def line_rows(docs: DataFrame, min_chars: int) -> DataFrame:
    def rows(batches):
        from xxhash import xxh3_64_intdigest

        for batch in slices(batches):
            hi, doc, tag, pos = [], [], [], []
            ids = batch.column(0).fill_null(NULL_ID).to_pylist()
            for i, text in zip(ids, batch.column(1).to_pylist(), strict=True):
                mark = xxh3_64_intdigest(text) - (1 << 63)
                for at, h in text_lines(text, min_chars):
                    hi.append(h)
                    doc.append(i)
                    tag.append(mark)
                    pos.append(at)
            h = np.frombuffer(b"".join(hi), dtype=">i8").reshape(-1, 2).astype(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(h[:, 0]), pa.array(h[:, 1]), pa.array(doc, pa.int64()), pa.array(tag, pa.int64()), pa.array(pos, pa.int32())], ["h1", "h2", "doc", "tag", "pos"])

    return id_and_bytes(docs).mapInArrow(rows, "h1 long, h2 long, doc long, tag long, pos int")


def stream_first(batches, heads: dict | None = None):
    """Marks the rows, sorted by hash and document, that lie after the hash's first document.

    ``heads`` maps the partition's (part, h1, h2) to the first document of a hash
    that began in an earlier partition.
    """
    last, first, part = None, None, None
    for batch in batches:
        if not batch.num_rows:
            continue
        h1, h2, doc = (batch.column(k).to_numpy(zero_copy_only=False) for k in (0, 1, 2))
        new = np.ones(len(doc), dtype=bool)
        new[1:] = (h1[1:] != h1[:-1]) | (h2[1:] != h2[:-1])
        head = (int(h1[0]), int(h2[0]))
        new[0] = head != last
        start = np.maximum.accumulate(np.where(new, np.arange(len(doc)), -1))
        lead = np.where(start >= 0, doc[np.maximum(start, 0)], first if first is not None else 0)
        yield batch, doc != lead
        last, first = (int(h1[-1]), int(h2[-1])), int(lead[-1])


def dropped_lines(docs: DataFrame, min_chars: int = 10) -> DataFrame:
    """doc, tag, pos of every line that a smaller document also holds."""
    spark = docs.sparkSession
    rows = line_rows(docs, min_chars).repartitionByRange("h1", "h2", "doc", "tag", "pos").sortWithinPartitions("h1", "h2", "doc", "tag", "pos")

    def mark(batches):
        from pyspark import TaskContext

        part, at = TaskContext.get().partitionId(), 0
        for batch, later in stream_first(batches):
            n = batch.num_rows
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(later), pa.array([part] * n, pa.int32()), pa.array(np.arange(at, at + n), pa.int64())], [*batch.schema.names, "later", "part", "at"])
            at += n

    marked = written(rows.mapInArrow(mark, "h1 long, h2 long, doc long, tag long, pos int, later boolean, part int, at long"), "lines")
    # a hash at the head of a partition may have begun before: one row per partition
    heads = marked.where("at = 0").select("h1", "h2", F.col("part").alias("head"))
    fix = (
        marked.join(F.broadcast(heads.select("h1", "h2").distinct()), ["h1", "h2"])
        .groupBy("h1", "h2")
        .agg(F.min("doc").alias("first"))
    )
    fixed = marked.join(F.broadcast(fix), ["h1", "h2"], "left")
    return fixed.where(F.col("later") | (F.col("first").isNotNull() & (F.col("doc") != F.col("first")))).select("doc", "tag", "pos")


def keep_bitmaps(docs: DataFrame, min_chars: int = 10) -> DataFrame:
    """doc_id, tag, and ``drops``: a zlib-compressed bitmap of the lines to drop.

    Documents that lose no line have no row.  A group is the lines of one text.
    """
    dropped = dropped_lines(docs, min_chars).groupBy("doc", "tag").agg(F.collect_set("pos").alias("at"))

    def bitmap(batches):
        for batch in batches:
            maps = []
            for at in batch.column(2).to_pylist():
                bits = np.zeros(max(at) + 1, dtype=np.uint8)
                bits[at] = 1
                maps.append(zlib.compress(np.packbits(bits).tobytes(), 1))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(maps, pa.binary())], ["doc", "tag", "drops"])

    return dropped.mapInArrow(bitmap, "doc long, tag long, drops binary")


def dedup_lines(docs: DataFrame, min_chars: int = 10, keep: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, n_lines, n_dropped, ``kept_text``, and the columns named in ``keep``."""
    from xxhash import xxh3_64_intdigest

    maps = keep_bitmaps(docs, min_chars)
    names = handed_on(tuple(c for c in keep if c != "doc_id"), ("doc_id", "n_lines", "n_dropped", "kept_text"))
    others = [f"_keep{i}" for i in range(len(names))]
    source = docs.select(F.coalesce(F.col("text").cast("binary"), F.lit(b"")).alias("_text"), F.coalesce(F.col("doc_id").cast("long"), F.lit(NULL_ID)).alias("_doc"), *[F.col(f"`{c}`").alias(o) for c, o in zip(names, others, strict=True)])

    def tagged(batches):
        for batch in slices(batches):
            tags = [xxh3_64_intdigest(t) - (1 << 63) for t in batch.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(tags, pa.int64())], [*batch.schema.names, "_tag"])

    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in source.schema)
    maps = maps.withColumnsRenamed({"doc": "__of", "tag": "__tag", "drops": "__drops"})
    joined = source.mapInArrow(tagged, f"{kinds}, _tag long").join(maps, (F.col("_doc") == F.col("__of")) & (F.col("_tag") == F.col("__tag")), "left").select("_text", "_doc", "__drops", *others)

    def apply(batches):
        for batch in slices(batches):
            n_lines, n_dropped, kept = [], [], []
            for text, drops in zip(batch.column(0).to_pylist(), batch.column(2).to_pylist(), strict=True):
                if drops is None:
                    n_lines.append(text.count(b"\n") + 1)
                    n_dropped.append(0)
                    kept.append(text)
                    continue
                lines = text.split(b"\n")
                bits = np.unpackbits(np.frombuffer(zlib.decompress(drops), dtype=np.uint8))
                gone = set(np.flatnonzero(bits).tolist())
                n_lines.append(len(lines))
                n_dropped.append(len(gone))
                kept.append(b"\n".join(x for i, x in enumerate(lines) if i not in gone))
            ids = batch.column(1).to_numpy(zero_copy_only=False)
            yield pa.RecordBatch.from_arrays(
                [pa.array(ids, pa.int64(), mask=ids == NULL_ID), pa.array(n_lines, pa.int64()), pa.array(n_dropped, pa.int64()), pa.array(kept, pa.binary()), *batch.columns[3:]],
                ["doc_id", "n_lines", "n_dropped", "kept_text", *others],
            )

    more = "".join(f", `{f.name}` {f.dataType.simpleString()}" for f in source.schema if f.name in others)
    out = joined.mapInArrow(apply, f"doc_id long, n_lines long, n_dropped long, kept_text binary{more}")
    return out.select("doc_id", "n_lines", "n_dropped", F.col("kept_text").cast("string").alias("kept_text"), *[F.col(o).alias(n) for o, n in zip(others, names.values(), strict=True)])
