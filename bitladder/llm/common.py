"""Shared plumbing: the shared work folder, document chunks and the bucket exchange.

Three operators (byte spans, word windows, near duplicates) ask one question of
the whole corpus: which keys occur elsewhere?  They ask it in packed form:

1. ``chunk_table`` writes the documents once as chunks of a bounded number of
   bytes (zstd), so that a chunk is the same rows whenever it is read again.
2. Each chunk sends every *distinct* key once, sorted and cut by leading key
   bits into one row per bucket.  A key that a third of all documents share so
   costs one entry per chunk, never one per occurrence.
3. A bucket answers every chunk row in the entry order of that row, so answers
   are plain arrays without keys, and go back by ``chunk_id``.

Chunks and buckets are of fixed size, so both grow with the input, and rows of one
chunk and bucket would become short.  Beyond ``2 ** DIRECT_BITS`` buckets keys go in
two steps: a chunk sends one row to each of so many coarse buckets, where the rows of
many chunks are dealt anew, and answers come back the same way.  Rows so grow with the input.
"""

from __future__ import annotations

import tempfile
import uuid
from itertools import groupby

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: stands for a null doc_id inside packed arrays; sorts before every other id
NULL_ID = -(2**63)
CHUNK_BYTES = 4 << 20
#: bytes of the smallest request that one bucket should gather
BUCKET_BYTES = 4 << 20
#: log2 of the buckets to which a chunk sends rows directly, of 64 to 400 bytes then; a second
#: step moves all keys twice, so it is left to inputs whose rows would be shorter
DIRECT_BITS = 14
#: bytes of a coarse bucket's rows that are dealt to its buckets together
DEAL_BYTES = 32 << 20
#: parts into which the rows of a coarse bucket are dealt
DEALERS = 16


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``.

    Only a local session without that setting gets a temporary folder.
    """
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not found:
        if not spark.sparkContext.master.startswith("local["):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        found = tempfile.mkdtemp(prefix="bitladder-")
        spark.conf.set("spark.checkpoint.dir", found)
    return found


def written(df: DataFrame, name: str, compression: str = "zstd") -> DataFrame:
    """Write ``df`` to the shared folder and read it back: lineage ends here."""
    spark = df.sparkSession
    path = f"{shared_dir(spark).rstrip('/')}/bitladder-{uuid.uuid4().hex}/{name}"
    df.write.option("compression", compression).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def id_and_bytes(docs: DataFrame) -> DataFrame:
    """``doc_id`` and the UTF-8 bytes of ``text`` (null: empty), no other column."""
    return docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        F.coalesce(F.col("text").cast("binary"), F.lit(b"")).alias("text"),
    )


def handed_on(keep: tuple[str, ...], own: tuple[str, ...]) -> dict[str, str]:
    """Names under which kept columns come back: with ``in_`` before a name that the operator itself returns."""
    out: dict[str, str] = {}
    for c in keep:
        name = c
        while name in own or name in out.values() or (name != c and name in keep):
            name = f"in_{name}"
        out[c] = name
    return out


def slices(batches, rows: int = 512):
    """Arrow batches in small parts, so that Python copies stay small."""
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)


def ids_out(ids: np.ndarray) -> pa.Array:
    return pa.array(ids, type=pa.int64(), mask=ids == NULL_ID)


def ids_in(column) -> np.ndarray:
    return np.asarray(column.fill_null(NULL_ID).to_numpy(zero_copy_only=False), dtype=np.int64)


def chunk_table(docs: DataFrame, chunk_bytes: int = CHUNK_BYTES) -> DataFrame:
    """Documents packed into rows of about ``chunk_bytes`` of text, written once.

    A document is never split, so only one that is longer makes a longer chunk.
    """

    def pack(batches):
        base, seq = TaskContext.get().partitionId() << 24, 0
        ids, texts, size = [], [], 0

        def row():
            blob = b"".join(texts)
            return pa.RecordBatch.from_pydict(
                {
                    "chunk_id": pa.array([base + seq], pa.int64()),
                    "n_bytes": pa.array([len(blob)], pa.int64()),
                    "ids": pa.array([np.array(ids, dtype=np.int64).tobytes()], pa.binary()),
                    "lens": pa.array([np.array([len(t) for t in texts], dtype=np.int64).tobytes()], pa.binary()),
                    "blob": pa.array([pa.compress(blob, codec="zstd", asbytes=True) if blob else b""], pa.binary()),
                }
            )

        for batch in slices(batches):
            for doc, text in zip(ids_in(batch.column(0)).tolist(), batch.column(1).to_pylist(), strict=True):
                if texts and size + len(text) > chunk_bytes:
                    yield row()
                    seq, ids, texts, size = seq + 1, [], [], 0
                ids.append(doc)
                texts.append(text)
                size += len(text)
        if texts:
            yield row()

    schema = "chunk_id long, n_bytes long, ids binary, lens binary, blob binary"
    return written(id_and_bytes(docs).mapInArrow(pack, schema), "chunks", "uncompressed")


class Chunk:
    """One row of ``chunk_table``, with the answers that were joined to it."""

    def __init__(self, row: dict):
        self.chunk_id = row["chunk_id"]
        self.ids = np.frombuffer(row["ids"], dtype=np.int64)
        self.lens = np.frombuffer(row["lens"], dtype=np.int64)
        self.blob = pa.decompress(row["blob"], decompressed_size=row["n_bytes"], codec="zstd", asbytes=True) if row["n_bytes"] else b""
        self.ends = np.cumsum(self.lens)
        self.starts = self.ends - self.lens
        self.row = row

    def texts(self):
        for a, b in zip(self.starts.tolist(), self.ends.tolist(), strict=True):
            yield self.blob[a:b]

    def answer(self, name: str) -> dict[int, bytes]:
        found: dict[int, bytes] = {}
        for x in self.row.get(name) or ():
            found.update([(x["bucket"], x["data"])] if x["bucket"] >= 0 else unpacked(x["data"]))
        return found


def each_chunk(batches):
    for batch in batches:
        for i in range(batch.num_rows):
            yield Chunk(batch.slice(i, 1).to_pylist()[0])


def bucket_bits(chunks: DataFrame, bytes_per_text_byte: float) -> int:
    """log2 of the number of buckets, so that a bucket gathers a bounded request."""
    total = chunks.agg(F.sum("n_bytes")).first()[0] or 0
    want = max(32, total * bytes_per_text_byte / BUCKET_BYTES)
    return int(np.ceil(np.log2(want)))


def later_bits(bits: int) -> int:
    """How many of a bucket's ``bits`` the second step tells; 0: there is one step only."""
    return max(0, bits - DIRECT_BITS)


def cut(sorted_keys: np.ndarray, bits: int):
    """(bucket, from, to) of sorted 64-bit keys, for the buckets that have any."""
    if not len(sorted_keys):
        return
    of = (sorted_keys >> np.uint64(64 - bits)).astype(np.int64)
    at = np.flatnonzero(np.diff(of, prepend=-1))
    for a, b in zip(at.tolist(), [*at[1:].tolist(), len(of)], strict=True):
        yield int(of[a]), a, b


REQUEST = "bucket int, chunk_id long, data binary"
ANSWER = "chunk_id long, bucket int, data binary"


def packed(parts) -> bytes:
    """(number, bytes) pairs as one value."""
    parts = list(parts)
    numbers = np.array([[n for n, _ in parts], [len(d) for _, d in parts]], dtype=np.int64)
    return b"".join((np.int64(len(parts)).tobytes(), numbers.tobytes(), *(d for _, d in parts)))


def unpacked(blob: bytes):
    n = int(np.frombuffer(blob, np.int64, 1)[0])
    numbers, sizes = np.frombuffer(blob, np.int64, 2 * n, 8).reshape(2, n).tolist()
    at = 8 + 16 * n
    for number, size in zip(numbers, sizes, strict=True):
        yield number, blob[at : at + size]
        at += size


def requests_batch(rows: list[tuple[int, int, bytes]], later: int) -> pa.RecordBatch:
    """The (bucket, chunk_id, data) rows of one chunk, in bucket order; packed by coarse bucket if there is a second step."""
    if later:
        rows = [(coarse, own[0][1], packed((b, d) for b, _, d in own)) for coarse, own in ((c, list(g)) for c, g in groupby(rows, lambda r: r[0] >> later))]
    b, c, d = zip(*rows, strict=True) if rows else ((), (), ())
    return pa.RecordBatch.from_arrays([pa.array(b, pa.int32()), pa.array(c, pa.int64()), pa.array(d, pa.binary())], ["bucket", "chunk_id", "data"])


def dealt(requests: DataFrame) -> DataFrame:
    """Packed rows of coarse buckets as rows of buckets: ``chunk_id`` numbers a block of chunks, ``data`` packs theirs.

    The sort makes the blocks the same whenever a lost task is run again.
    """
    limit = DEAL_BYTES

    def deal(batches):
        base, seq = TaskContext.get().partitionId() << 32, 0
        parts: dict[int, list] = {}
        size, now = 0, None
        for batch in batches:
            for coarse, chunk, data in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if parts and (coarse != now or size + len(data) > limit):
                    yield requests_batch([(b, base + seq, packed(p)) for b, p in parts.items()], 0)
                    seq, parts, size = seq + 1, {}, 0
                now, size = coarse, size + len(data)
                for b, d in unpacked(data):
                    parts.setdefault(b, []).append((chunk, d))
        if parts:
            yield requests_batch([(b, base + seq, packed(p)) for b, p in parts.items()], 0)

    by_key = requests.repartition("bucket", F.pmod(F.hash("chunk_id"), F.lit(DEALERS)))
    return by_key.sortWithinPartitions("bucket", "chunk_id").mapInArrow(deal, REQUEST)


def returned(answers: DataFrame, later: int) -> DataFrame:
    """Answers of blocks as one row for each chunk and coarse bucket, whose number is negative to mark it as packed."""

    def collect(batches):
        parts: dict[int, list] = {}
        now = None

        def rows():
            found = [(chunk, -1 - (p[0][0] >> later), packed(p)) for chunk, p in parts.items()]
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*found, strict=True), (pa.int64(), pa.int32(), pa.binary()), strict=True)], ["chunk_id", "bucket", "data"])

        for batch in batches:
            for block, bucket, data in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if parts and block != now:
                    yield rows()
                    parts = {}
                now = block
                for chunk, d in unpacked(data):
                    parts.setdefault(chunk, []).append((bucket, d))
        if parts:
            yield rows()

    return answers.repartition("chunk_id").sortWithinPartitions("chunk_id", "bucket").mapInArrow(collect, ANSWER)


def answered(requests: DataFrame, resolve, later: int) -> DataFrame:
    """``resolve(list of blobs) -> list of answers`` for each bucket, one answer a blob."""

    def group(table: pa.Table) -> pa.Table:
        bucket = table.column("bucket")[0].as_py()
        ids, blobs = table.column("chunk_id"), table.column("data").to_pylist()
        if later:
            blocks = [list(unpacked(b)) for b in blobs]
            found = iter(resolve([d for block in blocks for _, d in block]))
            out = [packed((chunk, next(found)) for chunk, _ in block) for block in blocks]
        else:
            out = resolve(blobs)
        return pa.table({"chunk_id": ids, "bucket": pa.array([bucket] * len(out), pa.int32()), "data": pa.array(out, pa.binary())})

    if not later:
        return requests.groupBy("bucket").applyInArrow(group, ANSWER)
    return returned(dealt(requests).groupBy("bucket").applyInArrow(group, ANSWER), later)


def with_answers(chunks: DataFrame, answers: DataFrame, name: str) -> DataFrame:
    """Answers of all buckets as one array column beside their chunk."""
    packed = answers.groupBy("chunk_id").agg(F.collect_list(F.struct("bucket", "data")).alias(name))
    return chunks.join(packed, "chunk_id", "left")


def mixed(h: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser."""
    h = h ^ (h >> np.uint64(32))
    h = h * np.uint64(0xD6E8FEB86659FD93)
    h = h ^ (h >> np.uint64(29))
    h = h * np.uint64(0xC2B2AE3D27D4EB4F)
    return h ^ (h >> np.uint64(32))


def sliding_min(x: np.ndarray, width: int) -> np.ndarray:
    """Minimum of every ``width`` neighbours, by doubling."""
    have, out = 1, x
    while have < width:
        step = min(have, width - have)
        out = np.minimum(out[:-step], out[step:])
        have += step
    return out


#: windows are handled in blocks whose positions fit this many low key bits
POSITION_BITS = 20


def anchors(hashes: np.ndarray, starts: np.ndarray, width: int):
    """For each window start, the position of the smallest hash among its ``width``.

    Equal windows choose equal relative positions: the leftmost smallest hash.
    ``starts`` are ascending; every start has ``width`` hashes from it onwards.
    """
    out = np.empty(len(starts), dtype=np.int64)
    low, block = np.uint64((1 << POSITION_BITS) - 1), 1 << 18
    lo = 0
    while lo < len(starts):
        first = int(starts[lo])
        hi = int(np.searchsorted(starts, first + block))
        part = hashes[first : int(starts[hi - 1]) + width]
        key = (part & ~low) | np.arange(len(part), dtype=np.uint64)
        best = sliding_min(key, width)
        out[lo:hi] = (best[starts[lo:hi] - first] & low).astype(np.int64) + first
        lo = hi
    return out


class HashCache(dict):
    """Word to 64-bit hash; forgets everything when it grows too large."""

    def __init__(self, of, limit: int = 200_000):
        self.of, self.limit = of, limit

    def __missing__(self, word):
        value = self.of(word)
        if len(word) <= 64:
            if len(self) >= self.limit:
                self.clear()
            self[word] = value
        return value


#: longer pieces than this are hashed one by one
LONGEST = 256
#: ASCII white space
SPACES = np.zeros(256, bool)
SPACES[[32, 9, 10, 11, 12, 13]] = True
_rng = np.random.default_rng(20240229)
BY_BYTE, BY_PLACE = _rng.integers(0, 2**64, 256, np.uint64), _rng.integers(0, 2**64, LONGEST + 1, np.uint64) | np.uint64(1)


def piece_hashes(buf: bytes, data: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """64-bit hashes of the byte ranges [start, end) of ``buf``, none of them empty.

    Random numbers of bytes times random factors of their places, summed and mixed.
    """
    from xxhash import xxh3_64_intdigest

    size = end - start
    begin = np.cumsum(size) - size
    place = np.arange(int(size.sum())) - np.repeat(begin, size)
    value = BY_BYTE[data[place + np.repeat(start, size)]] * BY_PLACE[np.minimum(place, LONGEST)]
    h = np.add.reduceat(value, begin) if len(size) else np.empty(0, np.uint64)
    for i in np.flatnonzero(size > LONGEST).tolist():
        h[i] = xxh3_64_intdigest(buf[start[i] : end[i]])
    return mixed(h + size.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))


def words_of(data: np.ndarray, edges: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """[start, end) of the runs without ASCII white space; no run crosses an edge."""
    solid = ~SPACES[data]
    cut_before = np.zeros(len(data) + 1, bool)
    cut_before[edges] = True
    cut_before[0] = cut_before[-1] = True
    start = solid.copy()
    start[1:] &= ~solid[:-1] | cut_before[1:-1]
    stop = solid.copy()
    stop[:-1] &= ~solid[1:] | cut_before[1:-1]
    return np.flatnonzero(start), np.flatnonzero(stop) + 1


def doc_blocks(lens: np.ndarray, size: int = 1 << 19):
    """Ranges of neighbouring documents of about ``size`` bytes: what is in memory at once."""
    number = (np.cumsum(lens) - lens) // size
    edges = [0, *(np.flatnonzero(np.diff(number)) + 1).tolist(), len(lens)]
    return [(a, b) for a, b in zip(edges[:-1], edges[1:], strict=True) if b > a]


def chunk_words(chunk: Chunk) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all words of a chunk, one after the other, and words per document.

    Words are runs without the ASCII white space 20 and 09-0D, as ``bytes.split``
    gives them.
    """
    per, parts = [np.empty(0, np.int64)], [np.empty(0, np.uint64)]
    for a, b in doc_blocks(chunk.lens):
        lo, hi = int(chunk.starts[a]), int(chunk.ends[b - 1])
        buf = chunk.blob[lo:hi]
        data = np.frombuffer(buf, np.uint8)
        start, end = words_of(data, chunk.starts[a:b] - lo)
        parts.append(piece_hashes(buf, data, start, end))
        per.append(np.searchsorted(start, chunk.ends[a:b] - lo) - np.searchsorted(start, chunk.starts[a:b] - lo))
    return np.concatenate(parts), np.concatenate(per)


def window_starts(lens: np.ndarray, window: int) -> tuple[np.ndarray, np.ndarray]:
    """Starts of all windows inside one document each, and their document's index."""
    count = np.maximum(lens - window + 1, 0)
    doc = np.repeat(np.arange(len(lens)), count)
    begin = np.cumsum(lens) - lens
    before = np.cumsum(count) - count
    return np.arange(int(count.sum())) - before[doc] + begin[doc], doc


def spans_of(flags: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """[start, end) of the maximal runs of true."""
    edge = np.diff(flags.astype(np.int8), prepend=0, append=0)
    return np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)


def covered(n: int, starts: np.ndarray, window: int) -> np.ndarray:
    """Which of ``n`` places lie in a window that begins at one of ``starts``."""
    edge = np.zeros(n + 1, dtype=np.int32)
    np.add.at(edge, starts, 1)
    np.add.at(edge, np.minimum(starts + window, n), -1)
    return np.cumsum(edge[:n]) > 0
