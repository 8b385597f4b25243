"""Near duplicates by consistent weighted sampling over TF-IDF shingles.

Shingles are runs of five words.  A shingle's weight in a document is its count
times an inverse document frequency scaled to 1..2, ``1 + ln((1+N)/(1+df)) /
ln(1+N)``, over all documents, so that a shingle which thousands of copies share
still counts.

1. Document frequencies come from the packed bucket exchange (``common``): every
   chunk sends its distinct shingles with counts, and learns the totals.
2. A shingle of one document only can be shared with nobody.  A document whose
   shared weight is below ``threshold`` of its whole weight has no partner, so it
   needs no samples; this is exact.  The others become vectors.
3. Improved consistent weighted sampling draws ``BANDS * ROWS`` samples: for each
   shingle and draw, two Gamma(2,1) variables and one uniform come from hashes of
   the shingle alone, the quantised weight and the key of the smallest value are
   the sample.  Samples are banded; a band's hash is a bucket.
4. Equal vectors are one from here on.  In a bucket every member is tied to the
   smallest one, never to all; the connected components of these ties are the
   candidate groups.  Only ids move up to this point.
5. Vectors come together by candidate group, and every pair in a group is
   verified by weighted Jaccard similarity as a product of sparse blocks; only
   links that join two parts leave.  A group beyond ``GROUP`` documents is dealt to
   blocks of bounded size: links within the blocks come first, then those between
   one document of each part, and only where a group is still in several parts do
   the others of its blocks meet, each pair of blocks a task's work.  So a link is
   lost only where no band ever tied its two texts into one group.

Keys that hold many rows (a text with thousands of copies, a popular band, a hub of
ties) are answered by a broadcast of at most ``HOT`` keys, the rest by a join, so
no task gathers the rows of one key.

A row without doc_id is known by a hash of its text, so that each different text
is a document of its own; two such rows of one text are two equal documents.  Rows
that repeat a doc_id are one document; with different texts each text is looked at
on its own and all that resemble any of them join its class.

The class is the smallest doc_id of the component, null where that is a row
without doc_id (they come first).  Null, empty or wordless texts are alone.  Under
five words the whole text is the one shingle.  Texts are taken whole; the longest
one is held in memory with a few numbers for each word.  Empty tables give no
rows, other columns are not looked at.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import NULL_ID, REQUEST, Chunk, answered, bucket_bits, chunk_table, chunk_words, cut, each_chunk, later_bits, mixed, requests_batch, window_starts, with_answers, written
from .windows import FACTORS, folded

WORDS, THRESHOLD = 5, 0.8
BANDS, ROWS = 16, 4
#: documents that one task compares with each other at most (twice this for two blocks)
GROUP = 1024
#: keys with more than one row in so many are hot; there are at most that many of them
HOT = 1000


class Shingles:
    """The distinct shingles of each document of a chunk, and of the chunk."""

    def __init__(self, chunk: Chunk, words: int):
        hashes, lens = chunk_words(chunk)
        at, doc = window_starts(lens, words)
        once = np.zeros(len(lens), bool)
        once[np.unique(chunk.ids, return_index=True)[1]] = True
        at, doc = at[once[doc]], doc[once[doc]]
        key = folded(hashes, words, FACTORS[0])[at] if len(at) else np.empty(0, np.uint64)
        short = np.flatnonzero((lens > 0) & (lens < words) & once)
        begin = np.cumsum(lens) - lens
        few = []
        for d in short.tolist():
            h = np.zeros(1, np.uint64)
            for x in hashes[begin[d] : begin[d] + lens[d]]:
                h = mixed(h * FACTORS[1] + x)
            few.append(h[0])
        key, doc = np.concatenate([key, np.array(few, np.uint64)]), np.concatenate([doc, short])
        order = np.argsort(key)
        # documents of a chunk seldom need more than 16 bits, which sort by radix
        order = order[np.argsort(doc[order].astype(np.uint16 if len(lens) <= 1 << 16 else np.int64), kind="stable")]
        key, ids = key[order], chunk.ids[doc[order]]
        new = np.ones(len(key), dtype=bool)
        new[1:] = (key[1:] != key[:-1]) | (ids[1:] != ids[:-1])
        head = np.flatnonzero(new)
        #: one entry for each document and shingle, by document
        self.key, self.ids = key[head], ids[head]
        self.tf = np.diff(np.append(head, len(key)))
        self.asked, self.entry, self.df = np.unique(self.key, return_inverse=True, return_counts=True)


def totals(blobs: list[bytes]) -> list[bytes]:
    """The documents of each shingle over all chunks: only where there are several."""
    parts = []
    for b in blobs:
        n = len(b) // 10
        parts.append((np.frombuffer(b[: 6 * n], np.uint8).reshape(n, 6), np.frombuffer(b[6 * n :], np.uint32)))
    wide = np.zeros((sum(len(k) for k, _ in parts), 8), np.uint8)
    wide[:, :6] = np.concatenate([k for k, _ in parts])
    keys = wide.view(np.uint64).ravel()
    counts = np.concatenate([c for _, c in parts]).astype(np.int64)
    order = np.argsort(keys, kind="stable")
    s = keys[order]
    new = np.ones(len(s), dtype=bool)
    new[1:] = s[1:] != s[:-1]
    number = np.cumsum(new) - 1
    total = np.empty(len(s), np.int64)
    total[order] = np.add.reduceat(counts[order], np.flatnonzero(new))[number]
    out, at = [], 0
    for k, _ in parts:
        mine = np.minimum(total[at : at + len(k)], 2**32 - 1).astype(np.uint32)
        out.append(pa.compress(mine.tobytes(), codec="zstd", asbytes=True))
        at += len(k)
    return out


def short_keys(keys: np.ndarray, bits: int) -> bytes:
    """Six bytes of each key, next to the ``bits`` that its bucket tells."""
    rest = (keys << np.uint64(bits)) >> np.uint64(16)
    return np.ascontiguousarray(rest.view(np.uint8).reshape(-1, 8)[:, :6]).tobytes()


def frequencies(s: Shingles, answer: dict[int, bytes], bits: int) -> np.ndarray:
    df = s.df.astype(np.int64)
    for bucket, a, b in cut(s.asked, bits):
        df[a:b] = np.frombuffer(pa.decompress(answer[bucket], decompressed_size=4 * (b - a), codec="zstd", asbytes=True), np.uint32)
    return df


def uniform(h: np.ndarray) -> np.ndarray:
    """(0, 1) from 64-bit hashes."""
    u = (h >> np.uint64(11)).astype(np.float64)
    u += 0.5
    u *= 2.0**-53
    return u


def gamma(first: np.ndarray, second: np.ndarray) -> np.ndarray:
    """Gamma(2,1) variables from two uniform ones each."""
    first *= second
    np.log(first, out=first)
    return np.negative(first, out=first)


def sample(key: np.ndarray, log_weight: np.ndarray, heads: np.ndarray, sizes: np.ndarray, draw: int) -> np.ndarray:
    """One consistent weighted sample (as a hash) of each document.

    ``heads`` are the places in ``key`` at which documents begin.
    """
    steps = np.arange(5 * draw + 1, 5 * draw + 6, dtype=np.uint64) * FACTORS[0]
    u = [uniform(mixed(key + step)) for step in steps]
    r, value, offset = gamma(u[0], u[1]), gamma(u[2], u[3]), u[4]
    t = log_weight / r
    t += offset
    np.floor(t, out=t)
    np.log(value, out=value)
    offset -= t
    offset -= 1.0
    r *= offset
    value += r
    least = np.minimum.reduceat(value, heads)
    at = np.flatnonzero(value == np.repeat(least, sizes))
    if len(at) > len(heads):  # the first of equal values
        group = np.searchsorted(heads, at, side="right") - 1
        at = at[np.concatenate([[True], group[1:] != group[:-1]])]
    return mixed(key[at] * FACTORS[1] + t[at].astype(np.int64).view(np.uint64))


def signatures(key: np.ndarray, weight: np.ndarray, heads: np.ndarray, tile: int = 1 << 14) -> np.ndarray:
    """documents x BANDS hashes, worked out for about ``tile`` entries at a time, which stay in a core's cache."""
    ends, log_weight = np.append(heads[1:], len(key)), np.log(weight)
    sizes, out = ends - heads, np.empty((len(heads), BANDS), np.uint64)
    cuts = np.flatnonzero(np.diff(heads // tile, prepend=-1))
    for a, b in zip(cuts, [*cuts[1:], len(heads)], strict=True):
        of, begin = slice(heads[a], ends[b - 1]), heads[a:b] - heads[a]
        for band in range(BANDS):
            h = np.full(b - a, np.uint64(band + 1))
            for row in range(ROWS):
                h = mixed(h * FACTORS[0] + sample(key[of], log_weight[of], begin, sizes[a:b], band * ROWS + row))
            out[a:b, band] = h
    return out


#: a text with words
WORDED = "[^ \\t\\n\\r\\x0B\\f]"


def text_key():
    """Of a row without doc_id: 62 bits of its text's hash, placed before other ids."""
    return F.shiftrightunsigned(F.xxhash64(F.coalesce(F.col("text").cast("binary"), F.lit(b""))), 2) + F.lit(NULL_ID)


def doc_key():
    """What a row counts as: its doc_id or, without one, its text."""
    return F.coalesce(F.col("doc_id").cast("long"), text_key())


def text_hash():
    return F.xxhash64(F.coalesce(F.col("text").cast("binary"), F.lit(b"")))


def other_texts(docs: DataFrame) -> DataFrame:
    """doc, first: doc_ids that come with different texts, and the least of their texts' hashes."""
    seen = docs.where(F.col("doc_id").isNotNull()).select(F.col("doc_id").cast("long").alias("_doc"), text_hash().alias("h"))
    return seen.groupBy("_doc").agg(F.min("h").alias("_first"), F.max("h").alias("_last")).where("_first <> _last").select("_doc", "_first")


def extra_key():
    """A key of its own, behind ordinary doc_ids, for a further text of a doc_id."""
    return F.shiftrightunsigned(F.xxhash64("doc_id", text_hash()), 2) + F.lit(1 << 62)


def keyed(docs: DataFrame) -> tuple[DataFrame, DataFrame | None]:
    """doc_id (as ``doc_key``) and text; and links a-b from a doc_id to its further texts, if any."""
    several = written(other_texts(docs), "several")
    if several.isEmpty():
        return docs.select(doc_key().alias("doc_id"), "text"), None
    rows = docs.select("doc_id", "text", doc_key().alias("_key")).join(several, F.col("_key") == F.col("_doc"), "left")
    further = F.col("_first").isNotNull() & (F.col("_first") != text_hash())
    links = rows.where(further).select(F.col("_key").alias("a"), extra_key().alias("b")).distinct()
    return rows.select(F.when(further, extra_key()).otherwise(F.col("_key")).alias("doc_id"), "text"), links


def looked_up(rows: DataFrame, found: DataFrame, key: str, total: int) -> DataFrame:
    """``rows`` joined to ``found`` (one row for each ``key``, with its row count ``n``), hot keys by broadcast.

    At most ``HOT`` keys can have more than one row in ``HOT``, so the broadcast is
    bounded, and what is shuffled has no key beyond that share (or ``GROUP`` rows).
    """
    hot, more = (F.col("n") * HOT > total) & (F.col("n") > GROUP), [c for c in found.columns if c != key]
    marked = rows.join(F.broadcast(found.where(hot).select(key, F.struct(*more).alias("_hot"))), key, "left")
    near_by = marked.where("_hot is not null").select(*rows.columns, *[F.col(f"_hot.{c}").alias(c) for c in more])
    far = marked.where("_hot is null").drop("_hot").join(found.where(~hot), key)
    return near_by.unionByName(far.select(*rows.columns, *more))


def unnamed(docs: DataFrame) -> DataFrame:
    """doc, copies and whether there are words, of the rows without doc_id."""
    rows = docs.where(F.col("doc_id").isNull()).select(text_key().alias("doc"), F.coalesce(F.col("text").cast("string").rlike(WORDED), F.lit(False)).alias("worded"))
    return rows.groupBy("doc", "worded").agg(F.count("*").alias("copies"))


def vectors(docs: DataFrame, words: int, threshold: float) -> DataFrame:
    """doc, key, tf and idf bytes, a hash of them, and band hashes, of documents that may have partners.

    ``docs`` has doc_id and text, one text for each doc_id, in any number of rows.
    """
    chunks = chunk_table(docs)
    bits = bucket_bits(chunks, 1.6)
    later = later_bits(bits)
    n_rows, n_docs = docs.select("doc_id").agg(F.count("*"), F.count_distinct("doc_id")).first()
    scale = np.log(1.0 + max(n_docs, 1))

    def ask(batches):
        for chunk in each_chunk(batches):
            s = Shingles(chunk, words)
            df = s.df.astype(np.uint32)
            yield requests_batch([(bucket, chunk.chunk_id, short_keys(s.asked[a:b], bits) + df[a:b].tobytes()) for bucket, a, b in cut(s.asked, bits)], later)

    joined = with_answers(chunks, answered(chunks.mapInArrow(ask, REQUEST), totals, later), "df")

    def weigh(batches):
        from xxhash import xxh3_128_digest

        for chunk in each_chunk(batches):
            s = Shingles(chunk, words)
            if not len(s.key):
                continue
            df = frequencies(s, chunk.answer("df"), bits)[s.entry]
            idf = 1.0 + np.log((1.0 + n_docs) / (1.0 + df)) / scale
            weight = s.tf * idf
            heads = np.flatnonzero(np.concatenate([[True], s.ids[1:] != s.ids[:-1]]))
            sizes = np.diff(np.append(heads, len(s.ids)))
            whole, shared = np.add.reduceat(weight, heads), np.add.reduceat(np.where(df > 1, weight, 0.0), heads)
            able = shared >= threshold * whole * (1.0 - 1e-9)
            pick = np.repeat(able, sizes)
            if not able.any():
                continue
            key, weight, tf, idf = s.key[pick], weight[pick], s.tf[pick].astype(np.uint32), idf[pick].astype(np.float32)
            ids, sizes = s.ids[heads[able]], sizes[able]
            ends = np.cumsum(sizes)
            heads = ends - sizes
            for lo in range(0, len(ids), 256):
                part = range(lo, min(lo + 256, len(ids)))
                of = slice(heads[lo], ends[part[-1]])
                bands = signatures(key[of], weight[of], heads[lo : lo + 256] - heads[lo])
                cols = [[x[heads[i] : ends[i]].tobytes() for i in part] for x in (key, tf, idf)]
                same = [xxh3_128_digest(k + t) for k, t in zip(cols[0], cols[1], strict=True)]
                yield pa.RecordBatch.from_arrays(
                    [pa.array(ids[lo : lo + 256], pa.int64()), *[pa.array(c, pa.binary()) for c in (*cols, same)], pa.array(list(bands.view(np.int64)), pa.list_(pa.int64()))],
                    ["doc", "key", "tf", "idf", "same", "bands"],
                )

    found = joined.mapInArrow(weigh, "doc long, key binary, tf binary, idf binary, same binary, bands array<long>")
    if n_rows > n_docs:  # an id in several chunks comes with one vector in each
        found = found.dropDuplicates(["doc"])
    return written(found, "vectors")


class Parts:
    """Union-find over positions."""

    def __init__(self, n: int):
        self.up = list(range(n))

    def root(self, x: int) -> int:
        while self.up[x] != x:
            self.up[x] = x = self.up[self.up[x]]
        return x

    def join(self, x: int, y: int) -> bool:
        x, y = self.root(x), self.root(y)
        self.up[max(x, y)] = min(x, y)
        return x != y


def similar_pairs(keys: list[bytes], tfs: list[bytes], idfs: list[bytes], threshold: float, step: int = 256, wide: int = 8192, parts: np.ndarray | None = None):
    """Pairs (i, j) of vectors whose weighted Jaccard similarity reaches the threshold.

    A shingle that occurs n times is n features of its weight, so the sum of the
    smaller weights is a product of 0/1 rows; features of one vector only drop out.
    With ``parts`` pairs within one part are of no interest, and blocks that hold a
    single part are not multiplied.
    """
    sizes = np.array([len(k) // 8 for k in keys])
    key = np.frombuffer(b"".join(keys), np.uint64)
    tf, idf = np.frombuffer(b"".join(tfs), np.uint32).astype(np.int64), np.frombuffer(b"".join(idfs), np.float32).astype(np.float64)
    row = np.repeat(np.arange(len(keys)), sizes)
    whole = np.bincount(row, weights=tf * idf, minlength=len(keys))
    nth = np.arange(int(tf.sum())) - np.repeat(np.cumsum(tf) - tf, tf)
    key, row, idf = np.repeat(key, tf), np.repeat(row, tf), np.repeat(idf, tf)
    key = np.where(nth > 0, mixed(key + nth.astype(np.uint64) * FACTORS[0]), key)
    _, feature, count = np.unique(key, return_inverse=True, return_counts=True)
    shared = count[feature] > 1
    row, feature, idf = row[shared], feature[shared], idf[shared]
    number = np.cumsum(count > 1) - 1
    feature, n_features = number[feature], int((count > 1).sum())
    order = np.lexsort((row, feature // wide))
    row, feature, idf = row[order], feature[order], idf[order]
    edge = np.searchsorted(feature // wide, np.arange(-(-n_features // wide) + 1))
    for a in range(0, len(keys), step):
        for b in range(a, len(keys), step):
            ra, rb = min(step, len(keys) - a), min(step, len(keys) - b)
            if parts is not None:
                both = np.concatenate([parts[a : a + ra], parts[b : b + rb]])
                if (both == both[0]).all():
                    continue
            common = np.zeros((ra, rb))
            for w, (lo, hi) in enumerate(zip(edge[:-1].tolist(), edge[1:].tolist(), strict=True)):
                r = row[lo:hi]
                left, right = slice(*np.searchsorted(r, (a, a + ra))), slice(*np.searchsorted(r, (b, b + rb)))
                if left.start == left.stop or right.start == right.stop:
                    continue
                x, y = np.zeros((ra, min(wide, n_features - w * wide))), np.zeros((rb, min(wide, n_features - w * wide)))
                f = feature[lo:hi] - w * wide
                x[r[left] - a, f[left]] = idf[lo:hi][left]
                y[r[right] - b, f[right]] = 1.0
                common += x @ y.T
            j = common / (whole[a : a + ra, None] + whole[None, b : b + rb] - common)
            yield from ((a + p, b + q) for p, q in zip(*np.nonzero(j >= threshold - 1e-6), strict=True) if a + p < b + q)


def verified(groups: DataFrame, threshold: float) -> DataFrame:
    """Links a-b within groups: as few as join what is similar.

    ``groups`` has g (the work unit), doc, part (what is joined already), key, tf, idf.
    """

    def compare(table: pa.Table) -> pa.Table:
        table = table.sort_by([("part", "ascending"), ("doc", "ascending")])
        docs, known = table.column("doc").to_pylist(), table.column("part").to_numpy()
        number = np.unique(known, return_inverse=True)[1]
        parts, a, b = Parts(int(number.max()) + 1), [], []
        for i, j in similar_pairs(*(table.column(c).to_pylist() for c in ("key", "tf", "idf")), threshold, parts=number):
            if parts.join(int(number[i]), int(number[j])):
                a.append(docs[i])
                b.append(docs[j])
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})

    return groups.groupBy("g").applyInArrow(compare, "a long, b long")


def forest(edges: DataFrame, rows: int = 1 << 17) -> DataFrame:
    """a, b: the same components by fewer edges, each from a doc to the smallest that its run of ``rows`` edges reaches."""

    def shorten(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, rows):
                part = batch.slice(at, rows)
                a, b = (part.column(k).to_numpy(zero_copy_only=False) for k in (0, 1))
                docs, number = np.unique(np.concatenate([a, b]), return_inverse=True)
                parts = Parts(len(docs))
                for x, y in zip(number[: len(a)].tolist(), number[len(a) :].tolist(), strict=True):
                    parts.join(x, y)
                roots = np.array([parts.root(x) for x in range(len(docs))], dtype=np.int64)
                child = np.flatnonzero(roots != np.arange(len(docs)))
                yield pa.RecordBatch.from_arrays([pa.array(docs[child]), pa.array(docs[roots[child]])], ["a", "b"])

    return edges.mapInArrow(shorten, "a long, b long")


def unsettled(edges: DataFrame) -> tuple[int, int, int]:
    """How many docs do not hang on one root that hangs on none, the largest degree, and the edges."""
    nodes = edges.select(F.col("a").alias("x"), F.lit(1).alias("child")).unionByName(edges.select(F.col("b").alias("x"), F.lit(0).alias("child")))
    per = nodes.groupBy("x").agg(F.sum("child").alias("c"), F.count("*").alias("n"))
    open_ = F.count_if((F.col("c") > 1) | ((F.col("c") == 1) & (F.col("n") > 1)))
    return tuple(per.agg(open_, F.coalesce(F.max("n"), F.lit(0)), F.coalesce(F.sum("c"), F.lit(0))).first())


def components(links: DataFrame) -> DataFrame:
    """doc, class: the smallest doc that links reach, by large-star and small-star steps.

    Each step is written to the shared folder; steps end when every doc hangs on
    its root.  Hubs are answered by broadcast (``looked_up``).
    """

    def star(edges: DataFrame, large: bool, total: int, hubs: bool) -> DataFrame:
        both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        if not large:
            both = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
        least = both.groupBy("a").agg(F.min("b").alias("m"), F.count("*").alias("n")).select("a", F.least("a", "m").alias("m"), "n")
        joined = looked_up(both, least, "a", total) if hubs else both.join(least, "a")
        if large:
            return joined.where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        return joined.select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(joined.select("a", F.col("m").alias("b"))).where("a <> b").distinct()

    edges = written(forest(links.where("a <> b")).distinct(), "edges")
    while True:
        left, most, total = unsettled(edges)
        if not left:
            return edges.select(F.col("a").alias("doc"), F.col("b").alias("class"))
        hubs = most > GROUP
        edges = written(star(star(edges, True, 2 * total, hubs), False, total, hubs), "edges")


def with_roots(found: DataFrame) -> DataFrame:
    """doc, class of ``components`` with the smallest docs themselves."""
    return found.unionByName(found.select(F.col("class").alias("doc"), "class").distinct())


def candidate_groups(reps: DataFrame) -> DataFrame:
    """doc, class: components of the ties in buckets, of documents with any tie."""
    members = reps.select("doc", F.explode("bands").alias("bucket"))
    least = members.groupBy("bucket").agg(F.min("doc").alias("least"), F.count("*").alias("n")).where("n > 1")
    ties = looked_up(members, least, "bucket", reps.count() * BANDS).where("doc <> least").select(F.col("least").alias("a"), F.col("doc").alias("b")).distinct()
    return written(with_roots(components(ties)), "groups")


def linked(groups: DataFrame, store: DataFrame, threshold: float) -> DataFrame:
    """Links a-b that join all similar documents of each candidate group.

    ``groups`` has doc, class.  Small groups are one unit of work.  A large group is
    first compared within blocks, then by one document of each part found so far;
    if parts remain, every document outside the largest meets all of the group.
    """
    shingles = store.select("doc", "key", "tf", "idf")
    sizes = groups.groupBy("class").agg(F.count("*").alias("n"))
    dealt = looked_up(groups, sizes, "class", groups.count()).withColumn("blocks", F.ceil(F.col("n") / F.lit(GROUP)).cast("int"))
    dealt = dealt.select("doc", "class", "n", "blocks", F.pmod(F.xxhash64("doc"), F.col("blocks")).cast("int").alias("i"))
    unit = F.struct(F.col("class"), F.col("i"), F.col("i").alias("j"))
    links = written(verified(dealt.select("doc", F.col("doc").alias("part"), unit.alias("g")).join(shingles, "doc"), threshold), "links")
    large = written(dealt.where("blocks > 1").select("doc", "class"), "large")
    if large.isEmpty():
        return links
    heads = parted_by(large, links).where("doc = part")
    few = heads.groupBy("class").agg(F.count("*").alias("heads")).where(f"heads between 2 and {GROUP}").select("class")
    once = F.struct("class", F.lit(0).alias("i"), F.lit(0).alias("j"))
    first = heads.join(few, "class", "left_semi").select("doc", "part", once.alias("g"))
    links = written(links.unionByName(verified(first.join(shingles, "doc"), threshold)), "links")
    parted = parted_by(large, links)
    left = written(remaining(parted), "left")
    if left.isEmpty():
        return links
    # blocks of the largest part do not meet each other, all others meet every block
    rest = looked_up(parted, left, "class", large.count())
    main = F.col("part") == F.col("main")
    mine = F.when(main, F.col("others") + F.pmod(F.xxhash64("doc"), F.col("mains"))).otherwise(F.pmod(F.xxhash64("doc"), F.col("others"))).cast("int")
    partners = F.when(main, F.sequence(F.lit(0), F.col("others") - 1)).otherwise(F.sequence(F.lit(0), F.col("others") + F.col("mains") - 1))
    met = rest.withColumn("mine", mine).withColumn("other", F.explode(partners))
    pair = F.struct("class", F.least("mine", "other").alias("i"), F.greatest("mine", "other").alias("j"))
    return written(links.unionByName(verified(met.select("doc", "part", pair.alias("g")).join(shingles, "doc"), threshold)), "links")


def remaining(parted: DataFrame) -> DataFrame:
    """class, main (its largest part), blocks of that part and of the others, n: groups in several parts."""
    counts = parted.groupBy("class", "part").agg(F.count("*").alias("k"))
    top = counts.groupBy("class").agg(F.max(F.struct("k", "part")).alias("top"), F.count("*").alias("parts"), F.sum("k").alias("n")).where("parts > 1")
    in_blocks = [F.ceil(x / F.lit(GROUP)).cast("int").alias(name) for x, name in ((F.col("top.k"), "mains"), (F.col("n") - F.col("top.k"), "others"))]
    return top.select("class", F.col("top.part").alias("main"), *in_blocks, "n")


def parted_by(groups: DataFrame, links: DataFrame) -> DataFrame:
    """doc, class, part: the part of each document under the links so far."""
    found = with_roots(components(links)).withColumnRenamed("class", "part")
    return written(groups.join(found, "doc", "left").select("doc", "class", F.coalesce("part", "doc").alias("part")), "parted")


def document_classes(docs: DataFrame, words: int = WORDS, threshold: float = THRESHOLD) -> DataFrame:
    """doc (as ``doc_key``) and class, of documents that share a class with another key."""
    rows, further = keyed(docs)
    store = vectors(rows, words, threshold)
    first = written(store.groupBy("same").agg(F.min("doc").alias("rep"), F.count("*").alias("n")), "first")
    copies = written(looked_up(store.select("doc", "same"), first.where("n > 1"), "same", store.count()).where("doc <> rep").select(F.col("rep").alias("a"), F.col("doc").alias("b")), "copies")
    reps = written(store.join(copies.select(F.col("b").alias("doc")), "doc", "left_anti"), "reps")
    links = linked(candidate_groups(reps), reps, threshold).unionByName(copies)
    if further is not None:
        links = links.unionByName(further)
    return written(with_roots(components(links)), "classes")


def near_duplicates(docs: DataFrame, words: int = WORDS, threshold: float = THRESHOLD) -> DataFrame:
    """doc_id, class_id and in_class (whether another document shares the class)."""
    classes = document_classes(docs, words, threshold)
    nulls = written(unnamed(docs), "unnamed")
    named = docs.where(F.col("doc_id").isNotNull()).select(F.col("doc_id").cast("long").alias("doc_id"), F.col("doc_id").cast("long").alias("doc"), F.lit(False).alias("again"))
    again = nulls.where(F.col("worded") & (F.col("copies") > 1)).select("doc", F.lit(True).alias("again"))
    rest = docs.where(F.col("doc_id").isNull()).select(F.lit(None).cast("long").alias("doc_id"), text_key().alias("doc")).join(again, "doc", "left").select("doc_id", "doc", F.coalesce("again", F.lit(False)).alias("again"))
    out = named.unionByName(rest).join(classes, "doc", "left")
    out = out.withColumn("in_class", F.col("class").isNotNull() | F.col("again")).withColumn("class", F.coalesce("class", "doc"))
    # only the lowest keys can be texts without doc_id; all others need no look
    low = F.col("class") < NULL_ID + (1 << 62)
    of_null = nulls.select(F.col("doc").alias("class"), F.lit(True).alias("nameless")).distinct()
    lowest = out.where(low).join(of_null, "class", "left").select("doc_id", F.when(F.col("nameless").isNull(), F.col("class")).alias("class_id"), "in_class")
    return out.where(~low).select("doc_id", F.col("class").alias("class_id"), "in_class").unionByName(lowest)
