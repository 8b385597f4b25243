"""Exact top-k inner products by a three-phase uniform threshold.

The components of a vector are dealt to ``lists`` blocks; a block's partial
product is a vector's score in that block's list.

1. Each partition sends, for each query, the ``k`` best entries of each list with
   their full scores.  The k-th best score over all of these is a safe cutoff:
   the true k-th is not below it.
2. The cutoff is broadcast.  A score of at least ``c`` needs a partial product of
   at least ``c / lists`` in some list (the uniform threshold), so entries that
   reach it are collected, and dropped again if what their other lists can add at
   most (less than the threshold each) leaves them below the cutoff.
3. What remains is scored exactly and ranked, first within the partition and then
   over all of them; ties go to the smaller id.

Queries pass in waves of bounded size, so what is broadcast never grows with the
data; candidates are read in blocks by their own partitions and never shuffled.

Components are floor(256 * x) as integers.  Vectors that are null or empty, or
hold a null or non-finite component, take no part, nor does a null vec_id; vectors
of another length than the query are no candidates.  Integers beyond ``SAFE`` use
exact Python integers; scores beyond a long are held at its end.  A query's own
vec_id is no candidate.  Equal rows count once; an id that comes with different
vectors is asked with the first of them and can be found with each.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import written

SAFE = 2**20
WAVE = 4096
BLOCK = 8192
LONG = 2**63
FOUND = "query_id long, vec_id long, score long"


def usable(vectors: DataFrame) -> DataFrame:
    """vec_id and the components as doubles, of the vectors that take part."""
    finite = F.forall("embedding", lambda e: e.isNotNull() & ~F.isnan(e) & (F.abs(e) < F.lit(float("inf"))))
    kept = vectors.where(F.col("vec_id").isNotNull() & F.col("embedding").isNotNull() & (F.size("embedding") > 0) & finite)
    return kept.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("v"))


def whole(x: np.ndarray) -> np.ndarray:
    return np.floor(256.0 * x)


def matrices(batch: pa.RecordBatch):
    """(ids, whole-number matrix) for each vector length in a batch."""
    ids = batch.column(0).to_numpy(zero_copy_only=False)
    sizes = np.asarray(batch.column(1).value_lengths())
    values = whole(batch.column(1).flatten().to_numpy(zero_copy_only=False))
    ends = np.cumsum(sizes)
    for d in np.unique(sizes).tolist():
        rows = np.flatnonzero(sizes == d)
        yield distinct_rows(ids[rows], values[(ends[rows] - d)[:, None] + np.arange(d)])


def distinct_rows(ids: np.ndarray, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Each (id, vector) once, in the order of its first row."""
    _, number, count = np.unique(ids, return_inverse=True, return_counts=True)
    seen, keep = set(), np.ones(len(ids), bool)
    for i in np.flatnonzero(count[number] > 1).tolist():
        row = (int(ids[i]), (x[i] + 0.0).tobytes())  # -0.0 is 0.0
        keep[i] = row not in seen
        seen.add(row)
    return ids[keep], x[keep]


def best_pairs(ids: np.ndarray, scores: np.ndarray, n: int) -> tuple[list, list]:
    """The n best different (id, score) pairs: largest score, then smaller id."""
    if scores.dtype == object:
        pairs = sorted(set(zip((-scores).tolist(), ids.tolist(), strict=True)))[:n]
        return [i for _, i in pairs], [-s for s, _ in pairs]
    order = np.lexsort((ids, -scores))
    ids, scores = ids[order], scores[order]
    new = np.ones(len(ids), bool)
    new[1:] = (ids[1:] != ids[:-1]) | (scores[1:] != scores[:-1])
    return ids[new][:n], scores[new][:n]


def small(x: np.ndarray, q: np.ndarray) -> bool:
    """Whether products stay exact in doubles."""
    return max(np.abs(x).max(initial=0), np.abs(q).max(initial=0)) <= SAFE


integers = np.vectorize(int, otypes=[object])


def blocks_of(d: int, lists: int) -> list[slice]:
    edges = np.linspace(0, d, lists + 1).astype(int)
    return [slice(a, b) for a, b in zip(edges[:-1], edges[1:], strict=True) if b > a]


class Best:
    """The k best (score, smaller id first) of each query, in bounded memory."""

    def __init__(self, k: int):
        self.k, self.found = k, {}

    def add(self, query: int, ids, scores) -> None:
        mine = self.found.setdefault(query, set())
        mine.update((-int(s), int(v)) for s, v in zip(scores, ids, strict=True))
        if len(mine) > 8 * self.k:
            self.found[query] = set(sorted(mine)[: self.k])

    def batch(self) -> pa.RecordBatch:
        rows = [(q, v, max(-LONG, min(LONG - 1, -s))) for q, mine in self.found.items() for s, v in sorted(mine)[: self.k]]
        cols = list(zip(*rows, strict=True)) if rows else [(), (), ()]
        return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], ["query_id", "vec_id", "score"])


def wave(candidates: DataFrame, ids: np.ndarray, q: np.ndarray, k: int, lists: int) -> DataFrame:
    """The k best candidates of each query of one wave (queries of one length)."""
    spark = candidates.sparkSession
    d = q.shape[1]
    parts = blocks_of(d, lists)
    sent = spark.sparkContext.broadcast((ids, q))

    def tiles(batches):
        """Blocks of candidates against blocks of queries, with partial products."""
        all_ids, all_q = sent.value
        for batch in batches:
            for a in range(0, batch.num_rows, BLOCK):
                for rows, x in matrices(batch.slice(a, BLOCK)):
                    if x.shape[1] != d:
                        continue
                    for b in range(0, len(all_ids), 256):
                        qi, qv = all_ids[b : b + 256], all_q[b : b + 256]
                        left, right = (x, qv) if small(x, qv) else (integers(x), integers(qv))
                        yield rows, qi, [np.dot(left[:, s], right[:, s].T) for s in parts]

    def local_lists(batches):
        best = Best(k)
        for rows, qi, partial in tiles(batches):
            total, own = sum(partial), rows[:, None] == qi[None, :]
            n = min(k + 1, len(rows))  # the query itself may be among them
            for p in partial:
                top = np.argsort(-p, axis=0)[:n] if p.dtype == object else np.argpartition(-p, n - 1, axis=0)[:n]
                for j, i in enumerate(qi.tolist()):
                    r = top[:, j][~own[top[:, j], j]]
                    best.add(i, rows[r], total[r, j])
        yield best.batch()

    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    lists_df = candidates.mapInArrow(local_lists, FOUND).distinct().withColumn("rank", rank).where(F.col("rank") <= k)
    cut = lists_df.groupBy("query_id").agg(F.min("score").alias("c"), F.count("*").alias("n")).where(F.col("n") >= k)
    safe = {r["query_id"]: r["c"] for r in cut.collect()}  # one row for each query of this wave
    cutoff = spark.sparkContext.broadcast(np.array([float(safe.get(i, -np.inf)) for i in ids.tolist()]))

    def sufficient(batches):
        place, best = {i: n for n, i in enumerate(ids.tolist())}, Best(k)
        for rows, qi, partial in tiles(batches):
            c = cutoff.value[[place[i] for i in qi.tolist()]]
            # doubles may round a large cutoff; a little slack keeps it safe
            c = np.where(np.abs(c) < 2.0**50, c, c - np.abs(c) * 1e-15)
            threshold = c / len(parts)
            reach = [(p >= threshold).astype(bool) for p in partial]
            upper = sum(np.where(r, p, threshold[None, :]) for r, p in zip(reach, partial, strict=True))
            collected = np.logical_or.reduce(reach) & (upper >= c).astype(bool) & (rows[:, None] != qi[None, :])
            collected |= np.isneginf(c)[None, :] & (rows[:, None] != qi[None, :])
            for j in np.flatnonzero(collected.any(axis=0)).tolist():
                r = np.flatnonzero(collected[:, j])
                exact = sum(p[r, j] for p in partial)
                good = (exact >= c[j]).astype(bool)
                found, exact = rows[r[good]], exact[good]
                if len(found) > 8 * k:  # only the k best of a partition can be among the k best
                    found, exact = best_pairs(found, exact, k)
                best.add(int(qi[j]), found, exact)
        yield best.batch()

    found = candidates.mapInArrow(sufficient, FOUND).distinct()
    return found.withColumn("rank", rank.cast("int")).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def top_k(vectors: DataFrame, queries: DataFrame, k: int = 5, lists: int = 2, wave_rows: int = WAVE) -> DataFrame:
    """query_id, rank, vec_id, score of each query's ``k`` best vectors.

    Both inputs have vec_id and embedding.  Queries are streamed to the driver in
    waves of ``wave_rows``, never held together; beyond the first, each wave is
    written to the shared folder before the next begins.
    """
    spark = vectors.sparkSession
    candidates = usable(vectors)
    results, rows, last = [], [], None

    def flush(final: bool):
        for d in sorted({len(v) for _, v in rows}):
            mine = [(i, v) for i, v in rows if len(v) == d]
            found = wave(candidates, np.array([i for i, _ in mine], dtype=np.int64), whole(np.array([v for _, v in mine], dtype=np.float64)), k, lists)
            results.append(found if final and not results else written(found, f"wave{len(results)}"))
        rows.clear()

    for r in usable(queries).distinct().orderBy("vec_id", "v").toLocalIterator():
        if r["vec_id"] == last:
            continue
        if len(rows) >= wave_rows:
            flush(final=False)
        last = r["vec_id"]
        rows.append((last, r["v"]))
    flush(final=True)
    if not results:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    out = results[0]
    for more in results[1:]:
        out = out.unionByName(more)
    return out
