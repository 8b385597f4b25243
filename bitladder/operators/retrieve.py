"""Retrieval: exhaustive match, selection, and the winners' attributes."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.codes import CodeSpec
from . import match, missprob, select

MODES = ("lane", "exact", "radix")
#: pairs from which on they are cut to queues before anything is shuffled
MANY_PAIRS = 1 << 20


def many(queries: DataFrame, index: DataFrame) -> bool:
    """Whether there are more than ``MANY_PAIRS`` pairs."""
    return queries.count() * index.count() > MANY_PAIRS


def scored_pairs(queries: DataFrame, index: DataFrame, qspec: CodeSpec, kspec: CodeSpec, exclude_self: bool = False) -> DataFrame:
    """query_id, pos, rank_key of every pair; ``pos`` is the keyword id where the index has none."""
    index = index if "pos" in index.columns else index.withColumn("pos", F.col("keyword_id"))
    pairs = match.exhaustive(queries, index, qspec, kspec)
    pairs = pairs.where("query_id <> keyword_id") if exclude_self else pairs
    return pairs.select("query_id", "pos", "rank_key")


def top_n(queries: DataFrame, index: DataFrame, qspec: CodeSpec, kspec: CodeSpec, N: int = 1000, lane_size: int = 256, lanes_per_block: int = 256, r: int = 1, mode: str = "lane", backend: str = "expr", exclude_self: bool = False, fan_in: int | None = None, where: str | None = None) -> DataFrame:
    """query_id, rank, pos, rank_key of each query's ``N`` best keywords.

    ``where`` filters keywords by attributes of the index (pushed to its scan).  The
    ``expr`` backend shuffles a row for every pair, or every lane, of a query; beyond
    ``MANY_PAIRS`` each partition first cuts its pairs in blocks, with the same result.
    """
    if not qspec.matches(kspec):
        raise ValueError("query and keyword codes come from different models")
    index = index.where(where) if where else index
    if mode not in MODES:
        raise ValueError(f"one of {MODES}")
    if backend == "block" or (not match.wide(qspec, kspec) and many(queries, index)):
        def cut(queues: DataFrame) -> DataFrame:
            if mode == "lane":
                queues = select.lane_cut(queues, r)
            if backend == "block":
                return select.merge_select(queues, N, fan_in, keep=("keyword_id",) if "keyword_id" in queues.columns else ())
            return select.radix_topn(queues, N) if mode == "radix" else select.merge_select(queues, N, fan_in)

        # radix selection looks at its rows twice, so its waves are written as they are
        radix = mode == "radix" and backend != "block"
        queues = block_queues(queries, index, qspec, kspec, N, lane_size if mode == "lane" else None, lanes_per_block, r, exclude_self, cut=None if radix else cut)
        return cut(queues) if radix else queues
    packed = match.key_bits(qspec, kspec) + select.place_bits(lane_size) <= 63

    def run(wave: DataFrame) -> DataFrame:
        pairs = scored_pairs(wave, index, qspec, kspec, exclude_self)
        if mode == "radix":
            return select.radix_topn(pairs, N)
        if mode == "exact":
            return exact_select(pairs, N)
        return select.merge_select(select.lane_select(pairs, lane_size, lanes_per_block, r, packed), N, fan_in)

    return match.in_waves(queries, run)


def exact_select(pairs: DataFrame, N: int) -> DataFrame:
    w = Window.partitionBy("query_id").orderBy(F.desc("rank_key"), "pos")
    return pairs.where("rank_key is not null").withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= N).select("query_id", "rank", "pos", "rank_key")


def exact_top_n(queries: DataFrame, index: DataFrame, qspec: CodeSpec, kspec: CodeSpec, N: int, exclude_self: bool = False) -> DataFrame:
    """The reference result: no queue, nothing lost."""
    return top_n(queries, index, qspec, kspec, N, mode="exact", exclude_self=exclude_self)


def above(queries: DataFrame, index: DataFrame, qspec: CodeSpec, kspec: CodeSpec, tau: float) -> DataFrame:
    """query_id, keyword_id, cosine of all pairs with cosine of at least ``tau``."""
    return match.exhaustive(queries, index, qspec, kspec).where(F.col("cosine") >= tau).select("query_id", "keyword_id", "cosine")


def block_queues(queries: DataFrame, index: DataFrame, qspec: CodeSpec, kspec: CodeSpec, N: int, lane_size: int | None, lanes_per_block: int, r: int = 1, exclude_self: bool = False, wave_rows: int | None = None, cut=None) -> DataFrame:
    """query_id, lane, pos, rank_key (and keyword_id, where the index has one): at most N rows per (partition, query).

    One Arrow pass per wave of queries: tiles of keywords are scored as products of
    unpacked codes (whole numbers, so floats hold them exactly), every lane's queue is
    kept in the worker, and the partition's best N leave.  Without
    ``lane_size`` every keyword is a lane (exact).  The index must keep a lane in
    one partition (``io.write_index`` does); else a lane has a queue in each.
    With ``cut`` each wave's rows pass through it before they are written, so that
    of several waves only what it leaves lies on disk.
    """
    spark = index.sparkSession
    kcols = kspec.columns()
    if match.wide(qspec, kspec):
        raise ValueError("codes too deep for the block backend: use backend='expr'")
    # scores are sifted as floats, with slack; keys of what is left are exact
    kind = match.exact_kind(qspec, kspec)
    slack = kind(max(1e-4, kspec.n * 4e-7) * math.sqrt(match.norm_bound(qspec)))
    wave_rows = wave_rows or max(1024, min(WAVE_ROWS, QUEUED // N))
    named = "keyword_id" in index.columns
    index = (index if "pos" in index.columns else index.withColumn("pos", F.col("keyword_id"))).select("pos", "norm_sq", *kcols, *(["keyword_id"] if named else []))
    if exclude_self and not named:
        raise ValueError("exclude_self needs keyword_id")
    names = ["query_id", "lane", "pos", "rank_key", *(["keyword_id"] if named else [])]
    schema = ", ".join(f"{c} long" for c in names)

    cores = spark.sparkContext.defaultParallelism
    if index.rdd.getNumPartitions() < cores:  # a small index: spread it, whole blocks of lanes together
        index = index.repartition(cores, F.floor(F.col("pos") / F.lit((lane_size or 1) * (lanes_per_block if lane_size else 64))))

    def wave(rows: list):
        ids, words = np.array([x[0] for x in rows], np.int64), np.array([x[1:] for x in rows], np.int64)
        sent = spark.sparkContext.broadcast((ids, words))

        def run(batches):
            qi, qw = sent.value
            asked, by_id = match.dense_codes(qw, qspec, kind), np.argsort(qi)
            kept, tile = Queues(len(qi), r, N), np.empty(SIDE * TILE, kind)
            for batch in batches:
                for at in range(0, batch.num_rows, TILE):
                    part = batch.slice(at, TILE)
                    pos, norm = part.column(0).to_numpy(zero_copy_only=False), part.column(1).to_numpy(zero_copy_only=False).astype(np.int64)
                    lane = pos if lane_size is None else pos // (lane_size * lanes_per_block) * lanes_per_block + pos % lanes_per_block
                    rows_ = np.lexsort((pos, lane))
                    rows_ = rows_[norm[rows_] > 0]  # a zero code is not ranked
                    if not len(rows_):
                        continue
                    k = match.dense_codes(np.stack([part.column(2 + c).to_numpy(zero_copy_only=False) for c in range(len(kcols))], axis=1)[rows_], kspec, kind)
                    own = part.column(2 + len(kcols)).to_numpy(zero_copy_only=False)[rows_] if named else pos[rows_]
                    pos, norm, lane = pos[rows_], norm[rows_], lane[rows_]
                    edge = np.flatnonzero(np.concatenate([[True], lane[1:] != lane[:-1]]))
                    number = np.cumsum(np.concatenate([[0], lane[1:] != lane[:-1]]))
                    unit = k * (1.0 / np.sqrt(norm)).astype(kind)[:, None]
                    row, col = match.same_ids(own, qi, by_id) if exclude_self else (by_id[:0], by_id[:0])
                    for a in range(0, len(qi), SIDE):
                        side = asked[a : a + SIDE]
                        score = np.matmul(side, unit.T, out=tile[: len(side) * len(k)].reshape(len(side), len(k)))
                        mine = (col >= a) & (col < a + SIDE)
                        score[col[mine] - a, row[mine]] = -np.inf
                        j, use = sifted(score, edge, number, kept.least[a : a + SIDE] - slack, N, r, slack)
                        for b in range(0, len(j), 1 << 15):
                            i, u = j[b : b + (1 << 15)], use[b : b + (1 << 15)]
                            dot = np.einsum("ij,ij->i", side[i], k[u]).astype(np.int64)
                            key = match.rank_keys(dot[:, None], norm[u], qspec, kspec)[:, 0]
                            kept.add(i + a, lane[u], pos[u], key, own[u], score[i, u])
                    kept.settle()
            i, lane, pos, key, own = kept.all()
            for b in range(0, len(i), 1 << 16):
                yield pa.RecordBatch.from_arrays([pa.array(x[b : b + (1 << 16)]) for x in (qi[i], lane, pos, key, *([own] if named else []))], names)

        found = index.mapInArrow(run, schema)
        return cut(found) if cut else found, sent

    out = match.wave_by_wave(spark, match.local_waves(queries.select("query_id", *qspec.columns("q_")), wave_rows), wave, schema)
    return cut(out) if cut and out.columns == names else out  # without queries nothing was cut


def lane_traffic(queries: DataFrame, index: DataFrame, lane_size: int, lanes_per_block: int, exclude_self: bool = False) -> DataFrame:
    """pairs, lanes: pairs that have a key, and lane queues that get one, over all queries.

    Blocks of lanes lie in one partition each and come in order of lanes, so a queue is
    counted where it is and nothing but sums leaves.
    """
    spark, schema = index.sparkSession, "pairs long, lanes long"
    index = index if "pos" in index.columns else index.withColumn("pos", F.col("keyword_id"))
    lane = select.lane_of(F.col("pos"), lane_size, lanes_per_block)
    block = F.floor(F.col("pos") / F.lit(lane_size * lanes_per_block))
    rows = index.where("norm_sq > 0").select(lane.alias("lane"), "keyword_id", block.alias("block")).repartition(spark.sparkContext.defaultParallelism, "block").sortWithinPartitions("lane").select("lane", "keyword_id")

    def wave(asked: list):
        sent = spark.sparkContext.broadcast(np.array([r[0] for r in asked], np.int64))

        def run(batches):
            qi, pairs, lanes, last = sent.value, 0, 0, None
            open_ = np.zeros(len(qi), bool)  # whose queue of the last lane has a keyword
            for batch in batches:
                for at in range(0, batch.num_rows, TILE):
                    part = batch.slice(at, TILE)
                    lane, own = (part.column(c).to_numpy(zero_copy_only=False) for c in (0, 1))
                    edge = np.flatnonzero(np.concatenate([[True], lane[1:] != lane[:-1]]))
                    for a in range(0, len(qi), 64):
                        mine = qi[a : a + 64]
                        valid = mine[:, None] != own[None, :] if exclude_self else np.ones((len(mine), len(own)), bool)
                        pairs += int(np.count_nonzero(valid))
                        filled = np.logical_or.reduceat(valid, edge, axis=1)
                        known = open_[a : a + 64] if lane[0] == last else np.zeros(len(mine), bool)
                        lanes += int(np.count_nonzero(filled)) - int(np.count_nonzero(filled[:, 0] & known))
                        open_[a : a + 64] = filled[:, -1] | (known if len(edge) == 1 else False)
                    last = lane[-1]
            yield pa.RecordBatch.from_arrays([pa.array([pairs], pa.int64()), pa.array([lanes], pa.int64())], ["pairs", "lanes"])

        return rows.mapInArrow(run, schema), sent

    found = match.wave_by_wave(spark, match.local_waves(queries.select("query_id"), WAVE_ROWS), wave, schema)
    return found.agg(F.coalesce(F.sum("pairs"), F.lit(0)).alias("pairs"), F.coalesce(F.sum("lanes"), F.lit(0)).alias("lanes"))


#: queries of a wave at most, and queue entries of a worker
WAVE_ROWS, QUEUED = 16_384, 400_000
#: keywords, and queries, that are scored at once
TILE, SIDE = 8192, 256


def sifted(score: np.ndarray, edge: np.ndarray, number: np.ndarray, least: np.ndarray, N: int, r: int, slack) -> tuple[np.ndarray, np.ndarray]:
    """(query row, keyword column) of scores that can still be among the N best of a queue.

    A score must reach ``least``, below the N-th best known; where none is known, the
    N-th best over the tile's lanes, and with queues of one its own lane's best.  What
    is below never returns: later entries of its lane that are worse are below it too.
    """
    fresh = np.flatnonzero(least == -np.inf)
    if not len(fresh):  # few queries find anything in a late tile
        live = np.flatnonzero(score.max(axis=1) >= least)
        at, use = np.divmod(np.flatnonzero(score[live] >= least[live, None]), score.shape[1])
        return live[at], use
    top = score[fresh] if len(edge) == score.shape[1] else np.maximum.reduceat(score[fresh], edge, axis=1)
    if top.shape[1] > N:
        at = top.shape[1] - N
        least = least.copy()
        least[fresh] = np.partition(top, at, axis=1)[:, at] - slack
    hit = (score >= least[:, None]) & (score > -np.inf)
    if r == 1 and len(edge) < score.shape[1]:
        hit[fresh] &= score[fresh] >= top[:, number] - slack
    return np.divmod(np.flatnonzero(hit), score.shape[1])


class Queues:
    """The queues of many queries, and the N best of each, over tiles of candidates.

    Candidates gather until there are as many as queue entries, then all queries' are
    cut at once.  ``least`` is the N-th best score of a query, once it has so many.
    """

    def __init__(self, queries: int, r: int, N: int, kind=np.float32):
        self.r, self.N, self.least = r, N, np.full(queries, -np.inf, kind)
        self.have: tuple | None = None
        self.fresh: list = []
        self.waiting = 0

    def add(self, *entry: np.ndarray) -> None:
        """Candidates (query number, lane, pos, key, own id, score)."""
        self.fresh.append(entry)
        self.waiting += len(entry[0])
        if self.waiting >= max(1 << 17, 0 if self.have is None else len(self.have[0])):
            self.cut()

    def settle(self) -> None:
        """After a tile: while some queries have no ``least``, it is looked for at once."""
        if self.fresh and (self.least == -np.inf).any():
            self.cut()

    def cut(self) -> None:
        cols = [np.concatenate(x) for x in zip(*([] if self.have is None else [self.have]), *self.fresh, strict=True)]
        self.fresh, self.waiting = [], 0
        i, lane, pos, key, _, score = cols
        order = np.lexsort((pos, -key, lane, i))
        order = order[place_among(lane[order], i[order]) < self.r]
        order = order[np.lexsort((pos[order], -key[order], i[order]))]
        order = order[place_among(i[order]) < self.N]
        self.have = tuple(x[order] for x in cols)
        i, score = self.have[0], self.have[5]
        start = np.flatnonzero(np.concatenate([[True], i[1:] != i[:-1]]))
        full = np.diff(np.append(start, len(i))) >= self.N
        self.least[i[start[full]]] = np.minimum.reduceat(score, start)[full]

    def all(self) -> tuple:
        """(query number, lane, pos, key, own id) of all that is kept, by query."""
        if self.fresh:
            self.cut()
        return (np.empty(0, np.int64),) * 5 if self.have is None else self.have[:5]


def place_among(*keys: np.ndarray) -> np.ndarray:
    """Number of each row among the rows before it that have the same keys, in sorted rows."""
    new = np.concatenate([[True], np.logical_or.reduce([k[1:] != k[:-1] for k in keys])]) if len(keys[0]) else np.empty(0, bool)
    at = np.arange(len(new))
    return at - np.maximum.accumulate(np.where(new, at, 0))


def attach(winners: DataFrame, keywords: DataFrame, key: str = "keyword_id") -> DataFrame:
    """Attributes of the winners only; ``pos`` or ``keyword_id`` joins them."""
    on = key if key in winners.columns else "pos"
    return winners.join(keywords, on)


def guard(C: int, N: int, lane_size: int, r: int = 1, least: float = 0.999) -> tuple[float, bool]:
    """Expected recall of lane selection and whether it reaches ``least``."""
    recall = 1.0 - missprob.expected_missed(C, N, lane_size, r) / N
    return recall, recall >= least
