"""Three-level selection: a short queue per lane, then per partition, then a merge.

A lane is the strided walk of one scoring thread over dense positions: lanes of
``lane_size`` keywords, ``lanes_per_block`` lanes side by side.  A queue of length
r can lose keywords; ``missprob`` has the exact odds.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def lane_of(pos: Column, lane_size: int, lanes_per_block: int) -> Column:
    """Lane of a position."""
    step = F.lit(lane_size * lanes_per_block).cast("long")
    return F.floor(pos / step).cast("long") * F.lit(lanes_per_block) + pos % F.lit(lanes_per_block)


def place_in_lane(pos: Column, lane_size: int, lanes_per_block: int) -> Column:
    """Number of a position within its lane, from 0."""
    return F.floor((pos % F.lit(lane_size * lanes_per_block).cast("long")) / F.lit(lanes_per_block)).cast("long")


def pos_of(lane: Column, place: Column, lane_size: int, lanes_per_block: int) -> Column:
    block = F.floor(lane / F.lit(lanes_per_block)).cast("long")
    return block * F.lit(lane_size * lanes_per_block).cast("long") + place * F.lit(lanes_per_block) + lane % F.lit(lanes_per_block)


def place_bits(lane_size: int) -> int:
    return max(1, math.ceil(math.log2(lane_size + 1)))


def lane_select(scored: DataFrame, lane_size: int, lanes_per_block: int, r: int = 1, packed: bool = True) -> DataFrame:
    """query_id, lane, pos, rank_key: the ``r`` best of each lane, ties to the smaller position.

    For r = 1 the key and the place in the lane are packed into one BIGINT and the
    lane's best is a hash aggregate whose partial step runs in the scan stage.
    Keys that leave no room for the place (``packed`` false, or decimals) take the
    way of longer queues.
    """
    lane = lane_of(F.col("pos"), lane_size, lanes_per_block)
    if r == 1 and packed and dict(scored.dtypes)["rank_key"] == "bigint":
        bits = place_bits(lane_size)
        place = place_in_lane(F.col("pos"), lane_size, lanes_per_block)
        word = F.shiftleft(F.col("rank_key"), bits) + (F.lit((1 << bits) - 1) - place)
        best = scored.where("rank_key is not null").select("query_id", lane.alias("lane"), word.alias("packed")).groupBy("query_id", "lane").agg(F.max("packed").alias("packed"))
        back = F.lit((1 << bits) - 1) - F.col("packed").bitwiseAND(F.lit((1 << bits) - 1).cast("long"))
        return best.select("query_id", "lane", pos_of(F.col("lane"), back, lane_size, lanes_per_block).alias("pos"), F.shiftright("packed", bits).alias("rank_key"))
    w = Window.partitionBy("query_id", "lane").orderBy(F.desc("rank_key"), "pos")
    rows = scored.where("rank_key is not null").select("query_id", lane.alias("lane"), "pos", "rank_key")
    return rows.withColumn("_r", F.row_number().over(w)).where(F.col("_r") <= r).drop("_r")


def lane_cut(queues: DataFrame, r: int = 1) -> DataFrame:
    """Queues of lanes that lie in several partitions, cut to ``r`` entries again.

    What a partition's cut to N dropped stays out: each of the N entries before it
    has its lane's best, here or elsewhere, before it too.
    """
    w = Window.partitionBy("query_id", "lane").orderBy(F.desc("rank_key"), "pos")
    return queues.repartition("query_id").withColumn("_r", F.row_number().over(w)).where(F.col("_r") <= r).drop("_r")


def merge_select(rows: DataFrame, N: int, fan_in: int | None = None, part: str = "lane", keep: tuple[str, ...] = ()) -> DataFrame:
    """query_id, rank, pos, rank_key (and ``keep``): the ``N`` best over all queues.

    With ``fan_in`` the rows are first cut to N within groups of ``fan_in``
    neighbouring parts, so that no task takes every partition's list at once.
    """
    rows = rows.select("query_id", "pos", "rank_key", *keep, *([part] if fan_in else []))
    if fan_in:
        w = Window.partitionBy("query_id", "_g").orderBy(F.desc("rank_key"), "pos")
        rows = rows.withColumn("_g", F.floor(F.col(part) / F.lit(fan_in))).withColumn("_r", F.row_number().over(w)).where(F.col("_r") <= N).drop("_g", "_r", part)
    w = Window.partitionBy("query_id").orderBy(F.desc("rank_key"), "pos")
    return rows.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= N).select("query_id", "rank", "pos", "rank_key", *keep)


def radix_topn(scored: DataFrame, N: int) -> DataFrame:
    """The same ``N`` best by a histogram of keys.

    Counts per (query, key) give each query's threshold key; a second pass keeps
    what reaches it, and only ties at the threshold are cut by position.  What is
    shuffled is one row per query and distinct key, then about N rows per query.
    """
    scored = scored.where("rank_key is not null").select("query_id", "pos", "rank_key")
    counts = scored.groupBy("query_id", "rank_key").agg(F.count("*").alias("n"))
    down = Window.partitionBy("query_id").orderBy(F.desc("rank_key"))
    before = F.sum("n").over(down) - F.col("n")
    threshold = counts.withColumn("before", before).where(F.col("before") < N).groupBy("query_id").agg(F.min("rank_key").alias("least"))
    kept = scored.join(threshold, "query_id").where("rank_key >= least")
    w = Window.partitionBy("query_id").orderBy(F.desc("rank_key"), "pos")
    return kept.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= N).select("query_id", "rank", "pos", "rank_key")
