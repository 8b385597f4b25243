"""Clicked pairs, cross sampling and sample groups."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def item_of(props: Column) -> Column:
    """The item of an event."""
    return F.get_json_object(props, "$.k").cast("long")


def numbered(pairs: DataFrame, *order: str) -> DataFrame:
    """``pair_id`` from the pair itself: stable, no global sort."""
    return pairs.select(F.xxhash64(*order).alias("pair_id"), "*")


#: bits of a turn's number within its id
TURN_BITS = 24


def turn_id(conversation: Column, turn: Column) -> Column:
    """One BIGINT for (conversation, turn); an error where either leaves its bits."""
    c, t = conversation.cast("long"), turn.cast("long")
    fits = t.between(0, (1 << TURN_BITS) - 2) & c.between(-(1 << (62 - TURN_BITS)), (1 << (62 - TURN_BITS)) - 1)
    return F.when(fits, F.shiftleft(c, TURN_BITS) + t).when(c.isNotNull() & t.isNotNull(), F.raise_error(F.lit("conversation or turn out of range")).cast("long"))


def clicked_pairs(events: DataFrame) -> DataFrame:
    """Distinct (query_id, keyword_id) of click events: user and item.  One shuffle."""
    clicks = events.where("event_type = 'click'").select(F.col("user_id").alias("query_id"), item_of(F.col("props")).alias("keyword_id"))
    return numbered(clicks.where("query_id is not null and keyword_id is not null").dropDuplicates(), "query_id", "keyword_id")


def turn_pairs(conversations: DataFrame) -> DataFrame:
    """A user turn and the assistant turn right after it."""
    w = Window.partitionBy("conv_id").orderBy("turn")
    rows = conversations.select("conv_id", "turn", "role", "text", F.lead("role").over(w).alias("next_role"), F.lead("text").over(w).alias("k_text"))
    hit = rows.where("role = 'user' and next_role = 'assistant'")
    key = turn_id(F.col("conv_id"), F.col("turn"))
    return hit.select(key.alias("pair_id"), key.alias("query_id"), (key + 1).alias("keyword_id"), F.col("text").alias("q_text"), "k_text")


def line_pairs(documents: DataFrame) -> DataFrame:
    """A document's first line and the rest of it."""
    at = F.instr("text", "\n")
    return documents.where(at > 0).select(
        F.col("doc_id").alias("pair_id"), F.col("doc_id").alias("query_id"), F.col("doc_id").alias("keyword_id"), F.expr("substring(text, 1, instr(text, '\n') - 1)").alias("q_text"), F.expr("substring(text, instr(text, '\n') + 1)").alias("k_text")
    )


def page_pairs(pages: DataFrame) -> DataFrame:
    """A page's title and its body without tags."""
    title = F.regexp_extract("html", r"(?is)<title[^>]*>(.*?)</title>", 1)
    body = F.trim(F.regexp_replace(F.regexp_replace(F.regexp_replace("html", r"(?is)<(script|style|head)[^>]*>.*?</\1>", " "), r"(?s)<[^>]+>", " "), r"\s+", " "))
    return pages.select(F.col("page_id").alias("pair_id"), F.col("page_id").alias("query_id"), F.col("page_id").alias("keyword_id"), title.alias("q_text"), body.alias("k_text"))


def cross_sample(pairs: DataFrame, negatives: int = 10, seed: int = 0, block: int = 1024, drop_false_negatives: bool = False, order: Column | None = None, placed: bool = False) -> DataFrame:
    """group_id, query_id, keyword_id, is_pos: each pair and ``negatives`` others' keywords.

    Pairs are dealt to hash blocks of about ``block`` and numbered there; the
    partner of a slot is a fixed offset on, so this is an equi-join on (block,
    slot).  Blocks are made larger until each holds more than ``negatives``
    pairs, so every pair gets exactly that many; a table without so many is an
    error.  ``drop_false_negatives`` takes known pairs away again.  ``placed`` adds
    ``place``: the group's block and slot, in whose order neighbours share keywords.
    """
    n = pairs.count()
    if 0 < n <= negatives:
        raise ValueError(f"{negatives} negatives need more than {negatives} pairs, not {n}")

    def block_of(blocks: int) -> Column:
        return F.pmod(F.xxhash64("pair_id", F.lit(seed + 1)), F.lit(blocks))

    blocks = max(1, n // max(block, 2 * negatives))
    while blocks > 1 and pairs.groupBy(block_of(blocks)).count().agg(F.count("*"), F.min("count")).where(f"`count(1)` < {blocks} or `min(count)` <= {negatives}").count():
        blocks //= 2
    order = order if order is not None else F.xxhash64("pair_id", F.lit(seed))
    slots = Window.partitionBy("block").orderBy("o", "pair_id")
    dealt = (
        pairs.select("pair_id", "query_id", "keyword_id", order.alias("o"))
        .withColumn("block", block_of(blocks))
        .withColumn("slot", F.row_number().over(slots) - 1)
        .withColumn("size", F.count("*").over(Window.partitionBy("block")))
    )
    place = ["place"] if placed else []
    dealt = dealt.withColumn("place", F.shiftleft(F.col("block").cast("long"), 32) + F.col("slot")) if placed else dealt
    step = F.explode(F.sequence(F.lit(1), F.lit(negatives)))
    asks = dealt.select(F.col("pair_id").alias("group_id"), *place, "query_id", "block", "size", "slot", step.alias("k")).withColumn("slot", ((F.col("slot") + F.col("k")) % F.col("size")).cast("int"))
    gives = dealt.select("block", "slot", "keyword_id")
    negative = asks.join(gives, ["block", "slot"]).select("group_id", *place, "query_id", "keyword_id", F.lit(False).alias("is_pos"))
    if drop_false_negatives:
        known = pairs.select("query_id", "keyword_id").distinct()
        negative = negative.join(known, ["query_id", "keyword_id"], "left_anti").select("group_id", *place, "query_id", "keyword_id", "is_pos")
    positive = dealt.select(F.col("pair_id").alias("group_id"), *place, "query_id", "keyword_id", F.lit(True).alias("is_pos"))
    return positive.unionByName(negative)


def groups(samples: DataFrame) -> DataFrame:
    """One row per group, its members sorted (positive first, then by keyword)."""
    member = F.struct((~F.col("is_pos")).alias("neg"), "keyword_id", "is_pos")
    packed = samples.groupBy("group_id", "query_id").agg(F.sort_array(F.collect_list(member)).alias("m"))
    return packed.select("group_id", "query_id", F.transform("m", lambda x: F.struct(x["keyword_id"].alias("keyword_id"), x["is_pos"].alias("is_pos"))).alias("members"))


def split_by_time(events: DataFrame, cut: str) -> DataFrame:
    """Adds ``fold``: train before ``cut``, validation from it on."""
    return events.withColumn("fold", F.when(F.col("ts") < F.lit(cut).cast("timestamp_ntz"), F.lit("train")).otherwise(F.lit("validation")))


def split_by_hash(pairs: DataFrame, key: str, share: int = 10) -> DataFrame:
    """Adds ``fold`` by a hash of ``key``: one in ``share`` is validation."""
    return pairs.withColumn("fold", F.when(F.pmod(F.xxhash64(key), F.lit(share)) == 0, F.lit("validation")).otherwise(F.lit("train")))


def attribute(views: DataFrame, clicks: DataFrame, within: str = "30 minutes") -> DataFrame:
    """Clicks with each view of the same user and item at most ``within`` before."""
    v = views.select("user_id", item_of(F.col("props")).alias("item"), F.col("ts").alias("view_ts"), F.col("event_id").alias("view_id"))
    c = clicks.select("user_id", item_of(F.col("props")).alias("item"), F.col("ts").alias("click_ts"), F.col("event_id").alias("click_id"))
    return c.join(v, ["user_id", "item"]).where(f"view_ts <= click_ts and view_ts >= click_ts - interval {within}")


def asof(clicks: DataFrame, views: DataFrame) -> DataFrame:
    """Each click with the latest earlier view of the same user: union and one window."""
    c = clicks.select("user_id", "ts", F.col("event_id").alias("click_id"), F.lit(None).cast("long").alias("view_id"), F.lit(1).alias("side"))
    v = views.select("user_id", "ts", F.lit(None).cast("long").alias("click_id"), F.col("event_id").alias("view_id"), F.lit(0).alias("side"))
    w = Window.partitionBy("user_id").orderBy("ts", "side", "view_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    rows = c.unionByName(v).withColumn("last_view", F.last("view_id", ignorenulls=True).over(w))
    return rows.where("click_id is not null").select("click_id", "user_id", F.col("last_view").alias("view_id"))
