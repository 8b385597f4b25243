"""The relational operators around retrieval, by the names the workloads use."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.text import letter_trigrams, words
from .match import checked_broadcast


def explode_terms(df: DataFrame, key: str, text: str = "text") -> DataFrame:
    """key, pos, term: one row per word."""
    return df.select(key, F.posexplode(words(F.col(text))).alias("pos", "term"))


def explode_trigrams(df: DataFrame, key: str, text: str = "text") -> DataFrame:
    return df.select(key, F.explode(F.flatten(F.transform(words(F.col(text)), lambda w: letter_trigrams(w)))).alias("trigram"))


def attach(df: DataFrame, dim: DataFrame, on, max_rows: int = 100_000) -> DataFrame:
    """Join a dimension: broadcast when it is small enough, else a plain join."""
    if dim.limit(max_rows + 1).count() <= max_rows:
        return df.join(F.broadcast(dim), on)
    return df.join(dim, on)


def join_large(left: DataFrame, right: DataFrame, on, how: str = "merge", kind: str = "inner") -> DataFrame:
    """Two large sides: ``merge`` (sort-merge) or ``shuffle_hash``."""
    return left.join(right.hint(how), on, kind)


def survivors(df: DataFrame, kept: DataFrame, on) -> DataFrame:
    return df.join(kept, on, "left_semi")


def minus_pairs(df: DataFrame, known: DataFrame, on) -> DataFrame:
    return df.join(known, on, "left_anti")


def nested_loop(df: DataFrame, small: DataFrame, condition: Column) -> DataFrame:
    """Theta join with a small side of checked size."""
    return df.join(checked_broadcast(small), condition)


def rolling_rate(events: DataFrame, seconds: int = 86_400) -> DataFrame:
    """Clicks over views of a user in the last ``seconds``."""
    t = F.unix_timestamp(F.col("ts").cast("timestamp"))
    w = Window.partitionBy("user_id").orderBy(t).rangeBetween(-seconds, 0)
    clicks, views = F.sum(F.when(F.col("event_type") == "click", 1).otherwise(0)).over(w), F.sum(F.when(F.col("event_type") == "view", 1).otherwise(0)).over(w)
    return events.select("event_id", "user_id", clicks.alias("clicks"), views.alias("views"), F.try_divide(clicks.cast("double"), views).alias("ctr"))


def smoothed(history: DataFrame, key: str = "epoch", value: str = "loss", rows: int = 7, by: str | None = None) -> DataFrame:
    """Moving average of a training history."""
    w = (Window.partitionBy(by) if by else Window.partitionBy(F.lit(1))).orderBy(key).rowsBetween(-(rows - 1), 0)
    return history.withColumn("smooth", F.avg(value).over(w))


def per_query_top(spark, table: str, by: str, order: str, n: int) -> DataFrame:
    """Best rows of each key by a correlated lateral subquery (planned as a window)."""
    return spark.sql(f"SELECT t.* FROM (SELECT DISTINCT {by} FROM {table}) k, LATERAL (SELECT * FROM {table} x WHERE x.{by} = k.{by} ORDER BY {order} LIMIT {n}) t")


#: distinct items of one heavy-item sketch, well below the 10,000 that it tracks
PER_SKETCH = 5_000


def heavy_items(df: DataFrame, column: str, k: int = 5) -> DataFrame:
    """item, count: the ``k`` most frequent values.

    A sketch that meets more distinct items than it tracks names fewer than ``k`` where none
    stands out, so items are dealt by hash to as many sketches as their number asks for.
    """
    known = df.where(F.col(column).isNotNull()).select(column)
    groups = max(1, -(-(known.agg(F.approx_count_distinct(column)).first()[0] or 0) // PER_SKETCH))
    parts = known.groupBy(F.pmod(F.xxhash64(column), F.lit(groups)).alias("_g")).agg(F.expr(f"approx_top_k({column}, {k})").alias("top"))
    return parts.select(F.inline("top")).orderBy(F.desc("count"), "item").limit(k)


def approx_profile(df: DataFrame, column: str) -> DataFrame:
    """Approximate distinct count, quantiles and heavy items."""
    rest = df.agg(F.approx_count_distinct(column).alias("distinct"), F.percentile_approx(column, [0.5, 0.95]).alias("quantiles"))
    return rest.crossJoin(F.broadcast(heavy_items(df, column).agg(F.collect_list(F.struct("item", "count")).alias("top"))))


def exact_profile(df: DataFrame, x: str, y: str) -> DataFrame:
    """Median, spread and correlation."""
    return df.agg(F.percentile(x, 0.5).alias("median"), F.stddev_samp(x).alias("spread"), F.corr(x, y).alias("corr"))


def page(df: DataFrame, order: list, size: int, number: int) -> DataFrame:
    """One page of an ordered result."""
    return df.orderBy(*order).offset(size * number).limit(size)
