"""Queries, clicks and keywords as streams."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StreamingQuery

from ..operators.samples import item_of


def events_stream(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """The event log as a stream; ``ts`` becomes a TIMESTAMP, as watermarks need."""
    schema = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def run(df: DataFrame, checkpoint: str, sink: Callable[[DataFrame, int], None], mode: str = "append") -> StreamingQuery:
    """All available input through ``sink`` per micro-batch."""
    return df.writeStream.outputMode(mode).option("checkpointLocation", checkpoint).foreachBatch(sink).trigger(availableNow=True).start()


def stream_top_n(queries: DataFrame, index, model, N: int, path: str, checkpoint: str, lookup: DataFrame) -> StreamingQuery:
    """Each micro-batch of queries is answered by the static index and appended to ``path``.

    ``queries`` has query_id; ``lookup`` holds the coded queries by query_id.
    """

    def answer(batch: DataFrame, number: int) -> None:
        asked = lookup.join(batch.select("query_id").distinct(), "query_id", "left_semi")
        found = index.top_n(asked, N, mode="exact", backend="block")
        found.withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{path}/batch={number}")

    return run(queries, checkpoint, answer)


def stream_pairs(events: DataFrame, within: str = "30 minutes", lateness: str = "10 minutes", outer: bool = False) -> DataFrame:
    """Clicks joined to views of the same user and item at most ``within`` before."""
    views = events.where("event_type = 'view'").select(F.col("user_id").alias("v_user"), item_of(F.col("props")).alias("v_item"), F.col("ts").alias("view_ts"), F.col("event_id").alias("view_id")).withWatermark("view_ts", lateness)
    clicks = events.where("event_type = 'click'").select("user_id", item_of(F.col("props")).alias("item"), F.col("ts").alias("click_ts"), F.col("event_id").alias("click_id")).withWatermark("click_ts", lateness)
    on = F.expr(f"user_id = v_user AND item = v_item AND view_ts <= click_ts AND view_ts >= click_ts - interval {within}")
    joined = clicks.join(views, on, "left_outer" if outer else "inner")
    return joined.select("user_id", "item", "click_ts", "click_id", "view_id", "view_ts")


def stream_unique_pairs(events: DataFrame, lateness: str = "1 hour") -> DataFrame:
    """(query_id, keyword_id) of clicks, each once within the watermark: bounded state."""
    clicks = events.where("event_type = 'click'").select(F.col("user_id").alias("query_id"), item_of(F.col("props")).alias("keyword_id"), "ts")
    return clicks.withWatermark("ts", lateness).dropDuplicatesWithinWatermark(["query_id", "keyword_id"])


def stream_rates(events: DataFrame, window: str = "1 hour", slide: str | None = None, gap: str | None = None, lateness: str = "10 minutes") -> DataFrame:
    """Views, clicks and click-through rate in tumbling, sliding or session windows."""
    marked = events.withWatermark("ts", lateness)
    view, click = F.count_if(F.col("event_type") == "view"), F.count_if(F.col("event_type") == "click")
    if gap:
        grouped = marked.groupBy(F.session_window("ts", gap).alias("w"), "user_id")
    else:
        grouped = marked.groupBy(F.window("ts", window, slide).alias("w") if slide else F.window("ts", window).alias("w"))
    out = grouped.agg(view.alias("views"), click.alias("clicks"))
    return out.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *(["user_id"] if gap else []), "views", "clicks", F.try_divide("clicks", "views").alias("ctr"))


def late_report(query: StreamingQuery) -> int:
    """Rows that came too late, over all progress reports."""
    return sum(int(s.get("numRowsDroppedByWatermark", 0)) for p in query.recentProgress for s in (p if isinstance(p, dict) else __import__("json").loads(p.json))["stateOperators"])


def stream_index_upsert(docs: DataFrame, encode: Callable[[DataFrame], DataFrame], path: str, checkpoint: str) -> StreamingQuery:
    """Encodes new keywords and appends them as a version; ``read_latest`` sees the newest."""

    def upsert(batch: DataFrame, number: int) -> None:
        encode(batch).withColumn("version", F.lit(number)).write.mode("overwrite").parquet(f"{path}/batch={number}")

    return run(docs, checkpoint, upsert)


def read_latest(spark: SparkSession, path: str, base: DataFrame | None = None) -> DataFrame:
    """Base and deltas, the newest version of each keyword."""
    rows = spark.read.parquet(path).drop("batch")
    if base is not None:
        rows = rows.unionByName(base.withColumn("version", F.lit(-1)))
    w = Window.partitionBy("keyword_id").orderBy(F.desc("version"))
    return rows.withColumn("_r", F.row_number().over(w)).where("_r = 1").drop("_r")


def stream_keyword_top_n(scored: DataFrame, N: int, path: str, checkpoint: str) -> StreamingQuery:
    """Running best N per query over a stream of scored keywords, merged batch by batch.

    ``scored`` has query_id, keyword_id, score.  State is the stored result: at
    most N rows per query.
    """

    def merge(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        w = Window.partitionBy("query_id").orderBy(F.desc("score"), "keyword_id")
        rows = batch.select("query_id", "keyword_id", "score")
        if number:
            rows = rows.unionByName(spark.read.parquet(f"{path}/state={number - 1}").select("query_id", "keyword_id", "score"))
        best = rows.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= N)
        best.write.mode("overwrite").parquet(f"{path}/state={number}")

    return run(scored, checkpoint, merge)


class TopNState(StatefulProcessor):
    """The same as a stateful operator: N rows of list state per query."""

    def __init__(self, N: int):
        self.N = N

    def init(self, handle) -> None:
        self.best = handle.getListState("best", "score double, keyword_id long")

    def handleInputRows(self, key, rows, timerValues):  # noqa: N802, N803
        import pandas as pd

        have = [(float(s), int(k)) for s, k in self.best.get()] if self.best.exists() else []
        for part in rows:
            have += list(zip(part["score"].astype(float), part["keyword_id"].astype(int), strict=True))
        have = sorted(set(have), key=lambda x: (-x[0], x[1]))[: self.N]
        self.best.put([(s, k) for s, k in have])
        yield pd.DataFrame([(int(key[0]), i + 1, k, s) for i, (s, k) in enumerate(have)], columns=["query_id", "rank", "keyword_id", "score"])

    def close(self) -> None:
        pass


def run_stateful_top_n(scored: DataFrame, N: int, path: str, checkpoint: str) -> StreamingQuery:
    """Writes the updates of ``stateful_top_n``: each batch holds the whole list of every query it changed."""
    spark = scored.sparkSession
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")

    def keep(batch: DataFrame, number: int) -> None:
        batch.withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{path}/part={number}")

    return run(stateful_top_n(scored, N), checkpoint, keep, "update")


def last_state(spark: SparkSession, path: str) -> str:
    """The newest ``state=`` folder under ``path``."""
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    found = p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).listStatus(p)
    return max((f.getPath().toString() for f in found if "state=" in f.getPath().getName()), key=lambda x: int(x.rsplit("=", 1)[1]))


def stateful_top_n(scored: DataFrame, N: int) -> DataFrame:
    """Updates of the running best N per query (RocksDB state store)."""
    return scored.groupBy("query_id").transformWithStateInPandas(TopNState(N), "query_id long, rank int, keyword_id long, score double", "Update", "None")
