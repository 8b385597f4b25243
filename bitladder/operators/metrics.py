"""Accuracy and cost measures, as plans over scored pairs and result sets."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, Observation, Window
from pyspark.sql import functions as F

from .loss import group_prob

GRADES = ("bad", "fair", "good", "excellent")


def log_loss(scored: DataFrame, gamma: float, denom: str = "groups", score: str = "cosine") -> DataFrame:
    """Mean of minus log probability: per group (default) or per sample."""
    rows = group_prob(scored, gamma, score)
    total = F.sum(F.when(F.col("is_pos"), -F.log("prob")))
    return rows.agg((total / (F.sum(F.col("is_pos").cast("int")) if denom == "groups" else F.count("*"))).alias("log_loss"))


def roc_auc(scored: DataFrame, by: list[str] | None = None, score: str = "score", label: str = "is_pos", bins: int = 4096) -> DataFrame:
    """Exact area under the ROC curve from distinct scores; ties count one half.

    One class only gives null.
    """
    by = by or []
    rows = scored.where(F.col(score).isNotNull()).groupBy(*by, F.col(score).alias("s")).agg(F.sum(F.when(F.col(label), 1).otherwise(0)).alias("p"), F.sum(F.when(F.col(label), 0).otherwise(1)).alias("n"))
    return auc_of_counts(rows, by, bins)


def auc_of_counts(rows: DataFrame, by: list[str], bins: int = 4096) -> DataFrame:
    """The same from counts of positives ``p`` and negatives ``n`` of each score ``s``.

    Scores are cut into bins; counts are cumulated within a bin and over the bins,
    so no window sees all distinct scores at once.
    """
    rows = rows.withColumn("bin", F.floor(F.col("s") * F.lit(bins)))
    keys = [*by, "bin"]
    below = F.sum("n").over(Window.partitionBy(*keys).orderBy("s")) - F.col("n")
    part = rows.withColumn("u", F.col("p") * (below + F.col("n") / F.lit(2.0)))
    binned = part.groupBy(*keys).agg(F.sum("u").alias("u"), F.sum("p").alias("p"), F.sum("n").alias("n"))
    over = (Window.partitionBy(*by) if by else Window.partitionBy(F.lit(1))).orderBy("bin")
    binned = binned.withColumn("u", F.col("u") + F.col("p") * (F.sum("n").over(over) - F.col("n")))
    area = F.sum("u") / F.when((F.sum("p") > 0) & (F.sum("n") > 0), F.sum("p") * F.sum("n"))
    return binned.groupBy(*by).agg(area.alias("auc"))


def histogram_auc(every: DataFrame, positive: DataFrame, by: list[str]) -> DataFrame:
    """Area from a histogram of all scores (score, n) and the few scored positives.

    Pairs are never listed: negatives of a score are its pairs less its positives.
    """
    p = positive.where(F.col("score").isNotNull()).groupBy(*by, "score").agg(F.count("*").alias("p"))
    rows = every.groupBy(*by, "score").agg(F.sum("n").alias("all")).join(p, [*by, "score"], "left")
    return auc_of_counts(rows.select(*by, F.col("score").alias("s"), F.coalesce("p", F.lit(0)).alias("p"), (F.col("all") - F.coalesce("p", F.lit(0))).alias("n")), by)


def auc_lift(auc: float, low: float, high: float) -> float:
    """Position of an AUC between two references, in percent of their gap."""
    return (auc - low) / (high - low) * 100.0


def grade_change(ours: DataFrame, theirs: DataFrame) -> DataFrame:
    """grade, ours, theirs, change: percent change of counts; null where theirs is 0."""
    a = ours.groupBy("grade").agg(F.count("*").alias("ours"))
    b = theirs.groupBy("grade").agg(F.count("*").alias("theirs"))
    both = a.join(b, "grade", "full_outer").select("grade", F.coalesce("ours", F.lit(0)).alias("ours"), F.coalesce("theirs", F.lit(0)).alias("theirs"))
    return both.withColumn("change", F.try_divide((F.col("ours") - F.col("theirs")) * F.lit(100.0), F.col("theirs")))


def overlap(ours: DataFrame, theirs: DataFrame, keys: tuple[str, ...] = ("query_id", "keyword_id")) -> DataFrame:
    """Common pairs, and their share of ours, of theirs and of the union."""
    a, b = ours.select(*keys).distinct(), theirs.select(*keys).distinct()
    marked = a.withColumn("a", F.lit(1)).join(b.withColumn("b", F.lit(1)), list(keys), "full_outer")
    both = F.sum(F.when(F.col("a").isNotNull() & F.col("b").isNotNull(), 1).otherwise(0))
    return marked.agg(both.alias("common"), F.try_divide(both.cast("double"), F.sum("a")).alias("of_ours"), F.try_divide(both.cast("double"), F.sum("b")).alias("of_theirs"), F.try_divide(both.cast("double"), F.count("*")).alias("jaccard"))


def recall_at(returned: DataFrame, truth: DataFrame, N: int, key: str = "pos") -> DataFrame:
    """query_id, hits, missed, recall: hits divided by N, for every query of ``truth``."""
    hits = truth.select("query_id", key).join(returned.select("query_id", key).withColumn("hit", F.lit(1)), ["query_id", key], "left")
    per = hits.groupBy("query_id").agg(F.count("hit").alias("hits"))
    return per.select("query_id", "hits", (F.lit(N) - F.col("hits")).alias("missed"), (F.col("hits") / F.lit(N)).alias("recall"))


def mean_recall(returned: DataFrame, truth: DataFrame, N: int, key: str = "pos") -> DataFrame:
    return recall_at(returned, truth, N, key).agg(F.count("*").alias("queries"), F.avg("recall").alias("recall"), F.avg("missed").alias("mean_missed"))


def drain(df: DataFrame) -> None:
    """Run a plan to its end and keep nothing."""
    df.write.format("noop").mode("overwrite").save()


def latency(run: Callable[[], DataFrame], queries: int, repeat: int = 3) -> dict[str, float]:
    """Milliseconds per query: the cold run, and mean, median and 95 % of the warm ones."""
    times = []
    for _ in range(repeat + 1):
        t = time.perf_counter()
        drain(run())
        times.append((time.perf_counter() - t) * 1000.0 / max(queries, 1))
    warm = sorted(times[1:]) or times
    return {"cold_ms": times[0], "mean_ms": sum(warm) / len(warm), "p50_ms": warm[len(warm) // 2], "p95_ms": warm[min(len(warm) - 1, int(0.95 * len(warm)))]}


def traffic(stages: dict[str, DataFrame]) -> dict[str, int]:
    """Rows that leave each stage of a selection, counted while it runs."""
    out = {}
    for name, df in stages.items():
        seen = Observation(name)
        drain(df.observe(seen, F.count(F.lit(1)).alias("rows")))
        out[name] = seen.get["rows"]
    return out


def index_bytes(spark, path: str) -> int:
    """Bytes of a stored index: what the file system lists under ``path``."""
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    return int(p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getContentSummary(p).getLength())


def plane_balance(codes: DataFrame, columns: list[str]) -> DataFrame:
    """For each plane word: bits that are set in all, in any, in an odd number, and their share.  One scan."""
    words = F.inline(F.array(*[F.struct(F.lit(c).alias("word"), F.col(c).alias("w")) for c in columns]))
    return codes.select(words).groupBy("word").agg(F.bit_and("w").alias("all_set"), F.bit_or("w").alias("any_set"), F.bit_xor("w").alias("parity"), (F.avg(F.bit_count("w")) / F.lit(64.0)).alias("share"))
