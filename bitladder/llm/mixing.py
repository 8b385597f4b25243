"""Mixing sources to target weights by proportionate-fair scheduling.

Source s with weight w gets block i (from 1) a release time floor((i-1)/w) and a
deadline ceil(i/w) in slots of one block.  Earliest deadline first among released
blocks puts each block in its window, so after any number of slots a source is
less than one block away from its share.

Weights are exact: a float is a whole number over a power of two, so windows are
computed in integers of any size and nothing drifts, however long the schedule.
(Only with ``resolution`` given are the weights first rounded to so many parts.)
The driver runs through the slots once, with one block a source in its heaps, and
writes them to the shared folder in runs of ``RUN`` slots: its memory is bounded by
the sources, its time grows with the slots.  When a source runs dry a new phase
begins and the others share its weight; sources that have had no block in a phase
wait in one order for all phases, so a phase costs what it schedules.  No document
is dropped or repeated.

Position within a source comes from a range partitioning by (source, order),
numbered per partition, with one offset per partition and source; a source that
holds a third of all rows is spread over many partitions.

A null source is a source of its own (its weight is given under None); sources
without a given weight share what the given ones leave, by their rows, or all
weights are row shares raised to ``temper``.  Ties in the order are numbered in
any order; equal rows keep one number each.  Texts are not looked at, nor are other
columns, whatever their names; an empty table gives no rows.
"""

from __future__ import annotations

import heapq
import uuid
from collections.abc import Callable
from fractions import Fraction
from itertools import islice

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import shared_dir, written

#: slots that the driver holds before it writes them
RUN = 1 << 18
LAST = 2**63 - 1


def quantised(weights: list[float], resolution: int) -> list[int]:
    """Positive whole parts of ``resolution`` in proportion, by largest remainder."""
    total = sum(weights)
    exact = [resolution * w / total for w in weights]
    parts = [max(1, int(x)) for x in exact]
    by_need = sorted(range(len(parts)), key=lambda i: (parts[i] - exact[i], i))
    k = 0
    while sum(parts) < resolution:
        parts[by_need[k % len(parts)]] += 1
        k += 1
    while sum(parts) > resolution:
        i = max((i for i in range(len(parts)) if parts[i] > 1), key=lambda i: (parts[i] - exact[i], -i))
        parts[i] -= 1
    return parts


def period_schedule(parts: list[int], length: int) -> list[int]:
    """Which source has each of ``length`` slots, when source i has ``parts[i]`` of them."""
    waiting = [(0, -(-length // p), i, 1) for i, p in enumerate(parts)]  # release, deadline, source, block
    heapq.heapify(waiting)
    ready: list[tuple[int, int, int]] = []
    out = []
    for slot in range(length):
        while waiting and waiting[0][0] <= slot:
            _, deadline, i, block = heapq.heappop(waiting)
            heapq.heappush(ready, (deadline, i, block))
        _, i, block = heapq.heappop(ready)
        out.append(i)
        if block < parts[i]:
            heapq.heappush(waiting, (block * length // parts[i], -(-(block + 1) * length // parts[i]), i, block + 1))
    return out


def whole_parts(weights: list[float]) -> list[int]:
    """Whole numbers in exactly the proportion of the weights."""
    exact = [Fraction(w) for w in weights]
    scale = max((x.denominator for x in exact), default=1)  # all are powers of two
    return [int(x * scale) for x in exact]


def slots(blocks: list[int], parts: list[int]):
    """(source, block, phase, slot, release, deadline) of every block, by slot.

    Source i has ``blocks[i]`` blocks and the share of ``parts[i]`` in the parts of
    the sources that still have blocks.
    """
    order = sorted((i for i, b in enumerate(blocks) if b), key=lambda i: (-parts[i], i))
    share, left = [parts[i] for i in order], [blocks[i] for i in order]
    done = [0] * len(order)
    after, before = list(range(1, len(order) + 1)), list(range(-1, len(order) - 1))  # live sources
    head, live, phase, begin = 0, sum(share), 0, 0
    while head < len(order):
        waiting: list[tuple[int, int, int, int]] = []  # release, deadline, source, block of this phase
        ready: list[tuple[int, int, int, int]] = []  # deadline, source, block of this phase, release
        fresh, at = head, 0  # from ``fresh`` on no source has had a block in this phase
        while True:
            while waiting and waiting[0][0] <= at:
                release, deadline, s, n = heapq.heappop(waiting)
                heapq.heappush(ready, (deadline, s, n, release))
            first = (-(-live // share[fresh]), fresh) if fresh < len(order) else None
            if first is not None and (not ready or first < ready[0][:2]):
                (deadline, s), n, release = first, 1, 0
                fresh = after[fresh]
            else:
                deadline, s, n, release = heapq.heappop(ready)
            yield order[s], done[s], phase, begin + at, min(begin + release, LAST), min(begin + deadline, LAST)
            done[s] += 1
            at += 1
            if done[s] == left[s]:
                break
            heapq.heappush(waiting, (n * live // share[s], -(-(n + 1) * live // share[s]), s, n + 1))
        live -= share[s]
        if before[s] >= 0:
            after[before[s]] = after[s]
        else:
            head = after[s]
        if after[s] < len(order):
            before[after[s]] = before[s]
        phase, begin = phase + 1, begin + at


SLOTS = "s int, block long, phase int, slot long, release long, deadline long"


def slot_table(spark, blocks: list[int], parts: list[int]) -> DataFrame:
    """``slots`` as a table in the shared folder."""
    path = f"{shared_dir(spark).rstrip('/')}/bitladder-{uuid.uuid4().hex}/slots"
    kinds, names = [pa.int32(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()], [x.split()[0] for x in SLOTS.split(", ")]
    source, rows = slots(blocks, parts), None
    while rows is None or len(rows) == RUN:
        rows = list(islice(source, RUN))
        cols = list(zip(*rows, strict=True)) if rows else [()] * len(kinds)
        run = pa.table([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names=names)
        spark.createDataFrame(run, SLOTS).write.mode("append").parquet(path)
    return spark.read.schema(SLOTS).parquet(path)


def numbered(docs: DataFrame, order: str) -> DataFrame:
    """source, doc_id, and ``seq``: the document's number in its source, from 0."""
    rows = docs.select(F.col("source").cast("string").alias("source"), F.col("doc_id").cast("long").alias("doc_id"), F.expr(order).alias("key"))
    rows = rows.repartitionByRange("source", "key", "doc_id").sortWithinPartitions("source", "key", "doc_id")

    def count(batches):
        part, at, last = TaskContext.get().partitionId(), 0, object()
        for batch in batches:
            found = []
            for s in batch.column(0).to_pylist():
                at, last = (at + 1, last) if s == last else (0, s)
                found.append(at)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(found, pa.int64()), pa.array([part] * batch.num_rows, pa.int32())], ["source", "doc_id", "at", "part"])

    return written(rows.mapInArrow(count, "source string, doc_id long, at long, part int"), "numbered")


def falling(names: list[str | None]) -> dict[str | None, float]:
    """Target weights 1, 1/2, 1/3, … of the sources in the order of their names (null first)."""
    total = sum(1.0 / (k + 1) for k in range(len(names)))
    return {s: 1.0 / (k + 1) / total for k, s in enumerate(names)}


def schedule(docs: DataFrame, weights: dict[str | None, float] | Callable[[list], dict] | None = None, block_docs: int = 8, temper: float = 0.5, order: str = "xxhash64(doc_id)", resolution: int | None = None) -> DataFrame:
    """source, doc_id, seq, block, phase, slot, release, deadline, position.

    ``position`` orders the mixture.  ``weights`` are given by source, or by a
    function of the sources' names; without them a source's weight is its number of
    rows to the power ``temper``.  Release and deadline are slots.
    """
    spark = docs.sparkSession
    rows = numbered(docs, order)
    # partitions and sources: a row for each pair that occurs, at most partitions + sources
    counts = rows.groupBy("source", "part").agg((F.max("at") + 1).alias("n")).collect()
    offsets, total = [], {}
    for r in sorted(counts, key=lambda r: (r["source"] is not None, r["source"] or "", r["part"])):
        offsets.append((r["source"], r["part"], total.get(r["source"], 0)))
        total[r["source"]] = total.get(r["source"], 0) + r["n"]
    names = list(total)
    shares = [float(total[s]) ** temper for s in names]
    weights = weights(names) if callable(weights) else weights
    if weights is not None:
        given = sum(weights.get(s, 0.0) for s in names)
        open_rows = sum(total[s] for s in names if s not in weights)
        left = max(0.0, 1.0 - given) or 1e-6
        shares = [max(weights[s], 1e-9) if s in weights else left * total[s] / open_rows for s in names]
    parts = whole_parts(shares) if resolution is None or not shares else quantised(shares, max(resolution, 2 * len(shares)))
    index = {s: k for k, s in enumerate(names)}
    spread = [(s, p, o, index[s]) for s, p, o in offsets]
    offset_df = spark.createDataFrame(spread, "source string, part int, offset long, s int") if spread else spark.createDataFrame([], "source string, part int, offset long, s int")
    joined = (
        rows.join(F.broadcast(offset_df.withColumnRenamed("source", "o_source").withColumnRenamed("part", "o_part")), F.col("source").eqNullSafe(F.col("o_source")) & (F.col("part") == F.col("o_part")))
        .withColumn("seq", F.col("at") + F.col("offset"))
        .withColumn("block", F.expr(f"seq div {block_docs}"))
    )
    placed = joined.join(slot_table(spark, [-(-total[s] // block_docs) for s in names], parts), ["s", "block"])
    return placed.select("source", "doc_id", "seq", "block", "phase", "slot", "release", "deadline", (F.col("slot") * F.lit(block_docs) + F.col("seq") % F.lit(block_docs)).cast("long").alias("position"))


def lag_bound(sequence: list[int], shares: list[Fraction]) -> Fraction:
    """The largest distance from a source's share over all prefixes (for tests)."""
    have, worst = [0] * len(shares), Fraction(0)
    for t, s in enumerate(sequence, 1):
        have[s] += 1
        worst = max(worst, *(abs(h - w * t) for h, w in zip(have, shares, strict=True)))
    return worst


def mixed_documents(docs: DataFrame, **options) -> DataFrame:
    """The rows of ``docs`` in the order of the mixture, all columns unchanged.

    Rows that repeat (source, doc_id) take the number of the first of them.
    """
    columns = docs.columns
    plan = schedule(docs, **options).groupBy("source", "doc_id").agg(F.min("position").alias("__mix_position")).withColumnsRenamed({"source": "__mix_source", "doc_id": "__mix_doc"})
    joined = docs.join(plan, docs["doc_id"].cast("long").eqNullSafe(plan["__mix_doc"]) & docs["source"].cast("string").eqNullSafe(plan["__mix_source"]), "left")
    return joined.repartitionByRange("__mix_position").sortWithinPartitions("__mix_position").select(*[docs[c] for c in columns])
