"""Scans, the code index on disk, models, and sinks."""

from __future__ import annotations

import json
import uuid

import numpy as np
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.codes import CodeSpec
from ..operators.ladder import LadderParams

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables; its columns and filters are pruned by the plan."""
    if name not in TABLES:
        raise ValueError(f"one of {TABLES}")
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_any(spark: SparkSession, path: str, fmt: str, schema: str | None = None, **options) -> DataFrame:
    """CSV, JSON, ORC, text or Parquet; malformed rows go to ``_corrupt_record``."""
    reader = spark.read.format(fmt).options(**options)
    if schema and fmt in ("csv", "json"):
        reader = reader.option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", "_corrupt_record").schema(f"{schema}, _corrupt_record string")
    elif schema:
        reader = reader.schema(schema)
    return reader.load(path)


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; only a local session gets its own."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not found:
        if not spark.sparkContext.master.startswith("local["):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        import tempfile

        found = tempfile.mkdtemp(prefix="bitladder-")
        spark.conf.set("spark.checkpoint.dir", found)
    return found


def checkpoint(df: DataFrame, name: str = "step") -> DataFrame:
    """Write to the shared folder and read back: survives executors, cuts lineage."""
    path = f"{shared_dir(df.sparkSession).rstrip('/')}/bitladder-{uuid.uuid4().hex}/{name}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def pin(df: DataFrame) -> DataFrame:
    """Keep in memory, on disk where memory ends."""
    from pyspark import StorageLevel

    return df.persist(StorageLevel.MEMORY_AND_DISK)


def dense_pos(df: DataFrame, key: str, seed: int | None = None) -> DataFrame:
    """Adds ``pos``: 0..C-1 in the order of ``key``, or of its hash (scattered).

    Rows are range-partitioned, numbered within their partition and written;
    partition counts give each partition's offset.  No global sort in one task.
    """
    order = F.col(key) if seed is None else F.xxhash64(key, F.lit(seed))
    ranged = df.withColumn("_o", order).repartitionByRange("_o", key).sortWithinPartitions("_o", key).drop("_o")
    from pyspark.sql.types import IntegerType, LongType, StructField, StructType

    def number(batches):
        import pyarrow as pa

        part, at = TaskContext.get().partitionId(), 0
        for b in batches:
            n = b.num_rows
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array([part] * n, pa.int32()), pa.array(np.arange(at, at + n))], [*b.schema.names, "_part", "_at"])
            at += n

    schema = StructType([*ranged.schema.fields, StructField("_part", IntegerType()), StructField("_at", LongType())])
    numbered = checkpoint(ranged.mapInArrow(number, schema), "numbered")
    counts = numbered.groupBy("_part").count().orderBy("_part").collect()  # one row per partition
    offsets, total = [], 0
    for r in counts:
        offsets.append((r["_part"], total))
        total += r["count"]
    offset = df.sparkSession.createDataFrame(offsets, "_part int, _offset long")
    return numbered.join(F.broadcast(offset), "_part").withColumn("pos", F.col("_at") + F.col("_offset")).drop("_part", "_at", "_offset")


def write_index(df: DataFrame, spec: CodeSpec, path: str, rows_per_part: int = 1 << 20, lane_size: int = 256, lanes_per_block: int = 256) -> None:
    """The index as Parquet: one column per plane word, sorted by position.

    A part holds a multiple of the lanes of a block, so no lane lies in two parts.
    """
    block = lane_size * lanes_per_block
    per = max(1, -(-rows_per_part // block)) * block
    parted = df.withColumn("part_id", F.floor(F.col("pos") / F.lit(per)).cast("int"))
    parts = max(1, (df.agg(F.max("pos")).first()[0] or 0) // per + 1)
    parted.repartitionByRange(int(parts), "part_id").sortWithinPartitions("part_id", "pos").write.mode("overwrite").partitionBy("part_id").parquet(f"{path}/data")
    meta = {"n": spec.n, "planes": spec.planes, "weighted": spec.weighted, "model": spec.model, "lane_size": lane_size, "lanes_per_block": lanes_per_block, "rows_per_part": per}
    df.sparkSession.createDataFrame([(json.dumps(meta),)], "meta string").coalesce(1).write.mode("overwrite").parquet(f"{path}/meta")


def read_index(spark: SparkSession, path: str, planes: int | None = None, model: str | None = None) -> tuple[DataFrame, CodeSpec]:
    """The index and its spec; with ``planes`` only the first planes' columns are read."""
    meta = json.loads(spark.read.parquet(f"{path}/meta").first()[0])
    if model is not None and meta["model"] != model:
        raise ValueError("the index comes from another model")
    spec = CodeSpec(meta["n"], meta["planes"] if planes is None else planes, meta["weighted"], meta["model"])
    df = spark.read.parquet(f"{path}/data")
    if planes is not None:
        drop = [c for c in CodeSpec(meta["n"], meta["planes"]).columns() if c not in spec.columns()]
        df = df.drop(*drop, "norm_sq")
    return df, spec


def save_model(spark: SparkSession, params: LadderParams, path: str) -> None:
    """Parameters as rows: name, t, row, values."""
    rows = [("W", 0, i, r.tolist()) for i, r in enumerate(np.asarray(params.W, float))]
    for t, (b, r) in enumerate(zip(params.B, params.R, strict=True)):
        rows += [("B", t, i, x.tolist()) for i, x in enumerate(np.asarray(b, float))] + [("R", t, i, x.tolist()) for i, x in enumerate(np.asarray(r, float))]
    rows.append(("flags", int(params.weighted), int(params.shared), []))
    spark.createDataFrame(rows, "name string, t int, row int, values array<double>").coalesce(1).write.mode("overwrite").parquet(path)


def load_model(spark: SparkSession, path: str) -> LadderParams:
    rows = spark.read.parquet(path).orderBy("name", "t", "row").collect()
    parts: dict[tuple[str, int], list] = {}
    flags = (True, False)
    for r in rows:
        if r["name"] == "flags":
            flags = bool(r["t"]), bool(r["row"])
        else:
            parts.setdefault((r["name"], r["t"]), []).append(r["values"])
    depth = sum(1 for n, _ in parts if n == "B")
    return LadderParams(np.array(parts["W", 0]), [np.array(parts["B", t]) for t in range(depth)], [np.array(parts["R", t]) for t in range(depth)], *flags)


def write_results(df: DataFrame, path: str, mode: str = "overwrite") -> None:
    df.write.mode(mode).parquet(path)


def generated_codes(spark: SparkSession, lineitem: DataFrame, planes: int = 3) -> DataFrame:
    """keyword_id, pos and planes of hash codes, one for each line item.

    Ids come from the four columns that tell rows apart; positions are ranks of
    the same hash order, so lanes are scattered.
    """
    keys = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]
    spec = CodeSpec(64, planes)
    coded = lineitem.select(F.xxhash64(*keys).alias("keyword_id"), *[F.xxhash64(*keys, F.lit(p)).alias(c) for p, c in enumerate(spec.columns())])
    from ..functions.codes import norm_sq_expr

    return coded.withColumn("norm_sq", norm_sq_expr(spec))


def save_tower(spark: SparkSession, model, path: str) -> None:
    """A two-sided encoder: one row of bytes for each 1024 parameter rows, and its shape."""
    rows = [("", "meta", 0, 0, 0, 0, json.dumps({"dims": model.dims, "width": model.width, "mode": model.mode, "vocab": model.vocab, "ladders": {s: None if model.side(s).ladder is None else [model.side(s).ladder.weighted, model.side(s).ladder.shared] for s in ("query", "keyword")}}).encode())]
    for side in ("query", "keyword"):
        for (name, t), x in model.side(side).arrays().items():
            for b in range(0, len(x), 1024):
                part = np.ascontiguousarray(x[b : b + 1024], dtype="<f8")
                rows.append((side, name, t, b, *part.shape, part.tobytes()))
    spark.createDataFrame(rows, "side string, name string, t int, block int, n_rows int, n_cols int, data binary").coalesce(1).write.mode("overwrite").parquet(path)


def load_tower(spark: SparkSession, path: str):
    from ..operators.encoder import SideParams, TwoTower

    parts: dict[tuple[str, str, int], list] = {}
    meta = {}
    for r in spark.read.parquet(path).orderBy("side", "name", "t", "block").collect():
        if r["name"] == "meta":
            meta = json.loads(bytes(r["data"]))
        else:
            parts.setdefault((r["side"], r["name"], r["t"]), []).append(np.frombuffer(bytes(r["data"]), "<f8").reshape(r["n_rows"], r["n_cols"]))
    found = {k: np.concatenate(v) for k, v in parts.items()}
    sides = []
    for side in ("query", "keyword"):
        def numbered(name: str, side: str = side) -> list[np.ndarray]:
            return [found[k] for k in sorted(found) if k[:2] == (side, name)]

        flags = meta["ladders"][side]
        own = None if flags is None else LadderParams(found[side, "W", 0], numbered("B"), numbered("R"), *flags)
        sides.append(SideParams(found.get((side, "conv", 0)), own, numbered("hidden")))
    return TwoTower(*sides, meta["dims"], meta["width"], meta["mode"], meta["vocab"])
