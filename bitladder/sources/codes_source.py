"""A generated source of codes, ``spark.read.format("ladder_codes")``.

Options: rows, planes, seed, partitions.  Codes are hashes of (seed, row, plane),
so a row is the same however the range is cut.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def mix64(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class RowRange(InputPartition):
    def __init__(self, start: int, end: int):
        self.start, self.end = start, end


class CodesReader(DataSourceReader):
    def __init__(self, options):
        self.rows, self.planes = int(options.get("rows", 1000)), int(options.get("planes", 2))
        self.seed, self.parts = int(options.get("seed", 0)), int(options.get("partitions", 8))

    def partitions(self):
        edges = [self.rows * i // self.parts for i in range(self.parts + 1)]
        return [RowRange(a, b) for a, b in zip(edges[:-1], edges[1:], strict=True) if b > a]

    def read(self, partition):
        for a in range(partition.start, partition.end, 65536):
            ids = np.arange(a, min(a + 65536, partition.end), dtype=np.int64)
            words = [mix64(mix64(ids.view(np.uint64) + np.uint64(self.seed * 0x9E3779B9 + 1)) + np.uint64(p + 1)).view(np.int64) for p in range(self.planes)]
            yield pa.RecordBatch.from_arrays([pa.array(ids), *[pa.array(w) for w in words]], ["keyword_id", *[f"p{p}_w0" for p in range(self.planes)]])


class LadderCodes(DataSource):
    @classmethod
    def name(cls):
        return "ladder_codes"

    def schema(self):
        planes = int(self.options.get("planes", 2))
        return ", ".join(["keyword_id long", *[f"p{p}_w0 long" for p in range(planes)]])

    def reader(self, schema):
        return CodesReader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(LadderCodes)
