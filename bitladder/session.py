"""Sessions, and the package on the executors."""

from __future__ import annotations

import os
import sys
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

ROOT = Path(__file__).resolve().parent.parent
_shipped: set[str] = set()


def session(name: str = "bitladder", **conf: str) -> SparkSession:
    """A local session for tests and benches; a cluster brings its own."""
    base = {"spark.sql.shuffle.partitions": "8", "spark.sql.session.timeZone": "UTC", "spark.ui.enabled": "false", "spark.driver.memory": "6g"}
    builder = SparkSession.builder.appName(name).master(os.environ.get("SPARK_MASTER", "local[8]"))
    for key, value in (base | conf).items():
        builder = builder.config(key, value)
    spark = builder.getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def ship(spark: SparkSession) -> SparkSession:
    """Make this package importable in Python workers, once per application.

    Nothing is done where PYTHONPATH already has it, as on a cluster with the
    package installed; else a zip of the sources goes the way of ``--py-files``.
    """
    sc = spark.sparkContext
    known = {os.path.realpath(p) for p in os.environ.get("PYTHONPATH", "").split(os.pathsep) if p}
    if str(ROOT) in known or sc.applicationId in _shipped:
        return spark
    path = Path(tempfile.mkdtemp(prefix="bitladder-src-")) / "bitladder.zip"
    with zipfile.ZipFile(path, "w", zipfile.ZIP_DEFLATED) as z:
        for f in sorted((ROOT / "bitladder").rglob("*.py")):
            z.write(f, f.relative_to(ROOT).as_posix())
    before = list(sys.path)
    sc.addPyFile(str(path))
    sys.path[:] = before  # the driver keeps importing from the sources
    _shipped.add(sc.applicationId)
    return spark
