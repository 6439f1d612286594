"""Session helpers: code on executors, shared storage, exact fractions of a row count."""

from __future__ import annotations

import atexit
import math
import os
import tempfile
import uuid
import zipfile
from fractions import Fraction
from pathlib import Path

from pyspark import SparkContext
from pyspark.sql import DataFrame, SparkSession

_shipped: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Make the package importable on executors, once per application."""
    app = spark.sparkContext.applicationId
    if app in _shipped:
        return
    root = Path(__file__).resolve().parents[1]
    target = Path(tempfile.mkdtemp()) / "collide_core.zip"
    with zipfile.ZipFile(target, "w") as z:
        for p in sorted((root / "collide").rglob("*.py")):
            z.write(p, p.relative_to(root))
    spark.sparkContext.addPyFile(str(target))
    _shipped.add(app)


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir, the folder that driver and executors share. On one machine a folder of our own serves where it is
    unset; on a cluster that would be another disk for each executor, so it is an error there."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        own = spark.sparkContext._jsc.sc().getCheckpointDir()
        if own.isDefined():
            return own.get()
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        found = os.path.join(tempfile.gettempdir(), "collide-checkpoints")
        spark.sparkContext.setCheckpointDir(found)
    return found


_tables: list[str] = []


def _remove_tables() -> None:
    """At the end of the driver: the tables it wrote are of no use to another one."""
    sc = SparkContext._active_spark_context
    if sc is None or sc._jsc is None or sc._jsc.sc().isStopped():
        return
    for path in _tables:
        p = sc._jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(sc._jsc.hadoopConfiguration()).delete(p, True)


def materialise(df: DataFrame, name: str = "table") -> DataFrame:
    """Written to the shared folder and read back: the plan starts anew from the files, and lost executors cost no recomputation.
    The files live as long as the driver."""
    path = f"{shared_folder(df.sparkSession).rstrip('/')}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    if not _tables:
        atexit.register(_remove_tables)
    _tables.append(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def table_bytes(df: DataFrame) -> int:
    """Bytes of the files that a materialised table is read from."""
    sc = df.sparkSession.sparkContext
    total = 0
    for folder in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        path = sc._jvm.org.apache.hadoop.fs.Path(folder)
        total += path.getFileSystem(sc._jsc.hadoopConfiguration()).getContentSummary(path).getLength()
    return total


def share_of(ratio: float, n: int) -> int:
    """ceil(ratio * n) in exact decimals: 0.07 of 100 is 7."""
    return math.ceil(Fraction(str(ratio)) * n)


#: Rows of a query set that may be broadcast; larger sets are walked in blocks.
BROADCAST_QUERIES = 10_000
