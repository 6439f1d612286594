"""Reading and making vector tables."""

from __future__ import annotations

import struct
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import ArrayType, DoubleType, LongType, StructField, StructType


def load_vectors(spark: SparkSession, path: str, id_col: str = "id", vec_col: str = "vec", format: str = "parquet", sep: str = ",") -> DataFrame:
    """(id bigint, vec array<double>) from parquet, orc, json (arrays), or csv and text (id, then values joined by sep)."""
    if format in ("parquet", "orc"):
        df = spark.read.format(format).load(path)
        return df.select(F.col(id_col).cast("long").alias("id"), F.col(vec_col).cast("array<double>").alias("vec"))
    if format == "json":
        return spark.read.schema(f"{id_col} long, {vec_col} array<double>").json(path).select(F.col(id_col).alias("id"), F.col(vec_col).alias("vec"))
    if format in ("csv", "text"):
        parts = F.split("value", sep)
        return spark.read.text(path).select(parts[0].cast("long").alias("id"), F.slice(parts, 2, F.size(parts) - 1).cast("array<double>").alias("vec"))
    if format == "binary":
        spark.dataSource.register(FixedVectorSource)
        return spark.read.format("fixed_vectors").load(path)
    raise ValueError(f"no reader for {format}")


class _Slice(InputPartition):
    def __init__(self, path: str, first: int, rows: int, d: int):
        self.path, self.first, self.rows, self.d = path, first, rows, d


class FixedVectorSource(DataSource):
    """Binary files of rows that each start with their length: a 32-bit count, then that many 32-bit floats. The id is the row
    number. Files are cut into slices of equal rows, read in parallel; the path is one that executors can open."""

    @classmethod
    def name(cls) -> str:
        return "fixed_vectors"

    def schema(self) -> StructType:
        return StructType([StructField("id", LongType()), StructField("vec", ArrayType(DoubleType()))])

    def reader(self, schema: StructType) -> DataSourceReader:
        return FixedVectorReader(self.options)


class FixedVectorReader(DataSourceReader):
    def __init__(self, options):
        self.path = options["path"]
        self.slice_rows = int(options.get("sliceRows", 100_000))

    def partitions(self) -> list[InputPartition]:
        import os

        with open(self.path, "rb") as f:
            head = f.read(4)
        if not head:
            return []
        d = struct.unpack("<i", head)[0]
        rows = os.path.getsize(self.path) // (4 + 4 * d)
        return [_Slice(self.path, at, min(self.slice_rows, rows - at), d) for at in range(0, rows, self.slice_rows)]

    def read(self, part: _Slice) -> Iterator[tuple]:
        width = 4 + 4 * part.d
        with open(part.path, "rb") as f:
            f.seek(part.first * width)
            for i in range(part.rows):
                row = f.read(width)
                if struct.unpack_from("<i", row)[0] != part.d:
                    raise ValueError(f"row {part.first + i} has another length")
                yield part.first + i, list(map(float, struct.unpack_from(f"<{part.d}f", row, 4)))


def write_fixed_vectors(path: str, rows: list[list[float]]) -> None:
    with open(path, "wb") as f:
        for r in rows:
            f.write(struct.pack(f"<i{len(r)}f", len(r), *r))


def synthetic_vectors(spark: SparkSession, n: int, d: int, seed: int = 0, centres: int = 0) -> DataFrame:
    """Made in place on the executors, any number of rows: uniform values, or around a number of centres."""
    value = [F.rand(seed * 1000 + i) for i in range(d)]
    if centres:
        value = [0.1 * v + F.pmod(F.xxhash64(F.pmod(F.xxhash64("id", F.lit(seed)), F.lit(centres)), F.lit(i)), F.lit(1000)) / 1000.0 for i, v in enumerate(value)]
    return spark.range(n).select("id", F.array(*value).alias("vec"))


def register_views(spark: SparkSession, sf_dir: str, tables: tuple[str, ...] = ("embeddings", "documents", "lineitem", "part", "events", "labels", "benchmark")) -> None:
    for t in tables:
        spark.read.parquet(f"{sf_dir}/{t}.parquet").createOrReplaceTempView(t)


def save_bucketed(points: DataFrame, table: str, buckets: int = 64) -> None:
    """Points as a table bucketed by id, so that pools join them without shuffling them."""
    points.write.mode("overwrite").bucketBy(buckets, "id").sortBy("id").saveAsTable(table)
