"""Vector sets of the given tables as (id bigint, vec array<double>), and their checks."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import materialise, ship


@dataclass(frozen=True)
class VectorSet:
    """Points and held-out queries, the dimension, and the step of the integer grid the values lie on (1: none)."""

    points: DataFrame
    queries: DataFrame
    d: int
    unit: float = 1.0
    n: int = 0


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def emb(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.transform("embedding", lambda x: x.cast("double")).alias("vec"))


def emb_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Embeddings on a grid of 1/10000: distances are whole numbers, so no engine's sums differ."""
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.transform("embedding", lambda x: F.floor(x.cast("double") * 10000 + 0.5).cast("double")).alias("vec"))


def tokens(text: str = "text") -> Column:
    return F.filter(F.split(F.lower(F.coalesce(F.col(text), F.lit(""))), "[\\x20\\x09-\\x0D]+"), lambda t: t != "")


#: Bytes of texts whose words are made at once, a longer text by itself.
TEXTS = 1 << 21


def token_counts(df: DataFrame, id_col: str, text: str = "text", d: int = 64) -> DataFrame:
    """Hashed token counts per id: tokens are counted where their text is read, some texts at a time, so that a row for each text is
    shuffled and none for a token; rows of one id are summed."""
    ship(df.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            t = b.column("t")
            ends = pc.binary_length(t).to_numpy().cumsum(dtype=np.int64)
            counts = np.zeros((len(b), d), dtype=np.int32)
            lo = 0
            while lo < len(b):
                hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + TEXTS, side="right")))
                words = pc.ascii_split_whitespace(t.slice(lo, hi - lo))  # at space and x09 to x0D alone; empty before the first and after the last
                each = words.flatten().dictionary_encode()
                distinct = each.dictionary.view(pa.binary()).to_pylist()
                places = np.frombuffer(b"".join([hashlib.md5(w).digest() for w in distinct]), dtype=">u4")[::4] % d  # first 32 bits
                places = np.where([w != b"" for w in distinct], places, d).astype(np.int64)
                at = np.repeat(np.arange(hi - lo), np.diff(words.offsets.to_numpy()))
                counts[lo:hi] = np.bincount(at * (d + 1) + places[each.indices.to_numpy()], minlength=(hi - lo) * (d + 1)).reshape(-1, d + 1)[:, :d]
                lo = hi
            offsets = pa.array(np.arange(0, counts.size + 1, d, dtype=np.int32))
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.ListArray.from_arrays(offsets, pa.array(counts.reshape(-1)))], ["id", "c"])

    t = df.select(F.col(id_col).alias("id"), F.lower(F.coalesce(F.col(text), F.lit(""))).alias("t"))
    c = t.mapInArrow(run, f"id {df.schema[id_col].dataType.simpleString()}, c array<int>")
    g = c.groupBy("id").agg(*[F.sum(F.col("c")[i]).alias(f"c{i}") for i in range(d)])
    return g.select("id", F.array(*[F.col(f"c{i}").cast("double") for i in range(d)]).alias("vec"))


def doc_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts(table(spark, sf_dir, "documents"), "doc_id")


def bench_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts(table(spark, sf_dir, "benchmark"), "item_id")


def normalised(df: DataFrame) -> DataFrame:
    """Each vector over its length; a zero vector stays."""
    norm = F.sqrt(F.aggregate("vec", F.lit(0.0), lambda s, x: s + x * x))
    return df.withColumn("norm", norm).select("id", F.when(F.col("norm") > 0, F.transform("vec", lambda x: x / F.col("norm"))).otherwise(F.col("vec")).alias("vec"))


def doc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return normalised(doc_counts(spark, sf_dir))


def summed(rows: DataFrame, d: int) -> DataFrame:
    """id, vec of rows of an id, a place below d and a value: the values of each place are summed, absent ones are 0. A batch is summed
    before its rows are dealt out by id, so that an id of very many rows sends few; dealt out, an id's rows stream by in a run."""
    ship(rows.sparkSession)
    null = int(np.iinfo(np.int64).min)

    def read(b: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        return b.column("id").fill_null(null).to_numpy(), b.column("m").to_numpy().astype(np.int64), b.column("q").fill_null(0.0).to_numpy()

    def fewer(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids, m, q = read(b)
            keys, at = np.unique(ids, return_inverse=True)
            cells, at = np.unique(at * d + m, return_inverse=True)
            ids = keys[cells // d]
            yield pa.RecordBatch.from_arrays([pa.array(ids, mask=ids == null), pa.array((cells % d).astype(np.int32)), pa.array(np.bincount(at, weights=q, minlength=len(cells)))], ["id", "m", "q"])

    def made(ids: np.ndarray, x: np.ndarray) -> pa.RecordBatch:
        vec = pa.ListArray.from_arrays(pa.array(np.arange(0, x.size + 1, d, dtype=np.int32)), pa.array(x.reshape(-1)))
        return pa.RecordBatch.from_arrays([pa.array(ids, mask=ids == null), vec], ["id", "vec"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, held = np.empty(0, dtype=np.int64), np.empty((0, d))  # an id may go on in the next batch
        for b in batches:
            if not len(b):
                continue
            ids, m, q = read(b)
            first = np.append(True, ids[1:] != ids[:-1])
            x = np.bincount((first.cumsum() - 1) * d + m, weights=q, minlength=int(first.sum()) * d).reshape(-1, d)
            ids = ids[first]
            if len(last) and last[0] == ids[0]:
                x[0] += held[0]
            elif len(last):
                yield made(last, held)
            yield made(ids[:-1], x[:-1])
            last, held = ids[-1:], x[-1:]
        yield made(last, held)

    rows = rows.select(F.col("id").cast("long"), F.col("m").cast("int"), F.col("q").cast("double")).mapInArrow(fewer, "id long, m int, q double")
    return rows.repartition("id").sortWithinPartitions("id").mapInArrow(run, "id long, vec array<double>")


def demand(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quantity sold per part and month, 84 months from January 1995."""
    li = table(spark, sf_dir, "lineitem").select(F.col("l_partkey").alias("id"), ((F.year("l_shipdate") - 1995) * 12 + F.month("l_shipdate") - 1).alias("m"), F.col("l_quantity").alias("q"))
    return summed(li.where(F.col("m").between(0, 83)), 84)


def user(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events per user, by type and hour: 120 counts."""
    ev = table(spark, sf_dir, "events")
    names = [r[0] for r in ev.select("event_type").distinct().orderBy("event_type").collect()]  # five names
    place = F.array_position(F.array(*[F.lit(x) for x in names]), F.col("event_type")) - 1
    g = ev.select(F.col("user_id").alias("id"), (place * 24 + F.hour("ts")).cast("int").alias("b")).groupBy("id", "b").agg(F.count(F.lit(1)).alias("c"))
    m = g.groupBy("id").agg(F.map_from_entries(F.collect_list(F.struct("b", "c"))).alias("m"))
    return m.select("id", F.transform(F.sequence(F.lit(0), F.lit(len(names) * 24 - 1)), lambda k: F.coalesce(F.element_at("m", k), F.lit(0)).cast("double")).alias("vec"))


def numbered(df: DataFrame, *kept: Column) -> DataFrame:
    """id: 1, 2, ... by all columns, and what is kept of a row: all of them, or `kept`. Ranges of rows are sorted apart and written; a range starts after all
    rows of those before it."""
    order = [F.col(c) for c in df.columns]
    runs = materialise(df.repartitionByRange(*order).sortWithinPartitions(*order).select(F.monotonically_increasing_id().alias("at"), *(kept or df.columns)), "numbered")
    sizes = sorted((r["range"], r["n"]) for r in runs.groupBy(F.shiftright("at", 33).alias("range")).agg(F.count(F.lit(1)).alias("n")).collect())  # a row per range
    before, total = [], 0
    for r, n in sizes:
        before.append((r, total))
        total += n
    first = df.sparkSession.createDataFrame(before, "range long, before long")
    placed = runs.withColumn("range", F.shiftright("at", 33)).join(F.broadcast(first), "range")
    return placed.select((F.col("before") + F.col("at").bitwiseAND(F.lit((1 << 33) - 1)) + 1).alias("id"), *runs.columns[1:])


def line(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Eight whole-number features of each line item; the id is a number over all columns, for test scale only. They
    are read from files."""
    day = F.datediff("l_shipdate", F.lit("1995-01-01"))
    values = [F.col("l_quantity") * 100, F.floor(F.col("l_extendedprice") / 10 + 0.5), F.floor(F.col("l_discount") * 10000 + 0.5), F.floor(F.col("l_tax") * 10000 + 0.5), F.col("l_linenumber") * 500, day, F.ascii("l_returnflag") * 50, F.ascii("l_linestatus") * 50]
    return numbered(table(spark, sf_dir, "lineitem"), F.array(*[v.cast("double") for v in values]).alias("vec"))


def held_out(vectors: DataFrame, modulus: int, rest: int, d: int, unit: float = 1.0) -> VectorSet:
    """Rows whose id leaves `rest` become queries and are removed from the points."""
    slice_ = F.pmod("id", F.lit(modulus)) == rest
    points = vectors.where(~slice_)
    queries = vectors.where(slice_).select(F.col("id").alias("qid"), F.col("vec").alias("qvec"))
    return VectorSet(points, queries, d, unit, points.count())


def validate_vectors(df: DataFrame) -> tuple[int, int]:
    """(rows, dimension); raises on null vectors, several lengths, or values that are not finite."""
    bad = F.exists("vec", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    r = df.agg(F.count(F.lit(1)).alias("n"), F.min(F.size("vec")).alias("lo"), F.max(F.size("vec")).alias("hi"), F.sum(F.col("vec").isNull().cast("long")).alias("nulls"), F.sum(F.coalesce(bad, F.lit(False)).cast("long")).alias("bad")).first()
    if r["nulls"] or r["bad"] or r["lo"] != r["hi"]:
        raise ValueError(f"vectors are to be present, finite and of one length: {r.asDict()}")
    return r["n"], r["hi"] or 0
