"""What the training-data operators share: shipping code, shared storage, word hashing, document keys."""

from __future__ import annotations

import zlib
from collections.abc import Callable, Iterator

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import session

#: Entries of a worker's word cache; beyond it the cache starts anew, so a worker's memory stays bounded.
CACHE_ENTRIES = 400_000
#: Rows of an Arrow batch handed to Python; long texts are also bounded by bytes where Spark offers that.
BATCH_ROWS = 2_000
BATCH_BYTES = 32 * 2**20


def ship(spark: SparkSession) -> None:
    """Make this package importable on executors, once per application, and bound the Arrow batches."""
    session.ship(spark)
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(BATCH_ROWS))
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(BATCH_BYTES))


def materialise(df: DataFrame) -> DataFrame:
    """Write the rows to the shared folder and read them back: lineage ends here and lost executors cost no recomputation."""
    return session.materialise(df, "documents")


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """body of a value that is computed once. A column that a lambda uses may be written out into it by the optimiser, and then
    is computed anew for every element; a lambda's own variable is not."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def text_or_empty(name: str = "text") -> Column:
    return F.coalesce(F.col(name).cast("string"), F.lit(""))


def doc_key(doc_id: str = "doc_id", text: str = "text") -> Column:
    """64-bit key of a row's id and text. Rows that repeat both share a key and so always get the same result."""
    return F.xxhash64(F.coalesce(F.col(doc_id).cast("string"), F.lit("\0null")), text_or_empty(text))


def keyed(docs: DataFrame) -> DataFrame:
    """(doc_id, key, text) with null texts as empty ones; other columns are left out, whatever their names."""
    return docs.select(F.col("doc_id"), doc_key().alias("key"), text_or_empty().alias("text"))


def wrapped(docs: DataFrame) -> DataFrame:
    """(row, key): all columns of docs within one struct, so that their names clash with none of an operator's own."""
    return docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), doc_key().alias("key"))


def row_text() -> Column:
    """The text of a wrapped row, null as empty."""
    return text_or_empty("row.text")


def unwrapped(df: DataFrame, columns: list[str], **changed: Column) -> DataFrame:
    """The columns that `wrapped` took in, some of them changed."""
    return df.select(*[(changed[c] if c in changed else F.col("row").getField(c)).alias(c) for c in columns])


def with_text(df: DataFrame, docs: DataFrame) -> DataFrame:
    """The columns of docs from wrapped rows; where `new` is not null it replaces `text`, and `n_chars` is counted anew."""
    changed = {"text": F.coalesce(F.col("new"), F.col("row").getField("text"))}
    kinds = dict(docs.dtypes)
    if kinds.get("n_chars") in ("int", "bigint"):
        changed["n_chars"] = F.when(F.col("new").isNull(), F.col("row").getField("n_chars")).otherwise(F.length("new").cast(kinds["n_chars"]))
    return unwrapped(df, docs.columns, **changed)


def mix(h: np.ndarray) -> np.ndarray:
    """Finaliser of a 64-bit hash, elementwise."""
    h = h.astype(np.uint64, copy=True)
    h ^= h >> np.uint64(33)
    h *= np.uint64(0xFF51AFD7ED558CCD)
    h ^= h >> np.uint64(33)
    h *= np.uint64(0xC4CEB9FE1A85EC53)
    h ^= h >> np.uint64(33)
    return h


class WordHashes(dict):
    """bytes -> 64-bit hash, remembered up to CACHE_ENTRIES words."""

    def __missing__(self, word: bytes) -> int:
        if len(self) >= CACHE_ENTRIES:
            self.clear()
        import xxhash

        h = self[word] = xxhash.xxh3_64_intdigest(word)
        return h


_words = WordHashes()


def words_of(text: str) -> list[bytes]:
    """Maximal runs without space or U+0009 to U+000D, as UTF-8."""
    return text.encode("utf-8", "surrogatepass").split()


def word_hashes(words: list[bytes]) -> np.ndarray:
    return np.fromiter(map(_words.__getitem__, words), dtype=np.uint64, count=len(words))


def windows_hash(h: np.ndarray, size: int, seed: int = 0) -> np.ndarray:
    """Hash of each run of `size` neighbouring elements; order matters. Doubling, so log(size) passes."""
    n = len(h) - size + 1
    if n <= 0:
        return np.empty(0, dtype=np.uint64)
    power, width = mix(h + np.uint64((0x9E3779B97F4A7C15 * (seed + 1)) % 2**64)), 1
    out: np.ndarray | None = None
    done = 0
    left = size
    while left:
        if left & 1:
            part = power[done : done + n]
            out = part if out is None else mix(out * np.uint64(0x9E3779B97F4A7C15) + part)
            done += width
        left >>= 1
        if left:
            power = mix(power[:-width] * np.uint64(0xD6E8FEB86659FD93) + power[width:])
            width *= 2
    return out


def signed(h: np.ndarray) -> np.ndarray:
    return h.view(np.int64)


def covered(starts: np.ndarray, ends: np.ndarray, n: int) -> np.ndarray:
    """Boolean mask of 0..n-1 that lies in any [start, end)."""
    step = np.zeros(n + 1, dtype=np.int64)
    np.add.at(step, starts, 1)
    np.add.at(step, np.minimum(ends, n), -1)
    return np.cumsum(step[:n]) > 0


def trim() -> None:
    """Give freed memory back to the system: workers are kept between tasks and would hold on to their largest batch."""
    import ctypes

    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def crc(data: bytes) -> int:
    return zlib.crc32(data) & 0xFFFFFFFF


def texts(batch, column: str = "text") -> Iterator[str]:
    for x in batch.column(column):
        yield x.as_py() or ""
