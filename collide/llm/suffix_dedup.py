"""Removal of byte strings that start more than once, by bucket-pointer suffix refinement.

A suffix sort of a whole corpus does not fit any machine, so suffixes are first brought together: the window minimum of
q-gram hashes selects, from a window's content alone, one anchor in it; equal windows have equal anchors and meet in one
block. Inside a block suffixes start in buckets of equal q-grams. Buckets with several members are refined by sorting
them on the bucket pointers of the suffixes one depth further on, so the depth doubles with each round because every round
reads the pointers that the last one wrote. Rounds are kept in step, so the final buckets hold suffixes that agree in
exactly the asked length.

Defined results: texts are UTF-8 bytes, null as empty; shorter ones lose nothing; matches never cross documents; repeated
rows are occurrences like any other; an empty table gives an empty result; a very long text is anchored whole; other columns
are ignored, whatever their names. A run of anchors too large for one block is refined by the same rounds over shuffled
bucket pointers, so no task holds it.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common
from .repeats import CTX_BITS, OPEN, REP, RangeHash, merge_ranges, numbers, range_arrays, repeated_windows, settle, unpacked, with_ranges

LENGTH = 200
GRAM = 32
#: Bytes of texts hashed at a time, of contexts refined at a time, and of the largest run of one anchor refined whole.
CHUNK, BLOCK, RUN = 1 << 18, 1 << 20, 1 << 22

_CODES = common.mix(np.arange(1, 257, dtype=np.uint64) * np.uint64(0xA0761D6478BD642F))


def window_minima(h: np.ndarray, width: int) -> np.ndarray:
    """Position of the leftmost least value in each window of `width` values."""
    n = len(h)
    best, reach = np.arange(n), 1
    while reach * 2 <= width:
        left, right = best[: n - 2 * reach + 1], best[reach : n - reach + 1]
        best = np.where(h[left] <= h[right], left, right)
        reach *= 2
    if reach < width:
        left, right = best[: n - width + 1], best[width - reach : width - reach + n - width + 1]
        best = np.where(h[left] <= h[right], left, right)
    return best


def _chunk_anchors(data: list[bytes], keys: list[int], length: int, gram: int) -> tuple[np.ndarray, ...]:
    sizes = np.array([len(x) for x in data], dtype=np.int64)
    begin = np.cumsum(sizes) - sizes
    hashes = RangeHash(_CODES[np.frombuffer(b"".join(data), dtype=np.uint8)])
    grams = hashes.all(gram)
    anchor = window_minima(grams, length - gram + 1)
    doc = np.repeat(np.arange(len(data)), sizes)[: len(anchor)]
    start = np.flatnonzero(np.arange(len(anchor)) - begin[doc] + length <= sizes[doc])
    a, d = anchor[start], doc[start]
    new = np.ones(len(start), dtype=bool)
    new[1:] = (a[1:] != a[:-1]) | (d[1:] != d[:-1])
    at = np.flatnonzero(new)
    s, a, d = start[at], a[at], d[at]
    e = start[np.append(at[1:] - 1, len(start) - 1)] if len(at) else s
    ctx = common.mix(hashes(s, e + length) + (a - s).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    return grams[a], ctx & CTX_BITS, np.array(keys, dtype=np.int64)[d], s - begin[d], e - begin[d]


def _anchors(length: int, gram: int):
    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            found, data, keys, held = [], [], [], 0
            for t, k in zip(common.texts(b), b.column("key").to_pylist(), strict=True):
                raw = t.encode("utf-8", "surrogatepass")
                if len(raw) >= length:
                    data.append(raw)
                    keys.append(k)
                    held += len(raw)
                if held >= CHUNK:
                    found.append(_chunk_anchors(data, keys, length, gram))
                    data, keys, held = [], [], 0
            if data:
                found.append(_chunk_anchors(data, keys, length, gram))
            if found:
                yield settle(*(np.concatenate(x) for x in zip(*found, strict=True)))
        common.trim()

    return find


_CONTEXT = "h long, key long, lo int, hi int, bytes binary"


def _contexts(length: int):
    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            h, key, lo, hi, raw = [], [], [], [], []
            held = 0
            for i, k in enumerate(b.column("key").to_pylist()):
                text = unpacked(b.column("packed")[i].as_py())
                los, his = range_arrays(b.column("ranges"), i)
                hs = numbers(b.column("names"), i)
                for x, y, z in zip(los.tolist(), his.tolist(), hs.tolist(), strict=True):
                    raw.append(text[x : y + length])
                    held += y + length - x
                h += hs.tolist()
                key += [k] * len(los)
                lo += los.tolist()
                hi += his.tolist()
                if held >= BLOCK or i == b.num_rows - 1:
                    yield pa.RecordBatch.from_arrays([pa.array(h, pa.int64()), pa.array(key, pa.int64()), pa.array(lo, pa.int32()), pa.array(hi, pa.int32()), pa.array(raw, pa.binary())], ["h", "key", "lo", "hi", "bytes"])
                    h, key, lo, hi, raw, held = [], [], [], [], [], 0

    return cut


def refine(data: np.ndarray, room: np.ndarray, length: int) -> np.ndarray:
    """Bucket pointer of each position: equal for positions whose next `length` bytes agree; -1 where fewer are left (room)."""
    n = len(data)
    gram = 8 if length >= 8 else 1
    # initial buckets: the next bytes as one number
    code = np.zeros(n, dtype=np.uint64)
    for k in range(gram):
        code[: n - k] |= data[k:].astype(np.uint64) << np.uint64(8 * (gram - 1 - k))
    pointer = np.full(n, -1, dtype=np.int32)
    live = np.flatnonzero(room >= gram).astype(np.int32)
    code = code[live]
    live = _point(pointer, live, code)
    del code
    depth = gram
    while depth < length and len(live):
        step = min(depth, length - depth)
        live = live[room[live] >= depth + step]
        # members of one bucket are told apart by the pointers `step` further on
        key = pointer[live].astype(np.uint64)
        key <<= np.uint64(32)
        key |= pointer[live + step].astype(np.uint64)
        pointer[room < depth + step] = -1
        live = _point(pointer, live, key)
        depth += step
    return pointer


def _point(pointer: np.ndarray, live: np.ndarray, key: np.ndarray) -> np.ndarray:
    """Sort members by key, write each new bucket's first member as the pointer of all its members, and return the members of
    buckets of several. A bucket is named by a member's position, so names never clash with those of settled buckets."""
    if not len(live):
        return live
    order = np.argsort(key)  # members of equal key may come in any order
    live = live[order]
    key = key[order]
    del order
    new = np.ones(len(live), dtype=bool)
    new[1:] = key[1:] != key[:-1]
    at = np.flatnonzero(new)
    size = np.diff(np.append(at, len(live)))
    pointer[live] = np.repeat(live[at], size)
    return live[np.repeat(size > 1, size)]


def _block(rows: list[tuple], length: int) -> pa.RecordBatch:
    """Windows of the block's contexts that occur twice or more in it."""
    raw = [r[4] for r in rows]
    sizes = np.array([len(x) for x in raw], dtype=np.int64)
    begin = np.cumsum(sizes) - sizes
    which = np.repeat(np.arange(len(raw), dtype=np.int32), sizes)
    room = (begin + sizes).astype(np.int32)[which]
    room -= np.arange(len(which), dtype=np.int32)
    pointer = refine(np.frombuffer(b"".join(raw), dtype=np.uint8), room, length)
    at = np.flatnonzero(room >= length)
    at = at[np.bincount(pointer[at], minlength=1)[pointer[at]] > 1]
    w = which[at]
    lo = np.array([r[2] for r in rows], dtype=np.int64)[w] + at - begin[w]
    key, lo, hi = merge_ranges(np.array([r[1] for r in rows], dtype=np.int64)[w], lo, lo)
    return _refined(key, lo, hi, pa.nulls(len(key), pa.binary()))


#: What refinement gives: window starts lo..hi that repeat, or (bytes not null) a context of a run too large for one task.
_REFINED = "key long, lo int, hi int, bytes binary"


def _refined(key, lo, hi, raw) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(key, pa.int64()), pa.array(lo, pa.int32()), pa.array(hi, pa.int32()), pa.array(raw, pa.binary())], ["key", "lo", "hi", "bytes"])


def _refine_blocks(length: int, largest: int):
    """Rows sorted by h: whole runs are gathered up to a block and refined; runs of more than `largest` bytes are passed on."""

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        whole: list[tuple] = []
        run: list[tuple] = []
        whole_bytes = run_bytes = 0
        passing: int | None = None  # the run that is passed on
        for b in batches:
            on: list[tuple] = []
            for row in zip(*(b.column(i).to_pylist() for i in range(5)), strict=True):
                if row[0] == passing:
                    on.append(row)
                    continue
                passing = None
                if run and row[0] != run[0][0]:
                    whole += run
                    whole_bytes += run_bytes
                    if whole_bytes >= BLOCK:
                        yield _block(whole, length)
                        if whole_bytes > 2 * BLOCK:
                            common.trim()
                        whole, whole_bytes = [], 0
                    run, run_bytes = [], 0
                run.append(row)
                run_bytes += len(row[4])
                if run_bytes > largest:
                    on += run
                    passing, run, run_bytes = row[0], [], 0
            if on:
                yield _refined(*([r[i] for r in on] for i in range(1, 5)))
        whole += run
        if whole:
            yield _block(whole, length)
        common.trim()

    return go


_SUFFIXES = "key long, lo int, place int, room int, gram binary"


def _suffixes(gram: int):
    """The suffixes of each context with their first bytes, as far as they have so many."""

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            key, lo, raw = (b.column(c).to_pylist() for c in ("key", "lo", "bytes"))
            for at in range(0, len(raw), 256):
                rows = [(key[i], lo[i], p, len(raw[i]) - p, raw[i][p : p + gram]) for i in range(at, min(at + 256, len(raw))) for p in range(len(raw[i]) - gram + 1)]
                kinds = (pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array([r[j] for r in rows], t) for j, t in enumerate(kinds)], ["key", "lo", "place", "room", "gram"])

    return go


#: Shares that the members of one bucket are dealt to when they learn their new pointer.
SALTS = 16


def _pointed(members: DataFrame, by: list[str]) -> DataFrame:
    """(key, lo, place, room, pointer): members of equal `by` get one member as their pointer; those alone go."""
    least = F.min(F.struct("key", "lo", "place")).alias("pointer")
    buckets = members.groupBy(*by).agg(least, F.count(F.lit(1)).alias("n")).where("n > 1").drop("n")
    every = buckets.withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(SALTS - 1).cast("long"))))
    dealt = members.withColumn("salt", F.pmod(F.xxhash64("key", "lo", "place"), F.lit(SALTS)))
    return common.materialise(dealt.join(every, [*by, "salt"]).select("key", "lo", "place", "room", "pointer"))


def refine_shuffled(contexts: DataFrame, length: int) -> DataFrame:
    """(key, lo, hi) of the window starts of (key, lo, bytes) contexts whose next `length` bytes are found twice or more. Buckets
    of equal grams are refined by the pointers of the suffixes one depth further on; each round is a table."""
    gram = max(1, -(-length // 8))
    one = contexts.dropDuplicates(["key", "lo"])
    live = _pointed(one.mapInArrow(_suffixes(gram), _SUFFIXES), ["gram"])
    depth = gram
    while depth < length:
        step = min(depth, length - depth)
        further = live.select(F.col("key").alias("f_key"), F.col("lo").alias("f_lo"), (F.col("place") - step).alias("f_place"), F.col("pointer").alias("ahead"))
        same = (F.col("key") == F.col("f_key")) & (F.col("lo") == F.col("f_lo")) & (F.col("place") == F.col("f_place"))
        both = live.where(F.col("room") >= depth + step).withColumnRenamed("pointer", "here").join(further, same)
        live = _pointed(both.select("key", "lo", "place", "room", "here", "ahead"), ["here", "ahead"])
        depth += step
    at = F.col("lo") + F.col("place")
    return live.where(F.col("room") >= length).select("key", at.alias("lo"), at.alias("hi"))


def repeated_byte_windows(docs: DataFrame, length: int = LENGTH, gram: int = GRAM, largest: int = RUN) -> DataFrame:
    """(key, lo, hi) of the starts of repeated byte strings; docs are `keyed`."""

    def compare(first: DataFrame) -> DataFrame:
        some = first.where(F.col("state").isin(OPEN, REP))
        contexts = with_ranges(docs, some, "inner", named=True).mapInArrow(_contexts(length), _CONTEXT)
        refined = common.materialise(contexts.repartition("h").sortWithinPartitions("h").mapInArrow(_refine_blocks(length, largest), _REFINED))
        marks, large = refined.where("bytes IS NULL").drop("bytes"), refined.where("bytes IS NOT NULL")
        return marks if large.isEmpty() else marks.unionByName(refine_shuffled(large.select("key", "lo", "bytes"), length))

    return repeated_windows(docs, _anchors(length, min(gram, length)), compare)


def _strip(length: int, texts_too: bool):
    def strip(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for i in range(b.num_rows):
                raw = unpacked(b.column("packed")[i].as_py())
                lo, hi = range_arrays(b.column("ranges"), i)
                removed = spans = 0
                kept = raw
                if len(lo):
                    gone = common.covered(lo, hi + length, len(raw))
                    removed = int(gone.sum())
                    spans = int(gone[0]) + int((gone[1:] & ~gone[:-1]).sum())
                    kept = np.frombuffer(raw, dtype=np.uint8)[~gone].tobytes()
                rows.append((len(raw), removed, spans, hashlib.sha256(kept).hexdigest(), kept if texts_too else None))
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.binary())
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("key"), *(pa.array([r[j] for r in rows], t) for j, t in enumerate(kinds))], ["doc_id", "key", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept_bytes"])

    return strip


def remove_repeats(docs: DataFrame, length: int = LENGTH, bytes_too: bool = True, largest: int = RUN) -> DataFrame:
    """doc_id, key, n_bytes, n_removed, n_spans, kept_sha256, kept_bytes (null unless asked), a row per row of docs."""
    common.ship(docs.sparkSession)
    k = common.keyed(docs)
    marks = repeated_byte_windows(k, length, largest=largest)
    return with_ranges(k, marks, "left").mapInArrow(_strip(length, bytes_too), "doc_id long, key long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept_bytes binary")


def op5_suffix_dedup(spark, sf_dir: str) -> DataFrame:
    """Bytes, removed bytes, spans and digest of every document; defined results as in the module's docstring."""
    return remove_repeats(spark.read.parquet(f"{sf_dir}/documents.parquet"), bytes_too=False).select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256")
