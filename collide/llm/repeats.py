"""Repeated stretches across a corpus: what the substring and suffix operators share.

An *anchor* is a place in a document that content alone selects; `h` names the content at the anchor and `ctx` the
content of all windows that the anchor answers for, those starting at lo..hi. Anchors of equal `h` meet in one sorted
run. A run is read as a stream, so no group is ever held:

* `ctx` found twice or more: all its windows repeat (state MARK);
* `ctx` found once in a run that has others: its windows must be compared one by one (state OPEN), and each other `ctx`
  of that run sends one representative along;
* a run of one: nothing repeats.

Before the shuffle each Arrow batch settles what it can: a `ctx` that occurs twice in the batch is marked there, and one
representative goes on. So a passage that a third of all documents share costs one row per batch, not one per document.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

NEW, MARK, OPEN, REP = 0, 1, 2, 3
ANCHORS = "h long, ctx long, key long, lo int, hi int, state byte"
_NAMES = ["h", "ctx", "key", "lo", "hi", "state"]
_TYPES = [pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int8()]

_BASE = np.uint64(0x9E3779B97F4A7C15)
_INVERSE = np.uint64(pow(0x9E3779B97F4A7C15, -1, 2**64))
_powers = (np.ones(1, dtype=np.uint64), np.ones(1, dtype=np.uint64))


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    global _powers
    if len(_powers[0]) < n:
        size = 1 << max(16, int(n - 1).bit_length())
        made = []
        for b in (_BASE, _INVERSE):
            p = np.full(size, b, dtype=np.uint64)
            p[0] = 1
            made.append(np.cumprod(p, dtype=np.uint64))
        _powers = (made[0], made[1])
    return _powers


class RangeHash:
    """Hash of any range [s, e) of a sequence of 64-bit values in constant time: weighted prefix sums modulo 2**64."""

    def __init__(self, values: np.ndarray):
        up, self.down = _power_tables(len(values) + 1)
        self.sums = np.zeros(len(values) + 1, dtype=np.uint64)
        np.cumsum(values * up[: len(values)], dtype=np.uint64, out=self.sums[1:])

    def __call__(self, s: np.ndarray, e: np.ndarray) -> np.ndarray:
        return common.mix((self.sums[e] - self.sums[s]) * self.down[s] + (e - s).astype(np.uint64))

    def all(self, width: int) -> np.ndarray:
        n = len(self.sums) - width
        return common.mix((self.sums[width:] - self.sums[:n]) * self.down[:n] + np.uint64(width)) if n > 0 else np.empty(0, dtype=np.uint64)


def to_batch(h, ctx, key, lo, hi, state) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip((h, ctx, key, lo, hi, state), _TYPES, strict=True)], _NAMES)


def settle(h: np.ndarray, ctx: np.ndarray, key: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> pa.RecordBatch:
    """Within one batch: pairs (h, ctx) found twice or more are marked; one representative of each pair goes on."""
    if not len(h):
        return to_batch(*(np.empty(0, dtype=np.int64) for _ in range(6)))
    order = np.lexsort((ctx, h))
    new = np.ones(len(h), dtype=bool)
    new[1:] = (h[order[1:]] != h[order[:-1]]) | (ctx[order[1:]] != ctx[order[:-1]])
    many = np.bincount(np.cumsum(new) - 1) > 1
    first = order[np.flatnonzero(new)]
    back = np.argsort(first)  # rows of a document stay together, which the shuffle's compression uses
    rep, state = first[back], np.where(many[back], REP, NEW)
    found = order[many[np.cumsum(new) - 1]]
    mk, ml, mh = merge_ranges(key[found], lo[found], hi[found])
    return to_batch(
        np.concatenate([common.signed(h[rep]), mk]), np.concatenate([common.signed(ctx[rep]), np.zeros(len(mk), dtype=np.int64)]), np.concatenate([key[rep], mk]),
        np.concatenate([lo[rep], ml]), np.concatenate([hi[rep], mh]), np.concatenate([state, np.full(len(mk), MARK)]),
    )


def merge_ranges(key: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Union of the inclusive ranges of each key; neighbours join."""
    if not len(key):
        return key, lo, hi
    order = np.lexsort((lo, key))
    key, lo, hi = key[order], lo[order].astype(np.int64), hi[order].astype(np.int64)
    group = np.zeros(len(key), dtype=np.int64)
    group[1:] = np.cumsum(key[1:] != key[:-1])
    top = np.maximum.accumulate(hi + group * (1 << 33)) - group * (1 << 33)
    new = np.ones(len(key), dtype=bool)
    new[1:] = (key[1:] != key[:-1]) | (lo[1:] > top[:-1] + 1)
    at = np.flatnonzero(new)
    return key[at], lo[at], np.maximum.reduceat(hi, at)


def _classify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows sorted by (h, ctx) in, states out. At most two rows of the last run wait for the next batch."""
    held: dict[str, np.ndarray] | None = None
    company = False  # the held run's h had another ctx before it
    for b in batches:
        cols = {n: b.column(n).to_numpy(zero_copy_only=False) for n in _NAMES}
        done = cols["state"] == MARK
        if done.any():
            yield to_batch(*(cols[n][done] for n in _NAMES))
            cols = {n: v[~done] for n, v in cols.items()}
        if not len(cols["h"]):
            continue
        if held is not None:
            cols = {n: np.concatenate([held[n], cols[n]]) for n in _NAMES}
        out, held, company = _runs(cols, company, last=False)
        if out is not None:
            yield out
    if held is not None:
        out, _, _ = _runs(held, company, last=True)
        if out is not None:
            yield out
    common.trim()


def _runs(c: dict[str, np.ndarray], company: bool, last: bool):
    """States of all rows but those of the last (h, ctx) run, which is kept back unless `last`. REP rows stand for two or more."""
    h, ctx = c["h"], c["ctx"]
    n = len(h)
    new_h = np.ones(n, dtype=bool)
    new_h[1:] = h[1:] != h[:-1]
    new_c = new_h.copy()
    new_c[1:] |= ctx[1:] != ctx[:-1]
    at_c = np.flatnonzero(new_c)
    run_c, run_h = np.cumsum(new_c) - 1, np.cumsum(new_h) - 1
    size_c = np.add.reduceat(np.where(c["state"] == REP, 2, 1), at_c)
    kinds = np.bincount(run_h[at_c])  # distinct ctx of each h
    kinds[0] += company
    state = np.where(size_c[run_c] > 1, MARK, np.where(kinds[run_h] > 1, OPEN, NEW)).astype(np.int8)
    sent, held, before = np.ones(n, dtype=bool), None, False
    if not last:
        tail = at_c[-1]
        cut = max(tail, n - 2)  # of a long run two rows are enough to tell
        sent[cut:] = False
        held = {k: v[cut:].copy() for k, v in c.items()}
        before = bool(run_h[tail] == run_h[tail - 1]) if tail else company
    go = sent & (state != NEW)
    parts = {k: v[go] for k, v in c.items()}
    parts["state"] = state[go]
    reps = at_c[(size_c > 1) & (kinds[run_h[at_c]] > 1) & sent[at_c]]
    if len(reps):
        extra = {k: v[reps] for k, v in c.items()}
        extra["state"] = np.full(len(reps), REP, dtype=np.int8)
        parts = {k: np.concatenate([parts[k], extra[k]]) for k in _NAMES}
    return (to_batch(*(parts[k] for k in _NAMES)) if len(parts["h"]) else None), held, before


def classify(anchors: DataFrame) -> DataFrame:
    """One shuffle by h; equal anchors become neighbours by sorting, which spills, and are judged as a stream."""
    return anchors.repartition("h").sortWithinPartitions("h", "ctx").mapInArrow(_classify, ANCHORS)


def _squeeze(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    pack = zstandard.ZstdCompressor(level=1).compress
    for b in batches:
        yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("key"), pa.array([pack(t.encode("utf-8", "surrogatepass")) for t in common.texts(b)], pa.binary())], ["doc_id", "key", "packed"])


def squeezed(docs: DataFrame) -> DataFrame:
    """(doc_id, key, packed): texts compressed well before they are shuffled, whole."""
    return docs.mapInArrow(_squeeze, "doc_id long, key long, packed binary")


_unpack = zstandard.ZstdDecompressor()


def unpacked(packed: bytes) -> bytes:
    return _unpack.decompress(packed)


def with_ranges(docs: DataFrame, marks: DataFrame, how: str, named: bool = False) -> DataFrame:
    """Documents (squeezed) with the ranges of window starts of their key, lo and hi in one number, and if `named` the
    ranges' h in the same order. A key is one document, so the lists are bounded by the document."""
    both = F.shiftleft(F.col("lo").cast("long"), 32) + F.col("hi")
    item = F.struct(both.alias("r"), F.col("h")) if named else both
    r = marks.groupBy("key").agg(F.collect_list(item).alias("got"))
    r = r.select(F.col("key").alias("r_key"), *([F.col("got.r").alias("ranges"), F.col("got.h").alias("names")] if named else [F.col("got").alias("ranges")]))
    return squeezed(docs).join(r, F.col("key") == F.col("r_key"), how).drop("r_key")


def numbers(column, row: int) -> np.ndarray:
    value = column[row]
    return value.values.to_numpy(zero_copy_only=False) if value.is_valid else np.empty(0, dtype=np.int64)


def range_arrays(column, row: int) -> tuple[np.ndarray, np.ndarray]:
    """lo and hi of one row."""
    v = numbers(column, row)
    return v >> 32, v & 0xFFFFFFFF


#: Bits of ctx that are kept: beside 64 equal bits of h, 48 tell contexts apart.
CTX_BITS = np.uint64(0xFFFFFFFFFFFF)


Found = Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]


def repeated_windows(docs: DataFrame, find: Found, compare: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """(key, lo, hi): starts of all windows that occur twice or more. `find` emits anchors, `compare` settles OPEN ones."""
    first = common.materialise(classify(docs.mapInArrow(find, ANCHORS)))
    sure = first.where(F.col("state") == MARK)
    return sure.select("key", "lo", "hi").unionByName(compare(first).select("key", "lo", "hi"))
