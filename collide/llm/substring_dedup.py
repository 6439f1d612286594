"""Removal of word windows that occur more than once, by difference-cover anchors.

Word positions are taken modulo a period; those whose residue lies in a difference cover carry an anchor, the hash of the
next few words. For any two positions some shift below the period takes both onto the cover, so two equal windows share
an anchor at the same place inside them, whatever their own positions. Anchors of equal hash are then extended both ways
to whole windows. Every word under a window that starts anywhere else as well is removed, first copies included.

Defined results: a null or empty text has no words and keeps none; texts shorter than a window lose nothing; repeated rows
are occurrences like any other, so both lose what they share; an empty table gives an empty result; other columns of the
table are ignored, whatever their names.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common
from .repeats import ANCHORS, CTX_BITS, MARK, OPEN, REP, RangeHash, classify, merge_ranges, range_arrays, repeated_windows, settle, unpacked, with_ranges

WINDOW = 35
#: A perfect difference set, every residue modulo PERIOD is a difference of two members.
PERIOD, COVER = 21, (3, 6, 7, 12, 14)


def _anchors(window: int):
    """Anchors of a batch; its documents are laid end to end, and no range crosses from one to the next."""
    reach = PERIOD - 1
    width = window - reach
    on_cover = np.zeros(PERIOD, dtype=bool)
    on_cover[list(COVER)] = True

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            words: list[bytes] = []
            sizes = []
            for t in common.texts(b):
                w = common.words_of(t)
                words += w
                sizes.append(len(w))
            n = np.array(sizes, dtype=np.int64)
            begin = np.cumsum(n) - n
            hashes = RangeHash(common.word_hashes(words))
            del words
            doc = np.repeat(np.arange(len(n)), n)
            pos = np.arange(len(doc)) - begin[doc]
            size = n[doc]
            at = np.flatnonzero(on_cover[pos % PERIOD] & (size >= window) & (pos + width <= size))
            p, d = pos[at], doc[at]
            lo, hi = np.maximum(p - reach, 0), np.minimum(p, n[d] - window)
            ok = lo <= hi
            at, p, d, lo, hi = at[ok], p[ok], d[ok], lo[ok], hi[ok]
            h = hashes(at, at + width)
            ctx = common.mix(hashes(begin[d] + lo, begin[d] + hi + window) + (p - lo).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
            yield settle(h, ctx & CTX_BITS, b.column("key").to_numpy()[d], lo, hi)
        common.trim()

    return find


#: Fixed value: sets a second hash of the same words apart from the first.
SECOND = np.uint64(0xC2B2AE3D27D4EB4F)


def _extend(window: int):
    """The windows that anchors to be compared answer for, each once, named by all their words: which anchor brought a window
    here does not matter to whether its words are found again."""

    def extend(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out: list[list[np.ndarray]] = []
            for i, key in enumerate(b.column("key").to_pylist()):
                lo, hi = range_arrays(b.column("ranges"), i)
                if not len(lo):
                    continue
                _, lo, hi = merge_ranges(np.zeros(len(lo), dtype=np.int64), lo, hi)
                w = common.word_hashes(common.words_of(unpacked(b.column("packed")[i].as_py()).decode("utf-8", "surrogatepass")))
                sizes = hi - lo + 1
                p = np.arange(int(sizes.sum())) + np.repeat(lo - np.cumsum(sizes) + sizes, sizes)
                out.append([RangeHash(w)(p, p + window), RangeHash(common.mix(w ^ SECOND))(p, p + window), np.full(len(p), key, dtype=np.int64), p])
            if out:
                h, ctx, key, p = (np.concatenate(x) for x in zip(*out, strict=True))
                yield settle(h, ctx & CTX_BITS, key, p, p)

    return extend


def repeated_word_windows(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """(key, lo, hi) of the starts of repeated windows; docs are `keyed`."""
    if window < PERIOD:
        raise ValueError(f"a window has at least {PERIOD} words")

    def compare(first: DataFrame) -> DataFrame:
        some = first.where(F.col("state").isin(OPEN, REP))
        return classify(with_ranges(docs, some, "inner").mapInArrow(_extend(window), ANCHORS)).where(F.col("state") == MARK)

    return repeated_windows(docs, _anchors(window), compare)


def _strip(window: int, texts_too: bool):
    def strip(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for i in range(b.num_rows):
                words = common.words_of(unpacked(b.column("packed")[i].as_py()).decode("utf-8", "surrogatepass"))
                lo, hi = range_arrays(b.column("ranges"), i)
                if len(lo):
                    gone = common.covered(lo, hi + window, len(words))
                    kept = b" ".join([w for w, g in zip(words, gone.tolist(), strict=True) if not g])
                    removed = int(gone.sum())
                else:
                    kept, removed = b" ".join(words), 0
                rows.append((len(words), removed, hashlib.sha256(kept).hexdigest(), kept.decode("utf-8", "surrogatepass") if texts_too else None))
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("key"), pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.int64()), pa.array([r[2] for r in rows], pa.string()), pa.array([r[3] for r in rows], pa.string())], ["doc_id", "key", "n_words", "n_removed", "kept_sha256", "kept_text"])

    return strip


def remove_repeats(docs: DataFrame, window: int = WINDOW, texts: bool = True) -> DataFrame:
    """doc_id, key, n_words, n_removed, kept_sha256, kept_text (null unless `texts`), a row per row of docs."""
    common.ship(docs.sparkSession)
    k = common.keyed(docs)
    marks = repeated_word_windows(k, window)
    return with_ranges(k, marks, "left").mapInArrow(_strip(window, texts), "doc_id long, key long, n_words long, n_removed long, kept_sha256 string, kept_text string")


def op8_substring_dedup(spark, sf_dir: str) -> DataFrame:
    """Words, removed words and digest of every document; defined results as in the module's docstring."""
    return remove_repeats(spark.read.parquet(f"{sf_dir}/documents.parquet"), texts=False).select("doc_id", "n_words", "n_removed", "kept_sha256")
