"""Quality by a vote of the nearest labelled documents in a latent-semantic space.

Texts become counts of byte trigrams and of a few marks of repetition, weighted by rarity. The space is fitted on a
bounded sample of labelled documents (SAMPLE, chosen by hash of the id) by a truncated singular value decomposition. The
sample's vectors and the projection have a fixed size, so they are broadcast; every document is compared with all of them
by blocked products, and the nearest vote with weights that grow with the cosine.

Defined results: a null or empty text has a zero vector and gets the sample's share of good documents, as has any
document when there is no labelled sample (then 0.5); a null doc_id is never in the held-out third; a document labelled
more than once counts once, by its least label; repeated rows are scored one by one; an empty table gives an empty
result; a very long text is counted whole; other columns are ignored, whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common

#: The bound on labelled documents used.
SAMPLE = 4000
BUCKETS, MARKS = 4096, 8
RANK, NEIGHBOURS, POWER = 64, 15, 8


def counts(texts: list[str]) -> np.ndarray:
    """A row per text: counts of hashed byte trigrams, then marks of repetition."""
    raw = [t.encode("utf-8", "surrogatepass") for t in texts]
    out = np.zeros((len(raw), BUCKETS + MARKS), dtype=np.float32)
    for i, r in enumerate(raw):
        if len(r) >= 3:
            b = np.frombuffer(r, dtype=np.uint8).astype(np.uint32)
            code = (b[:-2] * np.uint32(0x9E3779B1)) ^ (b[1:-1] * np.uint32(0x85EBCA6B)) ^ (b[2:] * np.uint32(0xC2B2AE35))
            out[i, :BUCKETS] = np.bincount((code * np.uint32(0x27D4EB2F)) >> np.uint32(20), minlength=BUCKETS)
        words = r.split()
        if words:
            n = len(words)
            again = sum(map(bytes.__eq__, words[1:], words[:-1]))
            lines = [x for x in r.split(b"\n") if x.strip()]
            shares = (again / n, 1 - len(set(words)) / n, 1 - len(set(lines)) / max(1, len(lines)))
            for k, x in enumerate(shares):
                out[i, BUCKETS + 2 * k] = x * n
                out[i, BUCKETS + 2 * k + 1] = n if x > 0.3 else 0
    return out


@dataclass
class Model:
    weight: np.ndarray
    projection: np.ndarray
    vectors: np.ndarray
    labels: np.ndarray
    share: float

    def latent(self, c: np.ndarray) -> np.ndarray:
        x = np.log1p(c) * self.weight
        x /= np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-9)
        v = x @ self.projection
        return v / np.maximum(np.linalg.norm(v, axis=1, keepdims=True), 1e-9)

    def score(self, c: np.ndarray) -> np.ndarray:
        """Share of good documents among the nearest, weighted by similarity."""
        if not len(self.labels):
            return np.full(len(c), self.share)
        v = self.latent(c)
        cosine = v @ self.vectors.T
        k = min(NEIGHBOURS, cosine.shape[1])
        near = np.argpartition(-cosine, k - 1, axis=1)[:, :k]
        w = np.maximum(np.take_along_axis(cosine, near, axis=1), 0).astype(np.float64) ** POWER
        score = ((w * self.labels[near]).sum(axis=1) + 0.01 * self.share) / (w.sum(axis=1) + 0.01)
        return np.clip(score, 0.0, 1.0)


def fit(c: np.ndarray, labels: np.ndarray, rank: int = RANK) -> Model:
    """Truncated decomposition by subspace iteration with a fixed start, so the same sample gives the same model."""
    if not len(labels):
        none = np.zeros((BUCKETS + MARKS, 1), dtype=np.float32)
        return Model(np.ones(BUCKETS + MARKS, dtype=np.float32), none, np.zeros((0, 1), dtype=np.float32), np.zeros(0), 0.5)
    weight = (np.log((1 + len(c)) / (1 + (c > 0).sum(axis=0))) + 0.1).astype(np.float32)
    x = np.log1p(c) * weight
    x /= np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-9)
    rank = min(rank, *x.shape)
    q = np.random.default_rng(7).standard_normal((x.shape[1], min(rank + 16, *x.shape))).astype(np.float32)
    for _ in range(5):
        q, _ = np.linalg.qr(x.T @ (x @ q))
    _, _, vt = np.linalg.svd(x @ q, full_matrices=False)
    model = Model(weight, (q @ vt.T)[:, :rank].astype(np.float32), np.zeros((0, rank), dtype=np.float32), labels.astype(np.float64), float(labels.mean()))
    model.vectors = model.latent(c).astype(np.float32)
    return model


def _counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        c = counts(list(common.texts(b)))
        yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("label"), pa.array([np.minimum(r, 65535).astype(np.uint16).tobytes() for r in c], pa.binary())], ["doc_id", "label", "counts"])


def held_out(doc_id: str = "doc_id") -> Column:
    return F.coalesce(F.pmod(F.crc32(F.col(doc_id).cast("string").cast("binary")), F.lit(3)) == 1, F.lit(False))


def train(docs: DataFrame, labels: DataFrame, label: str = "quality", sample: int = SAMPLE) -> Model:
    """Fit on at most `sample` labelled documents outside the held-out third."""
    common.ship(docs.sparkSession)
    usable = labels.select(F.col("doc_id").cast("long").alias("l_id"), F.col(label).cast("int").alias("label")).where(F.col("l_id").isNotNull() & F.col("label").isNotNull() & ~held_out("l_id"))
    picked = usable.groupBy("l_id").agg(F.min("label").alias("label")).orderBy(F.xxhash64("l_id"), "l_id").limit(sample)
    pairs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), common.text_or_empty().alias("text")).join(F.broadcast(picked), F.col("doc_id") == F.col("l_id"))  # `sample` rows at most
    got = pairs.select("doc_id", "label", "text").mapInArrow(_counted, "doc_id long, label int, counts binary").toPandas()
    got = got.sort_values(["doc_id", "counts"]).drop_duplicates("doc_id")
    c = np.stack([np.frombuffer(x, dtype=np.uint16) for x in got["counts"]]).astype(np.float32) if len(got) else np.zeros((0, BUCKETS + MARKS), dtype=np.float32)
    return fit(c, got["label"].to_numpy(dtype=np.float64))


def scored(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, held_out, score, predicted for every row; one scan, no shuffle."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for b in batches:
            texts = list(common.texts(b))
            scores = [m.score(counts(texts[i : i + 256])) for i in range(0, len(texts), 256)]
            s = np.concatenate(scores) if scores else np.zeros(0)
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("held_out"), pa.array(s, pa.float64()), pa.array((s >= 0.5).astype(np.int32), pa.int32())], ["doc_id", "held_out", "score", "predicted"])

    picked = docs.select(F.col("doc_id").cast("long").alias("doc_id"), held_out().alias("held_out"), common.text_or_empty().alias("text"))
    return picked.mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int")


def op10_quality_classifier(spark, sf_dir: str) -> DataFrame:
    """Score of every document by labels outside the held-out third; defined results as in the module's docstring."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return scored(docs, train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))
