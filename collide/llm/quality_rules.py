"""Quality rules with host-level verdicts.

Each document is measured and judged by fixed rules. Failures are summed by host (the `source` column), each host's
failure rate is shrunk towards the mean of all hosts by a beta prior fitted to the mean and variance of the hosts' own
rates, and the verdict on a host is joined back to its documents: a host whose rate lies above the prior's mean, at odds of
three to one or more by its own beta distribution, is suspect and held to stricter limits. A clean document of a suspect
host stays.

Defined results: a null text counts as an empty one (no words, so it fails); a null host is a host of its own; repeated
rows are judged one by one; an empty table gives an empty result; a very long text is measured whole, in time close to
proportion; other columns are ignored whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

SYMBOLS = "#*$%&|<>"
_SPACES, _SYMBOLS = b" \t\n\x0b\x0c\r", SYMBOLS.encode()
WINDOW = 5


@dataclass(frozen=True)
class Limits:
    """Shares above which a document fails: of symbols in its word characters, of repeated lines, of repeated words, and of capitals."""

    symbols: float
    dup_lines: float
    repeats: float
    capitals: float


#: Anywhere, and on a suspect host.
USUAL = Limits(symbols=0.10, dup_lines=0.60, repeats=0.20, capitals=0.70)
STRICT = Limits(symbols=0.04, dup_lines=0.30, repeats=0.10, capitals=0.40)
#: A host is suspect if its shrunk rate exceeds the prior's mean by so many of its standard deviations: odds of three to one.
SUSPECT = 0.6745
MIN_WORDS = 10



def measure_text(text: str) -> tuple[int, ...]:
    """(words, word characters, symbols, repeated lines, words in repeated windows, lines, capitals, cased letters)."""
    raw = text.encode("utf-8", "surrogatepass")
    words = raw.split()
    seen: set[bytes] = set()
    lines = dup = 0
    for line in raw.split(b"\n"):
        if line and line.strip():
            lines += 1
            if line in seen:
                dup += 1
            else:
                seen.add(line)
    repeated = 0
    if len(words) > WINDOW:
        _, inverse, counts = np.unique(common.windows_hash(common.word_hashes(words), WINDOW), return_inverse=True, return_counts=True)
        starts = np.flatnonzero(counts[inverse] > 1)
        if len(starts):
            repeated = int(common.covered(starts, starts + WINDOW, len(words)).sum())
    ascii_bytes = np.frombuffer(raw, dtype=np.uint8)
    upper = int(((ascii_bytes >= 65) & (ascii_bytes <= 90)).sum())
    lower = int(((ascii_bytes >= 97) & (ascii_bytes <= 122)).sum())
    return (len(words), len(text) - len(raw) + len(raw.translate(None, _SPACES)), len(raw) - len(raw.translate(None, _SYMBOLS)), dup, repeated, lines, upper, upper + lower)


def _measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        rows = [measure_text(t) for t in common.texts(b)]
        columns = [pa.array([r[i] for r in rows], pa.int64()) for i in range(8)]
        yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("host"), b.column("key"), *columns], ["doc_id", "host", "key", *_MEASURES])


_MEASURES = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_capitals", "n_letters"]


def measures(docs: DataFrame, host: str = "source") -> DataFrame:
    """One row of counts per row of docs: doc_id, host, key and the measures. One scan, no shuffle."""
    common.ship(docs.sparkSession)
    picked = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(host).cast("string").alias("host"), common.doc_key().alias("key"), common.text_or_empty().alias("text"))
    return picked.mapInArrow(_measure, "doc_id long, host string, key long, " + ", ".join(f"{m} long" for m in _MEASURES))


def _over(limits: Limits):
    return (
        (F.col("n_symbols") > limits.symbols * F.col("word_chars"))
        | (F.col("n_dup_lines") > limits.dup_lines * F.col("n_lines"))
        | (F.col("n_repeat_words") > limits.repeats * F.col("n_words"))
        | ((F.col("n_letters") >= 20) & (F.col("n_capitals") > limits.capitals * F.col("n_letters")))
    )


def host_verdicts(measured: DataFrame, suspect: float = SUSPECT) -> DataFrame:
    """(host, n_docs, n_failed, shrunk_rate, host_bad). The prior's two parameters come from the mean and variance of all hosts' rates."""
    hosts = measured.groupBy("host").agg(F.count(F.lit(1)).alias("n_docs"), F.sum(F.col("failed").cast("long")).alias("n_failed"))
    rate = F.col("n_failed") / F.col("n_docs")
    prior = hosts.agg(F.avg(rate).alias("m"), F.coalesce(F.var_pop(rate), F.lit(0.0)).alias("v"))
    # a beta distribution of mean m and strength s has the variance m(1-m)/(s+1)
    strength = F.least(F.greatest(F.col("m") * (1 - F.col("m")) / F.greatest(F.col("v"), F.lit(1e-6)) - 1, F.lit(2.0)), F.lit(1000.0))
    fitted = prior.select("m", strength.alias("s")).first()  # two numbers; null without hosts
    m, s = (fitted["m"], fitted["s"]) if fitted["m"] is not None else (0.5, 2.0)
    judged = hosts.withColumn("shrunk_rate", (F.col("n_failed") + F.lit(m * s)) / (F.col("n_docs") + F.lit(s)))
    spread = F.sqrt(F.col("shrunk_rate") * (1 - F.col("shrunk_rate")) / (F.col("n_docs") + F.lit(s + 1)))
    return judged.select("host", "n_docs", "n_failed", "shrunk_rate", (F.col("shrunk_rate") - F.lit(m) > suspect * spread).alias("host_bad"))


def judge(docs: DataFrame, host: str = "source", suspect: float = SUSPECT) -> DataFrame:
    """Measures and verdict of every row: doc_id, key, the measures, base_failed, shrunk_rate, kept."""
    base = (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))
    measured = common.materialise(measures(docs, host).withColumn("base_failed", base).withColumn("failed", F.col("base_failed") | _over(USUAL)))
    verdicts = host_verdicts(measured, suspect).select(F.col("host").alias("v_host"), "shrunk_rate", "host_bad")
    joined = measured.join(verdicts, F.col("host").eqNullSafe(F.col("v_host")), "left")
    kept = ~F.col("failed") & ~(F.coalesce(F.col("host_bad"), F.lit(False)) & _over(STRICT))
    return joined.withColumn("kept", kept).drop("v_host")


def keep_good(docs: DataFrame, host: str = "source") -> DataFrame:
    """The rows of docs that the rules keep, with all their columns."""
    rejected = judge(docs, host).where(~F.col("kept")).select(F.col("key").alias("rejected"), F.col("doc_id").alias("r_doc")).distinct()
    same = (F.col("key") == F.col("rejected")) & F.col("row.doc_id").cast("long").eqNullSafe(F.col("r_doc"))
    return common.unwrapped(common.wrapped(docs).join(rejected, same, "left_anti"), docs.columns)


def op3_quality_rules(spark, sf_dir: str) -> DataFrame:
    """Measures, base rules and the method's verdict of every document; defined results as in the module's docstring."""
    judged = judge(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return judged.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", F.round("shrunk_rate", 6).alias("shrunk_rate"))
