"""Streams: coding new points, answering query streams, and vectors of users over windows."""

from __future__ import annotations

from collections.abc import Callable, Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from ..functions.vectors import VectorSet
from ..operators.cellindex import CellIndex, assign_codes
from ..operators.scan import SearchParams
from ..operators.search import indexed_search

EVENT_SCHEMA = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def ingest(index: CellIndex, points: DataFrame, path: str, checkpoint: str) -> StreamingQuery:
    """New points coded under frozen centroids and appended to codes at `path`: map only. Shares and sizes are read from the
    index version a query loads, so appends do not shift them under it."""
    coded = assign_codes(points, index.centroids, index.parts(), index.d, index.params.metric, index.params.parts)
    return coded.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).outputMode("append").trigger(availableNow=True).start()


def answer(index: CellIndex, points: DataFrame, queries: DataFrame, params: SearchParams, sink: Callable[[DataFrame, int], None], checkpoint: str) -> StreamingQuery:
    """Every micro-batch of queries runs the indexed search."""

    def each(batch: DataFrame, number: int) -> None:
        sink(indexed_search(index, VectorSet(points, batch, index.d, 1.0, index.n), params), number)

    return queries.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def _timed(events: DataFrame, late: str) -> DataFrame:
    """Event times as instants, with a watermark where the table is a stream."""
    e = events.withColumn("ts", F.col("ts").cast("timestamp"))
    return e.withWatermark("ts", late) if events.isStreaming else e


def user_windows(events: DataFrame, late: str = "1 hour", size: str = "1 day", slide: str | None = None) -> DataFrame:
    """start, user_id, event_type, n per window; rows later than the watermark are dropped. Batch tables give the same rows."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    e = _timed(events, late)
    return e.groupBy(w.alias("w"), "user_id", "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "user_id", "event_type", "n")


def late_rows(query: StreamingQuery) -> int:
    """Rows that a query's watermark has dropped so far."""
    return sum(op.numRowsDroppedByWatermark for p in query.recentProgress for op in p.stateOperators)


def user_sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    e = _timed(events, late)
    return e.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "user_id", "n")


def running_counts(events: DataFrame) -> DataFrame:
    """user_id, seen, total: state per user, updated with each batch."""
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def update(key: tuple, frames: Iterator, state: GroupState) -> Iterator:
        import pandas as pd

        seen, total = state.get if state.exists else (0, 0.0)
        for f in frames:
            seen += len(f)
            total += float(f["value"].fillna(0).sum())
        state.update((seen, total))
        yield pd.DataFrame({"user_id": [key[0]], "seen": [seen], "total": [total]})

    return events.groupBy("user_id").applyInPandasWithState(update, "user_id long, seen long, total double", "seen long, total double", "update", GroupStateTimeout.NoTimeout)


def once(events: DataFrame) -> DataFrame:
    """Each event once, within the watermark."""
    return _timed(events, "1 hour").dropDuplicatesWithinWatermark(["event_id"])


def drifted(index: CellIndex, new_sizes: DataFrame, limit: float = 4.0) -> bool:
    """Is some cell so much larger than the mean that the index is due for a rebuild?"""
    r = new_sizes.agg(F.max("n_points").alias("most"), F.avg("n_points").alias("mean")).first()
    return bool(r["most"] and r["most"] > limit * r["mean"] * max(1, len(index.centroids[0])))
