"""Streams: continuous ingestion as idempotent batches, windows with late data, state."""

from __future__ import annotations

from collections.abc import Iterable, Iterator, Sequence

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from ..sources.adapters import SourceSpec


def ingest_stream(engine, stream: DataFrame, table: str, name: str, mapping: dict[str, str], checkpoint: str, features: Sequence[str] = (), **options) -> StreamingQuery:
    """Every micro-batch becomes the batch `name-epoch`; an epoch that is committed already is passed over.

    features: backfilled as soon as an epoch is committed.
    """

    def one(frame: DataFrame, epoch: int) -> None:
        batch = f"{name}-{epoch:06d}"
        if engine.catalog.exists(table) and engine.catalog.has_batch(table, batch):
            return
        engine.ingest(SourceSpec("memory", frame=frame), table, batch, mapping, mode="append", **options)
        if features:
            engine.backfill(table, columns=features, batches=[batch])

    return stream.writeStream.foreachBatch(one).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def with_time(events: DataFrame, ts: str = "ts") -> DataFrame:
    """Time without a zone as an instant, which a watermark needs."""
    return events.withColumn(ts, F.col(ts).cast("timestamp"))


def windowed(stream: DataFrame, kind: str, size: str, slide: str | None = None, delay: str = "1 day", by: str = "event_type", ts: str = "ts") -> DataFrame:
    """Counts and sums by tumbling, sliding or session windows."""
    w = F.session_window(ts, size) if kind == "session" else F.window(ts, size, slide if kind == "sliding" else None)
    return stream.withWatermark(ts, delay).groupBy(w.alias("w"), by).agg(F.count("*").alias("n"), F.sum(F.col("value").cast("decimal(28,6)")).alias("total"))


def dedup(stream: DataFrame, key: str, delay: str = "1 day", ts: str = "ts") -> DataFrame:
    """The first row of each key within the watermark."""
    return stream.withWatermark(ts, delay).dropDuplicatesWithinWatermark([key])


def interval_join(left: DataFrame, right: DataFrame, by: str, within: str, delay: str = "1 day") -> DataFrame:
    """Left rows with right rows of the same key at most `within` later."""
    a = left.withWatermark("ts", delay).alias("a")
    b = right.withWatermark("ts", delay).alias("b")
    return a.join(b, F.expr(f"a.{by} = b.{by} and b.ts >= a.ts and b.ts <= a.ts + interval {within}"))


def running_totals(stream: DataFrame, by: str = "user_id", value: str = "value") -> DataFrame:
    """Count and largest value by key, kept as state across micro-batches."""

    def update(key: tuple, frames: Iterable[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n, top = state.get if state.exists else (0, float("-inf"))
        for f in frames:
            n, top = n + len(f), max(top, float(f[value].max()))
        state.update((n, top))
        yield pd.DataFrame({by: [key[0]], "n": [n], "top": [top]})

    return stream.select(by, value).groupBy(by).applyInPandasWithState(update, f"{by} long, n long, top double", "n long, top double", "update", "NoTimeout")


def drain(frame: DataFrame, name: str, mode: str, checkpoint: str) -> DataFrame:
    """Run a stream over what is there now and return what its memory sink holds."""
    query = frame.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    return frame.sparkSession.table(name)
