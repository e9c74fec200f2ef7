"""Streams over splitters: window loads per bucket, late rows, re-splitting, counters in state."""

from __future__ import annotations

from collections.abc import Iterator
from typing import Any

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from rangecut.functions.udfs import bucket_udf
from rangecut.plans import exchange, search
from rangecut.plans.keys import KeySpec


def windowed_loads(rows: DataFrame, key: str, bounds: list[float], window: str, slide: str | None = None, gap: str | None = None, watermark: str | None = None) -> DataFrame:
    """start, end, bucket, rows of tumbling, sliding or session windows; works on streams and on tables."""
    timed = rows.withColumn("ts", F.col("ts").cast("timestamp")).withColumn("bucket", bucket_udf(bounds)(key))
    if watermark:
        timed = timed.withWatermark("ts", watermark)
    at = F.session_window("ts", gap) if gap else F.window("ts", window, slide) if slide else F.window("ts", window)
    return timed.groupBy(at.alias("w"), "bucket").agg(F.count("*").alias("rows")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "bucket", "rows")


def run_to_memory(stream: DataFrame, name: str, mode: str = "complete", checkpoint: str | None = None) -> DataFrame:
    """Everything that is there, into a table in memory."""
    writer = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True)
    if checkpoint:
        writer = writer.option("checkpointLocation", checkpoint)
    writer.start().awaitTermination()
    return stream.sparkSession.table(name)


def late_rows(batches: DataFrame, batch: str, ts: str, delay_seconds: int) -> DataFrame:
    """The batch twin of a watermark: rows older than the greatest time of earlier batches less the delay."""
    from pyspark.sql import Window

    tops = batches.groupBy(batch).agg(F.max(ts).alias("_top"))
    seen = F.max("_top").over(Window.orderBy(batch).rowsBetween(Window.unboundedPreceding, -1))  # a row for each batch
    edges = tops.withColumn("_seen", seen).select(batch, "_seen")
    return batches.join(F.broadcast(edges), batch).where(F.col(ts) < F.col("_seen") - F.expr(f"INTERVAL {delay_seconds} SECONDS")).drop("_seen")


class Resplitter:
    """A foreachBatch sink that keeps splitters: counts each batch on them, and narrows anew where the balance is gone."""

    def __init__(self, spec: KeySpec, parts: int, eps: float):
        self.spec, self.parts, self.eps = spec, parts, eps
        self.keys: list = []
        self.log: list[tuple[int, float, int]] = []
        self.done: set[int] = set()

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        if batch_id in self.done:  # a batch that is delivered again changes nothing
            return
        held = batch.persist()
        try:
            if held.isEmpty():
                return
            if self.keys:
                result = search.warm_start(held, self.spec, self.keys, self.parts, self.eps)
            else:
                result = search.budget_rounds(held, self.spec, self.parts, self.eps, portable=False)
            self.keys = result.keys
            self.log.append((batch_id, exchange.imbalance(exchange.assign_bucket(held, self.spec, self.keys), self.parts), result.rounds))
            self.done.add(batch_id)
        finally:
            held.unpersist()


def counted_in_state(rows: DataFrame, key: str, bounds: list[float]) -> DataFrame:
    """Running rows per bucket, kept in the stream's state."""

    def count(bucket: tuple[Any, ...], parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        total = (state.get[0] if state.exists else 0) + sum(len(p) for p in parts)
        state.update((total,))
        yield pd.DataFrame({"bucket": [bucket[0]], "rows": [total]})

    placed = rows.withColumn("bucket", bucket_udf(bounds)(key)).select("bucket")
    return placed.groupBy("bucket").applyInPandasWithState(count, "bucket int, rows long", "total long", "update", GroupStateTimeout.NoTimeout)
