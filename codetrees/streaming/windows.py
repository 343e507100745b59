"""Streaming: counts are sums, so compact data can be kept per time window; and models score rows as they come.

Every function takes a streaming or a static DataFrame; on static ones the same windows give exact batch results.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codetrees.operators.apply import code_length
from codetrees.plans.model import Model


def stream_compact(df: DataFrame, ts: str, mask: str, duration: str, slide: str | None = None, late: str = "1 day") -> DataFrame:
    """Compact rows per tumbling (or, with slide, sliding) window: (start, m, n). Rows later than `late` are dropped by
    the watermark when streaming."""
    rows = df.select(F.col(ts).cast("timestamp").alias("ts"), F.expr(mask).alias("m"))
    rows = rows.withWatermark("ts", late) if df.isStreaming else rows
    w = F.window("ts", duration, slide) if slide else F.window("ts", duration)
    return rows.groupBy(w.alias("w"), "m").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "m", "n")


def session_baskets(df: DataFrame, key: str, ts: str, item: str, gap: str, late: str = "1 day") -> DataFrame:
    """Sessions of a key with pauses shorter than `gap`: (key, start, items sorted, n)."""
    rows = df.withColumn("__ts", F.col(ts).cast("timestamp"))
    rows = rows.withWatermark("__ts", late) if df.isStreaming else rows
    out = rows.groupBy(F.session_window("__ts", gap).alias("w"), key).agg(F.array_sort(F.collect_set(item)).alias("items"), F.count("*").alias("n"))
    return out.select(key, F.col("w.start").alias("start"), "items", "n")


def previous_event(df: DataFrame, key: str, value: str):
    """Stateful: each event with the key's event before it by event_id, across micro-batches that come in that order
    (state: one value a key). The events of a key in one micro-batch are held together, as Arrow may split them anywhere."""
    kind = df.schema[key].dataType.simpleString()

    def step(k, frames, state):
        last = state.get[0] if state.exists else None
        pdf = pd.concat(list(frames)).sort_values("event_id")
        state.update((pdf[value].iloc[-1],))
        yield pd.DataFrame({key: k[0], "event_id": pdf["event_id"], value: pdf[value], "prev": [last, *pdf[value].tolist()[:-1]]})

    return df.groupBy(key).applyInPandasWithState(step, f"{key} {kind}, event_id long, {value} string, prev string", "last string", "append", "NoTimeout")


def without_repeats(df: DataFrame, ts: str, ident: str, late: str = "1 day") -> DataFrame:
    """Each id once within the watermark; state is bounded by it."""
    if df.isStreaming:
        return df.withWatermark(ts, late).dropDuplicatesWithinWatermark([ident])
    return df.dropDuplicates([ident])


def score_stream(packed: DataFrame, model: Model, sink, smoothing: str = "kt"):
    """Start a query that scores rows (with m) micro-batch by micro-batch and hands (batch id, rows, mean bits) to `sink`;
    it takes what is there and stops."""

    def each(batch: DataFrame, number: int) -> None:
        got = code_length(batch, model, smoothing).agg(F.count("*").alias("rows"), F.avg("bits").alias("bits")).first()
        sink(number, got["rows"], got["bits"])

    return packed.writeStream.foreachBatch(each).trigger(availableNow=True).start()
