"""Encoding of streams: samples per series in order of event time, sealed into segments.

State for each series is what the next segment needs: its position, the newest event time that was taken,
and fewer samples than a segment.  Rows that are older than what was taken come out as ``late`` and never
enter a sealed block.  Replays write the same rows, so a sink that is keyed by (series, segment) is idempotent.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators.codec import pack_many
from ..operators.options import Options

OUTPUT = "kind string, series_id string, t_start bigint, n_samples int, n_slots int, crc bigint, body binary, late_value bigint"
STATE = "next_t bigint, newest bigint, pending array<bigint>"
#: For amounts in cents, which 16 bits do not hold from 655.36 on; negative ones fit too.
CENTS = Options(width_bits=32, forecaster="adaptive", clamp=True, signed=True)


def encode_stream(samples: DataFrame, o: Options, segment: int = 1024, hold: bool = False, idle_seconds: int | None = None, keep_seconds: int | None = None) -> DataFrame:
    """Rows ``segment`` and ``late`` of a stream (series_id, ts timestamp, tie bigint, v bigint).

    ``hold`` keeps an unfinished segment for later batches; without it each batch ends with a short one, so nothing waits
    longer than a trigger.  With ``idle_seconds`` (and a watermark on ``ts``) a held segment is sealed as it is once the
    watermark is that much beyond the series' newest sample.  With ``keep_seconds`` the state of a series that long without
    samples is dropped after that; should it come back, its positions go on from 0 and rows are not late by what was before.
    Samples that do not fit ``o.width_bits`` are refused, as their upper bits would be lost.
    """
    timed = idle_seconds is not None or keep_seconds is not None
    low, high = (-(1 << (o.width_bits - 1)), 1 << (o.width_bits - 1)) if o.signed else (0, 1 << o.width_bits)

    def advance(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        next_t, newest, pending = state.get if state.exists else (0, -(1 << 62), [])
        out = []

        def seal(values: np.ndarray) -> None:
            nonlocal next_t
            (body, slots), *_ = pack_many([values.reshape(-1, 1)], o)
            out.append(("segment", key[0], int(next_t), len(values), slots, zlib.crc32(body), body, None))
            next_t += len(values)

        def remember(values: list[int]) -> None:
            state.update((int(next_t), int(newest), values))
            waits = [s for s in (idle_seconds if values else None, keep_seconds) if s is not None]
            if timed and waits:
                state.setTimeoutTimestamp(int(max(newest // 1000 + min(waits) * 1000, state.getCurrentWatermarkMs() + 1)))

        if timed and state.hasTimedOut:
            if len(pending):
                seal(np.array(pending, np.int64))
            if keep_seconds is not None and state.getCurrentWatermarkMs() >= newest // 1000 + keep_seconds * 1000:
                state.remove()
            else:
                remember([])
        else:
            rows = pd.concat(list(frames)).sort_values(["us", "tie"])
            late, taken = rows[rows.us < newest], rows[rows.us >= newest]
            if ((taken.v < low) | (taken.v >= high)).any():
                raise ValueError(f"samples of {key[0]} don't fit {o.width_bits} bits")
            values = np.array([*pending, *taken.v.tolist()], np.int64)
            out += [("late", key[0], int(next_t), 0, 0, 0, b"", int(v)) for v in late.v]
            whole = len(values) // segment * segment if hold else len(values)
            for a in range(0, whole, segment):
                seal(values[a : min(a + segment, whole)])
            newest = max(newest, taken.us.max() if len(taken) else newest)
            remember([int(v) for v in values[whole:]])
        yield pd.DataFrame(out, columns=["kind", "series_id", "t_start", "n_samples", "n_slots", "crc", "body", "late_value"]).astype({"late_value": "Int64"})

    rows = samples.select("series_id", "ts", F.unix_micros("ts").alias("us"), F.col("tie").cast("bigint").alias("tie"), F.col("v").cast("bigint").alias("v"))
    timeout = GroupStateTimeout.EventTimeTimeout if timed else GroupStateTimeout.NoTimeout
    return rows.groupBy("series_id").applyInPandasWithState(advance, OUTPUT, STATE, "append", timeout)


def as_segments(encoded: DataFrame, o: Options) -> DataFrame:
    """Sealed rows in the form that ``codec.decode`` reads."""
    w = o.width_bits // 8
    options = F.struct(*[F.lit(v).alias(k) for k, v in o.as_dict().items()])
    return encoded.where("kind = 'segment'").select("series_id", F.col("t_start").alias("segment_id"), "t_start", "n_samples", F.lit(1).alias("dims"), (F.col("n_samples") * w).cast("bigint").alias("raw_bytes"), F.length("body").cast("bigint").alias("body_bytes"), "n_slots", "crc", F.lit(1).alias("format_version"), options.alias("options"), "body")


def windowed(samples: DataFrame, size: str = "1 day", lateness: str = "1 hour") -> DataFrame:
    """Sums and counts in tumbling windows of event time, each out once when the watermark has passed it."""
    out = samples.withWatermark("ts", lateness).groupBy(F.window("ts", size), "series_id").agg(F.sum("v").alias("total"), F.count(F.lit(1)).alias("n"))
    return out.select(F.unix_seconds("window.start").alias("start"), "series_id", F.col("total").cast("bigint").alias("total"), "n")


def sessions(samples: DataFrame, gap: str = "30 minutes", lateness: str = "1 hour") -> DataFrame:
    """Sums and counts of sessions: samples of a series less than ``gap`` apart; each out once when the watermark has passed its end."""
    out = samples.withWatermark("ts", lateness).groupBy(F.session_window("ts", gap), "series_id").agg(F.sum("v").alias("total"), F.count(F.lit(1)).alias("n"))
    return out.select(F.unix_micros("session_window.start").alias("start"), F.unix_micros("session_window.end").alias("end"), "series_id", F.col("total").cast("bigint").alias("total"), "n")


def replay(spark, path: str, schema, transform, sink: str, checkpoint: str) -> None:
    """Runs all that is there now of a file stream through ``transform`` into a Parquet sink."""
    source = spark.readStream.schema(schema).parquet(path)
    query = transform(source).writeStream.format("parquet").outputMode("append").option("path", sink).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
