"""Surfaces around the codec: sources and sinks, streams, set operations, samples, functions of one's own."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from ..functions import bits as B
from ..operators import analysis, codec, forecast
from ..operators.relayout import null_policy, wide
from ..sources import builders as S
from ..sources import files
from ..sources.shared import fresh
from ..sources.tables import load
from ..streaming import encoder
from .queries import UNIVARIATE, query, r6, series


def _arrivals(spark, d):
    """Events as samples of their types, with a time that a watermark can follow."""
    e = load(spark, d, "events")
    return e.select(F.col("event_type").alias("series_id"), F.col("ts").cast("timestamp").alias("ts"), F.col("event_id").alias("tie"), S.cents("value").alias("v"), "user_id")


def _in_turns(spark, parts, transform, name: str):
    """What a query writes that is stopped and started again after each of ``parts`` has arrived."""
    root = fresh(spark, name)
    for part in parts:
        part.write.mode("append").parquet(f"{root}/in")
        encoder.replay(spark, f"{root}/in", part.schema, transform, f"{root}/out", f"{root}/state")
    return spark.read.parquet(f"{root}/out")


@query
def q60_stream_late_rows(spark, d):
    """Rows that come after newer ones were sealed: told apart, and never in a block."""
    e = _arrivals(spark, d).drop("user_id")
    o = encoder.CENTS
    out = _in_turns(spark, [e.where("tie % 10 <> 0"), e.where("tie % 10 = 0")], lambda s: encoder.encode_stream(s, o, 256), "q60")
    return out.where("kind = 'late'").groupBy("series_id").agg(F.count(F.lit(1)).alias("n"), F.sum("late_value").alias("total"))


@query
def q60_stream_idle_flush(spark, d):
    """Held segments that an event-time timer seals; every sample comes out once."""
    e = _arrivals(spark, d).drop("user_id")
    end = e.agg(F.max("ts").alias("m"))
    # one sample of a series of its own, a month later, moves the watermark past every timer
    mark = end.select(F.lit("mark").alias("series_id"), (F.col("m") + F.expr("INTERVAL 30 DAYS")).alias("ts"), F.lit(0).cast("bigint").alias("tie"), F.lit(0).cast("bigint").alias("v"))
    o = encoder.CENTS
    out = _in_turns(spark, [e, mark, mark], lambda s: encoder.encode_stream(s.withWatermark("ts", "1 hour"), o, 256, hold=True, idle_seconds=3600), "q60i")
    return codec.decode(encoder.as_segments(out.where("series_id <> 'mark'"), o)).select("series_id", "t", F.col("x")[0].alias("x"))


@query
def q60_stream_sessions(spark, d):
    """Sessions of each user that a stream has closed."""
    root = fresh(spark, "q60s")
    make = lambda s: encoder.sessions(s.select(F.col("user_id").cast("string").alias("series_id"), F.col("ts").cast("timestamp").alias("ts"), S.cents("value").alias("v")))
    encoder.replay(spark, f"{d}/events.parquet*", load(spark, d, "events").schema, make, f"{root}/out", f"{root}/state")
    return spark.read.parquet(f"{root}/out")


@query
def q85_top_blocks(spark, d):
    """The five widest blocks of each series; partial results keep five a task, not all blocks of a series."""
    stats = forecast.lag1(series(spark, d, UNIVARIATE, 16), 16).groupBy("series_id", B.divided(F.col("t"), 8).alias("block_id")).agg(B.bit_width(F.bit_or(B.zigzag(F.col("residual")))).alias("bits"), F.sum(F.abs("residual")).alias("total"))
    return analysis.top(stats, ["series_id"], ["bits", "total"], "block_id", 5).select("series_id", "place", "block_id", "bits", "total")


@query
def q86_json_channel(spark, d):
    """A number inside a JSON column as a series of its own, by type."""
    e = load(spark, d, "events").select("event_id", "ts", "event_type", F.variant_get(F.try_parse_json("props"), "$.k", "bigint").alias("k"))
    made = S.positions(e, F.unix_date(F.to_date("ts")), ["ts", "event_id"], ("event_type",))
    return null_policy(made.select(F.col("event_type").alias("series_id"), "t", F.col("k").alias("v")), "carry_forward").select("series_id", "t", "v")


@query
def q87_functions_of_ones_own(spark, d):
    """A vectorized function and an aggregate over Pandas beside the native ones they must equal."""

    @F.pandas_udf("bigint")
    def zigzagged(e: pd.Series) -> pd.Series:
        return pd.Series(np.where(e >= 0, 2 * e, -2 * e - 1))

    @F.pandas_udf("bigint")
    def width_of(z: pd.Series) -> int:
        return int(np.bitwise_or.reduce(z.to_numpy(np.int64))).bit_length()

    r = forecast.lag1(series(spark, d, ["ev_walk"], 16), 16).withColumn("block_id", B.divided(F.col("t"), 64))
    z = r.select("block_id", zigzagged("residual").alias("z"), B.zigzag(F.col("residual")).alias("native"))
    own = z.groupBy("block_id").agg(width_of("z").alias("own_bits"))
    native = z.groupBy("block_id").agg(B.bit_width(F.bit_or("native")).alias("bits"), F.sum("native").alias("total"))
    return own.join(native, "block_id")


@query
def q88_set_operations(spark, d):
    """Users that bought and erred, that bought and never erred, and that did either."""
    e = load(spark, d, "events")
    of = lambda kind: e.where(F.col("event_type") == kind).select("user_id")
    made = {"both": of("purchase").intersect(of("error")), "first only": of("purchase").subtract(of("error")), "either": of("purchase").union(of("error")).distinct()}
    parts = [df.select(F.lit(k).alias("kind"), "user_id") for k, df in made.items()]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


@query
def q89_sampled_advice(spark, d):
    """Advice from every eighth run of 512 samples; how far it is from that on all of them."""
    q = series(spark, d, UNIVARIATE, 16)
    return analysis.advise(analysis.every_nth_run(q, 8, 512)).select("series_id", "n", "levels", *r6("zero_share", "roughness"), "advice")


@query
def q90_text_and_binary_sources(spark, d):
    """A series through delimited text and through dumps of little-endian numbers."""
    q = series(spark, d, ["ev_walk", "ev_total"], 16)
    root = fresh(spark, "q90")
    files.write_delimited(q, f"{root}/text")
    files.write_dumps(q, f"{root}/dumps", 16)
    a = files.read_delimited(spark, f"{root}/text").withColumnRenamed("x", "from_text")
    b = files.read_dumps(spark, f"{root}/dumps", 16).withColumnRenamed("x", "from_dump")
    return a.join(b, ["series_id", "t"], "full_outer")


@query
def q91_datasource_write(spark, d):
    """Samples written by the data source and read back by it, once as a table and once as a stream."""
    from ..sources.datasource import EncodedSeries, arranged

    spark.dataSource.register(EncodedSeries)
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    root = fresh(spark, "q91")
    rows = arranged(wide(series(spark, d, ["ev_ma64"], 16)), 1024)
    rows.write.format("encoded_series").option("path", f"{root}/in").option("segment_length", "1024").mode("append").save()
    source = spark.readStream.format("encoded_series").option("path", f"{root}/in").load()
    query_ = source.writeStream.format("parquet").option("path", f"{root}/out").option("checkpointLocation", f"{root}/state").trigger(availableNow=True).start()
    query_.awaitTermination()
    streamed = spark.read.schema("series_id string, t bigint, x array<bigint>").parquet(f"{root}/out").select("t", F.col("x")[0].alias("streamed"))
    table = spark.read.format("encoded_series").option("path", f"{root}/in").load().select("t", F.col("x")[0].alias("x"))
    return table.join(streamed, "t", "full_outer")
