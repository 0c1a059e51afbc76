"""Queries over series and segments: materialize, downsample, correlate, align, advise."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.bits import divided, wrap, zigzag
from .codec import decode
from .forecast import steps


def materialize(segments: DataFrame, t0: int, t1: int, step: int = 1, columns: list[int] | None = None) -> DataFrame:
    """Samples of a range, every ``step``-th; segments outside it are pruned."""
    out = decode(segments, t0, t1, columns)
    return out if step == 1 else out.where((F.col("t") - F.lit(t0)) % step == 0)


def downsample(series: DataFrame, bucket: Column, keys: tuple[str, ...] = (), value: str = "x") -> DataFrame:
    """Least, most, sum and count by bucket; partial sums are made before the exchange."""
    return series.withColumn("bucket", bucket).groupBy(*keys, "bucket").agg(F.min(value).alias("least"), F.max(value).alias("most"), F.sum(value).cast("bigint").alias("total"), F.count(F.lit(1)).alias("n"))


def pairwise_corr(long: DataFrame, on: str, name: str, value: str) -> DataFrame:
    """Correlation of each pair of variables over common positions (an equi-join on the position)."""
    o = long.select(F.col(on), F.col(name).alias("other"), F.col(value).alias("_v"))
    return long.join(o, on).where(F.col(name) < F.col("other")).groupBy(F.col(name).alias("one"), "other").agg(F.corr(value, "_v").alias("corr"))


def asof(left: DataFrame, right: DataFrame, time: str, value: str, bucket: Column) -> DataFrame:
    """``left`` with the latest ``value`` of ``right`` at or before ``time``.

    Rows of both are ordered within ranges of time only; what earlier ranges end with is carried over as a
    row for each range.  Without a match the value is null.
    """
    cols = left.columns
    both = left.withColumn("_right", F.lit(0)).withColumn("_v", F.lit(None).cast(right.schema[value].dataType)).unionByName(right.select(*[F.col(c) if c == time else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in cols], F.lit(1).alias("_right"), F.col(value).alias("_v")))
    both = both.withColumn("_bucket", bucket)
    order = Window.partitionBy("_bucket").orderBy(F.col(time), F.desc("_right")).rowsBetween(Window.unboundedPreceding, 0)
    filled = both.withColumn("_latest", F.last("_v", ignorenulls=True).over(order))
    ends = both.groupBy("_bucket").agg(F.max_by("_v", F.when(F.col("_v").isNotNull(), F.col(time))).alias("_end"))
    carried = ends.select("_bucket", F.last("_end", ignorenulls=True).over(Window.orderBy("_bucket").rowsBetween(Window.unboundedPreceding, -1)).alias("_carried"))
    out = filled.where("_right = 0").join(F.broadcast(carried), "_bucket")
    return out.select(*cols, F.coalesce("_latest", "_carried").alias("latest"))


def advise(series: DataFrame, width: int = 16) -> DataFrame:
    """What to compress each series with, and why.

    Few levels or mostly zero blocks favour a general compressor (repeats); differences that resemble the
    one before favour the learning forecaster; the rest is left to lag1.
    """
    d = steps(series, width).withColumnRenamed("_step", "residual")
    d = d.withColumn("_dd", wrap(F.col("residual") - F.col("_last"), width).cast("double"))
    level = d.groupBy("series_id", "x").agg(F.count(F.lit(1)).alias("c"), F.sum(F.col("residual").cast("double") * F.col("residual")).alias("e"), F.sum(F.col("_dd") * F.col("_dd")).alias("ee"))
    whole = level.groupBy("series_id").agg(F.sum("c").alias("n"), F.count(F.lit(1)).alias("levels"), (F.sum("ee") / F.nullif(F.sum("e"), F.lit(0.0))).alias("roughness"))
    block = d.groupBy("series_id", divided(F.col("t"), 8).alias("b")).agg(F.bit_or(zigzag(F.col("residual"))).alias("o"))
    zero = block.groupBy("series_id").agg(F.avg((F.col("o") == 0).cast("double")).alias("zero_share"))
    advice = F.when((F.col("zero_share") > 0.5) | (F.col("levels") < 64), "general").when(F.col("roughness") < 1.5, "adaptive").otherwise("lag1")
    return whole.join(zero, "series_id").select("series_id", "n", "levels", "zero_share", "roughness", advice.alias("advice"))


def every_nth_run(series: DataFrame, nth: int, length: int) -> DataFrame:
    """A systematic sample: every ``nth`` run of ``length`` samples of each series, with positions closed up."""
    run = divided(F.col("t"), length)
    return series.where(run % nth == 0).withColumn("t", divided(run, nth) * length + F.col("t") % length)


def top(df: DataFrame, keys: list[str], by: list[str], tie: str, n: int) -> DataFrame:
    """The ``n`` rows of each key with the greatest ``by`` (the least ``tie`` first among equals), with their ``place`` from 1.

    Rows are cut to ``n`` for each key and salt before those of a key meet, so one key's rows never lie in one task.
    """
    order = [F.desc(c) for c in by] + [F.asc(tie)]
    salted = df.withColumn("_salt", F.pmod(F.xxhash64(tie), F.lit(64)))
    local = salted.withColumn("place", F.row_number().over(Window.partitionBy(*keys, "_salt").orderBy(*order))).where(F.col("place") <= n).drop("_salt")
    return local.withColumn("place", F.row_number().over(Window.partitionBy(*keys).orderBy(*order)).cast("bigint")).where(F.col("place") <= n)
