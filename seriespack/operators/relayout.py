"""Re-layout of series: concatenation with interpolated gaps, column chunks, wide and long, null policies."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.bits import divided
from .ordering import PART


def concat_series(parts: DataFrame, gap: int = 5) -> DataFrame:
    """(dataset_id, t, v): the short series of each dataset in the order of ``part_id``, with ``gap`` interpolated samples between.

    Lengths are aggregated first; only (dataset, part) rows pass an ordered window, samples are joined to their offset.
    """
    ends = parts.groupBy("dataset_id", "part_id").agg(F.count(F.lit(1)).alias("n"), F.min_by("v", "t").alias("first"), F.max_by("v", "t").alias("last"))
    order = Window.partitionBy("dataset_id").orderBy("part_id")
    ends = ends.withColumn("offset", F.coalesce(F.sum(F.col("n") + gap).over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).withColumn("next", F.lead("first").over(order))
    own = parts.join(ends.select("dataset_id", "part_id", "offset"), ["dataset_id", "part_id"]).select("dataset_id", (F.col("t") + F.col("offset")).cast("bigint").alias("t"), F.col("v").cast("bigint").alias("v"))
    between = ends.where("next is not null").select("dataset_id", "offset", "n", "last", "next", F.explode(F.sequence(F.lit(1), F.lit(gap))).alias("i"))
    filled = between.select("dataset_id", (F.col("offset") + F.col("n") + F.col("i") - 1).cast("bigint").alias("t"), (F.col("last") + divided((F.col("next") - F.col("last")) * F.col("i"), gap + 1)).cast("bigint").alias("v"))
    return own.unionByName(filled)


def to_column_chunks(series: DataFrame, width: int, buffer_values: int | None = None) -> DataFrame:
    """(series_id, col, chunk, n, raw): each column's values, contiguous and little-endian, in buffers of a bounded number of values."""
    item = width // 8
    per = buffer_values or (1 << 16)
    flat = series.select("series_id", "t", F.posexplode("x").alias("col", "v")).withColumn("chunk", divided(F.col("t"), per))
    hexed = F.lpad(F.hex(F.pmod(F.col("v"), F.lit(1 << width))), item * 2, "0")
    swapped = F.concat(*[F.substring(hexed, 2 * i + 1, 2) for i in reversed(range(item))])
    grouped = flat.withColumn("h", swapped).groupBy("series_id", "col", "chunk").agg(F.array_sort(F.collect_list(F.struct("t", "h"))).alias("s"))
    return grouped.select("series_id", F.col("col").cast("bigint").alias("col"), "chunk", F.size("s").cast("bigint").alias("n"), F.unhex(F.array_join(F.transform("s", lambda r: r["h"]), "")).alias("raw"))


def wide(series: DataFrame) -> DataFrame:
    """(series_id, t, x array) of (series_id, t, x) with one column."""
    return series.select("series_id", "t", F.array("x").alias("x"))


def null_policy(df: DataFrame, policy: str = "error", value: str = "v") -> DataFrame:
    """Nulls in a series: refuse; drop (positions are kept as they are); carry the last value forward (0 before the first);
    or interpolate whole numbers between the values on both sides (nulls before the first and after the last value are dropped).
    """
    if policy == "drop":
        return df.where(F.col(value).isNotNull())
    if policy == "carry_forward":
        parted = df.withColumn("_part", divided(F.col("t"), PART))
        local = Window.partitionBy("series_id", "_part").orderBy("t").rowsBetween(Window.unboundedPreceding, 0)
        ends = parted.groupBy("series_id", "_part").agg(F.max_by(value, F.when(F.col(value).isNotNull(), F.col("t"))).alias("_end"))
        before = Window.partitionBy("series_id").orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
        carried = ends.select("series_id", "_part", F.last("_end", ignorenulls=True).over(before).alias("_carried"))
        out = parted.withColumn(value, F.last(value, ignorenulls=True).over(local)).join(carried, ["series_id", "_part"])
        return out.withColumn(value, F.coalesce(value, "_carried", F.lit(0))).drop("_part", "_carried")
    if policy == "interpolate":
        known = df.where(F.col(value).isNotNull()).select("series_id", F.col("t").alias("_t"), F.col(value).alias("_v"))
        order = Window.partitionBy("series_id", "_part").orderBy("_t")
        starts = known.withColumn("_part", divided(F.col("_t"), PART)).groupBy("series_id", "_part").agg(F.min("_t").alias("_t"), F.min_by("_v", "_t").alias("_v"))
        following = starts.select("series_id", "_part", F.lead("_t").over(Window.partitionBy("series_id").orderBy("_part")).alias("_part_t"), F.lead("_v").over(Window.partitionBy("series_id").orderBy("_part")).alias("_part_v"))
        spans = known.withColumn("_part", divided(F.col("_t"), PART)).withColumns({"_next_t": F.lead("_t").over(order), "_next_v": F.lead("_v").over(order)}).join(following, ["series_id", "_part"])
        spans = spans.select("series_id", "_t", "_v", F.coalesce("_next_t", "_part_t").alias("_next_t"), F.coalesce("_next_v", "_part_v").alias("_next_v"))
        gaps = spans.where(F.col("_next_t") > F.col("_t") + 1).withColumn("_i", F.explode(F.expr("sequence(1L, _next_t - _t - 1)")))
        filled = gaps.select("series_id", (F.col("_t") + F.col("_i")).alias("t"), (F.col("_v") + divided((F.col("_next_v") - F.col("_v")) * F.col("_i"), F.col("_next_t") - F.col("_t"))).alias("_filled"))
        return df.join(filled, ["series_id", "t"], "left").withColumn(value, F.coalesce(value, "_filled")).drop("_filled").where(F.col(value).isNotNull())
    if policy == "error":
        return df.withColumn(value, F.coalesce(F.col(value), F.raise_error(F.lit("a sample is null")).cast("bigint")))
    raise ValueError("policy is error, drop, carry_forward or interpolate")
