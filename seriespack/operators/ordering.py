"""Positions, running sums and neighbours over long series, without one task that sees a whole table or series.

Rows fall into ordered ranges by a coarse key (a day, a block of positions), which a second key refines as the
table grows; sums by range are a small table, and only their prefix sums pass an ordered window.  Within a range,
rows are numbered and summed in parallel.  Neighbours of a range's first rows come along as copies.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.bits import divided

#: Rows of a range: what one task sorts at a time is about this much where keys are spread evenly.
RANGE_ROWS = 1 << 18
#: Samples of a series that are ordered together.
PART = 1 << 16


def _ranged(df: DataFrame, coarse: Column, fine: Column | None, rows: int) -> DataFrame:
    """``df`` with ``_bucket``: the coarse key, each of whose values is parted by the fine key into equal spans, more as the table grows."""
    if fine is None:
        return df.withColumn("_bucket", coarse)
    keyed = df.withColumn("_coarse", coarse.cast("bigint")).withColumn("_fine", fine.cast("bigint"))
    spans = keyed.agg(F.count(F.lit(1)).alias("_count"), F.min("_coarse").alias("_c0"), F.max("_coarse").alias("_c1"), F.min("_fine").alias("_f0"), F.max("_fine").alias("_f1"))
    spans = spans.select("_c0", "_f0", (F.col("_f1") - F.col("_f0") + 1).cast("decimal(38,0)").alias("_width"), F.greatest(F.lit(1).cast("bigint"), divided(F.col("_count"), (F.col("_c1") - F.col("_c0") + 1) * rows)).alias("_parts"))
    out = keyed.crossJoin(F.broadcast(spans))
    place = F.call_function("div", (F.col("_fine") - F.col("_f0")).cast("decimal(38,0)") * F.col("_parts"), F.col("_width")).cast("bigint")
    bucket = F.when(F.col("_parts") == 1, F.col("_coarse")).otherwise((F.col("_coarse") - F.col("_c0")) * F.col("_parts") + place)
    return out.withColumn("_bucket", bucket).drop("_coarse", "_fine", "_c0", "_f0", "_width", "_parts")


def positions(df: DataFrame, bucket: Column, order: list, keys: tuple[str, ...] = (), sums: dict[str, Column] | None = None, fine: Column | None = None, rows: int = RANGE_ROWS) -> DataFrame:
    """``df`` with ``t`` (0, 1, ... in the order of bucket, then ``order``) within each of ``keys``, and inclusive running sums.

    ``fine`` is a whole number that ascends with ``order`` within a bucket; equal rows share no position but may swap them, which no result can tell.
    """
    sums = sums or {}
    placed = _ranged(df, bucket, fine, rows)
    marked = placed.withColumns({f"_s_{k}": v for k, v in sums.items()}) if sums else placed
    local = Window.partitionBy(*keys, "_bucket").orderBy(*order)
    so_far = local.rowsBetween(Window.unboundedPreceding, 0)
    marked = marked.withColumns({"_t": F.row_number().over(local) - 1} | {k: F.sum(f"_s_{k}").over(so_far) for k in sums})
    totals = placed.groupBy(*keys, "_bucket").agg(F.count(F.lit(1)).alias("_n"), *[F.sum(v).alias(f"_b_{k}") for k, v in sums.items()])
    before = (Window.partitionBy(*keys) if keys else Window.partitionBy()).orderBy("_bucket").rowsBetween(Window.unboundedPreceding, -1)
    prefix = totals.select(*keys, F.col("_bucket"), *[F.coalesce(F.sum(c).over(before), F.lit(0)).alias(f"_p{c}") for c in ["_n", *[f"_b_{k}" for k in sums]]])
    out = marked.join(prefix, [*keys, "_bucket"])
    out = out.withColumns({"t": (F.col("_t") + F.col("_p_n")).cast("bigint")} | {k: (F.col(k) + F.col(f"_p_b_{k}")).cast("bigint") for k in sums})
    return out.drop("_bucket", "_t", "_p_n", *[f"_s_{k}" for k in sums], *[f"_p_b_{k}" for k in sums])


def moving_sum(df: DataFrame, running: str, size: int, keys: tuple[str, ...] = (), value: str = "v") -> DataFrame:
    """Sums of the last ``size`` values out of an inclusive running sum; only full windows, renumbered from 0.

    A difference of two running sums, so an equi-join on the position and no ordered window.
    """
    earlier = df.select(*keys, (F.col("t") + size).alias("t"), F.col(running).alias("_earlier"))
    out = df.join(earlier, [*keys, "t"], "left").where(F.col("t") >= size - 1)
    return out.withColumn(value, (F.col(running) - F.coalesce("_earlier", F.lit(0))).cast("bigint")).withColumn("t", F.col("t") - (size - 1)).drop("_earlier")


def neighbours(df: DataFrame, made: dict[str, tuple[str, int]], keys: tuple[str, ...], order: str = "t", part: int = PART) -> DataFrame:
    """``df`` with columns of earlier rows of the same ``keys``: name -> (column, how many rows before), null before the first.

    ``order`` counts rows densely.  A window orders ``part`` rows; the last rows of a part are copied into the next one.
    """
    back, own = max(n for _, n in made.values()), divided(F.col(order), part)
    at_end = F.col(order) % part >= part - back
    out = df.withColumn("_part", F.explode(F.when(at_end, F.array(own, own + 1)).otherwise(F.array(own))))
    window = Window.partitionBy(*keys, "_part").orderBy(order)
    out = out.withColumns({name: F.lag(column, n).over(window) for name, (column, n) in made.items()})
    return out.where(own == F.col("_part")).drop("_part")


def prefix_sums(df: DataFrame, value: str, name: str, keys: tuple[str, ...], order: str = "t", part: int = PART) -> DataFrame:
    """``df`` with inclusive running sums of ``value``: within parts of ``part`` rows, plus the sums of the parts before."""
    parted = df.withColumn("_part", divided(F.col(order), part))
    local = Window.partitionBy(*keys, "_part").orderBy(order).rowsBetween(Window.unboundedPreceding, 0)
    totals = parted.groupBy(*keys, "_part").agg(F.sum(value).alias("_total"))
    before = Window.partitionBy(*keys).orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    totals = totals.select(*keys, "_part", F.coalesce(F.sum("_total").over(before), F.lit(0)).alias("_so_far"))
    out = parted.withColumn(name, F.sum(value).over(local)).join(totals, [*keys, "_part"])
    return out.withColumn(name, F.col(name) + F.col("_so_far")).drop("_part", "_so_far")
