"""Quantizers: a linear rescale to the whole range of w bits, rounded down; and back.

Bounds are a small aggregate that is joined back.  Equal bounds give 0.  Nulls stay null.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.bits import divided

_WIDE = "decimal(20,0)"


def rescaled(value: Column, lo: Column, hi: Column, top: int) -> Column:
    """Whole numbers from ``lo`` .. ``hi`` to 0 .. ``top``, rounded down; ranges whose product with ``top`` passes 64 bits go through decimals."""
    lo_, span = lo.cast(_WIDE), hi.cast(_WIDE) - lo.cast(_WIDE)
    exact = F.call_function("div", (value.cast(_WIDE) - lo_) * F.lit(top).cast("decimal(10,0)"), span)
    return F.when(span > ((1 << 63) - 1) // top, exact).otherwise(divided((value - lo) * F.lit(top), F.greatest(hi - lo, F.lit(1))))


def bounds(df: DataFrame, keys: list[str], value: str = "v") -> DataFrame:
    return df.groupBy(*keys).agg(F.min(value).alias("lo"), F.max(value).alias("hi"))


def quantize(df: DataFrame, width: int, keys: tuple[str, ...] = ("series_id",), value: str = "v", mode: str = "exact", levels: int | None = None) -> DataFrame:
    """``df`` with ``x`` (0 .. 2^width-1) and the bounds ``lo``, ``hi``.  ``exact``: whole-number values and division; ``float``: doubles."""
    top = (1 << width) - 1 if levels is None else levels
    out = df.join(F.broadcast(bounds(df, list(keys), value)), list(keys))
    if mode == "exact":
        x = rescaled(F.col(value), F.col("lo"), F.col("hi"), top)
    elif mode == "float":
        x = F.floor((F.col(value) - F.col("lo")) / F.nullif(F.col("hi") - F.col("lo"), F.lit(0.0)) * F.lit(float(top)))
        x = F.when(F.col(value).isNotNull(), F.coalesce(x, F.lit(0)))
    else:
        raise ValueError("mode is exact or float")
    return out.withColumn("x", x.cast("bigint"))


def dequantize(df: DataFrame, width: int, levels: int | None = None) -> DataFrame:
    """``df`` with ``restored``, the lower end of each level."""
    top = (1 << width) - 1 if levels is None else levels
    return df.withColumn("restored", F.col("lo").cast("double") + F.col("x") * (F.col("hi") - F.col("lo")).cast("double") / F.lit(float(top)))


def scale_exact(df: DataFrame, decimals: int, value: str = "v") -> DataFrame:
    """Values with a fixed number of decimals as whole numbers, without loss."""
    return df.withColumn(value, F.round(F.col(value) * F.lit(10**decimals)).cast("bigint"))


def nmse(df: DataFrame, keys: list[str], width: int, value: str = "v", levels: int | None = None) -> DataFrame:
    """Mean squared quantization error over variance, for each of ``keys``; null where the variance is 0."""
    q = dequantize(quantize(df, width, tuple(keys), value, "float", levels), width, levels)
    out = q.groupBy(*keys).agg(F.avg(F.pow(F.col(value) - F.col("restored"), 2)).alias("mse"), F.var_pop(value).alias("variance"))
    return out.withColumn("nmse", F.col("mse") / F.nullif(F.col("variance"), F.lit(0.0)))
