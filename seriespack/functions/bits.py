"""Column functions of the codec: modular wrap, zigzag, significant bits, stored widths, sizes.

All stay inside generated code; nulls give null.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def wrap(value: Column, width: int) -> Column:
    """``value`` modulo 2^width as a signed number of that many bits."""
    half = 1 << (width - 1)
    return F.pmod(value + F.lit(half), F.lit(1 << width)) - F.lit(half)


def unsigned(value: Column, width: int) -> Column:
    return F.pmod(value, F.lit(1 << width))


def zigzag(residual: Column) -> Column:
    """Twice the absolute value, less one for negative numbers."""
    return F.when(residual >= 0, residual * 2).otherwise(residual * -2 - 1)


def unzigzag(z: Column) -> Column:
    return F.when(z % 2 == 0, F.shiftright(z, 1)).otherwise(-F.shiftright(z, 1) - 1)


def bit_width(value: Column) -> Column:
    """Significant bits of a value that is not negative."""
    return F.when(value == 0, F.lit(0)).otherwise(F.length(F.bin(value))).cast("bigint")


def width_code(bits: Column, width: int) -> Column:
    """What the header stores: all of w-1 and w share the top code."""
    return F.least(bits, F.lit(width - 1)).cast("bigint")


def stored_width(bits: Column, width: int) -> Column:
    return F.when(bits >= width - 1, F.lit(width)).otherwise(bits).cast("bigint")


def header_bits(width: int) -> int:
    """Bits of one column's width in a header."""
    return width.bit_length() - 1


def payload_bytes(widths_sum: Column, dims: int, width: int, layout: str = "auto", block: int = 8) -> Column:
    """Payload of a block out of the sum of its stored widths (column-major blocks of 8 need no padding)."""
    if resolve_layout(layout, dims, width) == "column":
        return F.ceil(widths_sum * block / 8).cast("bigint")
    return (F.ceil(widths_sum / 8) * block).cast("bigint")


def resolve_layout(layout: str, dims: int, width: int) -> str:
    """Column-major up to samples of 32 bits, row-major beyond."""
    if layout == "auto":
        return "column" if dims * width <= 32 else "row"
    if layout not in ("column", "row"):
        raise ValueError(f"no such layout: {layout}")
    return layout


def varint_bytes(value: Column) -> Column:
    """Length of an unsigned LEB128 number of at least 1."""
    return F.ceil(F.length(F.bin(value)) / 7).cast("bigint")


def divided(value: Column, by: Column | int) -> Column:
    """Whole-number division that truncates toward zero."""
    by = F.lit(by) if isinstance(by, int) else by
    return F.call_function("div", value.cast("bigint"), by.cast("bigint"))


def with_zigzag(df: DataFrame, column: str = "residual") -> DataFrame:
    return df.withColumn("z", zigzag(F.col(column)))
