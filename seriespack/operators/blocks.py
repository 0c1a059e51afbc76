"""Blocks of residuals as aggregates: widths, zero runs and exact sizes without encoding a byte."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import bits as B
from .options import Options
from .ordering import PART, neighbours, prefix_sums


def ors(df: DataFrame, keys: tuple[str, ...] = ("series_id",), block: int = 8) -> DataFrame:
    """(keys, block_id, n, ored): of each block of ``residual``, all bits that its zigzagged values have.

    Partial results are made before the exchange, a row for each block.
    """
    z = df.withColumn("block_id", B.divided(F.col("t"), block)).withColumn("z", B.zigzag(F.col("residual")))
    return z.groupBy(*keys, "block_id").agg(F.count(F.lit(1)).alias("n"), F.bit_or("z").alias("ored"))


def coarser(ored: DataFrame, times: int, keys: tuple[str, ...] = ("series_id",)) -> DataFrame:
    """``ors`` of blocks ``times`` as long."""
    if times == 1:
        return ored
    return ored.groupBy(*keys, B.divided(F.col("block_id"), times).alias("block_id")).agg(F.sum("n").alias("n"), F.bit_or("ored").alias("ored"))


def of_ors(ored: DataFrame, width: int) -> DataFrame:
    """``ored`` as the significant bits and the stored width of each block."""
    return ored.withColumn("bits", B.bit_width(F.col("ored"))).withColumn("stored", B.stored_width(F.col("bits"), width)).drop("ored")


def widths(df: DataFrame, width: int, keys: tuple[str, ...] = ("series_id",), block: int = 8) -> DataFrame:
    """(keys, block_id, n, bits, stored): of each block of ``residual``, the significant bits of its zigzagged values."""
    return of_ors(ors(df, keys, block), width)


def whole_blocks(stats: DataFrame, block: int = 8) -> DataFrame:
    return stats.where(F.col("n") == block)


def by_block(stats: DataFrame, keys: tuple[str, ...] = ("series_id",)) -> DataFrame:
    """A row for each block of a multivariate series: the sum of its columns' stored widths (keys without the column)."""
    return stats.groupBy(*keys, "block_id").agg(F.sum("stored").cast("bigint").alias("stored"), F.count(F.lit(1)).alias("dims"))


def runs(blocks: DataFrame, keys: tuple[str, ...] = ("series_id",)) -> DataFrame:
    """(keys, slot, first_block, n_blocks, kind, stored): data blocks, and maximal runs of blocks of width 0.

    Gaps and islands: blocks of data count up, so the blocks of a run share a count.  Parts of a series are ordered apart
    and joined by their sums.
    """
    marked = neighbours(blocks.withColumn("_zero", F.col("stored") == 0), {"_before": ("_zero", 1)}, keys, "block_id")
    marked = marked.withColumn("_start", (~F.col("_zero") | ~F.coalesce("_before", F.lit(False))).cast("bigint"))
    marked = prefix_sums(marked, "_start", "slot", keys, "block_id").withColumn("slot", F.col("slot") - 1)
    out = marked.groupBy(*keys, "slot").agg(F.min("block_id").alias("first_block"), F.count(F.lit(1)).alias("n_blocks"), F.max("stored").alias("stored"))
    return out.withColumn("kind", F.when(F.col("stored") == 0, F.lit("run")).otherwise(F.lit("data")))


def zero_runs(full: DataFrame, keys: tuple[str, ...] = ("series_id",), part: int = PART) -> DataFrame:
    """(keys, first_block, n_blocks) of maximal runs of blocks of width 0, out of whole blocks.

    Runs are found in each part of a series apart.  Those that reach an edge of their part, two for each part at most, are
    ordered by series and put together; no other row passes a window with more than a part.
    """
    parted = full.where(F.col("stored") == 0).withColumn("_part", B.divided(F.col("block_id"), part))
    nth = F.row_number().over(Window.partitionBy(*keys, "_part").orderBy("block_id"))
    found = parted.withColumn("_island", F.col("block_id") - nth).groupBy(*keys, "_part", "_island").agg(F.min("block_id").alias("first_block"), F.count(F.lit(1)).alias("n_blocks"))
    after = F.col("first_block") + F.col("n_blocks")
    at_edge = (F.col("first_block") % part == 0) | (after % part == 0)
    order = Window.partitionBy(*keys, "_where").orderBy("first_block")
    found = found.withColumn("_where", F.when(at_edge, F.lit(-1).cast("bigint")).otherwise(F.col("_part")))
    found = found.withColumn("_new", (~F.coalesce(F.lag(after).over(order) == F.col("first_block"), F.lit(False))).cast("bigint"))
    found = found.withColumn("_run", F.sum("_new").over(order.rowsBetween(Window.unboundedPreceding, 0)))
    return found.groupBy(*keys, "_where", "_run").agg(F.min("first_block").alias("first_block"), F.sum("n_blocks").alias("n_blocks")).drop("_where", "_run")


def body_sizes(residuals: DataFrame, o: Options, keys: tuple[str, ...] = ("series_id",)) -> DataFrame:
    """(keys, n, body_bytes, and its parts) of univariate residuals: exact sizes in generated code."""
    return sizes_of_stats(widths(residuals, o.width_bits, keys, o.block), o, keys)


def sizes_of_stats(stats: DataFrame, o: Options, keys: tuple[str, ...] = ("series_id",)) -> DataFrame:
    """The same of the blocks' widths: blocks of data add up in any order, only blocks of width 0 are put in order, to find their runs."""
    h, whole = B.header_bits(o.width_bits), F.col("n") == o.block
    data = whole & (F.col("stored") > 0) if o.rle else whole
    total = lambda found, of: F.sum(F.when(found, of).otherwise(F.lit(0)))
    out = stats.groupBy(*keys).agg(
        F.sum("n").alias("n"),
        (total(F.col("n") < o.block, F.col("n")) * (o.width_bits // 8)).alias("tail_bytes"),
        total(data, F.lit(1)).alias("slots"),
        total(data, B.payload_bytes(F.col("stored"), 1, o.width_bits, o.layout, o.block)).alias("payload_bytes"),
    )
    runs_ = zero_runs(whole_blocks(stats, o.block) if o.rle else stats.where(F.lit(False)), keys)
    runs_ = runs_.groupBy(*keys).agg(F.count(F.lit(1)).alias("_runs"), F.sum(B.varint_bytes(F.col("n_blocks"))).alias("run_bytes"), F.sum("n_blocks").alias("zero_blocks"))
    out = out.join(runs_, list(keys), "left").fillna(0, ["_runs", "run_bytes", "zero_blocks"])
    out = out.withColumn("slots", F.col("slots") + F.col("_runs")).drop("_runs")
    full, rest = B.divided(F.col("slots"), o.group), F.col("slots") % o.group
    header = full * F.lit(-(-o.group * h // 8)) + F.ceil(rest * h / 8)
    out = out.withColumn("header_bytes", header.cast("bigint"))
    return out.withColumn("body_bytes", (F.col("header_bytes") + F.col("payload_bytes") + F.col("run_bytes") + F.col("tail_bytes")).cast("bigint"))
