"""Forecasters as Column expressions over ``(series_id, t, x)``, all in generated code.

Each segment starts from zeros, and positions ``t`` count its samples densely.  Windows order parts of a series, whose
last samples are carried into the next part, so no task orders a whole series; the adaptive forecaster, sequential by
nature, folds a group's samples with a state of a few numbers.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.bits import unsigned, wrap
from .ordering import neighbours, prefix_sums

#: Samples folded into one array before it is put away: appending copies the array it appends to.
CHUNK = 512


def lag1(df: DataFrame, width: int, keys: tuple[str, ...] = ("series_id",)) -> DataFrame:
    """``residual`` against the sample before."""
    out = neighbours(df, {"_one": ("x", 1)}, keys)
    return out.withColumn("residual", wrap(F.col("x") - F.coalesce("_one", F.lit(0)), width)).drop("_one")


def steps(df: DataFrame, width: int, keys: tuple[str, ...] = ("series_id",)) -> DataFrame:
    """``_step`` and ``_last``: each sample's difference from the one before, and the difference before that."""
    return steps_of(df, {"": ("x", width)}, keys)


def steps_of(df: DataFrame, columns: dict[str, tuple[str, int]], keys: tuple[str, ...] = ("series_id",)) -> DataFrame:
    """The same of several columns in one window: suffix of the names -> (column, width)."""
    out = neighbours(df, {f"_{name}{s}": (c, n) for s, (c, _) in columns.items() for name, n in (("one", 1), ("two", 2))}, keys)
    for s, (c, width) in columns.items():
        one, two = (F.coalesce(f"_{name}{s}", F.lit(0)) for name in ("one", "two"))
        out = out.withColumns({f"_step{s}": wrap(F.col(c) - one, width), f"_last{s}": wrap(one - two, width)}).drop(f"_one{s}", f"_two{s}")
    return out


def of_coefficient(stepped: DataFrame, width: int, coef_num: int | Column, suffix: str = "") -> Column:
    """The residual of ``steps`` against the sample before plus ``coef_num``/2^width of the last difference."""
    coef = F.lit(coef_num) if isinstance(coef_num, int) else coef_num
    return wrap(F.col(f"_step{suffix}") - F.shiftright(F.col(f"_last{suffix}") * coef, width), width)


def fixed(df: DataFrame, width: int, coef_num: int | Column, keys: tuple[str, ...] = ("series_id",)) -> DataFrame:
    """``residual`` against the sample before plus ``coef_num``/2^width of the last difference."""
    stepped = steps(df, width, keys)
    return stepped.withColumn("residual", of_coefficient(stepped, width, coef_num)).drop("_step", "_last")


def double_delta(df: DataFrame, width: int, keys: tuple[str, ...] = ("series_id",)) -> DataFrame:
    """Coefficient 1: linear extrapolation."""
    return fixed(df, width, 1 << width, keys)


def two_point_mean(df: DataFrame, width: int, keys: tuple[str, ...] = ("series_id",)) -> DataFrame:
    """Coefficient -1/2: the mean of the last two samples."""
    return fixed(df, width, -(1 << (width - 1)), keys)


def adaptive(df: DataFrame, width: int, keys: tuple[str, ...] = ("series_id",), update: str = "block", rate_shift: int = 1) -> DataFrame:
    """(keys, t, residual, coef) of the learning forecaster by a fold over each group's samples.

    ``coef`` is what the sample was predicted with.  A group may be a whole series: it is folded chunk by chunk, the
    state going on from one to the next.  A group's samples still are one row's array, so a group must fit in a task.
    """
    mod, half = 1 << width, 1 << (width - 1)
    gain_top = 1 << (2 * width - 1)
    grouped = df.groupBy(*keys).agg(F.sort_array(F.collect_list(F.struct("t", "x"))).alias("s"))
    zero = F.lit(0).cast("bigint")
    none = F.expr("cast(array() as array<struct<t: bigint, residual: bigint, coef: bigint>>)")
    numbers = ("prev", "step", "gain", "coef", "total", "i")
    start = F.struct(*[zero.alias(c) for c in numbers], F.array(none).alias("done"), none.alias("out"))

    def clipped(v: Column) -> Column:
        return F.least(F.greatest(v, F.lit(-gain_top)), F.lit(gain_top - 1))

    def next_state(a: Column, s: Column) -> Column:
        coef = F.shiftright(a["gain"], rate_shift) if update == "sample" else F.when(a["i"] % 8 == 0, F.shiftright(a["gain"], rate_shift)).otherwise(a["coef"])
        now = F.pmod(s["x"] - a["prev"] + half, F.lit(mod)) - half
        residual = F.pmod(now - F.shiftright(coef * a["step"], width) + half, F.lit(mod)) - half
        push = F.signum(residual.cast("double")).cast("bigint") * a["step"]
        if update == "sample":
            gain, total = clipped(a["gain"] + push), zero
        else:
            total = F.when(a["i"] % 8 == 0, zero).otherwise(a["total"]) + F.when(a["i"] % 2 == 1, push).otherwise(zero)
            gain = F.when(a["i"] % 8 == 7, clipped(a["gain"] + F.call_function("div", total, F.lit(4).cast("bigint")))).otherwise(a["gain"])
        row = F.struct(s["t"].alias("t"), residual.alias("residual"), coef.alias("coef"))
        return F.struct(s["x"].alias("prev"), now.alias("step"), gain.alias("gain"), coef.alias("coef"), total.alias("total"), (a["i"] + 1).alias("i"), a["done"].alias("done"), F.concat(a["out"], F.array(row)).alias("out"))

    def next_chunk(a: Column, chunk: Column) -> Column:
        put_away = F.struct(*[a[c].alias(c) for c in numbers], F.concat(a["done"], F.array(a["out"])).alias("done"), none.alias("out"))
        return F.aggregate(chunk, put_away, next_state)

    chunks = F.expr(f"transform(sequence(0, (size(s) - 1) div {CHUNK}), i -> slice(s, cast(i * {CHUNK} + 1 as int), {CHUNK}))")
    all_rows = lambda a: F.flatten(F.concat(a["done"], F.array(a["out"])))
    folded = grouped.select(*keys, F.aggregate(chunks, start, next_chunk, all_rows).alias("out"))
    return folded.select(*keys, F.explode("out").alias("r")).select(*keys, "r.t", "r.residual", "r.coef")


def reconstruct(df: DataFrame, width: int, order: int = 1, keys: tuple[str, ...] = ("series_id",)) -> DataFrame:
    """``restored`` samples (unsigned) of lag-1 residuals, or (order 2) of double-delta residuals: one or two prefix sums."""
    out = prefix_sums(df, "residual", "restored", keys).withColumn("restored", unsigned(F.col("restored"), width))
    if order == 2:
        out = prefix_sums(out, "restored", "_twice", keys).withColumn("restored", unsigned(F.col("_twice"), width)).drop("_twice")
    return out


def fit_coefficients(df: DataFrame, keys: tuple[str, ...] = ("series_id",), value: str = "v") -> DataFrame:
    """For analysis, a least-squares fit per series: ``alpha`` of one difference on the one before, and the (a, b) it stands for."""
    d = neighbours(df, {"_one": (value, 1), "_two": (value, 2)}, keys)
    d = d.select(*keys, (F.col(value) - F.col("_one")).cast("double").alias("_d"), (F.col("_one") - F.col("_two")).cast("double").alias("_p")).where("_d is not null and _p is not null")
    out = d.groupBy(*keys).agg((F.sum(F.col("_d") * F.col("_p")) / F.nullif(F.sum(F.col("_p") * F.col("_p")), F.lit(0.0))).alias("alpha"), F.corr("_d", "_p").alias("corr"), F.count(F.lit(1)).alias("n"))
    return out.select(*keys, "n", "alpha", (1 + F.col("alpha")).alias("a"), (-F.col("alpha")).alias("b"), "corr")


def fit_two(df: DataFrame, keys: tuple[str, ...] = ("series_id",), value: str = "v") -> DataFrame:
    """(keys, n, a, b): the two coefficients of the last two samples that predict best in least squares, not tied to each other.

    Sums are taken about each series' first value, which keeps them exact for longer; null where the two samples are collinear.
    """
    x = neighbours(df, {"_one": (value, 1), "_two": (value, 2)}, keys).where("_two is not null")
    origin = df.where(F.col("t") == 0).select(*keys, F.col(value).alias("_origin"))
    x = x.join(F.broadcast(origin), list(keys)).select(*keys, *[(F.col(c) - F.col("_origin")).cast("double").alias(n) for c, n in ((value, "_y"), ("_one", "_p"), ("_two", "_q"))])
    dot = lambda i, j: F.sum(F.col(i) * F.col(j))
    s = x.groupBy(*keys).agg(F.count(F.lit(1)).alias("n"), dot("_p", "_p").alias("pp"), dot("_q", "_q").alias("qq"), dot("_p", "_q").alias("pq"), dot("_y", "_p").alias("yp"), dot("_y", "_q").alias("yq"))
    det = F.nullif(F.col("pp") * F.col("qq") - F.col("pq") * F.col("pq"), F.lit(0.0))
    return s.select(*keys, "n", ((F.col("yp") * F.col("qq") - F.col("yq") * F.col("pq")) / det).alias("a"), ((F.col("yq") * F.col("pp") - F.col("yp") * F.col("pq")) / det).alias("b"))
