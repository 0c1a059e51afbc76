"""Measures: ratios, ranks and their tests, quantization, noise, fronts; each a plan over small tables.

A method's name, ``method``, a dataset's, ``dataset_id``, and ``width_bits`` key a size table
``(dataset_id, method, width_bits, raw_bytes, enc_bytes)``.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.bits import bit_width, zigzag
from .ordering import neighbours

#: Studentized range over sqrt(2) at 0.05 for 2, 3, ... 20 methods.
Q05 = (1.960, 2.343, 2.569, 2.728, 2.850, 2.949, 3.031, 3.102, 3.164, 3.219, 3.268, 3.313, 3.354, 3.391, 3.426, 3.458, 3.489, 3.517, 3.544)
#: The same at 0.10.
Q10 = (1.645, 2.052, 2.291, 2.459, 2.589, 2.693, 2.780, 2.855, 2.920, 2.978, 3.030, 3.077, 3.120, 3.159, 3.196, 3.230, 3.261, 3.291, 3.319)


def compression_ratio(sizes: DataFrame) -> DataFrame:
    return sizes.groupBy("dataset_id", "method", "width_bits").agg(F.sum("raw_bytes").alias("raw_bytes"), F.sum("enc_bytes").alias("enc_bytes")).withColumn("ratio", F.col("raw_bytes") / F.col("enc_bytes"))


def ratio_boxplot(ratios: DataFrame) -> DataFrame:
    q = F.percentile("ratio", F.array(*[F.lit(p) for p in (0.0, 0.25, 0.5, 0.75, 1.0)]))
    out = ratios.groupBy("method", "width_bits").agg(F.count(F.lit(1)).alias("n"), q.alias("q"))
    return out.select("method", "width_bits", "n", *[F.col("q")[i].alias(k) for i, k in enumerate(("least", "q1", "median", "q3", "most"))])


def ranks(ratios: DataFrame) -> DataFrame:
    """``rank`` of each method on each dataset: 1 for the highest ratio, ties averaged."""
    w = Window.partitionBy("dataset_id", "width_bits")
    first = F.rank().over(w.orderBy(F.desc("ratio")))
    ties = F.count(F.lit(1)).over(Window.partitionBy("dataset_id", "width_bits", "ratio"))
    return ratios.withColumn("rank", first + (ties - 1) / 2)


def mean_ranks(ratios: DataFrame) -> DataFrame:
    return ranks(ratios).groupBy("method", "width_bits").agg(F.avg("rank").alias("mean_rank"), F.count(F.lit(1)).alias("n"))


def friedman(ratios: DataFrame) -> DataFrame:
    """Friedman's chi-square of the mean ranks."""
    m = mean_ranks(ratios).groupBy("width_bits").agg(F.count(F.lit(1)).alias("k"), F.max("n").alias("n"), F.sum(F.col("mean_rank") * F.col("mean_rank")).alias("s"))
    k = F.col("k")
    return m.select("width_bits", "k", "n", (F.lit(12.0) * F.col("n") / (k * (k + 1)) * (F.col("s") - k * (k + 1) * (k + 1) / F.lit(4.0))).alias("chi2"))


def critical(ratios: DataFrame, alpha: float = 0.05) -> DataFrame:
    """Mean ranks with the critical difference ``cd``; 2 to 20 methods are in the table."""
    if alpha not in (0.05, 0.10):
        raise ValueError("critical values are for 0.05 and 0.10")
    table = Q05 if alpha == 0.05 else Q10
    k = F.count(F.lit(1)).over(Window.partitionBy("width_bits"))
    q = F.when(k.between(2, len(table) + 1), F.get(F.array(*[F.lit(x) for x in table]), (k - 2).cast("int"))).otherwise(F.raise_error(F.lit(f"critical values are for 2 to {len(table) + 1} methods")).cast("double"))
    return mean_ranks(ratios).withColumn("cd", q * F.sqrt(k * (k + 1) / (6.0 * F.col("n"))))


def nemenyi(ratios: DataFrame, alpha: float = 0.05) -> DataFrame:
    """Pairs of methods, the difference of their mean ranks, the critical difference, and whether they differ."""
    m = critical(ratios, alpha)
    o = m.select("width_bits", F.col("method").alias("other"), F.col("mean_rank").alias("other_rank"))
    out = m.join(o, "width_bits").where("method < other")
    return out.select("width_bits", "method", "other", F.abs(F.col("mean_rank") - F.col("other_rank")).alias("difference"), "cd", (F.abs(F.col("mean_rank") - F.col("other_rank")) > F.col("cd")).alias("differ"))


def rank_groups(ratios: DataFrame, alpha: float = 0.05) -> DataFrame:
    """The bars of a rank diagram: (width_bits, first_rank, last_rank, methods) of maximal runs of methods within a critical difference.

    Each method opens a run of those behind it within the difference; runs of one method, and runs that end where an earlier one does, are no bars.
    """
    m = critical(ratios, alpha).select("width_bits", "method", "mean_rank", "cd")
    o = m.select("width_bits", F.col("method").alias("_m"), F.col("mean_rank").alias("_r"))
    runs = m.join(o, "width_bits").where("_r >= mean_rank and _r - mean_rank <= cd").groupBy("width_bits", "method", "mean_rank")
    runs = runs.agg(F.max("_r").alias("last_rank"), F.array_join(F.transform(F.array_sort(F.collect_set(F.struct("_r", "_m"))), lambda s: s["_m"]), ",").alias("methods"), F.count(F.lit(1)).alias("size"))
    out = runs.where("size > 1").groupBy("width_bits", "last_rank").agg(F.min("mean_rank").alias("first_rank"), F.min_by("methods", "mean_rank").alias("methods"))
    return out.select("width_bits", "first_rank", "last_rank", "methods")


def paired(sizes: DataFrame, a: str, b: str) -> DataFrame:
    """(dataset_id, width_bits, a, b): ratios of two methods side by side."""
    r = compression_ratio(sizes)
    return r.where(F.col("method") == a).select("dataset_id", "width_bits", F.col("ratio").alias("a")).join(r.where(F.col("method") == b).select("dataset_id", "width_bits", F.col("ratio").alias("b")), ["dataset_id", "width_bits"])


def win_count(pairs: DataFrame) -> DataFrame:
    return pairs.groupBy("width_bits").agg(*[F.sum(c.cast("bigint")).alias(k) for k, c in (("wins", F.col("a") > F.col("b")), ("ties", F.col("a") == F.col("b")), ("losses", F.col("a") < F.col("b")))], F.count(F.lit(1)).alias("n"))


def signed_ranks(pairs: DataFrame) -> DataFrame:
    """Rank sums of the differences a - b by width: zeros dropped, ties averaged, and the tie term of the variance."""
    d = pairs.withColumn("d", F.round(F.col("a") - F.col("b"), 12)).where("d <> 0").withColumn("m", F.abs("d"))
    ties = F.count(F.lit(1)).over(Window.partitionBy("width_bits", "m"))
    d = d.withColumn("r", F.rank().over(Window.partitionBy("width_bits").orderBy("m")) + (ties - 1) / 2).withColumn("c", ties)
    return d.groupBy("width_bits").agg(F.count(F.lit(1)).alias("n"), F.sum(F.when(F.col("d") > 0, F.col("r")).otherwise(0.0)).alias("plus"), F.sum(F.when(F.col("d") < 0, F.col("r")).otherwise(0.0)).alias("minus"), F.sum((F.col("c") * F.col("c") - 1) / 48.0).alias("tie_term"))


def exact_p(n: int, w: float) -> float:
    """Two-sided p of a signed-rank sum without ties, by counting subsets."""
    counts = [1] + [0] * (n * (n + 1) // 2)
    for r in range(1, n + 1):
        for s in range(len(counts) - 1, r - 1, -1):
            counts[s] += counts[s - r]
    return min(1.0, 2 * sum(counts[: int(math.floor(w)) + 1]) / 2**n)


def wilcoxon(pairs: DataFrame, exact_up_to: int = 25) -> DataFrame:
    """The signed-rank test by width; a handful of rows come to the driver, one for each width."""
    spark: SparkSession = pairs.sparkSession
    rows = []
    for r in signed_ranks(pairs).collect():
        n, w = r["n"], min(r["plus"], r["minus"])
        if n <= exact_up_to and not r["tie_term"]:
            p = exact_p(n, w)
        else:
            variance = n * (n + 1) * (2 * n + 1) / 24 - r["tie_term"]
            p = math.erfc(abs(w - n * (n + 1) / 4) / math.sqrt(variance) / math.sqrt(2)) if variance else 1.0
        rows.append((r["width_bits"], n, float(w), float(p)))
    return spark.createDataFrame(rows, "width_bits bigint, n bigint, w double, p double")


def noise_floor(residuals: DataFrame, width: int, keys: tuple[str, ...] = ("series_id",)) -> DataFrame:
    """Mean significant bits of zigzagged residuals: what no forecast takes away."""
    return residuals.groupBy(*keys).agg(F.avg(bit_width(zigzag(F.col("residual")))).alias("mean_bits"), F.count(F.lit(1)).alias("n")).withColumn("width_bits", F.lit(width).cast("bigint"))


def next_step_bayes_error(residuals: DataFrame, keys: tuple[str, ...] = ("series_id",)) -> DataFrame:
    """1 - sum over a of max over b of P(a, b), for neighbouring differences in {-1, 0, 1}."""
    pairs = neighbours(residuals, {"a": ("residual", 1)}, keys).where("a between -1 and 1 and residual between -1 and 1")
    counts = pairs.groupBy(*keys, "a", "residual").count()
    best = counts.groupBy(*keys, "a").agg(F.max("count").alias("best"), F.sum("count").alias("all"))
    return best.groupBy(*keys).agg(F.sum("all").alias("pairs"), (1 - F.sum("best") / F.sum("all")).alias("bayes_error"))


def byte_entropy(df: DataFrame, keys: tuple[str, ...], byte: str = "x") -> DataFrame:
    """Shannon entropy of bytes, in bits: the bound of any order-0 entropy stage."""
    counts = df.groupBy(*keys, byte).agg(F.count(F.lit(1)).alias("c"))
    total = F.sum("c").over(Window.partitionBy(*keys))
    return counts.withColumn("p", F.col("c") / total).groupBy(*keys).agg(F.sum("c").alias("bytes"), (-F.sum(F.col("p") * F.log2("p"))).alias("entropy_bits"))


def pareto(points: DataFrame) -> DataFrame:
    """``on_front``: no other method of the dataset is at least as good in both and better in one of ratio and speed."""
    o = points.select("dataset_id", "width_bits", F.col("method").alias("_m"), F.col("ratio").alias("_r"), F.col("speed").alias("_s"))
    beaten = points.join(o, (points["dataset_id"] == o["dataset_id"]) & (points["width_bits"] == o["width_bits"]) & (F.col("_r") >= F.col("ratio")) & (F.col("_s") >= F.col("speed")) & ((F.col("_r") > F.col("ratio")) | (F.col("_s") > F.col("speed"))), "left_semi").select("dataset_id", "width_bits", "method", F.lit(False).alias("on_front"))
    return points.join(beaten, ["dataset_id", "width_bits", "method"], "left").withColumn("on_front", F.coalesce("on_front", F.lit(True)))


def timing_spread(timing: DataFrame) -> DataFrame:
    """(method, direction) -> best and mean rate in MB/s, and the best over the mean."""
    rate = F.col("bytes") * 1000.0 / F.col("ns")
    out = timing.groupBy("method", "direction", "dims", "width_bits").agg(F.max(rate).alias("best_mb_s"), F.avg(rate).alias("mean_mb_s"), F.count(F.lit(1)).alias("reps"))
    return out.withColumn("best_over_mean", F.col("best_mb_s") / F.col("mean_mb_s"))
