"""Experiments on wide, byte and float data: where the codec wins and loses, what low widths cost, how fast kernels are."""

from __future__ import annotations

import time
from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import bits as B
from ..operators import baselines, blocks, codec, forecast, huffman
from ..operators import kernels as K
from ..operators import measures as M
from ..operators import quantize as Q
from ..operators.options import Options, preset
from ..operators.relayout import wide
from ..sources import builders as S
from ..sources.shared import fresh
from ..sources.tables import load
from .queries import RANKED, all_bits, at_both, both, floats, fresh_table, grid_of, lanes_of, query, r6, series, sized, stored_vectors, summed, values

WIDE_SETS = ("wide80", "wide31", "wide18", "stair80", "state3", "state2")
PRESETS = ("speed", "balanced", "ratio", "speed_huffman")


def best_of(reps: int, *steps: Callable) -> list[list[float]]:
    """Seconds of each step in ``reps`` rounds; a step is given what the one before returned."""
    rounds = []
    for _ in range(reps):
        made, row = None, []
        for step in steps:
            began = time.perf_counter()
            made = step(made)
            row.append(time.perf_counter() - began)
        rounds.append(row)
    return [list(column) for column in zip(*rounds, strict=True)]


def wide_both(spark: SparkSession, d: str, names: tuple[str, ...], make: Callable) -> DataFrame:
    """``make(wide datasets at w bits, w)`` for 8 and 16 bits, over columns that are built once."""
    columns = S.wide_columns(spark, d, names)
    return both(lambda w: make(fresh_table(spark, S.at_width(columns, w), "wide"), w))


def _compare(width: int):
    """For a kernel: sizes and rates of presets and general codecs on one segment of a wide dataset."""
    names = ("speed", "balanced", "ratio")

    def run(key: tuple, frame: pd.DataFrame) -> pd.DataFrame:
        x, out = np.stack(frame.sort_values("t").x.to_numpy()).astype(np.int64), []
        raw = np.ascontiguousarray(x.T).astype(f"<u{width // 8}").tobytes()

        def row(name, packed, seconds):
            out.append((key[0], name, width, len(raw), packed, *(int(min(s) * 1e9) for s in seconds)))

        for name in names:
            o = preset(name, width)
            body, slots = codec.pack_many([x], o)[0]
            row(name, len(body), best_of(3, lambda _: codec.pack_many([x], o), lambda _: codec.unpack_many([(body, slots, len(x), x.shape[1])], o)))
        for name in baselines.GENERAL:
            packed = baselines.general_encode(name, raw)
            row(name, len(packed), best_of(3, lambda _: baselines.general_encode(name, raw), lambda _: baselines.general_decode(name, packed, len(raw))))
        return pd.DataFrame(out, columns=["dataset_id", "method", "width_bits", "raw_bytes", "enc_bytes", "encode_ns", "decode_ns"])

    return run


@query
def q48_pareto_wide(spark, d):
    """Where it wins and where it loses: ratio against decoding rate at both widths, and who is on the front."""
    ddl = "dataset_id string, method string, width_bits bigint, raw_bytes bigint, enc_bytes bigint, encode_ns bigint, decode_ns bigint"

    def make(x, w):
        cut = x.withColumn("segment", B.divided(F.col("t"), 1 << 14))
        return summed(cut.groupBy("series_id", "segment").applyInPandas(_compare(w), ddl), "raw_bytes", "enc_bytes", "encode_ns", "decode_ns")

    rate = lambda c: F.col("raw_bytes") * 1000.0 / F.col(c)
    points = fresh_table(spark, wide_both(spark, d, WIDE_SETS, make), "pareto").withColumns({"ratio": F.col("raw_bytes") / F.col("enc_bytes"), "encode_mb_s": rate("encode_ns"), "speed": rate("decode_ns")})
    return M.pareto(points.drop("encode_ns", "decode_ns"))


def lossless(x: DataFrame, width: int) -> DataFrame:
    """(preset, samples, mismatches, raw_bytes) of all rows after encoding and decoding with every preset."""
    out = None
    for p in PRESETS:
        segments = fresh_table(x.sparkSession, codec.encode(x, p, width), "lossless")
        a = x.select(F.col("series_id"), "t", F.col("x").cast("array<bigint>").alias("x"))
        pairs = a.join(codec.decode(segments).withColumnRenamed("x", "decoded"), ["series_id", "t"], "full_outer")
        wrong = (~F.col("x").eqNullSafe(F.col("decoded"))).cast("bigint")
        rows = pairs.groupBy("series_id").agg(F.count(F.lit(1)).alias("samples"), F.sum(wrong).alias("mismatches"))
        raw = segments.groupBy("series_id").agg(F.sum("raw_bytes").alias("raw_bytes"))
        part = rows.join(raw, "series_id").select(F.col("series_id").alias("dataset_id"), F.lit(p).alias("preset"), F.lit(width).cast("bigint").alias("width_bits"), "samples", "mismatches", "raw_bytes")
        out = part if out is None else out.unionByName(part)
    return out


@query
def q73_lossless_univariate(spark, d):
    """Every univariate dataset, preset and width decodes to what was encoded."""
    return at_both(spark, d, RANKED, lambda q, w: lossless(wide(q), w))


@query
def q73_lossless_wide(spark, d):
    return wide_both(spark, d, tuple(S.WIDE), lossless)


@query
def q74_wide_sizes(spark, d):
    """Bytes of the presets without an entropy stage on wide datasets, in segments of the usual length."""

    def make(x, w):
        parts = [codec.encode(x, p, w).groupBy("series_id").agg(F.sum("raw_bytes").alias("raw_bytes"), F.sum("body_bytes").alias("body_bytes")).select("series_id", F.lit(p).alias("preset"), F.lit(w).cast("bigint").alias("width_bits"), "raw_bytes", "body_bytes") for p in ("speed", "balanced")]
        return parts[0].unionByName(parts[1])

    return wide_both(spark, d, ("wide18", "state3", "state2", "wide80", "stair80"), make)


@query
def q75_byte_series(spark, d):
    """Texts as series of bytes, which repeat themselves: the negative control where dictionary codecs win."""

    def run(key: tuple, frame: pd.DataFrame) -> pd.DataFrame:
        raw = b"".join(frame.sort_values("k").b)
        x = np.frombuffer(raw, np.uint8).astype(np.int64).reshape(-1, 1)
        bodies = {n: codec.pack_many([x], preset(n, 8))[0][0] for n in ("speed", "balanced")}
        bodies["ratio"] = huffman.encode(bodies["balanced"])  # the same body with the entropy stage after it
        made = [(n, len(body)) for n, body in bodies.items()]
        made += [(n, len(baselines.general_encode(n, raw))) for n in baselines.GENERAL]
        return pd.DataFrame([(key[0], n, len(raw), size) for n, size in made], columns=["series_id", "method", "raw_bytes", "enc_bytes"])

    parts = S.texts(spark, d).groupBy("series_id", "segment_id").applyInPandas(run, "series_id string, method string, raw_bytes bigint, enc_bytes bigint")
    return summed(parts, "raw_bytes", "enc_bytes")


@query
def q75_byte_series_speed(spark, d):
    """The same for lag-1 packing alone, in generated code."""
    x = S.text_bytes(spark, d)
    sizes = blocks.body_sizes(forecast.lag1(x, 8, ("series_id", "segment_id")), Options(width_bits=8), ("series_id", "segment_id"))
    return sizes.groupBy("series_id").agg(F.sum("n").cast("bigint").alias("raw_bytes"), F.sum("body_bytes").cast("bigint").alias("enc_bytes"))


@query
def q76_gain_by_stratum(spark, d):
    """Why 16 bits gain more from learning: gain over lag-1 of datasets that lag-1 shrinks fourfold, and of the rest."""
    pairs = M.paired(sized(spark, d), "balanced", "lag1")
    stratum = F.when(F.col("b") >= 4, "4 or more").otherwise("below 4")
    out = pairs.groupBy(stratum.alias("stratum"), "width_bits").agg(F.count(F.lit(1)).alias("n"), F.sum((F.col("a") > F.col("b")).cast("bigint")).alias("wins"), F.avg(F.col("a") / F.col("b")).alias("mean_gain"))
    return out.select("stratum", "width_bits", "n", "wins", *r6("mean_gain"))


@query
def q77_nmse_corpus(spark, d):
    """Quantization error over variance of every univariate dataset, and whether it is below one percent."""
    v = values(spark, d, RANKED).select("series_id", F.col("v").cast("double").alias("v"))
    made = both(lambda w: Q.nmse(v, ["series_id"], w).select("series_id", "nmse", F.lit(w).cast("bigint").alias("width_bits")))
    return made.select("series_id", "width_bits", *r6("nmse"), (F.col("nmse") < 0.01).alias("below_one_percent"))


LABEL_BITS = (1, 2, 4, 6, 8)


@query
def q78_label_accuracy(spark, d):
    """Vectors told by the nearest centroid of their labels, before quantization and after it to few bits."""
    exact = load(spark, d, "embeddings").select("vec_id", F.col("label").cast("bigint").alias("label"), F.posexplode(F.transform("embedding", lambda x: F.round(x.cast("double") * 1000000).cast("bigint"))).alias("i", "v"))
    exact = fresh_table(spark, exact, "vectors")
    parts = [accuracy(exact).withColumn("bits", F.lit(0).cast("bigint"))]
    span = exact.agg(F.min("v").alias("lo"), F.max("v").alias("hi"))
    for b in LABEL_BITS:
        x = B.divided((F.col("v") - F.col("lo")) * ((1 << b) - 1), F.greatest(F.col("hi") - F.col("lo"), F.lit(1)))
        parts.append(accuracy(exact.crossJoin(F.broadcast(span)).select("vec_id", "label", "i", (x * 1000).alias("v"))).withColumn("bits", F.lit(b).cast("bigint")))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def accuracy(points: DataFrame) -> DataFrame:
    """(vectors, right) of points (vec_id, label, i, v): the least squared distance to a label's mean, in whole numbers; ties go to the lesser label.

    Centroids are one row for each label, a table of at most labels times dimensions, which is broadcast.
    """
    centroid = points.groupBy("label", "i").agg(B.divided(F.sum("v"), F.count(F.lit(1))).alias("c"))
    by_label = centroid.groupBy(F.col("label").alias("guess")).agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "c"))), lambda s: s["c"]).alias("c"))
    vectors = points.groupBy("vec_id", "label").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "v"))), lambda s: s["v"]).alias("x"))
    all_labels = by_label.agg(F.collect_list(F.struct("guess", "c")).alias("labels"))
    distance = lambda g: F.aggregate(F.zip_with("x", g["c"], lambda a, b: (a - b) * (a - b)), F.lit(0).cast("bigint"), lambda s, y: s + y)
    told = vectors.crossJoin(F.broadcast(all_labels)).select("label", F.array_min(F.transform("labels", lambda g: F.struct(distance(g).alias("d"), g["guess"].alias("guess"))))["guess"].alias("guess"))
    return told.agg(F.count(F.lit(1)).alias("vectors"), F.sum((F.col("label") == F.col("guess")).cast("bigint")).alias("right"))


@query
def q79_layouts_by_columns(spark, d):
    """Payload bytes of both layouts forced on 1 to 64 columns of eight bits."""
    long = S.wide64(spark, d, 8).select("t", F.posexplode("x").alias("col", "x")).select(F.col("col").cast("string").alias("series_id"), "t", "x")
    stored = blocks.whole_blocks(blocks.widths(forecast.lag1(long, 8), 8)).select("block_id", F.col("series_id").cast("int").alias("col"), "stored")
    counts = (1, 2, 4, 5, 8, 16, 31, 32, 64)
    per = stored.withColumn("dims", F.explode(F.array(*[F.lit(n).cast("bigint") for n in counts]))).where("col < dims").groupBy("dims", "block_id").agg(F.sum("stored").alias("w"))
    return per.groupBy("dims").agg(F.sum("w").cast("bigint").alias("column_bytes"), F.sum(F.ceil(F.col("w") / 8) * 8).cast("bigint").alias("row_bytes"))


@query
def q80_prestep_sizes(spark, d):
    """Integer codecs on samples as they are and on zigzagged lag-1 residuals."""

    def make(q, w):
        pre = forecast.lag1(q, w).select("series_id", "t", B.zigzag(F.col("residual")).alias("x"))
        parts = [baselines.bp128_sizes(x).select("series_id", F.lit(p).alias("pre_step"), F.lit(w).cast("bigint").alias("width_bits"), "enc_bytes") for p, x in (("none", q), ("lag1_zigzag", pre))]
        return parts[0].unionByName(parts[1])

    return at_both(spark, d, RANKED, make)


@query
def q81_two_coefficients(spark, d):
    """The two coefficients that predict best from the last two samples, free of each other."""
    return forecast.fit_two(values(spark, d, ["ev_value", "ev_walk", "ord_total"])).select("series_id", "n", *[F.round(c, 4).alias(c) for c in ("a", "b")])


@query
def q82_exact_scaling(spark, d):
    """Floats with a fixed number of decimals as whole numbers and back, without loss."""
    back = F.col("v") / 100
    scaled = Q.scale_exact(floats(spark, d).withColumn("original", F.col("v")), 2)
    return scaled.groupBy("name").agg(F.count(F.lit(1)).alias("n"), F.sum("v").cast("bigint").alias("total"), F.sum((back != F.col("original")).cast("bigint")).alias("changed"))


def _timed(rows: list[tuple]) -> pd.DataFrame:
    return pd.DataFrame(rows, columns=["method", "direction", "dims", "width_bits", "rep", "ns", "bytes"])


TIMING = "method string, direction string, dims bigint, width_bits bigint, rep bigint, ns bigint, bytes bigint"


@query
def q83_forecaster_speed(spark, d):
    """Rates of forecasters both ways on all bits of all embeddings, beside a copy of them: best and mean of ten, a group for each piece, width and number of columns."""

    def run(key: tuple, frame: pd.DataFrame) -> pd.DataFrame:
        w, n, rows = int(key[1]), int(key[2]), []
        samples = all_bits(frame, w)
        x = lanes_of(samples, n)
        options = {"lag1": Options(width_bits=w), "double_delta": Options(width_bits=w, forecaster="fixed", coef_num=1 << w), "adaptive": Options(width_bits=w, forecaster="adaptive")}
        steps = {k: (lambda _, o=o: K.residuals(x, o), lambda e, o=o: K.reconstruct(e, o)) for k, o in options.items()}
        steps["copy"] = (lambda _: x.copy(), lambda e: e.copy())
        for name, both_ways in steps.items():
            for direction, seconds in zip(("encode", "decode"), best_of(10, *both_ways), strict=True):
                rows += [(name, direction, n, w, i, int(s * 1e9), samples.size * w // 8) for i, s in enumerate(seconds)]
        return _timed(rows)

    keys = ("piece", "width_bits", "dims")
    tasks = int(spark.conf.get("spark.sql.shuffle.partitions"))  # a count that is named is kept: groups cost far more time than their bytes tell
    pieces = stored_vectors(spark, d, 1000).crossJoin(F.broadcast(grid_of(spark, (8, 16), (1, 8, 32, 80)))).repartition(tasks, *keys)
    each = pieces.groupBy(*keys).applyInPandas(run, TIMING)
    return M.timing_spread(summed(each, "ns", "bytes"))


@query
def q84_speed_by_data(spark, d):
    """Decoding rates on noise, on smooth samples and on long runs: speed should hardly depend on how well data packs."""

    def run(key: tuple, frame: pd.DataFrame) -> pd.DataFrame:
        x = frame.sort_values("t").x.to_numpy(np.int64)
        parts, rows = [x[i : i + 4096].reshape(-1, 1) for i in range(0, len(x), 4096)], []
        for name in ("speed", "balanced"):
            o = preset(name, 16)
            made = codec.pack_many(parts, o)
            bodies = [(*m, len(p), 1) for m, p in zip(made, parts, strict=True)]
            seconds = best_of(10, lambda _: codec.unpack_many(bodies, o))[0]
            rows += [(f"{key[0]}/{name}", "decode", 1, 16, i, int(s * 1e9), 2 * len(x)) for i, s in enumerate(seconds)]
        return _timed(rows)

    names = ["ev_value", "ev_ma64x2", "ev_total", "li_day"]
    cut = series(spark, d, names, 16).withColumn("segment", B.divided(F.col("t"), 1 << 18))
    return M.timing_spread(cut.groupBy("series_id", "segment").applyInPandas(run, TIMING))
