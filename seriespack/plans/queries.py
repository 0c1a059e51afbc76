"""The catalogue: each method, variant, baseline, measure and workload as a query over the given tables."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import bits as B
from ..functions import sql
from ..operators import analysis, baselines, blocks, codec, forecast, huffman, models
from ..operators import kernels as K
from ..operators import measures as M
from ..operators import quantize as Q
from ..operators.options import Options, preset
from ..operators.relayout import to_column_chunks, wide
from ..sources import builders as S
from ..sources.container import read_segments, write_segments
from ..sources.shared import fresh
from ..sources.tables import load
from ..streaming import encoder

UNIVARIATE = ["ev_value", "ev_total", "ev_walk", "ev_ma64", "ev_ma64x2", "ev_walk2", "ev_ts", "li_day", "li_qty", "ord_total", "ord_cum"]
RANKED = list(S.UNIVARIATE)
KERNEL = 1 << 20
QUERIES: dict = {}


def query(f):
    QUERIES[f.__name__] = f
    return f


def values(spark: SparkSession, d: str, names: list[str]) -> DataFrame:
    """Raw values of some series.  Several are built once into a table in the shared folder, so what follows plans over one scan."""
    made = S.corpus(spark, d, names)
    if len(names) < 4:
        return made
    path = fresh(spark, "values")
    made.write.parquet(path)
    return spark.read.schema(made.schema).parquet(path)


def fresh_table(spark: SparkSession, df: DataFrame, name: str) -> DataFrame:
    """``df`` written to the shared folder and read back."""
    path = fresh(spark, name)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def series(spark: SparkSession, d: str, names: list[str], width: int) -> DataFrame:
    return Q.quantize(values(spark, d, names), width).select("series_id", "t", "x")


def at_both(spark: SparkSession, d: str, names: list[str], make) -> DataFrame:
    """``make(series at w bits, w)`` for 8 and 16 bits, over one table of values."""
    raw = values(spark, d, names)
    return both(lambda w: make(Q.quantize(raw, w).select("series_id", "t", "x"), w))


def at_once(spark: SparkSession, d: str, names: list[str]) -> DataFrame:
    """(series_id, t, x8, x16): series at both widths, for methods that size both in one pass."""
    q = Q.quantize(values(spark, d, names), 8).withColumnRenamed("x", "x8")
    return q.select("series_id", "t", "x8", Q.rescaled(F.col("v"), F.col("lo"), F.col("hi"), (1 << 16) - 1).cast("bigint").alias("x16"))


def typed(spark: SparkSession, d: str, width: int = 16) -> DataFrame:
    return Q.quantize(S.ev_types(spark, d, False), width).select("series_id", "t", "x")


def r6(*columns: str):
    return [F.round(c, 6).alias(c) for c in columns]


def both(make, widths=(8, 16)) -> DataFrame:
    a, *rest = [make(w) for w in widths]
    for b in rest:
        a = a.unionByName(b)
    return a


def by_kernel(df: DataFrame, make, ddl: str, length: int = KERNEL) -> DataFrame:
    """``make(series_id, start, x as samples x 1)`` yields rows for each segment of at most ``length`` samples, which starts anew."""

    def run(key: tuple, frame: pd.DataFrame) -> pd.DataFrame:
        x = frame.sort_values("t").x.to_numpy(np.int64).reshape(-1, 1)
        return pd.DataFrame(list(make(key[0], int(key[1]) * length, x)), columns=[c.split()[0] for c in ddl.split(", ")])

    return df.withColumn("segment", B.divided(F.col("t"), length)).groupBy("series_id", "segment").applyInPandas(run, ddl)


def summed(parts: DataFrame, *sums: str) -> DataFrame:
    """Sizes of segments, added up by what names them."""
    return parts.groupBy(*[c for c in parts.columns if c not in sums]).agg(*[F.sum(c).cast("bigint").alias(c) for c in sums]).select(*parts.columns)


def cut(series_: DataFrame, length: int = codec.SEGMENT) -> DataFrame:
    """Series as segments that start anew: (series_id, segment_id, t within it, x)."""
    return series_.select("series_id", B.divided(F.col("t"), length).alias("segment_id"), (F.col("t") % length).alias("t"), "x")


SEGMENTED = ("series_id", "segment_id")


def body_bytes(spark, d, names: list[str], kind: str, w: int, q: DataFrame | None = None) -> DataFrame:
    """(series_id, body_bytes) of a preset in segments of the usual length."""
    q = series(spark, d, names, w) if q is None else q
    return codec.encode(wide(q), kind, w).groupBy("series_id").agg(F.sum("body_bytes").alias("body_bytes"))


@query
def q01_lag1_residuals(spark, d):
    return forecast.lag1(series(spark, d, ["ev_value"], 16), 16).select("t", "residual")


@query
def q02_double_delta(spark, d):
    return forecast.double_delta(series(spark, d, ["ev_ma64x2"], 16), 16).select("t", "residual")


@query
def q03_two_point_mean(spark, d):
    return forecast.two_point_mean(series(spark, d, ["ev_value"], 16), 16).select("t", "residual")


@query
def q04_fixed_alpha_grid(spark, d):
    q = series(spark, d, ["ev_value", "ev_walk", "ev_ma64x2"], 16)
    parts = [forecast.fixed(q, 16, n * 16384).withColumn("series_id", F.concat("series_id", F.lit(f":{n}"))) for n in range(-2, 5)]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out.groupBy("series_id").agg(F.sum(F.abs("residual")).alias("total"), F.count(F.when(F.col("residual") == 0, 1)).alias("zeros"))


@query
def q05_adaptive_sample_residuals(spark, d):
    out = forecast.adaptive(cut(typed(spark, d)), 16, SEGMENTED, update="sample")
    return out.select("series_id", (F.col("segment_id") * codec.SEGMENT + F.col("t")).alias("t"), "residual")


def _residual_rows(o: Options):
    def make(key, start, x):
        padded = np.concatenate([x, np.zeros((-len(x) % 8, 1), np.int64)])
        for t, e in enumerate(K.residuals(padded, o)[: len(x), 0].tolist(), start):
            yield key, t, e

    return make


@query
def q06_adaptive_block_residuals(spark, d):
    return by_kernel(typed(spark, d), _residual_rows(Options(width_bits=16, forecaster="adaptive")), "series_id string, t bigint, residual bigint", codec.SEGMENT)


@query
def q07_adaptive_final_alpha(spark, d):
    o = Options(width_bits=16, forecaster="adaptive")
    q = series(spark, d, ["ev_value", "ev_walk", "ev_ma64x2"], 16)
    out = by_kernel(q, lambda key, start, x: [(key, start, float(K.final_gain(x, o)[0]))], "series_id string, start bigint, coef double", codec.SEGMENT)
    return out.select("series_id", "start", F.round(F.col("coef") / 65536.0, 6).alias("alpha"))


@query
def q08_adaptive_native_vs_kernel(spark, d):
    q = typed(spark, d)
    native = forecast.adaptive(cut(q), 16, SEGMENTED).select("series_id", (F.col("segment_id") * codec.SEGMENT + F.col("t")).alias("t"), F.col("residual").alias("native"))
    kernel = by_kernel(q, _residual_rows(Options(width_bits=16, forecaster="adaptive")), "series_id string, t bigint, residual bigint", codec.SEGMENT)
    both_ = native.join(kernel, ["series_id", "t"], "full_outer")
    return both_.groupBy("series_id").agg(F.count(F.lit(1)).alias("n"), F.sum(F.abs("residual")).alias("total"), F.sum((~F.col("native").eqNullSafe(F.col("residual"))).cast("bigint")).alias("mismatches"))


@query
def q09_zigzag_roundtrip(spark, d):
    r = forecast.lag1(series(spark, d, ["ev_walk"], 16), 16).withColumn("z", B.zigzag(F.col("residual")))
    return r.select("t", "residual", "z", B.unzigzag(F.col("z")).alias("back"))


@query
def q10_block_widths(spark, d):
    return blocks.widths(forecast.lag1(series(spark, d, UNIVARIATE, 8), 8), 8).select("series_id", "block_id", "n", "bits", "stored")


@query
def q11_stored_width_rule(spark, d):
    """The stored width and its code of every width that hashed line prices have."""
    lines = load(spark, d, "lineitem").select((S.cents("l_extendedprice") * F.col("l_orderkey").cast("bigint")).alias("p"))
    bits = lambda w: lines.select(B.bit_width(F.pmod("p", F.lit(1 << w))).alias("bits")).groupBy("bits").agg(F.count(F.lit(1)).alias("n"))
    return both(lambda w: bits(w).select(F.lit(w).cast("bigint").alias("width_bits"), "bits", B.stored_width(F.col("bits"), w).alias("stored"), B.width_code(F.col("bits"), w).alias("code"), "n"), (8, 16, 32))


def _slots(spark, d, names, w):
    return blocks.runs(blocks.whole_blocks(blocks.widths(forecast.lag1(series(spark, d, names, w), w), w)))


@query
def q12_header_bytes_by_group(spark, d):
    n = _slots(spark, d, ["li_day"], 16).agg(F.count(F.lit(1)).alias("n"))
    g = F.col("group_size")
    pad = lambda k: F.ceil(k * 4 / 8)
    return n.crossJoin(spark.range(1, 9).withColumnRenamed("id", "group_size")).select("group_size", (B.divided(F.col("n"), g) * pad(g) + pad(F.col("n") % g)).cast("bigint").alias("header_bytes"))


def _quad_long(spark, d) -> DataFrame:
    return S.li_quad(spark, d).select(F.lit("li_quad").alias("dataset"), "t", F.posexplode("x").alias("col", "x")).select(F.concat(F.lit("c"), F.col("col").cast("string")).alias("series_id"), "t", "x")


@query
def q13_payload_layout_sizes(spark, d):
    stats = blocks.whole_blocks(blocks.widths(forecast.lag1(_quad_long(spark, d), 8), 8))
    per = stats.groupBy("block_id").agg(F.sum("stored").alias("w"))
    parts = [per.agg(F.sum(B.payload_bytes(F.col("w"), 4, 8, layout)).cast("bigint").alias("payload_bytes")).select(F.lit(layout).alias("layout"), "payload_bytes") for layout in ("column", "row")]
    return parts[0].unionByName(parts[1])


@query
def q14_column_major_packed_bytes(spark, d):
    o = Options(width_bits=8, group=1, rle=False)
    residuals = forecast.lag1(series(spark, d, ["ev_ma64x2"], 8), 8).select("series_id", "t", F.col("residual").alias("x"))

    def make(_, start, e):
        z = K.zigzag(e[: len(e) // 8 * 8]).reshape(-1, 8, 1)
        for b in range(len(z)):
            yield start // 8 + b, K.pack(z[b : b + 1], o)[0][1:].hex()

    return by_kernel(residuals, make, "block_id bigint, payload string")


@query
def q15_zero_runs(spark, d):
    return _slots(spark, d, ["li_day", "ev_total"], 16).select("series_id", "slot", "first_block", "n_blocks", "kind")


@query
def q16_encoded_size_speed(spark, d):
    return at_both(spark, d, UNIVARIATE, lambda q, w: body_bytes(spark, d, [], "speed", w, q).withColumn("width_bits", F.lit(w).cast("bigint")))


@query
def q17_encoded_size_balanced(spark, d):
    return body_bytes(spark, d, ["ev_value", "ev_walk", "ev_ma64x2", "ord_total"], "balanced", 16)


@query
def q18_encoded_size_ratio(spark, d):
    return at_both(spark, d, UNIVARIATE, lambda q, w: body_bytes(spark, d, [], "ratio", w, q).withColumn("width_bits", F.lit(w).cast("bigint")))


def _roundtrip(spark, d, name, width, kind, length=4096):
    return codec.decode(codec.encode(wide(series(spark, d, [name], width)), kind, width, segment_length=length)).select("t", F.col("x")[0].alias("x"))


@query
def q19_roundtrip_speed(spark, d):
    return _roundtrip(spark, d, "ev_walk", 16, "speed")


@query
def q20_roundtrip_balanced(spark, d):
    return _roundtrip(spark, d, "ev_ma64x2", 16, "balanced")


@query
def q21_roundtrip_ratio(spark, d):
    return _roundtrip(spark, d, "ev_total", 8, "ratio")


@query
def q22_roundtrip_speed_huffman(spark, d):
    return _roundtrip(spark, d, "li_day", 8, "speed_huffman")


@query
def q23_decode_range_pruned(spark, d):
    path = fresh(spark, "q23")
    write_segments(codec.encode(wide(series(spark, d, ["ev_ma64x2"], 16)), "ratio", 16, segment_length=1024), path)
    return analysis.materialize(read_segments(spark, path, "default"), 3000, 5500).select("t", F.col("x")[0].alias("x"))


@query
def q24_compressed_max(spark, d):
    return codec.run_aggregate(codec.encode(wide(series(spark, d, UNIVARIATE, 16)), "speed", 16, segment_length=8192)).select("series_id", F.col("max").alias("most"))


@query
def q25_compressed_min_count_sum(spark, d):
    path = fresh(spark, "q25")
    write_segments(codec.encode(wide(series(spark, d, UNIVARIATE, 8)), "balanced", 8, segment_length=8192), path)
    return codec.compressed_aggregate(read_segments(spark, path)).select("series_id", F.col("min").alias("least"), F.col("count").alias("n"), F.col("sum").alias("total"))


@query
def q26_downsample_hourly(spark, d):
    decoded = _roundtrip(spark, d, "ev_walk", 16, "balanced")
    clock = S._events(spark, d).select("t", F.date_trunc("hour", F.col("ts").cast("timestamp")).alias("hour"))
    out = analysis.downsample(decoded.join(clock, "t"), F.unix_seconds("hour"))
    return out.withColumnRenamed("bucket", "hour")


@query
def q27_pairwise_corr(spark, d):
    e = load(spark, d, "events").select("event_type", B.divided(F.unix_seconds(F.col("ts").cast("timestamp")), 86400).alias("b"), S.cents("value").alias("c"))
    daily = e.groupBy("event_type", "b").agg(F.sum("c").cast("double").alias("c"))
    return analysis.pairwise_corr(daily, "b", "event_type", "c").select("one", "other", *r6("corr"))


@query
def q28_asof_align(spark, d):
    e = load(spark, d, "events").select("event_id", "ts", "event_type", S.cents("value").alias("c"))
    left, right = e.where("event_type = 'purchase'").select("event_id", "ts"), e.where("event_type = 'view'")
    return analysis.asof(left, right, "ts", "c", F.to_date("ts")).select("event_id", "latest")


@query
def q29_quantize_8(spark, d):
    return series(spark, d, ["ev_value", "ev_walk", "ord_cum"], 8)


@query
def q30_quantize_16(spark, d):
    return series(spark, d, ["ev_value", "ev_walk", "ord_cum"], 16)


FLOATS = (("events", "value"), ("orders", "o_totalprice"), ("lineitem", "l_extendedprice"), ("part", "p_retailprice"), ("customer", "c_acctbal"), ("supplier", "s_acctbal"))


def floats(spark, d) -> DataFrame:
    parts = [load(spark, d, t).select(F.lit(f"{t}.{c}").alias("name"), F.col(c).alias("v")) for t, c in FLOATS]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


@query
def q31_dequantize_error(spark, d):
    return both(lambda w: Q.nmse(floats(spark, d), ["name"], w).select("name", *r6("nmse"), F.lit(w).cast("bigint").alias("width_bits")))


@query
def q32_concat_interpolated(spark, d):
    return S.emb_series(spark, d, False).select(F.col("series_id").alias("dataset_id"), "t", "v")


@query
def q33_column_chunks(spark, d):
    return to_column_chunks(S.li_quad(spark, d), 8, 4096).select("col", "chunk", "n", F.sha2(F.hex("raw"), 256).alias("digest"))


@query
def q34_bp128_size(spark, d):
    return baselines.bp128_sizes(series(spark, d, UNIVARIATE, 16))


@query
def q35_pfor_size(spark, d):
    return baselines.pfor_sizes(series(spark, d, ["ev_value", "ev_walk", "ev_total"], 16), most_bits=17)


@query
def q36_simple8b_roundtrip(spark, d):
    def make(_, start, x):
        yield from enumerate(baselines.simple8b_decode(baselines.simple8b_encode(x[:, 0]), len(x)).tolist(), start)

    return by_kernel(series(spark, d, ["ev_ma64"], 16), make, "t bigint, x bigint")


def all_methods(q: DataFrame, presets: tuple[str, ...], level: int = 9) -> DataFrame:
    """Sizes of every codec and of presets on each series of ``at_once``, in one pass over its samples; presets that differ in the entropy stage share a body."""

    def make(segments):
        for key, _, *columns in segments:
            for width, x in zip((8, 16), columns, strict=True):
                raw, bodies = x.astype(f"<u{width // 8}").tobytes(), {}
                for name, size in baselines.SIZES.items():
                    yield key, name, width, len(raw), size(x)
                for name in baselines.GENERAL:
                    yield key, name, width, len(raw), len(baselines.general_encode(name, raw, level))
                for name in presets:
                    o = preset(name, width)
                    if o.forecaster not in bodies:
                        bodies[o.forecaster] = codec.pack_many([x.reshape(-1, 1)], preset(name, width, entropy="none"))[0][0]
                    body = bodies[o.forecaster]
                    yield key, name, width, len(raw), huffman.encoded_size(body) if o.entropy == "huffman" else len(body)

    parts = codec.by_segments(q, ["x8", "x16"], make, "dataset_id string, method string, width_bits bigint, raw_bytes bigint, enc_bytes bigint", KERNEL)
    return summed(parts, "raw_bytes", "enc_bytes")


@query
def q37_all_codecs_size(spark, d):
    return all_methods(at_once(spark, d, RANKED), ("speed", "balanced", "ratio", "speed_huffman"))


@query
def q38_byte_entropy(spark, d):
    return M.byte_entropy(series(spark, d, UNIVARIATE, 8), ("series_id",)).select("series_id", "bytes", *r6("entropy_bits"))


def coefficients(w: int) -> dict[str, int]:
    """Fixed coefficients times 2^w of the forecasters without a state."""
    return {"lag1": 0, "double_delta": 1 << w, "two_point_mean": -(1 << (w - 1))}


def sized(spark, d) -> DataFrame:
    """Sizes of the methods that SQL can size too, on the whole univariate corpus, as a table in the shared folder."""
    methods = {f"x{w}": {m: Options(width_bits=w, forecaster="fixed", coef_num=c) for m, c in coefficients(w).items()} | {"balanced": preset("balanced", w), "bp128": None} for w in (8, 16)}
    made = fresh_table(spark, codec.method_sizes(at_once(spark, d, RANKED), methods), "sizes")
    width = F.when(F.col("column") == "x8", 8).otherwise(16).cast("bigint")
    made = made.select(F.col("series_id").alias("dataset_id"), "method", width.alias("width_bits"), (F.col("n_samples") * B.divided(width, 8)).alias("raw_bytes"), "enc_bytes")
    plain = made.where("method = 'balanced'").select("dataset_id", F.lit("raw").alias("method"), "width_bits", "raw_bytes", F.col("raw_bytes").alias("enc_bytes"))
    return made.unionByName(plain)


@query
def q39_ratio_table(spark, d):
    return M.compression_ratio(sized(spark, d)).select("dataset_id", "method", "width_bits", "raw_bytes", "enc_bytes", *r6("ratio"))


@query
def q40_ratio_boxplot(spark, d):
    return M.ratio_boxplot(M.compression_ratio(sized(spark, d))).select("method", "width_bits", "n", *r6("least", "q1", "median", "q3", "most"))


@query
def q41_mean_ranks(spark, d):
    return M.mean_ranks(M.compression_ratio(sized(spark, d))).select("method", "width_bits", *r6("mean_rank"), "n")


@query
def q42_friedman(spark, d):
    return M.friedman(M.compression_ratio(sized(spark, d))).select("width_bits", "k", "n", *r6("chi2"))


@query
def q42_nemenyi(spark, d):
    return M.nemenyi(M.compression_ratio(sized(spark, d))).select("width_bits", "method", "other", *r6("difference", "cd"), "differ")


@query
def q43_wins(spark, d):
    return M.win_count(M.paired(sized(spark, d), "double_delta", "lag1"))


@query
def q44_signed_ranks(spark, d):
    return M.signed_ranks(M.paired(sized(spark, d), "double_delta", "lag1")).select("width_bits", "n", "plus", "minus")


@query
def q43_wins_adaptive(spark, d):
    return M.win_count(M.paired(sized(spark, d), "balanced", "lag1"))


@query
def q44_signed_ranks_adaptive(spark, d):
    return M.signed_ranks(M.paired(sized(spark, d), "balanced", "lag1")).select("width_bits", "n", "plus", "minus")


@query
def q44_wilcoxon_adaptive(spark, d):
    return M.wilcoxon(M.paired(sized(spark, d), "balanced", "lag1"), exact_up_to=0).select("width_bits", "n", "w", *r6("p"))


@query
def q42_rank_groups(spark, d):
    return M.rank_groups(M.compression_ratio(sized(spark, d))).select("width_bits", *r6("first_rank", "last_rank"), "methods")


def compared(spark, d) -> DataFrame:
    """Sizes of the ten methods (three presets, seven codecs) on every univariate series, as a table in the shared folder."""
    return fresh_table(spark, all_methods(at_once(spark, d, RANKED), ("speed", "balanced", "ratio")), "compared")


@query
def q39_ratio_table_ten(spark, d):
    return M.compression_ratio(compared(spark, d)).select("dataset_id", "method", "width_bits", "raw_bytes", "enc_bytes", *r6("ratio"))


@query
def q40_ratio_boxplot_ten(spark, d):
    return M.ratio_boxplot(M.compression_ratio(compared(spark, d))).select("method", "width_bits", "n", *r6("least", "q1", "median", "q3", "most"))


@query
def q41_mean_ranks_ten(spark, d):
    return M.mean_ranks(M.compression_ratio(compared(spark, d))).select("method", "width_bits", *r6("mean_rank"), "n")


@query
def q42_friedman_ten(spark, d):
    return M.friedman(M.compression_ratio(compared(spark, d))).select("width_bits", "k", "n", *r6("chi2"))


@query
def q42_nemenyi_ten(spark, d):
    return M.nemenyi(M.compression_ratio(compared(spark, d))).select("width_bits", "method", "other", *r6("difference", "cd"), "differ")


@query
def q42_rank_groups_ten(spark, d):
    return M.rank_groups(M.compression_ratio(compared(spark, d))).select("width_bits", *r6("first_rank", "last_rank"), "methods")


@query
def q45_noise_floor(spark, d):
    return at_both(spark, d, UNIVARIATE, lambda q, w: M.noise_floor(forecast.lag1(q, w), w).select("series_id", *r6("mean_bits"), "n", "width_bits"))


@query
def q46_bayes_error(spark, d):
    return M.next_step_bayes_error(forecast.lag1(series(spark, d, UNIVARIATE, 8), 8)).select("series_id", "pairs", *r6("bayes_error"))


@query
def q47_size_breakdown(spark, d):
    parts = ("header_bytes", "payload_bytes", "run_bytes", "tail_bytes", "zero_blocks")
    sizes = at_both(spark, d, UNIVARIATE, lambda q, w: blocks.body_sizes(forecast.lag1(q, w), Options(width_bits=w)).withColumn("width_bits", F.lit(w).cast("bigint")))
    out = sizes.cube("series_id", "width_bits").agg(*[F.sum(c).cast("bigint").alias(c) for c in parts])
    return out.select(*[F.coalesce(F.col(c).cast("string"), F.lit("all")).alias(c) for c in ("series_id", "width_bits")], *parts)


@query
def q49_spike_example(spark, d):
    """Errors among events as isolated samples of -1: bits that they take raw and under two forecasters, and how many samples they touch."""
    x = S._events(spark, d).select(F.lit("x").alias("series_id"), "t", F.when(F.col("event_type") == "error", F.lit(255)).otherwise(F.lit(0)).cast("bigint").alias("x"))
    kinds = {"raw": x.withColumn("residual", B.wrap(F.col("x"), 8)), "lag1": forecast.lag1(x, 8), "double_delta": forecast.double_delta(x, 8)}
    parts = [df.agg(B.bit_width(F.bit_or(B.zigzag(F.col("residual")))).alias("bits"), F.count(F.when(F.col("residual") != 0, 1)).alias("touched")).select(F.lit(kind).alias("kind"), "bits", "touched") for kind, df in kinds.items()]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


@query
def q50_widths_worked_example(spark, d):
    """Bits, leading zeros and stored width of the low bytes of line prices."""
    z = load(spark, d, "lineitem").groupBy(F.pmod(S.cents("l_extendedprice"), F.lit(256)).alias("z")).agg(F.count(F.lit(1)).alias("n")).withColumn("bits", B.bit_width(F.col("z")))
    return z.select("z", "n", "bits", (8 - F.col("bits")).alias("leading_zeros"), B.stored_width(F.col("bits"), 8).alias("stored"))


@query
def q51_buffer_latency(spark, d):
    """How long a buffer takes to fill at the rate at which events of a type come."""
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    rates = load(spark, d, "events").groupBy("event_type").agg((F.count(F.lit(1)) * 1e6 / (F.max(us) - F.min(us))).alias("hertz"))
    parts = [rates.select("event_type", *[F.lit(v).cast("bigint").alias(c) for c, v in (("buffer_bytes", b), ("dims", n), ("width_bits", w))], *r6("hertz"), F.round(models.fill_seconds(b, n, w, F.col("hertz")), 3).alias("seconds")) for b, n, w in ((10000, 9, 8), (8, 1, 8))]
    return parts[0].unionByName(parts[1])


@query
def q52_memory_model(spark, d):
    """Bytes of an encoder with a column for each user of an hour, and how many hours need them."""
    hours = load(spark, d, "events").groupBy(B.divided(F.unix_seconds(F.col("ts").cast("timestamp")), 3600).alias("h")).agg(F.countDistinct("user_id").alias("dims"))
    memory = lambda w: F.col("dims") * models.encoder_memory_bytes(1, Options(width_bits=w, forecaster="adaptive"))
    return both(lambda w: hours.groupBy("dims").agg(F.count(F.lit(1)).alias("hours")).select("dims", "hours", F.lit(w).cast("bigint").alias("width_bits"), memory(w).alias("bytes")))


@query
def q53_power_bound(spark, d):
    """Power at best by what lag-1 packing shrinks series of events to, at 8 bits."""
    sizes = blocks.body_sizes(forecast.lag1(series(spark, d, ["ev_value", "ev_total", "ev_walk"], 8), 8), Options(width_bits=8))
    ratio = F.col("n") / F.col("body_bytes")
    return sizes.select("series_id", F.round(ratio, 6).alias("ratio"), F.round(models.power_milliwatts(ratio, 30.0, 50.0), 6).alias("milliwatts"))


@query
def q54_advisor(spark, d):
    return analysis.advise(series(spark, d, UNIVARIATE, 16)).select("series_id", "n", "levels", *r6("zero_share", "roughness"), "advice")


@query
def q55_segment_ablation(spark, d):
    q = series(spark, d, UNIVARIATE, 16)

    def make(n):
        cut = q.withColumn("segment_id", B.divided(F.col("t"), n)).withColumn("t", F.col("t") % n)
        sizes = blocks.body_sizes(forecast.lag1(cut, 16, ("series_id", "segment_id")), Options(width_bits=16), ("series_id", "segment_id"))
        return sizes.groupBy("series_id").agg(F.count(F.lit(1)).alias("segments"), F.sum("body_bytes").cast("bigint").alias("body_bytes")).withColumn("segment_length", F.lit(n).cast("bigint"))

    return both(make, (1024, 4096, 16384, 65536))


@query
def q56_block_size_ablation(spark, d):
    fours = fresh_table(spark, blocks.ors(forecast.lag1(series(spark, d, RANKED, 16), 16), block=4), "fours")  # longer blocks add up from these
    sizes = lambda n: blocks.sizes_of_stats(blocks.of_ors(blocks.coarser(fours, n // 4), 16), Options(width_bits=16, block=n))
    return both(lambda n: sizes(n).select("series_id", F.lit(n).cast("bigint").alias("block"), "body_bytes"), (4, 8, 16, 32, 64))


@query
def q57_lowbit_nmse(spark, d):
    return both(lambda k: Q.nmse(floats(spark, d), ["name"], 8, levels=(1 << k) - 1).select("name", *r6("nmse"), F.lit(k).cast("bigint").alias("bits")), (2, 4, 6))


def _stream(spark, d, transform, name: str) -> DataFrame:
    sink = fresh(spark, name)
    schema = load(spark, d, "events").schema
    prepared = lambda s: transform(s.select(F.col("event_type").alias("series_id"), F.col("ts").cast("timestamp").alias("ts"), F.col("event_id").alias("tie"), S.cents("value").alias("v")))
    encoder.replay(spark, f"{d}/events.parquet*", schema, prepared, sink, f"{sink}-state")
    return spark.read.parquet(sink)


@query
def q58_stream_encode_equals_batch(spark, d):
    o = encoder.CENTS
    out = encoder.as_segments(_stream(spark, d, lambda s: encoder.encode_stream(s, o, 256), "q58"), o)
    return codec.decode(out).select("series_id", "t", F.col("x")[0].alias("x"))


@query
def q59_stream_windows(spark, d):
    return _stream(spark, d, encoder.windowed, "q59")


@query
def q61_ar2_fit(spark, d):
    return forecast.fit_coefficients(S.corpus(spark, d, ["ev_value", "ev_walk", "ev_ma64x2"])).select("series_id", "n", *r6("alpha", "a", "b"))


@query
def q62_prefix_reconstruct(spark, d):
    q = series(spark, d, ["ev_walk", "ev_ma64x2"], 16)
    one = forecast.reconstruct(forecast.lag1(q, 16).drop("x"), 16).select("series_id", "t", F.col("restored").alias("lag1"))
    two = forecast.reconstruct(forecast.double_delta(q, 16).drop("x"), 16, 2).select("series_id", "t", F.col("restored").alias("double_delta"))
    return one.join(two, ["series_id", "t"])


def wide_roundtrip(spark, d, name: str, width: int = 16) -> DataFrame:
    """For a wide dataset and each preset: sizes and mismatches after decoding."""
    made, path = S.WIDE[name](spark, d, width), fresh(spark, name)
    made.write.parquet(path)
    x = spark.read.schema(made.schema).parquet(path)
    out = None
    for p in ("speed", "balanced", "ratio", "speed_huffman"):
        segments = codec.encode(x, p, width)
        sizes = segments.agg(F.sum("raw_bytes").alias("raw_bytes"), F.sum("body_bytes").alias("body_bytes"))
        row = codec.verify_roundtrip(x, segments).crossJoin(sizes).select(F.lit(name).alias("dataset_id"), F.lit(p).alias("preset"), "samples", "mismatches", "raw_bytes", "body_bytes", F.round(F.col("raw_bytes") / F.col("body_bytes"), 6).alias("ratio"))
        out = row if out is None else out.unionByName(row)
    return out


@query
def q63_wide80_roundtrip(spark, d):
    return wide_roundtrip(spark, d, "wide80")


@query
def q64_wide18_roundtrip(spark, d):
    return wide_roundtrip(spark, d, "wide18")


@query
def q65_udtf_decode(spark, d):
    sql.register(spark)
    path = fresh(spark, "q65")
    write_segments(codec.encode(wide(series(spark, d, ["ev_walk"], 16)), "balanced", 16, segment_length=1024), path)
    read_segments(spark, path).createOrReplaceTempView("q65_segments")
    return spark.sql("SELECT t, x[0] AS x FROM decode_segments(TABLE(q65_segments))")


@query
def q65_block_stats(spark, d):
    s = codec.block_stats(codec.encode(wide(series(spark, d, ["li_day", "ev_total"], 16)), "speed", 16))
    first = F.sum("n_blocks").over(Window.partitionBy("series_id", "segment_id").orderBy("slot").rowsBetween(Window.unboundedPreceding, -1))
    return s.select("series_id", "segment_id", "slot", F.coalesce(first, F.lit(0)).cast("bigint").alias("first_block"), "n_blocks", "kind")


@query
def q66_datasource_read(spark, d):
    from ..sources.datasource import EncodedSeries

    path = fresh(spark, "q66")
    write_segments(codec.encode(wide(series(spark, d, ["ev_walk"], 16)), "ratio", 16, segment_length=1024), path)
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(EncodedSeries)
    return spark.read.format("encoded_series").option("path", path).load().where("t >= 2000 and t < 4000").select("t", F.col("x")[0].alias("x"))


@query
def q67_huffman_kraft(spark, d):
    """Codes of three columns of lines: their Kraft sum, and whether they spend from the entropy to a bit more a symbol."""
    symbols = {"price": F.pmod(S.cents("l_extendedprice"), F.lit(256)), "quantity": F.col("l_quantity").cast("bigint"), "flag": F.ascii("l_returnflag").cast("bigint")}
    found = load(spark, d, "lineitem").select(F.explode(F.array(*[F.struct(F.lit(k).alias("kind"), v.alias("symbol")) for k, v in symbols.items()])).alias("s"))
    counts = found.groupBy("s.kind", "s.symbol").agg(F.count(F.lit(1)).alias("n"))

    def run(key: tuple, frame: pd.DataFrame) -> pd.DataFrame:
        n = frame.sort_values("symbol").n.to_numpy(np.int64)
        lengths = huffman.code_lengths(n)
        spent, least = float((n * lengths).sum()), float(-(n * np.log2(n / n.sum())).sum())
        return pd.DataFrame([(key[0], len(n), int(n.sum()), int((1 << (huffman.LIMIT - lengths)).sum()), bool(least - 1e-6 * n.sum() <= spent <= least + n.sum()))], columns=["kind", "symbols", "total", "kraft_2048", "within_a_bit"])

    return counts.groupBy("kind").applyInPandas(run, "kind string, symbols bigint, total bigint, kraft_2048 bigint, within_a_bit boolean")


@query
def q68_entropy_ablation(spark, d):
    """Bytes without an entropy stage, with one after packing, one before, and the order-0 bound after packing."""

    def make(segments):
        for key, _, x in segments:
            x, o = x.reshape(-1, 1), preset("balanced", 16)
            z = K.zigzag(K.residuals(x[: len(x) // o.block * o.block], o)).reshape(-1, o.block, 1)
            none = codec.pack_segment(x, z, o)[0]
            yield key, "none", len(none)
            yield key, "after", huffman.encoded_size(none)
            yield key, "before", huffman.encoded_size(codec.unpacked(x, z, o))
            p = np.bincount(np.frombuffer(none, np.uint8)) / max(len(none), 1)
            yield key, "bound", int(np.ceil(-(p[p > 0] * np.log2(p[p > 0])).sum() * len(none) / 8))

    return summed(codec.by_segments(series(spark, d, RANKED, 16), ["x"], make, "series_id string, stage string, bytes bigint", KERNEL), "bytes")


LEARNING = {
    "block, every other": {},
    "block, every sample": {"grad_stride": 1},
    "sample": {"update": "sample", "grad_stride": 1},
    "rate 1": {"rate_shift": 0},
    "rate 1/4": {"rate_shift": 2},
    "rate 1/16": {"rate_shift": 4},
    "clamped": {"clamp": True},
    "rounded product": {"round_product": True},
    "case rule": {"zero_rule": "case"},
    "floor mean": {"mean_rounding": "floor"},
}


@query
def q69_learning_ablation(spark, d):
    """Sizes of variants of learning, of segments that lie side by side."""

    def make(segments):
        for name, change in LEARNING.items():
            sizes = codec.size_many([x.reshape(-1, 1) for _, _, x in segments], preset("balanced", 16, **change))
            yield from ((key, name, n) for (key, _, _), n in zip(segments, sizes, strict=True))

    return summed(codec.by_segments(series(spark, d, RANKED, 16), ["x"], make, "series_id string, variant string, bytes bigint", codec.SEGMENT, KERNEL), "bytes")


@query
def q70_buffer_ablation(spark, d):
    """General codecs on buffers of 1, 10 and 64 KB and on all, and how long a buffer takes to fill at 20 Hz."""

    def make(key, _, x):
        raw = x.astype("<u2").tobytes()
        for size in (1000, 10_000, 64_000, 2 * KERNEL):
            for name in baselines.GENERAL:
                yield key, name, size, sum(len(baselines.general_encode(name, raw[i : i + size])) for i in range(0, len(raw), size))

    made = summed(by_kernel(series(spark, d, RANKED, 16), make, "series_id string, method string, buffer_bytes bigint, enc_bytes bigint"), "enc_bytes")
    return made.withColumn("fill_seconds", F.col("buffer_bytes") / (2 * 20.0))


@query
def q71_header_group_bytes(spark, d):
    q = series(spark, d, RANKED, 16)

    def make(key, _, x):
        for g in range(1, 9):
            yield key, g, len(codec.pack_many([x], preset("speed", 16, group=g))[0][0])

    return summed(by_kernel(q, make, "series_id string, group_size bigint, body_bytes bigint", codec.SEGMENT), "body_bytes")


def noise(spark, d, vectors: int) -> DataFrame:
    """(piece, vec_id, v): embeddings in millionths, whose low bits don't compress, in pieces of at most ``vectors`` ids."""
    e = load(spark, d, "embeddings").select(F.col("vec_id").cast("bigint").alias("vec_id"), F.transform("embedding", lambda x: F.round(x.cast("double") * 1000000).cast("bigint")).alias("v"))
    return e.withColumn("piece", B.divided(F.col("vec_id"), vectors))


def stored_vectors(spark, d, ids: int) -> DataFrame:
    """(piece, vec_id, v): embeddings as they are stored, in pieces of at most ``ids`` ids; a null or an empty one has no values."""
    e = load(spark, d, "embeddings").select(F.col("vec_id").cast("bigint").alias("vec_id"), F.col("embedding").alias("v"))
    return e.where("size(v) > 0").withColumn("piece", B.divided(F.col("vec_id"), ids))


def all_bits(frame: pd.DataFrame, width: int) -> np.ndarray:
    """All bits of a piece's floats as samples of ``width`` bits: the lowest digit of every float, then the next, up to the one with the sign."""
    flat = np.concatenate(frame.sort_values("vec_id").v.to_numpy())
    return flat.view(f"u{width // 8}").reshape(len(flat), 8 * flat.itemsize // width).T.ravel().astype(np.int64)


def low_bits(frame: pd.DataFrame, width: int) -> np.ndarray:
    """The low ``width`` bits of a piece's whole numbers, which don't compress."""
    return np.concatenate(frame.sort_values("vec_id").v.to_numpy()).astype(np.int64) & ((1 << width) - 1)


def lanes_of(samples: np.ndarray, lanes: int) -> np.ndarray:
    """All samples as whole blocks of rows of ``lanes`` columns; zeros fill the last one."""
    return np.pad(samples, (0, -len(samples) % (8 * lanes))).reshape(-1, lanes)


def grid_of(spark, widths: tuple[int, ...], dims: tuple[int, ...]) -> DataFrame:
    return spark.createDataFrame([(w, n) for w in widths for n in dims], "width_bits bigint, dims bigint")


@query
def q72_speed_by_columns(spark, d):
    """Rates of kernels on incompressible samples, all embeddings, a group for each piece, width and number of columns (best of three)."""
    spent = ("encode_s", "decode_s", "forecast_s", "reconstruct_s")

    def run(key: tuple, frame: pd.DataFrame) -> pd.DataFrame:
        import time

        w, n, rows = int(key[1]), int(key[2]), []
        x = lanes_of(low_bits(frame, w), n)
        for name in ("speed", "balanced", "ratio"):
            o, best = preset(name, w), [1e9] * 4
            for _ in range(3):
                t = [time.perf_counter()]
                made = codec.pack_many([x], o)
                t.append(time.perf_counter())
                codec.unpack_many([(*made[0], len(x), n)], o)
                t.append(time.perf_counter())
                e = K.residuals(x, o)
                t.append(time.perf_counter())
                K.reconstruct(e, o)
                t.append(time.perf_counter())
                best = [min(b, float(c)) for b, c in zip(best, np.diff(t), strict=True)]
            rows.append((name, w, n, *best, x.size * w // 8, len(made[0][0])))
        return pd.DataFrame(rows, columns=["method", "width_bits", "dims", *spent, "raw", "packed"])

    ddl = f"method string, width_bits bigint, dims bigint, {', '.join(f'{c} double' for c in spent)}, raw bigint, packed bigint"
    each = noise(spark, d, 2500).crossJoin(F.broadcast(grid_of(spark, (8, 16), (1, 2, 4, 5, 8, 16, 31, 80)))).groupBy("piece", "width_bits", "dims").applyInPandas(run, ddl)
    rates = [(F.sum("raw") / F.sum(c) / 1e6).alias(c.removesuffix("_s") + "_mb_s") for c in spent]
    return each.groupBy("method", "width_bits", "dims").agg(*rates, (F.sum("raw") / F.sum("packed")).alias("ratio"))


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The flagship: the wide dataset and a running total, encoded for ratio, decoded, compared."""
    return wide_roundtrip(spark, sf_dir, "wide18")
