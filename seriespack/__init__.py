"""seriespack: lossless time-series compression and analytics on Spark DataFrames.

Executors need no installed copy: functions of this package travel by value with each task.
"""

import importlib
import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])

#: What the package offers, and where it is.
API = {
    "Options": "operators.options:Options",
    "preset": "operators.options:preset",
    "encode_series": "operators.codec:encode",
    "decode_series": "operators.codec:decode",
    "assign_segments": "operators.codec:segmented",
    "block_stats": "operators.codec:block_stats",
    "compressed_aggregate": "operators.codec:compressed_aggregate",
    "run_aggregate": "operators.codec:run_aggregate",
    "verify_roundtrip": "operators.codec:verify_roundtrip",
    "forecast_lag1": "operators.forecast:lag1",
    "forecast_fixed": "operators.forecast:fixed",
    "forecast_double_delta": "operators.forecast:double_delta",
    "forecast_adaptive": "operators.forecast:adaptive",
    "reconstruct": "operators.forecast:reconstruct",
    "fit_alpha": "operators.forecast:fit_coefficients",
    "fit_two": "operators.forecast:fit_two",
    "quantize": "operators.quantize:quantize",
    "dequantize": "operators.quantize:dequantize",
    "scale_exact": "operators.quantize:scale_exact",
    "quantization_nmse": "operators.quantize:nmse",
    "concat_series": "operators.relayout:concat_series",
    "to_column_chunks": "operators.relayout:to_column_chunks",
    "null_policy": "operators.relayout:null_policy",
    "wide": "operators.relayout:wide",
    "positions": "operators.ordering:positions",
    "materialize": "operators.analysis:materialize",
    "downsample": "operators.analysis:downsample",
    "pairwise_corr": "operators.analysis:pairwise_corr",
    "asof_align": "operators.analysis:asof",
    "advise": "operators.analysis:advise",
    "every_nth_run": "operators.analysis:every_nth_run",
    "top": "operators.analysis:top",
    "compression_ratio": "operators.measures:compression_ratio",
    "ratio_boxplot": "operators.measures:ratio_boxplot",
    "mean_ranks": "operators.measures:mean_ranks",
    "friedman": "operators.measures:friedman",
    "nemenyi": "operators.measures:nemenyi",
    "rank_groups": "operators.measures:rank_groups",
    "wilcoxon": "operators.measures:wilcoxon",
    "win_count": "operators.measures:win_count",
    "noise_floor": "operators.measures:noise_floor",
    "next_step_bayes_error": "operators.measures:next_step_bayes_error",
    "pareto": "operators.measures:pareto",
    "timing_spread": "operators.measures:timing_spread",
    "size_breakdown": "operators.blocks:body_sizes",
    "write_segments": "sources.container:write_segments",
    "read_segments": "sources.container:read_segments",
    "compact_segments": "sources.container:compact",
    "EncodedSeries": "sources.datasource:EncodedSeries",
    "stream_encode": "streaming.encoder:encode_stream",
    "stream_windows": "streaming.encoder:windowed",
    "stream_sessions": "streaming.encoder:sessions",
    "register_sql": "functions.sql:register",
}
__all__ = list(API)


def __getattr__(name: str):
    if name not in API:
        raise AttributeError(f"module {__name__!r} has no attribute {name!r}")
    module, _, attribute = API[name].partition(":")
    return getattr(importlib.import_module(f"{__name__}.{module}"), attribute)
