"""The SQL surface: scalar functions and table functions, registered by name."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.functions import arrow_udtf

from ..operators import codec
from ..operators.options import Options

SCALARS = {
    "zigzag(e BIGINT) RETURNS BIGINT": "CASE WHEN e >= 0 THEN 2 * e ELSE -2 * e - 1 END",
    "unzigzag(z BIGINT) RETURNS BIGINT": "CASE WHEN z % 2 = 0 THEN shiftright(z, 1) ELSE -shiftright(z, 1) - 1 END",
    "bit_width(o BIGINT) RETURNS BIGINT": "CASE WHEN o = 0 THEN 0 ELSE length(bin(o)) END",
    "packed_size(stored BIGINT, dims INT, width INT) RETURNS BIGINT": "CASE WHEN dims * width <= 32 THEN stored ELSE 8 * ceil(stored / 8) END",
}


def register(spark: SparkSession) -> None:
    """``zigzag``, ``unzigzag``, ``bit_width``, ``packed_size`` (payload bytes of a block of 8 whose columns' widths sum to ``stored``);
    ``decode_segments(TABLE(...))`` and ``block_stats(TABLE(...))``, which work on Arrow batches of segment rows."""
    for signature, body in SCALARS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {signature} RETURN {body}")
    spark.udtf.register("decode_segments", arrow_udtf(DecodeSegments, returnType="series_id string, t bigint, x array<bigint>"))
    spark.udtf.register("block_stats", arrow_udtf(BlockStats, returnType="series_id string, segment_id bigint, slot bigint, kind string, n_blocks bigint, widths array<bigint>, payload_bytes bigint"))


class DecodeSegments:
    """Samples of segment rows."""

    def eval(self, batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        for row in batch.to_pylist():
            codec.check(row)
            x = codec.unpack_many([(row["body"], row["n_slots"], row["n_samples"], row["dims"])], Options(**row["options"]))[0]
            if len(x):
                yield codec.sample_batch(row, x)


class BlockStats:
    """Slots of segment rows, from their headers."""

    def eval(self, batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        for row in batch.to_pylist():
            yield codec.slot_batch(row)
