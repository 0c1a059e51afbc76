"""Series as delimited text and as dumps of little-endian numbers, the forms in which benchmark series are passed on."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.bits import divided

#: Samples of one dump: a file holds one, so no task holds a series.
DUMP = 1 << 16


def write_delimited(series: DataFrame, path: str, separator: str = ";") -> None:
    """(series_id, t, x) as lines of text with a head."""
    series.select("series_id", "t", "x").write.option("header", True).option("sep", separator).csv(path)


def read_delimited(spark: SparkSession, path: str, separator: str = ";") -> DataFrame:
    """(series_id, t, x); a line that does not fit its types is refused."""
    return spark.read.schema("series_id string, t bigint, x bigint").option("header", True).option("sep", separator).option("mode", "FAILFAST").csv(path)


def write_dumps(series: DataFrame, path: str, width: int) -> None:
    """Numbers of ``width`` bits, ``DUMP`` samples a row, in Parquet beside the series' name and first position; positions are dense."""

    def pack(key: tuple, frame: pd.DataFrame) -> pd.DataFrame:
        values = frame.sort_values("t")
        return pd.DataFrame([(key[0], int(values.t.iloc[0]), values.x.to_numpy().astype(f"<u{width // 8}").tobytes())], columns=["series_id", "start", "content"])

    cut = series.select("series_id", "t", "x", divided(F.col("t"), DUMP).alias("dump"))
    cut.groupBy("series_id", "dump").applyInPandas(pack, "series_id string, start bigint, content binary").write.parquet(path)


def unpacked(dumps: DataFrame, width: int) -> DataFrame:
    """(series_id, t, x) of rows (series_id, start, content); a dump whose bytes are no whole number of samples is refused."""

    def unpack(frames):
        for frame in frames:
            for r in frame.itertuples(index=False):
                x = np.frombuffer(r.content, f"<u{width // 8}").astype(np.int64)
                yield pd.DataFrame({"series_id": r.series_id, "t": np.arange(len(x)) + r.start, "x": x})

    return dumps.select("series_id", "start", "content").mapInPandas(unpack, "series_id string, t bigint, x bigint")


def read_dumps(spark: SparkSession, path: str, width: int) -> DataFrame:
    return unpacked(spark.read.schema("series_id string, start bigint, content binary").parquet(path), width)


def read_raw_files(spark: SparkSession, path: str, width: int) -> DataFrame:
    """(series_id, t, x) of files that hold numbers and nothing else, each a series named like its file."""
    found = spark.read.format("binaryFile").load(path)
    name = F.element_at(F.split("path", "/"), -1)
    return unpacked(found.select(name.alias("series_id"), F.lit(0).cast("bigint").alias("start"), "content"), width)
