"""``encoded_series``: a folder of segments as a Spark data source, to read, write and read as a stream.

Reading takes over filters on ``series_id`` and ``t``: row groups whose statistics rule them out are not read, and of the
others only the columns that decoding needs.  Writing encodes the rows of each task as they come, so rows of a segment
should lie together (``arranged``); a file shows up under its name only when its task is done, and an aborted write is
taken back.  As a stream, files come in the order in which they were written.
Options: ``path``, a folder that the executors reach through Arrow's file systems; ``preset``, ``width_bits`` and
``segment_length`` for writing.
"""

from __future__ import annotations

import uuid
from dataclasses import dataclass

import pyarrow as pa
import pyarrow.compute as pc
import pyarrow.parquet as pq
from pyarrow import fs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.datasource import (
    DataSource,
    DataSourceArrowWriter,
    DataSourceReader,
    DataSourceStreamReader,
    EqualTo,
    GreaterThan,
    GreaterThanOrEqual,
    InputPartition,
    LessThan,
    LessThanOrEqual,
    WriterCommitMessage,
)

from ..operators import codec
from ..operators.options import Options, preset

NEEDED = ["series_id", "segment_id", "t_start", "n_samples", "dims", "n_slots", "crc", "format_version", "options", "body"]


def arranged(series: DataFrame, length: int) -> DataFrame:
    """(series_id, t, x) with the rows of each segment together and in order, as the writer wants them."""
    segment = F.call_function("div", F.col("t"), F.lit(length).cast("bigint"))
    return series.select("series_id", "t", "x").repartition("series_id", segment).sortWithinPartitions("series_id", "t")


class EncodedSeries(DataSource):
    @classmethod
    def name(cls):
        return "encoded_series"

    def schema(self):
        return "series_id string, t bigint, x array<bigint>"

    def reader(self, schema):
        return EncodedReader(self.options["path"])

    def writer(self, schema, overwrite):
        if overwrite:
            raise ValueError("encoded_series appends; write to a new folder instead")
        return EncodedWriter(self.options["path"], self.options.get("preset", "balanced"), int(self.options.get("width_bits", 16)), int(self.options.get("segment_length", 8192)))

    def streamReader(self, schema):
        return EncodedStream(self.options["path"])


def files_of(uri: str) -> list[tuple[int, str]]:
    """(time of writing in ns, path) of the files in a folder, oldest first."""
    system, path = fs.FileSystem.from_uri(uri)
    found = system.get_file_info(fs.FileSelector(path, recursive=True, allow_not_found=True))
    return sorted((f.mtime_ns, f.path) for f in found if f.path.endswith(".parquet"))


class Decoder:
    """Reads segment files; what ``series``, ``low`` and ``high`` rule out by row-group statistics is not read."""

    def __init__(self, uri: str, series: str | None = None, low: int | None = None, high: int | None = None):
        self.uri, self.series, self.low, self.high = uri, series, low, high

    def wanted(self, group) -> bool:
        stats = {group.column(i).path_in_schema: group.column(i).statistics for i in range(group.num_columns)}
        stats = {k: v for k, v in stats.items() if v is not None and v.has_min_max}
        name, start, n = stats.get("series_id"), stats.get("t_start"), stats.get("n_samples")
        if self.series is not None and name and not name.min <= self.series <= name.max:
            return False
        if self.high is not None and start and start.min > self.high:
            return False
        return not (self.low is not None and start and n and start.max + n.max <= self.low)

    def read(self, path: str):
        system, _ = fs.FileSystem.from_uri(self.uri)
        with system.open_input_file(path) as stream:
            file = pq.ParquetFile(stream)
            for g in range(file.num_row_groups):
                if not self.wanted(file.metadata.row_group(g)):
                    continue
                for batch in file.iter_batches(256, row_groups=[g], columns=NEEDED):
                    for row in batch.to_pylist():
                        if self.series not in (None, row["series_id"]) or (self.high is not None and row["t_start"] > self.high) or (self.low is not None and row["t_start"] + row["n_samples"] <= self.low):
                            continue
                        codec.check(row)
                        yield codec.sample_batch(row, codec.unpack_many([(row["body"], row["n_slots"], row["n_samples"], row["dims"])], Options(**row["options"]))[0])


class EncodedReader(DataSourceReader):
    def __init__(self, path: str):
        self.decoder = Decoder(path)

    def pushFilters(self, filters):
        d = self.decoder
        for f in filters:
            column, value = getattr(f, "attribute", None), getattr(f, "value", None)
            if isinstance(f, EqualTo) and column == ("series_id",):
                d.series = value
            elif column == ("t",) and isinstance(f, (GreaterThan, GreaterThanOrEqual)):
                d.low = max(d.low if d.low is not None else value, value)
            elif column == ("t",) and isinstance(f, (LessThan, LessThanOrEqual)):
                d.high = min(d.high if d.high is not None else value, value)
            yield f  # pruning is coarse, so Spark filters rows again

    def partitions(self):
        return [InputPartition(path) for _, path in files_of(self.decoder.uri)]

    def read(self, partition):
        yield from self.decoder.read(partition.value)


class EncodedStream(DataSourceStreamReader):
    """An offset is the time of the newest file that was seen."""

    def __init__(self, path: str):
        self.decoder = Decoder(path)

    def initialOffset(self):
        return {"written_ns": 0}

    def latestOffset(self):
        return {"written_ns": max((ns for ns, _ in files_of(self.decoder.uri)), default=0)}

    def partitions(self, start, end):
        return [InputPartition(path) for ns, path in files_of(self.decoder.uri) if start["written_ns"] < ns <= end["written_ns"]]

    def read(self, partition):
        yield from self.decoder.read(partition.value)


@dataclass
class Written(WriterCommitMessage):
    path: str | None


class EncodedWriter(DataSourceArrowWriter):
    def __init__(self, path: str, name: str, width_bits: int, length: int):
        self.uri, self.length = path, length
        self.chosen = preset(name, width_bits)

    def write(self, iterator):
        system, folder = fs.FileSystem.from_uri(self.uri)
        with_segments = (
            pa.RecordBatch.from_arrays([b.column("series_id"), pc.divide(b.column("t"), self.length), b.column("t"), b.column("x")], ["series_id", "segment_id", "t", "x"]) for b in iterator if b.num_rows
        )
        made, path, out = codec.segment_batches(with_segments, self.chosen), None, None
        for batch in made:
            if out is None:
                system.create_dir(folder, recursive=True)
                path = f"{folder}/{uuid.uuid4().hex}"
                out = pq.ParquetWriter(system.open_output_stream(f"{path}.part"), codec.KINDS, compression="none")
            out.write_batch(batch)
        if out is not None:
            out.close()
            system.move(f"{path}.part", f"{path}.parquet")
        return Written(path and f"{path}.parquet")

    def commit(self, messages):
        """Files are complete already."""

    def abort(self, messages):
        system, _ = fs.FileSystem.from_uri(self.uri)
        for m in messages:
            if m is not None and m.path:
                system.delete_file(m.path)
