"""Encoding series into segments and back.

``encode`` takes ``(series_id, t, x array<bigint>)``: one exchange brings a segment's samples together in
order, then a kernel packs many segments at once, lanes side by side.  ``decode`` needs no exchange.
Segments are independent, so a long series is cut by position (or any ``segment_id`` the caller gives);
a group that a task holds is bounded by the segment length, never by a series.

Defined cases: an empty series makes no row; fewer samples than a block are stored raw; nulls in ``x`` are
refused (see ``null_policy`` in ``relayout``); a change of the number of columns within a segment is refused.
"""

from __future__ import annotations

import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.bits import divided, header_bits
from . import baselines, huffman
from . import kernels as K
from .options import Options, preset
from .ordering import PART

SEGMENT = 8192
BATCH_VALUES = 1 << 21
#: Samples of a series that lie in one row on their way to the task that sizes it whole, and that it takes at a time.
PIECE, PIECES = 2048, 1 << 18
FORMAT = 1
OPTIONS = "struct<width_bits:int,forecaster:string,entropy:string,block:int,group:int,layout:string,signed:boolean,coef_num:bigint,rate_shift:int,update:string,grad_stride:int,zero_rule:string,mean_rounding:string,clamp:boolean,round_product:boolean,rle:boolean,entropy_order:string>"
SCHEMA = f"series_id string, segment_id bigint, t_start bigint, n_samples int, dims int, raw_bytes bigint, body_bytes bigint, n_slots int, col_min array<bigint>, col_max array<bigint>, col_sum array<decimal(38,0)>, crc bigint, format_version int, options {OPTIONS}, body binary"

_TEXT, _INT, _LONG, _LONGS, _FLAG = pa.string(), pa.int32(), pa.int64(), pa.list_(pa.int64()), pa.bool_()
_OPTION_KINDS = [
    *(("width_bits", _INT), ("forecaster", _TEXT), ("entropy", _TEXT), ("block", _INT), ("group", _INT), ("layout", _TEXT), ("signed", _FLAG), ("coef_num", _LONG)),
    *(("rate_shift", _INT), ("update", _TEXT), ("grad_stride", _INT), ("zero_rule", _TEXT), ("mean_rounding", _TEXT), ("clamp", _FLAG), ("round_product", _FLAG), ("rle", _FLAG), ("entropy_order", _TEXT)),
]
#: ``SCHEMA`` as Arrow has it, for places without a Spark session.
KINDS = pa.schema([
    *(("series_id", _TEXT), ("segment_id", _LONG), ("t_start", _LONG), ("n_samples", _INT), ("dims", _INT), ("raw_bytes", _LONG), ("body_bytes", _LONG), ("n_slots", _INT)),
    *(("col_min", _LONGS), ("col_max", _LONGS), ("col_sum", pa.list_(pa.decimal128(38, 0))), ("crc", _LONG), ("format_version", _INT), ("options", pa.struct(_OPTION_KINDS)), ("body", pa.binary())),
])


def unpacked(x: np.ndarray, z: np.ndarray, o: Options) -> bytes:
    """One segment's zigzagged residuals and raw tail as they are, for an entropy stage before packing."""
    item = f"<u{o.width_bits // 8}"
    return z.astype(item).tobytes() + (x[len(z) * o.block :] & ((1 << o.width_bits) - 1)).astype(item).tobytes()


def pack_segment(x: np.ndarray, z: np.ndarray, o: Options) -> tuple[bytes, int]:
    """Body and number of slots of one segment: packed blocks, raw tail, entropy stage."""
    whole = len(z) * o.block
    item = f"<u{o.width_bits // 8}"
    if o.entropy == "huffman" and o.entropy_order == "before":
        return huffman.encode(unpacked(x, z, o)), len(z)
    body, slots = K.pack(z, o)
    body += (x[whole:] & ((1 << o.width_bits) - 1)).astype(item).tobytes()
    return (huffman.encode(body) if o.entropy == "huffman" else body), slots


def _rectangles(shapes: list[tuple[int, int]], most: int) -> Iterator[list[int]]:
    """Numbers of segments (samples, columns) that lie side by side: alike in length, so that none pads much, and of at most ``most`` values as padded."""
    part, width = [], 0
    for i in sorted(range(len(shapes)), key=lambda i: shapes[i][0]):
        n, dims = shapes[i]
        if part and (max(n, 1) * (width + dims) > most or n > 2 * shapes[part[0]][0] + 64):
            yield part
            part, width = [], 0
        part.append(i)
        width += dims
    if part:
        yield part


def _beside(arrays: list[np.ndarray]) -> np.ndarray:
    """Arrays (samples x columns) side by side, shorter ones padded with zeros."""
    if len(arrays) == 1:
        return arrays[0]
    out, lane = np.zeros((max(map(len, arrays)), sum(a.shape[1] for a in arrays)), np.int64), 0
    for a in arrays:
        out[: len(a), lane : lane + a.shape[1]] = a
        lane += a.shape[1]
    return out


def pack_many(segments: list[np.ndarray], o: Options, most: int | None = None) -> list[tuple[bytes, int]]:
    """Bodies of several segments (samples x columns): forecasts run over the lanes of segments alike in length at once."""
    out: list = [None] * len(segments)
    for part in _rectangles([x.shape for x in segments], most or BATCH_VALUES):
        whole = [segments[i][: len(segments[i]) // o.block * o.block] for i in part]
        z, lane = K.zigzag(K.residuals(_beside(whole), o)), 0
        for i, x in zip(part, whole, strict=True):
            out[i] = pack_segment(segments[i], z[: len(x), lane : lane + x.shape[1]].reshape(-1, o.block, x.shape[1]), o)
            lane += x.shape[1]
    return out


def size_many(segments: list[np.ndarray], o: Options, most: int | None = None) -> list[int]:
    """Bytes of the bodies that ``pack_many`` makes without an entropy stage."""
    if o.entropy != "none":
        raise ValueError("an entropy stage has to see the body")
    out: list = [0] * len(segments)
    for part in _rectangles([x.shape for x in segments], most or BATCH_VALUES):
        whole = [segments[i][: len(segments[i]) // o.block * o.block] for i in part]
        beside, lane = _beside(whole), 0
        widths = K.widths_of(K.zigzag(K.residuals(beside, o)).reshape(-1, o.block, beside.shape[1]), o)
        for i, x in zip(part, whole, strict=True):
            out[i] = K.stream_bytes(widths[: len(x) // o.block, lane : lane + x.shape[1]], o) + (segments[i].size - x.size) * (o.width_bits // 8)
            lane += x.shape[1]
    return out


def unpack_many(bodies: list[tuple[bytes, int, int, int]], o: Options, most: int | None = None) -> list[np.ndarray]:
    """Samples of several bodies (body, slots, samples, columns) with the same options."""
    item, out = f"<u{o.width_bits // 8}", [None] * len(bodies)
    for part in _rectangles([(n, dims) for _, _, n, dims in bodies], most or BATCH_VALUES):
        raw = [bodies[i][0] for i in part]
        if o.entropy == "huffman":
            raw = huffman.decode_many(raw)
        residuals, tails = [], []
        for i, body in zip(part, raw, strict=True):
            _, slots, n, dims = bodies[i]
            whole = n // o.block * o.block
            if o.entropy == "huffman" and o.entropy_order == "before":
                z, end = np.frombuffer(body, item, whole * dims).astype(np.int64).reshape(-1, o.block, dims), whole * dims * (o.width_bits // 8)
            else:
                z, end = K.unpack(body, slots, dims, o)
            if len(z) * o.block != whole:
                raise ValueError("a body doesn't hold the samples its row names")
            residuals.append(K.unzigzag(z).reshape(-1, dims))
            tails.append(np.frombuffer(body, item, (n - whole) * dims, end).astype(np.int64).reshape(-1, dims))
        x, lane = K.reconstruct(_beside(residuals), o), 0
        for i, e, tail in zip(part, residuals, tails, strict=True):
            full = np.concatenate([x[: len(e), lane : lane + e.shape[1]], tail])
            out[i] = K.wrap(full, o.width_bits) if o.signed else full
            lane += e.shape[1]
    return out


def segmented(series: DataFrame, length: int = SEGMENT) -> DataFrame:
    """``segment_id`` by position, where the caller has not given one."""
    return series if "segment_id" in series.columns else series.withColumn("segment_id", divided(F.col("t"), length))


def _emit(names: list[tuple[str, int, int]], samples: list[np.ndarray], o: Options) -> pa.RecordBatch:
    made = pack_many(samples, o)
    w = o.width_bits // 8
    columns = {
        "series_id": [n[0] for n in names],
        "segment_id": [n[1] for n in names],
        "t_start": [n[2] for n in names],
        "n_samples": [len(x) for x in samples],
        "dims": [x.shape[1] for x in samples],
        "raw_bytes": [x.size * w for x in samples],
        "body_bytes": [len(b) for b, _ in made],
        "n_slots": [s for _, s in made],
        "col_min": [x.min(0).tolist() for x in samples],
        "col_max": [x.max(0).tolist() for x in samples],
        "col_sum": [[int(v) for v in x.sum(0)] for x in samples],
        "crc": [zlib.crc32(b) for b, _ in made],
        "format_version": [FORMAT] * len(names),
        "options": [o.as_dict()] * len(names),
        "body": [b for b, _ in made],
    }
    return pa.RecordBatch.from_arrays([pa.array(columns[f.name], f.type) for f in KINDS], schema=KINDS)


def arrow_schema(ddl: str) -> pa.Schema:
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import StructType

    return to_arrow_schema(StructType.fromDDL(ddl))


def segment_batches(batches: Iterator[pa.RecordBatch], o: Options) -> Iterator[pa.RecordBatch]:
    """Segment rows of batches (series_id, segment_id, t, x) whose segments lie together and in order."""
    names, done, held = [], [], 0
    open_key, open_t, parts = None, 0, []

    def close() -> None:
        nonlocal held
        if open_key is not None:
            names.append((*open_key, open_t))
            done.append(np.concatenate(parts))
            held += done[-1].size

    for batch in batches:
        if not batch.num_rows:
            continue
        lists = batch.column("x")
        lengths = np.diff(lists.offsets.to_numpy())
        flat = lists.flatten()
        if lists.null_count or flat.null_count:
            raise ValueError("x has nulls; choose a null policy first")
        flat, base = flat.to_numpy(), np.concatenate([[0], np.cumsum(lengths)])
        ids, segments, ts = batch.column("series_id"), batch.column("segment_id").to_numpy(), batch.column("t").to_numpy()
        codes = ids.dictionary_encode().indices.to_numpy(zero_copy_only=False)
        cuts = np.concatenate([[0], np.flatnonzero((np.diff(codes) != 0) | (np.diff(segments) != 0)) + 1, [len(ts)]])
        for a, b in zip(cuts[:-1], cuts[1:], strict=True):
            if (lengths[a:b] != lengths[a]).any() or not lengths[a]:
                raise ValueError("the number of columns changes within a segment")
            key = (ids[int(a)].as_py(), int(segments[a]))
            part = flat[base[a] : base[b]].reshape(b - a, -1)
            if key != open_key:
                close()
                if held >= BATCH_VALUES:
                    yield _emit(names, done, o)
                    names, done, held = [], [], 0
                open_key, open_t, parts = key, int(ts[a]), []
            elif part.shape[1] != parts[0].shape[1]:
                raise ValueError("the number of columns changes within a segment")
            parts.append(part)
    close()
    if names:
        yield _emit(names, done, o)


def encode(series: DataFrame, options: Options | str = "balanced", width_bits: int = 16, segment_length: int = SEGMENT, arranged: bool = False, **changes) -> DataFrame:
    """Segments of ``(series_id, t, x)``.  ``arranged``: rows already are together and in order within partitions."""
    o = preset(options, width_bits, **changes) if isinstance(options, str) else options
    rows = segmented(series, segment_length).select(F.col("series_id").cast("string").alias("series_id"), F.col("segment_id").cast("bigint").alias("segment_id"), F.col("t").cast("bigint").alias("t"), F.col("x").cast("array<bigint>").alias("x"))
    if not arranged:
        rows = rows.repartition("series_id", "segment_id").sortWithinPartitions("series_id", "segment_id", "t")
    return rows.mapInArrow(lambda batches: segment_batches(batches, o), SCHEMA)


class _WholeSize:
    """Bytes of one column's body, whole from its first sample on, out of samples that come in order in pieces."""

    def __init__(self, o: Options):
        self.o, self.n, self.slots, self.bytes, self.zeros = o, 0, 0, 0, 0
        self.sample, self.step, self.gain, self.rest = 0, 0, 0, np.zeros(0, np.int64)

    def add(self, x: np.ndarray) -> None:
        o, w = self.o, self.o.width_bits
        self.n += len(x)
        x = np.concatenate([self.rest, x])
        whole = len(x) // o.block * o.block
        x, self.rest = x[:whole], x[whole:]
        if not whole:
            return
        e = step = K.wrap(np.diff(x, prepend=self.sample), w)
        last = np.concatenate([[self.step], step[:-1]])
        if o.forecaster == "adaptive":
            coef, self.gain = K.coefficients(step, last, o, self.gain)
            e = K.wrap(step - K.Learner(1, o).estimate(coef, last), w)
        elif o.forecaster == "fixed":
            e = K.wrap(step - (o.coef_num * last >> w), w)
        self.sample, self.step = int(x[-1]), int(step[-1])
        widths = K.widths_of(K.zigzag(e).reshape(-1, o.block, 1), o)
        data = np.flatnonzero(widths[:, 0])
        self.slots += len(data)
        self.bytes += int(K.payload_sizes(widths[data], o).sum()) if len(data) else 0
        gaps = np.diff(data, prepend=-1, append=len(widths)) - 1
        gaps[0] += self.zeros
        self._runs(gaps[:-1][gaps[:-1] > 0])
        self.zeros = int(gaps[-1])

    def _runs(self, blocks: np.ndarray) -> None:
        self.slots += len(blocks)
        self.bytes += int(K.varint_sizes(blocks).sum())

    def close(self) -> int:
        if self.zeros:
            self._runs(np.array([self.zeros]))
        bits, (full, rest) = header_bits(self.o.width_bits), divmod(self.slots, self.o.group)
        return self.bytes + full * -(-self.o.group * bits // 8) + -(-rest * bits // 8) + len(self.rest) * (self.o.width_bits // 8)


class _PackedSize:
    """The same of binary packing."""

    def __init__(self):
        self.n, self.bytes, self.rest = 0, 0, np.zeros(0, np.int64)

    def add(self, x: np.ndarray) -> None:
        self.n += len(x)
        x = np.concatenate([self.rest, x])
        whole = len(x) // baselines.PACK * baselines.PACK
        self.bytes, self.rest = self.bytes + baselines.bp128_size(x[:whole]), x[whole:]

    def close(self) -> int:
        return self.bytes + baselines.bp128_size(self.rest)


def _in_pieces(batches: Iterator[pa.RecordBatch], columns: list[str]) -> Iterator[pa.RecordBatch]:
    """Rows (series_id, t, columns), which lie in order, as rows of up to ``PIECE`` samples that follow each other; ``t`` is that of the first."""
    for batch in batches:
        if not batch.num_rows:
            continue
        ids, t = batch.column("series_id").dictionary_encode(), batch.column("t").to_numpy()
        codes, data = ids.indices.to_numpy(zero_copy_only=False), [batch.column(c).to_numpy().astype("<u2") for c in columns]
        cuts = [0, *(np.flatnonzero((np.diff(codes) != 0) | (np.diff(t) != 1)) + 1).tolist(), len(t)]
        spans = [(i, min(i + PIECE, b)) for a, b in zip(cuts[:-1], cuts[1:], strict=True) for i in range(a, b, PIECE)]
        made = [pa.array([ids.dictionary[int(codes[a])].as_py() for a, _ in spans], pa.string()), pa.array([int(t[a]) for a, _ in spans], pa.int64())]
        yield pa.RecordBatch.from_arrays([*made, *[pa.array([x[a:b].tobytes() for a, b in spans], pa.binary()) for x in data]], ["series_id", "t", *columns])


def _ordered(series: DataFrame, columns: list[str], length: int) -> DataFrame:
    """(series_id, t, columns) with ``length`` samples of a series in one task, in order."""
    rows = series.select(F.col("series_id").cast("string").alias("series_id"), F.col("t").cast("bigint").alias("t"), *[F.col(c).cast("bigint").alias(c) for c in columns])
    return rows.repartition("series_id", divided(F.col("t"), length)).sortWithinPartitions("series_id", "t")


def method_sizes(series: DataFrame, methods: dict[str, dict[str, Options | None]]) -> DataFrame:
    """(series_id, column, method, n_samples, enc_bytes): bodies of each whole series (series_id, t, columns), never cut, by column of samples and method; options of None stand for binary packing.

    What the learning forecaster predicts a sample with depends on all before it, so a series passes one task, in order and piece by piece: that takes
    time with its length, but memory only for a piece.  Samples are put in order in parts of a series, in parallel; that task orders only pieces of them.
    """
    if any(p and (p.entropy == "huffman" or p.signed or not p.rle or p.width_bits > 16) for of in methods.values() for p in of.values()):
        raise ValueError("whole sizes are for unsigned samples of 8 or 16 bits, without an entropy stage")
    columns, fields = list(methods), ["series_id", "column", "method", "n_samples", "enc_bytes"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        name, open_, made = None, [], []

        def close() -> None:
            made.extend((name, c, m, s.n, s.close()) for c, of in zip(columns, open_, strict=bool(open_)) for m, s in of)

        for batch in batches:
            ids, data = batch.column("series_id").to_pylist(), [batch.column(c) for c in columns]
            cuts = [0, *[i for i in range(1, len(ids)) if ids[i] != ids[i - 1]], len(ids)] if ids else [0]
            for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                if not open_ or ids[a] != name:
                    close()
                    name, open_ = ids[a], [[(m, _WholeSize(p) if p else _PackedSize()) for m, p in methods[c].items()] for c in columns]
                for i in range(a, b, PIECES // PIECE):
                    for of, x in zip(open_, data, strict=True):
                        samples = np.frombuffer(b"".join(x.slice(i, min(PIECES // PIECE, b - i)).to_pylist()), "<u2").astype(np.int64)
                        for _, size in of:
                            size.add(samples)
        close()
        yield pa.RecordBatch.from_arrays([pa.array([m[i] for m in made], kind) for i, kind in enumerate((pa.string(), pa.string(), pa.string(), pa.int64(), pa.int64()))], fields)

    pieces = _ordered(series, columns, PART).mapInArrow(lambda batches: _in_pieces(batches, columns), f"series_id string, t bigint, {', '.join(f'{c} binary' for c in columns)}")
    return pieces.repartition("series_id").sortWithinPartitions("series_id", "t").mapInArrow(run, "series_id string, column string, method string, n_samples bigint, enc_bytes bigint")


def whole_sizes(series: DataFrame, o: Options | dict[str, Options]) -> DataFrame:
    """(series_id, enc_bytes) of ``method_sizes`` for the samples ``x`` and one method.  Of several columns of samples, each with options: (series_id, column, enc_bytes)."""
    out = method_sizes(series, {c: {"": p} for c, p in ({"x": o} if isinstance(o, Options) else o).items()}).drop("method", "n_samples")
    return out.drop("column") if isinstance(o, Options) else out


def _segments_in_order(batches: Iterator[pa.RecordBatch], columns: list[str], length: int) -> Iterator[tuple]:
    """(series_id, first position, samples of each column) of segments of ``length`` positions, out of rows in order."""
    key, parts = None, []
    for batch in batches:
        if not batch.num_rows:
            continue
        ids, place = batch.column("series_id").dictionary_encode(), batch.column("t").to_numpy() // length
        codes, data = ids.indices.to_numpy(zero_copy_only=False), [batch.column(c).to_numpy() for c in columns]
        cuts = [0, *(np.flatnonzero((np.diff(codes) != 0) | (np.diff(place) != 0)) + 1).tolist(), len(place)]
        for a, b in zip(cuts[:-1], cuts[1:], strict=True):
            at = ids.dictionary[int(codes[a])].as_py(), int(place[a]) * length
            if at != key:
                if key is not None:
                    yield *key, *[np.concatenate(p) for p in parts]
                key, parts = at, [[] for _ in columns]
            for part, x in zip(parts, data, strict=True):
                part.append(x[a:b])
    if key is not None:
        yield *key, *[np.concatenate(p) for p in parts]


def by_segments(series: DataFrame, columns: list[str], make: Callable[[list[tuple]], Iterator[tuple]], ddl: str, length: int, most: int = 1) -> DataFrame:
    """Rows that ``make`` yields for segments (series_id, first position, samples of each column) of at most ``length`` samples; it gets them until there are ``most`` samples.

    One exchange brings samples together and in order: a segment's, or those of a part of a series that holds whole segments.
    """
    schema = arrow_schema(ddl)

    def rows(segments: list[tuple]) -> pa.RecordBatch:
        made = list(make(segments))
        return pa.RecordBatch.from_arrays([pa.array([m[i] for m in made], f.type) for i, f in enumerate(schema)], schema=schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0
        for segment in _segments_in_order(batches, columns, length):
            held.append(segment)
            n += len(segment[2])
            if n >= most:
                yield rows(held)
                held, n = [], 0
        if held:
            yield rows(held)

    return _ordered(series, columns, length if length >= PART else PART // length * length).mapInArrow(run, ddl)


def check(row: dict) -> None:
    """Refuses a segment of another format version or with a damaged body."""
    if row["format_version"] != FORMAT:
        raise ValueError(f"unknown format version {row['format_version']}")
    if zlib.crc32(row["body"]) != row["crc"]:
        raise ValueError(f"segment {row['series_id']}/{row['segment_id']} is damaged")


def sample_batch(row: dict, x: np.ndarray, first: int = 0) -> pa.RecordBatch:
    """(series_id, t, x) of a segment's samples from its ``first`` on."""
    flat = pa.array(np.ascontiguousarray(x).reshape(-1))
    lists = pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1, dtype=np.int32) * x.shape[1]), flat)
    kinds = [pa.array([row["series_id"]] * len(x), pa.string()), pa.array(np.arange(len(x)) + row["t_start"] + first), lists.cast(pa.list_(pa.int64()))]
    return pa.RecordBatch.from_arrays(kinds, ["series_id", "t", "x"])


def _options(row: dict) -> Options:
    return Options(**row)


def decode(segments: DataFrame, t0: int | None = None, t1: int | None = None, columns: list[int] | None = None, checked: bool = True) -> DataFrame:
    """(series_id, t, x) with t0 <= t < t1 of the segments; segments outside the range are not read, columns not asked for not returned.

    The predicates on ``t_start`` reach the Parquet scan when the segments come from files.
    """
    if t1 is not None:
        segments = segments.where(F.col("t_start") < t1)
    if t0 is not None:
        segments = segments.where(F.col("t_start") + F.col("n_samples") > t0)
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows, at = batch.to_pylist(), 0
            while at < len(rows):
                o, held, stop = rows[at]["options"], 0, at
                while stop < len(rows) and rows[stop]["options"] == o and held < BATCH_VALUES:
                    held += rows[stop]["n_samples"] * rows[stop]["dims"]
                    stop += 1
                part = rows[at:stop]
                for r in part if checked else ():
                    check(r)
                made = unpack_many([(r["body"], r["n_slots"], r["n_samples"], r["dims"]) for r in part], _options(o))
                for r, x in zip(part, made, strict=True):
                    a = max(0, (t0 or 0) - r["t_start"]) if t0 is not None else 0
                    b = len(x) if t1 is None else min(len(x), t1 - r["t_start"])
                    x = x[a:b] if columns is None else x[a:b, columns]
                    if len(x):
                        yield sample_batch(r, x, a)
                at = stop

    needed = ["series_id", "segment_id", "t_start", "n_samples", "dims", "n_slots", "crc", "format_version", "options", "body"]
    return segments.select(*needed).mapInArrow(run, "series_id string, t bigint, x array<bigint>")


STATS = "series_id string, segment_id bigint, slot bigint, kind string, n_blocks bigint, widths array<bigint>, payload_bytes bigint"
STATS_KINDS = pa.schema([("series_id", pa.string()), ("segment_id", pa.int64()), ("slot", pa.int64()), ("kind", pa.string()), ("n_blocks", pa.int64()), ("widths", pa.list_(pa.int64())), ("payload_bytes", pa.int64())])


def slot_batch(row: dict) -> pa.RecordBatch:
    """A row for each slot of a segment, in the columns of ``STATS``."""
    o = _options(row["options"])
    body = huffman.decode(row["body"]) if o.entropy == "huffman" else row["body"]
    widths, runs, _, _ = K.parse_slots(body, row["n_slots"], row["dims"], o)
    n, is_run = len(runs), runs > 0
    size = np.where(is_run, [len(K.varint(int(k))) for k in runs], K.payload_sizes(widths, o) if n else 0)
    columns = ([row["series_id"]] * n, [row["segment_id"]] * n, range(n), np.where(is_run, "run", "data").tolist(), np.where(is_run, runs, 1), widths.tolist(), size)
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(columns, STATS_KINDS, strict=True)], schema=STATS_KINDS)


def block_stats(segments: DataFrame) -> DataFrame:
    """(series_id, segment_id, slot, kind, n_blocks, widths, payload_bytes) of each slot, from headers alone."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        return (slot_batch(r) for batch in batches for r in batch.to_pylist())

    return segments.select("series_id", "segment_id", "n_slots", "dims", "options", "body").mapInArrow(run, STATS)


def compressed_aggregate(segments: DataFrame) -> DataFrame:
    """(series_id, col, min, max, sum, count) without materializing samples.

    Whole segments answer from their row's statistics, so the bodies are pruned from the scan.
    """
    z = segments.select("series_id", "n_samples", F.posexplode(F.arrays_zip("col_min", "col_max", "col_sum")).alias("col", "s"))
    return z.groupBy("series_id", "col").agg(F.min("s.col_min").alias("min"), F.max("s.col_max").alias("max"), F.sum("s.col_sum").cast("bigint").alias("sum"), F.sum("n_samples").alias("count"))


def run_aggregate(segments: DataFrame, t0: int | None = None, t1: int | None = None) -> DataFrame:
    """(series_id, col, min, max, sum, count) from bodies: a run of constant samples counts through its first value.

    For lag1 a zero run repeats one vector, so only data blocks are decoded; other forecasters roll.
    A range cuts segments at their ends and, for those, decodes.
    """
    ddl = "series_id string, col int, min bigint, max bigint, sum decimal(38,0), count bigint"
    picked = segments
    if t1 is not None:
        picked = picked.where(F.col("t_start") < t1)
    if t0 is not None:
        picked = picked.where(F.col("t_start") + F.col("n_samples") > t0)

    kinds = arrow_schema(ddl)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for r in batch.to_pylist():
                o, dims, n = _options(r["options"]), r["dims"], r["n_samples"]
                a, b = max(0, (t0 or 0) - r["t_start"]), n if t1 is None else min(n, t1 - r["t_start"])
                weight = None
                if o.forecaster == "lag1" and o.entropy_order == "after" and (a, b) == (0, n):
                    body = huffman.decode(r["body"]) if o.entropy == "huffman" else r["body"]
                    widths, runs, _, end = K.parse_slots(body, r["n_slots"], dims, o)
                    flat = Options(**{**r["options"], "rle": False})
                    z, _ = _data_blocks(body, widths, runs, r["n_slots"], dims, o)
                    x = K.reconstruct(K.unzigzag(z).reshape(-1, dims), flat)
                    weight = np.ones(len(x), np.int64)
                    at = np.cumsum(np.where(runs > 0, 1, o.block)) - np.where(runs > 0, 1, o.block)
                    weight[at[runs > 0]] = runs[runs > 0] * o.block
                    tail = np.frombuffer(body, f"<u{o.width_bits // 8}", (n % o.block) * dims, end).astype(np.int64).reshape(-1, dims)
                    x, weight = np.concatenate([x, tail]), np.concatenate([weight, np.ones(len(tail), np.int64)])
                    x = K.wrap(x, o.width_bits) if o.signed else x
                else:
                    x = unpack_many([(r["body"], r["n_slots"], n, dims)], o)[0][a:b]
                    weight = np.ones(len(x), np.int64)
                if len(x):
                    for j in range(dims):
                        rows.append((r["series_id"], j, int(x[:, j].min()), int(x[:, j].max()), int((x[:, j] * weight).sum()), int(weight.sum())))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), kinds, strict=True)], schema=kinds)

    parts = picked.select("series_id", "t_start", "n_samples", "dims", "n_slots", "options", "body").mapInArrow(run, ddl)
    return parts.groupBy("series_id", "col").agg(F.min("min").alias("min"), F.max("max").alias("max"), F.sum("sum").cast("bigint").alias("sum"), F.sum("count").alias("count"))


def _data_blocks(body: bytes, widths: np.ndarray, runs: np.ndarray, n_slots: int, dims: int, o: Options) -> tuple[np.ndarray, int]:
    """Residuals of data blocks, with a single zero residual in place of each run."""
    z, end = K.unpack(body, n_slots, dims, o)
    length = np.where(runs > 0, runs, 1)
    first = np.cumsum(length) - length
    rows = [z[f, :1] if r else z[f] for f, r in zip(first, runs, strict=True)]
    return (np.concatenate(rows) if rows else np.zeros((0, dims), np.int64)), end


def verify_roundtrip(series: DataFrame, segments: DataFrame) -> DataFrame:
    """One row: how many samples are missing, extra or different after decoding."""
    a = series.select(F.col("series_id").cast("string").alias("series_id"), "t", F.col("x").cast("array<bigint>").alias("x"))
    b = decode(segments).withColumnRenamed("x", "decoded")
    both = a.join(b, ["series_id", "t"], "full_outer")
    return both.agg(F.count(F.lit(1)).alias("samples"), F.sum((~F.col("x").eqNullSafe(F.col("decoded"))).cast("bigint")).alias("mismatches"))
