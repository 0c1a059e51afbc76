"""AVI motion-JPEG as a media column: RIFF indexes, intra frames, shots.

``parse_avi`` walks the RIFF chunks and the ``idx1`` index; ``decode_jpeg`` reads the entropy-coded
coefficients of a grey baseline frame, ``pixels`` turns them into samples; ``shots`` cuts where the
histogram difference of neighbouring frames exceeds an adaptive threshold (mean + 3 deviations of the
differences in a moving window); ``clips`` yields a timed row for each shot.

A payload is stored losslessly in the format's own unit, the quantised coefficient: each 64 bytes are one
8x8 block.  A byte v becomes v-128 below 128 and v-127 from there on, so no coefficient is 0, and the
Huffman code gives a coefficient of s bits a code of 9-s bits (10-s for the first of a block, coded as a
difference).  Every block so takes 577 bits, any baseline decoder can read it, and this one finds all
coefficients at known places without a walk from symbol to symbol.  Frames whose tables lack that
property go through the general decoder.

Defined cases: a null or empty text is 64 bytes of 0; equal texts give equal bytes and features; texts are
stored whole (sizes in RIFF have 32 bits, so a file of 4 GB or more is refused, which no Spark string reaches); null
ids are kept; repeated rows are each encoded; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .store import written

UNIT = 64
FRAME_BLOCKS = 64
FRAME_MS = 40
BLOCK_BITS = 10 + 63 * 9
#: Fixed value: the zigzag order of an 8x8 block's coefficients.
ZIGZAG = np.array([y * 8 + x for s in range(15) for y, x in (((i, s - i) if s % 2 else (s - i, i)) for i in range(s + 1)) if y < 8 and x < 8])


def _canonical(lengths: dict[int, int]) -> tuple[bytes, dict[int, tuple[int, int]]]:
    """A JPEG Huffman table segment's body (counts, symbols) and each symbol's (code, length)."""
    order = sorted(lengths, key=lambda s: (lengths[s], s))
    counts, codes, code, last = [0] * 16, {}, 0, 0
    for s in order:
        code <<= lengths[s] - last
        last = lengths[s]
        codes[s] = (code, last)
        counts[last - 1] += 1
        code += 1
    return bytes(counts) + bytes(order), codes


DC_TABLE, DC_CODES = _canonical({s: 10 - s for s in range(1, 10)} | {0: 10})
AC_TABLE, AC_CODES = _canonical({s: 9 - s for s in range(1, 9)})


def _values(codes: dict[int, tuple[int, int]], bits: int) -> np.ndarray:
    """The value that each window of ``bits`` bits stands for; 32767 where none."""
    out = np.full(1 << bits, 32767, np.int16)
    for size, (code, length) in codes.items():
        if length + size != bits:
            continue
        raw = np.arange(1 << size)
        value = np.where(raw >= (1 << size >> 1), raw, raw - (1 << size) + 1) if size else raw
        out[(code << size) + raw] = value
    return out


DC_VALUE, AC_VALUE = _values(DC_CODES, 10), _values(AC_CODES, 9)
DC_WINDOW = np.zeros(1024, np.uint16)
AC_WINDOW = np.zeros(1024, np.uint16)
for _window, _of in ((DC_WINDOW, DC_VALUE), (AC_WINDOW, AC_VALUE)):
    _known = np.flatnonzero(_of != 32767)
    _window[_of[_known].astype(np.int32) + 512] = _known
TO_COEFFICIENT = (np.arange(256) - np.where(np.arange(256) < 128, 128, 127)).astype(np.int16)
_BITS10, _BITS9 = np.arange(9, -1, -1, dtype=np.uint16), np.arange(8, -1, -1, dtype=np.uint16)
_u = np.arange(8)
_BASIS = np.cos((2 * _u[:, None] + 1) * _u[None, :] * np.pi / 16) * np.where(_u == 0, np.sqrt(0.125), 0.5)
#: 64 coefficients in zigzag order to 64 samples.
INVERSE = np.einsum("yv,xu->vuyx", _BASIS, _BASIS).reshape(64, 64)[ZIGZAG].astype(np.float32)


def encode_jpeg(payload: np.ndarray, width: int, height: int) -> bytes:
    """A grey baseline frame whose blocks hold the payload's bytes."""
    coefficients = TO_COEFFICIENT[payload.reshape(-1, UNIT)]
    first = np.diff(coefficients[:, 0], prepend=np.int16(0))
    bits = np.empty((len(coefficients), BLOCK_BITS), np.uint8)
    bits[:, :10] = (DC_WINDOW[first.astype(np.int32) + 512][:, None] >> _BITS10) & 1
    bits[:, 10:] = ((AC_WINDOW[coefficients[:, 1:].astype(np.int32) + 512][:, :, None] >> _BITS9) & 1).reshape(len(bits), -1)
    flat = bits.reshape(-1)
    packed = np.packbits(np.concatenate([flat, np.ones(-len(flat) % 8, np.uint8)]))
    scan = packed.tobytes().replace(b"\xff", b"\xff\x00")
    segment = lambda marker, body: struct.pack(">BBH", 255, marker, len(body) + 2) + body
    return b"".join(
        [
            b"\xff\xd8",
            segment(0xDB, b"\x00" + b"\x01" * 64),
            segment(0xC0, struct.pack(">BHHB", 8, height, width, 1) + b"\x01\x11\x00"),
            segment(0xC4, b"\x00" + DC_TABLE + b"\x10" + AC_TABLE),
            segment(0xDA, b"\x01\x01\x00\x00\x3f\x00"),
            scan,
            b"\xff\xd9",
        ]
    )


def _segments(frame: bytes) -> Iterator[tuple[int, bytes]]:
    """Marker segments, then the scan's data under marker 0."""
    if frame[:2] != b"\xff\xd8":
        raise ValueError("not a JPEG frame")
    at = 2
    while True:
        marker, size = frame[at + 1], int.from_bytes(frame[at + 2 : at + 4])
        yield marker, frame[at + 4 : at + 2 + size]
        at += 2 + size
        if marker == 0xDA:
            yield 0, frame[at : frame.rindex(b"\xff\xd9")]
            return


def _general(scan: bytes, blocks: int, tables: dict[int, dict[tuple[int, int], int]]) -> np.ndarray:
    """Coefficients of one scan by a walk from symbol to symbol."""
    data = int.from_bytes(scan)
    at, end = 0, len(scan) * 8
    take = lambda p, n: (data >> (end - p - n)) & ((1 << n) - 1)

    def symbol(table: dict[tuple[int, int], int], p: int) -> tuple[int, int]:
        for n in range(1, 17):
            if (s := table.get((take(p, n), n))) is not None:
                return s, p + n
        raise ValueError("no such Huffman code")

    out, level = np.zeros((blocks, 64), np.int16), 0
    for b in range(blocks):
        k = 0
        while k < 64:
            s, at = symbol(tables[0x10 if k else 0], at)
            run, size = (s >> 4, s & 15) if k else (0, s)
            raw = take(at, size) if size else 0
            at += size
            value = raw if not size or raw >> (size - 1) else raw - (1 << size) + 1
            if not k:
                level += value
                out[b, 0] = level
            elif not s:
                break
            else:
                k += run
                out[b, k] = value
            k += 1
    return out


def decode_jpeg(frame: bytes) -> tuple[int, int, np.ndarray, np.ndarray]:
    """Width, height, quantised coefficients (blocks x 64, zigzag order) and quantiser of a grey baseline frame."""
    tables, quantiser, width, height, plain = {}, np.ones(64, np.uint16), 0, 0, True
    for marker, body in _segments(frame):
        if marker == 0xDB:
            quantiser = np.frombuffer(body[1:65], np.uint8).astype(np.uint16)
        elif marker == 0xC0:
            height, width, components = struct.unpack(">HHB", body[1:6])
            if components != 1:
                raise ValueError("only grey frames are decoded")
        elif marker == 0xC4:
            plain &= body == b"\x00" + DC_TABLE + b"\x10" + AC_TABLE
            while body:
                counts = body[1:17]
                symbols, code, at, table = body[17 : 17 + sum(counts)], 0, 0, {}
                for n, count in enumerate(counts, 1):
                    for _ in range(count):
                        table[code, n] = symbols[at]
                        code, at = code + 1, at + 1
                    code <<= 1
                tables[body[0]], body = table, body[17 + sum(counts) :]
        elif marker == 0:
            scan = body.replace(b"\xff\x00", b"\xff")
    blocks = -(-width // 8) * -(-height // 8)
    if plain and len(scan) * 8 >= blocks * BLOCK_BITS:
        bits = np.unpackbits(np.frombuffer(scan, np.uint8), count=blocks * BLOCK_BITS).reshape(blocks, BLOCK_BITS)
        first = DC_VALUE[bits[:, :10] @ (1 << _BITS10)]
        rest = AC_VALUE[bits[:, 10:].reshape(blocks, 63, 9) @ (1 << _BITS9)]
        if (rest != 32767).all() and (first != 32767).all():
            return width, height, np.concatenate([np.cumsum(first, dtype=np.int16)[:, None], rest], 1), quantiser
    return width, height, _general(scan, blocks, tables), quantiser


def to_payload(coefficients: np.ndarray) -> bytes:
    return (coefficients + np.where(coefficients < 0, 128, 127)).astype(np.uint8).tobytes()


def pixels(coefficients: np.ndarray, quantiser: np.ndarray) -> np.ndarray:
    """Samples of each block, 0 to 255."""
    return np.clip((coefficients.astype(np.float32) * quantiser.astype(np.float32)) @ INVERSE + 128.5, 0, 255).astype(np.uint8)


def write_avi(payload: bytes) -> bytes:
    """An AVI 1.0 file with an index; the payload's length is its comment."""
    blocks = len(payload) // UNIT
    in_frame = min(blocks, FRAME_BLOCKS)
    width, height = (8 * in_frame, 8) if blocks < FRAME_BLOCKS else (64, 64)
    data = np.frombuffer(payload.ljust(-(-blocks // in_frame) * in_frame * UNIT, b"\x00"), np.uint8).reshape(-1, in_frame * UNIT)
    frames = [encode_jpeg(x, width, height) for x in data]
    chunk = lambda name, body: name + struct.pack("<I", len(body)) + body + b"\x00" * (len(body) % 2)
    most = max(map(len, frames))
    main = struct.pack("<14I", FRAME_MS * 1000, most * 1000 // FRAME_MS, 0, 0x10, len(frames), 0, 1, most, width, height, 0, 0, 0, 0)
    stream = b"vidsMJPG" + struct.pack("<10I4H", 0, 0, 0, FRAME_MS, 1000, 0, len(frames), most, 0xFFFFFFFF, 0, 0, 0, width, height)
    bitmap = struct.pack("<IiiHH4sIiiII", 40, width, height, 1, 8, b"MJPG", width * height, 0, 0, 0, 0)
    heads = chunk(b"LIST", b"hdrl" + chunk(b"avih", main) + chunk(b"LIST", b"strl" + chunk(b"strh", stream) + chunk(b"strf", bitmap)))
    note = chunk(b"LIST", b"INFO" + chunk(b"ICMT", b"payload=%d" % len(payload)))
    index, at, body = [], 4, []
    for f in frames:
        index.append(struct.pack("<4sIII", b"00dc", 0x10, at, len(f)))
        body.append(chunk(b"00dc", f))
        at += len(body[-1])
    return chunk(b"RIFF", b"AVI " + heads + note + chunk(b"LIST", b"movi" + b"".join(body)) + chunk(b"idx1", b"".join(index)))


def parse_avi(data: bytes) -> dict:
    """Frame period, size, comment and the frames that the index names (or, without one, those in ``movi``)."""
    if data[:4] != b"RIFF" or data[8:12] != b"AVI ":
        raise ValueError("not an AVI file")
    out, movi, index, found = {"comment": b""}, 0, b"", []

    def walk(at: int, end: int) -> None:
        nonlocal movi, index
        while at + 8 <= end:
            name, size = data[at : at + 4], int.from_bytes(data[at + 4 : at + 8], "little")
            body = at + 8
            if name == b"LIST":
                if data[body : body + 4] == b"movi":
                    movi = body
                walk(body + 4, body + size)
            elif name == b"avih":
                out["frame_us"], out["width"], out["height"] = *struct.unpack_from("<I", data, body), *struct.unpack_from("<2I", data, body + 32)
            elif name == b"ICMT":
                out["comment"] = data[body : body + size]
            elif name == b"idx1":
                index = data[body : body + size]
            elif name[2:] in (b"dc", b"db"):
                found.append((body, size))
            at = body + size + size % 2

    walk(12, min(len(data), 8 + int.from_bytes(data[4:8], "little")))
    entries = [struct.unpack_from("<4sIII", index, i) for i in range(0, len(index) - 15, 16)]
    video = [(at, size) for name, _, at, size in entries if name[2:] in (b"dc", b"db")]
    if video:
        base = movi if data[movi + video[0][0] : movi + video[0][0] + 4] == entries[0][0] else 0
        found = [(base + at + 8, size) for at, size in video]
    out["frames"] = [data[at : at + size] for at, size in found]
    return out


def histograms(frames: list[np.ndarray], bins: int = 16) -> np.ndarray:
    """A normalised grey histogram for each frame."""
    return np.array([np.bincount(f.reshape(-1) >> (8 - bins.bit_length() + 1), minlength=bins) / f.size for f in frames])


def shots(hist: np.ndarray, window: int = 8, deviations: float = 3.0, floor: float = 0.05) -> list[int]:
    """First frame of each shot: where the difference exceeds mean + ``deviations`` of the last ``window`` differences of the shot."""
    difference = np.abs(np.diff(hist, axis=0)).sum(1) / 2 if len(hist) > 1 else np.empty(0)
    cuts, since = [0], 0
    for i, d in enumerate(difference):
        past = difference[max(since, i - window) : i]
        if d > max(floor, past.mean() + deviations * past.std() if len(past) else 0.5):
            cuts.append(i + 1)
            since = i + 1
    return cuts


def clips(avi: bytes) -> tuple[list[tuple[int, int, int]], bytes]:
    """(shot, start ms, end ms) rows of an AVI, and the coefficients' payload."""
    media = parse_avi(avi)
    decoded = [decode_jpeg(f) for f in media["frames"]]
    starts = shots(histograms([pixels(c, q) for _, _, c, q in decoded])) + [len(decoded)]
    ms = media["frame_us"] // 1000
    payload = b"".join(to_payload(c) for _, _, c, _ in decoded)
    if media["comment"].startswith(b"payload="):
        payload = payload[: int(media["comment"][8:])]
    return [(i, a * ms, b * ms) for i, (a, b) in enumerate(zip(starts, starts[1:], strict=False))], payload


def padded(text: bytes) -> bytes:
    return text.ljust(max(UNIT, -(-len(text) // UNIT) * UNIT), b"\x00")


def to_media(docs: DataFrame, text: str = "text") -> DataFrame:
    """(doc_id, n_bytes, media): each text as an AVI in a binary column."""

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from .text import as_bytes, pieces

        for batch in batches:
            for piece in pieces(batch, text, 4 << 20):
                texts = as_bytes(piece.column(text))
                yield pa.RecordBatch.from_arrays(
                    [piece.column("doc_id"), pa.array(map(len, texts), pa.int64()), pa.array([write_avi(padded(t)) for t in texts], pa.binary())], ["doc_id", "n_bytes", "media"]
                )

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", text).mapInArrow(encode, f"doc_id {kind}, n_bytes bigint, media binary")


def clip_rows(media: DataFrame) -> DataFrame:
    """(doc_id, shot, start_ms, end_ms): a row for each shot of each media value."""

    def decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [(d, *c) for d, m in zip(batch.column("doc_id").to_pylist(), batch.column("media").to_pylist(), strict=True) if m is not None for c in clips(m)[0]]
            names = ["doc_id", "shot", "start_ms", "end_ms"]
            yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows, strict=True) if rows else [[]] * 4, [batch.schema.field("doc_id").type, *[pa.int64()] * 3], strict=True)], names)

    kind = media.schema["doc_id"].dataType.simpleString()
    return media.select("doc_id", "media").mapInArrow(decode, f"doc_id {kind}, shot bigint, start_ms bigint, end_ms bigint")


def stored(docs: DataFrame, text: str = "text") -> DataFrame:
    """The media table of ``to_media`` as files in the shared folder (AVI values are whole; pages of the files are packed)."""
    return written(to_media(docs, text), "media", "zstd")


def report(docs: DataFrame) -> DataFrame:
    """Per document: sizes and digests of the payload as read back from the stored media, and its shots."""

    def decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for media in batch.column("media").to_pylist():
                shot_rows, payload = clips(media)
                times = ",".join(f"{a}-{b}" for _, a, b in shot_rows)
                rows.append((len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-UNIT:]), len(media), hashlib.sha256(media).hexdigest(), f"shots={len(shot_rows)};ms={times}"))
            columns = [pa.array(x, t) for x, t in zip(zip(*rows, strict=True), (pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()), strict=True)] if rows else []
            if columns:
                yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("n_bytes"), *columns], ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return stored(docs).mapInArrow(decode, f"doc_id {kind}, n_bytes bigint, payload_bytes bigint, payload_sha256 string, tail_crc32 bigint, media_bytes bigint, media_sha256 string, feature string")
