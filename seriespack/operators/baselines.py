"""Published codecs to compare with: binary packing, patched packing, word packing, general compressors.

They get each variable's values contiguous; whole-number codecs see 32-bit values.  Sizes of the two
packing codecs follow from aggregates alone; all have an encoder and a decoder here.
"""

from __future__ import annotations

import zlib

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.bits import bit_width, divided
from .kernels import bit_length, varint_sizes

PACK = 128
#: Fixed values of the word-packing format: how many values, of how many bits, for each selector.
SIMPLE8B = ((240, 0), (120, 0), (60, 1), (30, 2), (20, 3), (15, 4), (12, 5), (10, 6), (8, 7), (7, 8), (6, 10), (5, 12), (4, 15), (3, 20), (2, 30), (1, 60))
GENERAL = ("snappy", "zstd", "lz4", "zlib")


def _variable(values: np.ndarray) -> bytes:
    """Seven bits a byte."""
    out = bytearray()
    for v in values.tolist():
        while v >= 128:
            out.append(v & 127 | 128)
            v >>= 7
        out.append(v)
    return bytes(out)


def _unvariable(data: bytes, n: int) -> np.ndarray:
    out, at = [], 0
    for _ in range(n):
        v = shift = 0
        while True:
            byte = data[at]
            v, at, shift = v | (byte & 127) << shift, at + 1, shift + 7
            if byte < 128:
                break
        out.append(v)
    return np.array(out, np.int64)


def _bits(values: np.ndarray, width: int) -> bytes:
    return np.packbits((values[:, None] >> np.arange(width) & 1).astype(np.uint8).reshape(-1), bitorder="little").tobytes()


def _unbits(data: bytes, n: int, width: int) -> np.ndarray:
    bits = np.unpackbits(np.frombuffer(data, np.uint8), bitorder="little")[: n * width].reshape(n, width)
    return bits @ (1 << np.arange(width, dtype=np.int64))


def bp128_encode(v: np.ndarray) -> bytes:
    """Blocks of 128 values at the width of their largest, a byte for each width, the rest in variable bytes."""
    whole, out = len(v) // PACK * PACK, []
    for i in range(0, whole, PACK):
        width = int(bit_length(np.bitwise_or.reduce(v[i : i + PACK])))
        out.append(bytes([width]) + _bits(v[i : i + PACK], width))
    return b"".join(out) + _variable(v[whole:])


def bp128_decode(data: bytes, n: int) -> np.ndarray:
    out, at = [], 0
    for _ in range(n // PACK):
        width = data[at]
        out.append(_unbits(data[at + 1 : at + 1 + 16 * width], PACK, width) if width else np.zeros(PACK, np.int64))
        at += 1 + 16 * width
    return np.concatenate([*out, _unvariable(data[at:], n % PACK)])


def _patched_width(bits: np.ndarray) -> tuple[int, int, int]:
    """Base width, greatest width and count of exceptions that cost least; the narrower base on ties."""
    top = int(bits.max())
    over = [(int((bits > b).sum()), b) for b in range(top + 1)]
    cost, base, exceptions = min((PACK * b + c * (top - b + 8), b, c) for c, b in over)
    return base, top, exceptions


def pfor_encode(v: np.ndarray) -> bytes:
    """Blocks of 128 at a base width; values that need more leave their high bits apart, with their places."""
    whole, out, pools = len(v) // PACK * PACK, [], {}
    for i in range(0, whole, PACK):
        block = v[i : i + PACK]
        bits = bit_length(block)
        base, top, count = _patched_width(bits)
        places = np.flatnonzero(bits > base)
        out.append(bytes([base, top, count]) + places.astype(np.uint8).tobytes() + _bits(block & ((1 << base) - 1), base))
        if count:
            pools.setdefault(top - base, []).append(block[places] >> base)
    high = []
    for width in sorted(pools):
        packed = _bits(np.concatenate(pools[width]), width)
        high.append(packed.ljust(-(-len(packed) // 4) * 4, b"\0"))
    return b"".join(out) + b"".join(high) + _variable(v[whole:])


def pfor_decode(data: bytes, n: int) -> np.ndarray:
    at, blocks, counts = 0, [], {}
    for _ in range(n // PACK):
        base, top, count = data[at : at + 3]
        places = np.frombuffer(data, np.uint8, count, at + 3)
        at += 3 + count
        blocks.append((base, top - base, places, _unbits(data[at : at + 16 * base], PACK, base) if base else np.zeros(PACK, np.int64)))
        at += 16 * base
        if count:
            counts[top - base] = counts.get(top - base, 0) + count
    pools = {}
    for width in sorted(counts):
        size = -(-(-(-counts[width] * width // 8)) // 4) * 4
        pools[width] = _unbits(data[at : at + size], counts[width], width)
        at += size
    for base, width, places, block in blocks:
        if len(places):
            block[places] |= pools[width][: len(places)] << base
            pools[width] = pools[width][len(places) :]
    return np.concatenate([*[b[3] for b in blocks], _unvariable(data[at:], n % PACK)])


def simple8b_encode(v: np.ndarray) -> bytes:
    """64-bit words: a selector of 4 bits and as many values as fit, greedily; zeros have run selectors."""
    bits, out, at = bit_length(v), [], 0
    if len(v) and int(bits.max()) > 60:
        raise ValueError("values of more than 60 bits don't fit")
    while at < len(v):
        for selector, (count, width) in enumerate(SIMPLE8B):
            part = bits[at : at + count]
            if (part > width).any() or not width and len(part) < count:
                continue
            word = selector
            for i, x in enumerate(v[at : at + count].tolist() if width else ()):
                word |= x << (4 + i * width)
            out.append(word)
            at += count
            break
    return np.array(out, np.uint64).tobytes()


def simple8b_decode(data: bytes, n: int) -> np.ndarray:
    out: list[int] = []
    for word in np.frombuffer(data, np.uint64).tolist():
        count, width = SIMPLE8B[word & 15]
        out += [word >> (4 + i * width) & ((1 << width) - 1) for i in range(count)] if width else [0] * count
    return np.array(out[:n], np.int64)


def general_encode(codec: str, data: bytes, level: int = 9) -> bytes:
    if codec == "zlib":
        return zlib.compress(data, level)
    import pyarrow as pa

    name = {"lz4": "lz4_raw"}.get(codec, codec)
    made = pa.Codec(name, compression_level=level) if codec == "zstd" else pa.Codec(name)
    return made.compress(data, asbytes=True)


def general_decode(codec: str, data: bytes, size: int) -> bytes:
    if codec == "zlib":
        return zlib.decompress(data)
    import pyarrow as pa

    return pa.Codec({"lz4": "lz4_raw"}.get(codec, codec)).decompress(data, size, asbytes=True)


INTEGER = {"bp128": (bp128_encode, bp128_decode), "pfor": (pfor_encode, pfor_decode), "simple8b": (simple8b_encode, simple8b_decode)}


def _in_packs(v: np.ndarray) -> tuple[np.ndarray, int]:
    """Whole blocks, and the bytes of the values after them."""
    whole = len(v) // PACK * PACK
    return v[:whole].reshape(-1, PACK), int(varint_sizes(v[whole:]).sum())


def bp128_size(v: np.ndarray) -> int:
    """Bytes that ``bp128_encode`` makes."""
    blocks, rest = _in_packs(v)
    return int((1 + PACK // 8 * bit_length(np.bitwise_or.reduce(blocks, axis=1))).sum()) + rest


def pfor_size(v: np.ndarray) -> int:
    """Bytes that ``pfor_encode`` makes: all blocks choose their base width at once, the narrower one on ties."""
    blocks, rest = _in_packs(v)
    bits = bit_length(blocks).astype(np.int8)
    top = bits.max(axis=1, initial=0).astype(np.int64)
    cost, base, count = PACK * top, top.copy(), np.zeros(len(top), np.int64)
    for b in range(int(top.max(initial=0)) - 1, -1, -1):
        over = np.count_nonzero(bits > b, axis=1)
        made = PACK * b + over * (top - b + 8)
        better = (b < top) & (made <= cost)
        cost, base, count = np.where(better, made, cost), np.where(better, b, base), np.where(better, over, count)
    high = np.bincount(top - base, count, 1).astype(np.int64)
    pools = -(-(-(-high * np.arange(len(high)) // 8)) // 4) * 4
    return int((3 + count + PACK // 8 * base).sum() + pools.sum()) + rest


def simple8b_size(v: np.ndarray) -> int:
    """Bytes that ``simple8b_encode`` makes: how many values a word takes is found for all places at once, then words are counted from one to the next."""
    bits, n = bit_length(v).astype(np.int8), len(v)
    if n and int(bits.max()) > 60:
        raise ValueError("values of more than 60 bits don't fit")
    place, taken = np.arange(n, dtype=np.int32), np.ones(n, np.uint8)
    for count, width in reversed(SIMPLE8B[:-1]):
        wider = np.minimum.accumulate(np.where(bits > width, place, np.int32(n))[::-1])[::-1]
        taken[(wider - place >= count) | (wider == n if width else False)] = count
    step, at, words = taken.tobytes(), 0, 0
    while at < n:
        at += step[at]
        words += 1
    return 8 * words


#: What the encoders of ``INTEGER`` make, without making it.
SIZES = {"bp128": bp128_size, "pfor": pfor_size, "simple8b": simple8b_size}


def _varbytes(bits):
    return F.greatest(F.lit(1), F.ceil(bits / 7)).cast("bigint")


def bp128_sizes(df: DataFrame, keys: tuple[str, ...] = ("series_id",)) -> DataFrame:
    """(keys, enc_bytes) of ``x`` by aggregates."""
    blocks = df.withColumn("_b", divided(F.col("t"), PACK)).groupBy(*keys, "_b").agg(F.count(F.lit(1)).alias("n"), bit_width(F.bit_or("x")).alias("bits"), F.sum(_varbytes(bit_width(F.col("x")))).alias("tail"))
    return blocks.groupBy(*keys).agg(F.sum(F.when(F.col("n") == PACK, 1 + 16 * F.col("bits")).otherwise(F.col("tail"))).cast("bigint").alias("enc_bytes"))


def pfor_sizes(df: DataFrame, keys: tuple[str, ...] = ("series_id",), most_bits: int = 32) -> DataFrame:
    """(keys, enc_bytes) of ``x`` by aggregates: each block's base width minimizes the cost over its histogram of widths."""
    rows = df.withColumn("_b", divided(F.col("t"), PACK)).withColumn("bits", bit_width(F.col("x")))
    over = [F.sum((F.col("bits") > b).cast("bigint")).alias(f"c{b}") for b in range(most_bits)]
    blocks = rows.groupBy(*keys, "_b").agg(F.count(F.lit(1)).alias("n"), F.max("bits").alias("top"), F.sum(_varbytes(F.col("bits"))).alias("tail"), *over)
    choice = F.array_min(F.filter(F.array(*[F.struct((F.lit(PACK * b) + F.col(f"c{b}") * (F.col("top") - b + 8)).alias("cost"), F.lit(b).cast("bigint").alias("base"), F.col(f"c{b}").alias("count")) for b in range(most_bits)]), lambda s: s["base"] <= F.col("top")))
    blocks = blocks.select(*keys, "n", "tail", "top", choice.alias("p"))
    full = F.col("n") == PACK
    own = F.when(full, 3 + F.col("p.count") + 16 * F.col("p.base")).otherwise(F.col("tail"))
    pools = blocks.where(full & (F.col("p.count") > 0)).groupBy(*keys, (F.col("top") - F.col("p.base")).alias("w")).agg(F.sum("p.count").alias("c"))
    pooled = pools.groupBy(*keys).agg(F.sum(F.ceil(F.ceil(F.col("c") * F.col("w") / 8) / 4) * 4).cast("bigint").alias("pool"))
    return blocks.groupBy(*keys).agg(F.sum(own).cast("bigint").alias("own")).join(pooled, list(keys), "left").select(*keys, (F.col("own") + F.coalesce("pool", F.lit(0))).cast("bigint").alias("enc_bytes"))
