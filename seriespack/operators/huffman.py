"""Byte-wise Huffman coding: canonical, lengths limited to 11 bits, never more than a byte above stored.

A coded body is a flag (0 stored, 1 coded, 2 one symbol only), a 32-byte map of the symbols, their code
lengths in nibbles, the number of bytes, and sub-streams of a fixed symbol count that are decoded in
lock-step; their lengths are part of the bytes.
"""

from __future__ import annotations

import numpy as np

LIMIT = 11
STREAM = 512


def code_lengths(counts: np.ndarray, limit: int = LIMIT) -> np.ndarray:
    """Optimal lengths of at most ``limit`` bits (package-merge); 0 for symbols that don't occur.

    A level holds the symbols and the pairs of the level below, by weight, symbols first among equals.  Of the last level
    2n - 2 items are taken, of each level below twice the pairs taken above; a symbol's length is how often it is taken.
    """
    symbols = np.flatnonzero(counts)
    out = np.zeros(len(counts), np.int64)
    if len(symbols) == 1:
        out[symbols] = 1
    if len(symbols) < 2:
        return out
    order = symbols[np.argsort(counts[symbols], kind="stable")]
    single, levels = counts[order].astype(np.int64), []
    weights, is_pair = single, np.zeros(len(single), bool)
    for _ in range(limit):
        levels.append(is_pair)
        pairs = weights[: len(weights) // 2 * 2].reshape(-1, 2).sum(1)
        merged = np.concatenate([single, pairs])
        by = np.argsort(merged, kind="stable")
        weights, is_pair = merged[by], by >= len(single)
    taken = 2 * len(symbols) - 2
    for is_pair in reversed(levels):
        pairs = int(is_pair[:taken].sum())
        out[order[: taken - pairs]] += 1
        taken = 2 * pairs
    return out


def codes_of(lengths: np.ndarray) -> np.ndarray:
    """Canonical codes: shorter first, then by symbol."""
    out, code, last = np.zeros(len(lengths), np.int64), 0, 0
    for s in sorted(np.flatnonzero(lengths), key=lambda s: (lengths[s], s)):
        code <<= int(lengths[s]) - last
        last = int(lengths[s])
        out[s] = code
        code += 1
    return out


def _put_codes(codes: np.ndarray, place: np.ndarray, size: np.ndarray, n_bytes: int) -> bytes:
    """Codes of ``size`` bits from bit ``place`` on, most significant first."""
    out = np.zeros(n_bytes // 8 + 2, np.uint64)
    word, room = place >> 6, 64 - (place & 63) - size
    codes = codes.astype(np.uint64)
    high = np.where(room >= 0, codes << np.maximum(room, 0).astype(np.uint64), codes >> np.maximum(-room, 0).astype(np.uint64))
    first = np.flatnonzero(np.diff(word, prepend=-1))
    out[word[first]] = np.bitwise_or.reduceat(high, first)
    over = np.flatnonzero(room < 0)
    out[word[over] + 1] |= codes[over] << (64 + room[over]).astype(np.uint64)
    return out.astype(">u8").tobytes()[:n_bytes]


def encode(body: bytes) -> bytes:
    data = np.frombuffer(body, np.uint8)
    counts = np.bincount(data, minlength=256)
    lengths = code_lengths(counts)
    symbols = np.flatnonzero(lengths)
    if len(symbols) == 1:
        return b"\x02" + bytes([int(symbols[0])]) + len(body).to_bytes(4, "little")
    if len(body) < 40:
        return b"\x00" + body
    codes = codes_of(lengths)
    size = lengths[data]
    groups = np.arange(len(data)) // STREAM
    bits = np.bincount(groups, size).astype(np.int64)
    stream_bytes = -(-bits // 8)
    starts = (np.cumsum(stream_bytes) - stream_bytes) * 8
    inner = np.cumsum(size) - size
    place = starts[groups] + inner - inner[groups * STREAM]
    out = _put_codes(codes[data], place, size, int(stream_bytes.sum()))
    nibbles = lengths[symbols]
    nibbles = np.concatenate([nibbles, np.zeros(len(nibbles) % 2, np.int64)])
    table = np.packbits(lengths > 0).tobytes() + (nibbles[::2] << 4 | nibbles[1::2]).astype(np.uint8).tobytes()
    made = b"\x01" + table + len(body).to_bytes(4, "little") + stream_bytes.astype("<u2").tobytes() + out
    return made if len(made) <= len(body) else b"\x00" + body


def encoded_size(body: bytes) -> int:
    """Bytes that ``encode`` makes, without making them."""
    data = np.frombuffer(body, np.uint8)
    lengths = code_lengths(np.bincount(data, minlength=256))
    symbols = np.count_nonzero(lengths)
    if symbols == 1:
        return 6
    if len(body) < 40:
        return 1 + len(body)
    bits = np.add.reduceat(lengths.astype(np.uint8)[data], np.arange(0, len(data), STREAM), dtype=np.int64)
    made = 1 + 32 + -(-symbols // 2) + 4 + 2 * len(bits) + int((-(-bits // 8)).sum())
    return int(made if made <= len(body) else 1 + len(body))


def decode(data: bytes) -> bytes:
    return decode_many([data])[0]


def _tables(data: bytes) -> tuple[int, int, int, np.ndarray]:
    """Of a coded body: bytes that it stands for, streams, where their lengths begin, and for each window of bits symbol * 16 + length."""
    present = np.flatnonzero(np.unpackbits(np.frombuffer(data, np.uint8, 32, 1)))
    at = 33 + -(-len(present) // 2)
    pairs = np.frombuffer(data, np.uint8, at - 33, 33)
    lengths = np.zeros(256, np.int64)
    lengths[present] = np.stack([pairs >> 4, pairs & 15], 1).reshape(-1)[: len(present)]
    order = sorted(present.tolist(), key=lambda s: (lengths[s], s))
    spans = (1 << LIMIT) >> lengths[order]  # canonical codes fill the windows in this order
    table = np.zeros(1 << LIMIT, np.uint16)
    filled = np.repeat(np.array(order, np.int64) * 16 + lengths[order], spans)
    table[: len(filled)] = filled
    n = int.from_bytes(data[at : at + 4], "little")
    return n, -(-n // STREAM), at + 4, table


def decode_many(bodies: list[bytes]) -> list[bytes]:
    """Bytes of several coded bodies; the streams of all run in lock-step."""
    out: list = [None] * len(bodies)
    coded = []
    for i, data in enumerate(bodies):
        if not data or data[0] == 0:
            out[i] = data[1:]
        elif data[0] == 2:
            out[i] = data[1:2] * int.from_bytes(data[2:6], "little")
        else:
            coded.append(i)
    if not coded:
        return out
    parts, places, tables, counts, at = [], [], [], [], 0
    for i in coded:
        n, streams, begin, table = _tables(bodies[i])
        sizes = np.frombuffer(bodies[i], "<u2", streams, begin).astype(np.int64)
        parts.append(bodies[i][begin + 2 * streams :])
        places.append((np.cumsum(sizes) - sizes + at) * 8)
        at += len(parts[-1])
        tables.append(table)
        counts.append((n, streams))
    raw = np.frombuffer(b"".join([*parts, bytes(4)]), np.uint8).astype(np.uint32)
    window = raw[:-3] << 16 | raw[1:-2] << 8 | raw[2:-1]
    table = np.concatenate(tables)
    base = np.repeat(np.arange(len(coded)) << LIMIT, [s for _, s in counts])
    place, last = np.concatenate(places), len(window) - 1
    symbols = np.zeros((min(STREAM, max(n for n, _ in counts)), len(place)), np.uint8)
    for t in range(len(symbols)):
        seen = window[np.minimum(place >> 3, last)] >> (24 - LIMIT - (place & 7)).astype(np.uint32) & ((1 << LIMIT) - 1)
        found = table[base + seen]
        symbols[t] = found >> 4
        place += found & 15
    lane = 0
    for i, (n, streams) in zip(coded, counts, strict=True):
        flat = np.ascontiguousarray(symbols[:, lane : lane + streams].T).reshape(-1)
        if streams > 1 or len(symbols) == STREAM:
            out[i] = flat[:n].tobytes()
        else:
            out[i] = symbols[:n, lane].tobytes()
        lane += streams
    return out
