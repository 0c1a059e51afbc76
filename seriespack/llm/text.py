"""Words, hashes and shingles of texts, over Arrow batches."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

CHUNK_BYTES = 1 << 20
GOLDEN = 0x9E3779B97F4A7C15
#: ASCII letters (lower-cased), digits and all bytes beyond ASCII make words; the rest parts them.
ALNUM = bytes(c + 32 if 65 <= c <= 90 else c if 48 <= c <= 57 or 97 <= c <= 122 or c >= 128 else 32 for c in range(256))


def unused(columns: list[str], name: str) -> str:
    """``name``, with underscores added until none of ``columns`` has it (names differ beyond case)."""
    taken = {c.lower() for c in columns}
    while name.lower() in taken:
        name += "_"
    return name


def as_bytes(column: pa.Array) -> list[bytes]:
    """UTF-8 of each text; null as empty."""
    return [x or b"" for x in column.cast(pa.binary()).to_pylist()]


def pieces(batch: pa.RecordBatch, column: str = "text", most: int = CHUNK_BYTES) -> Iterator[pa.RecordBatch]:
    """Slices of a batch with about ``most`` bytes of text each; a longer text is a slice of its own."""
    import pyarrow.compute as pc

    ends = np.cumsum(pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False))
    start = 0
    while start < batch.num_rows:
        base = ends[start - 1] if start else 0
        stop = max(start + 1, int(np.searchsorted(ends, base + most, "right")))
        yield batch.slice(start, stop - start)
        start = stop


def space_words(text: bytes) -> list[bytes]:
    """Words parted by ASCII white space, with A-Z lower-cased."""
    return text.lower().split()


def alnum_words(text: bytes) -> list[bytes]:
    """Runs of letters, digits and non-ASCII characters, with A-Z lower-cased."""
    return text.translate(ALNUM).split()


class WordHashes(dict):
    """64-bit hashes of words, remembered up to a bound."""

    def __init__(self, most: int = 200_000):
        super().__init__()
        self.most = most

    def __missing__(self, word: bytes) -> int:
        import xxhash

        if len(self) >= self.most:
            self.clear()
        value = self[word] = xxhash.xxh3_64_intdigest(word)
        return value

    def of(self, words: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, words), np.uint64, len(words))


def windows(hashes: np.ndarray, k: int) -> np.ndarray:
    """A hash for each run of ``k`` words."""
    n = len(hashes) - k + 1
    out = np.zeros(max(n, 0), np.uint64)
    for i in range(k if n > 0 else 0):
        out = (out ^ (hashes[i : i + n] + np.uint64((i + 1) * GOLDEN % (1 << 64)))) * np.uint64(0xD6E8FEB86659FD93)
        out ^= out >> np.uint64(32)
    return out


def shingle_set(hashes: np.ndarray, k: int = 5) -> np.ndarray:
    """Sorted distinct shingles; the whole sequence is the one shingle of a shorter text."""
    if not len(hashes):
        return np.empty(0, np.uint64)
    return np.unique(windows(hashes, min(k, len(hashes))))


def multipliers(n: int, seed: int) -> np.ndarray:
    """Odd 64-bit factors, one for each hash function."""
    return np.random.default_rng(seed).integers(1, 1 << 63, n, dtype=np.int64).astype(np.uint64) | np.uint64(1)
