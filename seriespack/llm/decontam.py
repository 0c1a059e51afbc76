"""Benchmark decontamination by a broadcast hash set of normalised test n-grams.

Words are runs of letters, digits and non-ASCII characters with A-Z lower-cased.  A window is ``width``
consecutive words of a benchmark item; an item with fewer words, but not none, is one window.  A block of
the benchmark is a few flat arrays: the normalised text, where its words begin, and the windows' 64-bit
hashes in order with their places, about 30 bytes a word.  It is sent to the executors as a broadcast of at most
about ``BLOCK_BYTES``, counted before it is built; a larger benchmark is cut into blocks, each scanned in a
pass of its own (an item lies in one block as a whole).  Document windows are looked up by hash, each hit is
verified word for word, and words inside an occurrence are marked.

Defined cases: a null or empty text has no words and is clean; items without words are ignored; equal
items all count; the words of an item with a null id are marked, but it is not listed among the items of
a document; repeated documents are each scanned; other columns pass untouched, and where one has the name
of a column made here, that gets underscores until it has a name of its own.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .store import worker_cache, written
from .text import WordHashes, alnum_words, as_bytes, pieces, unused, windows

WIDTH = 10
BLOCK_BYTES = 160 << 20
#: What a word of the benchmark takes besides its text: its place, its window's hash, place and item.
WORD_BYTES = 8 + 8 + 8 + 4
WORD = re.compile(rb"[0-9A-Za-z\x80-\xff]+")
LOW_BITS = 22


class WindowSet:
    """Windows of benchmark items in flat arrays, found by hash and confirmed word by word."""

    def __init__(self, items: Iterable[tuple[str | None, bytes]], width: int = WIDTH):
        hashes, self.names, texts, lengths = WordHashes(), [], [], [np.zeros(0, np.int64)]
        made: dict[int, list[tuple[np.ndarray, np.ndarray, np.ndarray]]] = {}
        at = 0
        for item, text in items:
            words = alnum_words(text)
            if not words:
                continue
            n = min(width, len(words))
            keys = windows(hashes.of(words), n)
            made.setdefault(n, []).append((keys, np.arange(at, at + len(keys)), np.full(len(keys), len(self.names), np.int32)))
            self.names.append(item)
            texts.append(b" ".join(words))
            lengths.append(np.fromiter(map(len, words), np.int64, len(words)))
            at += len(words)
        ends = np.cumsum(np.concatenate(lengths) + 1)
        self.text, self.ends = b" ".join(texts), ends - 1
        self.starts = ends - 1 - np.concatenate(lengths)
        self.tables = []
        for n in sorted(made):
            keys, place, item = (np.concatenate(column) for column in zip(*made.pop(n), strict=True))
            order = np.argsort(keys, kind="stable")
            self.tables.append((n, keys[order], place[order], item[order], self.low(keys)))

    @classmethod
    def of(cls, state: dict) -> "WindowSet":
        """The set whose ``vars`` were sent."""
        made = cls.__new__(cls)
        vars(made).update(state)
        return made

    @staticmethod
    def low(keys: np.ndarray) -> np.ndarray:
        """Which low bits occur: most windows of documents need no search."""
        out = np.zeros(1 << LOW_BITS, bool)
        out[(keys & np.uint64((1 << LOW_BITS) - 1)).astype(np.int64)] = True
        return out

    def _items(self, table: tuple, key: int, gram: bytes) -> list[str | None] | None:
        """Items with this very window; None if there is none, whatever its hash."""
        n, keys, place, item, _ = table
        lo, hi = np.searchsorted(keys, key, "left"), np.searchsorted(keys, key, "right")
        same = [int(i) for p, i in zip(place[lo:hi].tolist(), item[lo:hi].tolist(), strict=True) if self.text[self.starts[p] : self.ends[p + n - 1]] == gram]
        return [self.names[i] for i in same] or None

    def scan(self, words: list[bytes], hashes: np.ndarray) -> tuple[np.ndarray, set[str]]:
        """Which words are inside an occurrence, and the items that occur."""
        hit, items = np.zeros(len(words), bool), set()
        for table in self.tables:
            n, keys, *_, low = table
            if len(words) < n:
                continue
            found = windows(hashes, n)
            at = np.flatnonzero(low[(found & np.uint64((1 << LOW_BITS) - 1)).astype(np.int64)])
            at = at[keys[np.minimum(np.searchsorted(keys, found[at]), len(keys) - 1)] == found[at]]
            known: dict[bytes, bool] = {}
            for i in at.tolist():
                gram = b" ".join(words[i : i + n])
                if gram not in known:
                    who = self._items(table, found[i], gram)
                    known[gram] = who is not None
                    items.update(x for x in who or () if x is not None)
                if known[gram]:
                    hit[i : i + n] = True
        return hit, items


def _blocks(benchmark: DataFrame, width: int, item: str, text: str, block_bytes: int) -> Iterator[WindowSet]:
    """The benchmark in blocks of a bounded size once built; the driver holds one at a time."""
    rows = benchmark.select(F.col(item).cast("string").alias("item"), F.coalesce(F.col(text), F.lit("")).alias("text")).distinct()
    size = rows.agg(F.sum(F.octet_length("text") + WORD_BYTES * F.regexp_count("text", F.lit(r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+")))).first()[0] or 0
    n = int(size // block_bytes) + 1
    for b in range(n):
        part = rows if n == 1 else rows.where(F.pmod(F.xxhash64("item", "text"), F.lit(n)) == b)
        yield WindowSet(((r.item, r.text.encode()) for r in part.toLocalIterator()), width)


def made_names(columns: list[str]) -> tuple[str, str, str]:
    """Names of the columns that ``hits`` adds to these."""
    return unused(columns, "_hit_words"), unused(columns, "_hit_items"), unused(columns, "_n_words")


def hits(docs: DataFrame, benchmark: DataFrame, width: int = WIDTH, text: str = "text", item: str = "item_id", item_text: str = "text", block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """``docs`` with ``_n_words``, ``_hit_words`` (positions) and ``_hit_items`` (ids as strings, sorted)."""
    in_words, in_items, n_words = made_names(docs.columns)
    out = docs.select(*docs.columns, F.lit(None).cast("array<int>").alias(in_words), F.lit(None).cast("array<string>").alias(in_items), F.lit(0).cast("bigint").alias(n_words))
    schema, first = out.schema, True

    def kernel(shared):
        def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            known, of = WindowSet.of(shared.value), worker_cache().setdefault("decontam words", WordHashes(400_000)).of
            for batch in (p for b in batches for p in pieces(b, text, 4 << 20)):
                words_hit, items_hit, counts = [], [], []
                before = zip(batch.column(in_words).to_pylist(), batch.column(in_items).to_pylist(), strict=True)
                for body, (old_words, old_items) in zip(as_bytes(batch.column(text)), before, strict=True):
                    words = alnum_words(body)
                    hit, items = known.scan(words, of(words))
                    if old_words:
                        hit[old_words] = True
                    words_hit.append(np.flatnonzero(hit).astype(np.int32))
                    items_hit.append(sorted(items.union(old_items or ())))
                    counts.append(len(words))
                new = {in_words: pa.array(words_hit, pa.list_(pa.int32())), in_items: pa.array(items_hit, pa.list_(pa.string())), n_words: pa.array(counts, pa.int64())}
                yield pa.RecordBatch.from_arrays([new.get(c, batch.column(c)) for c in batch.schema.names], batch.schema.names)

        return scan

    for block in _blocks(benchmark, width, item, item_text, block_bytes):
        shared = docs.sparkSession.sparkContext.broadcast(vars(block))
        out = (out if first else written(out, "decontam")).mapInArrow(kernel(shared), schema)
        first = False
    return out


def report(docs: DataFrame, benchmark: DataFrame, width: int = WIDTH) -> DataFrame:
    """Per document: n_words, n_hit, n_items, items_sha256, contaminated."""
    found = hits(docs.select("doc_id", "text"), benchmark, width)
    return found.select(
        "doc_id",
        F.col("_n_words").alias("n_words"),
        F.size("_hit_words").cast("bigint").alias("n_hit"),
        F.size("_hit_items").cast("bigint").alias("n_items"),
        F.sha2(F.array_join("_hit_items", ","), 256).alias("items_sha256"),
        (F.size("_hit_words") > 0).alias("contaminated"),
    )


def _cut(text: bytes, positions: list[int]) -> bytes:
    """``text`` without the runs of words at ``positions``."""
    gone, out, end, previous = set(positions), [], 0, -2
    for i, m in enumerate(WORD.finditer(text)):
        if i in gone:
            if previous != i - 1:
                out.append(text[end : m.start()])
            end, previous = m.end(), i
    return b"".join([*out, text[end:]])


def decontaminate(docs: DataFrame, benchmark: DataFrame, mode: str = "documents", width: int = WIDTH) -> DataFrame:
    """Clean documents, with the columns of ``docs``: ``documents`` drops what has a hit, ``spans`` cuts the hits out."""
    if mode not in ("documents", "spans"):
        raise ValueError(f"mode is documents or spans, not {mode!r}")
    found, (in_words, *_) = hits(docs, benchmark, width), made_names(docs.columns)
    if mode == "documents":
        return found.where(F.size(in_words) == 0).select(*docs.columns)

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [t if not p else _cut(t.encode(), p).decode() for t, p in zip(batch.column("text").to_pylist(), batch.column(in_words).to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(texts, batch.column("text").type) if c == "text" else batch.column(c) for c in docs_columns], docs_columns)

    docs_columns = docs.columns
    return found.mapInArrow(cut, docs.schema)


def digest(items: list[str]) -> str:
    """What ``items_sha256`` holds for these items."""
    return hashlib.sha256(",".join(sorted(items)).encode()).hexdigest()
