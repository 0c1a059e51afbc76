"""Token ids in Arrow stream files of fixed-size lists.

Documents are range-partitioned and sorted by id, encoded, closed with an end id and packed without gaps
into sequences of equal length.  Each partition is one stream file whose record batches all hold the same
number of sequences (``input_ids`` and ``mask``, both fixed-size lists), so batch i starts at a place that
is computed, and a mapped file gives its sequences without a copy.  Only a file's last sequence is padded,
where ``mask`` is false.  The index (document, file, start, length) is a table beside the files.

The tokenizer library's parts are called apart: its pre-tokenizer cuts a text into words, its model turns a
word into ids, and ids of words are remembered up to a bound.  Long texts are taken in slices that end before
a single space between two characters that are not white space; the pre-tokenizer always cuts there, as such
a space belongs to what follows, and it always cuts around a single line break between two such characters.
So most slices need no pre-tokenizer: they are split at spaces and line breaks, and chunks are looked up.  A
slice where a space or line break touches other white space of any kind (the vocabulary has a token for line
feed and no-break space) goes through the library's pre-tokenizer; a text that holds the text of an added
token goes through the library as a whole.

Defined cases: a null or empty text is the end id alone; null ids come first; rows with equal ids are
ordered by text and all kept; an empty table writes no file; other columns are ignored.
"""

from __future__ import annotations

import re
import sys
import zlib
from array import array
from collections.abc import Iterator
from itertools import islice

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .store import AtomicFile, new_path, opened, worker_cache, written

END = 2
LENGTH = 2048
BATCH = 64
CACHE = 600_000
SLICE = 4096
#: Latin letters, then ASCII signs without the apostrophe: the pre-tokenizer parts the two and nothing else.
WORD = re.compile(r"([A-Za-z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u024f]+)([!-&(-/:-@\[-`{-~]*)")


def forget_oldest(known: dict, most: int) -> None:
    """Drops the older half of what is remembered once there is more than ``most``."""
    if len(known) > most:
        for key in list(islice(known, len(known) // 2)):
            del known[key]


def byte_letters() -> dict[int, str]:
    """Byte-level BPE's letter for each byte: printable bytes stand for themselves, the rest follow from 256 on."""
    plain = {*range(33, 127), *range(161, 173), *range(174, 256)}
    others = (b for b in range(256) if b not in plain)
    return {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(others)}


LETTERS = byte_letters()


class Irregular(Exception):
    """A slice can't be cut at spaces alone."""


class Chunks(dict):
    """Ids of chunks that a single space or line break stands before; new ones are encoded as they are asked for."""

    def __init__(self, encoder: "Encoder", before: str):
        super().__init__()
        self.encoder, self.before = encoder, before

    def __missing__(self, chunk: str) -> bytes:
        body = chunk[1:] if chunk[:1] == "\n" else chunk
        if not body or body[:1].isspace() or body[-1:].isspace():
            raise Irregular
        if body is not chunk:
            value = self.encoder.newline + self.encoder.first[body]
        elif (m := WORD.fullmatch(chunk)) and m.end(1) < m.end():
            value = self[m[1]] + self.encoder.signs[m[2]]
        elif m:
            value = self.encoder.piece((self.before + chunk).encode().decode("latin-1").translate(LETTERS))
        else:
            value = self.encoder.pieces(self.before + chunk)
        self[chunk] = value
        return value


class Encoder:
    """A tokenizer of byte-level BPE with a bounded memory of chunks."""

    def __init__(self, path: str, dtype: str = "<u2"):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.dtype, self.code = dtype, {"<u2": "H", "<u4": "I"}[dtype]
        if self.tokenizer.get_vocab_size() > np.iinfo(dtype).max + 1:
            raise ValueError(f"{dtype} can't hold the ids")
        self.model, self.cutter = self.tokenizer.model, self.tokenizer.pre_tokenizer
        self.added = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.spaced, self.first, self.signs, self.known = Chunks(self, " "), Chunks(self, ""), Chunks(self, ""), {}
        self.newline = self.pieces("\n")

    @classmethod
    def shared(cls, path: str, dtype: str) -> "Encoder":
        cache = worker_cache()
        if ("encoder", path, dtype) not in cache:
            cache["encoder", path, dtype] = cls(path, dtype)
        return cache["encoder", path, dtype]

    def packed(self, ids: list[int]) -> bytes:
        out = array(self.code, ids)
        if sys.byteorder != "little":
            out.byteswap()
        return out.tobytes()

    def piece(self, letters: str) -> bytes:
        """Ids of one word, given in byte-level letters."""
        return self.packed([t.id for t in self.model.tokenize(letters)])

    def pieces(self, text: str) -> bytes:
        """Ids of a text without added tokens, by the library's pre-tokenizer and model."""
        known, out = self.known, []
        for letters, _ in self.cutter.pre_tokenize_str(text):
            if (ids := known.get(letters)) is None:
                ids = known[letters] = self.piece(letters)
            out.append(ids)
        return b"".join(out)

    def whole(self, text: str) -> bytes:
        return self.packed(self.tokenizer.encode(text, add_special_tokens=False).ids)

    def slice(self, text: str, start: int, stop: int) -> bytes:
        """Ids of text[start:stop]; a slice that does not begin the text begins with the space it was cut at."""
        try:
            chunks = text[start + (start > 0) : stop].replace("\n", " \n").split(" ")
            if start:
                return b"".join(map(self.spaced.__getitem__, chunks))
            return self.first[chunks[0]] + b"".join(map(self.spaced.__getitem__, chunks[1:]))
        except Irregular:
            return self.pieces(text[start:stop])

    def ids(self, text: str) -> bytes:
        for held, most in ((self.spaced, CACHE), (self.first, CACHE // 8), (self.signs, CACHE // 8), (self.known, CACHE // 8)):
            forget_oldest(held, most)
        if not text:
            return b""
        if any(t in text for t in self.added):
            return self.whole(text)
        out, start = [], 0
        while start < len(text):
            stop = text.find(" ", start + SLICE)
            while stop >= 0 and (text[stop - 1].isspace() or text[stop + 1 : stop + 2].isspace() or stop + 1 == len(text)):
                stop = text.find(" ", stop + 1)
            stop = len(text) if stop < 0 else stop
            out.append(self.slice(text, start, stop))
            start = stop
        return b"".join(out)


def sequence_schema(length: int, dtype: str) -> pa.Schema:
    return pa.schema([("input_ids", pa.list_(pa.from_numpy_dtype(np.dtype(dtype)), length)), ("mask", pa.list_(pa.bool_(), length))])


class SequenceWriter:
    """Packs ids into one stream file; all batches but the last hold ``batch`` sequences."""

    def __init__(self, stream, length: int, dtype: str, batch: int):
        self.schema, self.length, self.dtype, self.batch = sequence_schema(length, dtype), length, np.dtype(dtype), batch
        self.out, self.parts, self.held, self.total = pa.ipc.new_stream(stream, self.schema), [], 0, 0

    def add(self, ids: bytes) -> None:
        self.parts.append(ids)
        self.held += len(ids)
        self.total += len(ids) // self.dtype.itemsize
        if self.held >= (full := self.length * self.batch * self.dtype.itemsize):
            data = b"".join(self.parts)
            whole = len(data) - len(data) % full
            for i in range(0, whole, full):
                self._write(np.frombuffer(data, self.dtype, full // self.dtype.itemsize, i), full // self.dtype.itemsize)
            self.parts, self.held = [data[whole:]], len(data) - whole

    def _write(self, ids: np.ndarray, real: int) -> None:
        lists = [pa.FixedSizeListArray.from_arrays(pa.array(x), self.length) for x in (ids, np.arange(len(ids)) < real)]
        self.out.write_batch(pa.RecordBatch.from_arrays(lists, schema=self.schema))

    def close(self) -> None:
        ids = np.frombuffer(b"".join(self.parts), self.dtype)
        if len(ids):
            self._write(np.concatenate([ids, np.zeros(-len(ids) % self.length, self.dtype)]), len(ids))
        self.out.close()


class SequenceFile:
    """Random access to a stream file's sequences; without a copy where the file can be mapped."""

    def __init__(self, uri: str):
        fs, path = opened(uri)
        self.file = pa.memory_map(path) if fs.type_name == "local" else fs.open_input_file(path)
        self.schema = pa.ipc.read_schema(pa.ipc.read_message(self.file))
        self.first = self.file.tell()
        pa.ipc.read_message(self.file)
        self.size = self.file.tell() - self.first
        self.length = self.schema.field("input_ids").type.list_size
        self.batch_rows = self.batch(0).num_rows

    def batch(self, i: int) -> pa.RecordBatch:
        self.file.seek(self.first + i * self.size)
        return pa.ipc.read_record_batch(pa.ipc.read_message(self.file), self.schema)

    def sequence(self, i: int) -> tuple[np.ndarray, np.ndarray]:
        """Ids and mask of sequence ``i``."""
        batch, at = self.batch(i // self.batch_rows), i % self.batch_rows
        return batch.column("input_ids")[at].values.to_numpy(), batch.column("mask")[at].values.to_numpy(zero_copy_only=False)

    def ids(self, start: int, n: int) -> np.ndarray:
        """``n`` ids from place ``start`` of the file."""
        per, out = self.batch_rows * self.length, []
        while n > 0:
            i, at = divmod(start, per)
            if getattr(self, "_held", (None,))[0] != i:
                self._held = (i, self.batch(i).column("input_ids").flatten().to_numpy())
            out.append(self._held[1][at : at + n])
            if not len(out[-1]):
                raise ValueError("the file is shorter than its index says")
            start, n = start + len(out[-1]), n - len(out[-1])
        return np.concatenate(out) if out else np.empty(0, np.uint16)


def write_sequences(docs: DataFrame, path: str, tokenizer: str, end: int = END, length: int = LENGTH, dtype: str = "<u2", batch: int = BATCH) -> DataFrame:
    """Writes the files; the index: (part, file, doc_id, local_start, n_tokens), each file's documents in order."""

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task = TaskContext.get()
        uri = f"{path}/{task.partitionId():06d}-{task.taskAttemptId()}.arrows"
        encoder, close = Encoder.shared(tokenizer, dtype), np.array([end], dtype).tobytes()
        batches = (b for b in batches if b.num_rows)
        if (first := next(batches, None)) is None:
            return
        with AtomicFile(uri) as stream:
            out = SequenceWriter(stream, length, dtype, batch)
            while first is not None:
                starts, counts = [], []
                for text in first.column("text").to_pylist():
                    starts.append(out.total)
                    out.add(encoder.ids(text or "") + close)
                    counts.append(out.total - starts[-1])
                n = len(starts)
                yield pa.RecordBatch.from_arrays(
                    [pa.array([task.partitionId()] * n, pa.int32()), pa.array([uri] * n), first.column("doc_id"), pa.array(starts, pa.int64()), pa.array(counts, pa.int64())],
                    ["part", "file", "doc_id", "local_start", "n_tokens"],
                )
                first = next(batches, None)
            out.close()

    kind = docs.schema["doc_id"].dataType.simpleString()
    ordered = docs.select("doc_id", "text").repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text")
    return written(ordered.mapInArrow(write, f"part int, file string, doc_id {kind}, local_start bigint, n_tokens bigint"), "token-index")


def with_starts(index: DataFrame) -> DataFrame:
    """The index with ``start``: ids of all documents before.  A row for each file, not for each document, passes the one ordered window."""
    files = index.groupBy("part").agg(F.sum("n_tokens").alias("_n"))
    before = files.select("part", F.coalesce(F.sum("_n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_before"))
    return index.join(F.broadcast(before), "part").withColumn("start", F.col("_before") + F.col("local_start")).drop("_before")


def report(docs: DataFrame, tokenizer: str, **options) -> DataFrame:
    """Per document, from the files: doc_id, start, n_tokens, ids_crc32."""
    index = write_sequences(docs, new_path(docs.sparkSession, "tokens"), tokenizer, **options)

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        uri = held = None
        for batch in batches:
            sums = []
            for f, start, n in zip(*(batch.column(c).to_pylist() for c in ("file", "local_start", "n_tokens")), strict=True):
                if f != uri:
                    uri, held = f, SequenceFile(f)
                sums.append(zlib.crc32(held.ids(start, n).astype("<u4").tobytes()))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("start"), batch.column("n_tokens"), pa.array(sums, pa.int64())], ["doc_id", "start", "n_tokens", "ids_crc32"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    placed = with_starts(index).repartitionByRange("part").sortWithinPartitions("part", "local_start")
    return placed.mapInArrow(read, f"doc_id {kind}, start bigint, n_tokens bigint, ids_crc32 bigint")
