"""License scans: MinHash bands over overlapping windows retrieve templates, exact containment confirms.

Texts are cut into words (letters, digits, non-ASCII; A-Z lower-cased) and hashed five-word shingles.
Templates fall into classes by size: class S holds those with more than S/2 and up to S shingles, S a
power of two.  Windows of a class are 2S shingles long and start every S, so S consecutive shingles always
lie within one window.  A window that holds ``CONTAINED`` of a template then has a similarity of at least
CONTAINED * (S/2) / (2S + (1 - CONTAINED) * S/2) with it, and the number of bands (of one row each) is
chosen so that such a window misses with a probability of at most ``MISS``.  Minima of windows are built
up from those of half the size.  A hit is confirmed on exact shingles.

Defined cases: null and empty texts have no windows; a text or template of fewer than five words is one
shingle; a template without words is refused; very long texts are scanned in full; null ids are kept; repeated
rows are each scanned; other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .license_texts import TEXTS
from .store import worker_cache
from .text import WordHashes, alnum_words, as_bytes, multipliers, pieces, windows

SHINGLE = 5
CONTAINED = 0.75
MISS = 1e-3
SEED = 41
#: Templates that a caller gives as a table may hold this many bytes; they are held by every task.
TEMPLATE_BYTES = 64 << 20


def shingles(text: bytes, k: int = SHINGLE) -> np.ndarray:
    """Shingle hashes in the order of the text."""
    words = alnum_words(text)
    hashes = worker_cache().setdefault("license words", WordHashes()).of(words)
    return windows(hashes, min(k, len(words))) if words else np.empty(0, np.uint64)


def bands(size: int, contained: float = CONTAINED, miss: float = MISS) -> int:
    """How many one-row bands a class needs so that a window holding ``contained`` of a template is missed with probability ``miss`` at most."""
    least = math.floor(size / 2) + 1
    similar = contained * least / (2 * size + (1 - contained) * least)
    return math.ceil(math.log(miss) / math.log(1 - similar))


class Templates:
    """Band tables of the templates, by class."""

    def __init__(self, texts: dict[str, str], contained: float = CONTAINED, miss: float = MISS, seed: int = SEED):
        self.names, self.sets, self.contained = list(texts), [], contained
        by: dict[int, list[int]] = {}
        for i, text in enumerate(texts.values()):
            s = np.unique(shingles(text.encode()))
            if not len(s):
                raise ValueError(f"template {self.names[i]} has no words")
            self.sets.append(s)
            by.setdefault(1 << (len(s) - 1).bit_length(), []).append(i)
        self.sizes = sorted(by)
        self.factors = multipliers(max(bands(s, contained, miss) for s in by), seed)
        self.tables: dict[int, list[tuple[np.ndarray, np.ndarray, dict[int, list[int]]]]] = {}
        for size, members in by.items():
            self.tables[size] = []
            for f in self.factors[: bands(size, contained, miss)]:
                at: dict[int, list[int]] = {}
                for i in members:
                    at.setdefault(int((self.sets[i] * f).min()), []).append(i)
                keys = np.array(sorted(at), np.uint64)
                low = np.zeros(1 << 16, bool)
                low[(keys >> np.uint64(20)).astype(np.int64) & 0xFFFF] = True
                self.tables[size].append((keys, low, at))

    def candidates(self, texts: list[np.ndarray]) -> list[set[tuple[int, int, int]]]:
        """For each text (start, end, template) of the windows that share a band with a template.

        Texts lie in one array, each from a multiple of the largest class on and followed by a whole empty
        block, so no window reaches from one into the next.
        """
        out: list[set[tuple[int, int, int]]] = [set() for _ in texts]
        pad, lengths = self.sizes[-1], np.array([len(t) for t in texts], np.int64)
        room = (-(-lengths // pad) + 1) * pad
        starts = np.cumsum(room) - room
        flat, empty = np.zeros(int(room.sum()), np.uint64), np.ones(int(room.sum()), bool)
        for at, t in zip(starts.tolist(), texts, strict=True):
            flat[at : at + len(t)] = t
            empty[at : at + len(t)] = False
        none = np.flatnonzero(empty)
        for b, f in enumerate(self.factors):
            blocks, size = flat * f, 1
            blocks[none] = np.uint64(0xFFFFFFFFFFFFFFFF)
            for s in self.sizes:
                while size < s:
                    blocks = np.minimum(blocks[::2], blocks[1::2])
                    size *= 2
                if b >= len(self.tables[s]):
                    continue
                least = np.minimum(blocks[:-1], blocks[1:])
                _, low, at = self.tables[s][b]
                for w in np.flatnonzero(low[(least >> np.uint64(20)).astype(np.int64) & 0xFFFF]).tolist():
                    for i in at.get(int(least[w]), ()):
                        doc = int(np.searchsorted(starts, w * s, "right")) - 1
                        start = w * s - int(starts[doc])
                        if start < lengths[doc]:
                            out[doc].add((start, min(start + 2 * s, int(lengths[doc])), i))
        return out

    def find(self, texts: list[np.ndarray]) -> list[list[tuple[str, int, int, float]]]:
        """For each text (name, start, end, containment) of confirmed windows, in shingles; of neighbouring windows with the same template the better one."""
        out = []
        for text, windows_ in zip(texts, self.candidates(texts), strict=True):
            best: dict[tuple[int, int], tuple[float, int, int]] = {}
            for start, end, i in sorted(windows_):
                part = float(np.isin(self.sets[i], text[start:end]).mean())
                if part >= self.contained:
                    half = 1 << (len(self.sets[i]) - 1).bit_length()
                    last = best.get((i, start - half))
                    if last is None or part > last[0]:
                        best.pop((i, start - half), None)
                        best[i, start] = (part, start, end)
            out.append([(self.names[i], a, b, p) for (i, _), (p, a, b) in sorted(best.items())])
        return out


def read_templates(table: DataFrame, most: int = TEMPLATE_BYTES) -> dict[str, str]:
    """Templates of a table (name, text), whose size is checked before it comes to the driver; later texts of a name get numbers, null ones are left out."""
    rows = table.select(F.col("name").cast("string").alias("name"), "text").where("name is not null and text is not null").distinct()
    size = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    if size > most:
        raise ValueError(f"templates of {size} bytes are more than {most}; scan with parts of them")
    out: dict[str, str] = {}
    for name, text in sorted(map(tuple, rows.collect())):
        key, n = name, 1
        while key in out:
            n += 1
            key = f"{name}#{n}"
        out[key] = text
    return out


def scan(docs: DataFrame, templates: dict[str, str] | DataFrame | None = None, contained: float = CONTAINED, text: str = "text") -> DataFrame:
    """Per row: doc_id, n_shingles, and licenses, an array of (name, start, end, containment).

    Templates are a table (name, text) or a dictionary; without them, the texts and notices of ``license_texts``.
    """
    texts = TEXTS if templates is None else read_templates(templates) if isinstance(templates, DataFrame) else templates

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = Templates(texts, contained)
        kind = pa.list_(pa.struct([("name", pa.string()), ("start", pa.int64()), ("end", pa.int64()), ("containment", pa.float64())]))
        for batch in batches:
            for piece in pieces(batch, text):
                all_ = [shingles(t) for t in as_bytes(piece.column(text))]
                found = [[dict(zip(("name", "start", "end", "containment"), m, strict=True)) for m in one] for one in known.find(all_)]
                yield pa.RecordBatch.from_arrays([piece.column("doc_id"), pa.array(map(len, all_), pa.int64()), pa.array(found, kind)], ["doc_id", "n_shingles", "licenses"])

    id_kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", text).mapInArrow(run, f"doc_id {id_kind}, n_shingles bigint, licenses array<struct<name:string,start:bigint,end:bigint,containment:double>>")


def report(docs: DataFrame, templates: dict[str, str] | DataFrame | None = None) -> DataFrame:
    """Per document: doc_id, n_shingles, n_matches, license_ids (distinct, sorted, comma-joined), best containment."""
    names = F.array_sort(F.array_distinct(F.transform("licenses", lambda x: x["name"])))
    return scan(docs, templates).select("doc_id", "n_shingles", F.size("licenses").cast("bigint").alias("n_matches"), F.array_join(names, ",").alias("license_ids"), F.coalesce(F.array_max(F.transform("licenses", lambda x: x["containment"])), F.lit(0.0)).alias("best"))
