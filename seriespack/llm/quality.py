"""Quality by logistic regression on hashed word n-grams, trained with follow-the-regularised-leader.

A word counts twice: as itself and by its shape (case, digits, trailing signs, whether it repeats the word
before).  Unigrams and bigrams of both are hashed into 2^18 places; an n-gram's value is the square root of
its share among the text's n-grams of that kind, so long and short texts compare.  FTRL-proximal keeps a
pair of sums for each place; weights follow in closed form, with L1 making most of them 0.  A score is a
sparse dot product.  Only texts are looked at: not labels, languages, sources or ids.

Defined cases: a null or empty text has no n-grams and scores by the bias alone; texts are read whole;
labels without a document, and null labels, are ignored; a repeated document is scored each time; without
any label every score is 0.5; ids may be of any type; where a column of ``docs`` is named like the score, that
gets underscores until it has a name of its own.  Labels are a sample of at most ``most`` rows and about
``MOST_FEATURES`` n-grams.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .labelled import BUCKET_BITS, fitted, mixed, training_set
from .store import worker_cache
from .text import as_bytes, pieces, unused

MOST = 20_000
MOST_FEATURES = 16_000_000
EPOCHS = 3
THRESHOLD = 0.3


def shape(word: bytes) -> bytes:
    """Case of the letters, digits, and the last signs of a word."""
    text = word.decode(errors="replace")
    core = text.rstrip("!?.,;:%*&$#|+~=-_")
    case = "n" if not core else "d" if any(c.isdigit() for c in core) else "U" if core.isupper() and len(core) > 1 else "C" if core[0].isupper() else "l" if core.isalpha() else "s"
    return (case + text[len(core) :][:3]).encode()


class WordIds(dict):
    """(hash of the lower-cased word, hash of its shape), in one number of 62 bits; bounded."""

    def __missing__(self, word: bytes) -> int:
        import xxhash

        if len(self) >= 200_000:
            self.clear()
        value = self[word] = (xxhash.xxh3_64_intdigest(word.lower()) & 0x3FFFFFFF) << 31 | (xxhash.xxh3_64_intdigest(b"shape" + shape(word)) & 0x7FFFFFFF)
        return value


def _grams(ids: np.ndarray) -> list[np.ndarray]:
    """Unigrams and bigrams of words and of shapes, as 64-bit numbers."""
    word, form = ids >> np.uint64(31), ids & np.uint64(0x7FFFFFFF)
    if len(ids) > 1:
        form = form.copy()
        form[1:][word[1:] == word[:-1]] = np.uint64(1)
    out = []
    for kind, x in ((1, word), (3, form)):
        out.append(x * np.uint64(8) + np.uint64(kind))
        if len(x) > 1:
            out.append((x[:-1] * np.uint64(0x9E3779B1) + x[1:]) * np.uint64(8) + np.uint64(kind + 1))
    return out


def features(texts: list[bytes]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Places and values of each text's n-grams."""
    ids = worker_cache().setdefault("quality words", WordIds())
    for text in texts:
        words = text.split()
        known = np.fromiter(map(ids.__getitem__, words), np.uint64, len(words))
        parts = []
        for grams in _grams(known):
            place = ((grams * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - BUCKET_BITS)).astype(np.int32)
            place.sort()
            first = np.flatnonzero(np.concatenate([[True], place[1:] != place[:-1]])) if len(place) else np.empty(0, np.int64)
            parts.append((place[first], np.sqrt(np.diff(first, append=len(place)) / max(len(place), 1))))
        yield np.concatenate([p for p, _ in parts]), np.concatenate([v for _, v in parts])


class FollowTheLeader:
    """FTRL-proximal for logistic loss, with the usual four parameters."""

    def __init__(self, bits: int = BUCKET_BITS, alpha: float = 0.3, beta: float = 1.0, l1: float = 0.05, l2: float = 0.5):
        self.z, self.n = np.zeros((1 << bits) + 1), np.zeros((1 << bits) + 1)
        self.alpha, self.beta, self.l1, self.l2 = alpha, beta, l1, l2

    def weights(self, at=slice(None)) -> np.ndarray:
        z, n = self.z[at], self.n[at]
        return np.where(np.abs(z) <= self.l1, 0.0, -(z - np.sign(z) * self.l1) / ((self.beta + np.sqrt(n)) / self.alpha + self.l2))

    def learn(self, at: np.ndarray, x: np.ndarray, y: int) -> None:
        """One update; an n-gram kind may share a place with another, so places can repeat."""
        at, x = np.append(at, len(self.z) - 1), np.append(x, 1.0)
        w = self.weights(at)
        g = (1 / (1 + np.exp(-np.clip(w @ x, -30, 30))) - y) * x
        s = (np.sqrt(self.n[at] + g * g) - np.sqrt(self.n[at])) / self.alpha
        np.add.at(self.z, at, g - s * w)
        np.add.at(self.n, at, g * g)


def train(docs: DataFrame, labels: DataFrame, column: str = "quality", most: int = MOST, epochs: int = EPOCHS, passes=lambda x: x) -> np.ndarray:
    """Weights of all places and, last, the bias."""
    def fit(rows) -> dict:
        model = FollowTheLeader()
        for epoch in range(epochs):
            for _, y, at, x in sorted(rows, key=lambda r: mixed(f"{epoch}:{r[0]}")):
                model.learn(at, x, y)
        return {"weights": model.weights().astype(np.float32)}

    return fitted(training_set(docs, labels, column, features, most, passes), fit, most, MOST_FEATURES)["weights"]


def score(docs: DataFrame, weights: np.ndarray, column: str = "score") -> DataFrame:
    """``docs`` with the probability of label 1."""
    column = unused(docs.columns, column)
    shared = docs.sparkSession.sparkContext.broadcast(weights)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        w = shared.value
        for batch in batches:
            for piece in pieces(batch):
                dots = np.array([float(w[at] @ x.astype(np.float32)) for at, x in features(as_bytes(piece.column("text")))]) + float(w[-1])
                yield pa.RecordBatch.from_arrays([*piece.columns, pa.array(1 / (1 + np.exp(-np.clip(dots, -30, 30))), pa.float64())], [*piece.schema.names, column])

    schema = docs.select(*docs.columns, F.lit(0.0).alias(column)).schema
    return docs.mapInArrow(run, schema)


def held_out() -> "F.Column":
    """True for rows that no label is learnt from; a null id is not held out."""
    return F.coalesce(F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(5)) == 0, F.lit(False))


def report(docs: DataFrame, labels: DataFrame, most: int = MOST) -> DataFrame:
    """Per document: doc_id, held_out, score, predicted."""
    weights = train(docs, labels, most=most, passes=lambda x: x.where(~held_out()))
    return score(docs.select("doc_id", "text"), weights).select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
