"""A bounded sample of labelled documents, and sparse features of texts."""

from __future__ import annotations

import pickle
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .text import as_bytes, pieces

Features = Callable[[list[bytes]], Iterator[tuple[np.ndarray, np.ndarray]]]
BUCKET_BITS = 18


def sample(labels: DataFrame, column: str, most: int) -> DataFrame:
    """At most ``most`` rows (doc_id, label): those with the least hash of their id; null ids and labels are left out."""
    known = labels.select("doc_id", F.col(column).cast("int").alias("label")).where("doc_id is not null and label is not null")
    return known.orderBy(F.xxhash64(F.col("doc_id").cast("string")), "doc_id", "label").limit(most)


def training_set(docs: DataFrame, labels: DataFrame, column: str, features: Features, most: int, passes: Callable[[DataFrame], DataFrame] = lambda x: x) -> DataFrame:
    """(doc_id, label, indexes, values) of the sample, made where the texts lie; ids may be of any type.

    The sample is at most ``most`` rows of two numbers, so it is broadcast; texts stay where they are.
    """
    chosen = F.broadcast(sample(passes(labels), column, most))

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for piece in pieces(batch):
                made = list(features(as_bytes(piece.column("text"))))
                yield pa.RecordBatch.from_arrays(
                    [piece.column("doc_id"), piece.column("label"), pa.array([i.astype("<i4").tobytes() for i, _ in made], pa.binary()), pa.array([v.astype("<f4").tobytes() for _, v in made], pa.binary())],
                    ["doc_id", "label", "indexes", "values"],
                )

    return docs.select(F.col("doc_id").cast("string").alias("doc_id"), "text").join(chosen.withColumn("doc_id", F.col("doc_id").cast("string")), "doc_id").select("doc_id", "text", "label").mapInArrow(make, "doc_id string, label int, indexes binary, values binary")


def fitted(rows: DataFrame, fit: Callable[[list[tuple[str, int, np.ndarray, np.ndarray]]], dict], most: int, most_features: int) -> dict:
    """What ``fit`` makes of a bounded training set, in one task of an executor; only the model comes to the driver.

    Spark sorts the rows by a hash of their ids (and spills); the task takes them in that order until it has ``most`` rows or
    ``most_features`` features, so neither repeated ids nor very long texts make it hold more.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found, held = [], 0
        for batch in batches:
            for d, y, i, v in zip(*(batch.column(c) for c in ("doc_id", "label", "indexes", "values")), strict=True):
                if len(found) >= most or held >= most_features:
                    break
                found.append((d.as_py(), y.as_py(), np.frombuffer(i.as_py(), "<i4"), np.frombuffer(v.as_py(), "<f4")))
                held += len(found[-1][2])
        yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(fit(found))], pa.binary())], ["model"])

    ordered = rows.withColumn("_hash", F.xxhash64("doc_id")).repartition(1).sortWithinPartitions("_hash", "doc_id", "label", "indexes", "values").drop("_hash")
    made = ordered.mapInArrow(run, "model binary").first()
    return pickle.loads(made[0]) if made else fit([])


def mixed(key: str) -> int:
    """A key's order in a shuffle that is the same in every run."""
    import xxhash

    return xxhash.xxh3_64_intdigest(key.encode())
