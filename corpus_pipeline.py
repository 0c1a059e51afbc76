"""A corpus pipeline out of the training-data operators of ``seriespack.llm``.

Stages, in order: toxic documents go; one document of each group of near-duplicates stays; documents with
passages of the benchmark go; sources are mixed to target weights (one epoch at most, a text that the
budget ends in is kept whole); token ids are written and read back.  Each stage works on all that the one
before kept, as a Parquet table in the shared folder.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from seriespack.llm import decontam, mixing, neardup, store, tokenout, toxicity
from seriespack.llm.queries import table, tokenizer_path

MIX_SHARE, MIX_EPOCHS = (8, 10), 1
#: SQL has no tokenizer and no trained model; tests hold each stage against a brute-force version.
ORACLE_SQL = None


def civil(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return toxicity.keep_civil(docs, table(spark, sf_dir, "labels"))


def distinct(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return neardup.deduplicate(docs)


def clean(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontam.decontaminate(docs, table(spark, sf_dir, "benchmark"))


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.mix(docs, share=MIX_SHARE, max_epochs=MIX_EPOCHS)


def token_ids(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return tokenout.report(docs, tokenizer_path())


STAGES = [("toxicity", civil), ("near_duplicates", distinct), ("decontamination", clean), ("mixing", mixed), ("token_ids", token_ids)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = store.written(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
