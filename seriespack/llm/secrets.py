"""Secret scans over an incremental ledger of blobs.

Each historical version of a file (here: each document) is addressed by the SHA-256 of its text.  A
ledger in the shared folder lists which (blob, rule version) pairs were scanned and what was found.  A rule
version is a name and the patterns that go by it; a changed pattern needs a new name.  A scan hashes all
versions, keeps one text for each blob that the ledger lacks under these rules, scans only those, appends to
the ledger, and joins findings back to every path that holds the blob.  Grouping by blob combines on the map
side, so a blob with a third of all paths sends one row a task.

Defined cases: a null text is an empty one; null and repeated paths are kept, a row each; equal versions share
one scan and each get its findings; a ledger that does not exist yet is empty; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .store import new_path


@dataclass(frozen=True)
class Rule:
    """A kind of secret: its pattern, and the fewest characters of a group (0: the whole match)."""

    kind: str
    pattern: str
    least: int = 0
    group: int = 0
    any_case: bool = False


@dataclass(frozen=True)
class Rules:
    """A version of the rules: what the ledger knows them by, and the rules in the order that breaks ties."""

    version: str
    rules: tuple[Rule, ...]


#: The base kinds in their order, the pattern of each, and the fewest characters.
BASE = Rules(
    "base-1",
    (
        Rule("assign", r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 8, 2, True),
        Rule("access", r"AKIA[A-Z0-9]+", 16),
        Rule("hex", r"[0-9a-f]+", 32),
    ),
)
#: Well-known forms of keys, beside the base kinds.
EXTENDED = Rules(
    "extended-1",
    (
        *BASE.rules,
        Rule("pem", r"-----BEGIN [A-Z ]*PRIVATE KEY-----"),
        Rule("jwt", r"eyJ[A-Za-z0-9_-]+\.eyJ[A-Za-z0-9_-]+\.[A-Za-z0-9_-]+"),
        Rule("hosted", r"gh[pousr]_[A-Za-z0-9]{36,}"),
    ),
)
KINDS = tuple(r.kind for r in BASE.rules)
LEDGER = "blob string, rules string, spans array<struct<kind:string,start:int,end:int>>"


def compiled(rules: Rules) -> list[tuple[str, re.Pattern, int, int]]:
    """Patterns to search with.  Of a run of one kind of character only those that are long enough are looked for: a shorter run can't hold a longer one."""
    out = []
    for r in rules.rules:
        run = re.fullmatch(r"(\w*)(\[[^]]+\])\+", r.pattern) if not r.group else None
        pattern = f"{run[1]}{run[2]}{{{r.least - len(run[1])},}}" if run and r.least > len(run[1]) else r.pattern
        out.append((r.kind, re.compile(pattern, re.ASCII | (re.IGNORECASE if r.any_case else 0)), r.group, r.least))
    return out


def find(text: str, rules: Rules = BASE, patterns: list | None = None) -> list[tuple[str, int, int]]:
    """Spans of secrets by start, then kind as listed; positions are code points, the end is exclusive."""
    order = {r.kind: i for i, r in enumerate(rules.rules)}
    found = [(kind, *m.span()) for kind, pattern, group, least in patterns or compiled(rules) for m in pattern.finditer(text) if m.end(group) - m.start(group) >= least]
    return sorted(found, key=lambda x: (x[1], order[x[0]]))


def _scanner(rules: Rules):
    def scan_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        span = pa.struct([("kind", pa.string()), ("start", pa.int32()), ("end", pa.int32())])
        patterns = compiled(rules)
        for batch in batches:
            spans = [[dict(kind=k, start=a, end=b) for k, a, b in find(t, rules, patterns)] for t in batch.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("blob"), batch.column("rules"), pa.array(spans, pa.list_(span))], ["blob", "rules", "spans"])

    return scan_batches


def exists(spark: SparkSession, path: str) -> bool:
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark._jsc.hadoopConfiguration()).exists(at)


def scan(versions: DataFrame, ledger: str | None = None, path: str = "path", text: str = "text", rules: Rules = BASE) -> DataFrame:
    """Findings of every version: (path, blob, spans).  ``ledger`` grows by what was new to it."""
    spark = versions.sparkSession
    ledger = ledger or new_path(spark, "secret-ledger")
    addressed = versions.select(F.col(path).alias("path"), F.coalesce(F.col(text), F.lit("")).alias("text")).withColumn("blob", F.sha2("text", 256))
    unseen = addressed.groupBy("blob").agg(F.first("text").alias("text")).withColumn("rules", F.lit(rules.version))
    if exists(spark, ledger):
        unseen = unseen.join(spark.read.schema(LEDGER).parquet(ledger).select("blob", "rules"), ["blob", "rules"], "left_anti")
    unseen.mapInArrow(_scanner(rules), LEDGER).write.mode("append").parquet(ledger)
    known = spark.read.schema(LEDGER).parquet(ledger).where(F.col("rules") == rules.version).where(F.size("spans") > 0).select("blob", "spans").dropDuplicates(["blob"])
    return addressed.select("path", "blob").join(known, "blob", "left").select("path", "blob", F.coalesce("spans", F.array().cast("array<struct<kind:string,start:int,end:int>>")).alias("spans"))


def report(docs: DataFrame, ledger: str | None = None, rules: Rules = BASE) -> DataFrame:
    """Per document: how many of each base kind, the digest of the base spans, and all spans."""
    line = lambda spans: F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")
    base = F.filter("spans", lambda s: s["kind"].isin(*KINDS))
    count = lambda kind: F.size(F.filter("spans", lambda s: s["kind"] == kind)).cast("bigint")
    return scan(docs.select("doc_id", "text"), ledger, "doc_id", rules=rules).select(
        F.col("path").alias("doc_id"), *[count(k).alias(f"n_{k}") for k in KINDS], F.sha2(line(base), 256).alias("base_sha256"), line("spans").alias("spans")
    )


def digest(spans: list[tuple[str, int, int]]) -> str:
    """What ``base_sha256`` holds for these spans."""
    return hashlib.sha256(",".join(f"{k}:{a}:{b}" for k, a, b in spans).encode()).hexdigest()
